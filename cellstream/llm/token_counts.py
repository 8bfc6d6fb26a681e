"""Token counts by a tokenizer compiled into a deterministic finite-state transducer.

The machine reads ASCII bytes, lower case, and its states are what the tokenizer still has open: nothing, an apostrophe that
may begin a contraction, or the letters or marks of the word so far. A word's state knows the last token of the
word's encoding and where it begins; that of the next state follows from the vocabulary's merges alone (the last token is the
longest one that ends here and that the token before it stays apart from), so the tokens of a word are counted while
it is read. Each transition is annotated with the tokens it emits: those of the word that it ends. States and transitions are made
on first use, up to a bounded number.

Texts of a batch are put end to end and cut into equal chunks that advance in lockstep. White space takes every state to
the open one, so the state map of a chunk is constant behind its first white space; the part before it is a map of the
state that enters. The maps are composed by a scan over the chunks: where the chunk before is constant its exit enters at once,
and where it has no white space at all its own map is applied first.

Units (between white space) with other bytes, special strings or states beyond the bound are counted by the library and
kept in a bounded memo, so counts are exact whatever has been compiled. The rules of word ends are those of the
vocabulary with word ends (word_bpe_49k.json); others are refused.

Null and empty texts have no bytes and no tokens; very long texts are counted whole; rows, repeated ones too, are kept one
for one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import PieceEncoder, text_bytes

OPEN, UNKNOWN, QUOTE, QUOTE_R, QUOTE_V, QUOTE_L, LETTERS, MARKS = range(8)
#: Contractions that stand apart, by what is open and the letter that completes them.
_COMPLETE = {(QUOTE, "s"), (QUOTE, "t"), (QUOTE, "m"), (QUOTE, "d"), (QUOTE_R, "e"), (QUOTE_V, "e"), (QUOTE_L, "l")}
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
END = "</w>"


class Merges:
    """The vocabulary's merges: whole encodings of short strings, and the incremental step."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        model = told["model"]
        if model["type"] != "BPE" or model["end_of_word_suffix"] != END or model["continuing_subword_prefix"]:
            raise ValueError("not a vocabulary with word ends")
        self._vocabulary = model["vocab"]
        self._rank = {tuple(m) if isinstance(m, list) else tuple(m.split(" ")): k for k, m in enumerate(model["merges"])}
        self.longest = max(len(v.removesuffix(END)) for v in self._vocabulary)
        self._apart: dict[tuple[str | None, str], bool] = {}
        # Bytes without a printable character of their own stand for characters from 256 on, in order.
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in shown]
        self.symbol = {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(rest)}

    def encode(self, symbols: list[str]) -> list[str]:
        """Lowest merge first, leftmost first."""
        parts = list(symbols)
        while len(parts) > 1:
            rank, at = min((self._rank.get((a, b), 1 << 60), k) for k, (a, b) in enumerate(zip(parts, parts[1:], strict=False)))
            if rank == 1 << 60:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    @staticmethod
    def _split(token: str) -> list[str]:
        word = token.removesuffix(END)
        return [*word] if word == token else [*word[:-1], word[-1] + END]

    def apart(self, before: str | None, token: str) -> bool:
        """Whether a text of these tokens is encoded as just these."""
        key = (before, token)
        if key not in self._apart:
            if len(self._apart) > 2_000_000:
                self._apart.clear()
            whole = self._split(token) if before is None else [*before, *self._split(token)]
            self._apart[key] = self.encode(whole) == [t for t in key if t is not None]
        return self._apart[key]

    def last(self, chain: list, symbol: str) -> tuple[str, int]:
        """Last token after one more symbol, and its number of symbols. ``chain[k]`` is the last token k symbols back."""
        ending, text, plain = [], "", symbol.removesuffix(END)
        for k in range(min(len(chain), self.longest)):
            text = plain + text if not k else chain[k - 1][1] + text
            token = text + symbol[len(plain) :]
            if token in self._vocabulary:
                ending.append((token, k + 1))
        for token, k in reversed(ending):
            if self.apart(chain[k - 1][0], token):
                return token, k
        raise ValueError(f"no token ends with {symbol}")


class CountTransducer:
    """Deterministic transducer with ``max_states`` states at most; grows until full, then stays."""

    def __init__(self, vocabulary: str, max_states: int = 1 << 17, memo: int = 600_000):
        self._merges = Merges(vocabulary)
        self._library = PieceEncoder(vocabulary, keep_space=False, capacity=1)
        # Class 0: bytes that are not ASCII; 1: white space; then a class a byte, capitals with their small letters.
        self._classes = np.zeros(256, np.int32)
        self._classes[_SPACE] = 1
        kinds = [b for b in range(128) if not _SPACE[b] and not 65 <= b <= 90]
        for k, b in enumerate(kinds, 2):
            self._classes[b] = k
            if 97 <= b <= 122:
                self._classes[b - 32] = k
        self._bytes = [None, None, *kinds]
        self._width = len(self._bytes)
        self._max = min(max(max_states, 8), (1 << 24) // self._width)
        # An entry is the next state * width, with the tokens emitted above bit 24.
        self._table = np.full((self._max, self._width), UNKNOWN * self._width, np.int32)
        self._table[:, 1] = OPEN
        self._made = np.zeros((self._max, self._width), bool)
        self._n_states = 8
        # Of a word's state: kind, symbol, state before, last token, the state where that begins, tokens so far, tokens if it ends.
        self._words: list = [None] * 8
        self._words[LETTERS] = self._words[MARKS] = (None, "", None, None, None, 0, 0)
        self._quote = len(self._merges.encode(["'" + END]))
        self._memo: dict[bytes, int] = {}
        self._memo_size = memo

    # Compilation ------------------------------------------------------------------------------------------------------
    def _child(self, state: int, kind: int, byte: int) -> int:
        """State of a word with one more byte; UNKNOWN if there is no room."""
        symbol = self._merges.symbol[byte]
        key = int(self._classes[byte])
        if kind in (LETTERS, MARKS) and self._made[state, key] and state == kind:
            return int(self._table[state, key] & 0xFFFFFF) // self._width
        if self._n_states == self._max:
            return UNKNOWN
        chain, at = [], state
        while at is not None and len(chain) <= self._merges.longest:
            chain.append((self._words[at][3], self._words[at][1], at))
            at = self._words[at][2]
        token, k = self._merges.last(chain, symbol)
        begin = chain[k - 1][2]
        end, e = self._merges.last(chain, symbol + END)
        self._words.append((kind, symbol, state, token, begin, self._words[begin][5] + 1, self._words[chain[e - 1][2]][5] + 1))
        self._n_states += 1
        return self._n_states - 1

    def _start(self, byte: int) -> tuple[int, int]:
        """(state, tokens emitted) after a byte with nothing open."""
        char = chr(byte)
        if char.isdigit():
            return OPEN, 1
        if char == "'":
            return QUOTE, 0
        root = LETTERS if char.isalpha() else MARKS
        state = self._child(root, root, byte)
        if state != UNKNOWN:
            self._set(root, byte, state, 0)
        return state, 0

    def _set(self, state: int, byte: int, after: int, emitted: int) -> None:
        self._table[state, self._classes[byte]] = after * self._width | emitted << 24
        self._made[state, self._classes[byte]] = True

    def _step(self, state: int, byte: int) -> tuple[int, int]:
        """The transition, made if it is not there yet."""
        key = self._classes[byte]
        if self._made[state, key]:
            value = int(self._table[state, key])
            return (value & 0xFFFFFF) // self._width, value >> 24
        after, emitted = self._arrive(state, byte)
        if emitted > 127:
            after = UNKNOWN
        if after != UNKNOWN:
            self._set(state, byte, after, emitted)
        return after, emitted

    def _arrive(self, state: int, byte: int) -> tuple[int, int]:
        char = chr(byte)
        if state == UNKNOWN or byte >= 128:
            return UNKNOWN, 0
        if state == OPEN:
            return self._start(byte)
        if (state, char) in _COMPLETE:
            word = {QUOTE: "", QUOTE_R: "r", QUOTE_V: "v", QUOTE_L: "l"}[state] + char
            return OPEN, len(self._merges.encode(["'", *word[:-1], word[-1] + END]))
        if state == QUOTE:
            if char in "rvl":
                return {"r": QUOTE_R, "v": QUOTE_V, "l": QUOTE_L}[char], 0
            if char.isalnum():
                after, more = self._start(byte)
                return after, self._quote + more
            first, _ = self._step_word(MARKS, MARKS, ord("'"))
            return (UNKNOWN, 0) if first == UNKNOWN else self._step_word(first, MARKS, byte)
        if state in (QUOTE_R, QUOTE_V, QUOTE_L):
            letter, _ = self._start(ord({QUOTE_R: "r", QUOTE_V: "v", QUOTE_L: "l"}[state]))
            after, more = self._step(letter, byte)
            return (UNKNOWN, 0) if after == UNKNOWN else (after, self._quote + more)
        kind, done = self._words[state][0], self._words[state][6]
        if kind == LETTERS and char.isalpha():
            return self._step_word(state, LETTERS, byte)
        if kind == MARKS and not char.isalnum():
            if char == "|" and self._words[state][1] == "<":
                return UNKNOWN, 0  # may begin a special string
            return self._step_word(state, MARKS, byte)
        after, more = self._start(byte)
        return after, done + more

    def _step_word(self, state: int, kind: int, byte: int) -> tuple[int, int]:
        key = self._classes[byte]
        if self._made[state, key]:
            return int(self._table[state, key] & 0xFFFFFF) // self._width, 0
        after = self._child(state, kind, byte)
        if after != UNKNOWN:
            self._set(state, byte, after, 0)
        return after, 0

    def _ending(self, state: int) -> int:
        """Tokens emitted by white space."""
        if state in (OPEN, UNKNOWN):
            return 0
        if state == QUOTE:
            return self._quote
        if state in (QUOTE_R, QUOTE_V, QUOTE_L):
            letter, _ = self._start(ord({QUOTE_R: "r", QUOTE_V: "v", QUOTE_L: "l"}[state]))
            return -1 if letter == UNKNOWN else self._quote + self._words[letter][6]
        return self._words[state][6]

    def compile(self, unit: bytes) -> int | None:
        """Tokens of a unit, its path made where it is not there; None if it is not ASCII or does not fit."""
        state, tokens = OPEN, 0
        for byte in unit.lower():
            state, emitted = self._step(state, byte)
            if state == UNKNOWN:
                return None
            tokens += emitted
        last = self._ending(state)
        if not 0 <= last <= 127:
            self._table[state, 1] = UNKNOWN * self._width  # never read as a count
            return None
        self._table[state, 1] = OPEN * self._width | last << 24
        self._made[state, 1] = True
        return tokens + last

    # Running ------------------------------------------------------------------------------------------------------------
    def _count_units(self, units: list[bytes]) -> list[int]:
        values = [self._memo.get(u) for u in units]
        fresh = []
        for u in {u for u, v in zip(units, values, strict=True) if v is None}:
            if u.isascii() and b"<|" not in u and (n := self.compile(u)) is not None:
                self._memo[u] = n
            else:
                fresh.append(u)
        texts = [u.decode("utf-8", "replace") for u in fresh]
        self._memo.update(zip(fresh, map(len, self._library.library_ids(texts)), strict=True))
        values = [self._memo[u] for u in units]
        if len(self._memo) > self._memo_size:
            self._memo.clear()
        return values

    def _run(self, column: np.ndarray, space: np.ndarray) -> np.ndarray:
        """Entries met by each lane at each step; lanes stand one behind another in the text."""
        steps, lanes = column.shape
        history = np.empty((steps, lanes), np.int32)
        flat = self._table.reshape(-1)
        state = np.full(lanes, OPEN * self._width, np.int32)
        for k in range(steps):
            np.add(state, column[k], out=state)
            np.take(flat, state, out=history[k])
            np.bitwise_and(history[k], 0xFFFFFF, out=state)
        # The head of a lane, up to its first white space, is its map of the state that enters.
        head = np.where(space.any(0), space.argmax(0) + 1, steps)
        constant = head < steps
        constant |= space[steps - 1]
        known = constant.copy()
        known[0] = True
        left = np.arange(1, lanes)
        while len(left):
            ready = left[known[left - 1]]
            left = left[~known[left - 1]]
            state = history[steps - 1, ready - 1] & 0xFFFFFF
            size = head[ready]
            order = np.argsort(-size, kind="stable")
            ready, state, size = ready[order], state[order], size[order]
            for k in range(int(size[0])):
                n = int(np.searchsorted(-size, -k))  # lanes whose head goes on
                met = flat[state[:n] + column[k, ready[:n]]]
                history[k, ready[:n]] = met
                state[:n] = met & 0xFFFFFF
            known[ready] = True
        return history

    def count(self, texts: list[bytes], lanes: int = 4096) -> np.ndarray:
        """Tokens of each text."""
        if not texts:
            return np.zeros(0, np.int64)
        joined = b"\n".join(texts) + b"\n"
        ends = np.cumsum([len(t) + 1 for t in texts])
        size = len(joined)
        lanes = max(1, min(lanes, size // 64))
        steps = -(-size // lanes)
        data = np.full(lanes * steps, 10, np.uint8)
        data[:size] = np.frombuffer(joined, np.uint8)
        space = _SPACE[data]
        met = self._run(np.ascontiguousarray(self._classes[data].reshape(lanes, steps).T), np.ascontiguousarray(space.reshape(lanes, steps).T)).T.reshape(-1)
        emitted = met >> 24
        lost = np.flatnonzero(((met & 0xFFFFFF) == UNKNOWN * self._width) | (space & ~self._made_space(met, space)))
        total = np.add.reduceat(emitted, np.concatenate([[0], ends[:-1]]), dtype=np.int64)
        if not len(lost):
            return total
        opened = np.flatnonzero(~space & np.concatenate([[True], space[:-1]]))
        closed = np.flatnonzero(space & np.concatenate([[False], ~space[:-1]]))
        unit = np.unique(np.searchsorted(opened, lost, "right") - 1)
        a, b = opened[unit], closed[unit]
        counted = self._count_units([joined[x:y] for x, y in zip(a.tolist(), b.tolist(), strict=True)])
        run = np.concatenate([[0], np.cumsum(emitted, dtype=np.int64)])
        change = np.array(counted, np.int64) - (run[b + 1] - run[a])
        return total + np.bincount(np.searchsorted(ends, a, "right"), weights=change, minlength=len(texts)).astype(np.int64)

    def _made_space(self, met: np.ndarray, space: np.ndarray) -> np.ndarray:
        """Whether the end of the unit before a white space is compiled: its state's transition on white space is made."""
        before = np.concatenate([[OPEN], met[:-1] & 0xFFFFFF])
        return self._made[before // self._width, 1] | (before == OPEN * self._width) | (before == UNKNOWN * self._width)


_MADE: dict[str, CountTransducer] = {}


def token_counts(docs: DataFrame, vocabulary: str, limit: int, block: int = 1 << 22) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) per row; texts are counted in blocks of about ``block`` bytes."""

    def tally(batches):
        if vocabulary not in _MADE:
            _MADE[vocabulary] = CountTransducer(vocabulary)
        machine = _MADE[vocabulary]
        for batch in batches:
            texts = batch.column(1).to_pylist()
            counts, group, held = [], [], 0
            for t in texts:
                group.append(t)
                held += len(t)
                if held >= block:
                    counts.append(machine.count(group))
                    group, held = [], 0
            counts.append(machine.count(group))
            n = np.concatenate(counts)
            arrays = [batch.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array(n > limit)]
            yield pa.RecordBatch.from_arrays(arrays, ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return text_bytes(docs).mapInArrow(tally, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
