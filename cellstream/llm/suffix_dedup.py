"""Removal of repeated 100-byte strings by blockwise suffix sorting with a difference cover.

Every string of ``length`` bytes holds a content-chosen anchor (the leftmost least hash of its ``gram``-byte grams), so
equal strings hold equal anchors in the same place and only suffixes at anchors that occur again need sorting. The context
of an anchor is what strings through it can reach. The suffix array is built block by block over these suffixes:

1. each text gives its anchors with a hash of each context. Contexts met before in the same task are compared byte by byte
   there and then; what is equal is a repeat;
2. one exchange by anchor finds anchors of several contexts (their suffixes are to be sorted) and contexts that came before in
   another task (the runs of text that they make up are compared byte by byte with the earlier place). An anchor with many
   contexts in one task is dealt by context, so a common one does not meet in one place;
3. a block holds the suffixes of some anchors, with their bytes. It is sorted a bucket, the suffixes of one anchor, at a time:
   by their first ``period`` bytes, then ties of any length by the precomputed ranks of the block's difference-cover
   sample. Common prefixes of neighbours, and the bytes before the anchors, give every earlier string.

Hashes only bring candidates together; bytes decide, and contexts that share a hash but differ go to blocks like any others.
A task holds one block at a time. A bucket of more than ``bucket`` suffixes is cut by the place of the anchor in the string:
strings with the anchor at x to y share the x bytes before it and the ``length - y`` after it, so each part is dealt by those bytes,
until the parts are small or hold one string each, which are aggregated before any exchange.

Null texts are empty; texts shorter than ``length`` lose nothing; very long texts are read in overlapping pieces; equal rows
and rows with null or repeated doc_id are ordered by (doc_id, text); an empty table gives an empty result; other columns are
ignored.
"""

from __future__ import annotations

import functools
import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import small, written

_BASES = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD1342543DE82EF95))  # odd multipliers
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(which: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of a base and of its inverse modulo 2**64."""
    if which not in _POWERS or len(_POWERS[which][0]) < n:
        size = max(n, 1 << 20)
        base = int(_BASES[which])
        both = []
        for b in (base, pow(base, -1, 1 << 64)):
            p = np.full(size, b, np.uint64)
            p[0] = 1
            both.append(np.multiply.accumulate(p))
        _POWERS[which] = (both[0], both[1])
    return _POWERS[which]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(32))


class Rolling:
    """Hashes of any substring of a byte buffer."""

    def __init__(self, data: np.ndarray, which: int = 0):
        up, self._down = _powers(which, len(data) + 1)
        self._sum = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=self._sum[1:])

    def all(self, k: int) -> np.ndarray:
        n = max(0, len(self._sum) - k)
        return _mixed((self._sum[k:] - self._sum[:n]) * self._down[:n])

    def some(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return _mixed((self._sum[b] - self._sum[a]) * self._down[a])


def anchors(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, length: int, gram: int):
    """Anchors of all ``length``-byte strings inside the given spans of a buffer: (place, anchor hash, context hash, low, high).

    ``starts`` and ``ends`` are the spans, end to end; low and high bound the context.
    """
    reach = length - gram
    empty = np.zeros(0, np.int64)
    if len(data) < length:
        return empty, empty.view(np.uint64), empty.view(np.uint64), empty, empty
    rolling = Rolling(data)
    grams = rolling.all(gram)
    keys = (grams & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(grams), dtype=np.uint64)
    least, span, width = keys, 1, reach + 1
    while 2 * span <= width:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if width > span:
        least = np.minimum(least[: len(least) - (width - span)], least[width - span :])
    whole = np.zeros(len(least) + 1, np.int8)
    last = ends - length
    fit = last >= starts
    whole[starts[fit]] += 1
    whole[last[fit] + 1] -= 1
    inside = np.cumsum(whole[:-1]).astype(bool)
    chosen = np.zeros(len(grams), bool)
    chosen[(least[inside] & np.uint64(0xFFFFFFFF)).astype(np.int64)] = True
    place = np.flatnonzero(chosen)
    doc = np.searchsorted(starts, place, "right") - 1
    low, high = np.maximum(place - reach, starts[doc]), np.minimum(place + length, ends[doc])
    second = Rolling(data, 1)
    shape = ((place - low).astype(np.uint64) << np.uint64(32)) | (high - place).astype(np.uint64)
    context = _mixed(rolling.some(low, high) ^ (second.some(low, high) * np.uint64(3)) ^ _mixed(shape))
    return place, grams[place], context, low, high

ANCHORS = "a long, s int, c long, uid long, pos long, end long"
MARKER, DONE = -1, -2  # uid of a row that says its anchor is dealt by context too; s of a row that is a finished span


def _merged(uid: np.ndarray, low: np.ndarray, high: np.ndarray):
    """(uid, start, end) of the union of spans of each uid."""
    order = np.lexsort((low, uid))
    uid, low, high = uid[order], low[order], high[order]
    if not len(uid):
        return uid, low, high
    fresh = np.concatenate([[True], uid[1:] != uid[:-1]])
    group = np.cumsum(fresh) - 1
    step = np.int64(1) << 40  # spans of different uids never touch
    reach = np.maximum.accumulate(high + group * step)
    cut = np.flatnonzero(np.concatenate([[True], low[1:] + group[1:] * step > reach[:-1]]))
    return uid[cut], low[cut], np.maximum.reduceat(high, cut)


def _anchor_rows(docs: DataFrame, length: int, gram: int, slab: int = 1 << 19, unit: int = 32, common: int = 16, mask: int = (1 << 64) - 1) -> DataFrame:
    """Anchors of all texts, without those whose whole context repeats within ``unit`` slabs: these come as finished spans.

    An anchor with ``common`` contexts or more within a unit is dealt by context too (s > 0), and a marker says so. ``mask``
    keeps only some bits of the hashes, to try what happens if different bytes share them.
    """
    reach = length - gram
    width = length + reach

    def spans(batch):
        """Slabs of whole texts; a longer text comes in overlapping pieces, whose strings start in separate ranges."""
        group, held = [], 0
        for uid, value in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            raw = value.as_buffer()
            n = raw.size
            if n < length:
                continue
            if n > slab:
                for at in range(0, n - length + 1, slab):
                    a, b = max(0, at - reach), min(n, at + slab + length + reach)
                    yield [(uid, a, at, min(n, at + slab + length - 1), memoryview(raw)[a:b])]
                continue
            group.append((uid, 0, 0, n, memoryview(raw)))
            held += n
            if held >= slab:
                yield group
                group, held = [], 0
        if group:
            yield group

    def equal(text, x, y, sizes):
        """Whether the contexts at x and y of a buffer, of equal sizes, have the same bytes."""
        windows = np.lib.stride_tricks.sliding_window_view(text, width)
        out, columns = np.zeros(len(x), bool), np.arange(width)
        for k in range(0, len(x), 20_000):
            part = slice(k, k + 20_000)
            out[part] = ~((windows[x[part]] != windows[y[part]]) & (columns < sizes[part, None])).any(1)
        return out

    def rows(parts, buffers):
        a, c, uid, pos, low, high, place = (np.concatenate(x) for x in zip(*parts, strict=True))
        keep = np.uint64(mask)
        a, c = (a & keep).view(np.int64), (c & keep).view(np.int64)
        order = np.lexsort((pos, uid, c, a))
        a, c, uid, pos, low, high, place = (x[order] for x in (a, c, uid, pos, low, high, place))
        new = np.concatenate([[True], (a[1:] != a[:-1]) | (c[1:] != c[:-1])])
        first = np.maximum.accumulate(np.where(new, np.arange(len(a)), 0))
        same = ~new & (pos - low == pos[first] - low[first]) & (high - pos == high[first] - pos[first])
        at = np.flatnonzero(same)
        text = np.concatenate([*buffers, np.zeros(width, np.uint8)])
        same[at] = equal(text, place[at], place[first[at]], high[at] - low[at])
        done = _merged(uid[same], low[same], high[same])
        a, c, uid, pos = (x[~same] for x in (a, c, uid, pos))
        lead = np.concatenate([[True], a[1:] != a[:-1]]) if len(a) else np.zeros(0, bool)
        starts = np.flatnonzero(lead)
        sizes = np.diff(np.append(starts, len(a)))
        hot = np.repeat(sizes >= common, sizes)
        salt = np.where(hot, 1 + (_mixed(c.view(np.uint64)) & np.uint64(63)).astype(np.int64), 0)
        marked = a[starts[sizes >= common]]
        own = _mixed(done[0].astype(np.uint64) * np.uint64(31) + done[1].astype(np.uint64)).view(np.int64)
        zeros = lambda k, v=0: np.full(k, v, np.int64)
        m, d = len(marked), len(done[0])
        columns = [(a, marked, own), (salt, zeros(m), zeros(d, DONE)), (c, zeros(m, -(1 << 63)), zeros(d)), (uid, zeros(m, MARKER), done[0]), (pos, zeros(m), done[1]), (zeros(len(a)), zeros(m), done[2])]
        arrays = [np.concatenate(x) for x in columns]
        return pa.RecordBatch.from_arrays([pa.array(x.astype(np.int32) if k == 1 else x) for k, x in enumerate(arrays)], ["a", "s", "c", "uid", "pos", "end"])

    def find(batches):
        for batch in batches:
            parts, buffers, offset, before = [], [], 0, (None, np.zeros(0, np.int64))
            for group in spans(batch):
                data = np.frombuffer(b"".join(x[4] for x in group), np.uint8)
                ends = np.cumsum([len(x[4]) for x in group])
                starts = ends - [len(x[4]) for x in group]
                if len(group) == 1 and len(group[0][4]) > length:
                    # A piece: anchors of strings that start in its own range; contexts reach into the neighbours.
                    uid, base, first, stop, _ = group[0]
                    whole = anchors(data, starts, ends, length, gram)
                    own = anchors(data[first - base : stop - base], np.array([0]), np.array([stop - first]), length, gram)[0] + first - base
                    take = np.isin(whole[0], own)
                    if before[0] == uid:
                        take &= ~np.isin(whole[0] + base, before[1])
                    before = (uid, whole[0][take] + base)
                    place, a, c, low, high = (x[take] for x in whole)
                    uids, bases = np.full(len(place), uid), np.full(len(place), base)
                else:
                    place, a, c, low, high = anchors(data, starts, ends, length, gram)
                    doc = np.searchsorted(starts, place, "right") - 1
                    uids, bases = np.array([x[0] for x in group], np.int64)[doc], -starts[doc]
                parts.append((a, c, uids, place + bases, low + bases, high + bases, low + offset))
                buffers.append(data)
                offset += len(data)
                if len(buffers) >= unit:
                    yield rows(parts, buffers)
                    parts, buffers, offset = [], [], 0
            if parts:
                yield rows(parts, buffers)

    return docs.mapInArrow(find, ANCHORS)


AGAIN = "kind int, a long, uid long, pos long, ref long, at long"
CONTEXT, COVERED, SPAN = 0, 1, 2


def _again(found: DataFrame) -> DataFrame:
    """What the exchange by anchor finds: CONTEXT rows, anchors of several contexts (the earliest of each); COVERED rows, whose
    context has the hash of an earlier one (``ref`` and ``at`` are its uid and place); SPAN rows from ``pos`` to ``at``.

    Rows come sorted and leave as they come; one row of an anchor is kept until a second context shows.
    """

    def group(batches):
        key, ref, several, waiting = None, (0, 0), False, None  # (a, s, c) of the row before; its earliest; its anchor's state
        for batch in batches:
            a, s, c, uid, pos, end = (x.to_numpy().astype(np.int64) for x in batch.columns)
            if not len(a):
                continue
            at = np.arange(len(a))
            new_a = np.concatenate([[key is None or (a[0], s[0]) != key[:2]], (a[1:] != a[:-1]) | (s[1:] != s[:-1])])
            new_c = new_a | np.concatenate([[key is None or c[0] != key[2]], c[1:] != c[:-1]])
            first = np.maximum.accumulate(np.where(new_c, at, -1))
            ref_uid, ref_pos = np.where(first >= 0, uid[first], ref[0]), np.where(first >= 0, pos[first], ref[1])
            number = np.cumsum(new_a) - 1  # -1: the anchor of the batch before goes on
            carried = int(number[0] < 0)
            contexts = np.bincount(number + carried, weights=new_c, minlength=int(number[-1]) + 1 + carried)
            many = (contexts >= 2) | (np.bincount(number + carried, weights=(uid == MARKER) | (s > 0), minlength=len(contexts)) > 0)
            if carried:
                many[0] = several or contexts[0] >= 1
            open_ = many[number + carried]
            parts = [np.zeros((0, 6), np.int64)]
            if carried and many[0] and waiting is not None:
                parts.append(np.array([waiting]))
                waiting = None
            done = s == DONE
            for kind, take, x, y in ((SPAN, done, uid, end), (CONTEXT, new_c & open_ & ~done & (uid != MARKER), uid, pos), (COVERED, ~new_c & ~done & (uid != MARKER), ref_uid, ref_pos)):
                parts.append(np.stack([np.full(take.sum(), kind), a[take], uid[take], pos[take], x[take], y[take]], 1))
            last = len(a) - 1
            if not open_[last] and not done[last] and number[last] >= 0:
                lone = int(np.flatnonzero(new_a)[-1])
                waiting = (CONTEXT, a[lone], uid[lone], pos[lone], uid[lone], pos[lone])
            elif number[last] >= 0:
                waiting = None
            key, ref, several = (a[last], s[last], c[last]), (ref_uid[last], ref_pos[last]), bool(open_[last])
            out = np.concatenate(parts)
            yield pa.RecordBatch.from_arrays([pa.array(out[:, 0].astype(np.int32)), *(pa.array(np.ascontiguousarray(out[:, k])) for k in range(1, 6))], [x.split()[0] for x in AGAIN.split(", ")])

    return found.repartition("a", "s").sortWithinPartitions("a", "s", "c", "uid", "pos").mapInArrow(group, AGAIN)


FETCHED = "kind int, a long, uid long, pos long, left int, right int, ref long, at long, bytes binary"


def _fetched(docs: DataFrame, marks: DataFrame, length: int, gram: int) -> DataFrame:
    """The bytes of marks: each CONTEXT with its own, and the runs of text that COVERED contexts of one earlier place make up."""
    reach = length - gram

    def fetch(batches):
        for batch in batches:
            raws, lists = batch.column(1).to_pylist(), batch.column(2)
            held = lists.flatten()
            kind, a, pos, ref, at = (held.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in range(5))
            row = np.repeat(np.arange(len(raws)), lists.value_lengths().to_numpy(zero_copy_only=False))
            uid = batch.column(0).to_numpy()[row] if len(row) else np.zeros(0, np.int64)
            sizes = np.array([len(r) for r in raws], np.int64)[row] if len(row) else np.zeros(0, np.int64)
            low, high = np.maximum(pos - reach, 0), np.minimum(pos + length, sizes)
            one = np.flatnonzero(kind == CONTEXT)
            run = np.flatnonzero(kind == COVERED)
            run = run[np.lexsort((pos[run], pos[run] - at[run], ref[run], row[run]))]
            shift = pos[run] - at[run]
            fresh = np.ones(len(run), bool)
            if len(run):
                fresh[1:] = (row[run][1:] != row[run][:-1]) | (ref[run][1:] != ref[run][:-1]) | (shift[1:] != shift[:-1]) | (low[run][1:] > high[run][:-1])
            lead = np.flatnonzero(fresh)
            top = np.maximum.reduceat(high[run], lead) if len(run) else np.zeros(0, np.int64)
            head = run[lead]
            data = [raws[r][x:y] for r, x, y in zip(row[one].tolist(), low[one].tolist(), high[one].tolist(), strict=True)]
            data += [raws[r][x:y] for r, x, y in zip(row[head].tolist(), low[head].tolist(), top.tolist(), strict=True)]
            both = lambda x, y: np.concatenate([x, y])
            columns = [both(kind[one], kind[head]), both(a[one], a[head]), both(uid[one], uid[head]), both(pos[one], low[head]), both(pos[one] - low[one], 0 * head), both(high[one] - pos[one], top - low[head]), both(ref[one], ref[head]), both(at[one], low[head] - shift[lead])]
            arrays = [pa.array(x.astype(np.int32) if k in (0, 4, 5) else x.astype(np.int64)) for k, x in enumerate(columns)]
            out = pa.RecordBatch.from_arrays([*arrays, pa.array(data, pa.binary())], [x.split()[0] for x in FETCHED.split(", ")])
            # Contexts overlap, so they may hold several times the batch's bytes: they leave in parts.
            yield from (out.slice(k, 20_000) for k in range(0, out.num_rows, 20_000))

    grouped = marks.groupBy("uid").agg(F.collect_list(F.struct("kind", "a", "pos", "ref", "at")).alias("marks"))
    return docs.join(grouped, "uid").select("uid", "raw", "marks").mapInArrow(fetch, FETCHED)


def difference_cover(period: int) -> np.ndarray:
    """Offsets such that any two residues have an offset that takes both into the set (period a square)."""
    side = int(round(period**0.5))
    if side * side != period:
        raise ValueError("the period must be a square")
    return np.array(sorted({*range(side), *range(0, period, side)}))


class SuffixBlock:
    """Suffixes of one block of text, sorted a bucket at a time to ``depth`` bytes; memory is the block, the ranks of its
    cover sample and one bucket's keys."""

    def __init__(self, text: np.ndarray, depth: int, period: int = 16):
        self.n, self.depth, self.period = len(text), depth, period
        self.text = np.concatenate([text, np.zeros(depth + 2 * period, np.uint8)])
        inside = np.isin(np.arange(period), difference_cover(period))
        self._to_sample = np.array([next(d for d in range(period) if inside[(r + d) % period]) for r in range(period)])
        self._shift = {(p, q): next(d for d in range(period) if inside[(p + d) % period] and inside[(q + d) % period]) for p in range(period) for q in range(period)}
        # Ranks of the sample: by one period, then doubled by rank pairs (a sample place plus periods is a sample place).
        place = np.arange(self.n + period)
        sample = place[inside[place % period]]
        self._rank = np.zeros(self.n + 2 * period, np.int64)
        words = self._words(np.minimum(sample, self.n))
        order = np.lexsort((words[:, 1], words[:, 0])) if period == 16 else np.lexsort(words.T[::-1])
        step = np.concatenate([[0], np.cumsum((words[order][1:] != words[order][:-1]).any(1))]) if len(sample) else np.zeros(0, np.int64)
        self._rank[sample[order]] = 1 + step
        known = period
        while known < depth and len(sample):
            ahead = np.where(sample + known < self.n, self._rank[np.minimum(sample + known, self.n)], 0)
            pair = self._rank[sample] * (len(sample) + 1) + ahead
            self._rank[sample] = 1 + np.unique(pair, return_inverse=True)[1]
            known *= 2

    def _words(self, places: np.ndarray) -> np.ndarray:
        """The next ``period`` bytes as numbers that compare as the bytes do."""
        head = np.lib.stride_tricks.sliding_window_view(self.text, self.period)[places]
        return np.ascontiguousarray(head).view(">u8").astype(np.uint64)

    def _compare(self, p: int, q: int) -> int:
        d = self._shift[p % self.period, q % self.period]
        return int(self._rank[p + d]) - int(self._rank[q + d])

    def sort_bucket(self, suffixes: np.ndarray, bucket: np.ndarray | None = None) -> np.ndarray:
        """Order of the suffixes by their first ``depth`` bytes, buckets one after another."""
        bucket = np.zeros(len(suffixes), np.int64) if bucket is None else bucket
        words = self._words(suffixes)
        residue = suffixes % self.period
        # Members of a tie that stand alike in the period compare by the rank of one sample place each.
        order = np.lexsort((self._rank[suffixes + self._to_sample[residue]], *words.T[::-1], bucket))
        tied = np.concatenate([[False], (words[order][1:] == words[order][:-1]).all(1) & (bucket[order][1:] == bucket[order][:-1])]) if len(order) else np.zeros(0, bool)
        cuts = np.flatnonzero(~tied)
        if len(cuts):
            mixed = np.flatnonzero(np.minimum.reduceat(residue[order], cuts) != np.maximum.reduceat(residue[order], cuts))
            for x, y in zip(cuts[mixed].tolist(), np.append(cuts, len(order))[mixed + 1].tolist(), strict=True):
                order[x:y] = sorted(order[x:y].tolist(), key=functools.cmp_to_key(lambda i, j: self._compare(int(suffixes[i]), int(suffixes[j]))))
        return order

    def common_prefixes(self, suffixes: np.ndarray) -> np.ndarray:
        """Bytes that each suffix shares with the one before it, ``depth`` at most; 0 for the first."""
        heads = np.lib.stride_tricks.sliding_window_view(self.text, self.depth)[suffixes]
        differ = heads[1:] != heads[:-1]
        shared = np.where(differ.any(1), differ.argmax(1), self.depth)
        return np.concatenate([[0], shared]) if len(suffixes) else np.zeros(0, np.int64)


def _block_repeats(keys, uids, places, lefts, rights, los, his, data: list[bytes], length: int, gram: int):
    """(uid, start, end) of strings in these contexts that also start earlier. Contexts of one key form a bucket; only strings
    with the anchor at los to his - 1 count."""
    reach, n = length - gram, len(keys)
    buffer = np.frombuffer(b"".join(data) + bytes(length), np.uint8)
    base = np.cumsum([0, *(len(x) for x in data[:-1])]) + lefts
    stride = 16 * (-(-(length + 1) // 16))
    ahead = np.arange(stride)
    after = np.where(ahead < rights[:, None], buffer[np.minimum(base[:, None] + ahead, len(buffer) - 1)], 0).astype(np.uint8)
    back = np.arange(reach)
    before = np.where(back < lefts[:, None], buffer[np.maximum(base[:, None] - 1 - back, 0)], 0).astype(np.uint8)
    block = SuffixBlock(after.reshape(-1), length)
    order = block.sort_bucket(np.arange(n) * stride, keys)
    shared = block.common_prefixes(order * stride)
    key, uid, place, left, right = keys[order], uids[order], places[order], lefts[order], rights[order]
    lo, hi, before = los[order], his[order], before[order]
    painted = np.zeros((n, reach + length + 1), np.int32)
    near = np.arange(n)  # suffixes that still share enough with the one ``gap`` places on
    prefix = np.full(n, length, np.int64)
    gap = 0
    while True:
        gap += 1
        near = near[near + gap < n]
        near = near[key[near] == key[near + gap]]
        prefix[near] = np.minimum(prefix[near], shared[near + gap])
        near = near[prefix[near] >= gram]  # strings reach ``reach`` bytes back at most
        if not len(near):
            break
        i, j = near, near + gap
        r = np.minimum(prefix[i], np.minimum(right[i], right[j]))
        may = r + np.minimum(left[i], left[j]) >= length
        i, j, r = i[may], j[may], r[may]
        differ = before[i] != before[j]
        back_shared = np.where(differ.any(1), differ.argmax(1), reach) if len(i) else np.zeros(0, np.int64)
        most = np.minimum(np.minimum(back_shared, np.minimum(left[i], left[j])), hi[i] - 1)
        least = np.maximum(length - r, lo[i])
        later = np.where((uid[i] > uid[j]) | ((uid[i] == uid[j]) & (place[i] > place[j])), i, j)
        hit = (least <= most) & ((uid[i] != uid[j]) | (place[i] != place[j]))
        np.add.at(painted, (later[hit], reach - most[hit]), 1)
        np.add.at(painted, (later[hit], reach - least[hit] + length), -1)
    on = np.cumsum(painted, 1) > 0
    edge = np.diff(np.concatenate([np.zeros((n, 1), np.int8), on.astype(np.int8)], 1), axis=1)
    row, start = np.nonzero(edge == 1)
    _, stop = np.nonzero(edge == -1)
    return _merged(uid[row], place[row] - reach + start, place[row] - reach + stop)


def _cut_buckets(contexts: DataFrame, length: int, gram: int, bucket: int) -> tuple[DataFrame, DataFrame | None]:
    """Contexts with their bucket (key, lo, hi), none of more than ``bucket`` rows, and those of parts of one string each."""
    rows = contexts.select(F.col("a").alias("key"), F.lit(0).alias("lo"), F.lit(length - gram + 1).alias("hi"), "uid", "pos", "left", "right", "bytes")
    ready, single = None, None
    add = lambda have, more: more if have is None else have.unionByName(more)
    while True:
        big = written(rows.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > bucket).select("key"), "big")
        n_big = big.count()
        if not n_big:
            return add(ready, rows), single
        ready = add(ready, rows.join(small(big, n_big), "key", "left_anti"))
        hot = rows.join(small(big, n_big), "key", "left_semi")
        single = add(single, hot.where("hi - lo = 1"))
        mid = F.floor((F.col("lo") + F.col("hi")) / 2).cast("int")
        parts = hot.where("hi - lo > 1").withColumn("part", F.explode(F.array(F.struct(F.col("lo").alias("x"), mid.alias("y")), F.struct(mid.alias("x"), F.col("hi").alias("y")))))
        # Strings with the anchor at x to y - 1 hold the x bytes before it and the length - y + 1 after it.
        parts = parts.where(f"left >= part.x AND right >= {length} - part.y + 1")
        shared = F.expr(f"substring(bytes, left - part.x + 1, part.x + {length} - part.y + 1)")
        rows = parts.select(F.xxhash64("key", "part.x", shared).alias("key"), F.col("part.x").alias("lo"), F.col("part.y").alias("hi"), "uid", "pos", "left", "right", "bytes")
        rows = written(rows, "parts")


def repeats(docs: DataFrame, length: int = 100, gram: int = 20, block_rows: int = 4000, bucket: int = 512, slab: int = 1 << 19, mask: int = (1 << 64) - 1) -> DataFrame:
    """(uid, start, end): spans whose strings start earlier elsewhere; ``docs`` has (uid, raw) with unique, ordered uid >= 0
    or any uid but -1."""
    again = written(_again(_anchor_rows(docs, length, gram, slab, mask=mask)), "again")
    fetched = written(_fetched(docs, again.where(F.col("kind") != SPAN), length, gram), "fetched")
    runs = fetched.where(F.col("kind") == COVERED).select("ref", "at", "uid", F.col("pos").alias("start"), (F.col("pos") + F.col("right")).alias("end"), "bytes")
    earlier = docs.select(F.col("uid").alias("ref"), F.col("raw").alias("there"))
    same = F.expr("at >= 0 AND substring(there, CAST(at AS INT) + 1, length(bytes)) = bytes")
    checked = written(runs.join(earlier, "ref").select("uid", "start", "end", "ref", "at", same.alias("same")), "checked")
    contexts = fetched.where(F.col("kind") == CONTEXT)
    false = checked.where("not same")
    if false.limit(1).count():
        # Different bytes under equal hashes: these contexts and the earlier ones are sorted like any others.
        hit = again.where(F.col("kind") == COVERED).alias("m").join(false.alias("f"), F.expr("m.uid = f.uid AND m.ref = f.ref AND m.pos - m.at = f.start - f.at AND m.pos BETWEEN f.start AND f.end"))
        pair = F.explode(F.array(F.struct(F.col("m.uid").alias("uid"), F.col("m.pos").alias("pos")), F.struct(F.col("m.ref").alias("uid"), F.col("m.at").alias("pos"))))
        own = hit.select("m.a", pair.alias("x")).select(F.lit(CONTEXT).alias("kind"), "a", "x.uid", "x.pos", F.col("x.uid").alias("ref"), F.col("x.pos").alias("at")).distinct()
        contexts = contexts.unionByName(written(_fetched(docs, own, length, gram), "contested"))
    rows, single = _cut_buckets(contexts, length, gram, bucket)
    names = ["uid", "start", "end"]

    def blocks(batches):
        held, count = [], 0

        def solve(table):
            numbers = (table.column(k).to_numpy().astype(np.int64) for k in ("key", "uid", "pos", "left", "right", "lo", "hi"))
            return pa.RecordBatch.from_arrays([pa.array(x) for x in _block_repeats(*numbers, table.column("bytes").to_pylist(), length, gram)], names)

        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            count += batch.num_rows
            if count >= block_rows:
                table = pa.Table.from_batches(held).combine_chunks()
                key = table.column("key").to_numpy()
                last = int(np.searchsorted(key, key[-1]))  # the last bucket may go on
                for x in range(0, last, block_rows):
                    x, y = (int(np.searchsorted(key, key[k])) if k < last else last for k in (x, x + block_rows))
                    if x < y:
                        yield solve(table.slice(x, y - x).combine_chunks())
                held = table.slice(last).combine_chunks().to_batches()
                count = table.num_rows - last
        if held:
            yield solve(pa.Table.from_batches(held).combine_chunks())

    found = rows.repartition("key").sortWithinPartitions("key").mapInArrow(blocks, "uid long, start long, end long")
    out = again.where(F.col("kind") == SPAN).select("uid", F.col("pos").alias("start"), F.col("at").alias("end"))
    out = out.unionByName(checked.where("same").select("uid", "start", "end")).unionByName(found)
    if single is None:
        return out
    # One string a part: the earliest by an aggregate over its bytes.
    strings = single.where(f"left >= lo AND right >= {length} - lo").select("uid", (F.col("pos") - F.col("lo")).alias("start"), F.expr(f"substring(bytes, left - lo + 1, {length})").alias("string"))
    # Written, so that the planner can split the join below where a string is very common.
    earliest = written(strings.groupBy("string").agg(F.min(F.struct("uid", "start")).alias("first")), "earliest")
    common = strings.join(earliest, "string").where("uid > first.uid OR (uid = first.uid AND start > first.start)")
    return out.unionByName(common.select("uid", "start", (F.col("start") + length).alias("end")))


def keyed(docs: DataFrame) -> DataFrame:
    """(uid, doc_id, raw) with unique uid in the order of (doc_id, text); doc_id itself where it is unique."""
    rows = docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("raw"))
    odd = docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1 or doc_id is null").limit(1).count()
    if not odd:
        return rows.select(F.col("doc_id").alias("uid"), "doc_id", "raw")
    ordered = rows.repartitionByRange("doc_id", "raw").sortWithinPartitions("doc_id", "raw")
    return written(ordered.select(F.monotonically_increasing_id().alias("uid"), "doc_id", "raw"), "keyed")


def deduplicated(docs: DataFrame, length: int = 100, gram: int = 20, texts: bool = True) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans, kept) per row; spans are (start, end) of removed runs.
    Without ``texts`` the last two are left out."""
    rows = keyed(docs)
    spans = written(repeats(rows.select("uid", "raw"), length, gram), "spans").groupBy("uid").agg(F.collect_list(F.struct("start", "end")).alias("spans"))

    def cut(batches):
        for batch in batches:
            out = [[] for _ in range(6 if texts else 4)]
            for raw, found in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                runs = []
                for a, b in sorted((s["start"], s["end"]) for s in found or ()):
                    if runs and a <= runs[-1][1]:
                        runs[-1][1] = max(b, runs[-1][1])
                    else:
                        runs.append([a, b])
                edges = [0, *(x for r in runs for x in r), len(raw)]
                kept = b"".join(raw[edges[k] : edges[k + 1]] for k in range(0, len(edges), 2))
                values = (len(raw), len(raw) - len(kept), len(runs), hashlib.sha256(kept).hexdigest(), [{"start": a, "end": b} for a, b in runs], kept)
                for column, value in zip(out, values[: len(out)], strict=True):
                    column.append(value)
            span = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), span, pa.binary())
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "kept"]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(out, kinds, strict=False))], names[: len(out) + 1])

    joined = rows.join(spans, "uid", "left").select("doc_id", "raw", "spans")
    columns = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    return joined.mapInArrow(cut, columns + (", spans array<struct<start:long,end:long>>, kept binary" if texts else ""))
