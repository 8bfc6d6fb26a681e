"""Integer range coder: 64-bit range, 16-bit words, carry propagated into words already out."""

from __future__ import annotations

import numpy as np

_TOP, _WORD = 1 << 64, 1 << 48


def _rest(total: int) -> int:
    return ((total - 1) & 0xFFFFFFFF) + 1


def _digits(total: int) -> tuple[int, int, int]:
    """High digits of an alphabet above 2**32: how many, the weight of a full one, and of the last one."""
    digits = (total - 1 >> 32) + 1
    weight = max(1, (1 << 31) // digits)
    return digits, weight, max(1, _rest(total) * weight >> 32)


class Encoder:
    def __init__(self):
        self._low, self._range, self._words = 0, _TOP - 1, []

    def put(self, cum: int, freq: int, total: int) -> None:
        """Narrow to [cum, cum + freq) of total; total at most 2**32."""
        part = self._range // total
        self._low += part * cum
        self._range = part * freq
        if self._low >= _TOP:
            self._low -= _TOP
            self._carry()
        while self._range < _WORD:
            self._words.append(self._low >> 48)
            self._low = (self._low << 16) & (_TOP - 1)
            self._range <<= 16

    def _carry(self) -> None:
        k = len(self._words) - 1
        while self._words[k] == 0xFFFF:
            self._words[k] = 0
            k -= 1
        self._words[k] += 1

    def put_uniform(self, value: int, total: int) -> None:
        if total > 1 << 32:
            digits, weight, tail = _digits(total)
            top = value >> 32
            self.put(top * weight, tail if top == digits - 1 else weight, (digits - 1) * weight + tail)
            self.put_uniform(value & 0xFFFFFFFF, _rest(total) if top == digits - 1 else 1 << 32)
        elif total > 1:
            self.put(value, 1, total)

    def finish(self) -> bytes:
        """The shortest end after which any bytes may follow; nothing for no symbols."""
        if not self._words and self._low == 0 and self._range == _TOP - 1:
            return b""
        for k in range(1, 9):
            step = 1 << (64 - 8 * k)
            value = -(-self._low // step) * step
            if value + step <= self._low + self._range:
                break
        if value >= _TOP:
            value -= _TOP
            self._carry()
        return b"".join(w.to_bytes(2, "big") for w in self._words) + value.to_bytes(8, "big")[:k]


class Decoder:
    def __init__(self, data: bytes):
        self._data, self._at, self._code, self._range = data, 0, 0, _TOP - 1
        for _ in range(4):
            self._code = self._code << 16 | self._next()

    def _next(self) -> int:
        two = self._data[self._at : self._at + 2]
        self._at += 2
        return int.from_bytes(two.ljust(2, b"\0"), "big")

    def target(self, total: int) -> int:
        return min(total - 1, self._code // (self._range // total))

    def take(self, cum: int, freq: int, total: int) -> None:
        part = self._range // total
        self._code -= part * cum
        self._range = part * freq
        while self._range < _WORD:
            self._code = self._code << 16 | self._next()
            self._range <<= 16
        if self._code >= self._range or self._at > len(self._data) + 16:
            raise ValueError("damaged or cut payload")

    def get_uniform(self, total: int) -> int:
        if total > 1 << 32:
            digits, weight, tail = _digits(total)
            top = min(digits - 1, self.target((digits - 1) * weight + tail) // weight)
            self.take(top * weight, tail if top == digits - 1 else weight, (digits - 1) * weight + tail)
            return top << 32 | self.get_uniform(_rest(total) if top == digits - 1 else 1 << 32)
        if total <= 1:
            return 0
        value = self.target(total)
        self.take(value, 1, total)
        return value


#: Bits of a group of digits of several radices, so that a group's total stays within 2**32 with one more digit of four bits.
_GROUP = 28


def radix_groups(sizes: np.ndarray) -> np.ndarray:
    """First of each run of alphabets (of 2 symbols or more) that are coded as one number; alphabets over 16 stand alone."""
    bits = np.ceil(np.log2(np.minimum(sizes, 16))).astype(np.int64)
    start = np.cumsum(bits) - bits
    block, alone = start // _GROUP, sizes > 16
    new = np.ones(len(sizes), bool)
    new[1:] = (block[1:] != block[:-1]) | alone[1:] | alone[:-1]
    return np.flatnonzero(new)


def _places(starts: np.ndarray, n: int):
    """Indices of the first, second, ... member of each group."""
    lengths = np.diff(np.append(starts, n))
    for k in range(int(lengths.max(initial=0))):
        yield np.flatnonzero(lengths > k), starts[lengths > k] + k


def put_digits(coder: Encoder, values: np.ndarray, sizes: np.ndarray) -> None:
    """Uniform symbols, many as one number of mixed radix."""
    starts = radix_groups(sizes)
    number, total = np.zeros(len(starts), np.int64), np.ones(len(starts), np.int64)
    for group, at in _places(starts, len(sizes)):
        number[group] += values[at] * total[group]
        total[group] *= sizes[at]
    for v, t in zip(number.tolist(), total.tolist(), strict=True):
        coder.put_uniform(v, t)


def get_digits(coder: Decoder, sizes: np.ndarray) -> np.ndarray:
    starts = radix_groups(sizes)
    total = np.ones(len(starts), np.int64)
    for group, at in _places(starts, len(sizes)):
        total[group] *= sizes[at]
    number = np.array([coder.get_uniform(t) for t in total.tolist()], np.int64)
    out = np.zeros(len(sizes), np.int64)
    for group, at in _places(starts, len(sizes)):
        out[at] = number[group] % sizes[at]
        number[group] //= sizes[at]
    return out


#: Fixed-point half bell: weights at sixteenths of sigma, the same in every build.
BELL = [round(65535 * 2.718281828459045 ** (-((k / 16) ** 2) / 2)) for k in range(97)]
_RING = np.array([0, *BELL[:0:-1], *BELL, 0], np.int64)
#: Points of a cell that the bell's whole-number arithmetic takes; no cell of a codestream has more.
MOST = 1 << 42


def _root(x: np.ndarray) -> np.ndarray:
    """Whole-number square root, rounded up."""
    r = np.sqrt(x.astype(np.float64)).astype(np.int64)
    r -= r * r > x
    r += (r + 1) * (r + 1) <= x
    return r + (r * r < x)


def bell_bins(cnt: np.ndarray, left: np.ndarray, right: np.ndarray, shrink: int = 16) -> tuple[np.ndarray, np.ndarray]:
    """The model of 0..cnt around the predicted count as runs of equally likely values: edges (a row a symbol) and weights.

    A discrete bell of sigma = sqrt(cnt) / 2 over a floor, of counts of any size; whole-number arithmetic only, so equal
    on both sides. The number of runs does not depend on the count.
    """
    total = left + right + 2 * shrink
    mean = cnt * (((left + shrink) << 20) // total) >> 16  # in sixteenths
    steps = np.arange(1, len(BELL) + 1) * np.maximum(1, _root(64 * cnt))[:, None]
    centre = 16 * mean[:, None]
    lower, upper = (centre - steps) // 256 + 1, -((-centre - steps) // 256)
    ends = (cnt + 1)[:, None]
    edges = np.clip(np.concatenate([0 * ends, lower[:, ::-1], upper, ends], 1), 0, ends)
    counts = np.diff(edges, axis=1)
    floor = 1 + 3277 * 16 // (cnt + 1)
    shift = np.maximum(0, np.ceil(np.log2(cnt + 2.0)).astype(np.int64) + 17 - 31)
    weights = np.maximum((counts * (floor[:, None] + _RING)) >> shift[:, None], counts > 0)
    return edges, weights


def bell_bits(cnt: np.ndarray, left: np.ndarray, right: np.ndarray, value: np.ndarray, chunk: int = 4096) -> np.ndarray:
    """What the coder pays for each value under ``bell_bins``."""
    out = np.zeros(len(cnt))
    for k in range(0, len(cnt), chunk):
        part = slice(k, k + chunk)
        edges, weights = bell_bins(cnt[part], left[part], right[part])
        at = (edges[:, 1:] <= value[part, None]).sum(1)
        row = np.arange(len(at))
        out[part] = np.log2(weights.sum(1) / weights[row, at]) + np.log2(edges[row, at + 1] - edges[row, at])
    return out


def bell_table(cnt: int, left: int, right: int) -> list[int]:
    """Whole-number weights of the runs that hold 0..cnt, one a value."""
    edges, weights = (x[0] for x in bell_bins(*(np.array([v], np.int64) for v in (cnt, left, right))))
    return np.repeat(weights, np.diff(edges)).tolist()
