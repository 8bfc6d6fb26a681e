"""Interleaved keys: the length-l prefix of a key is the point's cell at level l. Columns only, inside codegen."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from .schedule import SplitSchedule

WORD = 60


def _bit(value: Column, at: int, to: int) -> Column:
    return F.shiftleft(F.shiftright(value, at).bitwiseAND(F.lit(1).cast("long")), to)


def cell_key(schedule: SplitSchedule, axes: list[str] | None = None) -> Column:
    """BIGINT key of the columns a0, a1, ...; for at most 62 bits."""
    if schedule.q > 62:
        raise ValueError("more than 62 bits: use wide_key")
    names = axes or [f"a{i}" for i in range(len(schedule.bits))]
    terms = [_bit(F.col(names[a]), bit, schedule.q - 1 - k) for k, (a, bit) in enumerate(schedule.steps)]
    return reduce(lambda x, y: x.bitwiseOR(y), terms, F.lit(0).cast("long"))


def wide_key(schedule: SplitSchedule, axes: list[str] | None = None) -> Column:
    """ARRAY<BIGINT> of 60-bit words, for any number of bits."""
    names = axes or [f"a{i}" for i in range(len(schedule.bits))]
    words = []
    for first in range(0, max(1, schedule.q), WORD):
        part = schedule.steps[first : first + WORD]
        terms = [_bit(F.col(names[a]), bit, len(part) - 1 - k) for k, (a, bit) in enumerate(part)]
        words.append(reduce(lambda x, y: x.bitwiseOR(y), terms, F.lit(0).cast("long")))
    return F.array(*words)


def key_axis(schedule: SplitSchedule, axis: int, key: Column) -> Column:
    """Coordinate of one axis from a whole key."""
    terms = [_bit(key, schedule.q - 1 - k, bit) for k, (a, bit) in enumerate(schedule.steps) if a == axis]
    return reduce(lambda x, y: x.bitwiseOR(y), terms, F.lit(0).cast("long"))


def whole(schedule: SplitSchedule, level: Column, prefix: Column) -> Column:
    """Smallest key of a cell."""
    return F.call_function("shiftleft", prefix, (F.lit(schedule.q) - level).cast("int"))


def free_bits(schedule: SplitSchedule, axis: int, level: Column) -> Column:
    """Bits of an axis that are still open at a level."""
    table = F.array(*[F.lit(schedule.bits[axis] - schedule.used(lv)[axis]) for lv in range(schedule.q + 1)])
    return F.element_at(table, level.cast("int") + 1)


def cell_axis(schedule: SplitSchedule, axis: int, level: Column, prefix: Column) -> Column:
    """Cell coordinate on one axis: the point coordinate without its open bits."""
    return F.call_function("shiftright", key_axis(schedule, axis, whole(schedule, level, prefix)), free_bits(schedule, axis, level))


def cell_bounds(schedule: SplitSchedule, axis: int, level: Column, prefix: Column) -> tuple[Column, Column]:
    """Lowest and highest coordinate of a cell on one axis."""
    low = key_axis(schedule, axis, whole(schedule, level, prefix))
    return low, low + F.call_function("shiftleft", F.lit(1).cast("long"), free_bits(schedule, axis, level)) - 1


def box_to_ranges(schedule: SplitSchedule, box: list[tuple[int, int]], max_ranges: int = 64) -> list[tuple[int, int]]:
    """Key ranges that cover a box of closed intervals, at most ``max_ranges``; exact if it takes no more."""
    out, open_ = [], [(0, 0)]

    def bounds(level, prefix):
        lows = [0] * len(schedule.bits)
        key = prefix << (schedule.q - level)
        for k, (a, bit) in enumerate(schedule.steps):
            lows[a] |= (key >> (schedule.q - 1 - k) & 1) << bit
        return [(lo, lo + (1 << (b - u)) - 1) for lo, b, u in zip(lows, schedule.bits, schedule.used(level), strict=True)]

    while open_:
        level, prefix = open_.pop(0)
        cell = bounds(level, prefix)
        if any(h < a or lo > b for (lo, h), (a, b) in zip(cell, box, strict=True)):
            continue
        inside = all(a <= lo and h <= b for (lo, h), (a, b) in zip(cell, box, strict=True))
        if inside or level == schedule.q or len(out) + len(open_) + 2 > max_ranges:
            shift = schedule.q - level
            out.append((prefix << shift, (prefix + 1 << shift) - 1))
        else:
            open_ += [(level + 1, 2 * prefix), (level + 1, 2 * prefix + 1)]
    merged: list[tuple[int, int]] = []
    for a, b in sorted(out):
        if merged and a == merged[-1][1] + 1:
            merged[-1] = (merged[-1][0], b)
        else:
            merged.append((a, b))
    return merged
