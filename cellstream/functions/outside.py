"""Points outside their lattice. A coordinate past its axis's bits, below zero or null would lose its high part in a key and meet
other points' cells. Such a set gets bits in front of the schedule, one number for each cell of the lattice's own size along
an axis and one for null, so that it is coded, and its cells are given, as they are. A set inside its lattice is left as it is.
Where these numbers would not fit a key, since few points lie far out, the outer cells that occur are numbered instead."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .schedule import SplitSchedule

#: Bits that a key can have.
MOST_BITS = 62


def outer_cell(column: str, bits: int) -> Column:
    """The lattice cell that a coordinate is in: 0 inside, null for null."""
    return F.shiftright(F.col(column), bits)


def inner(column: str, bits: int) -> Column:
    """The coordinate in its lattice cell; 0 for null."""
    return F.coalesce(F.col(column).bitwiseAND(F.lit((1 << bits) - 1).cast("long")), F.lit(0).cast("long"))


@dataclass(frozen=True)
class Frame:
    own: SplitSchedule
    schedule: SplitSchedule
    first: tuple[int, ...]  # outer cell with number 0, an axis
    null: tuple[int, ...]  # the number of null, an axis; -1 if there is none

    @property
    def extra(self) -> int:
        return self.schedule.q - self.own.q

    def coordinates(self, cells: DataFrame, level: int) -> DataFrame:
        """(level, c0.., cnt) of cells that are all at ``level`` of the lattice's own schedule."""
        from ..operators.tree import with_coordinates

        used, out = self.own.used(level), with_coordinates(cells, self.schedule).withColumn("level", F.lit(level))
        for i, u in enumerate(used):
            c, outer = F.col(f"c{i}"), F.shiftright(f"c{i}", u)
            moved = F.shiftleft(outer + self.first[i], u).bitwiseOR(c.bitwiseAND(F.lit((1 << u) - 1).cast("long")))
            if self.null[i] >= 0:
                moved = F.when(outer != self.null[i], moved)
            if self.null[i] >= 0 or self.first[i]:
                out = out.withColumn(f"c{i}", moved)
        return out


@dataclass(frozen=True)
class Numbered(Frame):
    """A frame whose outer cells are the rows of a table (number, o0..): an axis of their numbers stands before the others."""

    outer: DataFrame

    def coordinates(self, cells: DataFrame, level: int) -> DataFrame:
        from ..operators.tree import with_coordinates

        used, d = self.own.used(level), len(self.own.bits)
        out = with_coordinates(cells, self.schedule).withColumnRenamed(f"c{d}", "number").join(self.outer, "number")
        moved = [F.shiftleft(f"o{i}", u).bitwiseOR(F.col(f"c{i}")).alias(f"c{i}") for i, u in enumerate(used)]
        return out.select(F.lit(level).alias("level"), *moved, "cnt")


def numbered(points: DataFrame, schedule: SplitSchedule) -> tuple[DataFrame, Frame]:
    """``framed`` by numbers of the outer cells that occur; a row a partition is all that is counted in one place."""
    from pyspark.sql import Window

    from ..sources.shared import written

    d = range(len(schedule.bits))
    row = F.monotonically_increasing_id()
    cells = points.select(*[outer_cell(f"a{i}", schedule.bits[i]).alias(f"o{i}") for i in d]).distinct()
    # Written, since the numbers come from its rows' places and are read twice.
    placed = written(cells.select("*", F.shiftright(row, 33).alias("part"), row.bitwiseAND((1 << 33) - 1).alias("row")), "outer")
    sizes = placed.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    outer = placed.join(sizes.select("part", before.alias("base")), "part").select((F.col("base") + F.col("row")).alias("number"), *[f"o{i}" for i in d])
    width = max(0, placed.count() - 1).bit_length()
    if schedule.q + width > MOST_BITS:
        raise ValueError(f"{schedule.q} bits and 2**{width} cells of the lattice's size: more than a key of {MOST_BITS} bits tells apart")
    out = SplitSchedule.of_axes((*schedule.bits, width), [len(schedule.bits)] * width + [a for a, _ in schedule.steps])
    met = points.join(outer, [outer_cell(f"a{i}", schedule.bits[i]).eqNullSafe(F.col(f"o{i}")) for i in d])
    own = met.select(*[inner(f"a{i}", schedule.bits[i]).alias(f"a{i}") for i in d], F.col("number").alias(f"a{len(schedule.bits)}"))
    return own, Numbered(schedule, out, (), (), outer)


def framed(points: DataFrame, schedule: SplitSchedule) -> tuple[DataFrame, Frame]:
    """The points with their outer cells as high bits, and what undoes it. One row of bounds comes to the driver."""
    d = range(len(schedule.bits))
    ends = [f(outer_cell(f"a{i}", schedule.bits[i])) for i in d for f in (F.min, F.max)]
    row = points.agg(*ends, *[F.coalesce(F.bool_or(F.col(f"a{i}").isNull()), F.lit(False)) for i in d]).first()
    first, null, wide, axes = [], [], [], []
    for i in d:
        low, high, none = row[2 * i], row[2 * i + 1], row[2 * len(schedule.bits) + i]
        cells = 0 if low is None else high - low + 1
        first.append(low or 0)
        null.append(cells if none else -1)
        wide.append(max(0, cells + none - 1).bit_length())
    if schedule.q + sum(wide) > MOST_BITS:
        return numbered(points, schedule)
    out, terms = SplitSchedule.of_axes(tuple(b + w for b, w in zip(schedule.bits, wide, strict=True)), [i for i in d for _ in range(wide[i])] + [a for a, _ in schedule.steps]), []
    for i, b in enumerate(schedule.bits):
        number = F.coalesce(outer_cell(f"a{i}", b) - first[i], F.lit(max(0, null[i])).cast("long"))
        terms.append(F.shiftleft(number, b).bitwiseOR(inner(f"a{i}", b)).alias(f"a{i}"))
    frame = Frame(schedule, out, tuple(first), tuple(null))
    return (points if not any(wide) and not any(first) and max(null, default=-1) < 0 else points.select(*terms)), frame
