"""Coarse versions, anytime decoding, regions of interest, and the laws that place points inside cells."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.keys import cell_axis, cell_bounds
from ..functions.schedule import SplitSchedule
from .tree import leaf_multiset


def decode_symbols(symbols: DataFrame, n: int, schedule: SplitSchedule, to_level: int | None = None) -> DataFrame:
    """Relational decoder: wave by wave, each cell meets its left count by its number in the stream.

    For tests and small inputs; the stream codec decodes tiles in parallel. The number of a cell in its wave is its rank by
    prefix, so only (ord, left_cnt) is read from the stream.
    """
    from pyspark.sql import Window

    spark = symbols.sparkSession
    level_to = schedule.q if to_level is None else to_level
    cells = spark.createDataFrame([(0, n)] if n else [], "prefix long, cnt long")
    done = 0
    for level in range(level_to):
        ranked = cells.select("prefix", "cnt", (F.row_number().over(Window.orderBy("prefix")) + done).cast("long").alias("ord"))
        met = ranked.join(symbols.select("ord", "left_cnt"), "ord")
        halves = F.explode(F.array(F.struct((F.col("prefix") * 2).alias("prefix"), F.col("left_cnt").alias("cnt")), F.struct((F.col("prefix") * 2 + 1).alias("prefix"), (F.col("cnt") - F.col("left_cnt")).alias("cnt"))))
        nxt = met.select(halves.alias("h")).select("h.*").where("cnt > 0")
        if level % 4 == 3 or level == level_to - 1:
            from ..sources.shared import written

            nxt = written(nxt, "wave")
        done += cells.count()
        cells = nxt
    return cells.select(F.lit(level_to).alias("level"), "prefix", "cnt")


def frontier_after(symbols: DataFrame, k: int, q: int) -> DataFrame:
    """(level, prefix, cnt): cells known after the first k symbols, of mixed sizes."""
    sent = symbols.where(F.col("ord") <= k)
    halves = F.explode(F.array(F.struct((F.col("prefix") * 2).alias("prefix"), F.col("left_cnt").alias("cnt")), F.struct((F.col("prefix") * 2 + 1).alias("prefix"), (F.col("cnt") - F.col("left_cnt")).alias("cnt"))))
    children = sent.select((F.col("level") + 1).alias("level"), halves.alias("h")).select("level", "h.prefix", "h.cnt").where("cnt > 0")
    root = symbols.where("level = 0").select("level", "prefix", "cnt")
    return root.unionByName(children).join(sent.select("level", "prefix"), ["level", "prefix"], "left_anti")


def box_meets(schedule: SplitSchedule, boxes: list[list[tuple[int, int]]]) -> Column:
    """Whether a cell (level, prefix) meets one of the boxes of closed intervals."""
    tests = []
    for box in boxes:
        sides = []
        for i, (a, b) in enumerate(box):
            low, high = cell_bounds(schedule, i, F.col("level"), F.col("prefix"))
            sides.append((low <= b) & (high >= a))
        tests.append(reduce(lambda x, y: x & y, sides))
    return reduce(lambda x, y: x | y, tests)


def meets_at(schedule: SplitSchedule, boxes: list[list[tuple[int, int]]], level: int) -> Column:
    """``box_meets`` of cells that are all of one level: their coordinates against constants."""
    free = [b - u for b, u in zip(schedule.bits, schedule.used(level), strict=True)]
    cell = []
    for i in range(len(schedule.bits)):
        ours = [k for k, (a, _) in enumerate(schedule.steps[:level]) if a == i]
        bits = [F.shiftleft(F.shiftright("prefix", level - 1 - k).bitwiseAND(F.lit(1).cast("long")), len(ours) - 1 - j) for j, k in enumerate(ours)]
        cell.append(reduce(lambda x, y: x.bitwiseOR(y), bits, F.lit(0).cast("long")))
    tests = [reduce(lambda x, y: x & y, [c.between(a >> f, b >> f) for c, f, (a, b) in zip(cell, free, box, strict=True)]) for box in boxes]
    return reduce(lambda x, y: x | y, tests)


def refine(nodes: DataFrame, schedule: SplitSchedule, boxes, base_level: int, target_level: int) -> DataFrame:
    """Cells of a view that is coarse outside the boxes and fine inside."""
    inside = nodes.where((F.col("level") == target_level) & meets_at(schedule, boxes, target_level))
    coarse = nodes.where((F.col("level") == base_level) & ~meets_at(schedule, boxes, base_level))
    return inside.unionByName(coarse).select("level", "prefix", "cnt")


def roi_cost(nodes: DataFrame, schedule: SplitSchedule, boxes) -> DataFrame:
    """(bits_all, bits_roi, share): what a region needs of the whole stream."""
    bits = F.log2(F.col("cnt") + 1)
    sums = nodes.agg(F.sum(bits).alias("a"), F.sum(F.when(box_meets(schedule, boxes), bits)).alias("r"))
    return sums.select(F.round("a", 3).alias("bits_all"), F.round("r", 3).alias("bits_roi"), F.round(F.col("r") / F.col("a"), 4).alias("share"))


def roi_session(nodes: DataFrame, schedule: SplitSchedule, boxes) -> DataFrame:
    """(step, nodes_sent, bits_sent): a walk over boxes where each step sends only nodes the client lacks."""
    flags = [box_meets(schedule, [b]) for b in boxes]
    first = F.coalesce(*[F.when(f, F.lit(k)) for k, f in enumerate(flags)])
    return nodes.withColumn("step", first).where("step is not null").groupBy("step").agg(F.count(F.lit(1)).alias("nodes_sent"), F.round(F.sum(F.log2(F.col("cnt") + 1)), 3).alias("bits_sent"))


def beside(cells: DataFrame, schedule: SplitSchedule) -> DataFrame:
    """Cells of one level with lo<axis> and hi<axis>: points of the cells next to each on either side, 0 where there is none."""
    d, out = len(schedule.bits), cells
    axes = [cell_axis(schedule, i, F.col("level"), F.col("prefix")).alias(f"c{i}") for i in range(d)]
    own = cells.select("level", *axes, "cnt")
    out = cells.select("*", *axes)
    for i in range(d):
        for sign, name in ((1, f"lo{i}"), (-1, f"hi{i}")):
            other = own.select("level", *[(F.col(f"c{k}") + (sign if k == i else 0)).alias(f"c{k}") for k in range(d)], F.col("cnt").alias(name))
            out = out.join(other, ["level", *[f"c{k}" for k in range(d)]], "left").fillna(0, [name])
    return out.drop(*[f"c{i}" for i in range(d)])


def synthesise(cells: DataFrame, schedule: SplitSchedule, law: str = "uniform", seed: int = 7, grid: int = 16) -> DataFrame:
    """One row per point: a0.. inside its cell.

    uniform: a whole-number congruential draw on (prefix, number, axis); regular: even steps along each axis;
    grid: the cell centre snapped down to a grid step; gaussian: the mean of four draws; linear: a density that goes along each axis
    from that of the cell on one side to that of the other (one point more in each), so points lean to the dense side.
    """
    one = (beside(cells, schedule) if law == "linear" else cells).withColumn("i", F.explode(F.sequence(F.lit(1).cast("long"), F.col("cnt"))))
    axes = []
    for k in range(len(schedule.bits)):
        low, high = cell_bounds(schedule, k, F.col("level"), F.col("prefix"))
        side = high - low + 1

        def draw(j, k=k):
            x = F.pmod(F.pmod(F.col("prefix"), F.lit(65521)) * 7919 + F.col("i") * 104729 + F.lit(15485863 * (k + 1) + 32452843 * j + seed), F.lit(2147483647))
            return F.pmod(x * 48271, F.lit(2147483647))

        if law == "regular":
            at = low + F.expr("0L") + F.floor((2 * F.col("i") - 1) * side / (2 * F.col("cnt"))).cast("long")
        elif law == "grid":
            mid = low + F.floor(side / 2).cast("long")
            at = F.greatest(low, mid - F.pmod(mid, F.lit(grid)))
        elif law == "linear":
            a, b, u = (F.col(f"lo{k}") + 1).cast("double"), (F.col(f"hi{k}") + 1).cast("double"), draw(0) / 2147483647.0
            place = F.when(a == b, u).otherwise((F.sqrt(a * a + (b * b - a * a) * u) - a) / (b - a))
            at = low + F.least(side - 1, F.floor(place * side).cast("long"))
        elif law == "gaussian":
            at = low + F.floor((draw(0) + draw(1) + draw(2) + draw(3)) / 4 / 2147483647 * side).cast("long")
        else:
            at = low + F.pmod(draw(0), side)
        axes.append(at.alias(f"a{k}"))
    return one.select(*axes)


def law_errors(points: DataFrame, schedule: SplitSchedule, level: int, grid: int = 16) -> DataFrame:
    """(law, rmse, chosen): expected distance, over all axes, from a point to one its cell's law places at this level.

    A law's mean and variance on an axis are closed forms of the cell and its count, so each cell gives only its count and
    two sums an axis: one aggregate with partial sums, whatever a cell holds. ``chosen`` marks the smallest, by name if tied.
    """
    keyed = leaf_multiset(points, schedule).select("m", "key", F.expr(f"shiftright(key, {schedule.q - level})").alias("prefix"))
    d, names = len(schedule.bits), ("centre", "gaussian", "grid", "regular", "uniform")
    # Offsets from the cell's low corner keep the squares small.
    own = [(cell_axis(schedule, i, F.lit(schedule.q), F.col("key")) - cell_bounds(schedule, i, F.lit(level), F.col("prefix"))[0]).cast("double") for i in range(d)]
    sums = [s for i, x in enumerate(own) for s in (F.sum(x * F.col("m")).alias(f"s{i}"), F.sum(x * x * F.col("m")).alias(f"t{i}"))]
    cells = keyed.groupBy("prefix").agg(F.sum("m").alias("cnt"), *sums)
    errors = {n: F.lit(0.0) for n in names}
    for i in range(d):
        low, high = cell_bounds(schedule, i, F.lit(level), F.col("prefix"))
        side = (high - low + 1).cast("double")
        mid, spread = (side - 1) / 2, (side * side - 1) / 12
        half = low + F.floor((high - low + 1) / 2).cast("long")
        of = {
            "centre": (mid, F.lit(0.0)), "gaussian": (mid, spread / 4), "grid": ((F.greatest(low, half - F.pmod(half, F.lit(grid))) - low).cast("double"), F.lit(0.0)),
            "regular": (mid, side * side / 12 * (1 - 1 / (F.col("cnt") * F.col("cnt")))), "uniform": (mid, spread),
        }
        for n, (mean, var) in of.items():
            errors[n] = errors[n] + F.col(f"t{i}") - 2 * mean * F.col(f"s{i}") + F.col("cnt") * (mean * mean + var)
    total = cells.agg(F.sum("cnt").alias("n"), *[F.sum(e).alias(n) for n, e in errors.items()])
    laws = F.array(*[F.struct(F.round(F.sqrt(F.col(n) / F.col("n")), 4).alias("rmse"), F.lit(n).alias("law")) for n in names])
    rows = total.where("n > 0").select(F.array_min(laws)["law"].alias("best"), F.explode(laws).alias("x"))
    return rows.select("x.law", "x.rmse", (F.col("x.law") == F.col("best")).alias("chosen"))


def choose_law(points: DataFrame, schedule: SplitSchedule, level: int, grid: int = 16) -> str | None:
    """Law to name in a header; None for an empty set."""
    best = law_errors(points, schedule, level, grid).where("chosen").first()
    return best["law"] if best else None


def distortion(points: DataFrame, schedule: SplitSchedule, levels: list[int]) -> DataFrame:
    """(level, max_error, rmse) of cell centres, over all axes, for each level."""
    rows = leaf_multiset(points, schedule).select("key", "m", F.explode(F.array(*[F.lit(lv) for lv in levels])).alias("level"))
    prefix = F.call_function("shiftright", F.col("key"), (F.lit(schedule.q) - F.col("level")).cast("int"))
    rows = rows.withColumn("prefix", prefix)
    errors = []
    for i in range(len(schedule.bits)):
        low, high = cell_bounds(schedule, i, F.col("level"), F.col("prefix"))
        own = cell_axis(schedule, i, F.lit(schedule.q), F.col("key"))
        errors.append(F.abs(own - (low + high) / 2.0))
    square = reduce(lambda a, b: a + b, [e * e for e in errors])
    return rows.groupBy("level").agg(F.max(F.greatest(*errors) if len(errors) > 1 else errors[0]).alias("max_error"), F.round(F.sqrt(F.sum(square * F.col("m")) / F.sum("m")), 4).alias("rmse"))
