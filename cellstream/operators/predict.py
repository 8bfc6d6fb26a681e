"""Density prediction: neighbour counts before a wave is split, the expected lower-half count, and its coding cost."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.keys import cell_axis
from ..functions.schedule import SplitSchedule


def neighbour_counts(
    nodes: DataFrame, schedule: SplitSchedule, order: int = 1, weights: str = "1/dist", shape: str = "face", levels: list[int] | None = None, context: str = "wave", tile_bits: int | None = None
) -> DataFrame:
    """Nodes with nb_left and nb_right: weighted points in the cells on either side along the axis that is split next.

    ``face``: the same other coordinates, up to ``order`` cells away; one window a split axis, and its frames share one sort.
    ``moore``: all cells that touch, by low and high side; an equi-join on shifted cells, for few axes.
    ``context`` (nearest face neighbours only) says what the decoder knows of a neighbour. ``wave``: its count before the
    wave. ``two_colour``: cells of even place go first in that way, odd ones then see the nearer half of both neighbours,
    doubled. ``sequential``: the lower neighbour's nearer half, the upper one's count before the wave.
    ``tile_bits`` keeps face neighbours within a cell's tile (its ancestor at that level); waves above it are one tile.
    """
    if (context != "wave" or tile_bits is not None) and (shape != "face" or (context != "wave" and order != 1)):
        raise ValueError("other contexts are for nearest face neighbours, tiles for face neighbours")
    d, out = len(schedule.bits), None
    use = range(schedule.q) if levels is None else levels
    for axis in range(d):
        own = [lv for lv in use if schedule.steps[lv][0] == axis]
        if not own:
            continue
        rows = nodes.where(F.col("level").isin(own))
        for i in range(d):
            rows = rows.withColumn(f"c{i}", cell_axis(schedule, i, F.col("level"), F.col("prefix")))
        tile = []
        if tile_bits is not None:
            above = F.call_function("shiftright", F.col("prefix"), F.greatest(F.col("level") - tile_bits, F.lit(0)))
            rows, tile = rows.withColumn("tile", F.when(F.col("level") > tile_bits, above).otherwise(0)), ["tile"]
        part = _face(rows, d, axis, order, weights, context, tile) if shape == "face" else _moore(rows, d, axis)
        part = part.select("level", "prefix", "cnt", "left_cnt", "nb_left", "nb_right")
        out = part if out is None else out.unionByName(part)
    return out


def _line(rows: DataFrame, order: int, weigh, tile: list[str]) -> DataFrame:
    """Face neighbours of one axis alone: equi-joins on shifted cells, where a window would hold a whole wave."""
    out = rows.withColumn("nb_left", F.lit(0.0)).withColumn("nb_right", F.lit(0.0))
    for k in range(1, order + 1):
        for sign, side in ((1, "nb_left"), (-1, "nb_right")):
            other = rows.select("level", *tile, (F.col("c0") + sign * k).alias("c0"), F.col("cnt").alias("near"))
            out = out.join(other, ["level", *tile, "c0"], "left").withColumn(side, F.col(side) + F.coalesce("near", F.lit(0)) * weigh(k)).drop("near")
    return out


def _face(rows: DataFrame, d: int, axis: int, order: int, weights: str, context: str, tile: list[str]) -> DataFrame:
    if d == 1 and context == "wave":
        return _line(rows, order, (lambda k: 1.0 / k) if weights == "1/dist" else (lambda k: 0.5 ** (k - 1)), tile)
    line = Window.partitionBy("level", *tile, *[f"c{i}" for i in range(d) if i != axis]).orderBy(f"c{axis}")
    weigh = (lambda k: 1.0 / k) if weights == "1/dist" else (lambda k: 0.5 ** (k - 1))

    def side(sign):
        terms = [F.coalesce(F.sum("cnt").over(line.rangeBetween(sign * k, sign * k)), F.lit(0)) * weigh(k) for k in range(1, order + 1)]
        return reduce(lambda a, b: a + b, terms)

    if context == "wave":
        return rows.withColumn("nb_left", side(-1)).withColumn("nb_right", side(1))
    at = lambda value, k: F.coalesce(F.sum(value).over(line.rangeBetween(k, k)), F.lit(0)) * 1.0
    near_left, near_right = at(2 * (F.col("cnt") - F.col("left_cnt")), -1), at(2 * F.col("left_cnt"), 1)
    if context == "sequential":
        return rows.withColumn("nb_left", near_left).withColumn("nb_right", side(1))
    odd = F.col(f"c{axis}") % 2 == 1
    return rows.withColumn("nb_left", F.when(odd, near_left).otherwise(side(-1))).withColumn("nb_right", F.when(odd, near_right).otherwise(side(1)))


def _moore(rows: DataFrame, d: int, axis: int) -> DataFrame:
    shifts = [()]
    for i in range(d):
        shifts = [(*s, v) for s in shifts for v in ((-1, 1) if i == axis else (-1, 0, 1))]
    names = [f"c{i}" for i in range(d)]
    # Each cell tells the cells around it: the receiver at c + s sees the sender at offset -s.
    sent = rows.select("level", "cnt", F.explode(F.array(*[F.struct(*[(F.col(n) + v).alias(n) for n, v in zip(names, s, strict=True)], F.lit(s[axis]).alias("s")) for s in shifts])).alias("to"))
    heard = sent.select("level", "cnt", "to.*").groupBy("level", *names).agg(F.sum(F.when(F.col("s") == 1, F.col("cnt")).otherwise(0)).alias("l"), F.sum(F.when(F.col("s") == -1, F.col("cnt")).otherwise(0)).alias("r"))
    return rows.join(heard, ["level", *names], "left").withColumn("nb_left", F.coalesce("l", F.lit(0)) * 1.0).withColumn("nb_right", F.coalesce("r", F.lit(0)) * 1.0)


def predicted_left(left: Column, right: Column, cnt: Column, shrink: float = 0.0) -> Column:
    """Expected lower-half count: the cell's points in proportion to the densities on both sides; null without neighbours."""
    total = left + right + 2 * shrink
    return F.when(left + right > 0, cnt * (left + shrink) / total)


def gaussian_bits(cnt: Column, left_cnt: Column, mu: Column, c: float = 0.5, floor: float = 0.05) -> Column:
    """-log2 P(left) of a discrete Gaussian on 0..p with sigma = c*sqrt(p), mixed with a uniform floor; uniform if mu is null.

    Whole sums for p up to 4096; beyond, an integral times the share of the bell within 0..p (by a logistic curve).
    """
    sigma = F.greatest(F.lit(0.3), c * F.sqrt(cnt.cast("double")))
    weight = lambda k: F.exp(-F.pow((k - mu) / sigma, 2) / 2)
    exact = F.aggregate(F.sequence(F.lit(0).cast("long"), F.least(cnt, F.lit(4096))), F.lit(0.0), lambda acc, k: acc + weight(k))
    inside = 1 / (1 + F.exp(-1.702 * (cnt + 0.5 - mu) / sigma)) - 1 / (1 + F.exp(1.702 * (mu + 0.5) / sigma))
    total = F.when(cnt <= 4096, exact).otherwise(sigma * 2.5066282746310002 * inside)
    p = (1 - floor) * F.least(F.lit(1.0), weight(left_cnt) / total) + floor / (cnt + 1)
    return F.when(mu.isNull(), F.log2(cnt + 1)).otherwise(-F.log2(p))


def predicted_cost(context: DataFrame, c: float = 0.5, shrink: float = 16.0, floor: float = 0.05) -> DataFrame:
    """(level, nodes, uniform_bits, predicted_bits)."""
    mu = predicted_left(F.col("nb_left"), F.col("nb_right"), F.col("cnt"), shrink)
    costed = context.select("level", F.log2(F.col("cnt") + 1).alias("u"), gaussian_bits(F.col("cnt"), F.col("left_cnt"), mu, c, floor).alias("b"))
    return costed.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.round(F.sum("u"), 3).alias("uniform_bits"), F.round(F.sum("b"), 3).alias("predicted_bits"))


GRID = [(0.5, 0.0), (0.5, 4.0), (0.5, 16.0), (1.0, 4.0), (1.0, 16.0)]


def choose_model_per_wave(context: DataFrame, floor: float = 0.05) -> DataFrame:
    """(level, model, bits): the cheapest of uniform (0) and the grid settings (1..) for each wave; Q rows."""
    costs = [F.log2(F.col("cnt") + 1)]
    for c, shrink in GRID:
        costs.append(gaussian_bits(F.col("cnt"), F.col("left_cnt"), predicted_left(F.col("nb_left"), F.col("nb_right"), F.col("cnt"), shrink), c, floor))
    sums = context.groupBy("level").agg(*[F.round(F.sum(x), 3).alias(f"m{k}") for k, x in enumerate(costs)])
    best = F.array_min(F.array(*[F.struct(F.col(f"m{k}").alias("bits"), F.lit(k).alias("model")) for k in range(len(costs))]))
    return sums.select("level", best.alias("best")).select("level", F.col("best.model").alias("model"), F.col("best.bits").alias("bits"))
