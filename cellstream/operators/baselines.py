"""Baselines: raw, Huffman, strip-order linear prediction, growing polygon with crease, differential variable-length code.

The strip and polygon codecs are proxies on grid meshes and point orders: coordinates only, connectivity not counted.
"""

from __future__ import annotations

import heapq
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def entropy(residuals: DataFrame, column: str) -> DataFrame:
    """(n, distinct, bits): zero-order entropy cost of a column of whole numbers."""
    hist = residuals.groupBy(F.col(column).alias("v")).agg(F.count(F.lit(1)).alias("c"))
    total = hist.agg(F.sum("c").alias("n"))
    cost = hist.join(F.broadcast(total)).agg(F.max("n").alias("n"), F.count(F.lit(1)).alias("distinct"), F.round(F.sum(F.col("c") * F.log2(F.col("n") / F.col("c"))), 3).alias("bits"))
    return cost


def strip_linear(points: DataFrame, strip: str, order: str, axes: list[str], weights: list[float]) -> DataFrame:
    """Residuals r_<axis> against a weighted sum of the axis' last values in the strip, earliest points in full."""
    line = Window.partitionBy(strip).orderBy(order)
    out = points
    for a in axes:
        guess = F.lit(0.0)
        for k, w in enumerate(weights, 1):
            guess = guess + w * F.coalesce(F.lag(a, k).over(line), F.lit(0))
        out = out.withColumn(f"r_{a}", (F.col(a) - F.round(guess)).cast("long"))
    return out


def parallelogram(grid: DataFrame, i: str, j: str, z: str) -> DataFrame:
    """Residual of z against the parallelogram of the three earlier corners (two windows over rows and columns)."""
    row, col = Window.partitionBy(i).orderBy(j), Window.partitionBy(j).orderBy(i)
    step = grid.withColumn("up", F.lag(z).over(col)).withColumn("left", F.lag(z).over(row))
    step = step.withColumn("corner", F.lag("up").over(row))
    guess = F.when(F.col("corner").isNotNull(), F.col("up") + F.col("left") - F.col("corner")).otherwise(F.coalesce(F.col("left"), F.col("up"), F.lit(0)))
    return step.withColumn("r", (F.col(z) - guess).cast("long")).drop("up", "left", "corner")


def crease(grid: DataFrame, i: str, j: str, z: str, reach: int = 4) -> DataFrame:
    """Parallelogram residual corrected by the mean of the last residuals in its row."""
    row = Window.partitionBy(i).orderBy(j).rowsBetween(-reach, -1)
    seen = parallelogram(grid, i, j, z)
    return seen.withColumn("r2", (F.col("r") - F.round(F.coalesce(F.avg("r").over(row), F.lit(0.0)))).cast("long"))


def gamma_bits(delta: Column) -> Column:
    """Elias gamma length of a zig-zag coded whole number."""
    zig = F.when(delta < 0, -2 * delta - 1).otherwise(2 * delta) + 1
    return 2 * F.length(F.bin(zig)) - 1


def ordered_lags(rows: DataFrame, by: list[str], values: list[str], most: int = 1) -> DataFrame:
    """Rows with lag_<k>_<value> of the k-th row before in the order of ``by``, over the whole set and without one window for it.

    Rows are range-sorted and look back within their partition; the last ``most`` rows of each partition (so a bounded number a partition)
    serve the first ones of the next. Equal rows may stand in any order.
    """
    from ..sources.shared import written

    number = F.monotonically_increasing_id()
    placed = written(rows.repartitionByRange(*by).sortWithinPartitions(*by).select("*", F.shiftright(number, 33).alias("part"), number.bitwiseAND((1 << 33) - 1).alias("place")), "ordered")
    line = Window.partitionBy("part").orderBy("place")
    out = placed.select("*", *[F.lag(v, k).over(line).alias(f"lag_{k}_{v}") for k in range(1, most + 1) for v in values])
    sizes = placed.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    # The rows before a partition's first: at most ``most`` from each earlier one, numbered backwards over all of them.
    tails = placed.join(F.broadcast(sizes), "part").where(F.col("place") >= F.col("n") - most).select("part", "place", *values)
    back = Window.partitionBy("to").orderBy(F.desc("part"), F.desc("place"))
    heads = sizes.select(F.col("part").alias("to")).join(F.broadcast(tails), F.col("part") < F.col("to")).withColumn("k", F.row_number().over(back)).where(F.col("k") <= most)
    held = heads.groupBy("to").agg(*[F.max(F.when(F.col("k") == k, F.col(v))).alias(f"head_{k}_{v}") for k in range(1, most + 1) for v in values])
    out = out.join(F.broadcast(held), F.col("part") == F.col("to"), "left")
    for k in range(1, most + 1):
        for v in values:
            # The k-th row before a row at ``place`` is the (k - place)-th of those before the partition.
            before = F.coalesce(*[F.when(F.col("place") == k - j, F.col(f"head_{j}_{v}")) for j in range(1, k + 1)])
            out = out.withColumn(f"lag_{k}_{v}", F.coalesce(f"lag_{k}_{v}", before))
    return out.drop("part", "place", "to", *[f"head_{k}_{v}" for k in range(1, most + 1) for v in values])


def delta_varlen(keyed: DataFrame, key: str, axes: list[str], tile_shift: int) -> DataFrame:
    """(n, bits): deltas along a space-filling order within tiles of the key; a tile's first point pays from zero."""
    rows = ordered_lags(keyed.select(key, *axes), [key, *axes], [key, *axes])
    same = F.shiftright(f"lag_1_{key}", tile_shift) == F.shiftright(key, tile_shift)
    costs = [gamma_bits(F.col(a) - F.when(same, F.col(f"lag_1_{a}")).otherwise(0)) for a in axes]
    return rows.agg(F.count(F.lit(1)).alias("n"), F.sum(reduce(lambda x, y: x + y, costs)).cast("long").alias("bits"))


#: Weights of the last values in the linear predictions of the object table.
STRIP, POLYGON = [2.0, -1.0], [1.0, 1.0, -1.0]


def object_residuals(keyed: DataFrame, group: str, key: str, axes: list[str], tile_shift: int, reach: int = 4) -> DataFrame:
    """(group, gamma, strip_<axis>, polygon_<axis>, crease_<axis>): cost of the differential code of each point, and residuals of
    proxies of the two published codecs on a point order, for several sets (``group``) at once.

    strip: linear from two values before; polygon: from three, as a parallelogram; crease: that less the rounded mean of the last
    ``reach`` polygon residuals of the tile. Values of another set or tile count as nothing.
    """
    most = len(POLYGON) + reach
    rows = ordered_lags(keyed.select(group, key, *axes), [group, key, *axes], [group, key, *axes], most)
    near = [F.coalesce((F.col(f"lag_{k}_{group}") == F.col(group)) & (F.shiftright(f"lag_{k}_{key}", tile_shift) == F.shiftright(key, tile_shift)), F.lit(False)) for k in range(1, most + 1)]
    # One array an axis: the value, then those before it while they are of the tile.
    rows = rows.select(group, *[F.array(F.col(a).cast("double"), *[F.when(n, F.col(f"lag_{k}_{a}").cast("double")) for k, n in enumerate(near, 1)]).alias(a) for a in axes])

    def residual(values, k, weights):
        guess = reduce(lambda x, y: x + y, [w * F.coalesce(values[k + j], F.lit(0.0)) for j, w in enumerate(weights, 1)])
        return values[k] - F.round(guess)

    out, gamma = [], []
    for a in axes:
        v = F.col(a)
        before = F.filter(F.array(*[residual(v, k, POLYGON) for k in range(1, reach + 1)]), lambda x: x.isNotNull())
        mean = F.aggregate(before, F.lit(0.0), lambda x, y: x + y) / F.greatest(F.size(before), F.lit(1))
        own = residual(v, 0, POLYGON)
        gamma.append(gamma_bits((v[0] - F.coalesce(v[1], F.lit(0.0))).cast("long")))
        out += [residual(v, 0, STRIP).cast("long").alias(f"strip_{a}"), own.cast("long").alias(f"polygon_{a}"), (own - F.round(mean)).cast("long").alias(f"crease_{a}")]
    return rows.select(group, reduce(lambda x, y: x + y, gamma).cast("long").alias("gamma"), *out)


def file_bytes(df: DataFrame, codec: str) -> int:
    """Bytes of the table as Parquet under a general-purpose codec."""
    from ..sources.shared import fresh

    spark = df.sparkSession
    place = fresh(spark, f"bytes-{codec}")
    df.write.option("compression", codec).parquet(place)
    return spark.read.format("binaryFile").option("pathGlobFilter", "*.parquet").load(place).agg(F.coalesce(F.sum("length"), F.lit(0))).first()[0]


def huffman_lengths(counts: list[int]) -> list[int]:
    """Code lengths of an optimal prefix code (one symbol: no bits)."""
    if len(counts) < 2:
        return [0] * len(counts)
    heap = [(c, k) for k, c in enumerate(counts)]
    heapq.heapify(heap)
    above = [0] * (2 * len(counts) - 1)
    for serial in range(len(counts), 2 * len(counts) - 1):
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        above[a[1]] = above[b[1]] = serial
        heapq.heappush(heap, (a[0] + b[0], serial))
    depth = [0] * len(above)
    for k in range(len(above) - 2, -1, -1):  # a node's parent has a higher number
        depth[k] = depth[above[k]] + 1
    return depth[: len(counts)]


def huffman(nodes: DataFrame) -> DataFrame:
    """(cnt, n, bits): a Huffman code of left given p for each p; a group is one histogram, never rows of the tree."""
    hist = nodes.groupBy("cnt", "left_cnt").agg(F.count(F.lit(1)).alias("n"))

    def cost(pdf):
        import pandas as pd

        lengths = huffman_lengths(pdf["n"].tolist())
        return pd.DataFrame({"cnt": [int(pdf["cnt"].iloc[0])], "n": [int(pdf["n"].sum())], "bits": [int(sum(a * b for a, b in zip(lengths, pdf["n"], strict=True)))]})

    return hist.groupBy("cnt").applyInPandas(cost, "cnt long, n long, bits long")
