"""Code lengths of count trees under several models, and the measures built on them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def uniform_bits(cnt: Column) -> Column:
    """log2(p + 1): any lower-half count is as likely."""
    return F.log2(cnt + 1)


def integer_bits(cnt: Column) -> Column:
    """Whole bits for a count in 0..p."""
    return F.length(F.bin(cnt)).cast("long")


def code_length(nodes: DataFrame, model: str = "uniform") -> DataFrame:
    """(level, nodes, points, bits) per wave."""
    if model == "empirical":
        return empirical(nodes)
    bits = uniform_bits(F.col("cnt")) if model == "uniform" else integer_bits(F.col("cnt")).cast("double")
    return nodes.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.sum("cnt").alias("points"), F.round(F.sum(bits), 3).alias("bits"))


def empirical(nodes: DataFrame) -> DataFrame:
    """Zero-order cost of left given p from the measured histogram, per wave."""
    pairs = nodes.groupBy("level", "cnt", "left_cnt").agg(F.count(F.lit(1)).alias("n"))
    by_pair = pairs.groupBy("cnt", "left_cnt").agg(F.sum("n").alias("n_pair"))
    by_p = pairs.groupBy("cnt").agg(F.sum("n").alias("n_p"))
    cost = pairs.join(by_pair, ["cnt", "left_cnt"]).join(by_p, "cnt").withColumn("bits", F.col("n") * F.log2(F.col("n_p") / F.col("n_pair")))
    return cost.groupBy("level").agg(F.sum("n").alias("nodes"), F.sum(F.col("n") * F.col("cnt")).alias("points"), F.round(F.sum("bits"), 3).alias("bits"))


def phase_costs(nodes: DataFrame) -> DataFrame:
    """Separation (two points or more) and final localisation (one point)."""
    phase = F.when(F.col("cnt") > 1, "separation").otherwise("localisation")
    return nodes.groupBy(phase.alias("phase")).agg(F.count(F.lit(1)).alias("nodes"), F.round(F.sum(uniform_bits(F.col("cnt"))), 3).alias("bits"))


def rate_curve(nodes: DataFrame, schedule) -> DataFrame:
    """(level, precision, bits_level, bits_cum, cf): cost to reach the end of each wave. At most Q rows meet in the window."""
    per = nodes.groupBy("level").agg(F.sum(uniform_bits(F.col("cnt"))).alias("b"), F.sum("cnt").alias("n"))
    run = Window.orderBy("level").rowsBetween(Window.unboundedPreceding, 0)
    rounds = F.element_at(F.array(*[F.lit(schedule.round_of(lv + 1)) for lv in range(schedule.q)]), F.col("level") + 1)
    total = F.sum("b").over(run)
    return per.select("level", rounds.alias("precision"), F.round("b", 3).alias("bits_level"), F.round(total, 3).alias("bits_cum"), F.round(F.col("n") * schedule.q / total, 4).alias("cf"))


def summary(nodes: DataFrame, q: int) -> DataFrame:
    """One row: n, source bytes, ideal and integer bits, bits per point, factor, theoretical factor, redundancy inputs."""
    row = nodes.agg(
        F.max(F.when(F.col("level") == 0, F.col("cnt"))).alias("n"), F.count(F.lit(1)).alias("nodes"), F.sum("cnt").alias("touches"),
        F.sum(uniform_bits(F.col("cnt"))).alias("b"), F.sum(integer_bits(F.col("cnt"))).alias("integer_bits"),
    )
    return _measures(row, q)


def summary_of(points: DataFrame, schedule) -> DataFrame:
    """``summary`` of a point set whose tree is summed where it is swept, without a row a node."""
    from .tree import level_sums

    row = level_sums(points, schedule).agg(
        F.sum(F.when(F.col("level") == 0, F.col("cnt"))).alias("n"), F.sum("nodes").alias("nodes"), F.sum("cnt").alias("touches"), F.sum("b").alias("b"), F.sum("ib").alias("integer_bits"),
    )
    return _measures(row, schedule.q)


def _measures(row: DataFrame, q: int) -> DataFrame:
    n = F.col("n")
    return row.select(
        "n", F.ceil(n * q / 8.0).cast("long").alias("source_bytes"), F.ceil(F.round(F.col("b"), 3) / 8).cast("long").alias("ideal_bytes"), F.round("b", 3).alias("ideal_bits"), "integer_bits",
        F.round(F.col("b") / n, 4).alias("bpv"), F.round(n * q / F.col("b"), 4).alias("cf"), F.round(q / (q - F.log2(n) + 2.402), 4).alias("theor_cf"),
        F.round(F.log2(n) - 2.402, 4).alias("theor_gain"), F.round(q - F.col("b") / n, 4).alias("gain"), F.round(q - F.col("integer_bits") / n, 4).alias("integer_gain"),
        F.round(n * F.log2(n), 3).alias("order_bits"), "nodes", "touches", F.round(n * (q - F.log2(n) + 1), 3).alias("decoder_estimate"), (n * (q + 4)).alias("space_units"), F.round(q / F.log2(n), 4).alias("q_ratio"),
    )


def wave_bounds(nodes: DataFrame) -> DataFrame:
    """(level, bits, bound, holds): the worst case of each wave for any multiset."""
    per = nodes.groupBy("level").agg(F.sum(uniform_bits(F.col("cnt"))).alias("b"), F.sum("cnt").alias("n"))
    bound = F.least(F.col("n").cast("double"), F.pow(F.lit(2.0), F.col("level")) * F.log2(1 + F.col("n") / F.pow(F.lit(2.0), F.col("level"))))
    return per.select("level", F.round("b", 3).alias("bits"), F.round(bound, 3).alias("bound"), (F.col("b") <= bound + 1e-6).alias("holds"))


def empty_cells(nodes: DataFrame) -> DataFrame:
    """(level, empty): halves without points made by each wave."""
    none = (F.col("left_cnt") == 0).cast("long") + (F.col("left_cnt") == F.col("cnt")).cast("long")
    return nodes.groupBy("level").agg(F.sum(none).alias("empty"), F.count(F.lit(1)).alias("nodes"))
