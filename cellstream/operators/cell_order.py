"""Split orders chosen cell by cell: the decoder repeats the choice from what it has already read, so no axis is sent."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.keys import key_axis
from ..functions.schedule import SplitSchedule
from .tree import count_tree, leaf_multiset

COST = "level int, nodes long, points long, empty long, bits double"


def tile_level(points: DataFrame, schedule: SplitSchedule, tile_points: int) -> int:
    """The first level whose fullest cell holds ``tile_points`` different points at most; one number a level comes back."""
    axes = [f"a{i}" for i in range(len(schedule.bits))]
    fullest = count_tree(points.select(*axes).distinct(), schedule).groupBy("level").agg(F.max("cnt").alias("n"))
    small = fullest.where(F.col("n") <= tile_points).agg(F.min("level")).first()[0]
    return schedule.q if small is None else small


def waves_of_tile(coords: np.ndarray, m: np.ndarray, bits: tuple[int, ...], used: tuple[int, ...], last: int) -> list[tuple]:
    """(nodes, points, empty, bits) of each wave below a tile's root, all its cells at a time.

    A cell whose parent's split left one half empty is split on that axis again while the axis has bits; any other on the
    next axis in turn. Without bits left it is whole. ``last`` is the axis split before the root, -1 at the top.
    """
    d, n = len(bits), len(m)
    left_bits = np.tile(np.array(bits) - np.array(used), (n, 1))
    before = np.full(n, last)
    again = np.zeros(n, bool)
    cell = np.zeros(n, np.int64)
    rows, out = np.arange(n), []
    for _ in range(int(left_bits[0].sum()) if n else 0):
        axis = np.full(n, -1)
        for turn in range(d, 0, -1):  # the nearest axis in turn is written last
            a = (before + turn) % d
            axis = np.where(left_bits[rows, a] > 0, a, axis)
        stay = again & (left_bits[rows, before] > 0)
        axis = np.where(stay, before, axis)
        left_bits[rows, axis] -= 1
        high = coords[rows, axis] >> left_bits[rows, axis] & 1
        _, where = np.unique(cell, return_inverse=True)
        cnt = np.bincount(where, m).astype(np.int64)
        low = np.bincount(where, m * (1 - high)).astype(np.int64)
        bare = (low == 0) | (low == cnt)
        out.append((len(cnt), int(cnt.sum()), int(bare.sum()), float(np.log2(cnt + 1.0).sum())))
        again, before = bare[where], axis
        cell = where * 2 + high
    return out


def cell_order_cost(points: DataFrame, schedule: SplitSchedule, tile_points: int = 1 << 18) -> DataFrame:
    """(level, nodes, points, empty, bits) when each cell below the tiles picks its own axis.

    Waves above the tiles follow ``schedule`` (round robin). Tiles are cells of the level at which the fullest has at most
    ``tile_points`` different points, so a task's memory is bounded whatever the skew; coinciding points are one row.
    """
    t = tile_level(points, schedule, tile_points)
    bits, q, used = schedule.bits, schedule.q, schedule.used(t)
    last = schedule.steps[t - 1][0] if t else -1
    leaf = leaf_multiset(points, schedule).select(F.expr(f"shiftright(key, {q - t})").alias("tile"), *[key_axis(schedule, i, F.col("key")).alias(f"a{i}") for i in range(len(bits))], "m")

    def waves(pdf: pd.DataFrame) -> pd.DataFrame:
        coords = pdf[[f"a{i}" for i in range(len(bits))]].to_numpy(np.int64)
        costs = waves_of_tile(coords, pdf["m"].to_numpy(np.int64), bits, used, last)
        return pd.DataFrame([(t + k, *c) for k, c in enumerate(costs)], columns=["level", "nodes", "points", "empty", "bits"])

    below = leaf.groupBy("tile").applyInPandas(waves, COST)
    none = (F.col("left_cnt") == 0).cast("long") + (F.col("left_cnt") == F.col("cnt")).cast("long")
    top = count_tree(points, schedule).where(F.col("level") < t).select("level", F.lit(1).cast("long").alias("nodes"), F.col("cnt").alias("points"), none.alias("empty"), F.log2(F.col("cnt") + 1).alias("bits"))
    both = top.unionByName(below).groupBy("level").agg(F.sum("nodes").alias("nodes"), F.sum("points").alias("points"), F.sum("empty").alias("empty"), F.sum("bits").alias("bits"))
    return both.withColumn("bits", F.round("bits", 3))
