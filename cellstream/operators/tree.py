"""The count tree: a row per non-empty divisible cell with its points and those in its lower half.

Three physical paths give the same rows. ``explode`` lists the cells of each distinct key and aggregates them, with partial
sums before its one exchange, so heavy cells do not skew it. ``cascade`` folds level l + 1 into level l behind one exchange, for sets
whose keys spread evenly over their first bits (a subtree is one task). ``sweep`` is the path for very large inputs: keys are
range-partitioned (by sampled bounds, so evenly), each Arrow batch of sorted keys gives its inner cells at once, and only the
cells that cross a batch border, at most two a level and batch, meet in an aggregate.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.keys import cell_axis, cell_key, wide_key
from ..functions.schedule import SplitSchedule

NODE = "level int, prefix long, cnt long, left_cnt long"


def leaf_multiset(points: DataFrame, schedule: SplitSchedule) -> DataFrame:
    """(key, m): coinciding points as one row; m sums a column m where there is one."""
    weight = F.sum("m") if "m" in points.columns else F.count(F.lit(1))
    return points.groupBy(cell_key(schedule).alias("key")).agg(weight.cast("long").alias("m"))


def count_tree(points: DataFrame, schedule: SplitSchedule, path: str = "explode") -> DataFrame:
    """(level, prefix, cnt, left_cnt) for levels 0 to Q - 1."""
    leaves = leaf_multiset(points, schedule)
    return {"explode": _explode, "cascade": _cascade, "sweep": _sweep}[path](leaves, schedule)


def _cells(q: int, key, level):
    """Prefix at a level, and whether the next bit is 0."""
    shift = (F.lit(q) - level).cast("int")
    prefix = F.call_function("shiftright", key, shift)
    low = F.call_function("shiftright", key, (shift - 1).cast("int")).bitwiseAND(F.lit(1).cast("long")) == 0
    return prefix, low


def _explode(leaves: DataFrame, schedule: SplitSchedule) -> DataFrame:
    if not schedule.q:
        return leaves.sparkSession.createDataFrame([], NODE)
    rows = leaves.select("key", "m", F.explode(F.sequence(F.lit(0), F.lit(schedule.q - 1))).alias("level"))
    prefix, low = _cells(schedule.q, F.col("key"), F.col("level"))
    return rows.groupBy("level", prefix.alias("prefix")).agg(F.sum("m").alias("cnt"), F.sum(F.when(low, F.col("m")).otherwise(0)).alias("left_cnt"))


def _cascade(leaves: DataFrame, schedule: SplitSchedule, local: int = 12) -> DataFrame:
    """Folds level l + 1 into level l. Cells deeper than ``local`` meet in one exchange by their prefix of ``local`` bits and
    are folded there; the levels above are folds of the at most 2**local cells that come out."""
    q = schedule.q
    if not q:
        return leaves.sparkSession.createDataFrame([], NODE)
    top = min(local, q)

    def fold(table: pa.Table) -> pa.Table:
        prefix, m = table.column("key").to_numpy(), table.column("m").to_numpy()
        order = np.argsort(prefix, kind="stable")
        prefix, m = prefix[order], m[order]
        out = []
        for level in range(q - 1, top - 1, -1):
            starts = np.flatnonzero(np.concatenate([[True], prefix[1:] >> 1 != prefix[:-1] >> 1]))
            low = np.where(prefix & 1, 0, m)
            out.append((np.full(len(starts), level, np.int32), prefix[starts] >> 1, np.add.reduceat(m, starts), np.add.reduceat(low, starts)))
            prefix, m = out[-1][1], out[-1][2]
        # The cell itself, as a leaf of the levels above.
        out.append((np.full(len(prefix), q, np.int32), prefix, m, np.zeros(len(m), np.int64)))
        return pa.table(dict(zip(("level", "prefix", "cnt", "left_cnt"), map(np.concatenate, zip(*out, strict=True)), strict=True)))

    own = F.shiftright("key", q - top)
    deep = leaves.withColumn("own", own).groupBy("own").applyInArrow(fold, NODE)
    # At most 2**local rows, exploded over fewer than ``local`` levels.
    cells = deep.where(F.col("level") == q).select("prefix", "cnt", F.explode(F.sequence(F.lit(0), F.lit(top - 1))).alias("level"))
    prefix, low = _cells(top, F.col("prefix"), F.col("level"))
    upper = cells.groupBy("level", prefix.alias("prefix")).agg(F.sum("cnt").alias("cnt"), F.sum(F.when(low, F.col("cnt")).otherwise(0)).alias("left_cnt"))
    return deep.where(F.col("level") < q).unionByName(upper)


def _sweep(leaves: DataFrame, schedule: SplitSchedule) -> DataFrame:
    q = schedule.q

    def sweep(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            key, m = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            levels, prefixes, counts, lefts, border = [], [], [], [], []
            for level in range(q):
                prefix = key >> (q - level)
                starts = np.flatnonzero(np.concatenate([[True], prefix[1:] != prefix[:-1]]))
                low = np.where(key >> (q - level - 1) & 1, 0, m)
                edge = np.zeros(len(starts), bool)
                edge[[0, -1]] = True
                levels.append(np.full(len(starts), level, np.int32))
                prefixes.append(prefix[starts])
                counts.append(np.add.reduceat(m, starts))
                lefts.append(np.add.reduceat(low, starts))
                border.append(edge)
            arrays = [pa.array(np.concatenate(x)) for x in (levels, prefixes, counts, lefts, border)]
            yield pa.RecordBatch.from_arrays(arrays, ["level", "prefix", "cnt", "left_cnt", "border"])

    if not q:
        return leaves.sparkSession.createDataFrame([], NODE)
    from ..sources.shared import written

    # Written, since both parts below read it.
    swept = written(leaves.repartitionByRange("key").sortWithinPartitions("key").select("key", "m").mapInArrow(sweep, NODE + ", border boolean"), "sweep")
    inner = swept.where("not border").select("level", "prefix", "cnt", "left_cnt")
    met = swept.where("border").groupBy("level", "prefix").agg(F.sum("cnt").alias("cnt"), F.sum("left_cnt").alias("left_cnt"))
    return inner.unionByName(met)


SUMS = "level int, nodes long, cnt long, b double, ib long"


def level_sums(points: DataFrame, schedule: SplitSchedule) -> DataFrame:
    """Rows (level, nodes, cnt, b, ib) to be summed by level: nodes, points, ideal and integer bits of the count tree.

    The sweep of ``_sweep``, whose inner cells are summed where they are found: a batch gives a row a level and its border
    cells, and only these meet in an aggregate.
    """
    q = schedule.q
    if not q:
        return points.sparkSession.createDataFrame([], SUMS)

    def sweep(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            key, m = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            out = []
            for level in range(q):
                prefix = key >> (q - level)
                starts = np.flatnonzero(np.concatenate([[True], prefix[1:] != prefix[:-1]]))
                cnt = np.add.reduceat(m, starts)
                inner = cnt[1:-1]
                out.append((level, None, len(inner), int(inner.sum()), float(np.log2(inner + 1.0).sum()), int(np.frexp(inner.astype(np.float64))[1].sum())))
                for k in {0, len(starts) - 1}:
                    out.append((level, int(prefix[starts[k]]), 1, int(cnt[k]), 0.0, 0))
            names, kinds = ("level", "prefix", "nodes", "cnt", "b", "ib"), (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(map(list, zip(*out, strict=True)), kinds, strict=True)], list(names))

    from ..sources.shared import written

    # Leaves are written, since the bounds of the ranges are sampled from them; sums, since both parts below read them.
    leaves = written(leaf_multiset(points, schedule), "leaves")
    swept = written(leaves.repartitionByRange("key").sortWithinPartitions("key").select("key", "m").mapInArrow(sweep, SUMS.replace("nodes", "prefix long, nodes")), "sums")
    met = swept.where("prefix is not null").groupBy("level", "prefix").agg(F.sum("cnt").alias("cnt"))
    border = met.select("level", F.lit(1).cast("long").alias("nodes"), "cnt", F.log2(F.col("cnt") + 1).alias("b"), F.length(F.bin("cnt")).cast("long").alias("ib"))
    return swept.where("prefix is null").drop("prefix").unionByName(border)


def wide_tree(points: DataFrame, schedule: SplitSchedule) -> DataFrame:
    """(level, prefix ARRAY<BIGINT>, cnt, left_cnt) for keys of any width: whole words, then the open word's high bits."""
    word = 60
    keyed = points.groupBy(wide_key(schedule).alias("key")).agg(F.count(F.lit(1)).alias("m"))
    widths = [min(word, schedule.q - f) for f in range(0, schedule.q, word)]
    rows = keyed.select("key", "m", F.explode(F.sequence(F.lit(0), F.lit(schedule.q - 1))).alias("level"))
    at = F.floor(F.col("level") / word).cast("int")
    width = F.element_at(F.array(*[F.lit(w) for w in widths]), at + 1)
    open_word = F.element_at("key", at + 1)
    shift = (width - F.pmod(F.col("level"), F.lit(word))).cast("int")
    prefix = F.concat(F.slice("key", F.lit(1), at), F.array(F.call_function("shiftright", open_word, shift)))
    low = F.call_function("shiftright", open_word, shift - 1).bitwiseAND(F.lit(1).cast("long")) == 0
    return rows.groupBy("level", prefix.alias("prefix")).agg(F.sum("m").alias("cnt"), F.sum(F.when(low, F.col("m")).otherwise(0)).alias("left_cnt"))


def merge_trees(*trees: DataFrame) -> DataFrame:
    """Tree of the union of point sets: counts add cell by cell."""
    both = trees[0]
    for t in trees[1:]:
        both = both.unionByName(t)
    return both.groupBy("level", "prefix").agg(F.sum("cnt").alias("cnt"), F.sum("left_cnt").alias("left_cnt"))


def with_coordinates(cells: DataFrame, schedule: SplitSchedule) -> DataFrame:
    """Cell coordinates c0.. in place of the prefix."""
    axes = [cell_axis(schedule, i, F.col("level"), F.col("prefix")).alias(f"c{i}") for i in range(len(schedule.bits))]
    return cells.select("level", *axes, *[c for c in cells.columns if c not in ("level", "prefix")])


def cells_at(points: DataFrame, schedule: SplitSchedule, level: int) -> DataFrame:
    """(level, prefix, cnt): occupied cells of one level."""
    prefix = F.shiftright("key", schedule.q - level) if level < schedule.q else F.col("key")
    return leaf_multiset(points, schedule).groupBy(prefix.alias("prefix")).agg(F.sum("m").alias("cnt")).select(F.lit(level).alias("level"), "prefix", "cnt")


def symbol_stream(nodes: DataFrame, q: int, order: str = "breadth") -> DataFrame:
    """(ord, level, prefix, cnt, left_cnt) in coding order, numbered from 1 without a global window.

    Rows are range-sorted; a partition's rows are numbered by place, and partitions by their sizes (a row each).
    """
    head = F.call_function("shiftleft", F.col("prefix"), (F.lit(q) - F.col("level")).cast("int"))
    by = ["level", "prefix"] if order == "breadth" else [head, F.col("level")]
    row = F.monotonically_increasing_id()
    from ..sources.shared import written

    # Written, since both parts below read it: run twice, its rows may be dealt to other partitions and its numbers not meet.
    placed = written(nodes.repartitionByRange(*by).sortWithinPartitions(*by).select("level", "prefix", "cnt", "left_cnt", F.shiftright(row, 33).alias("part"), row.bitwiseAND((1 << 33) - 1).alias("row")), "placed")
    sizes = placed.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    from pyspark.sql import Window

    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = sizes.select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    return placed.join(F.broadcast(bases), "part").select((F.col("base") + F.col("row") + 1).alias("ord"), "level", "prefix", "cnt", "left_cnt")
