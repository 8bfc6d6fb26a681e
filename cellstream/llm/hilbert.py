"""Hilbert-curve ordering of documents into shards of a fixed law, built-in functions only.

Each dimension (language, source, bytes of the text) is quantised to ``bits`` bits at its quantiles: the edges are values of
the column that part the rows evenly, so a bucket is a range of the column's own order and the minimum and maximum of a file tell
a reader whether it can skip it. A value that many rows share falls in one bucket. A cell's place on the Hilbert curve
is looked up in a table of 2**(dims*bits) entries built by rule on the driver. Documents are range-sorted by (curve
place, text checksum, doc_id, size) and the sorted run is cut into shards by global rank. The law is "rows": shard counts differ
by one at most, however many documents share a cell or a text; equal texts of equal metadata lie together.

A null text has no bytes and checksum 0, null metadata falls in bucket 0, equal rows are kept one for one with any order among
them, very long texts count like others, an empty table gives an empty result, and other columns are ignored by ``shards`` and
written along by ``write_shards``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written


def curve_index(point: tuple[int, ...], bits: int) -> int:
    """Place of a lattice point on the Hilbert curve (transpose form with Gray decoding)."""
    x, n = list(point), len(point)
    q = 1 << (bits - 1)
    while q > 1:
        for i in range(n):
            if x[i] & q:
                x[0] ^= q - 1
            else:
                t = (x[0] ^ x[i]) & (q - 1)
                x[0] ^= t
                x[i] ^= t
        q >>= 1
    for i in range(1, n):
        x[i] ^= x[i - 1]
    t, q = 0, 1 << (bits - 1)
    while q > 1:
        if x[n - 1] & q:
            t ^= q - 1
        q >>= 1
    place = 0
    for b in range(bits - 1, -1, -1):
        for v in x:
            place = place << 1 | ((v ^ t) >> b & 1)
    return place


def curve_table(bits: int, dims: int = 3) -> list[int]:
    """Curve place of each cell, cells in row-major order."""
    side = 1 << bits
    cells = [()]
    for _ in range(dims):
        cells = [(*c, v) for c in cells for v in range(side)]
    return [curve_index(c, bits) for c in cells]


def _place(buckets: list[Column], bits: int) -> Column:
    cell = F.lit(0)
    for b in buckets:
        cell = cell * (1 << bits) + b
    # A foldable split of one literal: the planner keeps the table as one constant array.
    table = F.split(F.lit(",".join(map(str, curve_table(bits, len(buckets))))), ",")
    return F.element_at(table, cell.cast("int") + 1).cast("int")


def _offsets(sized: DataFrame) -> DataFrame:
    """(part, base, total) of (part, n): a row a range partition, so bounded by their number."""
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return sized.select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"), F.sum("n").over(whole).alias("total"))


def _part() -> Column:
    """Number of a row's partition: it stands above bit 33 of the generated id."""
    return F.shiftright(F.monotonically_increasing_id(), 33).cast("int")


def quantile_edges(df: DataFrame, column: str, buckets: int) -> list:
    """At most ``buckets - 1`` values, ascending: the smallest value up to which k of ``buckets`` equal shares of the rows lie.

    Distinct values are counted before any exchange, range-sorted, and summed by partition; only the edges reach the driver.
    """
    counts = df.where(F.col(column).isNotNull()).groupBy(F.col(column).alias("v")).agg(F.count(F.lit(1)).alias("n"))
    ranged = written(counts.repartitionByRange("v").sortWithinPartitions("v").select("v", "n", _part().alias("part")), "values")
    offsets = _offsets(ranged.groupBy("part").agg(F.sum("n").alias("n")))
    upto = F.sum("n").over(Window.partitionBy("part").orderBy("v").rowsBetween(Window.unboundedPreceding, 0))
    run = ranged.select("v", "n", "part", upto.alias("u")).join(F.broadcast(offsets), "part").withColumn("upto", F.col("base") + F.col("u"))
    # Value v holds the ends of the shares k with k * total / buckets in (upto - n, upto].
    marks = run.where(f"least({buckets - 1}, upto * {buckets} div total) > (upto - n) * {buckets} div total")
    return [r["v"] for r in marks.orderBy("v").select("v").collect()]


def _bucket(column: Column, edges: list) -> Column:
    """Number of edges below the value: a range of the column's order; null in bucket 0."""
    below = F.lit(0)
    for e in edges:
        below = below + F.coalesce((column > F.lit(e)).cast("int"), F.lit(0))
    return below


def _keyed(docs: DataFrame, dims: tuple[str, ...], *carried: Column) -> DataFrame:
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 1
    crc = F.coalesce(F.crc32(F.col("text").cast("binary")), F.lit(0))
    return docs.select("doc_id", size.alias("size"), crc.alias("text_crc32"), *[F.col(d).alias(f"dim{k}") for k, d in enumerate(dims)], *carried)


ORDER = ["curve", "text_crc32", "doc_id", "size"]


def _curved(keyed: DataFrame, edges: list[list], bits: int) -> DataFrame:
    buckets = [_bucket(F.col("size") if k == len(edges) - 1 else F.col(f"dim{k}"), e) for k, e in enumerate(edges)]
    return keyed.withColumn("curve", _place(buckets, bits)).drop(*[f"dim{k}" for k in range(len(edges) - 1)])


def _ranked(curved: DataFrame, n_shards: int) -> DataFrame:
    """Rows with shard and slot, in partitions that are runs of the curve."""
    row = F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)
    ranked = written(curved.repartitionByRange(*ORDER).sortWithinPartitions(*ORDER).select("*", _part().alias("part"), row.alias("row")), "curve")
    offsets = _offsets(ranked.groupBy("part").agg(F.count(F.lit(1)).alias("n")))
    shard = F.expr(f"(base + row) * {n_shards} div total")
    first = F.expr(f"(shard * total + {n_shards - 1}) div {n_shards}")
    placed = ranked.join(F.broadcast(offsets), "part").withColumn("shard", shard).withColumn("slot", F.col("base") + F.col("row") - first)
    return placed.withColumn("shard", F.col("shard").cast("int")).withColumn("slot", F.col("slot").cast("long"))


def _edges(keyed: DataFrame, dims: tuple[str, ...], bits: int) -> list[list]:
    if not 1 <= bits * (len(dims) + 1) <= 15:
        raise ValueError("the curve table holds 2**(dims*bits) cells, size among the dims; their bits must be 1 to 15 in all")
    return [quantile_edges(keyed, c, 1 << bits) for c in (*[f"dim{k}" for k in range(len(dims))], "size")]


def shards(docs: DataFrame, n_shards: int = 16, bits: int = 4, dims: tuple[str, ...] = ("lang", "source")) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard, curve) for every row."""
    keyed = written(_keyed(docs, dims), "keyed")
    placed = _ranked(_curved(keyed, _edges(keyed, dims, bits), bits), n_shards)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")


def write_shards(docs: DataFrame, path: str, n_shards: int = 16, bits: int = 4, dims: tuple[str, ...] = ("lang", "source"), name: str = "shard") -> None:
    """Write whole rows as one folder a shard (column ``name``), each file a run of the curve for file and row-group pruning.

    Rows travel once, with their own columns under one field, so any of them may have any name but ``name``.
    """
    if name in docs.columns:
        raise ValueError(f"the documents have a column {name}; pass another name for the shard")
    edges = _edges(written(_keyed(docs, dims), "keyed"), dims, bits)
    held = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("held")
    placed = _ranked(_curved(_keyed(docs, dims, held), edges, bits), n_shards)
    placed.select("held.*", F.col("shard").alias(name)).write.partitionBy(name).parquet(path)
