"""Benchmark decontamination: size-partitioned MinHash containment search with built-in functions only.

An item is found in a document if at least ``threshold`` of the item's distinct word shingles are in it. Items are
partitioned by size: items of fewer than ``n`` words by their number of words, each one shingle of all its words, and
the others by the power of two of their number q of shingles. A partition has one signature width, the largest
q - ceil(threshold*q) + 1 of its items; an item's signature is that many of its smallest MinHash values (a bottom-k sketch).
A document that contains ``threshold`` of the q shingles can miss q - ceil(threshold*q) of them at most, so it holds at least
the width less these of the signature: the search loses nothing, for documents of any length. Document shingle hashes
stream against the signatures, pairs with too few signature values are dropped, and exact containment on shingle strings decides.

Words are runs of letters and digits, lower case. Items of fewer than ``n`` words are found wherever their words stand in a
row, alone or in a longer document; items without words match nothing. Null and empty texts match nothing. Repeated rows of one
doc_id or item_id count as one; rows with a null doc_id or item_id match nothing; ties of hashes are settled by the strings; empty
tables give an empty result; other columns are ignored.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import bound, small, written


def _words(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^\\p{L}\\p{N}]+"), lambda w: w != "")


def _windows(words: Column, k, form) -> Column:
    """``form`` of each run of ``k`` words; none if there are fewer."""
    starts = F.when(F.size(words) >= k, F.sequence(F.lit(1), F.size(words) - k + 1)).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda i: form(F.slice(words, i, k)))


def _shingles(text: Column, lengths: list[int], form) -> Column:
    return bound(_words(text), lambda w: F.array_distinct(reduce(F.concat, [_windows(w, F.lit(k), form) for k in lengths])))


def _join(words: Column) -> Column:
    return F.array_join(words, " ")


def contained(docs: DataFrame, items: DataFrame, threshold: float = 0.8, n: int = 5) -> DataFrame:
    """(doc_id, item_id, n_shared, n_item, containment) for every pair at or above the threshold."""
    own = items.where(F.col("item_id").isNotNull()).select("item_id", _words(F.col("text")).alias("w")).where(F.size("w") > 0)
    width = F.least(F.size("w"), F.lit(n))
    cut = own.select("item_id", width.alias("k"), F.explode(bound(F.col("w"), lambda w: _windows(w, F.least(F.size(w), F.lit(n)), _join))).alias("shingle")).distinct()
    parts = written(cut.withColumn("h", F.xxhash64(F.split("shingle", " "))), "items")
    # At most n lengths: those of short items that there are, and n.
    lengths = sorted(r["k"] for r in parts.select("k").distinct().collect()) or [n]
    need = F.ceil(F.lit(threshold) * F.col("q") - 1e-9).cast("long")
    sizes = parts.groupBy("item_id").agg(F.count(F.lit(1)).alias("q"), F.max("k").alias("k")).withColumn("need", need)
    sizes = written(sizes.withColumn("part", F.when(F.col("k") < n, F.col("k")).otherwise(n + F.floor(F.log2("q"))).cast("int")), "sizes")
    widths = sizes.groupBy("part").agg(F.max(F.col("q") - F.col("need") + 1).alias("width"))
    # An item is one short text: its shingles fit a row.
    sketch = parts.groupBy("item_id").agg(F.array_sort(F.collect_set("h")).alias("hs")).join(sizes, "item_id").join(F.broadcast(widths), "part")
    hits_needed = F.greatest(F.lit(1).cast("long"), F.least("width", F.size("hs")) - (F.col("q") - F.col("need")))
    signature = written(sketch.select("item_id", hits_needed.alias("hits"), F.explode(F.slice("hs", F.lit(1), F.col("width").cast("int"))).alias("h")), "signature")
    n_signature, n_parts = signature.count(), parts.count()
    keys = signature.select("h").distinct()
    there = docs.where(F.col("doc_id").isNotNull())
    hits = there.select("doc_id", F.explode(_shingles(F.col("text"), lengths, F.xxhash64)).alias("h")).join(small(keys, n_signature), "h", "left_semi").distinct()
    counted = hits.join(small(signature, n_signature), "h").groupBy("doc_id", "item_id").agg(F.count(F.lit(1)).alias("found"), F.max("hits").alias("hits"))
    pairs = written(counted.where("found >= hits").select("doc_id", "item_id"), "candidates")
    n_pairs = pairs.count()
    texts = there.join(small(pairs.select("doc_id").distinct(), n_pairs), "doc_id", "left_semi")
    exact = texts.select("doc_id", F.explode(_shingles(F.col("text"), lengths, _join)).alias("shingle"))
    shared = exact.join(small(parts.select("item_id", "shingle"), n_parts), "shingle").join(small(pairs, n_pairs), ["doc_id", "item_id"], "left_semi")
    shared = shared.groupBy("doc_id", "item_id").agg(F.countDistinct("shingle").alias("n_shared"))
    found = shared.join(small(sizes, n_parts), "item_id").where("n_shared >= need")
    return found.select("doc_id", "item_id", "n_shared", F.col("q").alias("n_item"), (F.col("n_shared") / F.col("q")).alias("containment"))


def without_leaks(docs: DataFrame, items: DataFrame, threshold: float = 0.8, n: int = 5) -> DataFrame:
    """Documents that contain no item; rows with a null doc_id are kept."""
    leaked = written(contained(docs, items, threshold, n).select("doc_id").distinct(), "leaked")
    return docs.join(small(leaked, leaked.count()), "doc_id", "left_anti").select(*docs.columns)
