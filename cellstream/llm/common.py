"""Helpers shared by the training-data operators: shared intermediate tables, text columns, cached encoding."""

from __future__ import annotations

import os
import re
import struct
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def tokenizer_path(name: str) -> str:
    """Place of a public vocabulary file; callers may pass any other path instead."""
    import public_tokenizers

    return public_tokenizers.path(name)


#: Rows of a side that may be broadcast; beyond it a join shuffles.
BROADCAST_ROWS = 200_000


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share (spark.checkpoint.dir). Where it is unset, a temporary one is set if everything
    runs on this machine, and an error raised on a cluster, whose executors would not see it."""
    place = spark.conf.get("spark.checkpoint.dir", None)
    if not place:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        place = "file://" + tempfile.mkdtemp(prefix="cellstream-")
        spark.conf.set("spark.checkpoint.dir", place)
    return place.rstrip("/")


def small(df: DataFrame, rows: int) -> DataFrame:
    """``df`` marked for broadcast if its counted ``rows`` allow that."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def written(df: DataFrame, label: str, partition_by: str | None = None) -> DataFrame:
    """Cut lineage: write ``df`` as Parquet in the shared folder and read it back.

    The table stays until the folder is emptied or ``dropped`` is called: results are lazy and may read it later."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def dropped(df: DataFrame) -> None:
    """Delete the files of a ``written`` table that nothing reads any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    folders = {f.rsplit("/", 1)[0] for f in df.inputFiles()}
    for folder in folders:
        place = jvm.org.apache.hadoop.fs.Path(folder)
        place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def bound(value: Column, body) -> Column:
    """``body(x)`` with ``x`` evaluated once per row, however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def text_bytes(docs: DataFrame) -> DataFrame:
    """(doc_id, raw): the whole text as UTF-8 bytes, null as empty; other columns are ignored."""
    return docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("raw"))


# Unicode white space outside ASCII (fixed values of the White_Space property).
_WIDE_SPACE = "\u0085\u00a0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"


def _packed(ids: list[int]) -> bytes:
    """Little-endian unsigned 32-bit numbers; for a few at a time, where numpy's calls cost more than the numbers."""
    return struct.pack(f"<{len(ids)}I", *ids)


class PieceEncoder:
    """Exact token ids of whole texts, from a bounded two-generation cache of white-space delimited pieces.

    A boundary from non-space to ASCII space, or from an ASCII letter to ASCII punctuation but the apostrophe, is always a
    pre-token boundary of both vocabularies, so a text's ids are those of its pieces put together. A piece that ends with wide white space may share a run of white space
    with its follower; a text with such a piece goes to the library whole. ``keep_space`` keeps each piece's
    leading white space (byte-level vocabulary); without it white space is dropped.
    """

    def __init__(self, path: str, keep_space: bool, capacity: int = 500_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self._library = Tokenizer.from_file(path)
        lead = "[\\t-\\r ]*+" if keep_space else ""
        rest = "|[\\t-\\r ]++" if keep_space else ""
        word = r"[A-Za-z\x80-\xff]++(?<=[A-Za-z])(?=[!-&(-/:-@\[-`{-~])"
        self._cut = re.compile(f"{lead}(?:{word}|[^\\t-\\r ]++){rest}".encode("latin-1")).findall
        self._keep_space, self._capacity = keep_space, capacity
        self._young: dict[bytes, object] = {}
        self._old: dict[bytes, object] = {}

    def library_ids(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self._library.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, pieces: set[bytes]) -> dict[bytes, object]:
        fresh, found = [], {}
        for p in pieces:
            value = self._old.get(p)
            if value is None:
                fresh.append(p)
            else:
                found[p] = value
        texts = [p.decode("utf-8", "replace") for p in fresh]
        for p, text, ids in zip(fresh, texts, self.library_ids(texts), strict=True):
            unsafe = self._keep_space and text[-1] in _WIDE_SPACE
            found[p] = False if unsafe else _packed(ids)
        self._young.update((p, v) for p, v in found.items() if len(p) <= 64)
        if len(self._young) > self._capacity:
            self._old, self._young = self._young, {}
        return found

    def encode(self, raw: bytes) -> bytes:
        """Little-endian unsigned 32-bit ids of one text."""
        if not self._keep_space and raw.isascii() and b"<|" not in raw:
            raw = raw.lower()  # as the vocabulary's normalizer does; other texts may compose letters before
        pieces = self._cut(raw)
        values = list(map(self._young.get, pieces))
        if None in values:
            found = self._learn({p for p, v in zip(pieces, values, strict=True) if v is None})
            values = [found[p] if v is None else v for p, v in zip(pieces, values, strict=True)]
        if False in values:
            import numpy as np

            return np.asarray(self.library_ids([raw.decode("utf-8", "replace")])[0], "<u4").tobytes()
        return b"".join(values)


_ENCODERS: dict[tuple, PieceEncoder] = {}


def encoder(path: str, keep_space: bool, capacity: int = 500_000) -> PieceEncoder:
    """One encoder for each vocabulary and Python worker; ``capacity`` bounds each generation of its cache."""
    key = (path, keep_space, capacity)
    if key not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[key] = PieceEncoder(path, keep_space, capacity)
    return _ENCODERS[key]


def forgotten() -> None:
    """Drop the encoders that an earlier job left in this Python worker. Workers serve one job after another, and those caches would
    stand beside what this one holds."""
    _ENCODERS.clear()
