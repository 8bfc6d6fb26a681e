"""Token-id files of bit or byte planes.

A segment holds whole documents. Its ids are cut into blocks of a fixed number; each block is transposed into planes
(bit k, or byte k, of every id), empty planes are dropped, and each plane is compressed with zstandard. A chunk index at
the segment's head gives each block's place, its number of ids and the planes it stores. The document table (doc_id
and number of ids) is part of the segment, so a segment is read alone.

Layout of a segment, all numbers little-endian: magic "CSBP1\\0", plane width in bits (u16: 1 or 8), n_docs, n_ids, ids
per block, n_blocks (u64 each); compressed size of the document table (u64); the chunk index, n_blocks rows of
(offset u64, n_ids u32, plane mask u32); per stored plane its compressed size (u32); the document table; the planes.
Segments are the rows of a Parquet table, so a lost task is written again under Spark's commit protocol.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import encoder, text_bytes, written

MAGIC = b"CSBP1\0"
_HEAD = struct.Struct("<6sHQQQQQ")
_INDEX = np.dtype([("offset", "<u8"), ("n", "<u4"), ("mask", "<u4")])


def to_planes(ids: np.ndarray, width: int) -> list[bytes]:
    """Planes of one block, lowest first: 32 bit planes or 4 byte planes."""
    lanes = ids.astype("<u4").view(np.uint8).reshape(-1, 4)
    if width == 8:
        return [np.ascontiguousarray(lanes[:, k]).tobytes() for k in range(4)]
    out = []
    for k in range(4):
        byte = np.ascontiguousarray(lanes[:, k])
        if not byte.any():
            out += [b""] * 8
            continue
        out += [np.packbits((byte >> bit) & 1, bitorder="little").tobytes() for bit in range(8)]
    return out


def from_planes(planes: dict[int, bytes], n: int, width: int) -> np.ndarray:
    ids = np.zeros(n, "<u4")
    for k, plane in planes.items():
        raw = np.frombuffer(plane, np.uint8)
        values = raw if width == 8 else np.unpackbits(raw, count=n, bitorder="little")
        ids |= values.astype("<u4") << np.uint32(8 * k if width == 8 else k)
    return ids


def encode_segment(doc_ids: list, lengths: list[int], ids: np.ndarray, width: int = 1, block: int = 1 << 16, level: int = 3) -> bytes:
    """One segment; a null doc_id is stored with a flag."""
    press = zstandard.ZstdCompressor(level=level).compress
    null = np.array([d is None for d in doc_ids], np.uint8)
    table = press(np.array([d or 0 for d in doc_ids], "<i8").tobytes() + np.array(lengths, "<u8").tobytes() + null.tobytes())
    index = np.zeros(-(-len(ids) // block), _INDEX)
    sizes, planes, at = [], [], 0
    for b in range(len(index)):
        part = ids[b * block : (b + 1) * block]
        index[b] = (at, len(part), 0)
        for k, plane in enumerate(to_planes(part, width)):
            if plane.strip(b"\0"):
                data = press(plane)
                index[b]["mask"] |= 1 << k
                sizes.append(len(data))
                planes.append(data)
                at += len(data)
    head = _HEAD.pack(MAGIC, width, len(doc_ids), len(ids), block, len(index), len(table))
    return b"".join([head, index.tobytes(), np.array(sizes, "<u4").tobytes(), table, *planes])


def decode_segment(data: bytes, only_block: int | None = None) -> tuple[list, np.ndarray, np.ndarray]:
    """(doc ids, lengths, ids); with ``only_block`` the ids of that block alone, found by the chunk index."""
    magic, width, n_docs, n_ids, block, n_blocks, n_table = _HEAD.unpack_from(data)
    if magic != MAGIC:
        raise ValueError("not a bit-plane segment")
    index = np.frombuffer(data, _INDEX, n_blocks, _HEAD.size)
    stored = [int(m).bit_count() for m in index["mask"]]
    at = _HEAD.size + index.nbytes
    sizes = np.frombuffer(data, "<u4", sum(stored), at)
    at += sizes.nbytes
    open_ = zstandard.ZstdDecompressor().decompress
    table = open_(data[at : at + n_table])
    doc_ids = np.frombuffer(table, "<i8", n_docs).tolist()
    lengths = np.frombuffer(table, "<u8", n_docs, 8 * n_docs).astype(np.int64)
    for k in np.flatnonzero(np.frombuffer(table, np.uint8, n_docs, 16 * n_docs)):
        doc_ids[k] = None
    at += n_table
    parts, first = [], 0
    for b in range(n_blocks):
        count = stored[b]
        if only_block is None or only_block == b:
            place, planes = at + int(index["offset"][b]), {}
            kinds = [k for k in range(32) if int(index["mask"][b]) >> k & 1]
            for k, size in zip(kinds, sizes[first : first + count].tolist(), strict=True):
                planes[k] = open_(data[place : place + size])
                place += size
            parts.append(from_planes(planes, int(index["n"][b]), width))
        first += count
    return doc_ids, lengths, np.concatenate(parts) if parts else np.zeros(0, "<u4")


SEGMENTS = "shard int, segment int, n_docs long, n_ids long, payload binary"


def write_ids(docs: DataFrame, vocabulary: str, end_id: int = 0, width: int = 1, block: int = 1 << 16, segment_ids: int = 1 << 20) -> DataFrame:
    """Encode every text, in ascending doc_id order over shards, and write the segments; returns the segment table.

    A segment closes at the first document that brings it to ``segment_ids`` ids, so a task holds about one segment.
    """

    def encode(batches):
        codec, shard = encoder(vocabulary, keep_space=True), TaskContext.get().partitionId()
        end = int(end_id).to_bytes(4, "little")
        doc_ids, lengths, parts, held, number = [], [], [], 0, 0

        def segment():
            payload = encode_segment(doc_ids, lengths, np.frombuffer(b"".join(parts), "<u4"), width, block)
            columns = [[shard], [number], [len(doc_ids)], [held], [payload]]
            kinds = (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["shard", "segment", "n_docs", "n_ids", "payload"])

        for batch in batches:
            for doc, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = codec.encode(raw.as_py()) + end
                doc_ids.append(doc)
                lengths.append(len(ids) // 4)
                parts.append(ids)
                held += len(ids) // 4
                if held >= segment_ids:
                    yield segment()
                    doc_ids, lengths, parts, held, number = [], [], [], 0, number + 1
        if doc_ids:
            yield segment()

    ordered = text_bytes(docs).repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    return written(ordered.mapInArrow(encode, SEGMENTS), "idplanes")


def read_documents(segments: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) from the files; needs no shuffle of ids, only of segment sizes."""
    sizes = segments.select("shard", "segment", "n_ids")
    # One row a shard: bounded by the number of writing tasks.
    shard = sizes.groupBy("shard").agg(F.sum("n_ids").alias("n"))
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    bases = shard.select("shard", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("shard_base"))
    inner = Window.partitionBy("shard").orderBy("segment").rowsBetween(Window.unboundedPreceding, -1)
    firsts = sizes.select("shard", "segment", F.coalesce(F.sum("n_ids").over(inner), F.lit(0)).alias("inner_base")).join(bases, "shard").select("shard", "segment", (F.col("shard_base") + F.col("inner_base")).alias("first"))

    def decode(batches):
        for batch in batches:
            for shard_no, segment_no, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                doc_ids, lengths, ids = decode_segment(data.as_py())
                raw, ends = ids.tobytes(), np.cumsum(lengths)
                starts = ends - lengths
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
                n = len(doc_ids)
                arrays = [pa.array([shard_no] * n, pa.int32()), pa.array([segment_no] * n, pa.int32()), pa.array(doc_ids, pa.int64()), pa.array(starts, pa.int64()), pa.array(lengths, pa.int64()), pa.array(crc, pa.int64())]
                yield pa.RecordBatch.from_arrays(arrays, ["shard", "segment", "doc_id", "local", "n_tokens", "ids_crc32"])

    read = segments.select("shard", "segment", "payload").mapInArrow(decode, "shard int, segment int, doc_id long, local long, n_tokens long, ids_crc32 long")
    return read.join(firsts, ["shard", "segment"]).select("doc_id", (F.col("first") + F.col("local")).alias("start"), "n_tokens", "ids_crc32")
