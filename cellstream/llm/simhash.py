"""SimHash near-duplicates by a byte-position inverted index with count filtering.

Two 64-bit fingerprints that differ in at most ``max_bits`` = 4 bits agree in at least 8 - 4 of their 8 bytes, in place.
The index posts each distinct fingerprint under sets of three byte positions: 20 of the 56 sets are enough for every
choice of four positions to hold one (checked at import), so each pair to be found shares a posting. Within a posting the
equal positional bytes of a pair are tallied, pairs under the guaranteed minimum dropped and the rest verified by their
differing bits. A long posting is posted again by a fourth byte, then by half bytes, which its linked pairs must share, and
tallied in the parts. A posting gives the edges of a spanning forest of its links, not its pairs; components follow by
label spreading over the edges.

Texts with the same fingerprint are one node, so copies and repeated rows never form pairs; each row has its result. Null,
empty and blank texts have fingerprint zero and are linked like any other; very long texts are read whole. A null doc_id
never names a component unless it is alone in it. An empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dropped, text_bytes, written

BYTES = 8


def covering_triples() -> list[tuple[int, int, int]]:
    """Triples of byte positions such that every four positions hold one: groups of three, three and two in a ring."""
    groups = [(0, 1, 2), (3, 4, 5), (6, 7)]
    out = [g for g in groups if len(g) == 3]
    for k, g in enumerate(groups):
        out += [tuple(sorted((*pair, x))) for pair in combinations(g, 2) for x in groups[(k + 1) % 3]]
    return out


TRIPLES = covering_triples()
if not all(any(set(t) <= set(four) for t in TRIPLES) for four in combinations(range(BYTES), 4)):
    raise AssertionError("the posting sets miss a choice of four positions")


def fingerprints(docs: DataFrame, n: int = 4, seed: int = 42) -> DataFrame:
    """(doc_id, fp long): bit k is set if it is set in over half of the shingle hashes."""

    def mark(batches):
        import xxhash

        digest = xxhash.xxh64_intdigest
        for batch in batches:
            rows = batch.num_rows
            fps = np.zeros(rows, np.uint64)
            group, hashes, held = [], [], 0

            def flush():
                bits = np.unpackbits(np.array(hashes, "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
                starts = np.cumsum([0] + [k for _, k in group[:-1]])
                counts = np.add.reduceat(bits, starts, axis=0, dtype=np.int32)
                on = 2 * counts > np.array([k for _, k in group])[:, None]
                fps[[r for r, _ in group]] = np.packbits(on, axis=1, bitorder="little").view("<u8")[:, 0]

            for row, value in enumerate(batch.column(1)):
                words = value.as_py().lower().split()  # bytes: only A-Z change and only ASCII space parts
                if not words:
                    continue
                text = b" ".join(words)
                if len(words) <= n:
                    found = [digest(text, seed)]
                else:
                    ends = np.cumsum([len(w) + 1 for w in words])
                    a = [0, *ends[: len(words) - n].tolist()]
                    b = (ends[n - 1 :] - 1).tolist()
                    found = [digest(text[x:y], seed) for x, y in zip(a, b, strict=True)]
                group.append((row, len(found)))
                hashes += found
                held += len(found)
                if held > 100_000:
                    flush()
                    group, hashes, held = [], [], 0
            if group:
                flush()
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps.view(np.int64))], ["doc_id", "fp"])

    return text_bytes(docs).mapInArrow(mark, "doc_id long, fp long")


def _nibbles(fps: np.ndarray, k: int) -> np.ndarray:
    return (fps >> np.uint64(4 * k) & np.uint64(15)).astype(np.int64)


def _groups(values: np.ndarray):
    """Indices of each run of equal values of two members or more."""
    order = np.argsort(values, kind="stable")
    cuts = np.flatnonzero(np.diff(values[order])) + 1
    return [g for g in np.split(order, cuts) if len(g) > 1]


def _join(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Hook the components of a and b together, in place; parents point to the smallest member."""
    while len(a):
        ra, rb = parent[a], parent[b]
        low, high = np.minimum(ra, rb), np.maximum(ra, rb)
        apart = low != high
        a, b, low, high = a[apart], b[apart], low[apart], high[apart]
        np.minimum.at(parent, high, low)
        while True:
            jumped = parent[parent]
            if (jumped == parent).all():
                break
            parent[:] = jumped


def _tally(fps: np.ndarray, members: np.ndarray, parent: np.ndarray, max_bits: int, block: int = 512) -> None:
    """Pairs of a posting in blocks: tally equal bytes, drop pairs under the guaranteed minimum, verify the rest by bits."""
    for i in range(0, len(members), block):
        for j in range(i, len(members), block):
            a, b = members[i : i + block], members[j : j + block]
            x = fps[a][:, None] ^ fps[b][None, :]
            close = np.bitwise_count(x) <= max_bits
            close &= (x.view(np.uint8).reshape(*x.shape, BYTES) == 0).sum(2) >= BYTES - max_bits
            left, right = np.nonzero(close)
            _join(parent, a[left], b[right])


def _refined(fps: np.ndarray, members: np.ndarray, parent: np.ndarray, max_bits: int, free: tuple[int, ...], stage: int, size: int) -> None:
    """Links of a posting of any size. A long posting is posted again by further places that its linked pairs must share.

    Stage 0: three bytes are shared and ``free`` are the others; a pair shares a fourth. Stage 1: of the eight half bytes
    left, four at least are equal, so one of seven pairs of them. Stages 2 and 3: of the six left, two at least, so one of
    any five; of the five left, one. What is left differs in sixteen bits at most, which bounds a posting for good.
    """
    if len(members) <= size or stage > 3 or max_bits > 4:
        _tally(fps, members, parent, max_bits)
        return
    own = fps[members]
    if stage == 0:
        keys = [((own >> np.uint64(8 * p) & np.uint64(255)).astype(np.int64), tuple(2 * q + h for q in free if q != p for h in (0, 1))) for p in free]
    elif stage == 1:
        thirds = (free[:3], free[3:6], free[6:])
        keys = [(_nibbles(own, a) << 4 | _nibbles(own, b), tuple(k for k in free if k not in (a, b))) for t in thirds for a, b in combinations(t, 2)]
    else:
        keys = [(_nibbles(own, a), tuple(k for k in free if k != a)) for a in free[:5]]
    for values, rest in keys:
        for g in _groups(values):
            _refined(fps, members[g], parent, max_bits, rest, stage + 1, size)


def _posting_links(fps: np.ndarray, triple: tuple[int, ...], max_bits: int, size: int) -> list[tuple[int, int]]:
    """Edges of a spanning forest of one posting's links."""
    parent = np.arange(len(fps))
    _refined(fps, np.arange(len(fps)), parent, max_bits, tuple(k for k in range(BYTES) if k not in triple), 0, size)
    joined = np.flatnonzero(parent != np.arange(len(fps)))
    return [(int(fps[parent[v]]), int(fps[v])) for v in joined.tolist()]


def links(distinct_fps: DataFrame, max_bits: int = 4, size: int = 512) -> DataFrame:
    """(a, b): edges that connect the same fingerprints as all links of at most ``max_bits`` differing bits.

    Postings of over ``size`` members are posted again by more places; any size gives the same components."""
    if not 0 <= max_bits <= 4:
        raise ValueError("the postings guarantee links of up to four differing bits")
    shifted = [F.expr(" | ".join(f"(shiftleft(shiftrightunsigned(fp, {8 * p}) & 255L, {8 * k}))" for k, p in enumerate(t)) + f" | {i << 24}L") for i, t in enumerate(TRIPLES)]
    posted = distinct_fps.select("fp", F.explode(F.array(*shifted)).alias("key"))

    def link(batches):
        tail_k, tail_f = np.zeros(0, np.int64), np.zeros(0, np.int64)

        def edges(keys, fps):
            cuts = np.flatnonzero(np.diff(keys)) + 1
            starts, ends = np.concatenate([[0], cuts]), np.concatenate([cuts, [len(keys)]])
            out = []
            for a, b in zip(starts[ends - starts > 1].tolist(), ends[ends - starts > 1].tolist(), strict=True):
                out += _posting_links(fps[a:b].view(np.uint64), TRIPLES[int(keys[a]) >> 24], max_bits, size)
            array = np.array(out, np.uint64).reshape(-1, 2).view(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(array[:, 0]), pa.array(array[:, 1])], ["a", "b"])

        for batch in batches:
            keys = np.concatenate([tail_k, batch.column(0).to_numpy()])
            fps = np.concatenate([tail_f, batch.column(1).to_numpy()])
            if not len(keys):
                continue
            last = int(np.searchsorted(keys, keys[-1]))  # the last posting may go on
            tail_k, tail_f = keys[last:], fps[last:]
            if last:
                yield edges(keys[:last], fps[:last])
        if len(tail_k):
            yield edges(tail_k, tail_f)

    return posted.select("key", "fp").repartition("key").sortWithinPartitions("key").mapInArrow(link, "a long, b long").distinct()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root): smallest node reachable, by alternating large-star and small-star rounds; each round is written and
    the one before it deleted. Rounds grow with the logarithm of the longest path; ``max_rounds`` only stops a fault."""
    current = written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges")
    # Few edges need few tasks: about 100 000 a task, as many as the session gives beyond 64 tasks.
    parts = -(-current.count() // 100_000)
    fewer = lambda df: df.coalesce(max(1, parts)) if parts < 64 else df
    last = None
    for _ in range(max_rounds):
        both = current.unionByName(current.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # Written, so that the join below is between two plain exchanges, which the planner splits where a node is hot.
        least = written(fewer(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))), "least")
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(down.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        before, current = current, written(fewer(small), "edges")
        dropped(before)
        dropped(least)
        state = current.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == last:
            return current.select(F.col("u").alias("node"), F.col("v").alias("root"))
        last = state
    raise RuntimeError("label spreading did not settle")


def classes(docs: DataFrame, n: int = 4, seed: int = 42, max_bits: int = 4) -> DataFrame:
    """(doc_id, fp, component_id) for every row."""
    marked = written(fingerprints(docs, n, seed), "fingerprints")
    nodes = marked.groupBy("fp").agg(F.min("doc_id").alias("first"))
    tree = components(links(nodes.select("fp"), max_bits))
    rooted = written(nodes.join(tree.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root")), "rooted")
    named = written(rooted.groupBy("root").agg(F.min("first").alias("component_id")), "named")
    label = rooted.join(named, "root").select("fp", "component_id")
    return marked.join(label, "fp").select("doc_id", "fp", "component_id")


def first_of_each(docs: DataFrame, n: int = 4, seed: int = 42, max_bits: int = 4) -> DataFrame:
    """Documents that name their component; rows with a null doc_id are kept."""
    gone = classes(docs, n, seed, max_bits).where(F.col("doc_id") != F.col("component_id")).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
