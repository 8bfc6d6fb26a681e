"""Near-duplicate texts: SimHash candidates first, then every other pair that five-word shingles can still link.

Two texts are linked if the Jaccard similarity of their distinct ``n``-word shingles is ``percent`` or more. A 64-bit SimHash
shows few of these links (at 0.8 about ten of 64 bits differ), so the search has two steps and loses none:

1. Pairs that SimHash's byte-position index finds (``simhash.links`` on fingerprints of the same shingles), texts of one
   fingerprint, and pairs that stand next to or first in a posting of step 2 are compared, and the links give components.
2. Sets of ``n`` shingles that reach the similarity share one of their first ``n - ceil(t n) + 1`` shingles in any order that
   holds for all texts. Those prefixes are indexed; the order puts the most frequent shingles last, which only shortens
   postings. Within a posting, pairs that are not connected yet are tried if their sizes and places allow the similarity
   and their sketches do not rule it out.

A sketch is the parity of a set's members in each of about as many buckets as it has members. The buckets in which two
sketches differ are at most the members in which the sets differ, so the sketch rules out most pairs and never a link.
What they leave of a posting is not sent on pair by pair but as a family: edges that hold its members together, one a member at
most. Every link still to be found lies within a family, whose texts meet once; there wide sketches rule pairs out and
shingles decide, and a spanning forest of the links comes out. A posting or family with more members than a task should hold is cut
into blocks, and each pair of blocks is a group of its own.

Texts with the same words are one node: a 64-bit digest, drawn anew under another seed if a second digest shows that two
texts share one. Null, empty and blank texts have no words and are one node. Rows of equal doc_id and text are one document. A null
doc_id never names a component unless it is alone in it. An empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import forgotten, small, written

_FACTORS = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD], np.uint64)
#: Members of a posting that one group holds; a longer posting is cut into blocks.
BLOCK = 512


def _hashes(words: list[bytes], n: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles; a text of fewer words is one shingle."""
    import xxhash

    w = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    last = max(1, len(w) - n + 1)
    h = np.full(last, min(len(w), n), np.uint64)
    for k in range(min(n, len(w))):
        h = (h ^ w[k : k + last]) * _FACTORS[k % len(_FACTORS)]
        h ^= h >> np.uint64(29)
    return np.unique(h)


def shingles(raw: bytes, n: int) -> set[bytes]:
    w = raw.lower().split()
    return {b" ".join(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set()


def _digests(words: list[bytes], seed: int) -> tuple[int, int]:
    import xxhash

    text = b" ".join(words)
    return (xxhash.xxh3_64_intdigest(text, seed), xxhash.xxh64_intdigest(text, seed + 1)) if words else (0, 0)


def _signed(values) -> pa.Array:
    return pa.array(np.array(values, np.uint64).view(np.int64))


def _fingerprint(h: np.ndarray) -> int:
    bits = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return int(np.packbits(2 * bits.sum(0, dtype=np.int64) > len(h), bitorder="little").view("<u8")[0])


def _sketch(h: np.ndarray, times: int = 1) -> bytes:
    """Parity of the members in each bucket; a power of two of buckets, 128 to 32 768, not below the set's size (``times`` that and
    the limit) if it can."""
    width = min(times << 15, max(128, 1 << (times * len(h) - 1).bit_length()))
    odd = np.bincount((h >> np.uint64(17) & np.uint64(width - 1)).astype(np.int64), minlength=width) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def differing(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Buckets in which the sketch ``a`` and each row of ``b`` differ; the longer ones are folded onto the shorter."""
    while b.shape[1] > len(a):
        b = b[:, : b.shape[1] // 2] ^ b[:, b.shape[1] // 2 :]
    while len(a) > b.shape[1]:
        a = a[: len(a) // 2] ^ a[len(a) // 2 :]
    return np.bitwise_count(b ^ a).sum(1, dtype=np.int64)


def _tally(n: int, least: int, room: int):
    """Batches of (raw) to the hashes that ``room`` of them in a row have ``least`` times, with their counts; a worker holds ``room``."""

    def seen(h):
        # In place; only what is frequent is copied.
        h.sort()
        same = max(0, len(h) - least + 1)
        often = np.unique(h[:same][h[:same] == h[len(h) - same :]])
        c = np.searchsorted(h, often, "right") - np.searchsorted(h, often)
        return pa.RecordBatch.from_arrays([_signed(often), pa.array(c, pa.int64())], ["h", "c"])

    def tally(batches):
        forgotten()
        buffer, held = np.empty(room, np.uint64), 0
        for batch in batches:
            for value in batch.column(0):
                words = value.as_py().lower().split()
                fresh = _hashes(words, n) if words else buffer[:0]
                while len(fresh):
                    part = fresh[: room - held]
                    buffer[held : held + len(part)] = part
                    held, fresh = held + len(part), fresh[len(part) :]
                    if held == room:
                        yield seen(buffer)
                        held = 0
        if held:
            yield seen(buffer[:held])

    return tally


def frequent(raw: DataFrame, n: int, least: int = 16, most: int = 200_000) -> tuple[np.ndarray, np.ndarray]:
    """The most frequent shingle hashes, sorted, and their counts; from those that some millions in a row have ``least`` times.

    They only order the index, so ``most`` bounds what is broadcast and changes no result.
    """
    rows = raw.select("raw").mapInArrow(_tally(n, least, 4_000_000), "h long, c long").groupBy("h").agg(F.sum("c").alias("c")).orderBy(F.desc("c"), "h").limit(most).toArrow()
    h, c = rows.column("h").to_numpy().view(np.uint64), rows.column("c").to_numpy()
    order = np.argsort(h)
    return h[order], c[order]


SETS = "doc_id long, row long, node long, twin long, n int, fp long, sketch binary, prefix array<long>"


def shingle_sets(raw: DataFrame, n: int, percent: int, hot: tuple[np.ndarray, np.ndarray], seed: int = 0, mask: int = (1 << 64) - 1) -> DataFrame:
    """A row a text: its node, and once a task for each node the set's size, fingerprint, sketch and prefix.

    ``mask`` keeps only some bits of the node's digest, to try what happens if two texts share one.
    """
    shared = raw.sparkSession.sparkContext.broadcast(hot)

    def make(batches):
        known, counts = shared.value
        done = set()
        for batch in batches:
            nodes, twins, sizes, marks, sketches, prefixes = [], [], [], [], [], []
            for value in batch.column(2):
                words = value.as_py().lower().split()
                node, twin = _digests(words, seed)
                node &= mask
                nodes.append(node)
                twins.append(twin)
                if not words or (node, twin) in done:
                    for column in (sizes, marks, sketches, prefixes):
                        column.append(None)
                    continue
                done.add((node, twin))
                h = _hashes(words, n)
                sizes.append(len(h))
                marks.append(int(np.uint64(_fingerprint(h)).view(np.int64)))
                sketches.append(_sketch(h))
                if len(known):
                    i = np.minimum(np.searchsorted(known, h), len(known) - 1)
                    h = h[np.lexsort((h, np.where(known[i] == h, counts[i], 0)))]
                prefixes.append(h[: len(h) - -(-len(h) * percent // 100) + 1].view(np.int64))
            arrays = [batch.column(0), batch.column(1), _signed(nodes), _signed(twins), pa.array(sizes, pa.int32()), pa.array(marks, pa.int64()), pa.array(sketches, pa.binary()), pa.array(prefixes, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(arrays, [f.split()[0] for f in SETS.split(", ")])

    return raw.select("doc_id", "row", "raw").mapInArrow(make, SETS)


def _allowed(na, ia, nb, ib, percent: int):
    """Whether sets of these sizes that share the elements at these places can have the similarity."""
    most = np.minimum(ia, ib) + np.minimum(na - ia, nb - ib)
    return (100 * np.minimum(na, nb) >= percent * np.maximum(na, nb)) & ((100 + percent) * most >= percent * (na + nb))


def _near(na, nb, differ, percent: int):
    """Whether sets of these sizes that differ in so many members can have the similarity."""
    return (100 + percent) * differ <= (100 - percent) * (na + nb)


def _shared(posted: DataFrame, percent: int) -> DataFrame:
    """(key, node, n, at, first, before): postings of two nodes or more; ``first`` and ``before`` are members to be tried
    first, the node itself where the places do not allow them. Keeps one row of a posting at a time."""

    def group(batches):
        last = None  # the row before: key, node, n, at, its posting's first row, whether it is out already
        for batch in batches:
            keys, nodes, sizes, places = (c.to_numpy() for c in batch.columns)
            if not len(keys):
                continue
            if last is not None:
                keys, nodes, sizes, places = (np.concatenate([[x], c]).astype(c.dtype) for x, c in zip(last[:4], (keys, nodes, sizes, places), strict=True))
            take = np.concatenate([[True], (keys[1:] != keys[:-1]) | (nodes[1:] != nodes[:-1])])
            keys, nodes, sizes, places = keys[take], nodes[take], sizes[take], places[take]
            at = np.arange(len(keys))
            new = np.concatenate([[True], keys[1:] != keys[:-1]])
            first = np.maximum.accumulate(np.where(new, at, 0))
            out = [keys, nodes, sizes, places]
            for other in (first, np.where(new, at, at - 1)):
                on, oi, ox = sizes[other].astype(np.int64), places[other], nodes[other]
                if last is not None and other is first:
                    lead = first == 0
                    ox, on, oi = np.where(lead, last[4][0], ox), np.where(lead, last[4][1], on), np.where(lead, last[4][2], oi)
                out.append(np.where(_allowed(sizes.astype(np.int64), places, on, oi, percent), ox, nodes))
            ready = np.zeros(len(keys), bool)
            ready[1:] |= ~new[1:]
            ready[:-1] |= ~new[1:]
            if last is not None:
                ready[0] &= not last[5]
            k = len(keys) - 1
            head = last[4] if last is not None and first[k] == 0 else (nodes[first[k]], sizes[first[k]], places[first[k]])
            out_already = bool(ready[k]) or (k == 0 and last is not None and last[5])
            last = (keys[k], nodes[k], sizes[k], places[k], head, out_already)
            yield pa.RecordBatch.from_arrays([pa.array(c[ready]) for c in out], ["key", "node", "n", "at", "first", "before"])

    return posted.repartition("key").sortWithinPartitions("key", "n", "node").mapInArrow(group, "key long, node long, n int, at int, first long, before long")


def _sketched(pairs: DataFrame, sketches: DataFrame, percent: int) -> DataFrame:
    """The (a, b) of ``pairs`` that the sketches do not rule out."""

    def check(batches):
        for batch in batches:
            na, nb = batch.column(2).to_numpy().astype(np.int64), batch.column(3).to_numpy().astype(np.int64)
            keep = np.zeros(batch.num_rows, bool)
            for k, (x, y) in enumerate(zip(batch.column(4).to_pylist(), batch.column(5).to_pylist(), strict=True)):
                keep[k] = _near(na[k], nb[k], differing(np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")[None, :])[0], percent)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(keep)), batch.column(1).filter(pa.array(keep))], ["a", "b"])

    side = lambda x: sketches.select(F.col("node").alias(x), F.col("n").alias(f"n{x}"), F.col("sketch").alias(f"s{x}"))
    return pairs.join(side("b"), "b").join(side("a"), "a").select("a", "b", "na", "nb", "sa", "sb").mapInArrow(check, "a long, b long")


def _groups(batches, n_keys: int, solve, names: list[str]):
    """``solve(table)`` of the rows of each whole group at hand; rows come sorted by their first ``n_keys`` columns."""
    held, now = [], None
    for batch in batches:
        if not batch.num_rows:
            continue
        group = np.stack([batch.column(c).to_numpy() for c in range(n_keys)], 1)
        cuts = np.flatnonzero((group[1:] != group[:-1]).any(1)) + 1
        out = []
        for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(group)], strict=True):
            if now is not None and tuple(group[a]) != now:
                out.append(solve(pa.Table.from_batches(held)))
                held = []
            now = tuple(group[a])
            held.append(batch.slice(a, b - a))
        yield _edges(out, names)
    if held:
        yield _edges([solve(pa.Table.from_batches(held))], names)


def _edges(parts, names):
    both = np.concatenate([np.zeros((0, 2), np.int64), *parts])
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(both[:, 0])), pa.array(np.ascontiguousarray(both[:, 1]))], names)


def _tables(sketches: list[bytes]):
    """Sketches by their length: one matrix a length, and each sketch's row in it."""
    wide = np.array([len(x) for x in sketches])
    table, slot = {}, np.zeros(len(wide), np.int64)
    for w in np.unique(wide).tolist():
        slot[wide == w] = np.arange((wide == w).sum())
        table[w] = np.frombuffer(b"".join(x for x in sketches if len(x) == w), "<u8").reshape(-1, w // 8)
    return wide, table, slot


def _families(rows: DataFrame, percent: int) -> DataFrame:
    """(a, b): edges that bring together the members of a posting, of different components, that places and sketches allow to be
    linked; at most an edge a member, whatever the number of pairs. A group is two blocks of a posting at most."""

    def solve(table):
        n, node, at, root, block = (table.column(c).to_numpy().astype(np.int64) for c in ("n", "node", "at", "root", "block"))
        if len(n) < 2 or root.min() == root.max():
            return np.zeros((0, 2), np.int64)
        wide, tables, slot = _tables(table.column("sketch").to_pylist())
        _, first, own = np.unique(root, return_index=True, return_inverse=True)
        parent, crossed = np.arange(len(first)), block.min() != block.max()
        for i in range(len(n) - 1):  # sizes go up: later ones are too large from some place on
            j = np.arange(i + 1, max(int(np.searchsorted(n, n[i] * 100 // percent, "right")), i + 1))
            j = j[(parent[own[j]] != parent[own[i]]) & (not crossed or block[j] != block[i]) & _allowed(n[i], at[i], n[j], at[j], percent)]
            for w in np.unique(wide[j]).tolist():
                k = j[wide[j] == w]
                k = k[_near(n[i], n[k], differing(tables[int(wide[i])][slot[i]], tables[w][slot[k]]), percent)]
                simhash._join(parent, np.full(len(k), own[i]), own[k])
        joined = np.flatnonzero(parent != np.arange(len(first)))
        return np.stack([node[first[parent[joined]]], node[first[joined]]], 1)

    ordered = rows.select("key", "i", "j", "n", "node", "at", "root", "block", "sketch").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "n", "node")
    return ordered.mapInArrow(lambda batches: _groups(batches, 3, solve, ["a", "b"]), "a long, b long").distinct()


def _within(rows: DataFrame, n: int, percent: int) -> DataFrame:
    """(a, b): links of a spanning forest of each group's members, whose texts are all at hand: wide sketches rule pairs out,
    shingles decide. ``rows``: (family, i, j, n, node, root, block, words)."""

    def solve(table):
        size, node, root, block = (table.column(c).to_numpy().astype(np.int64) for c in ("n", "node", "root", "block"))
        if len(size) < 2 or root.min() == root.max():
            return np.zeros((0, 2), np.int64)
        texts = table.column("words").to_pylist()
        wide, tables, slot = _tables([_sketch(_hashes(t.split(), n), 16) for t in texts])
        _, own = np.unique(root, return_inverse=True)
        parent, crossed, sets, found = np.arange(own.max() + 1), block.min() != block.max(), {}, []

        def have(k):
            if k not in sets:
                if len(sets) > 64:
                    sets.clear()
                sets[k] = shingles(texts[k], n)
            return sets[k]

        for i in range(len(size) - 1):
            j = np.arange(i + 1, max(int(np.searchsorted(size, size[i] * 100 // percent, "right")), i + 1))
            j = j[(parent[own[j]] != parent[own[i]]) & (not crossed or block[j] != block[i])]
            for w in np.unique(wide[j]).tolist():
                k = j[wide[j] == w]
                for x in k[_near(size[i], size[k], differing(tables[int(wide[i])][slot[i]], tables[w][slot[k]]), percent)].tolist():
                    if parent[own[x]] != parent[own[i]]:
                        both = len(have(i) & have(x))
                        if 100 * both >= percent * (len(have(i)) + len(have(x)) - both):
                            simhash._join(parent, own[[i]], own[[x]])
                            found.append((node[i], node[x]))
        return np.array(found, np.int64).reshape(-1, 2)

    ordered = rows.select("family", "i", "j", "n", "node", "root", "block", "words").repartition("family", "i", "j").sortWithinPartitions("family", "i", "j", "n", "node")
    return ordered.mapInArrow(lambda batches: _groups(batches, 3, solve, ["a", "b"]), "a long, b long").distinct()


def _blocked(rows: DataFrame, counted: DataFrame, group: str, block: int) -> DataFrame:
    """Rows once for each pair of blocks of their group that has theirs; ``counted``: (group, m)."""
    cut = counted.select(group, F.ceil(F.col("m") / block).cast("int").alias("blocks"))
    rows = rows.join(cut, group).withColumn("block", F.pmod(F.xxhash64("node"), "blocks").cast("long")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    return rows.withColumn("i", F.least("block", F.col("other").cast("long"))).withColumn("j", F.greatest("block", F.col("other").cast("long"))).drop("other", "blocks")


def texts_of(raw: DataFrame, nodes: DataFrame, seed: int, mask: int, bits: int = 26) -> DataFrame:
    """(node, words) of the texts that may be among ``nodes`` (node); written.

    A bitmap of fixed size (``bits``) of the wanted nodes keeps most other texts from being moved; joins that follow are exact.
    """
    place = nodes.select(F.pmod("node", F.lit(1 << bits)).alias("p"))
    one = F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod("p", F.lit(64)).cast("int"))
    words = place.groupBy(F.floor(F.col("p") / 64).cast("long").alias("w")).agg(F.bit_or(one).alias("bits")).toArrow()
    marked = np.zeros((1 << bits) // 64, np.int64)
    marked[words.column("w").to_numpy()] = words.column("bits").to_numpy()
    shared = raw.sparkSession.sparkContext.broadcast(marked)

    def texts(batches):
        wanted, low = shared.value, (1 << bits) - 1
        done = set()
        for batch in batches:
            found, held = [], []
            for value in batch.column(0):
                split = value.as_py().lower().split()
                node = _digests(split, seed)[0] & mask
                if int(wanted[(node & low) >> 6]) >> (node & 63) & 1 and node not in done:
                    done.add(node)
                    found.append(node)
                    held.append(b" ".join(split))
            yield pa.RecordBatch.from_arrays([_signed(found), pa.array(held, pa.binary())], ["node", "words"])

    return written(raw.select("raw").mapInArrow(texts, "node long, words binary").dropDuplicates(["node"]), "texts")


def verified(raw: DataFrame, pairs: DataFrame, n: int, percent: int, seed: int, mask: int) -> DataFrame:
    """The (a, b) of ``pairs`` whose texts' shingles have the similarity."""

    def check(batches):
        last, have = None, set()
        for batch in batches:
            a, b = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            close = np.zeros(len(a), bool)
            for row in range(len(a)):
                if a[row] != last:
                    last, have = a[row], shingles(batch.column(2)[row].as_py(), n)
                other = shingles(batch.column(3)[row].as_py(), n)
                both = len(have & other)
                close[row] = 100 * both >= percent * (len(have) + len(other) - both)
            yield pa.RecordBatch.from_arrays([pa.array(a[close]), pa.array(b[close])], ["a", "b"])

    kept = texts_of(raw, pairs.select(F.explode(F.array("a", "b")).alias("node")), seed, mask)
    of_b = pairs.join(kept.select(F.col("node").alias("b"), F.col("words").alias("words_b")), "b")
    both = of_b.join(kept.select(F.col("node").alias("a"), F.col("words").alias("words_a")), "a")
    return both.select("a", "b", "words_a", "words_b").mapInArrow(check, "a long, b long")


def _pairs(df: DataFrame, x: str, y: str) -> DataFrame:
    return df.where(F.col(x) != F.col(y)).select(F.least(x, y).alias("a"), F.greatest(x, y).alias("b"))


def links(raw: DataFrame, sets: DataFrame, n: int, percent: int, seed: int, mask: int, block: int = BLOCK) -> DataFrame:
    """(a, b): links of the similarity that connect the same nodes as all such links do."""
    full = sets.where("prefix is not null")
    sketches = written(full.select("node", "n", "fp", "sketch").dropDuplicates(["node"]), "sketches")
    posted = full.select(F.posexplode("prefix").alias("at", "key"), "node", "n").select("key", "node", "n", "at")
    shared = written(_shared(posted, percent), "shared")
    # Step 1: by SimHash, by equal fingerprints, and the nearest members of postings.
    marks = sketches.groupBy("fp").agg(F.min("node").alias("rep"))
    bits = simhash.links(marks.select("fp"))
    of = lambda x: marks.select(F.col("fp").alias(x), F.col("rep").alias(f"r{x}"))
    tried = _pairs(bits.join(of("a"), "a").join(of("b"), "b"), "ra", "rb")
    tried = tried.unionByName(_pairs(sketches.join(marks, "fp"), "node", "rep"))
    beside = shared.groupBy("node").agg(*[f(c).alias(f"{k}{c}") for c in ("first", "before") for k, f in (("lo", F.min), ("hi", F.max))])
    tried = tried.unionByName(_pairs(beside.select("node", F.explode(F.array("lofirst", "hifirst", "lobefore", "hibefore")).alias("other")), "node", "other"))
    tried = written(_sketched(tried.distinct(), sketches, percent), "tried")
    near = written(verified(raw, tried, n, percent, seed, mask), "near")
    # Step 2: what the postings have besides, between components.
    tree = simhash.components(near)
    rooted = written(shared.drop("first", "before").join(tree, "node", "left").select("key", "node", "n", "at", F.coalesce("root", "node").alias("root")), "rooted")
    mixed = written(rooted.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("m")).where("lo < hi").select("key", "m"), "mixed")
    rows = _blocked(rooted, mixed, "key", block).join(sketches.select("node", "sketch"), "node")
    family = written(_families(rows, percent), "family")
    # Every link left lies within a family: its members come together once, with their texts.
    groups = simhash.components(near.unionByName(family))
    member = written(groups.select("node", F.col("root").alias("family")).unionByName(groups.select(F.col("root").alias("node"), F.col("root").alias("family")).distinct()), "members")
    member = member.join(tree, "node", "left").select("node", "family", F.coalesce("root", "node").alias("root"))
    open_ = written(member.groupBy("family").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("m")).where("lo < hi").select("family", "m"), "open")
    member = written(member.join(open_.select("family"), "family", "left_semi"), "open-members")
    words = texts_of(raw, member.select("node"), seed, mask)
    told = member.join(sketches.select("node", "n"), "node").join(words, "node")
    return near.unionByName(written(_within(_blocked(told, open_, "family", block), n, percent), "far"))


def _rows(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return docs.select("doc_id", F.xxhash64("text").alias("row"), text.alias("raw"))


def classes(docs: DataFrame, n: int = 5, percent: int = 80, mask: int = (1 << 64) - 1, block: int = BLOCK) -> DataFrame:
    """(doc_id, row, node, component_id) for every row; ``row`` is a hash of the text."""
    raw = _rows(docs)
    hot = frequent(raw, n)
    for seed in range(0, 64, 2):
        sets = written(shingle_sets(raw, n, percent, hot, seed, mask), "sets")
        nodes = sets.groupBy("node").agg(F.min("doc_id").alias("first"), F.min("twin").alias("lo"), F.max("twin").alias("hi"))
        if nodes.where("lo <> hi").limit(1).count() == 0:
            break
        mask = (1 << 64) - 1  # two texts share a digest: another seed, and all bits
    nodes = nodes.select("node", "first")
    tree = simhash.components(links(raw, sets, n, percent, seed, mask, block))
    rooted = written(nodes.join(tree, "node", "left").select("node", "first", F.coalesce("root", "node").alias("root")), "rooted")
    named = written(rooted.groupBy("root").agg(F.min("first").alias("component_id")), "named")
    label = rooted.join(named, "root").select("node", "component_id")
    return sets.select("doc_id", "row", "node").join(label, "node").select("doc_id", "row", "node", "component_id")


def first_of_each(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """Documents that name their component; rows with a null doc_id are kept, columns as they came."""
    gone = written(classes(docs, n, percent).where(F.col("doc_id") != F.col("component_id")).select(F.col("doc_id").alias("__id"), F.col("row").alias("__row")).distinct(), "gone")
    same = (F.col("__id") == F.col("doc_id")) & (F.col("__row") == F.xxhash64("text"))
    return docs.join(small(gone, gone.count()), same, "left_anti").select(*docs.columns)
