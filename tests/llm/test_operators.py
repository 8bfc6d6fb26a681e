"""Each operator against a brute-force version, on the smallest documents and edge cases."""

import hashlib
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import regex
import xxhash
from cellstream.llm import bitplanes, decontaminate, hilbert, licenses, packing, quality, simhash, suffix_dedup, surrogates, token_counts
from cellstream.llm.common import PieceEncoder, tokenizer_path
from pyspark.sql import functions as F
from tokenizers import Tokenizer

WORD, BYTE = "word_bpe_49k.json", "byte_bpe_50k.json"


def words(text):
    return (text or "").encode().split()


def ids(name, text):
    return np.array([*Tokenizer.from_file(tokenizer_path(name)).encode(text or "", add_special_tokens=False).ids, 0], "<u4")


def all_ids(name, rows):
    library = Tokenizer.from_file(tokenizer_path(name))
    return {d: np.array([*library.encode(t or "", add_special_tokens=False).ids, 0], "<u4") for d, t in rows.items()}


def test_packing(docs, rows):
    want = all_ids(WORD, rows)
    got = packing.pack(docs, tokenizer_path(WORD), 2048).collect()
    per, bins = defaultdict(list), defaultdict(list)
    for r in got:
        per[r["doc_id"]].append(r)
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    assert set(per) == set(rows)
    for d, ps in per.items():
        ps.sort(key=lambda r: r["piece"])
        assert [r["piece"] for r in ps] == list(range(len(ps))) and sum(r["length"] for r in ps) == len(want[d])
        for r in ps:
            assert r["start"] == 2048 * r["piece"] and r["ids_crc32"] == zlib.crc32(want[d][r["start"] : r["start"] + r["length"]].tobytes())
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 2048
    assert len(bins) <= 1.02 * -(-sum(map(len, want.values())) // 2048) + 1


def test_packing_plan_uses_the_histogram_up():
    rng = np.random.default_rng(1)
    counts = Counter(np.clip(rng.lognormal(3.5, 1, 20_000).astype(int), 1, 256).tolist())
    bins = packing.plan_bins(counts, 256)
    used = Counter()
    for parts, n in bins:
        assert sum(parts) <= 256 and n > 0
        for p in parts:
            used[p] += n
    assert used == counts
    assert sum(n for _, n in bins) <= 1.01 * sum(k * v for k, v in counts.items()) / 256 + 1
    assert packing.plan_bins({}, 256) == []


def test_token_counts(docs, rows):
    want = all_ids(WORD, rows)
    got = {r["doc_id"]: r for r in token_counts.token_counts(docs, tokenizer_path(WORD), 2048).collect()}
    assert set(got) == set(rows)
    for d, r in got.items():
        assert r["n_tokens"] == len(want[d]) - 1 and r["n_bytes"] == len((rows[d] or "").encode()) and r["over_limit"] == (r["n_tokens"] > 2048)


@pytest.mark.parametrize("states", [8, 64, 1 << 15])
def test_transducer_is_exact_whatever_fits(rows, states):
    machine = token_counts.CountTransducer(tokenizer_path(WORD), max_states=states, memo=50)
    texts = [(t or "").encode() for t in rows.values()]
    want = [len(x) - 1 for x in all_ids(WORD, rows).values()]
    for lanes in (1, 7, 4096, 4096):
        assert machine.count(texts, lanes).tolist() == want


def test_transducer_of_the_merges_is_the_tokenizer():
    """Paths compiled from the merges alone against the library, on words, marks, contractions and digits of all kinds."""
    rng = random.Random(3)
    library, machine = Tokenizer.from_file(tokenizer_path(WORD)), token_counts.CountTransducer(tokenizer_path(WORD))
    names = list(library.get_vocab())
    pieces = ["'s", "'re", "'r", "'ll", "'l", "'v", "'", "''", "I'", "x'y", "rock'n'roll", "7", "19", "...", "!?", "<", "|", "--", "\x1c", "\x7f", "the", "ing"]
    units = ["".join(rng.choice([*pieces, rng.choice(names).removesuffix("</w>"), "".join(rng.choices("etaoinshrdlucmfwyp", k=rng.randint(1, 14)))]) for _ in range(rng.randint(1, 5))) for _ in range(6000)]
    units = [u for u in units if u.isascii() and "<|" not in u and not any(c.isspace() for c in u.replace("\x1c", ""))]
    for u, e in zip(units, library.encode_batch(units, add_special_tokens=False), strict=True):
        assert machine.compile(u.encode()) == len(e.ids), u
    assert len(units) > 3000 and not machine._memo
    text = [" ".join(units[k : k + 300]).encode() for k in range(0, len(units), 300)] + [b"a" * 5000, b"", b"x'" * 700 + b" y"]
    want = [len(e.ids) for e in library.encode_batch([t.decode() for t in text], add_special_tokens=False)]
    for lanes in (1, 50, 4096):
        assert machine.count(text, lanes).tolist() == want


def test_bitplanes(docs, rows):
    want = all_ids(BYTE, rows)
    for width in (1, 8):
        files = bitplanes.write_ids(docs, tokenizer_path(BYTE), width=width, block=1000, segment_ids=20_000)
        got = {r["doc_id"]: r for r in bitplanes.read_documents(files).collect()}
        at = 0
        for d in sorted(rows):
            assert (got[d]["start"], got[d]["n_tokens"], got[d]["ids_crc32"]) == (at, len(want[d]), zlib.crc32(want[d].tobytes()))
            at += len(want[d])


def test_segment_blocks_are_read_alone():
    values = np.random.default_rng(0).integers(0, 1 << 32, 5000, dtype=np.uint64).astype("<u4")
    for width in (1, 8):
        data = bitplanes.encode_segment([None, 7], [2000, 3000], values, width, 777)
        assert bitplanes.decode_segment(data)[0] == [None, 7]
        assert (bitplanes.decode_segment(data)[2] == values).all()
        assert (bitplanes.decode_segment(data, 3)[2] == values[3 * 777 : 4 * 777]).all()


def test_quality(docs, rows):
    for r in quality.measures(docs).collect():
        text = rows[r["doc_id"]] or ""
        w = words(text)
        grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        counts, covered = Counter(grams), set()
        for i, g in enumerate(grams):
            if counts[g] > 1:
                covered |= set(range(i, i + 5))
        lines = [x for x in text.split("\n") if x.encode().split()]
        failed = len(w) < 10 or 100 * len(covered) > 20 * len(w)
        assert r["n_words"] == len(w) and r["word_chars"] == sum(len(x.decode()) for x in w)
        assert r["n_symbols"] == sum(c in "#*$%&|<>" for c in text) and r["n_dup_lines"] == len(lines) - len(set(lines))
        assert r["n_repeat_words"] == len(covered), r["doc_id"]
        assert r["base_failed"] == failed and not (failed and r["kept"])


def test_quality_lines(spark):
    kinds = ["Home", "Sign up now", "Wer mag, kann hier klicken", "A | B | C | D | of the long and short of it.", "$$$ %%% ### so", "This catalog in a blog is no log in a fire, and it ends well.", "a long line of prose that only lacks the mark at its very end here"]
    lines = spark.createDataFrame([(i, " ".join(f"word{k}" for k in range(40)) + ".\n" + t) for i, t in enumerate(kinds)], "doc_id long, text string")
    found = {r["doc_id"]: [k for k in quality.RULES if r[f"lines_{k}"]] for r in quality.measures(lines).collect()}
    assert [found[i] for i in range(7)] == [["punctuation"], ["boilerplate"], ["boilerplate"], ["navigation"], ["symbols"], [], []]
    clash = lines.selectExpr("doc_id", "text", "1 AS __m", "2 AS kept", "3 AS `a.b`")
    assert quality.clean(clash).columns == clash.columns and {r["__m"] for r in quality.clean(clash).collect()} == {1}
    text = "This is a plain and honest sentence of prose that nobody would remove, ever.\nHome | News | About | Contact\nClick here to read our cookie policy"
    df = spark.createDataFrame([(1, text), (2, "Home | A | B | C\nHome | A | B | D\nfoo bar baz | x | y | z k l m n o")], "doc_id long, text string")
    kept = quality.clean(df).collect()
    assert [(r["doc_id"], r["text"]) for r in kept if r["doc_id"] == 1] == [] or kept[0]["text"] == text.split("\n")[0]
    assert all(r["doc_id"] != 2 for r in kept)


def fingerprint(text):
    w = words((text or "").encode().lower().decode())
    if not w:
        return 0
    grams = [b" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))]
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << k for k in range(64) if 2 * sum(h >> k & 1 for h in hashes) > len(hashes))


def brute_components(fps):
    parent = {d: d for d in fps}

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    items = sorted(fps.items())
    for i, (a, x) in enumerate(items):
        for b, y in items[i + 1 :]:
            if (x ^ y).bit_count() <= 4:
                ra, rb = root(a), root(b)
                parent[max(ra, rb)] = min(ra, rb)
    return {d: root(d) for d in fps}


def test_simhash(docs, rows):
    fps = {d: fingerprint(t) for d, t in rows.items()}
    want = brute_components(fps)
    got = {r["doc_id"]: r for r in simhash.classes(docs).collect()}
    assert {d: r["fp"] % (1 << 64) for d, r in got.items()} == fps
    assert {d: r["component_id"] for d, r in got.items()} == want


@pytest.mark.parametrize("size", [2, 16, 512])
def test_simhash_links_dense_groups(spark, size):
    rng = np.random.default_rng(5)
    fps = set()
    for _ in range(6):
        seed = int(rng.integers(0, 1 << 63))
        fps |= {seed ^ sum(1 << int(b) for b in rng.choice(63, int(rng.integers(0, 6)), replace=False)) for _ in range(60)}
    nodes = {f: f for f in fps}
    df = spark.createDataFrame([(f,) for f in fps], "fp long")
    tree = {r["node"]: r["root"] for r in simhash.components(simhash.links(df, size=size)).collect()}
    assert {f: tree.get(f, f) for f in fps} == brute_components(nodes)


def brute_repeats(texts, length):
    seen, out = {}, {}
    for d in sorted(texts):
        raw = (texts[d] or "").encode()
        gone = np.zeros(len(raw), bool)
        for s in range(len(raw) - length + 1):
            w = raw[s : s + length]
            if w in seen:
                gone[s : s + length] = True
            else:
                seen[w] = d
        kept = bytes(b for b, g in zip(raw, gone, strict=True) if not g)
        out[d] = (len(raw), int(gone.sum()), int((gone & ~np.concatenate([[False], gone[:-1]])).sum()) if len(raw) else 0, hashlib.sha256(kept).hexdigest())
    return out


def test_suffix_dedup(docs, rows):
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.deduplicated(docs).collect()}
    assert got == brute_repeats(rows, 100)


@pytest.mark.parametrize("bucket,slab,mask", [(512, 1 << 20, 64), (3, 1 << 20, 64), (512, 700, 64), (2, 900, 4), (512, 1 << 20, 6)])
def test_suffix_dedup_paths(spark, bucket, slab, mask):
    """Small buckets, long texts in pieces, and hashes of a few bits, under which very different bytes meet."""
    rng = np.random.default_rng(2)
    bank = ["".join(rng.choice(list("abcd "), int(rng.integers(60, 400)))) for _ in range(12)]
    texts = {i: "".join(bank[int(k)][int(rng.integers(0, 40)) :] for k in rng.choice(12, int(rng.integers(1, 6)))) for i in range(80)}
    texts[80], texts[81], texts[82] = "z" * 3000, "", texts[7]
    df = spark.createDataFrame([(i, t.encode()) for i, t in texts.items()], "uid long, raw binary").repartition(4)
    found = defaultdict(list)
    for r in suffix_dedup.repeats(df, 100, 20, block_rows=50, bucket=bucket, slab=slab, mask=(1 << mask) - 1).collect():
        found[r["uid"]].append((r["start"], r["end"]))
    want = brute_repeats(texts, 100)
    for i, t in texts.items():
        gone = np.zeros(len(t), bool)
        for a, b in found[i]:
            gone[a:b] = True
        assert int(gone.sum()) == want[i][1], i


def test_suffix_block_sorts_any_suffixes():
    rng = np.random.default_rng(3)
    for size in (1, 40, 700):
        text = rng.integers(97, 99, size).astype(np.uint8)
        text[size // 3 : size // 2] = 97
        block = suffix_dedup.SuffixBlock(text, 100)
        places = rng.permutation(size)
        heads = [bytes(block.text[p : p + 100]) for p in places.tolist()]
        order = block.sort_bucket(places)
        assert [heads[k] for k in order] == sorted(heads)
        shared = block.common_prefixes(places[order])
        for k in range(1, size):
            x, y = heads[order[k - 1]], heads[order[k]]
            assert shared[k] == next((i for i in range(100) if x[i] != y[i]), 100)


def test_difference_cover():
    cover = set(suffix_dedup.difference_cover(64).tolist())
    for a in range(64):
        for b in range(64):
            assert any((a + d) % 64 in cover and (b + d) % 64 in cover for d in range(64))


def test_hilbert_curve_is_a_walk():
    table = hilbert.curve_table(3)
    assert sorted(table) == list(range(512))
    cells = {place: (k >> 6, k >> 3 & 7, k & 7) for k, place in enumerate(table)}
    assert all(sum(abs(a - b) for a, b in zip(cells[i], cells[i + 1], strict=True)) == 1 for i in range(511))


def test_hilbert(docs, rows):
    got = hilbert.shards(docs).collect()
    assert Counter(r["doc_id"] for r in got) == Counter(rows.keys())
    shards = defaultdict(list)
    for r in got:
        raw = (rows[r["doc_id"]] or "").encode()
        assert r["size"] == len(raw) + 1 and r["text_crc32"] == zlib.crc32(raw) and r["law"] == "rows" and r["grown_shard"] is None
        shards[r["shard"]].append(r)
    assert set(shards) == set(range(16)) and max(map(len, shards.values())) - min(map(len, shards.values())) <= 1
    curve = []
    for s in range(16):
        part = sorted(shards[s], key=lambda r: r["slot"])
        assert [r["slot"] for r in part] == list(range(len(part)))
        curve += [r["curve"] for r in part]
    assert curve == sorted(curve)
    # Each row's place, from quantiles and the curve, by brute force.
    table = {r["doc_id"]: (r["lang"], r["source"], len((r["text"] or "").encode()) + 1) for r in docs.collect()}

    def buckets(values):
        there = sorted(v for v in values if v is not None)
        edges = sorted({there[-(-k * len(there) // 16) - 1] for k in range(1, 16)}) if there else []
        return [0 if v is None else sum(e < v for e in edges) for v in values]

    cells = list(zip(*[buckets([table[d][k] for d in sorted(table)]) for k in range(3)], strict=True))
    assert {r["doc_id"]: r["curve"] for r in got} == {d: hilbert.curve_index(c, 4) for d, c in zip(sorted(table), cells, strict=True)}


def test_write_shards(spark, docs, tmp_path):
    df = docs.unionByName(docs.limit(3)).unionByName(spark.createDataFrame([(None, "a", None, None, None, 1, "x"), (None, "a", None, None, None, 1, "x")], docs.schema)).withColumn("curve", F.lit(5)).withColumn("slot", F.lit("s")).withColumn("held", F.lit(0))
    hilbert.write_shards(df, str(tmp_path / "out"))
    back = spark.read.parquet(str(tmp_path / "out"))
    assert back.drop("shard").exceptAll(df).count() == 0 == df.exceptAll(back.drop("shard")).count() and back.columns == [*df.columns, "shard"]
    sizes = [r["count"] for r in back.groupBy("shard").count().collect()]
    assert len(sizes) == 16 and max(sizes) - min(sizes) <= 1
    with pytest.raises(ValueError):
        hilbert.write_shards(back, str(tmp_path / "more"))


def shingles(text, n=5):
    w = [x for x in regex.split(r"[^\p{L}\p{N}]+", (text or "").lower()) if x]
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set()


def test_decontamination(spark, docs, rows):
    items = {r["item_id"]: r["text"] for r in spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet").collect()} | {900: "a b c", 901: "", 902: None, 903: "Text, twice", 904: "one", 905: "nowhere to be found"}
    df = spark.createDataFrame([*items.items(), (900, "a b c"), (None, "one")], "item_id long, text string")
    want = {}
    for d, t in rows.items():
        w = [x for x in regex.split(r"[^\p{L}\p{N}]+", (t or "").lower()) if x]
        have = {k: {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} for k in range(1, 6)}
        for i, x in items.items():
            if q := shingles(x):
                both = q & have[len(next(iter(q)))]
                if len(both) >= 0.8 * len(q) - 1e-9:
                    want[d, i] = (len(both), len(q))
    got = {(r["doc_id"], r["item_id"]): (r["n_shared"], r["n_item"]) for r in decontaminate.contained(docs, df).collect()}
    assert got == want and {(100_004, 900), (100_014, 903), (100_003, 904)} <= set(want)
    left = {r["doc_id"] for r in decontaminate.without_leaks(docs, df).select("doc_id").collect()}
    assert left == set(rows) - {d for d, _ in want}


def test_licenses(spark, docs):
    lines = ["We like it. Licensed under the Apache License, Version 2.0. And more prose follows here.", "Released under the MIT License.", "This work is licensed under the GNU General Public License, version 3.", "Licensed under CC BY-NC 4.0.", "a driving license is needed", "Licensed under the Apache License, Version 1.1", None, ""]
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in licenses.scan(df).collect()}
    assert {d: r["license"] for d, r in got.items() if r["confirmed"]} == {0: "Apache-2.0", 1: "MIT", 2: "GPL-3.0", 3: "CC-BY-NC-4.0"}
    assert not got[4]["confirmed"] and not got[5]["confirmed"] and "2.0" in got[5]["differences"]


def test_empty_tables(spark, empty):
    items = spark.createDataFrame([], "item_id long, text string")
    for df in (
        packing.pack(empty, tokenizer_path(WORD)), token_counts.token_counts(empty, tokenizer_path(WORD), 5), bitplanes.read_documents(bitplanes.write_ids(empty, tokenizer_path(BYTE))),
        quality.measures(empty), quality.clean(empty), simhash.classes(empty), suffix_dedup.deduplicated(empty), hilbert.shards(empty), decontaminate.contained(empty, items), surrogates.pseudonymised(empty, b"k"), licenses.scan(empty),
    ):
        assert df.count() == 0


def test_repeated_rows_and_null_ids(spark):
    long = "all of these words are said again and again by many people in many places " * 3
    df = spark.createDataFrame([(None, long), (None, long), (1, long), (1, long), (1, None)], "doc_id long, text string").withColumn("lang", F.lit(None).cast("string")).withColumn("source", F.lit(None).cast("string"))
    items = spark.createDataFrame([(None, long), (1, long), (1, long)], "item_id long, text string")
    assert packing.pack(df, tokenizer_path(WORD)).count() == 5
    assert token_counts.token_counts(df, tokenizer_path(WORD), 5).count() == 5
    assert bitplanes.read_documents(bitplanes.write_ids(df, tokenizer_path(BYTE))).count() == 5
    assert quality.measures(df).count() == 5 and hilbert.shards(df).count() == 5 and simhash.classes(df).count() == 5
    assert sorted(r["n_removed"] for r in suffix_dedup.deduplicated(df).collect())[0] == 0
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.contained(df, items).collect()} == {(1, 1)}
    assert surrogates.pseudonymised(df, b"k").count() == 5 and licenses.scan(df).count() == 0


def test_cached_pieces_are_the_library_ids(rows):
    """Ids put together from cached pieces are the library's, whatever white space, marks and scripts meet."""
    rng = random.Random(2)
    texts = [t or "" for t in rows.values()] + ["".join(rng.choice([" ", " ", "\n", "\u3000", "a", "B", ".", "'s", "7", "é", "<|endoftext|>", "<", "\t", "🙂"]) for _ in range(400)) for _ in range(60)]
    for name, keep in ((BYTE, True), (WORD, False)):
        codec, library = PieceEncoder(tokenizer_path(name), keep, capacity=300), Tokenizer.from_file(tokenizer_path(name))
        for t in texts:
            assert codec.encode(t.encode()) == np.asarray(library.encode(t, add_special_tokens=False).ids, "<u4").tobytes()
