"""The whole pipeline against brute force, and the SQL twins on documents with edge cases."""

import os
import zlib
from collections import Counter, defaultdict

import corpus_pipeline
import pyarrow.parquet as pq
import pytest
import regex
from cellstream.llm import registry, surrogates
from cellstream.llm.quality import ENDS, NAVIGATION, PHRASES
from compare import TABLES, compare
from test_jaccard import brute
from test_operators import WORD, all_ids, shingles, words

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(docs, tmp_path_factory):
    """The smallest tables, with the edge cases among the documents."""
    place = tmp_path_factory.mktemp("tables")
    for t in TABLES:
        if t != "documents":
            os.symlink(f"{SMALL}/{t}.parquet", place / f"{t}.parquet")
    pq.write_table(docs.toArrow(), place / "documents.parquet")
    return str(place)


def line_rule(line):
    if not line.encode().split():
        return 0
    plain = f" {' '.join(regex.findall(r'[\p{L}\p{N}]+', line.lower()))} "
    if 3 * sum(len(plain) - len(plain.replace(f" {p} ", " ")) for p in PHRASES) >= len(plain):
        return 1
    ends = line.rstrip(" \t\r")[-1:] in ENDS
    bars = sum(line.count(s) for s in NAVIGATION)
    if bars >= 2 and (not ends or 16 * bars >= len(line)):
        return 2
    if 5 * sum(c in "#*$%&|<>" for c in line) > len(line):
        return 3
    return 4 if not ends and len(line.encode().split()) < 12 else 0


def line_fails(line):
    return line_rule(line) > 0


def cleaned(text):
    """Text without failing lines, or None if the document is rejected."""
    w = words(text)
    grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    n = Counter(grams)
    repeated = {i + k for i, g in enumerate(grams) if n[g] > 1 for k in range(5)}
    lines = (text or "").split("\n")
    lost = sum(len(x) for x in lines if x.encode().split() and line_fails(x))
    if len(w) < 10 or 100 * len(repeated) > 20 * len(w) or 2 * lost > len(text):
        return None
    return "\n".join(x for x in lines if not line_fails(x))


def test_pipeline(spark, folder, rows):
    left = {d: c for d, t in rows.items() if (c := cleaned(t)) is not None}
    named = brute(left)  # five-word shingles of Jaccard 0.8 or more
    left = {d: t for d, t in left.items() if named[d] == d}
    items = [q for r in spark.read.parquet(f"{SMALL}/benchmark.parquet").collect() if (q := shingles(r["text"]))]
    left = {d: t for d, t in left.items() if not any(10 * len(q & shingles(t)) >= 8 * len(q) for q in items)}
    want = all_ids(WORD, {d: surrogates.replaced(t, registry.KEY, {})[0] for d, t in left.items()})
    got, bins = defaultdict(bytes), defaultdict(list)
    result = corpus_pipeline.run(spark, folder)
    for r in sorted(result.collect(), key=lambda r: (r["doc_id"], r["piece"])):
        piece = want[r["doc_id"]][r["start"] : r["start"] + r["length"]].tobytes()
        assert r["start"] * 4 == len(got[r["doc_id"]]) and r["ids_crc32"] == zlib.crc32(piece)
        got[r["doc_id"]] += piece
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    assert got == {d: v.tobytes() for d, v in want.items()} and len(rows) > len(want) > 100
    for b in bins.values():
        assert [o for o, _ in sorted(b)] == [sum(n for _, n in sorted(b)[:k]) for k in range(len(b))] and sum(n for _, n in b) <= 2048


def test_stages_keep_the_columns_of_documents(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for some in (docs, docs.limit(0)):
        at = some
        for _, stage in corpus_pipeline.STAGES[:-1]:
            at = stage(spark, at, folder)
            assert at.columns == docs.columns
        assert (corpus_pipeline.STAGES[-1][1](spark, at, folder).count() == 0) == (some is not docs)


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_queries_against_sql(spark, folder, name):
    assert compare(spark, registry.queries()[name], registry.oracle_sql()[name], folder) is None
