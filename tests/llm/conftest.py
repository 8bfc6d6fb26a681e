import pytest
from pyspark.sql import functions as F

SMALL = "/root/testdata/sf0.001"
EDGES = [
    (100_000, None), (100_001, ""), (100_002, "   \n\t "), (100_003, "one"), (100_004, "a b c"), (100_005, "\n\n"),
    (100_006, "x" * 5000), (100_007, "ab" * 300), (100_008, "the same line\n" * 50), (100_009, "A<|endoftext|>b  c   d  \n\nq"),
    (100_010, "Ünïcödé ßtraße 你好 世界 ΑΣ ς Ωmega é  end"), (100_011, "don't we'll I'VE it's 1234 5 6.7"), (100_012, "w%d " * 1), (100_013, " ".join(f"w{i % 700}" for i in range(9000))),
    (100_014, "same text twice here"), (100_015, "same text twice here"),
]


@pytest.fixture(scope="session")
def docs(spark):
    """The smallest documents with edge cases, repeated rows, a clashing extra column and a null in every column."""
    base = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")
    more = spark.createDataFrame([(i, t, None, "src0", None) for i, t in EDGES], base.schema)
    return base.unionByName(more).withColumn("h", F.lit(1)).withColumn("key", F.lit("x")).repartition(5)


@pytest.fixture(scope="session")
def rows(docs):
    return {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}


@pytest.fixture(scope="session")
def empty(docs):
    return docs.limit(0)
