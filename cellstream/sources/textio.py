"""Point files: vertex lists as text, CSV, JSON and ORC."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_vertices(spark: SparkSession, path: str, d: int) -> DataFrame:
    """One vertex a line, blanks between numbers; lines that are not d numbers are skipped."""
    parts = F.split(F.trim("value"), "\\s+")
    rows = spark.read.text(path).where(F.size(parts) == d).select(*[F.expr(f"try_cast(split(trim(value), '\\\\s+')[{k}] as bigint)").alias(f"a{k}") for k in range(d)])
    return rows.where(reduce(lambda a, b: a & b, [F.col(f"a{k}").isNotNull() for k in range(d)]))


def write_points(points: DataFrame, path: str, form: str) -> None:
    if form == "text":
        points.select(F.concat_ws(" ", *points.columns)).write.text(path)
    else:
        points.write.format(form).option("header", True).save(path)


def read_points(spark: SparkSession, path: str, form: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).format(form).option("header", True).load(path)
