"""Streaming forms: counts are additive, so windowed count trees are plain stateful aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.keys import cell_key
from ..functions.schedule import SplitSchedule
from ..operators.stream_codec import Codestream


def with_time(df: DataFrame, ts: str = "ts") -> DataFrame:
    """TIMESTAMP_NTZ as TIMESTAMP (session zone UTC): watermarks refuse the zone-free type."""
    return df.withColumn(ts, F.col(ts).cast("timestamp"))


def window_of(kind: str, ts: str = "ts") -> Column:
    if kind == "tumbling":
        return F.window(ts, "1 day")
    if kind == "sliding":
        return F.window(ts, "1 day", "12 hours")
    return F.session_window(ts, "30 minutes")


def windowed_tree(points: DataFrame, schedule: SplitSchedule, window: Column, key: Column, max_level: int = 12, extra: list[str] | None = None, session: bool = False, outer: list[str] | None = None) -> DataFrame:
    """(start, level, prefix, cnt) for levels up to ``max_level``; the same text for batch and stream. ``session``: the window is
    one of sessions, whose keys meet in a row before they are spread over levels (a session is bounded by its gap). ``outer``:
    columns that tell cells apart besides the prefix, without parting windows."""
    outer = outer or []
    if session:
        # A session is one of the extra columns' rows, whatever their cells: sessions first, then their cells.
        held = points.withColumn("key", key).groupBy(window.alias("w"), *(extra or [])).agg(F.collect_list(F.struct("key", *outer)).alias("keys"))
        points, key, window = held.select("w", *(extra or []), F.explode("keys").alias("k")).select("w", *(extra or []), "k.*"), F.col("key"), F.col("w")
    levels = F.explode(F.sequence(F.lit(0), F.lit(min(max_level, schedule.q))))
    rows = points.withColumn("key", key).withColumn("level", levels)
    prefix = F.call_function("shiftright", F.col("key"), (F.lit(schedule.q) - F.col("level")).cast("int"))
    return rows.groupBy(window.alias("w"), *(extra or []), *outer, "level", prefix.alias("prefix")).agg(F.count(F.lit(1)).alias("cnt")).select(F.col("w.start").alias("start"), *(extra or []), *outer, "level", "prefix", "cnt")


def stream_points(spark, folder: str, schema, watermark: str = "1 hour", ts: str = "ts", max_files: int = 1) -> DataFrame:
    """File stream of Parquet with a watermark on event time."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(folder)
    return with_time(raw, ts).withWatermark(ts, watermark)


def run_to_memory(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run what is there to its end and return the result table."""
    query = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.table(name)


def deliver_waves(spark, stream_folder: str, schema, on_wave, checkpoint: str) -> None:
    """Each wave's files are a micro-batch; ``on_wave(batch, id)`` sharpens the client's view."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(stream_folder)
    raw.writeStream.foreachBatch(on_wave).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def distinct_points(points: DataFrame, axes: list[str]) -> DataFrame:
    """Set semantics: a point seen again within the watermark is dropped."""
    return points.dropDuplicatesWithinWatermark(axes)


def in_frontier(points: DataFrame, schedule: SplitSchedule, frontier: DataFrame, level: int) -> DataFrame:
    """Points of a stream in the cells (prefix) of a static table at ``level``; the planner broadcasts it if it is small."""
    keyed = points.withColumn("prefix", F.call_function("shiftright", cell_key(schedule), F.lit(schedule.q - level)))
    return keyed.join(frontier.select("prefix").distinct(), "prefix", "left_semi").drop("prefix")


def closed_windows(points: DataFrame, schedule: SplitSchedule, window: Column) -> DataFrame:
    """(start, a0.., m): the multiset of each window. In append mode a window comes out whole, in one micro-batch, once the
    watermark has passed it; until then the state store holds one row a different point, spread by point."""
    axes = [f"a{i}" for i in range(len(schedule.bits))]
    return points.groupBy(window.alias("w"), *axes).agg(F.count(F.lit(1)).alias("m")).select(F.col("w.start").alias("start"), *axes, "m")


def encode_closed_windows(points: DataFrame, schedule: SplitSchedule, folder: str, checkpoint: str, window: Column | None = None, model: int = 0, tile_bits: int | None = None) -> None:
    """Write one codestream a window under ``folder``/start=<seconds> as the watermark closes it.

    A batch that is run again after a failure overwrites the same folders with the same windows.
    """

    def encode(batch: DataFrame, _: int) -> None:
        closed = batch.persist()
        # Windows closed by one batch: few, whatever the number of points.
        for row in closed.select(F.unix_seconds("start").alias("s")).distinct().orderBy("s").collect():
            own = closed.where(F.unix_seconds("start") == row["s"]).drop("start")
            Codestream.encode(own, schedule, model, tile_bits=tile_bits).write(f"{folder}/start={row['s']}", "overwrite")
        closed.unpersist()

    closed = closed_windows(points, schedule, window_of("tumbling") if window is None else window)
    query = closed.writeStream.foreachBatch(encode).outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()


def requested_waves(arrivals: DataFrame, requests: DataFrame, within: str = "1 minute") -> DataFrame:
    """Interval join of two streams with watermarks: waves (tile, wave, at) that answer requests (tile, to_wave, asked).

    A wave answers a request of its tile for at least that wave if the two are at most ``within`` apart.
    """
    near = F.expr(f"a.at BETWEEN r.asked - INTERVAL {within} AND r.asked + INTERVAL {within}")
    same = (F.col("a.tile") == F.col("r.tile")) & (F.col("a.wave") < F.col("r.to_wave"))
    return arrivals.alias("a").join(requests.alias("r"), same & near).select("a.tile", "a.wave", "a.at", "r.to_wave", "r.asked")
