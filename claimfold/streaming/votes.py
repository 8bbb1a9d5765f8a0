"""Votes over streams of claims, and stages replayed on entities as they arrive."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import resolver
from ..plans.workspace import workspace


def read_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def window_votes(events: DataFrame, key: str, value: str, at: str = "ts", window: str = "1 day", late: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(key, start, value, n) in tumbling or sliding windows; claims later than `late` are dropped."""
    w = F.window(at, window, slide) if slide else F.window(at, window)
    counted = events.withWatermark(at, late).groupBy(F.col(key), w.alias("w"), F.col(value)).agg(F.count(F.lit(1)).alias("n"))
    return counted.select(key, F.col("w.start").alias("start"), value, "n")


def session_votes(events: DataFrame, key: str, at: str = "ts", gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark(at, late).groupBy(F.col(key), F.session_window(at, gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(key, F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, id: str, at: str = "ts", late: str = "1 hour") -> DataFrame:
    return events.withWatermark(at, late).dropDuplicatesWithinWatermark([id])


def interval_pairs(left: DataFrame, right: DataFrame, key: str, at: str = "ts", within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Pairs of two streams on a key, the right one within an interval after the left; state is bounded by the watermarks."""
    a = left.withWatermark(at, late).alias("a")
    b = right.withWatermark(at, late).alias("b")
    return a.join(b, F.expr(f"a.{key} = b.{key} and b.{at} >= a.{at} and b.{at} < a.{at} + interval {within}"))


def run_complete(stream: DataFrame, name: str) -> DataFrame:
    """Run over what is there and return the final table; each batch replaces the one before."""
    spark = stream.sparkSession
    out = f"{workspace(spark)}/stream-{name}"
    where = f"{out}-{spark.range(1).select(F.expr('uuid()')).first()[0]}"

    def keep(batch: DataFrame, _: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/rows")

    query = stream.writeStream.outputMode("complete").option("checkpointLocation", f"{where}/state").trigger(availableNow=True).foreachBatch(keep).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{where}/rows")


def resolve_stream(fitted: resolver.Fitted, wide: DataFrame, out: str, state: str):
    """Score each batch of complete entities by replaying the fitted stages; answers are appended to `out`."""

    def replay(batch: DataFrame, _: int) -> None:
        if not batch.isEmpty():
            resolver.top(resolver.resolve_new(fitted, batch)).write.mode("append").parquet(out)

    return wide.writeStream.option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(replay).start()
