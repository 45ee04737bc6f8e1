"""Rectangle statistics on streams of points."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from planegrid.operators.rangejoin import box_of, points_in
from planegrid.operators.scan import count_in
from planegrid.plans.storage import settle


def windowed(points: DataFrame, length: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """points (ts, y, w): counts and sums by event time; on a stream, rows later than `late` behind are left out."""
    rows = points.withWatermark("ts", late) if late else points
    span = F.window("ts", length, slide) if slide else F.window("ts", length)
    return rows.groupBy(span.alias("span")).agg(F.count("*").alias("cnt"), F.sum("w").alias("s")).select(F.unix_micros("span.start").alias("start"), "cnt", "s")


def sessions(points: DataFrame, gap: str) -> DataFrame:
    """points (ts, user_id, w): a session of a user ends after a gap without points."""
    return points.groupBy("user_id", F.session_window("ts", gap).alias("span")).agg(F.count("*").alias("cnt"), F.sum("w").alias("s")).select("user_id", F.unix_micros("span.start").alias("start"), "cnt", "s")


def counts_from_files(spark: SparkSession, folder: str, schema, rects: DataFrame, target: str, checkpoint: str) -> DataFrame:
    """Reads point files (x, y, w) as a stream until none is left; each batch's partial counts are appended once, by batch.

    A batch that runs again after a failure overwrites its own folder, so counts stay exact.
    """
    points = spark.readStream.schema(schema).option("maxFilesPerTrigger", 2).parquet(folder)

    rects = settle(rects)
    box = box_of(rects)

    def keep(batch: DataFrame, number: int) -> None:
        inside = points_in(batch, rects, box=box)
        inside.groupBy("qid").agg(F.count("*").alias("cnt")).write.mode("overwrite").parquet(f"{target}/batch={number}")

    points.writeStream.foreachBatch(keep).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    partial = spark.read.parquet(target).groupBy("qid").agg(F.sum("cnt").alias("cnt"))
    return count_in(partial.where("false"), rects).select("qid").join(partial, "qid", "left").select("qid", F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))
