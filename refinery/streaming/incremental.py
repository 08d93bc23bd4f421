"""Structured Streaming: cross-run deduplication by micro-batches, and windowed stage counts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from refinery.operators.dedup import exact_key
from refinery.operators.storage import materialize


def _exists(spark, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def dedup_batch(batch: DataFrame, batch_id: int, root: str, text: str = "text", id_: str = "doc_id") -> None:
    """Marks a micro-batch against all earlier batches and itself; accepted keys and marked rows are written as the batch's own partition, so a replay
    overwrites what it wrote before."""
    spark = batch.sparkSession
    rows = materialize(batch.withColumn("key", exact_key(F.col(text))), "batch")
    earlier = None
    if _exists(spark, f"{root}/keys"):
        earlier = spark.read.parquet(f"{root}/keys").where(F.col("batch") < batch_id).select("key").distinct()
    first = rows.groupBy("key").agg(F.min(id_).alias("first"))
    marked = rows.join(first, "key")
    if earlier is not None:
        marked = marked.join(earlier.withColumn("seen", F.lit(True)), "key", "left")
    else:
        marked = marked.withColumn("seen", F.lit(None).cast("boolean"))
    reason = F.when(F.col("seen"), "seen_in_earlier_run").when(F.col(id_) != F.col("first"), "exact_duplicate")
    out = materialize(marked.withColumn("reason", reason).drop("seen", "first"), "marked")
    out.write.mode("overwrite").parquet(f"{root}/rows/batch={batch_id}")
    out.where("reason is null").select("key").distinct().write.mode("overwrite").parquet(f"{root}/keys/batch={batch_id}")


def run_incremental(stream: DataFrame, root: str, text: str = "text", id_: str = "doc_id"):
    """Reads what is there, in micro-batches, and stops (availableNow). Its checkpoint and tables live below root."""
    q = stream.writeStream.foreachBatch(lambda b, k: dedup_batch(b, k, root, text, id_)).option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def windowed_counts(events: DataFrame, width: str = "1 hour", late: str = "10 minutes", slide: str | None = None) -> DataFrame:
    """events: ts, event_type. Counts per window and type, with a watermark; works on streams and on tables."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    rows = rows.withWatermark("ts", late) if rows.isStreaming else rows
    return rows.groupBy(F.window("ts", width, slide or width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Sessions of a user: user_id, start, end, n."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    rows = rows.withWatermark("ts", late) if rows.isStreaming else rows
    return rows.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def distinct_within(events: DataFrame, keys: list[str], late: str = "10 minutes") -> DataFrame:
    """Exact keys on a stream with bounded state."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def split_late(events: DataFrame, late_before) -> tuple[DataFrame, DataFrame]:
    """Records behind a watermark are marked, not dropped: (on time, late with reason late_record)."""
    behind = F.col("ts").cast("timestamp") < late_before
    return events.where(~behind), events.where(behind).withColumn("reason", F.lit("late_record"))
