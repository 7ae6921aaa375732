"""Trees and events that arrive: hourly trees from an event stream, running bipartition supports, blocks as a sink."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators import codec as cd

#: Start of the hour numbers, 2024-01-01 UTC.
EPOCH = 1_704_067_200


def event_stream(spark, path: str, schema, max_files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def utc(events: DataFrame) -> DataFrame:
    """Wall-clock times read as UTC, whatever the session's zone and whether the column has one."""
    return events.withColumn("ts", F.to_timestamp(F.concat(F.col("ts").cast("string"), F.lit("Z"))))


def bucket_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "1 hour", buckets: int = 16) -> DataFrame:
    """(start, bucket, n) of tumbling or sliding windows; rows later than the watermark are dropped by Spark, which counts
    them. Works on streams and tables."""
    timed = events.withWatermark("ts", late)
    frame = F.window("ts", width, slide) if slide else F.window("ts", width)
    return timed.groupBy(frame.alias("w"), (F.col("user_id") % buckets).cast("int").alias("bucket")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "bucket", "n")


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, start, end, n) of sessions: one tree each in the session collection."""
    timed = events.withWatermark("ts", late)
    return timed.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def hourly_clusters(counts: DataFrame, buckets: int = 16, levels: int = 3) -> DataFrame:
    """(tree_id, members, card) of closed windows (start, bucket, n): dyadic clusters of the buckets by rank. A table, or
    the batch of a stream."""
    from pyspark.sql import Window

    hour = ((F.unix_timestamp("start") - EPOCH) / 3600).cast("long")
    per = counts.groupBy(hour.alias("tree_id")).agg(F.map_from_entries(F.collect_list(F.struct("bucket", "n"))).alias("m"))
    grid = per.select("tree_id", "m", F.explode(F.sequence(F.lit(0), F.lit(buckets - 1))).alias("taxon")).withColumn("n", F.coalesce(F.col("m")[F.col("taxon")], F.lit(0)))
    ranked = grid.withColumn("r", F.row_number().over(Window.partitionBy("tree_id").orderBy(F.desc("n"), "taxon")) - 1)
    level = ranked.select("tree_id", "taxon", "r", F.explode(F.sequence(F.lit(1), F.lit(levels))).alias("level"))
    cell = F.floor(F.col("r") * F.pow(F.lit(2), F.col("level")) / buckets)
    out = level.groupBy("tree_id", "level", cell.alias("cell")).agg(F.array_sort(F.collect_list(F.lpad(F.col("taxon").cast("string"), 2, "0"))).alias("m"))
    return out.select("tree_id", F.array_join("m", ",").alias("members"), F.size("m").alias("card"))


class RunningSupport(StatefulProcessor):
    """Support of each cluster over the trees seen so far: one count in state. With ttl_ms the count of a cluster that no
    tree has had for so long is forgotten."""

    def __init__(self, ttl_ms: int | None = None):
        self.ttl_ms = ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.count = handle.getValueState("count", "n long", ttlDurationMs=self.ttl_ms)

    def handleInputRows(self, key, rows, timer_values):
        had = self.count.get()[0] if self.count.exists() else 0
        now = had + sum(len(r) for r in rows)
        self.count.update((now,))
        yield pd.DataFrame({"members": [key[0]], "n_support": [now]})

    def close(self) -> None:
        pass


def running_support(clusters: DataFrame, ttl_ms: int | None = None) -> DataFrame:
    """Update stream (members, n_support) of a stream of clusters. Needs the RocksDB state store."""
    return clusters.groupBy("members").transformWithStateInPandas(RunningSupport(ttl_ms), "members string, n_support long", "Update", "None" if ttl_ms is None else "ProcessingTime")


def write_blocks(path: str, taxa: list[str] | None = None, **options):
    """Sink for foreachBatch: every micro-batch of trees becomes blocks under its own batch number; a repeated batch
    replaces what it wrote before."""

    def sink(batch: DataFrame, epoch: int) -> None:
        kept = batch.persist()
        if kept.limit(1).count():
            cd.compress(kept, taxa=taxa, **options).write.mode("overwrite").option("compression", "none").parquet(f"{path}/epoch={epoch}")
        kept.unpersist()

    return sink


def drain(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there into a table in memory, for tests and small results."""
    q = stream.writeStream.format("memory").queryName(name).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
