"""Interaction counts kept by a stream: users active in the same window with the same kind of event."""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probgraph.sources.graphs import by_count


def event_stream(spark: SparkSession, path: str, schema, max_files: int = 24) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def grouped(events: DataFrame, size: str = "5 minutes", slide: str | None = None, session_gap: str | None = None, late: str = "30 minutes", distinct_ids: bool = False) -> DataFrame:
    """(w, event_type, users): tumbling, sliding or session windows with a watermark; later rows are dropped by Spark, and counted in the progress."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    if distinct_ids:
        e = e.dropDuplicatesWithinWatermark(["event_id"])
    w = F.session_window("ts", session_gap) if session_gap else F.window("ts", size, slide) if slide else F.window("ts", size)
    return e.groupBy(w.alias("w"), "event_type").agg(F.collect_set("user_id").alias("users"))


def pairs_of(groups: DataFrame) -> DataFrame:
    """(src, dst, x) of groups of users."""
    u = groups.select(F.array_sort("users").alias("u"))
    src = u.select(F.posexplode("u").alias("i", "src"), "u")
    return src.select("src", F.explode(F.expr("slice(u, i + 2, size(u))")).alias("dst")).groupBy("src", "dst").agg(F.count("*").alias("x"))


def run_counts(groups: DataFrame, out: str, checkpoint: str, **trigger) -> object:
    """Run the stream until its input is used up; counts of each batch replace that batch's folder, so that a repeated batch changes nothing."""

    def write(df: DataFrame, batch: int) -> None:
        pairs_of(df).write.mode("overwrite").parquet(f"{out}/batch={batch}")

    q = groups.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(write).trigger(**(trigger or {"availableNow": True})).start()
    q.awaitTermination()
    return q


def dropped(query) -> int:
    """Rows that came after the watermark and were dropped, from the stream's progress reports."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


def counts(spark: SparkSession, out: str) -> DataFrame:
    return spark.read.schema("src long, dst long, x long, batch int").parquet(out).groupBy("src", "dst").agg(F.sum("x").alias("x"))


def interval_pairs(left: DataFrame, right: DataFrame, minutes: int = 5, late: str = "30 minutes") -> DataFrame:
    """Stream-stream join: two users' events of one kind at most so many minutes apart."""
    a = left.select(F.col("ts").cast("timestamp").alias("ta"), F.col("user_id").alias("src"), F.col("event_type").alias("ka")).withWatermark("ta", late)
    b = right.select(F.col("ts").cast("timestamp").alias("tb"), F.col("user_id").alias("dst"), F.col("event_type").alias("kb")).withWatermark("tb", late)
    return a.join(b, F.expr(f"ka = kb and src < dst and tb between ta - interval {minutes} minutes and ta + interval {minutes} minutes")).select("src", "dst", "ta", "tb")


def graph(spark: SparkSession, out: str) -> DataFrame:
    return by_count(counts(spark, out))


def batch_counts(events: DataFrame) -> DataFrame:
    """What the stream ends with, from a batch."""
    w = events.groupBy(F.window("ts", "5 minutes").alias("w"), "event_type").agg(F.collect_set("user_id").alias("users"))
    return pairs_of(w)


def relabel(labels: DataFrame, new_live: DataFrame) -> DataFrame:
    """Labels after worlds gained edges (counts only grow, and an edge's draw is fixed): new edges are contracted between old labels."""
    from probgraph.operators.components import label

    a, b = labels.select("world", F.col("node").alias("src"), F.col("label").alias("a")), labels.select("world", F.col("node").alias("dst"), F.col("label").alias("b"))
    between = new_live.join(a, ["world", "src"]).join(b, ["world", "dst"]).filter("a <> b").select("world", F.col("a").alias("src"), F.col("b").alias("dst"))
    merged = label(between).select("world", F.col("node").alias("label"), F.col("label").alias("new"))
    return labels.join(merged, ["world", "label"], "left").select("world", "node", F.coalesce("new", "label").alias("label"))


def split_by_hour(events: DataFrame, path: str, last: int | None = None) -> None:
    """Files of one hour each, in order (hour ``last`` put at the end), to feed the stream in tests."""
    e = events.withColumn("hour", F.date_trunc("hour", "ts"))
    hours = [x.hour for x in e.select("hour").distinct().orderBy("hour").collect()]
    if last is not None:
        hours.append(hours.pop(last))
    for i, part in enumerate(itertools.batched(hours, 24)):
        e.filter(F.col("hour").isin(list(part))).drop("hour").coalesce(1).write.mode("append").parquet(f"{path}/part={i:04d}")
