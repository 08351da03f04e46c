"""Writers of clusterings, worlds and traces; views for SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probgraph.functions import register


def write_result(assignment: DataFrame, path: str, graph: str, mode: str = "append") -> None:
    assignment.withColumn("graph", F.lit(graph)).write.mode(mode).partitionBy("graph").parquet(path)


def append_worlds(labels: DataFrame, path: str, batch: int) -> None:
    """A batch of labelled worlds; progressive sampling reads only the batches that it lacks."""
    labels.withColumn("world_batch", F.lit(batch)).write.mode("append").partitionBy("world_batch").parquet(path)


def write_trace(trace: DataFrame, path: str) -> None:
    trace.write.mode("append").json(path)


def register_views(spark: SparkSession, **frames: DataFrame) -> None:
    """Temporary views of the given names, and the SQL functions."""
    register(spark)
    for name, df in frames.items():
        df.createOrReplaceTempView(name)
