"""Readers of tables, edge lists and ground truth."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField("src", T.LongType(), False), T.StructField("dst", T.LongType(), False), T.StructField("prob", T.DoubleType(), False)])


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """One of the given tables; only ``columns`` are read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def edges(spark: SparkSession, path: str, fmt: str = "parquet", **options: str) -> DataFrame:
    """Edge list from parquet, csv, json or orc, with a fixed schema; malformed rows fail."""
    reader = spark.read.schema(EDGES)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    return canonical(reader.options(**options).format(fmt).load(path))


def edges_from_text(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(edges, rejected lines) from lines of two ids and a probability parted by white space."""
    line = spark.read.text(path).filter("trim(value) <> '' and value not like '#%'")
    part = F.split(F.trim("value"), r"\s+")
    row = line.select("value", F.size(part).alias("n"), F.try_element_at(part, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(part, F.lit(2)).try_cast("long").alias("dst"), F.try_element_at(part, F.lit(3)).try_cast("double").alias("prob"))
    good = (F.col("n") == 3) & F.col("src").isNotNull() & F.col("dst").isNotNull() & F.col("prob").isNotNull() & (F.col("prob") > 0) & (F.col("prob") <= 1) & (F.col("src") != F.col("dst"))
    ok = F.coalesce(good, F.lit(False))
    return canonical(row.filter(ok).select("src", "dst", "prob")), row.filter(~ok).select("value")


def truth(df: DataFrame, node: str, group: str) -> DataFrame:
    """Possibly overlapping ground-truth groups."""
    return df.select(F.col(node).cast("long").alias("node"), F.col(group).alias("grp")).filter("node is not null and grp is not null").dropDuplicates()


def canonical(df: DataFrame) -> DataFrame:
    """src < dst, one row a pair: parallel edges are merged as independent ones (certain edges win), self loops and p = 0 go."""
    pair = df.filter("src <> dst and prob > 0").select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst"), F.col("prob").cast("double"))
    merged = pair.groupBy("src", "dst").agg(F.count("*").alias("n"), F.max("prob").alias("top"), F.sum(F.when(F.col("prob") < 1, F.log1p(-F.col("prob")))).alias("s"))
    return merged.select("src", "dst", F.when((F.col("n") == 1) | (F.col("top") >= 1), F.col("top")).otherwise(1 - F.exp("s")).alias("prob"))


def check_graph(edges_: DataFrame) -> DataFrame:
    """The edges, if all are canonical and 0 < prob <= 1; else an error with the number of bad rows."""
    bad = edges_.filter("not coalesce(src < dst and prob > 0 and prob <= 1, false)").count()
    if bad:
        raise ValueError(f"{bad} edges are not canonical or have no probability in (0, 1]")
    return edges_


def nodes(edges_: DataFrame) -> DataFrame:
    return edges_.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
