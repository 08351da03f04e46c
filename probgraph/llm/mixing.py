"""Operator 2: mixing sources to target weights by capped water-filling.

Every source gets its weight's share of the budget, at most ``max_epochs`` times its size. What a clamped source can't
take goes to the others in proportion to their weights, until nothing is over its cap. The end of that process is
min(cap, level x weight) for one water level, found here from the sources ordered by cap / weight: one aggregation, one
window over the table of sources (as many rows as sources), one join back. Each document is then repeated
floor(epochs) times, and once more where a draw seeded by (seed, doc_id) falls under the fraction.

Size is the text's length in characters. A null source is a source of its own; null or empty text has size 0 and is
repeated as its source is; a source without weight, or of size 0, gives no rows. Rows that share a doc_id share
a draw. Budgets above the sum of the caps give every source its cap."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from probgraph.runtime import cut, fresh, small

SEED, MAX_EPOCHS, BUDGET = 42, 4.0, 1.0


def allocation(docs: DataFrame, weights: DataFrame | dict | None = None, max_epochs: float = MAX_EPOCHS, budget: float = BUDGET) -> DataFrame:
    """(source, size, weight, epochs) per source. weights: source to weight; None weighs all sources alike. budget: times the total size."""
    spark = docs.sparkSession
    sizes = docs.groupBy("source").agg(F.sum(F.coalesce(F.length("text"), F.lit(0))).cast("long").alias("size"))
    if weights is None:
        sizes = sizes.withColumn("weight", F.lit(1.0))
    else:
        if isinstance(weights, dict):
            weights = spark.createDataFrame([(k, float(v)) for k, v in weights.items()], "source string, weight double")
        w = weights.select(F.col("source").alias("s"), F.col("weight").cast("double").alias("weight"))
        sizes = sizes.join(w, sizes.source.eqNullSafe(w.s), "left").select("source", "size", F.coalesce("weight", F.lit(0.0)).alias("weight"))
    order = Window.orderBy("ratio", F.col("source").asc_nulls_first())
    live = (
        sizes.withColumn("total", F.sum("size").over(Window.partitionBy()))
        .filter("size > 0 and weight > 0")
        .withColumn("cap", F.lit(float(max_epochs)) * F.col("size"))
        .withColumn("ratio", F.col("cap") / F.col("weight"))
        .withColumn("before", F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("rest", F.sum("weight").over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing)))
        .withColumn("level", (F.lit(float(budget)) * F.col("total") - F.col("before")) / F.col("rest"))
        .withColumn("water", F.max(F.when(F.col("level") <= F.col("ratio"), F.col("level"))).over(Window.partitionBy()))
    )
    filled = F.when(F.col("water").isNull(), F.col("cap")).otherwise(F.least(F.col("cap"), F.col("water") * F.col("weight")))
    return live.select("source", "size", "weight", F.round(filled / F.col("size"), 9).alias("epochs"))


def draw(seed: int, key) -> F.Column:
    """Uniform number in [0, 1) of a seed and a key; DuckDB finds the same from md5."""
    text = F.concat_ws("|", F.lit(str(seed)), F.coalesce(key.cast("string"), F.lit("null")))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def mix_sources(docs: DataFrame, weights: DataFrame | dict | None = None, max_epochs: float = MAX_EPOCHS, budget: float = BUDGET, seed: int = SEED) -> DataFrame:
    """The columns of ``docs`` and ``repetition`` (1, 2, ...); an existing column of that name gives way."""
    docs = docs.drop("repetition")
    key, times = fresh(docs, "mix_key"), fresh(docs, "mix_times")
    share = small(cut(allocation(docs.select("source", "text"), weights, max_epochs, budget).select(F.struct("source").alias(key), F.col("epochs").alias(times))))
    copies = (F.floor(times) + (draw(seed, F.col("doc_id")) < F.col(times) - F.floor(times)).cast("long")).cast("int")
    return (
        docs.withColumn(key, F.struct("source"))
        .join(share, key)
        .withColumn(times, copies)
        .filter(F.col(times) > 0)
        .withColumn("repetition", F.explode(F.sequence(F.lit(1), F.col(times))))
        .drop(key, times)
    )


def oracle(docs: str = "documents", max_epochs: float = MAX_EPOCHS, budget: float = BUDGET, seed: int = SEED) -> str:
    """The same rows in DuckDB, sources weighed alike."""
    return f"""
with s as (select source, sum(coalesce(length(text), 0))::bigint as size from {docs} group by source),
c as (select source, size, {float(max_epochs)} * size as cap, sum(size) over () as total from s),
o as (select *, coalesce(sum(cap) over (order by cap, source nulls first rows between unbounded preceding and 1 preceding), 0.0) as before_,
        count(*) over (order by cap, source nulls first rows between current row and unbounded following) as rest from c where size > 0),
l as (select *, ({float(budget)} * total - before_) / rest as level from o),
w as (select *, max(case when level <= cap then level end) over () as water from l),
e as (select source, round(case when water is null then cap else least(cap, water) end / size, 9) as epochs from w),
d as (select x.*, (floor(epochs) + case when ('0x' || substr(md5('{seed}|' || coalesce(x.doc_id::varchar, 'null')), 1, 8))::bigint / 4294967296.0 < epochs - floor(epochs) then 1 else 0 end)::int as times
      from {docs} x join e on x.source is not distinct from e.source)
select * exclude (times), unnest(range(1, times + 1))::int as repetition from d where times > 0
"""
