"""Worlds: random subgraphs in which every edge is kept independently. An edge's fate in world w is a hash of (seed, w, src, dst):
worlds can be made anew, in any order and number, and a world with more probable edges only gains edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probgraph.functions import SEED, WORD, coin
from probgraph.sources import nodes


def sample(edges: DataFrame, r: int, seed: int = SEED, first: int = 0, fast: bool = False) -> DataFrame:
    """(world, src, dst) of the edges alive in worlds first .. first + r - 1. No shuffle."""
    w = edges.withColumn("world", F.explode(F.sequence(F.lit(first), F.lit(first + r - 1))))
    return w.filter(coin(seed, F.col("world"), F.col("src"), F.col("dst"), fast) < F.col("prob") * WORD).select("world", "src", "dst")


def masks(edges: DataFrame, r: int, seed: int = SEED, fast: bool = False) -> DataFrame:
    """(src, dst, mask): bit w % 64 of element w / 64 tells whether the edge is alive in world w. One row an edge, whatever r is."""
    alive = lambda w: coin(seed, w, F.col("src"), F.col("dst"), fast) < F.col("prob") * WORD
    one = F.lit(1).cast("long")
    word = lambda i: F.aggregate(
        F.sequence(i * 64, F.least(i * 64 + 63, F.lit(r - 1))), F.lit(0).cast("long"), lambda m, w: F.when(alive(w), m.bitwiseOR(F.call_function("shiftleft", one, (w % 64).cast("int")))).otherwise(m)
    )
    return edges.select("src", "dst", F.transform(F.sequence(F.lit(0), F.lit((r - 1) // 64)), word).alias("mask"))


def from_masks(masked: DataFrame, r: int) -> DataFrame:
    """Live edges of masks, as :func:`sample` gives them."""
    bit = F.call_function("shiftrightunsigned", F.element_at("mask", (F.col("world") / 64).cast("int") + 1), (F.col("world") % 64).cast("int")).bitwiseAND(F.lit(1))
    return masked.withColumn("world", F.explode(F.sequence(F.lit(0), F.lit(r - 1)))).filter(bit == 1).select("world", "src", "dst")


def enumerate_worlds(edges: DataFrame, max_edges: int = 20) -> tuple[DataFrame, DataFrame]:
    """All worlds of a small graph, one support component at a time.

    (live: world, src, dst), (weights: world, weight, comp). world = component x 2^40 + the mask of uncertain edges that are alive."""
    from probgraph.operators.components import label_support

    comp = label_support(edges).select(F.col("node").alias("src"), F.col("label").alias("comp"))
    e = edges.join(comp, "src").groupBy("comp").agg(F.array_sort(F.collect_list(F.struct("src", "dst", "prob"))).alias("e"))
    e = e.withColumn("sure", F.filter("e", lambda x: x.prob >= 1)).withColumn("maybe", F.filter("e", lambda x: x.prob < 1)).withColumn("m", F.size("maybe"))
    worst = e.agg(F.max("m")).first()[0] or 0
    if worst > max_edges:
        raise ValueError(f"a component has {worst} uncertain edges; enumeration is for at most {max_edges}")
    w = e.withColumn("mask", F.explode(F.sequence(F.lit(0).cast("long"), F.expr("shiftleft(1L, m) - 1"))))
    w = w.withColumn("world", F.col("comp") * F.lit(1 << 40) + F.col("mask"))
    live_at = F.expr("filter(transform(maybe, (x, i) -> struct(x.src as src, x.dst as dst, x.prob as prob, (shiftright(mask, i) & 1) as on)), x -> true)")
    w = w.withColumn("t", live_at).withColumn("weight", F.aggregate("t", F.lit(1.0), lambda a, x: a * F.when(x.on == 1, x.prob).otherwise(1 - x.prob)))
    live = w.select("world", F.explode(F.expr("concat(transform(sure, x -> struct(x.src as src, x.dst as dst)), transform(filter(t, x -> x.on = 1), x -> struct(x.src as src, x.dst as dst)))")).alias("x")).select("world", "x.src", "x.dst")
    return live, w.select("world", "weight", "comp")


def median_like(edges: DataFrame) -> DataFrame:
    """One representative world: the edges that are more likely there than not."""
    return edges.filter("prob >= 0.5").select("src", "dst")


def contracted(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Certain edges contracted: (edges between merged nodes, node to merged node). Keeps all connection probabilities without depth limit."""
    from probgraph.operators.components import label_support
    from probgraph.sources import canonical

    of = nodes(edges).join(label_support(edges.filter("prob >= 1")), "node", "left").select("node", F.coalesce("label", "node").alias("merged"))
    e = edges.filter("prob < 1").join(of.select(F.col("node").alias("src"), F.col("merged").alias("a")), "src").join(of.select(F.col("node").alias("dst"), F.col("merged").alias("b")), "dst")
    return canonical(e.select(F.col("a").alias("src"), F.col("b").alias("dst"), "prob")), of
