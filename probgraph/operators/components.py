"""Connected components in all worlds at once. A component's label is its least node."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probgraph.runtime import cut
from probgraph.sources import nodes as nodes_of

#: A graph of up to so many edges is labelled in one task, larger ones by stars.
EDGES_IN_TASK = 20_000_000


def least_labels(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, labels) of one world: hooking to the smaller root and pointer jumping, on whole arrays."""
    ids, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = ends[: len(src)], ends[len(src) :]
    root = np.arange(len(ids))
    while True:
        x, y = root[a], root[b]
        if (x == y).all():
            return ids, ids[root]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (up := root[root]).tolist() != root.tolist():
            root = up


def by_world(live: DataFrame) -> DataFrame:
    """A world fits in a task: one shuffle by world; a task labels all its worlds in one go. Nodes without live edges are left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        worlds, w = np.unique(t.column(0).to_numpy(), return_inverse=True)
        names, ends = np.unique(np.concatenate([t.column(1).to_numpy(), t.column(2).to_numpy()]), return_inverse=True)
        # a node of a world is one number; in a world their order is that of the nodes
        both = np.concatenate([w, w]) * len(names) + ends
        ids, label = least_labels(both[: len(w)], both[len(w) :])
        yield pa.RecordBatch.from_arrays([pa.array(worlds[ids // len(names)]), pa.array(names[ids % len(names)]), pa.array(names[label % len(names)])], names=["world", "node", "label"])

    kind = live.schema["world"].dataType.simpleString()
    return live.select("world", "src", "dst").repartition("world").mapInArrow(run, f"world {kind}, node long, label long")


def by_edge(live: DataFrame) -> DataFrame:
    """A world doesn't fit in a task: alternating large and small stars, keyed by (world, node); two shuffles a round."""
    pairs = cut(live.select("world", F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct())
    while True:  # a logarithmic number of rounds
        both = pairs.unionByName(pairs.select("world", F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("world", "a").agg(F.min("b").alias("n")).select("world", "a", F.least("n", "a").alias("m"))
        large = both.join(low, ["world", "a"]).filter("b > a and b <> m").select("world", F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = large.groupBy("world", "a").agg(F.min("b").alias("m"))
        new = large.join(low, ["world", "a"]).filter("b <> m").select("world", F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("world", "a", F.col("m").alias("b")))
        new = cut(new.distinct())
        stable = new.count() == pairs.count() and new.exceptAll(pairs).isEmpty()
        pairs = new
        if stable:
            break
    out = pairs.select("world", F.col("a").alias("node"), F.col("b").alias("label"))
    return out.unionByName(pairs.select("world", F.col("b").alias("node"), F.col("b").alias("label")).distinct())


def by_mask(masked: DataFrame, nodes: DataFrame, r: int) -> DataFrame:
    """Label propagation with one row a node for all r worlds; for graphs of small diameter. Gives signatures."""
    both = masked.unionByName(masked.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "mask"))
    sig = cut(nodes.select("node", F.transform(F.sequence(F.lit(0), F.lit(r - 1)), lambda w: F.col("node")).alias("labels")))
    on = lambda w: F.call_function("shiftrightunsigned", F.element_at("mask", (w / 64).cast("int") + 1), (w % 64).cast("int")).bitwiseAND(F.lit(1)) == 1
    while True:
        sent = both.join(sig.withColumnRenamed("node", "src"), "src").select(F.col("dst").alias("node"), F.transform("labels", lambda x, w: F.when(on(w), x)).alias("got"))
        least = sent.groupBy("node").agg(F.array(*[F.min(F.col("got")[i]) for i in range(r)]).alias("got"))
        new = cut(sig.join(least, "node", "left").select("node", F.when(F.col("got").isNull(), F.col("labels")).otherwise(F.zip_with("labels", "got", lambda a, b: F.least(a, b))).alias("labels")))
        if new.exceptAll(sig).isEmpty():
            return new
        sig = new


def label(live: DataFrame, strategy: str = "world") -> DataFrame:
    """(world, node, label) of nodes that have a live edge."""
    return {"world": by_world, "edge": by_edge}[strategy](live)


def label_support(edges: DataFrame, strategy: str = "auto") -> DataFrame:
    """(node, label) on the graph with all its edges. auto: in one task up to ``EDGES_IN_TASK`` edges, by stars beyond."""
    if strategy == "auto":
        strategy = "world" if edges.limit(EDGES_IN_TASK + 1).count() <= EDGES_IN_TASK else "edge"
    return label(edges.select(F.lit(0).alias("world"), "src", "dst"), strategy).select("node", "label")


def full(labels: DataFrame, nodes: DataFrame, r: int) -> DataFrame:
    """Labels of all nodes in worlds 0 .. r - 1: those without live edges are alone."""
    grid = nodes.select("node").withColumn("world", F.explode(F.sequence(F.lit(0), F.lit(r - 1))))
    return grid.join(labels, ["world", "node"], "left").select("world", "node", F.coalesce("label", "node").alias("label"))


def signatures(labels: DataFrame, nodes: DataFrame, r: int) -> DataFrame:
    """(node, labels): position w holds the label in world w. Only labels other than the node itself are shuffled."""
    some = labels.filter("label <> node").groupBy("node").agg(F.map_from_entries(F.collect_list(F.struct("world", "label"))).alias("m"))
    return nodes.select("node").join(some, "node", "left").select("node", F.transform(F.sequence(F.lit(0), F.lit(r - 1)), lambda w: F.coalesce(F.try_element_at("m", w), F.col("node"))).alias("labels"))


def largest(edges: DataFrame, strategy: str = "auto") -> DataFrame:
    """Edges of the largest component; of equal ones that with the least label."""
    lab = label_support(edges, strategy)
    best = lab.groupBy("label").count().orderBy(F.desc("count"), "label").limit(1).select("label")
    return edges.join(lab.join(F.broadcast(best), "label", "left_semi").select(F.col("node").alias("src")), "src", "left_semi")


def summary(edges: DataFrame) -> DataFrame:
    """(nodes, edges, components, largest_nodes, largest_edges) of a graph."""
    lab = label_support(edges)
    sizes = lab.groupBy("label").agg(F.count("*").alias("n"))
    m = edges.join(lab.select(F.col("node").alias("src"), "label"), "src").groupBy("label").agg(F.count("*").alias("m"))
    top = F.struct("n", -F.col("label"))
    return sizes.join(m, "label").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("nodes"), F.coalesce(F.sum("m"), F.lit(0)).alias("edges"), F.count("*").alias("components"), F.max_by("n", top).alias("largest_nodes"), F.max_by("m", top).alias("largest_edges"))


def nodes(edges: DataFrame) -> DataFrame:
    return nodes_of(edges)
