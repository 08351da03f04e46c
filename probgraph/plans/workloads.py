"""Experiments: methods side by side on the workload graphs. Each returns (graph, method, k, depth, seed, metric, value)."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probgraph.functions import SEED, edge_prob
from probgraph.operators import baselines, components, quality, reliability, worlds
from probgraph.operators.cluster import cluster_avg, cluster_min
from probgraph.operators.cover import Depth, Sampled
from probgraph.runtime import cut, release, stage

SCHEMA = "graph string, method string, k int, depth int, seed int, metric string, value double"
EVAL_SEED = 1001


def evaluator(edges: DataFrame, r: int, seed: int = EVAL_SEED):
    """Labels and signatures of worlds that no method has seen."""
    n = cut(components.nodes(edges))
    lab = stage(components.label(worlds.sample(edges, r, seed)))
    return stage(components.full(lab, n, r)), stage(components.signatures(lab, n, r))


def measures(assignment: DataFrame, full: DataFrame, sig: DataFrame, r: int) -> dict[str, float]:
    a = cut(assignment.select("node", "center"))
    x, y, z = quality.p_min_avg(a, sig, r).first(), quality.avpr(a, full, r).first(), quality.shape(a).first()
    return {"p_min": x.p_min, "p_avg": x.p_avg, "inner_avpr": y.inner_avpr, "outer_avpr": y.outer_avpr, "clusters": float(z.clusters)}


def run_method(method: str, edges: DataFrame, k: int, seed: int = SEED, **params) -> DataFrame:
    if method == "min":
        return cluster_min(edges, k, seed=seed, **params).assignment
    if method == "avg":
        return cluster_avg(edges, k, seed=seed, **params).assignment
    if method == "farthest_first":
        return baselines.farthest_first(edges, k, "hash", seed)
    if method == "pivot_star":
        return baselines.pivot_star(edges, seed)
    if method == "random":
        p = Sampled(edges, seed).ensure(200)
        from probgraph.operators.cover import assigned

        return assigned(p, baselines.random_centers(p, k, seed), 0)
    raise ValueError(method)


def compare(name: str, edges: DataFrame, inflations: list[float], seeds: list[int] = (SEED,), r_eval: int = 500, methods=("min", "avg", "farthest_first", "pivot_star"), largest: bool = True) -> DataFrame:
    """All methods at the number of clusters that the flow finds: objectives, pair reliabilities, milliseconds."""
    edges = cut(components.largest(edges) if largest else edges)
    full, sig = evaluator(edges, r_eval)
    rows = []
    for inflation in inflations:
        began = time.time()
        flow = cut(baselines.markov_flow(edges, inflation))
        k = flow.select("center").distinct().count()
        took = {"flow": 1000 * (time.time() - began)}
        for seed in seeds:
            for method in ("flow", *methods):
                if method == "flow" and seed != seeds[0] or k < 2 and method in ("min", "avg"):
                    continue
                began = time.time()
                a = flow if method == "flow" else cut(run_method(method, edges, k, seed))
                ms = took.get(method, 1000 * (time.time() - began))
                rows += [(name, method, k, None, seed, m, v) for m, v in {**measures(a, full, sig, r_eval), "millis": ms}.items()]
                del a
                release(edges.sparkSession)  # the driver gives back what the method's plans took
    return edges.sparkSession.createDataFrame(rows, SCHEMA)


def time_vs_k(name: str, edges: DataFrame, ks: list[int], seed: int = SEED, max_entries: int = baselines.MAX_ENTRIES) -> DataFrame:
    """Milliseconds of MIN, farthest-first and flow (bisected to k) as k grows; a flow that runs out of entries is reported with value -1."""
    rows = []
    edges = cut(edges)
    for k in ks:
        for method in ("min", "farthest_first", "flow"):
            began = time.time()
            try:
                if method == "flow":
                    baselines.markov_flow_for_k(edges, k, max_entries=max_entries)[1].count()
                else:
                    run_method(method, edges, k, seed).count()
                rows.append((name, method, k, None, seed, "millis", 1000 * (time.time() - began)))
            except baselines.OutOfMemory:
                rows.append((name, method, k, None, seed, "millis", -1.0))
    return edges.sparkSession.createDataFrame(rows, SCHEMA)


def predict(name: str, edges: DataFrame, truth: DataFrame, depths: list[int], k: int, seed: int = SEED, r: int = 100) -> DataFrame:
    """True and false positive rates of pairs: MIN and AVG within each depth, flow and star pivots without one."""
    rows = []
    truth = cut(truth)

    def add(method: str, depth, a, feasible: bool = True) -> None:
        if not feasible:
            rows.append((name, method, k, depth, seed, "infeasible", 1.0))
            return
        c = quality.pair_confusion(a, truth).first()
        rows.extend((name, method, k, depth, seed, m, None if c[m] is None else float(c[m])) for m in ("tpr", "fpr", "tp", "fp"))

    like = None  # each clustering begins with few worlds; those that another one has made are used again
    for d in depths:
        like = Depth(edges, d, None, seed, like=like)
        c = cluster_min(edges, k, depth=d, sampling=r, seed=seed, provider=like)
        add("min", d, c.assignment, c.status != "infeasible")
        like = Depth(edges, d, None, seed, like=like)
        add("avg", d, cluster_avg(edges, k, depth=d, sampling=r, seed=seed, provider=like).assignment)
    add("flow", None, baselines.markov_flow(edges, 2.0))
    add("pivot_star", None, baselines.pivot_star(edges, seed))
    return edges.sparkSession.createDataFrame(rows, SCHEMA)


def ablate(name: str, edges: DataFrame, k: int, param: str, values: list, method: str = "avg", seeds: list[int] = (SEED,), r_eval: int = 400) -> DataFrame:
    """One parameter's effect: gamma, alpha (None: all), power, or the first sample."""
    edges = cut(edges)
    full, sig = evaluator(edges, r_eval)
    rows = []
    for v in values:
        for seed in seeds:
            began = time.time()
            a = cut(run_method(method, edges, k, seed, **{param: v}))
            got = measures(a, full, sig, r_eval)
            rows += [(name, f"{method} {param}={v}", k, None, seed, m, x) for m, x in {**got, "millis": 1000 * (time.time() - began)}.items()]
    return edges.sparkSession.createDataFrame(rows, SCHEMA)


def start_size(name: str, edges: DataFrame, rs: list[int], exact: DataFrame, seed: int = SEED) -> DataFrame:
    """Largest and mean absolute error of estimates from so many worlds."""
    out = None
    for r in rs:
        e = reliability.estimator_error(exact, reliability.sampled_signatures(edges, r, seed), r).agg(F.max(F.abs(F.col("p_est") - F.col("prob"))).alias("max_error"), F.avg(F.abs(F.col("p_est") - F.col("prob"))).alias("mean_error")).select(F.lit(name).alias("graph"), F.lit(r).alias("r"), "max_error", "mean_error")
        out = e if out is None else out.unionByName(e)
    return out


def repeat(run, seeds: list[int]) -> DataFrame:
    """Mean and deviation of each metric over the seeds; run: seed to a report."""
    out = None
    for s in seeds:
        out = run(s) if out is None else out.unionByName(run(s))
    return out.groupBy("graph", "method", "k", "depth", "metric").agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("deviation"), F.count("*").alias("runs"))


def prob_table(spark: SparkSession, xs: tuple[int, ...] = (1, 2, 3, 5)) -> DataFrame:
    return spark.createDataFrame([(x,) for x in xs], "x long").select("x", F.round(edge_prob(F.col("x")), 6).alias("prob"))


def choose_by_avpr(report: DataFrame) -> DataFrame:
    """(graph, k, method): of MIN and AVG the one whose inner exceeds its outer reliability by more."""
    p = report.filter("method in ('min', 'avg')").groupBy("graph", "k", "method").pivot("metric", ["inner_avpr", "outer_avpr"]).avg("value")
    return p.groupBy("graph", "k").agg(F.max_by("method", F.col("inner_avpr") - F.col("outer_avpr")).alias("method"))


def rollup(report: DataFrame) -> DataFrame:
    """Means over grouping sets of (graph, method), (method) and all, told apart by ``level``."""
    return report.groupBy("metric").agg(F.lit(1)).select("metric").join(report, "metric").rollup("metric", "method", "graph").agg(F.round(F.avg("value"), 6).alias("value"), F.grouping_id().cast("int").alias("level")).filter("metric is not null")


__all__ = ["ablate", "choose_by_avpr", "compare", "evaluator", "measures", "predict", "prob_table", "repeat", "rollup", "start_size", "time_vs_k", "Depth"]
