"""Worked examples, exact answers, guarantees and SQL oracles of the graph library."""

import itertools
import math
import random
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probgraph import registry
from probgraph.functions import harmonic, needed, samples_avg, samples_min, samples_pair
from probgraph.operators import baselines, components, quality, reliability, worlds
from probgraph.operators.cluster import cluster_avg, cluster_min
from probgraph.operators.cover import Depth, Exact, Sampled, threshold_cover
from probgraph.plans import guess, planner, workloads
from probgraph.sources import canonical, check_graph, edges_from_text, graphs, sinks
from probgraph.streaming import interactions
from tests.conftest import duck, rows

SLOW = {"compare_methods", "predict_copies", "min_cluster_bisect", "min_cluster_progressive", "avg_cluster_depth", "min_cluster_depth", "farthest_by_connection"}


def edges_of(spark, rows_):
    return spark.createDataFrame([(int(a), int(b), float(p)) for a, b, p in rows_], "src long, dst long, prob double")


@pytest.fixture(scope="module")
def path4(spark):
    return edges_of(spark, [(1, 2, 0.9), (2, 3, 0.5), (3, 4, 0.9)]).cache()


@pytest.mark.parametrize("name", sorted(set(registry.ORACLE) - SLOW))
def test_oracle(spark, sf, name):
    assert rows(registry.QUERIES[name](spark, sf)) == rows(duck(sf).execute(registry.ORACLE[name]).df())


@pytest.mark.parametrize("name", sorted(set(registry.QUERIES) - set(registry.ORACLE) - SLOW))
def test_runs(spark, sf, name):
    assert registry.QUERIES[name](spark, sf).count() > 0


def brute(es, depth=None):
    """Connection probabilities by enumeration, in plain Python."""
    out = {}
    ns = sorted({x for a, b, _ in es for x in (a, b)})
    for mask in range(1 << len(es)):
        w, near = 1.0, {n: [] for n in ns}
        for i, (a, b, p) in enumerate(es):
            on = mask >> i & 1
            w *= p if on else 1 - p
            if on:
                near[a].append(b)
                near[b].append(a)
        for u in ns:
            dist, queue = {u: 0}, [u]
            for x in queue:
                for y in near[x]:
                    if y not in dist:
                        dist[y] = dist[x] + 1
                        queue.append(y)
            for v, d in dist.items():
                if u < v and (depth is None or d <= depth):
                    out[u, v] = out.get((u, v), 0) + w
    return {k: v for k, v in out.items() if v > 0}


def test_exact_by_enumeration(spark):
    r = random.Random(4)
    es = [(a, b, r.choice([0.2, 0.5, 0.9, 1.0])) for a, b in itertools.combinations(range(5), 2) if r.random() < 0.8] + [(10, 11, 0.3), (11, 12, 1.0)]
    df = edges_of(spark, es)
    for depth in (None, 1, 2):
        got = {(x.u, x.v): x.prob for x in reliability.exact_pairs(df, depth).collect()}
        want = brute(es, depth)
        assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-12 for k in want)
    assert reliability.triangle_slack(reliability.exact_pairs(df)).filter("slack < -1e-12").isEmpty()
    a, b, _ = es[0]
    assert reliability.edge_monotone(df, a, b).filter("present < absent - 1e-12").isEmpty()
    with pytest.raises(ValueError):
        reliability.exact_pairs(df, max_edges=2)


def test_hand_cases(spark):
    p = {(x.u, x.v): x.prob for x in reliability.exact_pairs(edges_of(spark, [(1, 2, 0.5), (2, 3, 0.8)])).collect()}
    assert abs(p[1, 3] - 0.4) < 1e-12
    t = edges_of(spark, [(1, 2, 0.5), (2, 3, 0.5), (1, 3, 0.5)])
    assert abs(reliability.exact_pairs(t).filter("u = 1 and v = 3").first().prob - 0.625) < 1e-12
    assert abs(reliability.exact_pairs(t, 1).filter("u = 1 and v = 3").first().prob - 0.5) < 1e-12
    assert abs(canonical(edges_of(spark, [(2, 1, 0.5), (1, 2, 0.5), (3, 3, 0.5), (4, 5, 0.0)])).first().prob - 0.75) < 1e-12
    with pytest.raises(ValueError, match="1 edges"):
        check_graph(edges_of(spark, [(1, 2, 0.5), (3, 2, 0.5)]))


def test_labels_agree(spark):
    r = random.Random(2)
    e = edges_of(spark, [(a, b, 0.4) for a, b in sorted({tuple(sorted(r.sample(range(40), 2))) for _ in range(60)})])
    live, n = worlds.sample(e, 12), components.nodes(e)
    a = rows(components.full(components.label(live, "world"), n, 12))
    assert a == rows(components.full(components.label(live, "edge"), n, 12))
    c = components.by_mask(worlds.masks(e, 12), n, 12).select(F.posexplode("labels").alias("world", "label"), "node").select("world", "node", "label")
    assert a == rows(c)
    assert rows(live) == rows(live.repartition(7))


def test_estimates_and_sizes(spark):
    e = edges_of(spark, [(1, 2, 0.6), (2, 3, 0.7), (1, 3, 0.4)])
    r = samples_pair(0.1, 0.05, 0.5)
    err = reliability.estimator_error(reliability.exact_pairs(e), reliability.sampled_signatures(e, r), r)
    assert r == 2214 and err.filter("error > 0.1").isEmpty()
    assert [samples_min(100, 1, 0.5), samples_min(100, 0.5, 0.5), samples_min(1153, 0.3, 0.1), samples_min(11985, 0.1, 0.1)] == [917, 1833, 105673, 401306]
    assert [samples_avg(100, 1, 0.5), samples_avg(100, 0.5, 0.5), samples_avg(1153, 0.3, 0.1), samples_avg(11985, 0.1, 0.1)] == [924, 7391, 1182854, 40395806]
    assert abs(harmonic(100) - 5.187377517639621) < 1e-12 and needed(0.3, 50) == 15
    assert [round(x, 9) for x in guess.practical(0.1, 1e-4)] == [0.9, 0.8, 0.6, 0.2, 1e-4]


def test_without_floor(spark, path4):
    m = cluster_min(path4, 2, schedule="geometric", sampling="free", order="id")
    assert m.status == "full" and set(m.centers) & {1, 2} and set(m.centers) & {3, 4}
    r = [t["r"] for t in m.trace]
    assert r == sorted(r)


def test_hot_events(spark, monkeypatch):
    df = spark.createDataFrame([(e, m) for e in range(4) for m in range(3 + 5 * e)], "e long, m long")
    plain = rows(graphs.pairs(df, "e", "m"))
    monkeypatch.setattr(graphs, "HOT", 9)
    assert rows(graphs.pairs(df, "e", "m")) == plain


def test_worked_example(spark, path4):
    x = Exact(path4)
    c = threshold_cover(x, 2, 0.9, order="id", pad="first")
    assert c.centers == [1, 3] and c.complete and c.assignment.agg(F.min("p_est")).first()[0] == 0.9
    c = threshold_cover(x, 2, 1.0, order="id", pad="first")
    assert c.centers == [1, 2] and {r.node for r in c.assignment.filter("not covered").collect()} == {3, 4}
    assert threshold_cover(x, 1, 0.45, None, 0.45, order="id", pad="first").centers == [2]
    m = cluster_min(path4, 2, schedule="geometric", exact=True, order="id", pad="first")
    assert len(m.trace) == 3 and abs(m.q - 1 / 1.21) < 1e-9 and m.assignment.agg(F.min("p_est")).first()[0] == 0.9
    a = cluster_avg(path4, 2, mode="theory", exact=True, order="id", pad="first")
    assert a.centers == [1, 3] and len(a.trace) == 2 and abs(a.assignment.agg(F.avg("p_est")).first()[0] - 0.95) < 1e-9
    a = cluster_avg(path4, 1, mode="theory", exact=True, order="id", pad="first")
    assert [round(t["phi"], 3) for t in a.trace] == [0.25, 0.475, 0.475] and abs(a.assignment.agg(F.avg("p_est")).first()[0] - 0.68875) < 1e-9
    assert cluster_min(path4, 1, schedule="geometric", exact=True, depth=1, order="id", pad="first", p_floor=0.2).status == "infeasible"
    two = edges_of(spark, [(1, 2, 0.97)])
    assert len(cluster_min(two, 1, schedule="geometric", exact=True).trace) == 2
    assert cluster_min(edges_of(spark, [(1, 2, 0.5), (3, 4, 0.5)]), 1, exact=True).status == "infeasible"


def test_infeasible_clusterings_are_tables(spark, tmp_path):
    """More components than clusters: every node is there, without a center, as in the SQL; no error."""
    pairs_ = spark.createDataFrame([(o, 2 * o + i, "R") for o in range(12) for i in (0, 1)], "l_orderkey long, l_suppkey long, l_returnflag string")
    pairs_.withColumn("l_shipdate", F.lit("1995-06-01").cast("timestamp_ntz")).coalesce(1).write.parquet(str(tmp_path / "lineitem.parquet"))
    for name in ("min_cluster", "min_cluster_bisect"):
        assert rows(registry.QUERIES[name](spark, str(tmp_path))) == rows(duck(str(tmp_path)).execute(registry.ORACLE[name]).df())
    a = registry.QUERIES["min_cluster_depth"](spark, str(tmp_path))
    assert a.count() == 24 and a.filter("center is not null or covered").isEmpty()


def test_guarantees(spark):
    r = random.Random(9)
    for _ in range(2):
        es = [(a, b, r.choice([0.3, 0.6, 0.9])) for a, b in itertools.combinations(range(5), 2) if r.random() < 0.7 or b == a + 1]
        e = edges_of(spark, es).cache()
        x = Exact(e)
        opt = baselines.brute_optimum(x.pairs.select("center", "node", "value"), x.nodes, 2).first()
        m = cluster_min(e, 2, schedule="geometric", exact=True, provider=x)
        assert m.assignment.agg(F.min("p_est")).first()[0] >= opt.best_min**2 / 1.1 - 1e-9
        assert len(m.trace) <= math.ceil(2 * math.log(1 / opt.best_min) / math.log(1.1)) + 1
        a = cluster_avg(e, 2, mode="theory", exact=True, provider=x)
        h = harmonic(x.n)
        assert a.assignment.agg(F.avg("p_est")).first()[0] >= (opt.best_avg / (1.1 * h)) ** 3
        assert len(a.trace) <= math.floor(math.log(h / opt.best_avg) / math.log(1.1)) + 2


def test_set_cover_gadget():
    """A k-clustering of value at least 1/N! exists exactly where k sets cover all (N nodes, rational arithmetic)."""
    sets = [{0, 1}, {1, 2}]
    n = 3 + len(sets)
    es = [(u, 3 + i) for i, s in enumerate(sets) for u in s] + [(3, 4)]
    p = Fraction(1, math.factorial(n))

    def conn(u, v):
        total = Fraction(0)
        for mask in range(1 << len(es)):
            seen, queue = {u}, [u]
            on = [e for i, e in enumerate(es) if mask >> i & 1]
            for x in queue:
                for a, b in on:
                    for y in ((b,) if a == x else (a,) if b == x else ()):
                        if y not in seen:
                            seen.add(y)
                            queue.append(y)
            if v in seen:
                total += p ** len(on) * (1 - p) ** (len(es) - len(on))
        return total

    table = {(u, v): Fraction(1) if u == v else conn(u, v) for u in range(n) for v in range(n)}
    for k in (1, 2):
        best = max(min(max(table[c, v] for c in cs) for v in range(n)) for cs in itertools.combinations(range(n), k))
        covers = any(set().union(*c) >= {0, 1, 2} for c in itertools.combinations(sets, k))
        assert (best >= p) == covers


def test_cover_variants(spark, sf):
    e = components.largest(graphs.part(spark, sf)).cache()
    p = Sampled(e).ensure(40)
    one = threshold_cover(p, 6, 0.3, order="id", block=1, pad="first")
    many = threshold_cover(p, 6, 0.3, order="id", block=64, pad="first")
    assert one.centers == many.centers and rows(one.assignment) == rows(many.assignment)
    low = 0.3 * 40
    for c in (many, threshold_cover(p, 6, 0.3, 8, 0.4), threshold_cover(p, 6, 0.3, None, 0.4)):
        a = c.assignment.toPandas()
        assert len(set(c.centers)) == 6 and all(a[a.node == x].center.item() == x for x in c.centers)
        assert (a[a.covered].p_est * 40 >= low - 1e-9).all() and a[~a.covered].center.isna().all()
    x, y = threshold_cover(p, 4, 0.3, None, 0.4), threshold_cover(p, 4, 0.3, None, 0.4, on_driver=0)
    assert x.centers == y.centers
    assert threshold_cover(p, 1, 0.9, abort=True).complete is False
    d = Depth(e, 2, 1).ensure(40)
    c = threshold_cover(d, 3, 0.3, order="id", pad="first")
    assert len(c.centers) == 3


def test_depth_grows_to_the_whole(spark, path4):
    m = worlds.masks(path4, 70)
    n = components.nodes(path4)
    whole = reliability.from_centers(reliability.sampled_signatures(path4, 70), [1, 2, 3, 4], 1)
    assert rows(reliability.from_centers_depth(m, n, 70, 3).select("center", "node", "hits")) == rows(whole)
    hits = [reliability.from_centers_depth(m, n, 70, d).agg(F.sum("hits")).first()[0] for d in (1, 2, 3)]
    assert hits == sorted(hits)
    both = reliability.from_centers_depth(m, n, 70, 3, 1).filter("disk_hits > 0").select("center", "node", F.col("disk_hits").alias("hits"))
    assert rows(both) == rows(reliability.from_centers_depth(m, n, 70, 1).select("center", "node", "hits"))


def test_baselines(spark, sf):
    e = components.largest(graphs.mixed(spark, sf)).cache()
    a, b = (baselines.farthest_first(e, 3, method=m).select("node", "center", F.round("dist", 9).alias("dist")) for m in ("task", "rounds"))
    assert rows(a) == rows(b)
    s = baselines.pivot_star(e)
    strong = {(x.src, x.dst) for x in e.filter("prob >= 0.5").collect()}
    got = s.collect()
    assert len(got) == components.nodes(e).count() and all(x.node == x.center or (min(x.node, x.center), max(x.node, x.center)) in strong for x in got)
    m = baselines.flow_step(baselines.flow_start(e), 2.0)
    assert m.groupBy("col").agg(F.sum("val").alias("t")).filter("abs(t - 1) > 1e-9").isEmpty()
    blocks = edges_of(spark, [(1, 2, 0.9), (2, 3, 0.9), (1, 3, 0.9), (11, 12, 0.9), (12, 13, 0.9), (11, 13, 0.9)])
    for method in ("task", "rounds"):
        f = {x.node: x.center for x in baselines.markov_flow(blocks, 2.0, method=method).collect()}
        assert len({f[1], f[2], f[3]}) == 1 and len({f[11], f[12], f[13]}) == 1 and f[1] != f[11]
    few, many = (baselines.markov_flow(e, i).select("center").distinct().count() for i in (1.3, 2.5))
    assert few <= many
    with pytest.raises(baselines.OutOfMemory):
        baselines.markov_flow(e, 2.0, max_entries=10)


def test_flow_ties_go_to_the_lowest_row(spark):
    """Entries that only rounding errors tell apart are equal: at the limit the lowest row stays."""
    m = spark.createDataFrame([(8, 0, 0.6), (9, 0, 0.6000000000000001), (0, 100, 1.0)], "row long, col long, val double")
    assert [x.row for x in baselines.flow_step(m, 2.0, top=1).filter("col = 100").collect()] == [8]


def test_flow_by_components(spark, monkeypatch):
    """Components are worked on apart, so that a table of many needs no joins; a large one by its entries, with the same clusters."""
    rng = random.Random(3)
    one = [(i, rng.randrange(i), rng.uniform(0.3, 0.95)) for i in range(1, 30)]
    e = edges_of(spark, [(min(a, b) + at, max(a, b) + at, p) for at in (0, 100, 200) for a, b, p in one])
    whole = rows(baselines.markov_flow(e, 2.0, method="rounds"))
    monkeypatch.setattr(baselines, "flow_step", None)
    assert rows(baselines.markov_flow(e, 2.0)) == whole
    ends = np.array([(a, b) for a, b, _ in one])
    monkeypatch.setattr(baselines, "PRODUCTS", 50)
    got = baselines._sparse_flow(30, ends, np.array([p for _, _, p in one]), 2.0, 1e-4, 100, 60)
    for _ in range(30):
        got = got[got]
    assert {(str(int(c)), str(i)) for i, c in enumerate(got)} == {x for x in whole if int(x[1]) < 100}
    # one node's component alone doesn't decide the others' form
    assert baselines.markov_flow(e, 2.0, max_entries=30 * 30).count() == 90


def test_best_least_connection_without_pairs(spark, monkeypatch):
    rng = random.Random(5)
    for near in (2, 40):
        e = edges_of(spark, {(a, b): (a, b, rng.uniform(0.2, 0.9)) for a in range(80) for b in (a + 1 + rng.randrange(near), a + 1)}.values())
        sig = reliability.sampled_signatures(e, 40).cache()
        all_ = {x.node: np.array(x.labels) for x in sig.collect()}
        least = {u: min(int((x == y).sum()) for y in all_.values()) for u, x in all_.items()}
        best = max(least, key=lambda u: (least[u], -u))
        with monkeypatch.context() as m:
            m.setattr(type(sig), "crossJoin", None)
            for block in (2, 32):
                assert reliability._best_least(sig, 40, block) == (best, least[best] / 40)
            assert [tuple(x) for x in reliability.best_source(None, 40, "min", sig).collect()] == [(best, least[best] / 40)]


def test_all_candidates_without_a_pair_table(spark, sf, monkeypatch):
    """Disks are counted, block by block, and centers are those of the pair table."""
    p = Sampled(components.largest(graphs.part(spark, sf)).cache()).ensure(40)
    pairs_ = p.table(12).collect()
    size = {}
    for x in pairs_:
        size[x.center] = size.get(x.center, 0) + (x.value >= 16)
    for most in (64 << 20, 40 * 8 * 7):
        assert {x.node: x.size for x in reliability.disk_sizes(p.sig, 16, most_bytes=most).collect() if x.size} == size
    some = np.array(sorted(size)[:9])
    got = {x.node: x.size for x in reliability.disk_sizes(p.sig, 16, some, 40 * 8 * 4).collect()}
    assert all(got.get(n, 0) == sum(x.center == n and x.node in some and x.value >= 16 for x in pairs_) for n in size)
    want = [threshold_cover(p, k, q, None, 0.4, assign=False) for k, q in ((6, 0.3), (3, 0.1))]
    monkeypatch.setattr(Sampled, "table", None)
    for (k, q), w in zip(((6, 0.3), (3, 0.1)), want):
        c = threshold_cover(p, k, q, None, 0.4, assign=False, on_driver=0)
        assert (c.centers, c.uncovered) == (w.centers, w.uncovered)


@pytest.mark.parametrize("name", ["avg_cluster", "cover_alpha"])
def test_large_tables_give_the_same_clusters(spark, sf, monkeypatch, name):
    """The form that large tables take needs no pair table and equals the SQL."""
    monkeypatch.setattr(Sampled, "met", lambda self, least: math.inf, raising=False)
    monkeypatch.setattr(Sampled, "table", None)
    assert rows(registry.QUERIES[name](spark, sf)) == rows(duck(sf).execute(registry.ORACLE[name]).df())


def test_measures_by_pairs(spark, path4):
    n, r = components.nodes(path4), 60
    lab = components.full(components.label(worlds.sample(path4, r)), n, r).cache()
    a = spark.createDataFrame([(1, 1), (2, 1), (3, 3), (4, 3)], "node long, center long")
    got = quality.avpr(a, lab, r).first()
    by = {(x.world, x.node): x.label for x in lab.collect()}
    p = {(u, v): np.mean([by[w, u] == by[w, v] for w in range(r)]) for u, v in itertools.combinations(range(1, 5), 2)}
    assert abs(got.inner_avpr - np.mean([p[1, 2], p[3, 4]])) < 1e-9 and abs(got.outer_avpr - np.mean([p[1, 3], p[1, 4], p[2, 3], p[2, 4]])) < 1e-9
    assert abs(quality.expected_edit_distance(a, path4).first()[0] - (0.1 + 0.1 + 0.5)) < 1e-9
    t = spark.createDataFrame([(1, "a"), (2, "a"), (3, "a"), (3, "b"), (4, "b"), (9, "b")], "node long, grp string")
    c = quality.pair_confusion(a, t).first()
    assert (c.tp, c.fp, c.fn, c.tn) == (2, 0, 2, 2)


def test_min_beats_farthest_first(spark, sf):
    e = components.largest(graphs.mixed(spark, sf)).cache()
    full, sig = workloads.evaluator(e, 200)
    k = max(2, components.nodes(e).count() // 10)
    got = {m: workloads.measures(workloads.run_method(m, e, k), full, sig, 200) for m in ("min", "farthest_first")}
    assert got["min"]["p_min"] >= got["farthest_first"]["p_min"] - 0.05


def test_contraction(spark):
    e = edges_of(spark, [(1, 2, 1.0), (2, 3, 0.5), (1, 3, 0.5), (3, 4, 0.7)])
    small, of = worlds.contracted(e)
    p = {(x.u, x.v): x.prob for x in reliability.exact_pairs(small).collect()}
    assert abs(p[1, 3] - 0.75) < 1e-12 and of.filter("node = 2").first().merged == 1
    assert worlds.median_like(e).count() == 4


def test_stream(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    hour = F.date_trunc("hour", "ts")
    hours = [x.hour for x in events.select(hour.alias("hour")).distinct().orderBy("hour").collect()]
    shared = events.groupBy(F.window("ts", "5 minutes").start.alias("w"), "event_type").agg(F.countDistinct("user_id").alias("n")).filter("n > 1").agg(F.min(F.date_trunc("hour", "w"))).first()[0]
    interactions.split_by_hour(events, f"{tmp_path}/in", last=hours.index(shared))  # an early hour that has pairs comes last: it is late and dropped
    end = events.limit(1).withColumn("ts", F.lit("2100-01-01").cast("timestamp").cast(events.schema["ts"].dataType)).withColumn("event_type", F.lit("end"))
    end.write.parquet(f"{tmp_path}/in/part=9999")
    s = interactions.event_stream(spark, f"{tmp_path}/in", T.StructType([*events.schema.fields, T.StructField("part", T.IntegerType())]), 1)
    q = interactions.run_counts(interactions.grouped(s), f"{tmp_path}/out", f"{tmp_path}/check")
    kept = events.filter(hour != F.lit(shared))
    got, all_, less = rows(interactions.counts(spark, f"{tmp_path}/out")), rows(interactions.batch_counts(events)), rows(interactions.batch_counts(kept))
    assert interactions.dropped(q) > 0 and got == less and less != all_ and q.exception() is None


def test_relabel(spark, path4):
    live = worlds.sample(path4, 20)
    old = live.filter("src <> 2")
    n = components.nodes(path4)
    new = interactions.relabel(components.full(components.label(old), n, 20), live.filter("src = 2"))
    assert rows(new) == rows(components.full(components.label(live), n, 20))


def test_files(spark, tmp_path, path4):
    (tmp_path / "g.txt").write_text("1 2 0.5\n2 1 0.5\n3 4 x\n5 5 0.5\n6 7 0.9\n")
    e, bad = edges_from_text(spark, str(tmp_path / "g.txt"))
    assert rows(e) == rows(edges_of(spark, [(1, 2, 0.75), (6, 7, 0.9)])) and bad.count() == 2
    sinks.write_result(path4, f"{tmp_path}/r", "p")
    assert spark.read.parquet(f"{tmp_path}/r").filter("graph = 'p'").count() == 3
    sinks.register_views(spark, edges=path4)
    assert spark.sql("select round(sum(conn_distance(prob)), 3) as d, edge_prob(2) as p from edges").first().d == 0.904


def test_plans(spark, sf):
    scan = graphs.supplier(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_returnflag)" in scan and "CartesianProduct" not in scan
    e = graphs.supplier(spark, sf)
    sig = reliability.sampled_signatures(e, 10).cache()
    sig.count()
    plan = reliability.from_centers(sig, [0])._jdf.queryExecution().executedPlan().toString().split("InMemoryTableScan")[0]
    assert "Exchange" not in plan
    assert planner.choose(100, 1000, 50, 0.5).labels == "world" and planner.choose(10**9, 10**12, 50, 0.5).labels == "edge"


def test_workloads(spark, sf):
    e = components.largest(graphs.supplier(spark, sf)).cache()
    rep = workloads.compare("supplier", e, [2.0], r_eval=50, methods=("min", "farthest_first", "random"))
    assert {"flow", "min"} <= {x.method for x in rep.select("method").distinct().collect()}
    assert workloads.time_vs_k("supplier", e, [2], max_entries=4).filter("value = -1").count() == 1
    assert workloads.choose_by_avpr(rep).count() == 1
    assert workloads.rollup(rep).count() > 0


def test_comparison_releases_between_methods(spark, path4, monkeypatch):
    calls = []
    monkeypatch.setattr(workloads, "release", lambda s: calls.append(s), raising=False)
    rep = workloads.compare("path", path4, [2.0], r_eval=10, methods=("farthest_first",))
    assert len(calls) == rep.select("method").distinct().count() == 2


def test_prediction_covers_the_whole_graph(spark, monkeypatch):
    """Copies in a small component are pairs to be found, at every depth; k is at least the number of components."""
    big, copies = [(i, i + 1, 0.6) for i in range(1, 6)], [(20, 21, 1.0), (21, 22, 1.0), (20, 22, 1.0), (30, 31, 1.0)]
    truth = spark.createDataFrame([(n, "a") for n in (20, 21, 22)] + [(30, "b"), (31, "b")], "node long, grp string")
    got = {}
    monkeypatch.setattr(workloads, "predict", lambda name, edges, truth, depths, k, **params: got.update(edges=edges, depths=depths, k=k, **params))
    registry._predict("g", edges_of(spark, big + copies), truth)
    assert got["k"] == 3 and got["depths"] == [2, 3, 4, 6, 8] and got["r"] == "progressive"
    c = quality.pair_confusion(baselines.pivot_star(got["edges"]), truth).first()
    assert c.tp == 4 and c.fn == 0
    assert "predict_labels" in registry.QUERIES


def test_overlap_counts_frequent_grams(spark, tmp_path):
    """Groups of more than 50 copies and 3-grams that more than 50 documents have, against brute force."""
    r = random.Random(4)
    word = lambda n: " ".join(f"w{r.randint(0, 10**6)}" for _ in range(n))
    copy, notice = word(12), word(5)
    docs = [(i, copy if i < 60 else None if i == 60 else notice + " " + word(4) + (" x y" if i % 2 else "")) for i in range(120)] + [(120, copy + " and more"), (121, "one"), (122, "ONE")]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    sets = {i: {" ".join(w[j : j + 3]) for j in range(max(1, len(w) - 2))} for i, t in docs if t is not None for w in [t.lower().split()]}
    j = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a, b in itertools.combinations(sorted(sets), 2)}
    got = {(x.src, x.dst): x.prob for x in graphs.doc_overlap(spark, str(tmp_path), high=None).collect()}
    assert got == {k: round(v, 6) for k, v in j.items() if v >= 0.05} and len(got) > 60 * 59 / 2
    assert (0, 1) not in {(x.src, x.dst) for x in graphs.doc_overlap(spark, str(tmp_path)).collect()}


def test_bounds_choose_the_same_centers(spark, sf):
    """Sizes of all thresholds are counted in one pass; greedy choices by bounds equal those of the pair table."""
    from probgraph.operators import cover

    e = graphs.supplier(spark, sf)
    p = Sampled(e).ensure(40)
    of, sizes = p.agreement()
    assert (sizes[:, 16] == [(of.hits(i) >= 16).sum() for i in range(p.n)]).all() and (sizes[:, 0] == p.n).all()
    ranked = p.nodes.select("node", cover.priority("hash").alias("priority"))
    for k, low, disk in ((6, 12, 16), (30, 30, 38), (3, 1, 1)):
        assert cover._greedy_by_bounds(p, ranked, k, low, disk) == cover._greedy(p.table(min(low, disk)), ranked, k, low, disk)


def test_hops_equal_joins(spark, sf):
    """Following centers one at a time gives the connections, covers and clusters of the joins, disks within fewer hops included."""
    e = graphs.supplier(spark, sf).cache()
    ids = [x.node for x in components.nodes(e).orderBy("node").limit(9).collect()]
    for depth, disk, r in ((3, 1, 70), (2, 2, 64), (2, 0, 20)):
        fast, slow = Depth(e, depth, disk).ensure(r), Depth(e, depth, disk, most_bytes=0).ensure(r)
        assert fast.hops is not None and slow.hops is None
        assert rows(fast.connections(ids, 0)) == rows(slow.connections(ids, 0))
        for k, q in ((5, 0.4), (40, 0.7)):
            a, b = (threshold_cover(p, k, q, abort=False) for p in (fast, slow))
            assert (a.centers, a.uncovered) == (b.centers, b.uncovered) and rows(a.assignment) == rows(b.assignment)
    again = Depth(e, 3, like=fast).ensure(20)
    assert again.r == 20 and again.masked is fast.masked and rows(again.connections(ids, 0)) == rows(Depth(e, 3, most_bytes=0).ensure(20).connections(ids, 0))


def test_overlap_by_blocks(spark, monkeypatch):
    """However small the blocks that go to the tasks are, each pair is counted once, and no table of pairs is formed."""
    monkeypatch.setattr(graphs, "pairs", None)
    r = random.Random(7)
    sets = {i: set(r.sample(range(40 if i % 3 else 200), r.randint(1, 25))) for i in range(60)}
    given = spark.createDataFrame([(i, sorted(s)) for i, s in sets.items()], "doc_id long, g array<long>")
    want = {(a, b): x for a, b in itertools.combinations(sorted(sets), 2) if (x := len(sets[a] & sets[b]) / len(sets[a] | sets[b])) >= 0.05}
    for most in (150, 10**6):
        found = graphs._met(given, given.select("doc_id", F.size("g").alias("n")), 0.05, most).collect()
        assert {(x.src, x.dst): x.p for x in found} == want and len(found) == len(want)


def test_flow_is_bisected_to_each_k(path4, monkeypatch):
    asked = []
    monkeypatch.setattr(workloads, "run_method", lambda method, edges, k, seed: edges)
    monkeypatch.setattr(baselines, "markov_flow_for_k", lambda edges, k, **params: asked.append(k) or (2.0, edges))
    assert workloads.time_vs_k("path", path4, [2, 3]).count() == 6 and asked == [2, 3]
