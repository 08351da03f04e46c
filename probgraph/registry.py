"""Registered queries of the graph library, with their DuckDB SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probgraph.functions import edge_prob, harmonic, register
from probgraph.operators import baselines, components, quality, reliability, worlds
from probgraph.operators.cluster import cluster_avg, cluster_min
from probgraph.operators.cover import Depth, Sampled, threshold_cover
from probgraph.plans import guess, workloads
from probgraph.runtime import cut
from probgraph.sources import graphs, table
from probgraph.streaming import interactions

QUERIES: dict = {}
ORACLE: dict = {}
R, SEED = 50, 42


def query(sql: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE[f.__name__] = sql
        return f

    return put


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """k suppliers to whom all others of the collaboration graph are as strongly connected as can be."""
    return cluster_min(components.largest(graphs.supplier(spark, sf)), 3, sampling=100).assignment


# --- SQL parts -------------------------------------------------------------------------------------------------------

GS = graphs.SUPPLIER_SQL
NODES = "v as (select distinct unnest([src, dst]) as node from e)"


def live_sql(r: int = R, seed: int = SEED) -> str:
    return f"live as (select w, src, dst from e, range({r}) t(w) where ('0x' || substr(md5('{seed}|' || w || '|' || src || '|' || dst), 1, 8))::bigint < prob * 4294967296.0)"


#: Needs e, v and live; gives lab(w, node, label).
LABELS = """adj as (select w, src as a, dst as b from live union all select w, dst, src from live),
reach(w, node, label) as (select w, node, node from v, (select distinct w from live) union select r.w, adj.b, r.label from reach r join adj on adj.w = r.w and adj.a = r.node where r.label < adj.b),
"""


def labels_sql(r: int = R, graph: str = GS) -> str:
    """lab: labels of all nodes in r worlds. A node's label is the least node that reaches it, walking from least nodes up through larger ones and back."""
    return f"""with recursive {graph}, {NODES}, {live_sql(r)},
adj as (select w, src as a, dst as b from live union all select w, dst, src from live),
reach(w, node, other) as (select w, node, node from v, range({r}) t(w) union select r.w, r.node, adj.b from reach r join adj on adj.w = r.w and adj.a = r.other),
lab as (select w, node, min(other) as label from reach group by all)"""


def sure_labels(graph: str) -> str:
    return f"""with recursive {graph}, {NODES}, adj as (select src as a, dst as b from e union all select dst, src from e),
prop(i, node, label) as (select 0, node, node from v union all
  (with c as (select * from prop) select any_value(c.i) + 1, c.node, least(any_value(c.label), coalesce(min(d.label), any_value(c.label))) from c left join adj on adj.a = c.node left join c d on d.node = adj.b where c.i < 40 group by c.node)),
lab as (select node, min(label) as label from prop group by node)"""


HITS = "h as (select a.node as u, b.node as v, count(*) as hits from lab a join lab b on a.w = b.w and a.label = b.label group by all)"


def supplier_graph(spark: SparkSession, sf: str) -> DataFrame:
    return cut(graphs.supplier(spark, sf))


# --- graphs ----------------------------------------------------------------------------------------------------------


@query(f"with {graphs.SUPPLIER_COUNTS_SQL} select src, dst, x, round(1 - exp(-x / 2.0), 6) as prob from x")
def prob_model(spark, sf):
    return graphs.supplier_counts(spark, sf).withColumn("prob", F.round(edge_prob(F.col("x")), 6))


def _graph(name: str):
    def f(spark, sf):
        return graphs.BUILDERS[name](spark, sf)

    f.__name__ = f"graph_{name}"
    query(f"with {graphs.SQL[name]} select src, dst, prob from e")(f)


for _name in graphs.BUILDERS:
    _graph(_name)


def _component_sql(graph: str) -> str:
    return f"with recursive {graph}, {NODES}, adj as (select src as a, dst as b from e union all select dst, src from e), reach(node, other) as (select node, node from v union select r.node, adj.b from reach r join adj on adj.a = r.other), lab as (select node, min(other) as label from reach group by node)"


@query(
    " union all ".join(
        f"(select '{n}' as graph, * from ({_component_sql(graphs.SQL[n])}, sizes as (select label, count(*) as n from lab group by label), ms as (select label, count(*) as m from e join lab on src = node group by label), t as (select * from sizes join ms using (label)) select sum(n)::bigint as nodes, sum(m)::bigint as edges, count(*) as components, max_by(n, n * 1000000000 - label) as largest_nodes, max_by(m, n * 1000000000 - label) as largest_edges from t))"
        for n in ("supplier", "nation", "knn")
    )
)
def graph_summary(spark, sf):
    out = None
    for n in ("supplier", "nation", "knn"):
        s = components.summary(graphs.BUILDERS[n](spark, sf)).select(F.lit(n).alias("graph"), "*")
        out = s if out is None else out.unionByName(s)
    return out


@query(f"{_component_sql(graphs.DOC_SQL)}, t as (select label from lab group by label order by count(*) desc, label limit 1) select src, dst, prob from e join lab on src = node where label = (select label from t)")
def largest_component(spark, sf):
    return components.largest(cut(graphs.doc_overlap(spark, sf)))


@query("select * from (values (1::bigint, 0.393469::double), (2, 0.632121), (3, 0.77687), (5, 0.917915)) t(x, prob)")
def prob_table(spark, sf):
    return workloads.prob_table(spark)


# --- worlds and reliability -----------------------------------------------------------------------------------------


@query(f"with {GS}, {live_sql()} select w::int as world, count(*) as alive from live group by w")
def worlds_sample(spark, sf):
    return worlds.sample(graphs.supplier(spark, sf), R).groupBy("world").agg(F.count("*").alias("alive"))


@query(f"with {GS}, {live_sql(100)} select w::int as world, src, dst from live")
def worlds_masks(spark, sf):
    return worlds.from_masks(worlds.masks(graphs.supplier(spark, sf), 100), 100)


@query(f"{labels_sql()} select w::int as world, node, label from lab")
def world_components(spark, sf):
    e = supplier_graph(spark, sf)
    return components.full(components.label(worlds.sample(e, R)), components.nodes(e), R)


@query(f"{labels_sql()} select w::int as world, node, label from lab")
def world_components_stars(spark, sf):
    e = supplier_graph(spark, sf)
    return components.full(components.label(worlds.sample(e, R), "edge"), components.nodes(e), R)


@query(f"{labels_sql(20)} select w::int as world, node, label from lab")
def world_components_masks(spark, sf):
    e = supplier_graph(spark, sf)
    return components.by_mask(worlds.masks(e, 20), components.nodes(e), 20).select(F.posexplode("labels").alias("world", "label"), "node").select("world", "node", "label")


@query(f"{labels_sql()}, {HITS} select src as u, dst as v, coalesce(hits, 0) as hits, {R} as r, round(coalesce(hits, 0) / {R}.0::double, 6) as p_est from e left join h on src = u and dst = v")
def conn_pairs_mc(spark, sf):
    e = supplier_graph(spark, sf)
    sig = reliability.sampled_signatures(e, R)
    return reliability.estimate_pairs(sig, e.select(F.col("src").alias("u"), F.col("dst").alias("v")), R).withColumn("p_est", F.round("p_est", 6))


@query(f"{labels_sql()}, {HITS}, c as (select node from v order by node limit 5) select u as center, v as node, hits from h where u in (select node from c)")
def conn_from_center(spark, sf):
    e = supplier_graph(spark, sf)
    first = [x.node for x in components.nodes(e).orderBy("node").limit(5).collect()]
    return reliability.from_centers(cut(reliability.sampled_signatures(e, R)), first, 1)


@query(f"{labels_sql(200)}, {HITS}, p as (select min(node) as s, max(node) as t from v) select s as u, t as v, coalesce(max(hits), 0) as hits, 200 as r, round(coalesce(max(hits), 0) / 200.0::double, 6) as p_est from p left join h on u = s and v = t group by s, t")
def two_terminal(spark, sf):
    e = supplier_graph(spark, sf)
    s, t = e.select(F.explode(F.array("src", "dst")).alias("n")).agg(F.min("n"), F.max("n")).first()
    return reliability.two_terminal(e, s, t, 200).select("u", "v", "hits", "r", F.round("p_est", 6).alias("p_est"))


@query(f"{labels_sql()}, c as (select node from v order by node limit 3) select count(*) as hits from (select w from lab where node in (select node from c) group by w having min(label) = max(label))")
def set_reliability(spark, sf):
    e = supplier_graph(spark, sf)
    members = [x.node for x in components.nodes(e).orderBy("node").limit(3).collect()]
    return reliability.set_reliability(components.full(components.label(worlds.sample(e, R)), components.nodes(e), R), members, R).select("hits")


@query(f"{labels_sql()}, {HITS} select v as node, hits from h where u = (select min(node) from v) and v <> u order by hits desc, v limit 10")
def nearest_k(spark, sf):
    e = supplier_graph(spark, sf)
    s = e.agg(F.min("src")).first()[0]
    return reliability.nearest(cut(reliability.sampled_signatures(e, R)), s, 10, R).select("node", "hits")


@query(f"{labels_sql()}, z as (select w, label, count(*) as n from lab group by all), t as (select node, sum(n) as total from lab join z using (w, label) group by node), m as (select count(*) as n from v) select node, round(total / (n * {R})::double, 6) as value from t, m order by total desc, node limit 1")
def best_source_avg(spark, sf):
    e = supplier_graph(spark, sf)
    return reliability.best_source(components.full(components.label(worlds.sample(e, R)), components.nodes(e), R), R).withColumn("value", F.round("value", 6))


@query(f"{labels_sql()}, {HITS}, m as (select count(*) as n from v), l as (select u, case when count(*) < any_value(n) then 0 else min(hits) end as hits from h, m group by u) select u as node, round(hits / {R}.0::double, 6) as value from l order by hits desc, u limit 1")
def best_source_min(spark, sf):
    e = supplier_graph(spark, sf)
    return reliability.best_source(None, R, "min", cut(reliability.sampled_signatures(e, R))).withColumn("value", F.round("value", 6))


@query(
    f"""{labels_sql()}, r0 as (select node, sum(n) as gain from lab join (select w, label, count(*) as n from lab group by all) using (w, label) group by node order by gain desc, node limit 1),
h0 as (select w, label from lab where node = (select node from r0)), r1 as (select node, sum(n) as gain from lab join (select w, label, count(*) as n from lab anti join h0 using (w, label) group by all) using (w, label) group by node order by gain desc, node limit 1),
h1 as (select * from h0 union select w, label from lab where node = (select node from r1)), r2 as (select node, sum(n) as gain from lab join (select w, label, count(*) as n from lab anti join h1 using (w, label) group by all) using (w, label) group by node order by gain desc, node limit 1)
select 0 as rank, node, round(gain / {R}.0::double, 6) as gain from r0 union all select 1, node, round(gain / {R}.0::double, 6) from r1 union all select 2, node, round(gain / {R}.0::double, 6) from r2"""
)
def greedy_spread(spark, sf):
    e = supplier_graph(spark, sf)
    return reliability.greedy_spread(components.full(components.label(worlds.sample(e, R)), components.nodes(e), R), 3, R).withColumn("gain", F.round("gain", 6))


_HOPS = f"""with recursive {GS}, {NODES}, {live_sql()}, adj as (select w, src as a, dst as b from live union all select w, dst, src from live),
walk(i, w, center, node) as (select 0, w, node, node from (select node from v order by node limit 4), range({R}) t(w) union select i + 1, r.w, center, adj.b from walk r join adj on adj.w = r.w and adj.a = r.node where i < 3),
hop as (select w, center, node, min(i) as i from walk group by all)"""


@query(f"{_HOPS} select center, node, count(*) as hits, count(*) filter (where i <= 2) as disk_hits from hop group by all")
def depth_conn_mc(spark, sf):
    e = supplier_graph(spark, sf)
    some = components.nodes(e).orderBy("node").limit(4)
    return reliability.from_centers_depth(worlds.masks(e, R), some, R, 3, 2)


#: Exact connection in every world of every region. mask = which of the (at most 10) edges of a region are alive.
def _exact_sql(depth: int | None) -> str:
    limit = f"where i < {depth}" if depth else ""
    i0, i1 = ("0 as i, ", "i + 1, ") if depth else ("", "")
    return f"""with recursive {graphs.NATION_SQL}, {NODES}, g as (select e.*, n_regionkey as reg, row_number() over (partition by n_regionkey order by src, dst) - 1 as bit, count(*) over (partition by n_regionkey) as m from e join nation on src = n_nationkey),
w as (select distinct reg, mask from g, range(1024) t(mask) where mask < (1 << m::int)),
p as (select w.reg, mask, product(case when (mask >> bit::int) & 1 = 1 then prob else 1 - prob end) as weight from w join g on g.reg = w.reg group by all),
adj as (select w.reg, mask, src as a, dst as b from w join g on g.reg = w.reg where (mask >> bit::int) & 1 = 1 union all select w.reg, mask, dst, src from w join g on g.reg = w.reg where (mask >> bit::int) & 1 = 1),
walk as (select {i0}reg, mask, a as u, a as v from (select distinct reg, mask, a from adj) union select {i1}r.reg, r.mask, u, adj.b from walk r join adj on adj.reg = r.reg and adj.mask = r.mask and adj.a = r.v {limit}),
ex as (select u, v, sum(weight) as prob from (select distinct reg, mask, u, v from walk) join p using (reg, mask) where u < v group by all)"""


@query(f"{_exact_sql(None)} select u, v, round(prob, 6) as prob from ex")
def conn_exact(spark, sf):
    return reliability.exact_pairs(graphs.nation(spark, sf)).withColumn("prob", F.round("prob", 6))


@query(f"{_exact_sql(2)} select u, v, round(prob, 6) as prob from ex")
def conn_exact_depth2(spark, sf):
    return reliability.exact_pairs(graphs.nation(spark, sf), 2).withColumn("prob", F.round("prob", 6))


@query(f"{_exact_sql(None)}, b as (select u, v, prob from ex union all select v, u, prob from ex) select p.u, p.v, q.v as z, round(o.prob - p.prob * q.prob, 5) + 0.0::double as slack from b p join b q on p.v = q.u and p.u < q.v join b o on o.u = p.u and o.v = q.v")
def triangle_slack(spark, sf):
    return reliability.triangle_slack(cut(reliability.exact_pairs(graphs.nation(spark, sf)))).withColumn("slack", F.round("slack", 5) + F.lit(0.0))


def _monotone_sql() -> str:
    """Exact probabilities twice: without the first edge, and with it for certain."""
    first = "(select src from e order by src, dst limit 1) and {t}dst = (select dst from e order by src, dst limit 1)"
    parts = []
    for name, keep, prob in (("absent", "not (src = " + first.format(t="") + ")", "prob"), ("present", "true", "case when src = " + first.format(t="") + " then 1.0 else prob end")):
        parts.append(f"""g_{name} as (select src, dst, {prob} as prob, n_regionkey as reg, row_number() over (partition by n_regionkey order by src, dst) - 1 as bit, count(*) over (partition by n_regionkey) as m from e join nation on src = n_nationkey where {keep}),
w_{name} as (select distinct reg, mask from g_{name}, range(1024) t(mask) where mask < (1 << m::int)),
p_{name} as (select w.reg, mask, product(case when (mask >> bit::int) & 1 = 1 then prob else 1 - prob end) as weight from w_{name} w join g_{name} g on g.reg = w.reg group by all),
a_{name} as (select w.reg, mask, src as a, dst as b from w_{name} w join g_{name} g on g.reg = w.reg where (mask >> bit::int) & 1 = 1 union all select w.reg, mask, dst, src from w_{name} w join g_{name} g on g.reg = w.reg where (mask >> bit::int) & 1 = 1),
k_{name} as (select reg, mask, a as u, a as v from (select distinct reg, mask, a from a_{name}) union select r.reg, r.mask, u, x.b from k_{name} r join a_{name} x on x.reg = r.reg and x.mask = r.mask and x.a = r.v),
x_{name} as (select u, v, sum(weight) as prob from (select distinct reg, mask, u, v from k_{name}) join p_{name} using (reg, mask) where u < v group by all)""")
    return f"with recursive {graphs.NATION_SQL}, {', '.join(parts)} select u, v, round(coalesce(x_absent.prob, 0), 6) as absent, round(coalesce(x_present.prob, 0), 6) as present from x_present full join x_absent using (u, v)"


@query(_monotone_sql())
def edge_monotone(spark, sf):
    e = cut(graphs.nation(spark, sf))
    s, d, _ = e.orderBy("src", "dst").first()
    return reliability.edge_monotone(e, s, d).select("u", "v", F.round("absent", 6).alias("absent"), F.round("present", 6).alias("present"))


@query(f"with {GS} select round(sum(ln(least(prob, 1 - prob))), 4) as log_p from e where prob < 1")
def unlikely_world_log(spark, sf):
    return reliability.log_unlikely_world(graphs.supplier(spark, sf)).select(F.round("log_p", 4).alias("log_p"))


@query("""with g as (select * from (values (100, 1.0::double, 0.5::double), (100, 0.5, 0.5), (1153, 0.3, 0.1), (11985, 0.1, 0.1)) t(n, q, eps)), h as (select n, (select sum(1.0::double / i) from range(1, n + 1) t(i)) as hn from g group by n)
select n::int as n, q, eps, ceil(3 * ln(2 / 0.05::double) / (eps * eps * q))::bigint as pair, ceil(12 / (q * eps * eps) * ln(2 * pow(n::double, 3) * (1 + floor(ln(1e4::double) / ln(1.1::double)))))::bigint as for_min, ceil(12 / (pow(q, 3) * eps * eps) * ln(2 * pow(n::double, 3) * (1 + floor(ln(hn / 1e-4::double) / ln(1.1::double)))))::bigint as for_avg from g join h using (n)""")
def sample_size_rules(spark, sf):
    register(spark)
    g = spark.createDataFrame([(100, 1.0, 0.5), (100, 0.5, 0.5), (1153, 0.3, 0.1), (11985, 0.1, 0.1)], "n int, q double, eps double")
    return g.selectExpr("n", "q", "eps", "samples_pair(eps, 0.05D, q) as pair", "samples_min(n, q, eps, 0.1D, 1e-4D) as for_min", "samples_avg(n, q, eps, 0.1D, 1e-4D) as for_avg")


# --- covers and clusterings -----------------------------------------------------------------------------------------


def _near(thr: str) -> str:
    return f"nb as (select u as node, list(v) as l from h where hits >= {thr} group by u)"


def _best(centers: str, least: int) -> str:
    return f"""k as (select unnest({centers}) as center, generate_subscripts({centers}, 1) as rank),
b as (select v as node, arg_max(center, (case when center = v then 1 else 0 end, hits, -rank)) as center, arg_max(hits, (case when center = v then 1 else 0 end, hits, -rank)) as hits from k join h on u = center group by v),
z as (select v.node, case when hits >= {least} then center end as center, round(case when hits >= {least} then hits / {R}.0::double else 0 end, 6) as p_est, coalesce(hits >= {least}, false) as covered from v left join b using (node))"""


def _cover_sql(q: float, k: int) -> str:
    least = -(-int(round(q * R * 1000)) // 1000)
    return f"""{labels_sql()}, {HITS}, {_near(str(least))},
g(i, left_, centers) as (select 0, (select list(node) from v), []::bigint[] union all select i + 1, list_filter(left_, lambda x: not list_contains(nb.l, x)), list_append(centers, nb.node) from g join nb on nb.node = list_min(left_) where i < {k} and len(left_) > 0),
o as (select centers as first_, list_sort((select list(node) from v)) as every from g order by i desc limit 1),
f as (select list_concat(first_, list_slice(list_filter(every, lambda x: not list_contains(first_, x)), 1, {k} - len(first_))) as centers from o), {_best('(select centers from f)', least)} select node, center, p_est, covered from z"""


@query(_cover_sql(0.3, 10))
def cover_q(spark, sf):
    p = Sampled(supplier_graph(spark, sf), SEED).ensure(R)
    return threshold_cover(p, min(10, p.n), 0.3, order="id", pad="first").assignment.withColumn("p_est", F.round("p_est", 6))


@query(_cover_sql(0.6, 5))
def cover_partial(spark, sf):
    p = Sampled(supplier_graph(spark, sf), SEED).ensure(R)
    return threshold_cover(p, min(5, p.n), 0.6, order="id", pad="first").assignment.withColumn("p_est", F.round("p_est", 6))


def _alpha_sql(q: float, q_disk: float, k: int) -> str:
    low, disk = round(q * R), round(q_disk * R)
    return f"""{labels_sql()}, {HITS}, {_near(str(low))}, dk as (select u as node, list(v) as d from h where hits >= {disk} group by u), both_ as (select node, l, d from nb join dk using (node)),
nbs as (select list(struct_pack(node := node, l := l, d := d) order by node) as a from both_),
g(i, left_, centers) as (select 0, (select list(node) from v), []::bigint[] union all
  select i + 1, list_filter(left_, lambda x: not list_contains(c.l, x)), list_append(centers, c.node) from (select i, left_, centers, list_reduce(list_transform(list_filter(a, lambda s: list_contains(left_, s.node)), lambda s: struct_pack(node := s.node, l := s.l, n := len(list_intersect(s.d, left_)))), lambda s, t: case when t.n > s.n then t else s end) as c from g, nbs where i < {k} and len(left_) > 0)),
o as (select centers as first_, list_sort((select list(node) from v)) as every from g order by i desc limit 1),
f as (select list_concat(first_, list_slice(list_filter(every, lambda x: not list_contains(first_, x)), 1, {k} - len(first_))) as centers from o), {_best('(select centers from f)', low)} select node, center, p_est, covered from z"""


@query(_alpha_sql(0.5, 0.6, 4))
def cover_alpha(spark, sf):
    p = Sampled(supplier_graph(spark, sf), SEED).ensure(R)
    c = threshold_cover(p, min(4, p.n), 0.5, None, 0.6, order="id", pad="first")
    return c.assignment.withColumn("p_est", F.round("p_est", 6))


@query()
def cover_alpha_some(spark, sf):
    p = Sampled(supplier_graph(spark, sf), SEED).ensure(R)
    return threshold_cover(p, min(4, p.n), 0.5, 8, 0.6).assignment


@query()
def cover_depth(spark, sf):
    p = Depth(supplier_graph(spark, sf), 3, 2, SEED).ensure(R)
    return threshold_cover(p, min(5, p.n), 0.3, 1, order="id", pad="first").assignment


def _min_sql(k: int, gamma: float = 0.1) -> str:
    return f"""{labels_sql()}, {HITS}, qs as (select j, ceil(pow(1 + {gamma}::double, -j) * {R} - 1e-9)::bigint as least from range(0, 100) t(j)),
few as (select distinct least from qs), nb as (select least, u as node, list(v) as l from h join few on hits >= least group by least, u),
g(least, i, left_, centers) as (select least, 0, (select list(node) from v), []::bigint[] from few union all select g.least, i + 1, list_filter(left_, lambda x: not list_contains(nb.l, x)), list_append(centers, nb.node) from g join nb on nb.least = g.least and nb.node = list_min(left_) where i < {k} and len(left_) > 0),
o as (select least, arg_max(centers, i) as first_, arg_max(len(left_), i) as miss, list_sort((select list(node) from v)) as every from g group by least),
f as (select list_concat(first_, list_slice(list_filter(every, lambda x: not list_contains(first_, x)), 1, {k} - len(first_))) as centers from o where miss = 0 order by least desc limit 1), {_best('(select centers from f)', 0)} select node, center, p_est, covered from z"""


@query(_min_sql(8))
def min_cluster(spark, sf):
    e = supplier_graph(spark, sf)
    c = cluster_min(e, 8, schedule="geometric", sampling=R, order="id", pad="first", seed=SEED)
    return c.assignment.withColumn("p_est", F.round("p_est", 6))


def _schedule_sql(k: int, avg: bool, gamma: float = 0.1, floor: float = 1e-4) -> str:
    """The practical guesses and the bisection after them, over the covers of all thresholds of R worlds (there are only R). avg: the best mean of all attempts, later ones first; else the last full cover."""
    qs = ", ".join(f"({i}, {q!r}::double)" for i, q in enumerate(guess.practical(gamma, floor)))
    need = lambda q: f"greatest(0, ceil({q} * {R} - 1e-9))::bigint"
    pick = "select centers from tried join f using (least) order by phi desc, step desc limit 1" if avg else "select centers from tried join f using (least) where miss = 0 order by q desc limit 1"
    return f"""{labels_sql()}, {HITS}, few as (select unnest(range(1, {R} + 1))::bigint as least), nb as (select least, u as node, list(v) as l from h join few on hits >= least group by least, u),
g(least, i, left_, centers) as (select least, 0, (select list(node) from v), []::bigint[] from few union all select g.least, i + 1, list_filter(left_, lambda x: not list_contains(nb.l, x)), list_append(centers, nb.node) from g join nb on nb.least = g.least and nb.node = list_min(left_) where i < {k} and len(left_) > 0),
o as (select least, arg_max(centers, i) as first_, arg_max(len(left_), i) as miss, list_sort((select list(node) from v)) as every from g group by least),
p as (select least, miss, list_concat(first_, list_slice(list_filter(every, lambda x: not list_contains(first_, x)), 1, {k} - len(first_))) as centers from o),
pc as (select least, unnest(centers) as center from p), pv as (select least, v as node, max(case when center = v then {R} else hits end) as hits from pc join h on u = center group by all),
ph as (select least, sum(hits) filter (where hits >= least) as phi from pv group by least), f as (select p.*, coalesce(phi, 0) as phi from p left join ph using (least)),
sched(i, q) as (values {qs}), sc as (select i, q, {need('q')} as least from sched), fst as (select min(i) as i from sc join f using (least) where miss = 0),
bis(step, low, high, q, least) as (select 100, a.q, coalesce(b.q, 1.0::double), null::double, null::bigint from sc a left join sc b on b.i = a.i - 1 where a.i = (select i from fst)
  union all select step + 1, case when f.miss = 0 then (low + high) / 2 else low end, case when f.miss = 0 then high else (low + high) / 2 end, (low + high) / 2, f.least from bis join f on f.least = {need('(low + high) / 2')} where low / high <= 1 - {gamma}::double),
tried as (select i as step, q, least from sc where i <= (select i from fst) union all select step, q, least from bis where least is not null),
ch as ({pick}), {_best('(select centers from ch)', 0)} select node, coalesce(center, (select centers[1] from ch)) as center, p_est, true as covered from z"""


@query(_schedule_sql(8, False))
def min_cluster_bisect(spark, sf):
    c = cluster_min(supplier_graph(spark, sf), 8, sampling=R, order="id", pad="first", seed=SEED)
    return c.assignment.withColumn("p_est", F.round("p_est", 6)).withColumn("covered", F.lit(True))


@query()
def min_cluster_progressive(spark, sf):
    return cluster_min(supplier_graph(spark, sf), 5, r_max=400).trace_df(spark)


@query()
def min_cluster_exact(spark, sf):
    """Exact probabilities on a small graph: the guarantee holds for every guess."""
    return cluster_min(graphs.nation(spark, sf), 5, schedule="geometric", exact=True, order="id", pad="first").assignment


def min_cluster_theory(spark, sf):
    """As many worlds at each guess as the guarantee asks for, thresholds lowered by half of the relative error."""
    return cluster_min(graphs.nation(spark, sf), 6, schedule="geometric", sampling="theory", order="id", pad="first").trace_df(spark).drop("millis")


def avg_cluster_theory_sampled(spark, sf):
    """As many worlds at each guess as the guarantee of the mean asks for."""
    return cluster_avg(graphs.nation(spark, sf), 6, mode="theory", sampling="theory", order="id", pad="first").trace_df(spark).drop("millis")


def avg_cluster_depth_theory(spark, sf):
    """Mean connection within 6 hops: all candidates, disks within 2 hops, covers at the cube of the guess."""
    return cluster_avg(supplier_graph(spark, sf), 8, mode="theory", depth=6, sampling=R, order="id", pad="first").assignment


@query()
def min_cluster_depth(spark, sf):
    return cluster_min(supplier_graph(spark, sf), 10, depth=4, sampling=R).assignment


def _avg_sql(k: int, gamma: float = 0.1, guesses: int = 14) -> str:
    """All guesses' covers (at the cube, disks at the guess, every uncovered node a candidate), then the rounds: one goes on while its cube can beat the best mean so far."""
    return f"""{labels_sql()}, {HITS}, qs as (select j, pow(1 + {gamma}::double, -j) as q from range(0, {guesses}) t(j)),
th as (select j, q, greatest(0, ceil(q * q * q * {R} - 1e-9))::bigint as low, greatest(0, ceil(q * {R} - 1e-9))::bigint as disk from qs),
nb as (select j, u as node, list(v) filter (where hits >= low) as l, list(v) filter (where hits >= disk) as d from h, th group by j, u),
nbs as (select j, list(struct_pack(node := node, l := l, d := d) order by node) as a from nb group by j),
g(j, i, left_, centers) as (select j, 0, (select list(node) from v), []::bigint[] from qs union all
  select j, i + 1, list_filter(left_, lambda x: not list_contains(c.l, x)), list_append(centers, c.node) from (select g.j, i, left_, centers, list_reduce(list_transform(list_filter(a, lambda s: list_contains(left_, s.node)), lambda s: struct_pack(node := s.node, l := s.l, n := len(list_intersect(s.d, left_)))), lambda s, t: case when t.n > s.n then t else s end) as c from g join nbs using (j) where i < {k} and len(left_) > 0)),
o as (select j, arg_max(centers, i) as first_, list_sort((select list(node) from v)) as every from g group by j),
p as (select j, list_concat(first_, list_slice(list_filter(every, lambda x: not list_contains(first_, x)), 1, {k} - len(first_))) as centers from o),
pv as (select j, v as node, max(case when center = v then {R} else hits end) as hits from (select j, unnest(centers) as center from p) join h on u = center group by all),
ph as (select j, q, coalesce(sum(hits) filter (where hits >= low), 0) / ({R}.0::double * (select count(*) from v)) as phi from th left join pv using (j) group by j, q),
lp(j, best, pick) as (select 0, phi, 0 from ph where j = 0 union all select ph.j, greatest(best, phi), case when phi >= best then ph.j else pick end from lp join ph on ph.j = lp.j + 1 where ph.q * ph.q * ph.q >= best),
ch as (select centers from p where j = (select arg_max(pick, j) from lp)), {_best('(select centers from ch)', 0)} select node, coalesce(center, (select centers[1] from ch)) as center, p_est, true as covered from z"""


@query(_avg_sql(8))
def avg_cluster(spark, sf):
    return cluster_avg(supplier_graph(spark, sf), 8, mode="theory", sampling=R, order="id", pad="first", seed=SEED).assignment.withColumn("p_est", F.round("p_est", 6))


@query(_schedule_sql(8, True))
def avg_cluster_practical(spark, sf):
    return cluster_avg(supplier_graph(spark, sf), 8, sampling=R, order="id", pad="first", seed=SEED).assignment.withColumn("p_est", F.round("p_est", 6))


@query()
def avg_cluster_depth(spark, sf):
    return cluster_avg(supplier_graph(spark, sf), 10, depth=4, sampling=R).assignment


@query(
    f"""{labels_sql()}, {HITS}, few as (select unnest(range(5, {R} + 1, 5)) as least), nb as (select least, u as node, list(v) as l from h join few on hits >= least group by least, u),
g(least, i, left_, centers) as (select least, 0, (select list(node) from v), []::bigint[] from few union all select g.least, i + 1, list_filter(left_, lambda x: not list_contains(nb.l, x)), list_append(centers, nb.node) from g join nb on nb.least = g.least and nb.node = list_min(left_) where i < 8 and len(left_) > 0)
select round(least / {R}.0::double, 6) as q, arg_max(len(left_), i)::bigint as uncovered from g group by least"""
)
def coverage_curve(spark, sf):
    p = Sampled(supplier_graph(spark, sf), SEED).ensure(R)
    rows = [(least / R, threshold_cover(p, min(8, p.n), least / R, order="id", assign=False).uncovered) for least in range(5, R + 1, 5)]
    return spark.createDataFrame(rows, "q double, uncovered long").withColumn("q", F.round("q", 6))


_FIXED = "fx as (select node, min(node) over (partition by node % 10) as center from v)"


@query(f"{labels_sql()}, {HITS}, {_FIXED}, p as (select coalesce(hits, 0) / {R}.0::double as p_est from fx a left join h on u = a.node and v = center), r as (select p_est, row_number() over (order by p_est) as i, count(*) over () as n from p) select round(max(p_est * (n - i + 1) / n), 6) as value, round(avg(p_est), 6) as mean from r")
def avg_existence_window(spark, sf):
    e = supplier_graph(spark, sf)
    a = quality.to_centers(_fixed(e), cut(reliability.sampled_signatures(e, R)), R)
    return reliability.coverage_window(a).select(F.round("value", 6).alias("value"), F.round("mean", 6).alias("mean"))


def _fixed(e: DataFrame) -> DataFrame:
    """A clustering by rule, to hold measures against SQL: the node's last digit, the least node as center."""
    n = components.nodes(e)
    return n.join(n.groupBy((F.col("node") % 10).alias("d")).agg(F.min("node").alias("center")), F.col("node") % 10 == F.col("d")).select("node", "center")


@query(f"{labels_sql()}, {HITS}, {_FIXED} select round(min(coalesce(hits, 0) / {R}.0::double), 6) as p_min, round(avg(coalesce(hits, 0) / {R}.0::double), 6) as p_avg from fx a left join h on u = a.node and v = center")
def p_min_avg(spark, sf):
    e = supplier_graph(spark, sf)
    return quality.p_min_avg(_fixed(e), cut(reliability.sampled_signatures(e, R)), R).select(F.round("p_min", 6).alias("p_min"), F.round("p_avg", 6).alias("p_avg"))


@query(
    f"{labels_sql()}, {HITS}, {_FIXED}, p as (select x.node as u, y.node as v, x.center = y.center as same from fx x join fx y on x.node < y.node), z as (select same, coalesce(hits, 0) / {R}.0::double as p from p left join h using (u, v)) select round(avg(p) filter (where same), 6) as inner_avpr, round(avg(p) filter (where not same), 6) as outer_avpr from z"
)
def avpr(spark, sf):
    e = supplier_graph(spark, sf)
    lab = cut(components.full(components.label(worlds.sample(e, R)), components.nodes(e), R))
    return quality.avpr(_fixed(e), lab, R).select(F.round("inner_avpr", 6).alias("inner_avpr"), F.round("outer_avpr", 6).alias("outer_avpr"))


_TRUTH = "t as (select doc_id as node, md5(text) as grp from documents union select doc_id, lang || '|' || source from documents)"


def _truth(spark, sf):
    d = table(spark, sf, "documents", ["doc_id", "text", "lang", "source"])
    return d.select(F.col("doc_id").alias("node"), F.md5("text").alias("grp")).unionByName(d.select(F.col("doc_id").alias("node"), F.concat_ws("|", "lang", "source").alias("grp"))).distinct()


@query(
    f"with {_TRUTH}, a as (select doc_id as node, doc_id % 50 as center from documents), p as (select distinct x.node as u, y.node as v from t x join t y on x.grp = y.grp and x.node < y.node), z as (select count(*) as pos, count(*) filter (where u % 50 = v % 50) as tp from p), s as (select sum(s)::bigint as n, sum(s * (s - 1) / 2)::bigint as tog from (select count(*) as s from a group by center)) select tp, tog - tp as fp, pos - tp as fn, (n * (n - 1) / 2)::bigint - tog - pos + tp as tn, round(tp / pos::double, 6) as tpr, round((tog - tp) / ((n * (n - 1) / 2) - pos)::double, 6) as fpr from z, s"
)
def pair_confusion(spark, sf):
    t = cut(_truth(spark, sf))
    a = t.select("node").distinct().select("node", (F.col("node") % 50).alias("center"))
    return quality.pair_confusion(a, t).withColumn("tpr", F.round("tpr", 6)).withColumn("fpr", F.round("fpr", 6))


@query(f"with {GS}, {NODES}, {_FIXED}, i as (select sum(s * (s - 1) / 2) as inside from (select count(*) as s from fx group by center)), c as (select sum(case when p.center = q.center then -prob else prob end) as cost from e join fx p on src = p.node join fx q on dst = q.node) select round(inside + cost, 4) as edit_distance from i, c")
def edit_distance(spark, sf):
    e = supplier_graph(spark, sf)
    return quality.expected_edit_distance(_fixed(e), e).select(F.round("edit_distance", 4).alias("edit_distance"))


@query(f"with {GS}, {NODES}, {_FIXED}, s as (select count(*) as s from fx group by center) select count(*) as clusters, min(s) as least, round(avg(s), 6) as mean, max(s) as largest, 0::bigint as outliers from s")
def cluster_shape(spark, sf):
    return quality.shape(_fixed(supplier_graph(spark, sf))).withColumn("mean", F.round("mean", 6))


# --- baselines ------------------------------------------------------------------------------------------------------


@query()
def farthest_first(spark, sf):
    return baselines.farthest_first(supplier_graph(spark, sf), 10)


@query(
    f"""{labels_sql()}, {HITS}, g(i, centers) as (select 1, [(select min(node) from v)] union all select i + 1, list_append(centers, (select node from (select v.node, max(coalesce(hits, 0)) as best from v left join h on h.v = v.node and list_contains(centers, h.u) group by v.node) order by best, node limit 1)) from g where i < least(5, (select count(*) from v)))
select (generate_subscripts(centers, 1) - 1)::int as rank, unnest(centers) as center from (select centers from g order by i desc limit 1)"""
)
def farthest_by_connection(spark, sf):
    p = Sampled(supplier_graph(spark, sf), SEED).ensure(R)
    return spark.createDataFrame(list(enumerate(baselines.farthest_by_connection(p, min(5, p.n), order="id"))), "rank int, center long")


@query(
    f"""with recursive {graphs.MIXED_SQL}, {NODES}, nb as (select node, list(o) as l from (select src as node, dst as o from e where prob >= 0.5 union all select dst, src from e where prob >= 0.5 union all select node, node from v) group by node),
g(i, left_, center, got) as (select 0, (select list(node) from v), null::bigint, []::bigint[] union all select i + 1, list_filter(left_, lambda x: not list_contains(nb.l, x)), nb.node, list_intersect(nb.l, left_) from g join nb on nb.node = list_min(left_) where len(left_) > 0)
select unnest(got) as node, center from g where center is not null"""
)
def pivot_star(spark, sf):
    return baselines.pivot_star(cut(graphs.mixed(spark, sf)), order="id")


_FLOW = f"""with {GS}, {NODES}, m0 as (select src as r, dst as c, prob as x from e union all select dst, src, prob from e union all select node, node, 1 from v), m as (select r, c, x / sum(x) over (partition by c) as x from m0)"""


@query(
    f"{_FLOW}, s as (select a.r, b.c, sum(a.x * b.x) as x from m a join m b on a.c = b.r group by all), f as (select r, c, pow(x, 2) / sum(pow(x, 2)) over (partition by c) as x from s), k as (select *, row_number() over (partition by c order by x desc, r) as n from f) select r as row, c as col, round(x / sum(x) over (partition by c), 6) as val from k where n = 1 or x >= 1e-4 and n <= 100"
)
def markov_flow_step(spark, sf):
    return baselines.flow_step(baselines.flow_start(supplier_graph(spark, sf)), 2.0).withColumn("val", F.round("val", 6))


@query()
def markov_flow(spark, sf):
    return baselines.markov_flow(supplier_graph(spark, sf), 2.0)


@query()
def random_centers(spark, sf):
    p = Sampled(supplier_graph(spark, sf), SEED).ensure(R)
    return spark.createDataFrame(list(enumerate(baselines.random_centers(p, 5))), "rank int, center long")


@query(
    f"""{_exact_sql(None)}, b as (select u as c, v as node, prob as p from ex union all select v, u, prob from ex union all select node, node, 1.0 from v),
s as (select a.c as c1, z.c as c2, coalesce(a.reg, z.reg) as reg, n.node, greatest(coalesce(p.p, 0), coalesce(q.p, 0)) as value from (select distinct c, n_regionkey as reg from b join nation on c = n_nationkey) a join (select distinct c, n_regionkey as reg from b join nation on c = n_nationkey) z on a.reg = z.reg and a.c < z.c join (select node, n_regionkey as reg from v join nation on node = n_nationkey) n on n.reg = a.reg left join b p on p.c = a.c and p.node = n.node left join b q on q.c = z.c and q.node = n.node)
select reg::int as region, round(max(low), 6) as best_min, round(max(mean), 6) as best_avg from (select reg, c1, c2, min(value) as low, avg(value) as mean from s group by all) group by reg"""
)
def brute_optimum(spark, sf):
    e = cut(graphs.nation(spark, sf))
    half = reliability.exact_pairs(e).select(F.col("u").alias("center"), F.col("v").alias("node"), F.col("prob").alias("value"))
    own = components.nodes(e).select(F.col("node").alias("center"), "node", F.lit(1.0).alias("value"))
    region = {x[0]: x[1] for x in table(spark, sf, "nation", ["n_nationkey", "n_regionkey"]).collect()}
    pairs = cut(half.unionByName(half.select(F.col("node").alias("center"), F.col("center").alias("node"), "value")).unionByName(own))
    out = None
    for reg in sorted(set(region.values())):
        ids = [int(k) for k, v in region.items() if v == reg]
        some = pairs.filter(F.col("center").isin(ids))
        if some.isEmpty():
            continue
        got = baselines.brute_optimum(some, some.select("node").distinct(), 2).select(F.lit(reg).cast("int").alias("region"), F.round("best_min", 6).alias("best_min"), F.round("best_avg", 6).alias("best_avg"))
        out = got if out is None else out.unionByName(got)
    return out


# --- experiments and streams ----------------------------------------------------------------------------------------


@query()
def compare_methods(spark, sf):
    return workloads.compare("supplier", graphs.supplier(spark, sf), [1.5], r_eval=200)


@query()
def graph_doc_overlap_whole(spark, sf):
    """The overlap of documents over all 3-grams, however many documents have them."""
    return graphs.doc_overlap(spark, sf, high=None)


DEPTHS, K_SHARE = [2, 3, 4, 6, 8], 0.214


def _predict(name: str, edges: DataFrame, truth: DataFrame) -> DataFrame:
    """Prediction on a whole graph; fewer clusters than components can't be formed."""
    e = cut(edges)
    k = max(2, int(K_SHARE * components.nodes(e).count()), components.label_support(e).select("label").distinct().count())
    return workloads.predict(name, e, truth, DEPTHS, k, r="progressive")


@query()
def predict_copies(spark, sf):
    """Exact copies from the overlap of documents."""
    d = table(spark, sf, "documents", ["doc_id", "text"])
    return _predict("doc_overlap", graphs.doc_overlap(spark, sf, high=None), d.select(F.col("doc_id").alias("node"), F.md5("text").alias("grp")).filter("grp is not null"))


@query()
def predict_labels(spark, sf):
    """Negative control: labels that have nothing to do with the embeddings' neighbours."""
    truth = table(spark, sf, "embeddings", ["vec_id", "label"])
    return _predict("knn", graphs.knn(spark, sf), truth.select(F.col("vec_id").alias("node"), F.col("label").alias("grp")))


@query()
def start_size(spark, sf):
    e = cut(graphs.nation(spark, sf))
    return workloads.start_size("nation", e, [25, 50, 100, 400], cut(reliability.exact_pairs(e)))


@query(f"with {GS}, d as (select 'supplier' as graph, 'rule' as method, src % 3 as metric, prob as value from e) select metric, method, graph, round(avg(value), 6) as value, grouping(metric, method, graph)::int as level from d group by rollup (metric, method, graph) having metric is not null")
def experiment_report(spark, sf):
    d = graphs.supplier(spark, sf).select(F.lit("supplier").alias("graph"), F.lit("rule").alias("method"), (F.col("src") % 3).alias("metric"), F.col("prob").alias("value"))
    return workloads.rollup(d)


@query(f"with {graphs.USER_COUNTS_SQL} select src, dst, x from x")
def stream_interactions(spark, sf):
    """Interaction counts, kept by a stream over the table's file and read from its sink."""
    import uuid

    from probgraph.runtime import shared_dir

    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    events = table(spark, sf, "events")
    interactions.split_by_hour(events, f"{base}/in")
    # a last event beyond the watermark closes the windows
    events.limit(1).withColumn("ts", F.lit("2100-01-01").cast("timestamp").cast(events.schema["ts"].dataType)).withColumn("event_type", F.lit("end")).write.parquet(f"{base}/in/part=9999")
    stream = interactions.event_stream(spark, f"{base}/in", T.StructType([*events.schema.fields, T.StructField("part", T.IntegerType())]), 1)
    interactions.run_counts(interactions.grouped(stream), f"{base}/out", f"{base}/check")
    return interactions.counts(spark, f"{base}/out")


@query(f"with {graphs.USER_COUNTS_SQL} select src, dst, x from x")
def batch_interactions(spark, sf):
    return interactions.batch_counts(table(spark, sf, "events"))


__all__ = ["ORACLE", "QUERIES", "flagship", "harmonic"]
