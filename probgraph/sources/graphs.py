"""Workload graphs on the given tables. Probabilities are rounded to 6 digits (4 for nations), so that SQL engines agree.

Each has a ``*_SQL`` text: the same graph as DuckDB common table expressions that end in ``e(src, dst, prob)``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from probgraph.functions import edge_prob
from probgraph.runtime import cut, lean, release, small, stage
from probgraph.sources import table

#: Events of more members than HOT are spread over SALT parts.
HOT, SALT = 2000, 8


def pairs(members: DataFrame, event: str, member: str) -> DataFrame:
    """(src, dst, x): how many events two members share. In a hot event each member's row meets one part of the others at a time."""
    m = members.select(F.col(event).alias("g"), F.col(member).cast("long").alias("m")).distinct()
    hot = cut(m.groupBy("g").count().filter(F.col("count") > HOT).select("g", F.lit(True).alias("hot")))
    if hot.isEmpty():
        both = m.withColumnRenamed("m", "src").join(m.withColumnRenamed("m", "dst"), "g").filter("src < dst")
    else:
        m = m.join(small(hot), "g", "left")
        parts = F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(SALT - 1))).otherwise(F.array(F.lit(0)))
        left = m.withColumn("part", F.explode(parts)).select("g", "part", F.col("m").alias("src"))
        right = m.withColumn("part", F.when(F.col("hot"), F.pmod(F.xxhash64("m"), F.lit(SALT)).cast("int")).otherwise(F.lit(0))).select("g", "part", F.col("m").alias("dst"))
        both = left.join(right, ["g", "part"]).filter("src < dst")
    return both.groupBy("src", "dst").agg(F.count("*").alias("x"))


def by_count(counts: DataFrame, scale: float = 2.0) -> DataFrame:
    return counts.select("src", "dst", F.round(edge_prob(F.col("x"), scale), 6).alias("prob"))


def supplier_counts(spark: SparkSession, sf: str) -> DataFrame:
    lines = table(spark, sf, "lineitem").filter("l_returnflag = 'R' and l_shipdate >= timestamp'1995-01-01' and l_shipdate < timestamp'1996-01-01'")
    return pairs(lines, "l_orderkey", "l_suppkey")


def supplier(spark: SparkSession, sf: str) -> DataFrame:
    """Suppliers that share a returned order line of 1995."""
    return by_count(supplier_counts(spark, sf))


def part_counts(spark: SparkSession, sf: str) -> DataFrame:
    orders = table(spark, sf, "orders").filter("o_orderdate >= timestamp'1995-01-01' and o_orderdate < timestamp'1996-01-01' and o_orderpriority like '1%'").select("o_orderkey")
    lines = table(spark, sf, "lineitem", ["l_orderkey", "l_partkey"]).join(orders, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")
    return pairs(lines, "l_orderkey", "l_partkey")


def part(spark: SparkSession, sf: str) -> DataFrame:
    """Parts that share an urgent order of 1995."""
    return by_count(part_counts(spark, sf))


def mixed(spark: SparkSession, sf: str) -> DataFrame:
    """The part graph's edges with a quarter of the probabilities above 0.9 and the others even in 0.27 to 0.9."""
    key = F.md5(F.concat_ws("|", F.lit("mix"), F.col("src").cast("string"), F.col("dst").cast("string")))
    h, t = (F.conv(F.substring(key, at, 8), 16, 10).cast("long") / F.lit(4294967296.0) for at in (1, 9))
    return part_counts(spark, sf).select("src", "dst", F.round(F.when(h < 0.25, 0.9 + 0.1 * t).otherwise(0.27 + 0.63 * t), 6).alias("prob"))


def nation(spark: SparkSession, sf: str) -> DataFrame:
    """Nations of a region, by the orders that a supplier of one and a customer of the other share."""
    n = table(spark, sf, "nation", ["n_nationkey", "n_regionkey"])
    s = table(spark, sf, "supplier", ["s_suppkey", "s_nationkey"]).join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra"))
    c = table(spark, sf, "customer", ["c_custkey", "c_nationkey"]).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb"))
    o = table(spark, sf, "orders", ["o_orderkey", "o_custkey"]).join(c, F.col("o_custkey") == F.col("c_custkey"))
    both = table(spark, sf, "lineitem", ["l_orderkey", "l_suppkey"]).join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(o, F.col("l_orderkey") == F.col("o_orderkey")).filter("a <> b and ra = rb")
    x = both.groupBy(F.least("a", "b").cast("long").alias("src"), F.greatest("a", "b").cast("long").alias("dst")).agg(F.countDistinct("o_orderkey").alias("x"))
    return x.withColumn("mean", F.avg("x").over(Window.partitionBy())).select("src", "dst", F.round(F.least(F.lit(0.95), 0.5 * F.col("x") / F.col("mean")), 4).alias("prob"))


def user_counts(events: DataFrame) -> DataFrame:
    """Users active in the same five minutes with the same kind of event."""
    return pairs(events.withColumn("g", F.struct(F.window("ts", "5 minutes").start.alias("t"), "event_type")), "g", "user_id")


def user(spark: SparkSession, sf: str) -> DataFrame:
    return by_count(user_counts(table(spark, sf, "events", ["ts", "user_id", "event_type"])))


def doc_overlap(spark: SparkSession, sf: str, low: int = 2, high: int | None = 50, least: float = 0.05) -> DataFrame:
    """Documents by the Jaccard similarity of their word 3-grams, over the 3-grams that ``low`` to ``high`` documents have.

    high None: over all 3-grams, without a table of pairs. Documents of equal sets are one while 3-grams are counted, so that copies cost no more than their own edges."""
    # zipped with its own shifts: the words are found once a text, not once a 3-gram
    w = F.regexp_extract_all(F.lower("text"), F.lit(r"(\S+)"))
    join = lambda a, b: F.concat_ws(" ", a, b)
    three = F.zip_with(F.zip_with("w", F.expr("slice(w, 2, greatest(size(w), 1))"), join), F.expr("slice(w, 3, greatest(size(w), 1))"), join)
    grams = F.when(F.size("w") < 3, F.array(F.array_join("w", " "))).otherwise(F.slice(three, F.lit(1), F.size("w") - 2))
    s = table(spark, sf, "documents", ["doc_id", "text"]).filter("text is not null").withColumn("w", w).select("doc_id", F.array_distinct(grams).alias("s"))
    if high is None:
        return _overlap_of_all(s, least)
    n = s.select("doc_id", F.size("s").alias("n"))
    one = s.select("doc_id", F.explode("s").alias("g")).select("doc_id", F.xxhash64("g").alias("g"))
    rare = one.groupBy("g").count().filter(F.col("count").between(low, high)).select("g")
    shared = pairs(one.join(rare, "g"), "g", "doc_id")
    j = shared.join(n.select(F.col("doc_id").alias("src"), F.col("n").alias("na")), "src").join(n.select(F.col("doc_id").alias("dst"), F.col("n").alias("nb")), "dst")
    return j.withColumn("p", F.col("x") / (F.col("na") + F.col("nb") - F.col("x"))).filter(F.col("p") >= least).select("src", "dst", F.round("p", 6).alias("prob"))


#: 3-grams of a block of documents that goes to the tasks at a time, 12 bytes each.
GRAMS_IN_BLOCK = 4_000_000


def _overlap_of_all(s: DataFrame, least: float) -> DataFrame:
    """(src, dst, prob) over all 3-grams. s: (doc_id, s)."""
    s = s.filter("doc_id is not null").withColumn("doc_id", F.col("doc_id").cast("long"))
    alike = s.select("doc_id", F.size("s").alias("n"), F.sha2(F.concat_ws("\n", F.array_sort("s")), 256).alias("set"))
    heads = stage(alike.withColumn("head", F.min("doc_id").over(Window.partitionBy("set"))).select("doc_id", "n", "head"))
    some = small(cut(heads.filter("doc_id = head").select("doc_id")), 2_000_000)
    e = _met(s.join(some, "doc_id", "left_semi").select("doc_id", F.transform("s", lambda g: F.xxhash64(g)).alias("g")), heads.select("doc_id", "n"), least)
    one, two = (small(heads.select(F.col("head").alias(end), F.col("doc_id").alias(c)), 2_000_000) for end, c in (("src", "a"), ("dst", "b")))
    far = e.select("src", "dst", F.round("p", 6).alias("prob")).join(one, "src").join(two, "dst").select("a", "b", "prob")
    same = one.join(two.withColumnRenamed("dst", "src"), "src").filter("a < b").select("a", "b", F.lit(1.0).alias("prob"))
    return far.unionByName(same).select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "prob")


def _flat(b: pa.RecordBatch, at: int) -> tuple[np.ndarray, np.ndarray]:
    """(elements of a column of arrays, number of each)."""
    c = b.column(at)
    return c.flatten().to_numpy(), c.value_lengths().to_numpy().astype(np.int64)


def _met(sets: DataFrame, sizes: DataFrame, least: float, most: int = GRAMS_IN_BLOCK) -> DataFrame:
    """(src, dst, p) of the pairs of sets with a Jaccard similarity of at least ``least``. sets: (doc_id, g); sizes: (doc_id, n).

    Only 3-grams that several sets hold go on. Blocks of sets go to the tasks, where all others' shared 3-grams are counted against them: no table of pairs is written."""
    spark = sets.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 16)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        for b in (x.slice(at, 500) for x in batches for at in range(0, x.num_rows, 500)):
            g, n = _flat(b, 1)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(b.column(0).to_numpy(), n)), pa.array(g)], names=["doc_id", "g"])

    def several(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        d, g = t.column(0).to_numpy(), t.column(1).to_numpy()
        del t, got
        order = np.lexsort((d, g))
        d, g = d[order], g[order]
        new = np.append(True, (g[1:] != g[:-1]) | (d[1:] != d[:-1]))
        d, g = d[new], g[new]
        start = np.flatnonzero(np.append(True, g[1:] != g[:-1]))
        many = np.diff(np.append(start, len(g)))
        on = np.repeat(many > 1, many)
        d, g = d[on], g[on]
        for at in range(0, len(d), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(d[at : at + 100_000]), pa.array(g[at : at + 100_000])], names=["doc_id", "g"])

    shared = sets.mapInArrow(rows, "doc_id long, g long").repartition(parts, "g").mapInArrow(several, "doc_id long, g long")
    lists = stage(shared.groupBy("doc_id").agg(F.array_sort(F.collect_list("g")).alias("g")).join(sizes, "doc_id").select("doc_id", "n", "g"))
    release(spark)
    count = lists.select("doc_id", F.size("g").alias("c")).orderBy("doc_id").toArrow()
    ids, ends = count.column(0).to_numpy(), np.cumsum(count.column(1).to_numpy(), dtype=np.int64)
    out, at = None, 0
    while at < len(ids):
        end = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, "right")))
        low, high = int(ids[at]), int(ids[end - 1])
        got = _against_block(lists, low, high, least)
        out = got if out is None else out.unionByName(got)
        at = end
    return spark.createDataFrame([], "src long, dst long, p double") if out is None else out


def _against_block(lists: DataFrame, low: int, high: int, least: float) -> DataFrame:
    """:func:`_met` of the sets of ids ``low`` to ``high`` with sets of lower ids."""
    block = lists.filter(F.col("doc_id").between(low, high)).toArrow()
    block = block.take(pa.array(np.argsort(block.column(0).to_numpy()))).combine_chunks()
    ids, n = block.column(0).to_numpy(), block.column(1).to_numpy().astype(np.int64)
    g = block.column(2).chunk(0)
    of = np.repeat(np.arange(len(ids), dtype=np.int32), g.value_lengths().to_numpy())
    g = g.flatten().to_numpy()
    order = np.argsort(g, kind="stable")
    names, ptr = np.unique(g[order], return_index=True)
    shared = lists.sparkSession.sparkContext.broadcast((ids, n, names, np.append(ptr, len(g)), of[order]))
    del block, g, of, order

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        ids, n, names, ptr, of = shared.value
        for b in (x.slice(at, 500) for x in batches for at in range(0, x.num_rows, 500)):
            doc, size = b.column(0).to_numpy(), b.column(1).to_numpy().astype(np.int64)
            g, many = _flat(b, 2)
            k = np.minimum(np.searchsorted(names, g), len(names) - 1)
            known = names[k] == g
            rows, k = np.repeat(np.arange(len(doc)), many)[known], k[known]
            first = np.searchsorted(rows, np.arange(len(doc) + 1))
            src, dst, p = [], [], []
            for i in range(len(doc)):
                own = k[first[i] : first[i + 1]]
                each = ptr[own + 1] - ptr[own]
                x = np.bincount(of[np.arange(each.sum()) + np.repeat(ptr[own] - (np.cumsum(each) - each), each)])
                j = np.flatnonzero(x)
                j = j[ids[j] > doc[i]]
                q = x[j] / (size[i] + n[j] - x[j])
                j, q = j[q >= least], q[q >= least]
                src.append(np.full(len(j), doc[i]))
                dst.append(ids[j])
                p.append(q)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(src)), pa.array(np.concatenate(dst)), pa.array(np.concatenate(p))], names=["src", "dst", "p"])

    out = stage(lists.filter(F.col("doc_id") < high).mapInArrow(run, "src long, dst long, p double"))
    shared.destroy()
    return out


def knn(spark: SparkSession, sf: str, k: int = 5, block: int = 4000) -> DataFrame:
    """Union of the k nearest by cosine, p = cosine. Exact: block against block as matrix products, then the k best over blocks."""
    import numpy as np
    import pandas as pd

    e = table(spark, sf, "embeddings", ["vec_id", "embedding"])
    parts = max(1, -(-e.count() // block))
    e = e.withColumn("part", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int"))
    left = e.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    right = e.withColumnRenamed("part", "other").withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))

    def best(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"v": [], "u": [], "p": []})
        unit = lambda x: (m := np.array(x.tolist(), float)) / np.linalg.norm(m, axis=1, keepdims=True)
        s = unit(a.embedding) @ unit(b.embedding).T
        s[a.vec_id.to_numpy()[:, None] == b.vec_id.to_numpy()[None, :]] = -2
        top = np.argsort(-s, axis=1)[:, :k]
        out = pd.DataFrame({"v": np.repeat(a.vec_id.to_numpy(), top.shape[1]), "u": b.vec_id.to_numpy()[top].ravel(), "p": np.take_along_axis(s, top, 1).ravel()})
        return out[out.p > -2]

    near = left.groupBy("part", "other").cogroup(right.groupBy("part", "other")).applyInPandas(best, "v long, u long, p double")
    ranked = near.withColumn("rank", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("p"), "u"))).filter(F.col("rank") <= k)
    return ranked.filter("p > 0").select(F.least("v", "u").alias("src"), F.greatest("v", "u").alias("dst"), F.round("p", 6).alias("prob")).groupBy("src", "dst").agg(F.max("prob").alias("prob"))


def _name_id(c: str) -> F.Column:
    return F.conv(F.substring(F.md5(c), 1, 15), 16, 10).cast("long")


def page_link(spark: SparkSession, sf: str) -> DataFrame:
    """Hosts and the targets their pages link to; ids are the first 60 bits of the names' md5."""
    p = table(spark, sf, "pages", ["url", "html"])
    links = p.select(F.concat(F.lit("host:"), F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1)).alias("h"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]+)"'))).alias("l")).withColumn("l", F.concat(F.lit("link:"), "l"))
    x = links.groupBy(_name_id("h").alias("a"), _name_id("l").alias("b")).agg(F.count("*").alias("x"))
    return by_count(x.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "x"))


BUILDERS = {"supplier": supplier, "part": part, "nation": nation, "user": user, "mixed": mixed, "doc_overlap": doc_overlap, "knn": knn, "page_link": page_link}

SUPPLIER_COUNTS_SQL = """a as (select distinct l_orderkey as o, l_suppkey as m from lineitem where l_returnflag = 'R' and l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01'),
x as (select p.m as src, q.m as dst, count(*) as x from a p join a q on p.o = q.o and p.m < q.m group by all)"""
PART_COUNTS_SQL = """a as (select distinct l_orderkey as o, l_partkey as m from lineitem join orders on l_orderkey = o_orderkey
  where o_orderdate >= timestamp '1995-01-01' and o_orderdate < timestamp '1996-01-01' and o_orderpriority like '1%'),
x as (select p.m as src, q.m as dst, count(*) as x from a p join a q on p.o = q.o and p.m < q.m group by all)"""
_P = ", e as (select src, dst, round(1 - exp(-x / 2.0), 6) as prob from x)"
SUPPLIER_SQL = SUPPLIER_COUNTS_SQL + _P
PART_SQL = PART_COUNTS_SQL + _P
MIXED_SQL = PART_COUNTS_SQL + """, h as (select src, dst, md5('mix|' || src || '|' || dst) as k from x),
t as (select src, dst, ('0x' || substr(k, 1, 8))::bigint / 4294967296.0 as h, ('0x' || substr(k, 9, 8))::bigint / 4294967296.0 as t from h),
e as (select src, dst, round(case when h < 0.25 then 0.9 + 0.1 * t else 0.27 + 0.63 * t end::double, 6) as prob from t)"""
NATION_SQL = """x as (select least(a.n_nationkey, b.n_nationkey)::bigint as src, greatest(a.n_nationkey, b.n_nationkey)::bigint as dst, count(distinct o_orderkey) as x
  from lineitem join supplier on l_suppkey = s_suppkey join nation a on s_nationkey = a.n_nationkey join orders on l_orderkey = o_orderkey
  join customer on o_custkey = c_custkey join nation b on c_nationkey = b.n_nationkey
  where a.n_nationkey <> b.n_nationkey and a.n_regionkey = b.n_regionkey group by all),
e as (select src, dst, round(least(0.95::double, 0.5::double * x / avg(x) over ()), 4) as prob from x)"""
USER_COUNTS_SQL = """a as (select distinct time_bucket(interval '5 minutes', ts) as b, event_type as k, user_id as m from events),
x as (select p.m as src, q.m as dst, count(*) as x from a p join a q on p.b = q.b and p.k = q.k and p.m < q.m group by all)"""
USER_SQL = USER_COUNTS_SQL + _P
DOC_SQL = r"""w as (select doc_id, regexp_extract_all(lower(text), '\S+') as w from documents where text is not null),
s as (select doc_id, list_distinct(case when len(w) < 3 then [array_to_string(w, ' ')] else list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) end) as s from w),
o as (select doc_id, len(s) as n, unnest(s) as g from s), r as (select g from o group by g having count(*) between 2 and 50), k as (select o.* from o join r using (g)),
x as (select p.doc_id as src, q.doc_id as dst, any_value(p.n) as na, any_value(q.n) as nb, count(*) as x from k p join k q on p.g = q.g and p.doc_id < q.doc_id group by p.doc_id, q.doc_id),
e as (select src, dst, round(x::double / (na + nb - x), 6) as prob from x where x::double / (na + nb - x) >= 0.05)"""
KNN_SQL = """d as (select vec_id, embedding::double[] as v from embeddings),
s as (select a.vec_id as v, b.vec_id as u, list_cosine_similarity(a.v, b.v) as p from d a join d b on a.vec_id <> b.vec_id),
r as (select *, row_number() over (partition by v order by p desc, u) as k from s),
e as (select least(v, u) as src, greatest(v, u) as dst, max(round(p, 6)) as prob from r where k <= 5 and p > 0 group by all)"""
LINK_SQL = """l as (select 'host:' || regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as h, 'link:' || unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) as l from pages),
i as (select ('0x' || substr(md5(h), 1, 15))::bigint as a, ('0x' || substr(md5(l), 1, 15))::bigint as b, count(*) as x from l group by all),
e as (select least(a, b) as src, greatest(a, b) as dst, round(1 - exp(-x / 2.0), 6) as prob from i)"""
SQL = {"supplier": SUPPLIER_SQL, "part": PART_SQL, "nation": NATION_SQL, "user": USER_SQL, "mixed": MIXED_SQL, "doc_overlap": DOC_SQL, "knn": KNN_SQL, "page_link": LINK_SQL}
