"""Operator 5: MinHash near-dedup by a containment ensemble.

A text is the set of its word 3-grams (all its words as one, if fewer). Q is a near duplicate of X if |Q| <= |X| <= ``ratio`` |Q| and X holds at
least ``threshold`` of Q's shingles. By default there is no ``ratio``: a text wholly held by one a thousand times its size is a near duplicate.

Near duplicates both ways (each holds ``threshold`` of the other, so sizes are up to 1 / ``threshold`` times apart) meet by bands. Texts are partitioned by the size of their set, four partitions a doubling.
The two partitions' sizes give the least Jaccard similarity of such a pair, and that the number of bands that miss it with probability (1 - ``recall``) / 5 at most. A text sends each of its bands once; a bucket's
pair counts if the banding of its two partitions has that band.

Texts held by larger ones of any size: as a containment, the threshold leaves so low a Jaccard similarity that bands would pair all texts with a common passage. So some of the query's
shingles are looked up in all larger sets. Shingles that a sample finds in many texts are avoided: if h of the query's n shingles are common, X holds at least
``threshold`` n - h of the others, and so many of these, those of least hash, are looked up that ``HITS`` are in X with the wanted probability; or, where that is cheaper (texts made of boilerplate), so many of the rarest
ones that one or ``HITS`` are in X for certain. Only sets that have that many are checked: chance meetings, whose number grows faster than the input, mostly have one. Only the largest text that holds a query counts, so lists
are read from the largest text on, and no further than one that holds it. So every text is a query against every partition.

Big groups: equal sets are one node. A first round checks each member of a bucket against the bucket's largest member of its own and the
next partition only, and joins what is confirmed; the second round takes all pairs of a bucket that are not yet in one group. So a group
of thousands costs no quadratic number of checks, and no pair of different groups is left out. Candidates whose signatures put them far under their threshold (as one in 30,000
of those at it would be) are dropped; the rest are checked exactly, set against set (32-bit shingle hashes).

Groups: texts that are near duplicates of each other in both directions are linked, and linked texts are one group; the largest set, then
the lowest doc_id, stays. A text that is only contained in a larger one is dropped for it, but doesn't link the larger one to others.

A pair's sets are compared as stored with the sketches, so texts are read and cut in words once, whole, however long. An empty table has no duplicates. Further columns aren't read and stay as they are.

Texts without words are in no group. Sets of fewer than ``least`` shingles count only if they hold ``threshold`` of each other.
Rows equal in doc_id and words are one text, of which one row stays; so do, of rows with null text, one for a doc_id. A null doc_id counts as the lowest id."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from probgraph.llm.passages import NULL_DOC, text_key
from probgraph.llm.text import Codes, grams, mix, words
from probgraph.runtime import cut, fresh, lean, release, small, stage

SHINGLE, HASHES, THRESHOLD, RATIO, RECALL, LEAST = 3, 96, 0.7, math.inf, 0.95, 10
#: Sets meet larger ones by shingles of the smaller set, preferably of its FEW least hashed ones; up to FILTERED of these are held against all shingles before the shuffle.
FEW, FILTERED = 12, 100_000_000
#: A shingle is common if COMMON texts or more of one in SAMPLE hold it; the MOST most common ones are known by their counts. They decide only which shingles are looked up.
SAMPLE, COMMON, MOST = 16, 3, 2_000_000
#: Texts of a shingle's list that are read at first, and by how many times more in each further round.
LIST, MORE = 64, 16
#: Looked-up shingles that a larger set must have to be checked, unless looking up so few that one is enough is ALONE times as cheap.
HITS, ALONE = 2, 16
STEPS = 4  # partitions a doubling


def shingles(code: np.ndarray, k: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 32-bit shingle hashes."""
    if not len(code):
        return np.zeros(0, np.uint32)
    return np.unique((grams(code, min(k, len(code))) >> np.uint64(32)).astype(np.uint32))


_RNG = np.random.default_rng(20240229)
_A = _RNG.integers(1, 2**63, HASHES, dtype=np.uint64) | np.uint64(1)
_B = _RNG.integers(0, 2**63, HASHES, dtype=np.uint64)


def signature(s: np.ndarray) -> np.ndarray:
    x = mix(s.astype(np.uint64))
    out = np.empty(HASHES, np.uint32)
    for at in range(0, HASHES, 16):
        out[at : at + 16] = ((x[:, None] * _A[None, at : at + 16] + _B[None, at : at + 16]) >> np.uint64(32)).min(axis=0)
    return out


def few(s: np.ndarray) -> np.ndarray:
    """The shingles of least hash, the same for equal sets."""
    return s[np.argsort(mix(s.astype(np.uint64) ^ np.uint64(0x5EED)), kind="stable")[:FEW]].view(np.int32)


def tries(n: int, held: int, miss: float, need: int = 1) -> int:
    """How many of n shingles have to be looked up so that, if ``held`` of them are in a set, fewer than ``need`` are found with probability ``miss`` at most."""
    k, fewer = 0, [1.0] + [0.0] * (need - 1)  # the probabilities of 0, 1, ... found
    while sum(fewer) > miss and k < n - held + need:
        fewer = [(fewer[j] * (n - held - k + j) + (fewer[j - 1] * (held - j + 1) if j else 0)) / (n - k) for j in range(need)]
        k += 1
    return k


@cache
def draws(miss: float) -> np.ndarray:
    """For shares of 0, 0.001, ..., 1 of all shingles held: how many to look up so that fewer than ``HITS`` are found with probability ``miss`` at most; FEW + 1 where FEW aren't enough."""
    fewer = lambda p, k: sum(math.comb(k, j) * p**j * (1 - p) ** (k - j) for j in range(HITS))
    return np.array([next((k for k in range(HITS, FEW + 1) if fewer(i / 1000, k) <= miss), FEW + 1) for i in range(1001)])


def chosen(s: np.ndarray, count: np.ndarray, t: float, miss: float) -> tuple[np.ndarray, int]:
    """The cheapest shingles to look up, and how many of them a set must have: some of those under a count, or the rarest ones of which no set that holds t of all can lack more."""
    n, held = len(s), math.ceil(t * len(s) - 1e-9)
    order = np.argsort(mix(s.astype(np.uint64) ^ np.uint64(0x5EED)), kind="stable")
    s, count = s[order], count[order]
    rarest = np.argsort(count, kind="stable")
    best, least = None, math.inf
    for need in range(1, min(HITS, held) + 1):
        some = [rarest[: n - held + need]]
        level, cold = COMMON, rarest[:0]
        while len(cold) < n:
            cold = np.flatnonzero(count < level)
            left = held - (n - len(cold))
            if left >= need:
                some.append(cold[: tries(len(cold), left, miss, need)])
            level *= 4
        for x in some:
            cost = (len(x) + SAMPLE * int(count[x].sum())) * (1 if need == HITS else ALONE)
            if cost < least:
                best, least = (s[x], need), cost
    return best


def partition(n: np.ndarray | int) -> np.ndarray:
    return np.floor(STEPS * np.log2(np.maximum(n, 1)) + 1e-9).astype(np.int64)


def jaccard_threshold(apart: int, t: float = THRESHOLD) -> float:
    """Least Jaccard similarity of two sets that hold t of each other, in partitions that are ``apart`` steps apart."""
    u = max(1.0, 2 ** ((apart - 1) / STEPS))
    return t * u / (1 + u - t * u)


def furthest(ratio: float = 1 / THRESHOLD) -> int:
    return int(math.ceil(STEPS * math.log2(ratio)))


@cache
def banding(apart: int, t: float = THRESHOLD, recall: float = RECALL) -> tuple[int, int]:
    """(rows a band, bands): the most rows for which a pair is missed with probability (1 - recall) / 5 at most, at every distance, and the fewest bands for it at this one."""
    need = lambda s, r: math.ceil(math.log((1 - recall) / 5) / math.log(1 - s**r))
    r = next((r for r in range(8, 1, -1) if need(jaccard_threshold(0, t), r) <= HASHES // r), 1)
    return r, min(need(jaccard_threshold(apart, t), r), HASHES // r)


SKETCH = "node long, doc long, text_key long, n int, set_key long, signature binary, low binary, few array<int>, shingles binary"
#: Rows of ids that may be broadcast to keep texts from being shuffled; beyond it they are joined by a shuffle.
ID_ROWS = 2_000_000


def node_id(doc: int, key: int) -> int:
    return xxhash.xxh3_64_intdigest(doc.to_bytes(8, "little", signed=True) + key.to_bytes(8, "little", signed=True)) - (1 << 63)


def sketches(docs: DataFrame) -> DataFrame:
    """One row per row of ``docs`` that has words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        codes = Codes()
        for b in (x.slice(at, 500) for x in batches for at in range(0, x.num_rows, 500)):
            rows = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1)):
                code = words(text.as_py(), codes)
                if not len(code):
                    continue
                s, key = shingles(code), text_key(code)
                node = node_id(doc, key)
                sig = signature(s)
                rows.append((node, doc, key, len(s), xxhash.xxh3_64_intdigest(s.tobytes()) - (1 << 63), sig.tobytes(), sig.astype(np.uint8).tobytes(), few(s), s.tobytes()))
            c = list(zip(*rows)) if rows else [()] * 9
            yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.int64()), pa.array(c[3], pa.int32()), pa.array(c[4], pa.int64()), pa.array(c[5], pa.binary()), pa.array(c[6], pa.binary()), pa.array(c[7], pa.list_(pa.int32())), pa.array(c[8], pa.binary())], names=["node", "doc", "text_key", "n", "set_key", "signature", "low", "few", "shingles"])

    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_DOC)).alias("doc"), F.col("text").cast("string")).filter("text is not null")
    return rows.mapInArrow(run, SKETCH)


def band_rows(nodes: DataFrame, r: int, count: int) -> DataFrame:
    """(key, band, node, n, group) of (node, n, group, signature), of bands 0 to ``count`` - 1 of r rows. Made anew where it is needed: cheaper than to store."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        for b in batches:
            if not b.num_rows:
                continue
            node, n, group = b.columns[:3]
            sig = np.stack([np.frombuffer(x.as_py(), np.uint32) for x in b.column(3)]).astype(np.uint64)
            for k in range(count):
                key = np.full(len(sig), np.uint64(100 * r + k))
                for j in range(r):
                    key = mix(key * np.uint64(31) + sig[:, k * r + j])
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(np.full(len(sig), k, np.int16)), node, n, group], names=["key", "band", "node", "n", "group"])

    return nodes.select("node", "n", "group", "signature").mapInArrow(run, "key long, band short, node long, n int, group long")


PAIRS = "a long, b long"


def star_pairs(rows: DataFrame) -> DataFrame:
    """Each member of a bucket with the bucket's largest one of its own partition and of the next."""
    part = F.floor(F.lit(STEPS) * F.log2(F.col("n")) + 1e-9).cast("int")
    rows = rows.withColumn("part", part)
    best = F.max_by("node", F.struct("n", F.bitwise_not("node")))
    tops = rows.groupBy("key", "part").agg(best.alias("top"), F.collect_list(F.struct("n", "node")).alias("members"))
    up = Window.partitionBy("key").orderBy("part")
    tops = tops.withColumn("next", F.when(F.lead("part").over(up) == F.col("part") + 1, F.lead("top").over(up)))
    pairs = tops.filter((F.size("members") > 1) | F.col("next").isNotNull()).select(F.explode("members.node").alias("a"), F.array("top", "next").alias("with")).select("a", F.explode("with").alias("b")).filter("b is not null and a <> b")
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def all_pairs(rows: DataFrame, t: float, ratio: float, recall: float) -> DataFrame:
    """Pairs of a bucket that are of different groups, with the banding of their partitions. rows: (key, band, node, n, group)."""
    many = rows.withColumn("members", F.count("*").over(Window.partitionBy("key"))).filter("members > 1").drop("members")
    plan = [banding(d, t, recall)[1] for d in range(furthest(ratio) + 1)]

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        table = pa.Table.from_batches(got)
        key, band, node, n, group = (table.column(c).to_numpy() for c in ("key", "band", "node", "n", "group"))
        order = np.lexsort((n, key))
        key, band, node, n, group = key[order], band[order].astype(np.int64), node[order], n[order].astype(np.int64), group[order]
        part = partition(n)
        start = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        end = np.repeat(np.append(start[1:], len(key)), np.diff(np.append(start, len(key))))
        reach = np.array(plan)
        # the i-th member with those after it, one distance at a time: in size order, so that it ends where sizes are too far apart
        live, gap, out, held = np.arange(len(key)), 1, [], 0
        while len(live):
            live = live[live + gap < end[live]]
            live = live[n[live + gap] <= ratio * n[live]]
            if not len(live):
                break
            x, y = live, live + gap
            apart = part[y] - part[x]
            ok = (group[x] != group[y]) & (apart < len(plan)) & (node[x] != node[y])
            apart = np.minimum(apart, len(plan) - 1)
            ok &= band[x] < reach[apart]
            x, y = x[ok], y[ok]
            if len(x):
                out.append(np.stack([np.minimum(node[x], node[y]), np.maximum(node[x], node[y])]))
                held += len(x)
            if held > 2_000_000:
                got_ = np.unique(np.concatenate(out, 1), axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(got_[0]), pa.array(got_[1])], names=["a", "b"])
                out, held = [], 0
            gap += 1
        if out:
            got_ = np.unique(np.concatenate(out, 1), axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(got_[0]), pa.array(got_[1])], names=["a", "b"])

    return many.mapInArrow(pairs, PAIRS).distinct()  # the window has put each bucket in one partition


def flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(shingles of a column of sets, number of each)."""
    own = column.to_pylist()
    return np.frombuffer(b"".join(own), np.uint32), np.array([len(x) // 4 for x in own], np.int64)


def common(every: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(shingles, counts) of the common ones, sorted."""

    def explode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        for b in (x.slice(at, 500) for x in batches for at in range(0, x.num_rows, 500)):
            s, count = np.unique(flat(b.column(0))[0], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(s.view(np.int32)), pa.array(count)], names=["s", "c"])

    some = every.filter(F.pmod("set_key", F.lit(SAMPLE)) == 0).groupBy("set_key").agg(F.first("shingles").alias("shingles"))
    counts = some.select("shingles").mapInArrow(explode, "s int, c long").groupBy("s").agg(F.sum("c").alias("c")).filter(F.col("c") >= COMMON)
    got = counts.orderBy(F.desc("c")).limit(MOST).toArrow()
    s, c = got.column("s").to_numpy().view(np.uint32), got.column("c").to_numpy()
    order = np.argsort(s)
    return s[order], c[order]


def lookups(every: DataFrame, t: float, recall: float, least: int) -> DataFrame:
    """(a, na, s, need): the shingles that are looked up in larger sets. A set that holds t of a has fewer than ``need`` of them with probability (1 - recall) / 5 at most."""
    miss = (1 - recall) / 5
    known = every.sparkSession.sparkContext.broadcast(common(every))

    def counts(s: np.ndarray) -> np.ndarray:
        of, count = known.value
        if not len(of):
            return np.zeros(len(s), np.int64)
        at = np.minimum(np.searchsorted(of, s), len(of) - 1)
        return np.where(of[at] == s, count[at], 0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        for b in (x.slice(at, 500) for x in batches for at in range(0, x.num_rows, 500)):
            if not b.num_rows:
                continue
            s, n = flat(b.column(3))
            count = counts(s)
            ends = np.cumsum(n)
            cold = n - np.add.reduceat((count > 0).astype(np.int64), ends - n)
            left = np.ceil(t * n - 1e-9) - (n - cold)
            k = np.where(left >= HITS, draws(miss)[np.floor(1000 * np.maximum(left, 0) / np.maximum(cold, 1)).astype(np.int64)], FEW + 1)
            # mostly enough of the few are not common
            own = b.column(2).flatten().to_numpy().view(np.uint32)
            at = np.repeat(np.arange(len(n)), np.minimum(n, FEW))
            use = counts(own) == 0
            rank = np.cumsum(use) - use
            rank -= np.repeat(rank[np.cumsum(np.minimum(n, FEW)) - np.minimum(n, FEW)], np.minimum(n, FEW))
            plain = (np.bincount(at[use], minlength=len(n)) >= k) & (k <= FEW * 2 // 3)
            use &= plain[at] & (rank < k[at])
            at, out, need = [at[use]], [own[use]], np.full(len(n), HITS, np.int8)
            for i in np.flatnonzero(~plain):
                some, need[i] = chosen(s[ends[i] - n[i] : ends[i]], count[ends[i] - n[i] : ends[i]], t, miss)
                out.append(some)
                at.append(np.full(len(some), i))
            at = np.concatenate(at)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at)), pa.array(np.concatenate(out).view(np.int32)), pa.array(need[at])], names=["a", "na", "s", "need"])

    return every.filter(F.col("n") >= least).select("node", "n", "few", "shingles").mapInArrow(run, "a long, na int, s int, need byte")


SLICES = 64


def bit_table(keys: DataFrame) -> np.ndarray:
    """A bit for each 16 shingles, set if one of them is in ``keys``. Made by slices in the tasks, so that only bits come to the driver."""
    width = (1 << 25) // SLICES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        made: dict[int, np.ndarray] = {}
        for b in batches:
            s = np.unique(b.column(0).to_numpy().view(np.uint32) >> np.uint32(4))
            for k in np.unique(s >> np.uint32(22)).tolist():
                x = s[(s >> np.uint32(22)) == k] & np.uint32((1 << 22) - 1)
                np.bitwise_or.at(made.setdefault(k, np.zeros(width, np.uint8)), x >> np.uint32(3), np.uint8(1) << (x & np.uint32(7)).astype(np.uint8))
        for k, x in made.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([x.tobytes()], pa.binary())], names=["k", "bits"])

    out = np.zeros(1 << 25, np.uint8)
    for r in keys.repartition(SLICES, F.shiftrightunsigned("s", 26)).mapInArrow(run, "k int, bits binary").toLocalIterator():
        out[r.k * width : (r.k + 1) * width] |= np.frombuffer(bytes(r.bits), np.uint8)
    return out


def far_pairs(every: DataFrame, nodes: DataFrame, settled: DataFrame, t: float, ratio: float, recall: float, least: int, filtered: int = FILTERED, first: int = LIST) -> DataFrame:
    """``CHECKED`` rows of nodes with larger sets, among them for each node the largest one that holds t of it.

    An inverted index: the shingles looked up meet all shingles of all nodes by a shuffle on the shingle. Up to ``filtered``
    lookups, a table of bits of them drops the others' shingles that none asks for before the shuffle; the pairs are the same without it. A shingle's list is in order of size; of each list the ``first`` are read, and further ones only for
    nodes for which a larger holder than the one found may follow. That ends with the lists, so no holder that counts is left out: by then
    all lists are read as far as sets of its size go, and its hits are counted."""
    spark = every.sparkSession
    ids = nodes.select("node").join(settled, "node", "left_anti")
    asked = stage(lookups(every, t, recall, least).join(ids.select(F.col("node").alias("a")), "a", "left_semi").distinct())
    bits = spark.sparkContext.broadcast(bit_table(asked.select("s"))) if asked.count() <= filtered else None

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        for b in (x.slice(at, 500) for x in batches for at in range(0, x.num_rows, 500)):
            s, n = flat(b.column(2))
            at = np.repeat(np.arange(len(n)), n)
            if bits is not None:
                on = (bits.value[s >> np.uint32(7)] >> ((s >> np.uint32(4)) & np.uint32(7)).astype(np.uint8)) & 1 > 0
                s, at = s[on], at[on]
            yield pa.RecordBatch.from_arrays([pa.array(s.view(np.int32)), b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at))], names=["s", "b", "nb"])

    large = every.filter(F.col("n") > least).select("node", "n", "shingles").join(small(nodes.select("node"), ID_ROWS), "node", "left_semi")
    have = large.mapInArrow(index, "s int, b long, nb int").distinct()
    # only lists of shingles that a smaller set asks for
    asking = asked.groupBy("s").agg(F.min("na").alias("least"))
    have = have.join(asking, "s").filter(F.col("nb") > F.col("least"))
    lists = stage(have.select("s", "b", "nb", F.row_number().over(Window.partitionBy("s").orderBy(F.desc("nb"), "b")).alias("rank")))
    release(spark)
    done, low, high = None, 0, first
    bound = asked.withColumn("found", F.lit(0))
    while True:
        met = bound.join(lists.filter(F.col("rank") <= high + 1), "s").filter((F.col("nb") > F.col("na")) & (F.col("nb") >= F.col("found")))
        met = stage(met.select("a", "b", "na", "nb", "need", "rank", "found"))
        hits = met.filter((F.col("rank") <= high) & (F.col("nb") <= ratio * F.col("na"))).groupBy("a", "b", "na", "nb", "need").agg(F.count("*").alias("hits"), F.count_if(F.col("rank") <= low).alias("before"))
        got = stage(checked(stage(hits.filter("hits >= need and before < need").select("a", "b", "na", "nb")), every))
        done = got if done is None else done.unionByName(got)
        held = got.filter(F.col("shared") >= t * F.col("na")).groupBy("a").agg(F.max("nb").alias("now"))
        more = met.filter(F.col("rank") > high).groupBy("a", "found").agg(F.max("nb").alias("next")).join(held, "a", "left").withColumn("found", F.greatest("found", F.coalesce("now", F.lit(0))))
        # of equally large ones the first counts
        open_ = cut(more.filter(F.col("next") >= F.col("found")).select("a", "found"))
        if open_.isEmpty():
            return done
        bound = asked.join(small(open_, ID_ROWS), "a").select("s", "a", "na", "need", "found")
        low, high = high, high * MORE


#: A pair at its threshold is ruled out by its signatures with at most this probability (that of 4 standard errors of a normal variable).
MISS = 3.2e-5


@cache
def least_agreement() -> list[int]:
    """For Jaccard similarities of 0, 0.001, ..., 1: the most agreeing hashes that still leave a probability of at most MISS of fewer."""
    out = []
    for i in range(1001):
        p, c, below = i / 1000, 0, 0.0
        while c <= HASHES:
            below += math.comb(HASHES, c) * p**c * (1 - p) ** (HASHES - c)
            if below > MISS:
                break
            c += 1
        out.append(c)
    return out


def agreeing(jaccard) -> F.Column:
    return F.element_at(F.lit(least_agreement()), F.floor(F.least(jaccard, F.lit(1.0)) * 1000).cast("int") + 1)


def plausible(pairs: DataFrame, nodes: DataFrame, t: float, ratio: float) -> DataFrame:
    """Pairs (a, b, na, nb, j) that may hold t of each other: the last 8 bits of the signatures' hashes don't rule it out. Other hashes agree there in one of 256."""
    import pandas as pd
    from pyspark.sql import types as T

    one = nodes.select("node", "n", "low")
    both = (
        pairs.join(one.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("low").alias("sa")), "a")
        .join(one.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("low").alias("sb")), "b")
        .filter((F.greatest("na", "nb") <= ratio * F.least("na", "nb")))
    )

    def agreement(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        lean()
        for x, y in parts:
            if not len(x):
                yield pd.Series([], dtype=float)
                continue
            a, b = (np.frombuffer(b"".join(map(bytes, s)), np.uint8).reshape(-1, HASHES) for s in (x, y))
            yield pd.Series((a == b).sum(axis=1).astype(np.int32))

    near = F.pandas_udf(agreement, T.IntegerType(), F.PandasUDFType.SCALAR_ITER)
    low, high = F.least("na", "nb"), F.greatest("na", "nb")
    both = both.withColumn("j", near("sa", "sb")).filter(F.col("j") >= agreeing(t * high / (low + high - t * high)))
    return both.select("a", "b", "na", "nb", "j")


def few_links(pairs: DataFrame) -> DataFrame:
    """For each node its largest partner and its most similar one: enough to link a group. Pairs left out here come up again in the second round unless their ends are linked by then."""
    both = pairs.select("a", "b", "na", "nb", "j", F.col("a").alias("of"), F.struct("nb", F.bitwise_not("b")).alias("top")).unionByName(pairs.select("a", "b", "na", "nb", "j", F.col("b").alias("of"), F.struct(F.col("na").alias("nb"), F.bitwise_not("a")).alias("top")))
    pair = F.struct("a", "b", "na", "nb")
    best = both.groupBy("of").agg(F.max_by(pair, "top").alias("x"), F.max_by(pair, F.struct("j", "top")).alias("y"))
    return best.select(F.explode(F.array("x", "y")).alias("p")).select("p.*").distinct()


CHECKED = "a long, b long, na int, nb int, shared int"


def checked(pairs: DataFrame, every: DataFrame) -> DataFrame:
    """Exact number of shared shingles of each pair. The smaller set goes with the pair, the larger one once to all its pairs."""
    flip = F.col("na") > F.col("nb")
    pairs = pairs.withColumn("x", F.when(flip, F.col("b")).otherwise(F.col("a"))).withColumn("y", F.when(flip, F.col("a")).otherwise(F.col("b")))
    ids = lambda c: small(cut(pairs.select(F.col(c).alias("node")).distinct()), ID_ROWS)
    have = every.select("node", "shingles")
    smaller = have.join(ids("x"), "node", "left_semi").dropDuplicates(["node"]).withColumnRenamed("node", "x")
    rows = pairs.join(smaller, "x").select(F.col("y").alias("node"), "a", "b", "na", "nb", "shingles")
    none = lambda kind, *names: [F.lit(None).cast(kind).alias(c) for c in names]
    larger = have.join(ids("y"), "node", "left_semi").select("node", *none("long", "a", "b"), *none("int", "na", "nb"), "shingles")
    parts = int(every.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = rows.unionByName(larger).repartition(parts, "node").sortWithinPartitions("node", F.col("a").asc_nulls_first())

    def shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        of = np.zeros(0, np.uint32)
        for b in (x.slice(at, 500) for x in batches for at in range(0, x.num_rows, 500)):
            got, pair = [], b.column(1).is_valid()
            for is_pair, own in zip(pair.to_pylist(), b.column(5)):
                s = np.frombuffer(own.as_py(), np.uint32)
                if is_pair:
                    at = np.searchsorted(of, s)
                    got.append(int((of[np.minimum(at, len(of) - 1)] == s).sum()))
                else:
                    of = s
            yield pa.RecordBatch.from_arrays([*b.filter(pair).columns[1:5], pa.array(got, pa.int32())], names=["a", "b", "na", "nb", "shared"])

    return met.mapInArrow(shared, CHECKED)


def components(edges: DataFrame) -> DataFrame:
    """(node, group) of the nodes of undirected edges (a, b): the group is its least node. Alternating large and small stars."""
    pairs = cut(edges.select("a", "b").distinct())
    while True:  # stars converge in a logarithmic number of rounds
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.join(low, "a").filter("b > a").select(F.col("b").alias("x"), F.col("m").alias("y")).filter("x <> y")
        low = large.groupBy("x").agg(F.min("y").alias("m"))
        small_ = large.join(low, "x").select(F.col("y").alias("u"), "m").filter("u <> m").unionByName(low.select(F.col("x").alias("u"), "m")).distinct()
        new = cut(small_.select(F.least("u", "m").alias("a"), F.greatest("u", "m").alias("b")).distinct())
        same = new.count() == pairs.count() and new.exceptAll(pairs).isEmpty()
        pairs = new
        if same:
            break
    return pairs.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("group")).unionByName(pairs.select(F.col("a").alias("node"), F.col("a").alias("group")).distinct()).groupBy("node").agg(F.min("group").alias("group"))


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, ratio: float = RATIO, recall: float = RECALL, least: int = LEAST) -> DataFrame:
    """(doc, text_key, keep_doc, keep_key): texts to drop and the text that stays for each."""
    every = stage(sketches(docs))
    one = every.select("node", "doc", "text_key", "n", "set_key").distinct()
    # equal sets: the lowest id stands for them
    heads = every.groupBy("set_key", "n").agg(F.min(F.struct("doc", "text_key", "node")).alias("head"), F.min(F.struct("signature", "low")).alias("s"))
    nodes = stage(heads.select("head.node", "head.doc", "head.text_key", "n", "set_key", "s.signature", "s.low"))
    near = min(ratio, 1 / threshold + 1e-9)
    most = banding(0, threshold, recall)
    mutual = F.col("shared") >= threshold * F.greatest("na", "nb")

    stars = star_pairs(band_rows(nodes.withColumn("group", F.col("node")), *most))
    first = stage(checked(stage(few_links(plausible(stars, nodes, threshold, near))), every))
    grouped = small(cut(components(first.filter(mutual))), ID_ROWS)
    best = F.max_by(F.struct("node", "n"), F.struct("n", F.bitwise_not("doc"), F.bitwise_not("text_key")))
    in_group = nodes.select("node", "doc", "text_key", "n").join(grouped, "node")
    settled = small(cut(in_group.select("node").join(in_group.groupBy("group").agg(best.alias("k")).select("k.node"), "node", "left_anti")), ID_ROWS)
    del stars
    release(docs.sparkSession)
    rows = band_rows(nodes.join(grouped, "node", "left").withColumn("group", F.coalesce("group", "node")), *most)
    candidates = stage(plausible(all_pairs(rows, threshold, near, recall), nodes, threshold, near).drop("j"))
    del rows
    release(docs.sparkSession)
    second = stage(checked(candidates, every))
    release(docs.sparkSession)
    # that a settled node is also held by a larger one changes nothing
    found = first.unionByName(second).unionByName(far_pairs(every, nodes, settled, threshold, ratio, recall, least))
    release(docs.sparkSession)
    groups = components(found.filter(mutual))
    info = nodes.select("node", "doc", "text_key", "n")
    full = stage(info.join(groups, "node", "left").withColumn("group", F.coalesce("group", "node")))
    keeper = full.groupBy("group").agg(best.alias("k")).select("group", F.col("k.node").alias("keeper"), F.col("k.n").alias("kn"))
    # contained in a larger text of another group
    one_way = found.filter(~mutual & (F.col("shared") >= threshold * F.least("na", "nb")) & (F.least("na", "nb") >= least))
    one_way = one_way.select(F.when(F.col("na") < F.col("nb"), F.col("a")).otherwise(F.col("b")).alias("node"), F.when(F.col("na") < F.col("nb"), F.col("b")).otherwise(F.col("a")).alias("over"), F.greatest("na", "nb").alias("size"))
    over = one_way.groupBy("node").agg(F.max_by("over", F.struct("size", F.bitwise_not("over"))).alias("over"))
    whole = full.join(keeper, "group").join(over, "node", "left")
    # the text that stays for it: its group's, or if that is itself, the one it is contained in
    stays = F.when(F.col("keeper") != F.col("node"), F.col("keeper")).otherwise(F.col("over"))
    heads_out = whole.withColumn("stays", stays).select("node", "stays")
    names = nodes.select(F.col("node").alias("stays"), F.col("doc").alias("keep_doc"), F.col("text_key").alias("keep_key"))
    dropped = heads_out.filter("stays is not null").join(names, "stays")
    of = one.select("node", "doc", "text_key", "set_key", "n").join(nodes.select("set_key", "n", F.col("node").alias("head")), ["set_key", "n"])
    copies = of.filter(F.col("node") != F.col("head")).join(nodes.select(F.col("node").alias("head"), F.col("doc").alias("head_doc"), F.col("text_key").alias("head_key")), "head")
    out = of.join(dropped.select(F.col("node").alias("head"), "keep_doc", "keep_key"), "head").select("doc", "text_key", "keep_doc", "keep_key")
    rest = copies.join(dropped.select(F.col("node").alias("head")), "head", "left_anti").select("doc", "text_key", F.col("head_doc").alias("keep_doc"), F.col("head_key").alias("keep_key"))
    return out.unionByName(rest)


def settled_links(links: DataFrame) -> DataFrame:
    """Rows of :func:`near_duplicates`, each with the text that stays in the end: what stays for a text may itself go for a larger one or for its group's."""
    at = cut(links)
    while True:  # each round doubles the length of the chains that are followed
        up = at.select(F.col("doc").alias("keep_doc"), F.col("text_key").alias("keep_key"), F.col("keep_doc").alias("next_doc"), F.col("keep_key").alias("next_key"))
        on = at.join(up, ["keep_doc", "keep_key"], "left")
        if on.filter("next_doc is not null").isEmpty():
            return at
        at = cut(on.select("doc", "text_key", F.coalesce("next_doc", "keep_doc").alias("keep_doc"), F.coalesce("next_key", "keep_key").alias("keep_key")))


def near_dedup(docs: DataFrame, **params) -> DataFrame:
    """(doc_id, kept_doc_id): each near duplicate and the document that stays for it; documents that stay aren't listed (see :func:`classes`)."""
    back = lambda c: F.when(F.col(c) != NULL_DOC, F.col(c))
    return settled_links(near_duplicates(docs, **params)).select(back("doc").alias("doc_id"), back("keep_doc").alias("kept_doc_id"))


def text_keys():
    """Column function: a text's key, by its words."""
    import pandas as pd
    from pyspark.sql import types as T

    def keys(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        lean()
        codes = Codes()
        for texts in parts:
            yield pd.Series([text_key(words(t, codes)) for t in texts], dtype="int64")

    return F.pandas_udf(keys, T.LongType(), F.PandasUDFType.SCALAR_ITER)


def classes(docs: DataFrame, **params) -> DataFrame:
    """(doc_id, class_id): every row of ``docs`` with the document that stays for it, those that stay with themselves."""
    links = settled_links(near_duplicates(docs, **params)).select("doc", "text_key", "keep_doc", F.lit(True).alias("goes"))
    own = docs.select("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_DOC)).alias("doc"), F.col("text").cast("string").alias("text"))
    key = F.when(F.col("text").isNotNull(), text_keys()(F.coalesce("text", F.lit("")))).alias("text_key")
    both = own.select("doc_id", "doc", key).join(links, ["doc", "text_key"], "left")
    return both.select("doc_id", F.when(F.col("goes") & (F.col("keep_doc") != NULL_DOC), F.col("keep_doc")).when(F.col("goes").isNull(), F.col("doc_id")).alias("class_id"))


def deduplicated(docs: DataFrame, **params) -> DataFrame:
    """The rows of ``docs`` that stay, columns unchanged: one of each group, and one of rows equal in doc_id and words."""
    columns = docs.columns
    doc, bad, many, key = (fresh(docs, n) for n in ("dup_doc", "dup_keys", "dup_rows", "dup_key"))
    drop = near_duplicates(docs, **params).groupBy(F.col("doc").alias(doc)).agg(F.collect_set("text_key").alias(bad))
    drop = small(cut(drop))
    release(docs.sparkSession)
    docs = docs.withColumn(doc, F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_DOC)))
    twice = small(cut(docs.groupBy(doc).count().filter("count > 1").select(F.col(doc), F.lit(True).alias(many))))
    udf = text_keys()
    marked = docs.join(drop, doc, "left").join(twice, doc, "left")
    asked = F.col(bad).isNotNull() | F.col(many).isNotNull()
    sure = marked.filter(~asked)
    rest = marked.filter(asked & F.col("text").isNotNull()).withColumn(key, udf("text"))
    rest = rest.filter(F.col(bad).isNull() | ~F.array_contains(F.col(bad), F.col(key))).dropDuplicates([doc, key])
    null = marked.filter(asked & F.col("text").isNull()).dropDuplicates([doc])
    return sure.select(columns).unionByName(rest.select(columns)).unionByName(null.select(columns))
