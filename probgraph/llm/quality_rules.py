"""Operator 10: quality rules. Robust multivariate outliers by minimum covariance determinant, per language and source.

Each text gives a vector of transformed statistics: log word count, log mean word length, and the angular transforms (arcsine of the
square root, which steadies a share's variance) of the shares of upper-case letters, symbols and digits, and of words
equal to the word before. Shares are drawn towards a typical value by ``PRIOR`` pseudo-counts, so that a few
characters can't make an outlier.

Per group, concentration steps start from the coordinatewise medians and spreads and from the same with half the spread: take
the ``share`` of rows with the least distance, estimate mean and covariance anew, repeat. The start with the
least determinant wins; then one reweighting step. A step is one aggregation over all rows, by group and distance bin
(bins of an eighth of a doubling), so that no group, however large, has to fit in a task. A variance never falls below ``FLOOR``
squared. Groups of fewer than ``min_rows`` rows use their language's estimates, small languages those of all rows.

A text is rejected if its squared distance is over the chi-square quantile ``quantile`` times ``slack``. A text without words has no vector and
is rejected. Null language or source: a group of their own. Rows are judged alone; repeated rows get the same verdict."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from probgraph.runtime import cut, small, stage

P = 6
PRIOR = 40.0
TYPICAL = (0.03, 0.03, 0.003, 0.01)
FLOOR = np.array([0.3, 0.08, 0.05, 0.07, 0.07, 0.07])
SHARE, MIN_ROWS, QUANTILE, SLACK, STEPS = 0.75, 200, 0.9999, 1.6, 5
BINS_PER_OCTAVE = 8


def _gamma_p(a: float, x: float) -> float:
    term = total = 1 / a
    n = a
    while term > total * 1e-15:
        n += 1
        term *= x / n
        total += term
    return total * math.exp(-x + a * math.log(x) - math.lgamma(a)) if x > 0 else 0.0


@cache
def chi2_quantile(q: float, p: int) -> float:
    lo, hi = 0.0, 200.0
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if _gamma_p(p / 2, mid / 2) < q else (lo, mid)
    return lo


def consistency(share: float, p: int = P) -> float:
    """Factor by which the covariance of the nearest ``share`` of normal rows has to grow."""
    return share / _gamma_p(p / 2 + 1, chi2_quantile(share, p) / 2)


_UP, _LOW, _DIGIT, _SPACE, _SYM, _MORE = 0, 1, 2, 3, 4, 5


def _kinds() -> np.ndarray:
    kind = np.full(256, _SYM, np.uint8)
    for b in range(256):
        c = chr(b)
        if b >= 0xC0:
            kind[b] = _LOW
        elif b >= 0x80:
            kind[b] = _MORE
        elif c.isupper():
            kind[b] = _UP
        elif c.islower():
            kind[b] = _LOW
        elif c.isdigit():
            kind[b] = _DIGIT
        elif c.isspace():
            kind[b] = _SPACE
    kind[ord(".")] = kind[ord(",")] = kind[ord("'")] = _MORE
    return kind


KINDS = _kinds()


def vector(text: str | None) -> list[float] | None:
    """Transformed statistics of a text; None without words."""
    words = (text or "").split()
    if not words:
        return None
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    n = np.bincount(KINDS[raw], minlength=6)
    letters, chars = int(n[_UP] + n[_LOW]), len(raw) - int(n[_MORE]) - int(n[_SPACE])
    same = sum(map(str.__eq__, words, words[1:]))
    shares = ((int(n[_UP]), letters), (int(n[_SYM]), chars), (int(n[_DIGIT]), chars), (same, len(words)))
    out = [math.log1p(len(words)), math.log((letters + PRIOR * 5) / (len(words) + PRIOR))]
    return out + [math.asin(math.sqrt(min(1.0, (x + PRIOR * t) / (m + PRIOR)))) for (x, m), t in zip(shares, TYPICAL)]


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vectors(text: pd.Series) -> pd.Series:
    return text.map(vector)


def _distance(z: pd.Series, mean: pd.Series, inverse: pd.Series) -> np.ndarray:
    z, m = np.array(z.tolist(), float).reshape(-1, P), np.array(mean.tolist(), float).reshape(-1, P)
    w = np.array(inverse.tolist(), float).reshape(-1, P, P)
    d = z - m
    return np.einsum("ij,ijk,ik->i", d, w, d)


@F.pandas_udf(T.DoubleType())
def distance(z: pd.Series, mean: pd.Series, inverse: pd.Series) -> pd.Series:
    return pd.Series(_distance(z, mean, inverse))


def _solve(n: float, s: np.ndarray, ss: np.ndarray, factor: float) -> tuple[np.ndarray, np.ndarray, float]:
    mean = s / n
    cov = (ss / n - np.outer(mean, mean)) * factor
    low = np.maximum(0, FLOOR**2 - np.diag(cov))
    cov = cov + np.diag(low) + np.diag(FLOOR**2 * 1e-3)
    return mean, np.linalg.inv(cov), float(np.linalg.slogdet(cov)[1])


_PAIRS = [(i, j) for i in range(P) for j in range(i, P)]


def _moments(z: str) -> list[F.Column]:
    one = [F.sum(F.col(z)[i]).alias(f"s{i}") for i in range(P)]
    return [F.count("*").alias("n"), *one, *[F.sum(F.col(z)[i] * F.col(z)[j]).alias(f"q{i}_{j}") for i, j in _PAIRS]]


def _sums() -> list[F.Column]:
    return [F.sum(c).alias(c) for c in ["n", *[f"s{i}" for i in range(P)], *[f"q{i}_{j}" for i, j in _PAIRS]]]


def _solved(df: DataFrame, factor: float) -> DataFrame:
    """Moments to (g, start, mean, inverse, logdet)."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            rows = []
            for r in part.itertuples(index=False):
                d = r._asdict()
                ss = np.zeros((P, P))
                for i, j in _PAIRS:
                    ss[i, j] = ss[j, i] = d[f"q{i}_{j}"]
                mean, inv, det = _solve(d["n"], np.array([d[f"s{i}"] for i in range(P)]), ss, factor)
                rows.append((d["g"], d["start"], mean.tolist(), inv.ravel().tolist(), det))
            yield pd.DataFrame(rows, columns=["g", "start", "mean", "inverse", "logdet"])

    return df.mapInPandas(run, "g string, start int, mean array<double>, inverse array<double>, logdet double")


def estimates(rows: DataFrame, share: float = SHARE, steps: int = STEPS) -> DataFrame:
    """(g, mean, inverse) of rows (g, z)."""
    mid = rows.groupBy("g").agg(*[F.percentile_approx(F.col("z")[i], F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), 1000).alias(f"m{i}") for i in range(P)])

    def first(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            out = []
            for r in part.itertuples(index=False):
                q = np.array([list(x) for x in r[1:]], float)
                sd = np.maximum((q[:, 2] - q[:, 0]) / 1.349, FLOOR)
                for start, times in enumerate((1.0, 0.5)):
                    out.append((r[0], start, q[:, 1].tolist(), np.diag(1 / (sd * times) ** 2).ravel().tolist(), 0.0) if times == 1 else (r[0], start, q[:, 1].tolist(), np.diag(1 / np.where(np.arange(P) < 2, sd * times, sd) ** 2).ravel().tolist(), 0.0))
            yield pd.DataFrame(out, columns=["g", "start", "mean", "inverse", "logdet"])

    now = cut(mid.mapInPandas(first, "g string, start int, mean array<double>, inverse array<double>, logdet double"))
    best = Window.partitionBy("g")
    for step in range(steps):
        now = cut(_step(rows, now, share))
    now = now.withColumn("rank", F.row_number().over(best.orderBy("logdet", "start"))).filter("rank = 1").drop("rank")
    # reweighting: the rows within the 97.5 % ellipsoid
    limit = chi2_quantile(0.975, P)
    near = rows.join(small(cut(now)), "g").withColumn("d", distance("z", "mean", "inverse")).filter(F.col("d") <= limit)
    return _solved(near.groupBy("g").agg(*_moments("z")).withColumn("start", F.lit(0)), consistency(0.975)).select("g", "mean", "inverse")


def _step(rows: DataFrame, now: DataFrame, share: float) -> DataFrame:
    """One concentration step of every group and start."""
    by = ("g", "start")
    bins = rows.join(small(now), "g").withColumn("d", distance("z", "mean", "inverse")).withColumn("bin", F.floor(F.log2(F.col("d") + 1e-9) * BINS_PER_OCTAVE)).groupBy(*by, "bin").agg(*_moments("z"))
    order = Window.partitionBy(*by).orderBy("bin")
    kept = (
        bins.withColumn("before", F.coalesce(F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("all", F.sum("n").over(Window.partitionBy(*by)))
        .filter(F.col("before") < F.col("all") * share)
    )
    return _solved(kept.groupBy(*by).agg(*_sums()), consistency(share))


def judged(docs: DataFrame, share: float = SHARE, min_rows: int = MIN_ROWS, quantile: float = QUANTILE, slack: float = SLACK, steps: int = STEPS, keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (all but the text by default) with ``distance2`` (null without words) and ``rejected``.

    Columns of these names give way."""
    docs = docs.drop("distance2", "rejected")
    keep = [c for c in docs.columns if c != "text"] if keep is None else keep
    z, g, own = "stat_vector", "stat_group", "stat_own"
    inner = [f"c{i}" for i in range(len(keep))]  # names that nothing here clashes with
    lang = F.coalesce(F.col("lang").cast("string"), F.lit("\x00"))
    both = F.concat_ws("\x01", F.lit("s"), lang, F.coalesce(F.col("source").cast("string"), F.lit("\x00")))
    slim = docs.select(*[F.col(f"`{c}`").alias(i) for c, i in zip(keep, inner)], vectors(F.coalesce("text", F.lit(""))).alias(z), both.alias(own), F.concat_ws("\x01", F.lit("l"), lang).alias(g))
    slim = stage(slim)
    live = slim.filter(F.col(z).isNotNull())
    counts = live.groupBy(own, g).count()
    of = Window.partitionBy(g)
    level = F.when(F.col("count") >= min_rows, F.col(own)).when(F.sum("count").over(of) >= min_rows, F.col(g)).otherwise(F.lit("all"))
    used = cut(counts.select(own, level.alias("level")))
    # a coarse group is estimated from all of its rows, those of its large sources too
    need = cut(used.select(F.col("level").alias("g")).distinct())
    spread = live.select(F.col(z).alias("z"), F.explode(F.array(F.col(own), F.col(g), F.lit("all"))).alias("g")).join(small(need), "g", "left_semi")
    found = small(cut(used.join(estimates(spread, share, steps), F.col("level") == F.col("g")).select(F.col(own).alias("key"), "mean", "inverse")))
    limit = chi2_quantile(quantile, P) * slack
    out = slim.join(found, F.col(own) == F.col("key"), "left")
    d = F.when(F.col(z).isNotNull(), distance(F.coalesce(F.col(z), F.array(*[F.lit(0.0)] * P)), F.coalesce("mean", F.array(*[F.lit(0.0)] * P)), F.coalesce("inverse", F.array(*[F.lit(0.0)] * (P * P)))))
    return out.withColumn("distance2", F.round(d, 6)).withColumn("rejected", F.coalesce(F.col("distance2") > limit, F.lit(True))).select(*[F.col(i).alias(c) for c, i in zip(keep, inner)], "distance2", "rejected")


def kept(docs: DataFrame, **params) -> DataFrame:
    """The rows of ``docs`` that the rules don't reject, columns unchanged.

    The verdict is found per distinct (doc_id, language, source, text hash) and joined back."""
    d = docs.select(F.col("doc_id"), "lang", "source", "text", F.xxhash64("text").alias("rule_hash"))
    bad = judged(d, **params).filter("rejected").select(F.col("doc_id").alias("rule_doc"), F.col("lang").alias("rule_lang"), F.col("source").alias("rule_source"), F.col("rule_hash")).distinct()
    bad = small(cut(bad))
    on = docs.doc_id.eqNullSafe(bad.rule_doc) & docs.lang.eqNullSafe(bad.rule_lang) & docs.source.eqNullSafe(bad.rule_source) & (F.xxhash64(docs.text) == bad.rule_hash)
    return docs.join(bad, on, "left_anti")
