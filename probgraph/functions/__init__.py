"""Column functions, sample-size rules and their SQL registration."""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

SEED = 42
WORD = 4294967296.0


def edge_prob(x: Column, scale: float = 2.0) -> Column:
    """Probability of an edge after x interactions."""
    return 1 - F.exp(-x / F.lit(float(scale)))


def conn_distance(p: Column) -> Column:
    """ln(1/p); infinite at 0."""
    return F.when(p > 0, -F.log(p)).otherwise(F.lit(float("inf")))


def coin(seed: int, world: Column, src: Column, dst: Column, fast: bool = False) -> Column:
    """32-bit draw of an edge in a world. ``fast`` takes xxhash64 instead of md5, which DuckDB doesn't have."""
    if fast:
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), world, src, dst), 32)
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed).cast("string"), world.cast("string"), src.cast("string"), dst.cast("string"))), 1, 8), 16, 10).cast("long")


def agreement(a: Column, b: Column) -> Column:
    """Worlds in which two signatures have the same label."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, v: s + v)


def needed(q: float, r: int, eps: float = 0.0) -> int:
    """Least number of agreeing worlds that passes threshold q (1 - eps/2)."""
    return max(0, math.ceil((1 - eps / 2) * q * r - 1e-9))


def harmonic(n: int) -> float:
    return math.fsum(1 / i for i in range(1, n + 1))


def samples_pair(eps: float, delta: float, p_floor: float) -> int:
    """Worlds for relative error eps with confidence 1 - delta on probabilities of at least p_floor."""
    return math.ceil(3 * math.log(2 / delta) / (eps * eps * p_floor))


def _guesses(x: float, gamma: float) -> int:
    return 1 + math.floor(math.log(x) / math.log(1 + gamma) + 1e-12)


def samples_min(n: int, q: float, eps: float, gamma: float = 0.1, p_floor: float = 1e-4) -> int:
    """Worlds that the weakest-connection guarantee asks for at guess q."""
    return math.ceil(12 / (q * eps * eps) * math.log(2 * n**3 * _guesses(1 / p_floor, gamma)))


def samples_avg(n: int, q: float, eps: float, gamma: float = 0.1, p_floor: float = 1e-4) -> int:
    """Worlds that the mean-connection guarantee asks for at guess q."""
    return math.ceil(12 / (q**3 * eps * eps) * math.log(2 * n**3 * _guesses(harmonic(n) / p_floor, gamma)))


def samples_free(n: int, q: float, eps: float, attempt: int, delta: float = 0.05) -> int:
    """Worlds for the attempt-th guess (from 1) when no floor is given: the attempts' failure probabilities delta / (2 i^2) add up to less than delta."""
    return math.ceil(12 / (q * eps * eps) * math.log(2 * n * n * 2 * attempt * attempt / delta))


def register(spark: SparkSession) -> None:
    """SQL functions, inlined by the optimizer."""
    for text in (
        "edge_prob(x DOUBLE) RETURNS DOUBLE RETURN 1 - exp(-x / 2)",
        "conn_distance(p DOUBLE) RETURNS DOUBLE RETURN CASE WHEN p > 0 THEN -ln(p) ELSE double('inf') END",
        "sig_agree(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS INT RETURN aggregate(zip_with(a, b, (x, y) -> int(x = y)), 0, (s, v) -> s + v)",
        "samples_pair(e DOUBLE, d DOUBLE, p DOUBLE) RETURNS BIGINT RETURN ceil(3 * ln(2 / d) / (e * e * p))",
        "samples_min(n DOUBLE, q DOUBLE, e DOUBLE, g DOUBLE, pl DOUBLE) RETURNS BIGINT RETURN ceil(12 / (q * e * e) * ln(2 * pow(n, 3) * (1 + floor(ln(1 / pl) / ln(1 + g)))))",
        "samples_avg(n INT, q DOUBLE, e DOUBLE, g DOUBLE, pl DOUBLE) RETURNS BIGINT RETURN ceil(12 / (pow(q, 3) * e * e) * ln(2 * pow(n, 3) * (1 + floor(ln(aggregate(sequence(1, n), 0D, (s, i) -> s + 1D / i) / pl) / ln(1 + g)))))",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
