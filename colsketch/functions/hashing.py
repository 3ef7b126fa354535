"""Hashes that give the same values in Spark and in DuckDB: pure expressions, never rand() inside a plan.

Each function has a SQL twin with suffix _sql for the oracles. Coefficients come from MD5 of (seed, role, index).
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import cut

PRIME = (1 << 31) - 1


def coefficient(seed: int, role: str, k: int) -> int:
    return 1 + int(hashlib.md5(f"{seed}/{role}/{k}".encode()).hexdigest()[:12], 16) % (PRIME - 1)


def bucket_of(i: Column, r: int, seed: int, family: str = "poly") -> Column:
    """g(i) in 0..r-1, linear modulo 2^31 - 1. family 'xxhash64' is faster and has no SQL twin (extension)."""
    if family == "xxhash64":
        return F.pmod(F.xxhash64(i, F.lit(seed)), F.lit(r)).cast("int")
    a, b = coefficient(seed, "bucket", 0), coefficient(seed, "bucket", 1)
    x = F.pmod(i.cast("long"), F.lit(PRIME))
    return F.pmod(F.pmod(x * a + b, F.lit(PRIME)), F.lit(r)).cast("int")


def bucket_of_sql(i: str, r: int, seed: int) -> str:
    a, b = coefficient(seed, "bucket", 0), coefficient(seed, "bucket", 1)
    return f"CAST(((({i} % {PRIME}) * {a}::BIGINT + {b}) % {PRIME}) % {r} AS INTEGER)"


def sign_of(i: Column, seed: int, signs: str = "random") -> Column:
    """sigma(i) in {-1, 1}: the low bit of a cubic polynomial modulo 2^31 - 1. signs 'identity' is the ablation without signs."""
    if signs == "identity":
        return F.lit(1)
    x = F.pmod(i.cast("long"), F.lit(PRIME))
    h = F.lit(coefficient(seed, "sign", 0)).cast("long")
    for k in range(1, 4):
        h = F.pmod(h * x + coefficient(seed, "sign", k), F.lit(PRIME))
    return (F.pmod(h, F.lit(2)) * 2 - 1).cast("int")


def sign_of_sql(i: str, seed: int) -> str:
    h = f"{coefficient(seed, 'sign', 0)}::BIGINT"
    for k in range(1, 4):
        h = f"(({h} * ({i} % {PRIME}) + {coefficient(seed, 'sign', k)}) % {PRIME})"
    return f"CAST(({h} % 2) * 2 - 1 AS INTEGER)"


def _cubic(seed: int, role: str) -> list[int]:
    return [coefficient(seed, role, k) for k in range(4)]


def drawn(i: Column, fraction: float, seed: int, role: str) -> Column:
    """Whether i is in a hash sample of that share: a cubic polynomial modulo 2^31 - 1 below fraction x (2^31 - 1)."""
    c, x = _cubic(seed, role), F.pmod(i.cast("long"), F.lit(PRIME))
    h = F.lit(c[0]).cast("long")
    for k in c[1:]:
        h = F.pmod(h * x + k, F.lit(PRIME))
    return h < int(fraction * PRIME)


def drawn_sql(i: str, fraction: float, seed: int, role: str) -> str:
    c = _cubic(seed, role)
    h = f"{c[0]}::BIGINT"
    for k in c[1:]:
        h = f"(({h} * ({i} % {PRIME}) + {k}) % {PRIME})"
    return f"({h} < {int(fraction * PRIME)})"


def drawn_array(i: np.ndarray, fraction: float, seed: int, role: str) -> np.ndarray:
    """drawn() for an array of ids that are not negative."""
    c, x = _cubic(seed, role), (i % PRIME).astype(np.uint64)
    h = np.full(len(x), c[0], np.uint64)
    for k in c[1:]:
        h = (h * x + np.uint64(k)) % np.uint64(PRIME)
    return h < int(fraction * PRIME)


def signs_array(i: np.ndarray, seed: int) -> np.ndarray:
    """sign_of() for an array of ids."""
    x = (i % PRIME).astype(np.uint64)
    h = np.full(len(x), coefficient(seed, "sign", 0), np.uint64)
    for k in range(1, 4):
        h = (h * x + np.uint64(coefficient(seed, "sign", k))) % np.uint64(PRIME)
    return (h % np.uint64(2)).astype(float) * 2 - 1


def random_columns(features: DataFrame, r: int, seed: int) -> DataFrame:
    """(feature_id, bucket, sign) from Spark's generator, for statistics only: written once to the checkpoint folder, as
    another evaluation could draw anew. The hash families give the same values everywhere and are the ones to sketch with."""
    return cut(features.select("feature_id", F.floor(F.rand(seed) * r).cast("int").alias("bucket"), F.when(F.randn(seed + 1) < 0, -1).otherwise(1).alias("sign")))


def uniform_of(seed: int, *parts: Column) -> Column:
    """A uniform draw in (0, 1) from the first 8 digits of an MD5."""
    text = F.concat_ws(":", F.lit(str(seed)), *[p.cast("string") for p in parts])
    return (F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") + 0.5) / 4294967296.0


def uniform_of_sql(seed: int, *parts: str) -> str:
    text = " || ':' || ".join([f"'{seed}'", *[f"CAST({p} AS VARCHAR)" for p in parts]])
    return f"((('0x' || substr(md5({text}), 1, 8))::BIGINT + 0.5) / 4294967296.0)"


def normal_of(seed: int, *parts: Column) -> Column:
    """A standard normal draw by two uniform ones."""
    u, v = uniform_of(seed, *parts, F.lit("u")), uniform_of(seed, *parts, F.lit("v"))
    return F.sqrt(-2.0 * F.log(u)) * F.cos(2.0 * F.pi() * v)


def normal_of_sql(seed: int, *parts: str) -> str:
    u, v = uniform_of_sql(seed, *parts, "'u'"), uniform_of_sql(seed, *parts, "'v'")
    return f"(sqrt(-2.0 * ln({u})) * cos(2.0 * pi() * {v}))"


def sample_features(features: DataFrame, k: int, seed: int, salt: str = "") -> DataFrame:
    """k features, those with the smallest hashes: (feature_id, bucket) with bucket in that order. One top-k."""
    top = features.select("feature_id", F.md5(F.concat_ws(":", F.lit(f"{seed}{salt}"), F.col("feature_id").cast("string"))).alias("h")).orderBy("h", "feature_id").limit(k)
    return top.selectExpr("feature_id", "cast(row_number() over (order by h, feature_id) - 1 as int) as bucket")


def sample_features_sql(features: str, k: int, seed: int, salt: str = "") -> str:
    return f"SELECT feature_id, CAST(row_number() OVER (ORDER BY h, feature_id) - 1 AS INTEGER) AS bucket FROM (SELECT feature_id, md5('{seed}{salt}:' || CAST(feature_id AS VARCHAR)) AS h FROM {features}) ORDER BY h, feature_id LIMIT {k}"
