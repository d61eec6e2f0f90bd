"""Scalar functions of the privacy tests and measures, as column expressions and for SQL."""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def gamma_bucket(logp: Column, gamma: float) -> Column:
    """The integer i >= 0 with gamma**-(i+1) < p <= gamma**-i; null for p = 0 (logp null or -inf).

    Worked in logarithms, then corrected by one step where rounding has put an exact power on the wrong side.
    """
    if gamma <= 1:
        raise ValueError("gamma must exceed 1")
    step = math.log(gamma)
    i = F.floor(-logp / step)
    edge = 1e-12 * F.greatest(F.lit(1.0), F.abs(logp))
    up = F.abs(-logp - (i + 1) * step) <= edge  # p is the power i + 1 but for rounding
    fixed = F.when(up, i + 1).otherwise(i)
    return F.when(logp.isNull() | (logp == float("-inf")), F.lit(None)).otherwise(F.greatest(fixed, F.lit(0))).cast("long")


def pass_probability(plausible: Column, k: float, eps0: float) -> Column:
    """Chance that plausible seeds reach a threshold k with Laplace(1/eps0) noise on it."""
    d = plausible - F.lit(float(k))
    return F.when(d >= 0, 1 - 0.5 * F.exp(-eps0 * d)).otherwise(0.5 * F.exp(eps0 * d))


def sym_uncertainty(hi: Column, hj: Column, hij: Column) -> Column:
    """2 - 2 H(i,j) / (H(i) + H(j)) within [0, 1]; 0 where both entropies vanish."""
    total = hi + hj
    return F.when(total <= 0, F.lit(0.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), 2 - 2 * hij / total)))


def entropy_bits(c: Column) -> Column:
    """Aggregate: entropy of counts, log2(n) - sum(c log2 c) / n."""
    n = F.sum(c)
    return F.log2(n) - F.sum(F.when(c > 0, c * F.log2(c)).otherwise(0.0)) / n


def register(spark: SparkSession) -> None:
    """The functions under their names in SQL (SQL-defined, so they stay in the JVM)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gamma_bucket(logp DOUBLE, gamma DOUBLE) RETURNS BIGINT RETURN CASE WHEN logp IS NULL OR logp = double('-inf') THEN NULL WHEN abs(-logp - (floor(-logp / ln(gamma)) + 1) * ln(gamma)) <= 1e-12 * greatest(1.0D, abs(logp)) THEN greatest(CAST(floor(-logp / ln(gamma)) AS BIGINT) + 1, 0L) ELSE greatest(CAST(floor(-logp / ln(gamma)) AS BIGINT), 0L) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pass_probability(plausible DOUBLE, k DOUBLE, eps0 DOUBLE) RETURNS DOUBLE RETURN CASE WHEN plausible >= k THEN 1 - 0.5 * exp(-eps0 * (plausible - k)) ELSE 0.5 * exp(-eps0 * (k - plausible)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sym_uncertainty(hi DOUBLE, hj DOUBLE, hij DOUBLE) RETURNS DOUBLE RETURN CASE WHEN hi + hj <= 0 THEN 0 ELSE greatest(0, least(1, 2 - 2 * hij / (hi + hj))) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION keyed_uniform(k STRING) RETURNS DOUBLE RETURN (CAST(conv(substring(sha2(k, 256), 1, 13), 16, 10) AS DOUBLE) + 0.5) / 4503599627370496")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION laplace_noise(scale DOUBLE, u DOUBLE) RETURNS DOUBLE RETURN -scale * sign(u - 0.5) * ln(1 - 2 * abs(u - 0.5))")
