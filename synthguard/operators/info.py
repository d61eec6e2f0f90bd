"""Histograms of attributes and pairs, entropies with and without noise, correlations."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from synthguard.functions.noise import laplace_value
from synthguard.functions.scalar import entropy_bits
from synthguard.operators.prep import bucket
from synthguard.plans.budget import entropy_sensitivity
from synthguard.plans.schema import Schema

_SCHEMA = "role string, i int, j int, vi int, vj int, c long"


def joint_histograms(df: DataFrame, schema: Schema, family: str = "paper_count", groups: int | None = None) -> DataFrame:
    """role, i, j, vi, vj, c: counts of x_i (role x), b(x_i) (role b), and (x_i, b(x_j)) (role xb) for all i, j apart;
    with family bucket_pairs those of (b(x_i), b(x_j)) for i < j (role bb) as well. With groups, df has _g (0..groups - 1), and each
    group is counted by itself (g).

    One scan: each task counts all of them in fixed arrays and sends each once, however many rows it has read.
    """
    names, m = schema.names, len(schema)
    cards, cuts = [a.card for a in schema.attributes], [a.buckets for a in schema.attributes]
    lookup = [np.array(a.bucket_of, np.int64) for a in schema.attributes]
    sets = [("x", i, -1, cards[i], 1) for i in range(m)] + [("b", i, -1, cuts[i], 1) for i in range(m)]
    sets += [("xb", i, j, cards[i], cuts[j]) for i in range(m) for j in range(m) if i != j]
    if family == "bucket_pairs":
        sets += [("bb", i, j, cuts[i], cuts[j]) for i in range(m) for j in range(i + 1, m)]

    def count(batches):
        total = [np.zeros((groups or 1) * a * b, np.int64) for *_, a, b in sets]
        for batch in batches:
            x = [batch.column(n).to_numpy(zero_copy_only=False).astype(np.int64) for n in names]
            b = [lookup[i][x[i]] for i in range(m)]
            g = batch.column("_g").to_numpy(zero_copy_only=False).astype(np.int64) if groups else 0
            for t, (role, i, j, ca, cb) in zip(total, sets, strict=True):
                left = g * ca + (b[i] if role in ("b", "bb") else x[i])
                t += np.bincount(left * cb + b[j] if j >= 0 else left, minlength=len(t))
        for t, (role, i, j, ca, cb) in zip(total, sets, strict=True):
            at = np.flatnonzero(t)
            if len(at):
                n = len(at)
                columns = [pa.array([role] * n), *(pa.array(np.full(n, v, np.int32)) for v in (i, j)), pa.array((at // cb % ca).astype(np.int32)), pa.array((at % cb).astype(np.int32)), pa.array(t[at]), pa.array((at // cb // ca).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(columns, names=["role", "i", "j", "vi", "vj", "c", "g"])

    own = ["g"] if groups else []
    return df.select(*names, *(["_g"] if groups else [])).mapInArrow(count, f"{_SCHEMA}, g int").groupBy(*own, "role", "i", "j", "vi", "vj").agg(F.sum("c").alias("c"))


def entropies(df: DataFrame, schema: Schema, family: str = "paper_count") -> DataFrame:
    """role, i, j, h (bits)."""
    return joint_histograms(df, schema, family).groupBy("role", "i", "j").agg(entropy_bits(F.col("c")).alias("h"))


def entropy_sets(df: DataFrame, schema: Schema, family: str = "paper_count") -> tuple[dict, int]:
    """(role, i, j) -> bits, and the number of rows: m(m+1) numbers for the driver."""
    rows = joint_histograms(df, schema, family).groupBy("role", "i", "j").agg(entropy_bits(F.col("c")).alias("h"), F.sum("c").alias("n")).collect()
    return {(r["role"], r["i"], r["j"]): r["h"] for r in rows}, int(rows[0]["n"]) if rows else 0


def entropy_sets_of(df: DataFrame, schema: Schema, groups: int) -> list[tuple[dict, int]]:
    """As entropy_sets(), for each group of df (_g): one scan for all. A group without rows has entropies of 0."""
    m = range(len(schema))
    out = [({k: 0.0 for k in [(role, i, -1) for role in "xb" for i in m] + [("xb", i, j) for i in m for j in m if i != j]}, 0) for _ in range(groups)]
    for r in joint_histograms(df, schema, groups=groups).groupBy("g", "role", "i", "j").agg(entropy_bits(F.col("c")).alias("h"), F.sum("c").alias("n")).collect():
        values = out[r["g"]][0]
        values[r["role"], r["i"], r["j"]] = r["h"]
        out[r["g"]] = (values, int(r["n"]))
    return out


def with_noise(values: dict, n: int, eps_entropy: float, eps_size: float, salt: str) -> dict:
    """Each entropy with its own Laplace noise, scaled by the sensitivity bound at a noisy record count (2 at least)."""
    noisy_n = max(2.0, n + laplace_value(1 / eps_size, salt, "size"))
    scale = entropy_sensitivity(noisy_n) / eps_entropy
    return {k: h + laplace_value(scale, salt, *k) for k, h in values.items()}


def correlations(values: dict, m: int) -> np.ndarray:
    """c[i, j]: symmetrical uncertainty of x_i and b(x_j), within [0, 1]; the diagonal is 1."""
    c = np.eye(m)
    for i in range(m):
        for j in range(m):
            if i != j:
                total = values["x", i, -1] + values["b", j, -1]
                c[i, j] = 0.0 if total <= 0 else min(1.0, max(0.0, 2 - 2 * values["xb", i, j] / total))
    return c


def merit(i: int, parents, c: np.ndarray) -> float:
    """Correlation of the parents with the child against their redundancy; ordered pairs of different parents count."""
    if not parents:
        return 0.0
    return sum(c[i, j] for j in parents) / math.sqrt(len(parents) + sum(c[j, k] for j in parents for k in parents if j != k))


def spurious_floor(values: dict, schema: Schema, n: int, i: int, j: int) -> float:
    """Symmetrical uncertainty that independent columns show on n rows, from the domains' sizes."""
    total = values["x", i, -1] + values["b", j, -1]
    a, b = schema.attributes[i], schema.attributes[j]
    return (a.card - 1) * (b.buckets - 1) / (n * math.log(2) * total) if total > 0 else 0.0


def bucketized(df: DataFrame, schema: Schema) -> DataFrame:
    return df.select(*[bucket(schema, n).alias(n) for n in schema.names])
