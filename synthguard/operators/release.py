"""The release mechanism: seeds, candidates, test, and the records that pass."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from synthguard.functions.noise import uniform
from synthguard.operators.deniability import capped, deterministic, mixture_counts, plausible_counts, randomized
from synthguard.operators.prep import sample_seeds
from synthguard.operators.synth import Model, synthesize, synthesize_random
from synthguard.plans.schema import DeniabilityParams


def judged(model: Model, seeds: DataFrame, params: DeniabilityParams, omega, salt: str, drawn: DataFrame, test: str = "randomized", omega_mode: str = "per_candidate") -> DataFrame:
    """All candidates with plausible and passed (for evaluation; not for release)."""
    n = seeds.count()
    if n < params.k:
        raise ValueError(f"{n} seeds are fewer than k = {params.k}")
    cands = synthesize(model, drawn, omega, salt) if isinstance(omega, int) else synthesize_random(model, drawn, omega, salt)
    if omega_mode == "mixture" and not isinstance(omega, int):
        order = [model.schema.names[i] for i in model.graph.order]
        own = drawn.select("cand_id", F.struct(*order).alias("_seed"))
        same, depth = F.lit(True), F.lit(0)
        for a in order:
            same = same & (F.col(a) == F.col(f"_seed.{a}"))
            depth = depth + F.when(same, 1).otherwise(0)
        counted = mixture_counts(model, cands.join(own, "cand_id").withColumn("depth", depth).drop("_seed"), seeds, omega, params.gamma).drop("depth", "bucket")
    else:
        counted = plausible_counts(model, cands, seeds, [omega] if isinstance(omega, int) else sorted(set(omega)))
    if params.max_plausible is not None or params.max_check is not None:
        counted = capped(counted, n, params.max_plausible or n, params.max_check or n, salt)
    return deterministic(counted, params.k) if test == "deterministic" else randomized(counted, params.k, params.eps0, salt)


def release(model: Model, seeds: DataFrame, params: DeniabilityParams, n_candidates: int, omega, salt: str, test: str = "randomized", omega_mode: str = "per_candidate", how: str = "rank") -> DataFrame:
    """Synthetic records that passed: attributes only, no ids, counts or verdicts."""
    drawn = sample_seeds(seeds, n_candidates, salt, how)
    return judged(model, seeds, params, omega, salt, drawn, test, omega_mode).where("passed").select(*model.schema.names)


def pooled_release(model: Model, seeds: DataFrame, params: DeniabilityParams, n_candidates: int, omegas, n_out: int, salt: str) -> DataFrame:
    """Records released at several omegas, n_out of them drawn at random."""
    pool = None
    for w in omegas:
        drawn = sample_seeds(seeds, n_candidates, f"{salt}-{w}")
        one = judged(model, seeds, params, w, f"{salt}-{w}", drawn).where("passed").select(*model.schema.names, uniform(f"{salt}-pool-{w}", "cand_id").alias("_u"))
        pool = one if pool is None else pool.unionByName(one)
    return pool.orderBy("_u").limit(n_out).drop("_u")
