"""Privacy tests of candidates against the seeds, and the definition they enforce.

For a re-sampling model the likelihood of a candidate is the same under every seed that shares the kept attributes, and 0
under all others; so plausible seeds are counted by a hash aggregate over prefixes of the re-sampling order and an
equi-join, in place of a scan of all seeds for each candidate. The generic test scans, for any likelihood.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from synthguard.functions.noise import laplace, uniform
from synthguard.functions.scalar import gamma_bucket
from synthguard.operators.synth import Model, log_q


def prefix_counts(seeds: DataFrame, order: list[str], depths) -> DataFrame:
    """depth, the first attributes of order (null beyond depth), n: one rollup serves all depths."""
    deepest = max(depths)
    if deepest == 0:
        return seeds.agg(F.count("*").alias("n")).select(F.lit(0).alias("depth"), "n")
    names = order[:deepest]
    rolled = seeds.rollup(*names).agg(F.count("*").alias("n"), F.grouping_id().alias("_g"))
    # a prefix of depth d has its last deepest - d columns rolled up
    depth = F.lit(deepest) - F.bit_count(F.col("_g"))
    return rolled.select(depth.cast("int").alias("depth"), *names, "n").where(F.col("depth").isin(*map(int, depths)))


def plausible_counts(model: Model, candidates: DataFrame, seeds: DataFrame, omegas=None) -> DataFrame:
    """candidates (with omega) and plausible: how many seeds could have given them, for omega known with the candidate.
    omegas: those that candidates may have; looked up where they aren't told."""
    omegas = sorted(set(omegas or [r[0] for r in candidates.select("omega").distinct().collect()]))  # at most m
    if not omegas:
        return candidates.withColumn("plausible", F.lit(0).cast("long"))
    order, m = [model.schema.names[i] for i in model.graph.order], model.m
    # one index of all depths, one scan of the candidates: attributes beyond a candidate's depth are blanked on both sides
    deepest = max(m - w for w in omegas)
    index = prefix_counts(seeds, order, [m - w for w in omegas])
    names = order[:deepest]
    index = index.select(F.col("depth").alias("_depth"), *[(F.when(F.col("depth") > j, F.col(a)).otherwise(F.lit(-1))).alias(f"_p{j}") for j, a in enumerate(names)], F.col("n").alias("_n"))
    depth = F.lit(m) - F.col("omega")
    asked = candidates.withColumn("_depth", depth).withColumns({f"_p{j}": F.when(depth > j, F.col(a)).otherwise(F.lit(-1)) for j, a in enumerate(names)})
    done = asked.join(index, ["_depth", *[f"_p{j}" for j in range(deepest)]], "left")
    return done.select(*candidates.columns, F.coalesce("_n", F.lit(0)).cast("long").alias("plausible"))


def mixture_counts(model: Model, candidates: DataFrame, seeds: DataFrame, omegas, gamma: float) -> DataFrame:
    """plausible for a model that draws omega from a set and does not tell it: by depth of agreement with the candidate,
    seeds are as likely as the sum over the omegas they allow; those in the true seed's gamma bucket count.

    candidates carry depth: how far their own seed agrees (see match_depth)."""
    omegas = sorted(set(omegas))
    order = [model.schema.names[i] for i in model.graph.order]
    depths = sorted({model.m - w for w in omegas})
    df = log_q(model, candidates, omegas)
    for d in depths:
        if d:
            names = order[:d]
            df = df.join(seeds.groupBy(*names).agg(F.count("*").alias(f"_n{d}")), names, "left").withColumn(f"_n{d}", F.coalesce(f"_n{d}", F.lit(0)))
        else:
            df = df.crossJoin(F.broadcast(seeds.agg(F.count("*").alias("_n0"))))
    # seeds agreeing to exactly this tier of depths, and their log likelihood (log-sum-exp over the omegas they allow)
    share, tiers = -math.log(len(omegas)), []
    for k, d in enumerate(depths):
        exact = F.col(f"_n{d}") - (F.col(f"_n{depths[k + 1]}") if k + 1 < len(depths) else F.lit(0))
        terms = [F.col(f"q_{w}") for w in omegas if model.m - w <= d]
        top = F.greatest(*terms) if len(terms) > 1 else terms[0]
        logp = top + F.ln(sum((F.exp(t - top) for t in terms), F.lit(0.0))) + share
        tiers.append((d, exact, gamma_bucket(logp, gamma)))
    own = F.lit(None).cast("long")
    for d, _, b in tiers:
        own = F.when(F.col("depth") >= d, b).otherwise(own)
    count = sum((F.when(b == own, n).otherwise(0) for _, n, b in tiers), F.lit(0))
    return df.select(*candidates.columns, own.alias("bucket"), count.cast("long").alias("plausible"))


def match_depth(order: list[str], a: str, b: str) -> Column:
    """Length of the longest common prefix of two structs in the given order."""
    out = F.lit(0)
    same = F.lit(True)
    for n in order:
        same = same & (F.col(f"{a}.{n}") == F.col(f"{b}.{n}"))
        out = out + F.when(same, 1).otherwise(0)
    return out


def deterministic(counted: DataFrame, k: int) -> DataFrame:
    return counted.withColumn("passed", F.col("plausible") >= k)


def randomized(counted: DataFrame, k: int, eps0: float, salt: str, key: str = "cand_id") -> DataFrame:
    """A threshold with its own Laplace(1/eps0) noise for each candidate, keyed by it: a retried task draws it again alike."""
    return counted.withColumn("threshold", F.lit(float(k)) + laplace(1 / eps0, salt, key, F.lit("threshold"))).withColumn("passed", F.col("plausible") >= F.col("threshold"))


def capped(counted: DataFrame, seeds_total: int, max_plausible: int, max_check: int, salt: str, key: str = "cand_id") -> DataFrame:
    """plausible as a scan of the seeds in random order would leave it that stops after max_check rows or max_plausible
    hits, and checked, the rows looked at: drawn from their laws, at a cost that does not depend on the seeds."""

    def draw(ids: pd.Series, hits: pd.Series) -> pd.DataFrame:
        import hashlib

        found, looked = [], []
        n = min(max_check, seeds_total)
        for c, k in zip(ids, hits, strict=True):
            rng = np.random.Generator(np.random.Philox(key=int.from_bytes(hashlib.sha256(f"{salt}|{c}|scan".encode()).digest()[:16], "little")))
            k = int(k)
            if k == 0 or n == 0:
                found.append(0)
                looked.append(n)
                continue
            if seeds_total < 10**9:
                got = int(rng.hypergeometric(k, seeds_total - k, n))
            else:  # the sampled share is tiny
                got = int(rng.binomial(n, k / seeds_total))
            if got < max_plausible:
                found.append(got)
                looked.append(n)
            else:
                # hits lie at a uniform subset of the n places: where the max_plausible-th of got stands
                place = np.sort(rng.choice(n, got, replace=False))[max_plausible - 1] if got <= 100_000 else int(n * rng.beta(max_plausible, got - max_plausible + 1))
                found.append(max_plausible)
                looked.append(int(place) + 1)
        return pd.DataFrame({"plausible": found, "checked": looked})

    told = F.pandas_udf(draw, "plausible long, checked long")
    keep = [c for c in counted.columns if c not in ("plausible", "checked")]
    return counted.withColumn("_scan", told(F.col(key).cast("string"), F.col("plausible"))).select(*keep, "_scan.plausible", "_scan.checked")


def capped_scan(pairs: DataFrame, max_plausible: int, max_check: int, salt: str, key: str = "cand_id") -> DataFrame:
    """The scan itself, for any model: pairs hold key, rk and plausible (boolean) of every candidate and seed."""
    order = Window.partitionBy(key).orderBy(uniform(salt, key, "rk"), "rk")
    seen = pairs.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= max_check)
    run = seen.withColumn("_k", F.sum(F.col("plausible").cast("long")).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    before = F.col("_k") - F.col("plausible").cast("long")
    return run.where(before < max_plausible).groupBy(key).agg(F.max("_k").alias("plausible"), F.count("*").alias("checked"))


def generic_counts(candidates: DataFrame, seeds: DataFrame, logp: Column, gamma: float, key: str = "cand_id", block: int = 10_000, max_check: int | None = None, salt: str = "scan") -> DataFrame:
    """key, bucket, plausible under any likelihood: every candidate against every seed, by definition of the test.

    candidates: key, y (struct), seed (struct); seeds: d (struct), and rk where max_check is given; logp: over y and d. Candidates come in blocks
    of about `block` by a hash of their key, which bounds what is broadcast; each block scans the seeds once. With max_check each block looks
    at as many seeds as that alone, those with the smallest keyed numbers (a random sample, the same for a block's candidates).
    """
    blocks = max(1, -(-candidates.count() // block))
    own = candidates.select(key, "y", F.col("seed").alias("d")).withColumn("own", gamma_bucket(logp, gamma)).select(key, "y", "own")
    out = None
    for k in range(blocks):
        some = own.where(F.pmod(F.xxhash64(F.col(key)), F.lit(blocks)) == k)
        looked = seeds if max_check is None else seeds.orderBy(uniform(f"{salt}-{k}", "rk"), "rk").limit(max_check)
        tested = looked.select("d").crossJoin(F.broadcast(some)).withColumn("b", gamma_bucket(logp, gamma))
        one = tested.groupBy(key).agg(F.first("own").alias("bucket"), F.count_if(F.col("b") == F.col("own")).alias("plausible"))
        out = one if out is None else out.unionByName(one)
    return out


def seed_partitions(pairs: DataFrame, gamma: float) -> DataFrame:
    """bucket, n: seeds by the gamma bucket of their likelihood for one candidate; pairs hold logp."""
    return pairs.withColumn("bucket", gamma_bucket(F.col("logp"), gamma)).where("bucket IS NOT NULL").groupBy("bucket").agg(F.count("*").alias("n"))


def is_deniable(likelihoods: DataFrame, k: int, gamma: float, key: str = "cand_id") -> DataFrame:
    """key, neglogp, n, deniable by the definition: some interval of likelihoods of width gamma holds the seed and k records.

    likelihoods: key, neglogp, n (records that share it). An interval may start at any record, so for each start the records
    within it are counted, and a seed takes the best of the starts whose interval reaches it.
    """
    width = math.log(gamma) + 1e-9
    over = f"OVER (PARTITION BY `{key}` ORDER BY neglogp RANGE BETWEEN"
    held = likelihoods.withColumn("_ahead", F.expr(f"sum(n) {over} CURRENT ROW AND {width!r}D FOLLOWING)"))
    return held.withColumn("deniable", F.expr(f"max(_ahead) {over} {width!r}D PRECEDING AND CURRENT ROW)") >= k).drop("_ahead")
