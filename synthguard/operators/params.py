"""Conditional tables of a graph: counts over a whole fixed domain, with or without noise, and estimates from them."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass
from math import lgamma, log

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from synthguard.functions.noise import laplace, laplace_value, uniform
from synthguard.operators.prep import bucket
from synthguard.operators.structure import config_cost
from synthguard.plans.schema import Graph, Schema


def config(schema: Schema, graph: Graph, i: int) -> Column:
    """The number of a row's parent configuration of attribute i: mixed radix over the parents' buckets."""
    out = F.lit(0).cast("long")
    for p in graph.parents[i]:
        a = schema.attributes[p]
        out = out * a.buckets + bucket(schema, a.name)
    return out


def config_numbers(schema: Schema, parents, x: list[np.ndarray]) -> np.ndarray:
    """The same numbers for arrays of codes, one array for each attribute."""
    out = np.zeros(len(x[0]), np.int64)
    for p in parents:
        a = schema.attributes[p]
        out = out * a.buckets + np.asarray(a.bucket_of, np.int64)[x[p]]
    return out


def _counted(df: DataFrame, schema: Schema, sets) -> DataFrame:
    """s, at, n: how often each cell (configuration times card plus value) of each (attribute, parents) in sets occurs: one scan, fixed arrays in each task."""
    sizes = [config_cost(ps, schema) * schema.attributes[i].card for i, ps in sets]

    def run(batches):
        total = [np.zeros(s, np.int64) for s in sizes]
        for batch in batches:
            x = [batch.column(n).to_numpy(zero_copy_only=False).astype(np.int64) for n in schema.names]
            for t, (i, ps) in zip(total, sets, strict=True):
                t += np.bincount(config_numbers(schema, ps, x) * schema.attributes[i].card + x[i], minlength=len(t))
        for k, t in enumerate(total):
            at = np.flatnonzero(t)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), k, np.int32)), pa.array(at), pa.array(t[at])], names=["s", "at", "n"])

    return df.select(*schema.names).mapInArrow(run, "s int, at long, n long").groupBy("s", "at").agg(F.sum("n").alias("n"))


def counts(df: DataFrame, schema: Schema, graph: Graph) -> DataFrame:
    """attr, config, value, n of what occurs."""
    found = _counted(df, schema, list(enumerate(graph.parents)))
    card = F.element_at(F.array(*[F.lit(a.card) for a in schema.attributes]), F.col("s") + 1)
    return found.select(F.col("s").alias("attr"), F.floor(F.col("at") / card).cast("long").alias("config"), F.pmod("at", card).cast("int").alias("value"), "n")


def counts_by_set(df: DataFrame, schema: Schema, graphs: list[Graph]) -> dict:
    """(attribute, parents) -> configurations x values, of all graphs' sets in one scan: at most maxcost * card numbers for each set."""
    sets = sorted({(i, ps) for g in graphs for i, ps in enumerate(g.parents)})
    out = [np.zeros((config_cost(ps, schema), schema.attributes[i].card)) for i, ps in sets]
    for r in _counted(df, schema, sets).collect():
        out[r["s"]].flat[r["at"]] = r["n"]
    return dict(zip(sets, out, strict=True))


def counts_by_group(df: DataFrame, schema: Schema, graphs: list[list[Graph]]) -> list[dict]:
    """As counts_by_set(), for each group of df (_g) with graphs of its own: one scan for all."""
    sets = [sorted({(i, ps) for g in own for i, ps in enumerate(g.parents)}) for own in graphs]
    out = [{(i, ps): np.zeros((config_cost(ps, schema), schema.attributes[i].card)) for i, ps in own} for own in sets]

    def run(batches):
        total = [[np.zeros(config_cost(ps, schema) * schema.attributes[i].card, np.int64) for i, ps in own] for own in sets]
        for batch in batches:
            x, group = [batch.column(n).to_numpy(zero_copy_only=False).astype(np.int64) for n in schema.names], batch.column("_g").to_numpy(zero_copy_only=False)
            for g, own in enumerate(sets):
                at = np.flatnonzero(group == g)
                if len(at):
                    y = [v[at] for v in x]
                    for t, (i, ps) in zip(total[g], own, strict=True):
                        t += np.bincount(config_numbers(schema, ps, y) * schema.attributes[i].card + y[i], minlength=len(t))
        for g, own in enumerate(total):
            for k, t in enumerate(own):
                at = np.flatnonzero(t)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), g, np.int32)), pa.array(np.full(len(at), k, np.int32)), pa.array(at), pa.array(t[at])], names=["g", "s", "at", "n"])

    for r in df.select(*schema.names, "_g").mapInArrow(run, "g int, s int, at long, n long").groupBy("g", "s", "at").agg(F.sum("n").alias("n")).collect():
        out[r["g"]][sets[r["g"]][r["s"]]].flat[r["at"]] = r["n"]
    return out


@dataclass(frozen=True)
class Tables:
    """Conditional tables as arrays: for each attribute a row of probabilities, and of their sums, for each configuration."""

    probs: tuple[np.ndarray, ...]
    cum: tuple[np.ndarray, ...]

    @staticmethod
    def of_rows(schema: Schema, graph: Graph, rows) -> Tables:
        """Of rows (attr, config, probs); a configuration that has none is not a number."""
        probs = [np.full((config_cost(ps, schema), schema.attributes[i].card), np.nan) for i, ps in enumerate(graph.parents)]
        for r in rows:
            probs[r["attr"]][r["config"]] = r["probs"]
        return Tables(tuple(probs), tuple(np.cumsum(p, 1) for p in probs))

    def rows(self):
        """(attr, config, probs, cum)."""
        for i, (p, c) in enumerate(zip(self.probs, self.cum, strict=True)):
            for k, (x, y) in enumerate(zip(p.tolist(), c.tolist(), strict=True)):
                yield i, k, x, y


def learn_tables(counted: dict, schema: Schema, graph: Graph, alpha: float = 1.0, estimator: str = "mean", eps: float | None = None, salt: str = "parameters") -> Tables:
    """The tables of learn_parameters from counts_by_set(), with the same noise and the same draws."""
    probs = []
    for i, ps in enumerate(graph.parents):
        n = counted[i, ps]
        if eps is not None:
            noise = [[laplace_value(1 / eps, salt, i, c, v) for v in range(n.shape[1])] for c in range(n.shape[0])]
            n = np.maximum(0.0, n + noise)
        if estimator == "sampled":
            p = np.array([_posterior_draw(salt, i, c, x, alpha) for c, x in enumerate(n)])
        else:
            raw = np.maximum(n + {"mean": alpha, "mode": alpha - 1}[estimator], 0.0)
            total = raw.sum(1, keepdims=True)
            p = np.where(total > 0, raw / np.where(total > 0, total, 1), 1 / n.shape[1])
        probs.append(p)
    return Tables(tuple(probs), tuple(np.cumsum(p, 1) for p in probs))


def _posterior_draw(salt: str, attr: int, conf: int, n, alpha: float) -> list[float]:
    seed = int.from_bytes(hashlib.sha256(f"{salt}|{attr}|{conf}".encode()).digest()[:16], "little")
    g = np.random.Generator(np.random.Philox(key=seed)).standard_gamma(np.asarray(n) + alpha)
    return (g / g.sum()).tolist() if g.sum() > 0 else [1 / len(n)] * len(n)


def all_configs(spark, schema: Schema, graph: Graph) -> DataFrame:
    """attr, config, card of every configuration there can be; at most maxcost for each attribute."""
    rows = [(i, config_cost(graph.parents[i], schema), a.card) for i, a in enumerate(schema.attributes)]
    return spark.createDataFrame(rows, "attr int, n long, card int").select("attr", "card", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("config"))


def cells(found: DataFrame, configs: DataFrame, eps: float | None = None, salt: str = "counts") -> DataFrame:
    """attr, config, value, n of every cell of the given configurations, zeros included, with Laplace(1/eps) noise cut at
    zero where eps is given. The noise hangs on the cell alone, so workers that meet a configuration on their own agree on it."""
    every = configs.select("attr", "config", F.explode(F.sequence(F.lit(0), F.col("card") - 1)).alias("value"))
    n = F.coalesce(F.col("n"), F.lit(0)).cast("double")
    full = every.join(found, ["attr", "config", "value"], "left").withColumn("n", n)
    return full if eps is None else full.withColumn("n", F.greatest(F.lit(0.0), F.col("n") + laplace(1 / eps, salt, "attr", "config", "value")))


def estimate(cells_: DataFrame, alpha: float = 1.0, estimator: str = "mean", salt: str = "draw") -> DataFrame:
    """attr, config, probs, cum: the posterior mean, the mode, or one draw from the posterior (fixed by salt and configuration)."""
    weights = cells_.groupBy("attr", "config").agg(F.transform(F.array_sort(F.collect_list(F.struct("value", "n"))), lambda s: s["n"]).alias("n"))
    if estimator == "sampled":
        def draw(attr: pd.Series, conf: pd.Series, n: pd.Series) -> pd.Series:
            out = [_posterior_draw(salt, a, c, x, alpha) for a, c, x in zip(attr, conf, n, strict=True)]
            return pd.Series(out)

        probs = F.pandas_udf(draw, T.ArrayType(T.DoubleType()))("attr", "config", "n")
    else:
        shift = {"mean": alpha, "mode": alpha - 1}[estimator]
        raw = F.transform("n", lambda x: F.greatest(x + F.lit(float(shift)), F.lit(0.0)))
        total = F.aggregate(raw, F.lit(0.0), lambda s, x: s + x)
        probs = F.when(total > 0, F.transform(raw, lambda x: x / total)).otherwise(F.transform("n", lambda x: F.lit(1.0) / F.size("n")))
    cum = F.transform(F.sequence(F.lit(1), F.size("probs")), lambda k: F.aggregate(F.slice("probs", 1, k), F.lit(0.0), lambda s, x: s + x))
    return weights.withColumn("probs", probs).select("attr", "config", "probs", cum.alias("cum"))


def learn_parameters(df: DataFrame, schema: Schema, graph: Graph, alpha: float = 1.0, estimator: str = "mean", eps: float | None = None, salt: str = "parameters") -> DataFrame:
    """The tables for all configurations; private where eps is given."""
    return estimate(cells(counts(df, schema, graph), all_configs(df.sparkSession, schema, graph), eps, salt), alpha, estimator, salt)


def lazy_parameters(df: DataFrame, schema: Schema, graph: Graph, wanted: DataFrame, alpha: float = 1.0, estimator: str = "mean", eps: float | None = None, salt: str = "parameters") -> DataFrame:
    """The tables of the configurations in wanted (attr, config) alone; the same as those of learn_parameters."""
    card = F.element_at(F.array(*[F.lit(a.card) for a in schema.attributes]), F.col("attr") + 1)
    return estimate(cells(counts(df, schema, graph), wanted.select("attr", "config").distinct().withColumn("card", card), eps, salt), alpha, estimator, salt)


def dirichlet_log_density(probs, weights) -> float:
    """Log density of a Dirichlet distribution with the given weights at probs."""
    return lgamma(sum(weights)) + sum((w - 1) * log(p) - lgamma(w) for p, w in zip(probs, weights, strict=True))


def gaussian_params(df: DataFrame, target: str, by: list[str]) -> DataFrame:
    """For a continuous target: mean and deviation in each configuration (an extension without a privacy claim)."""
    return df.groupBy(*by).agg(F.avg(target).alias("mean"), F.coalesce(F.stddev_samp(target), F.lit(0.0)).alias("deviation"), F.count("*").alias("n"))


def linear_params(df: DataFrame, target: str, regressor: str, by: list[str]) -> DataFrame:
    """For a continuous target: slope and intercept on one regressor in each configuration (an extension without a privacy claim)."""
    return df.groupBy(*by).agg(F.regr_slope(target, regressor).alias("slope"), F.regr_intercept(target, regressor).alias("intercept"), F.count("*").alias("n"))


def draw_continuous(df: DataFrame, params: DataFrame, by: list[str], salt: str, out: str, key: str = "rk", regressor: str | None = None, spread: float = 1.0) -> DataFrame:
    """df with a continuous target drawn for each row: normal with gaussian_params(), or linear_params() of the regressor with
    normal residuals of the given deviation. The draw hangs on salt and key (Box and Muller's transform of two keyed numbers)."""
    names = df.columns
    normal = F.sqrt(-2 * F.ln(uniform(salt, key, F.lit("r")))) * F.cos(2 * float(np.pi) * uniform(salt, key, F.lit("a")))
    known = params.select(*by, *[F.col(c).alias(f"_{c}") for c in params.columns if c not in (*by, "n")])
    told = df.join(known, by, "left")
    value = F.col("_mean") + F.col("_deviation") * normal if regressor is None else F.col("_slope") * F.col(regressor) + F.col("_intercept") + spread * normal
    return told.select(*names, value.alias(out))


def without_parents(schema: Schema) -> Graph:
    """The graph of the marginal baseline."""
    return Graph(((),) * len(schema), tuple(range(len(schema))))
