"""Synthesis: keep a seed's leading attributes, draw the others one after the other from the conditional tables.

The tables' cells are counted from the schema and the graph before anything is sent: up to BROADCAST_CELLS of them go to every
task as arrays, and records are drawn and weighed there in one scan without a join; larger tables stay a relation that is joined, each
attribute's part broadcast only if it is small enough by itself.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.functions.noise import uniform
from synthguard.operators.params import Tables, config, config_numbers, counts_by_set, learn_tables, without_parents
from synthguard.operators.structure import config_cost
from synthguard.plans.schema import Graph, Schema

#: Cells of the conditional tables up to which they are broadcast.
BROADCAST_CELLS = 4_000_000


@dataclass(frozen=True)
class Model:
    schema: Schema
    graph: Graph
    table: DataFrame  # attr, config, probs, cum

    @property
    def m(self) -> int:
        return len(self.schema)

    def kept(self, omega: int) -> list[str]:
        """Names of the attributes that are kept when omega are drawn anew."""
        return [self.schema.names[i] for i in self.graph.order[: self.m - omega]]

    def seed_independent(self, omega: int) -> bool:
        return omega == self.m

    def cells(self, i: int) -> int:
        return config_cost(self.graph.parents[i], self.schema) * self.schema.attributes[i].card

    @property
    def small(self) -> bool:
        return sum(map(self.cells, range(self.m))) <= BROADCAST_CELLS

    @cached_property
    def arrays(self) -> Tables:
        """All tables as arrays; for small ones."""
        if not self.small:
            raise ValueError("the tables are too large to be held")
        return Tables.of_rows(self.schema, self.graph, self.table.select("attr", "config", "probs").collect())

    def of(self, i: int) -> DataFrame:
        t = self.table.where(F.col("attr") == i).select(F.col("config").alias("_config"), F.col("probs").alias("_probs"), F.col("cum").alias("_cum"))
        return F.broadcast(t) if self.cells(i) <= BROADCAST_CELLS else t

    def log_prob(self, df: DataFrame, attributes=None, out: str = "logp") -> DataFrame:
        """df with the log probability of its rows under the network (of the given attributes given their parents)."""
        wanted = list(range(self.m) if attributes is None else attributes)
        if not self.small:
            names, total = df.columns, F.lit(0.0)
            for i in wanted:
                df = df.withColumn("_config", config(self.schema, self.graph, i)).join(self.of(i), "_config", "left")
                df = df.withColumn(f"_l{i}", F.ln(F.element_at("_probs", F.col(self.schema.names[i]) + 1))).drop("_config", "_probs", "_cum")
                total = total + F.col(f"_l{i}")
            return df.select(*names, total.alias(out))
        return _weighed(self, df, {out: wanted})


def from_tables(spark: SparkSession, schema: Schema, graph: Graph, tables: Tables) -> Model:
    """A model of tables that are held already."""
    model = Model(schema, graph, spark.createDataFrame(list(tables.rows()), "attr int, config long, probs array<double>, cum array<double>"))
    model.__dict__["arrays"] = tables
    return model


def _weighed(model: Model, df: DataFrame, sums: dict[str, list[int]]) -> DataFrame:
    """df with a column for each of sums: the log probability of those attributes given their parents; one scan."""
    held, schema, graph = df.sparkSession.sparkContext.broadcast(model.arrays), model.schema, model.graph

    @F.pandas_udf("struct<" + ", ".join(f"`{n}`: double" for n in sums) + ">")
    def told(rows):
        x = [rows[n].to_numpy().astype(np.int64) for n in schema.names]
        one = {}
        with np.errstate(divide="ignore"):
            for i in sorted({i for own in sums.values() for i in own}):
                one[i] = np.log(held.value.probs[i][config_numbers(schema, graph.parents[i], x), x[i]])
        return type(rows)({n: sum((one[i] for i in own), np.zeros(len(rows))) for n, own in sums.items()})

    names = df.columns
    done = df.withColumn("_told", told(F.struct(*schema.names)))
    return done.select(*names, *[F.col(f"_told.`{n}`").alias(n) for n in sums])


def marginal_model(df: DataFrame, schema: Schema, eps: float | None = None, salt: str = "marginals") -> Model:
    graph = without_parents(schema)
    return from_tables(df.sparkSession, schema, graph, learn_tables(counts_by_set(df, schema, [graph]), schema, graph, eps=eps, salt=salt))


def synthesize(model: Model, seeds: DataFrame, omega: int, salt: str, key: str = "cand_id") -> DataFrame:
    """key, the attributes, omega, logq: a candidate for each seed. logq is the log probability of what was drawn, which is
    the likelihood of the candidate under every seed that shares the kept attributes."""
    return synthesize_by(model, seeds.withColumn("omega", F.lit(omega)), [omega], salt, key)


def synthesize_random(model: Model, seeds: DataFrame, omegas, salt: str, key: str = "cand_id") -> DataFrame:
    """As synthesize, with omega drawn for each candidate from a set, independently of the data."""
    omegas = sorted(set(omegas))
    pick = F.element_at(F.array(*[F.lit(w) for w in omegas]), (F.floor(uniform(salt, key, F.lit("omega")) * len(omegas)) + 1).cast("int"))
    return synthesize_by(model, seeds.withColumn("omega", pick), omegas, salt, key)


def synthesize_by(model: Model, seeds: DataFrame, omegas, salt: str, key: str = "cand_id") -> DataFrame:
    """As synthesize, with each seed's omega in a column; omegas: those that occur."""
    if not all(1 <= w <= model.m for w in omegas):
        raise ValueError("omega must lie in 1..m: with 0 a record would be copied")
    schema, graph, m = model.schema, model.graph, model.m
    drawn = graph.order[m - max(omegas) :]
    numbers = [uniform(salt, key, F.lit(schema.names[i])).alias(f"_u{i}") for i in drawn]
    df = seeds.select(key, *schema.names, F.col("omega").cast("int").alias("omega"), *numbers)
    if not model.small:
        total = F.lit(0.0)
        for i in drawn:
            name, anew = schema.names[i], F.col("omega") >= m - graph.order.index(i)
            df = df.withColumn("_config", config(schema, graph, i)).join(model.of(i), "_config", "left")
            # bound once: a hash in the lambda would be made for each cell
            value = F.least(F.transform(F.array(f"_u{i}"), lambda u: F.size(F.filter("_cum", lambda c: c <= u)))[0], F.lit(schema.attributes[i].card - 1))
            df = df.withColumn(name, F.when(anew, value).otherwise(F.col(name))).withColumn(f"_l{i}", F.when(anew, F.ln(F.element_at("_probs", F.col(name) + 1))).otherwise(0.0)).drop("_config", "_probs", "_cum")
            total = total + F.col(f"_l{i}")
        return df.select(key, *schema.names, "omega", total.alias("logq"))
    held = seeds.sparkSession.sparkContext.broadcast(model.arrays)
    names = [key, *schema.names, "omega", "logq"]

    def run(batches):
        for b in batches:
            x = [b.column(n).to_numpy(zero_copy_only=False).astype(np.int64) for n in schema.names]
            w, logq = b.column("omega").to_numpy(zero_copy_only=False), np.zeros(b.num_rows)
            for i in drawn:
                at = np.flatnonzero(w >= m - graph.order.index(i))
                c = config_numbers(schema, graph.parents[i], [v[at] for v in x])
                u = b.column(f"_u{i}").to_numpy(zero_copy_only=False)[at]
                x[i][at] = np.minimum((held.value.cum[i][c] <= u[:, None]).sum(1), schema.attributes[i].card - 1)
                logq[at] += np.log(held.value.probs[i][c, x[i][at]])
            yield pa.RecordBatch.from_arrays([b.column(key), *(pa.array(v, pa.int32()) for v in x), b.column("omega"), pa.array(logq)], names=names)

    return df.mapInArrow(run, f"`{key}` {seeds.schema[key].dataType.simpleString()}, " + ", ".join(f"`{n}` int" for n in schema.names) + ", omega int, logq double")


def log_q(model: Model, candidates: DataFrame, omegas) -> DataFrame:
    """candidates with q_<omega>: the log probability of their last omega attributes given the others."""
    last = {w: list(reversed(model.graph.order))[:w] for w in omegas}
    if model.small:
        return _weighed(model, candidates, {f"q_{w}": own for w, own in last.items()})
    names = candidates.columns
    df = candidates
    for i in model.graph.order:
        df = model.log_prob(df, [i], f"_t{i}")
    sums: dict[int, Column] = {w: sum((F.col(f"_t{i}") for i in own), F.lit(0.0)) for w, own in last.items()}
    return df.select(*names, *[sums[w].alias(f"q_{w}") for w in omegas])
