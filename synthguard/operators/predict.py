"""Prediction of an attribute from the others, its accuracy, and the baselines of the same question."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from synthguard.operators.distance import distributions
from synthguard.operators.params import Tables, config, config_numbers
from synthguard.operators.synth import Model
from synthguard.plans.schema import Graph, Schema


def predict_attribute(model: Model, df: DataFrame, name: str, conditioning: str = "blanket", key: str = "rk") -> DataFrame:
    """key, truth, guess: the likeliest value given all other attributes (blanket: its own table and its children's) or
    given its parents alone; ties go to the smallest value."""
    i = model.schema.index(name)
    card = model.schema.attributes[i].card
    asked = df.select(key, *model.schema.names).withColumn("_truth", F.col(name)).withColumn(name, F.explode(F.sequence(F.lit(0), F.lit(card - 1))))
    touched = [i] + ([c for c, ps in enumerate(model.graph.parents) if i in ps] if conditioning == "blanket" else [])
    scored = model.log_prob(asked.select(key, "_truth", *model.schema.names), touched, "_score")
    best = scored.groupBy(key, "_truth").agg(F.max_by(name, F.struct("_score", -F.col(name))).alias("guess"))
    return best.select(key, F.col("_truth").alias("truth"), "guess")


def likeliest(schema: Schema, graph: Graph, tables: Tables, x: list[np.ndarray], i: int) -> np.ndarray:
    """For arrays of codes the likeliest value of attribute i given all others; ties go to the smallest."""
    with np.errstate(divide="ignore"):
        scores = np.log(tables.probs[i][config_numbers(schema, graph.parents[i], x)])
        bucket_of = np.asarray(schema.attributes[i].bucket_of)
        for c, ps in enumerate(graph.parents):
            if i in ps:
                for b in range(schema.attributes[i].buckets):
                    values = np.flatnonzero(bucket_of == b)
                    y = [np.full(len(x[0]), values[0]) if k == i else v for k, v in enumerate(x)]
                    scores[:, values] += np.log(tables.probs[c][config_numbers(schema, ps, y), x[c]])[:, None]
    return scores.argmax(1)


def model_errors(schema: Schema, models: dict[str, tuple[Graph, Tables]], test: DataFrame) -> DataFrame:
    """model, attr, error: the share of test rows whose value is guessed wrong, for each model and attribute: one scan for all."""
    held = test.sparkSession.sparkContext.broadcast(models)
    names = schema.names

    def run(batches):
        wrong, n = {(k, a): 0 for k in held.value for a in names}, 0
        for b in batches:
            x = [b.column(a).to_numpy(zero_copy_only=False).astype(np.int64) for a in names]
            n += b.num_rows
            for k, (graph, tables) in held.value.items():
                for i, a in enumerate(names):
                    wrong[k, a] += int((likeliest(schema, graph, tables, x, i) != x[i]).sum())
        yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in wrong]), pa.array([a for _, a in wrong]), pa.array(list(wrong.values()), pa.int64()), pa.array([n] * len(wrong), pa.int64())], names=["model", "attr", "wrong", "n"])

    counted = test.select(*names).mapInArrow(run, "model string, attr string, wrong long, n long")
    return counted.groupBy("model", "attr").agg((F.sum("wrong") / F.sum("n")).alias("error"))


def model_error(model: Model, test: DataFrame) -> DataFrame:
    """attr, error of one model."""
    return model_errors(model.schema, {"": (model.graph, model.arrays)}, test).select("attr", "error")


def baselines(train: DataFrame, test: DataFrame, schema) -> DataFrame:
    """attr, marginal_accuracy, random_accuracy: always the commonest training value (ties: the smallest), and 1 / domain; one scan of each side."""
    modes = distributions(train, schema).groupBy("attrs").agg(F.max_by("value", F.struct("p", -F.col("value"))).alias("value"))
    hit = distributions(test, schema).join(F.broadcast(modes), ["attrs", "value"]).select("attrs", "p")
    known = train.sparkSession.createDataFrame([(a.name, 1.0 / a.card) for a in schema.attributes], "attrs string, random_accuracy double")
    return known.join(hit, "attrs", "left").select(F.col("attrs").alias("attr"), F.coalesce("p", F.lit(0.0)).alias("marginal_accuracy"), "random_accuracy")


def relative_improvement(errors: DataFrame, marginal_errors: DataFrame) -> DataFrame:
    """attr, improvement: (marginal error - model error) / marginal error."""
    m = marginal_errors.withColumnRenamed("error", "_m")
    return errors.join(m, "attr").select("attr", F.when(F.col("_m") > 0, (F.col("_m") - F.col("error")) / F.col("_m")).otherwise(F.lit(0.0)).alias("improvement"))


def configs_met(model: Model, df: DataFrame) -> DataFrame:
    """attr, config of every parent configuration in df: what lazy learning has to learn."""
    out = None
    for i in range(model.m):
        one = df.select(F.lit(i).alias("attr"), config(model.schema, model.graph, i).alias("config")).distinct()
        out = one if out is None else out.unionByName(one)
    return out
