"""Sources and sinks of micro data: CSV with a declared schema, JSON metadata and configuration, releases, stored models."""

from __future__ import annotations

import json
import secrets

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from synthguard.operators import params as parameters
from synthguard.operators import prep, release, structure, synth
from synthguard.plans.budget import calibrate
from synthguard.plans.schema import DeniabilityParams, Graph, Schema


def read_csv(spark: SparkSession, path: str, schema: Schema, header: bool = True) -> DataFrame:
    """Records of a CSV file as codes; what the declared types or domains do not hold is null (and goes by prep.clean)."""
    fields = T.StructType([T.StructField(a.name, T.IntegerType() if a.kind == "numeric" else T.StringType()) for a in schema.attributes] + [T.StructField("_corrupt_record", T.StringType())])
    raw = spark.read.csv(path, schema=fields, header=header, mode="PERMISSIVE", columnNameOfCorruptRecord="_corrupt_record")
    codes = []
    for a in schema.attributes:
        code = F.col(a.name) - a.low if a.kind == "numeric" else F.array_position(F.array(*[F.lit(x) for x in a.labels]), F.col(a.name)) - 1
        codes.append(F.when((code >= 0) & (code < a.card), code).cast("int").alias(a.name))
    return raw.select(*codes)


def decoded(df: DataFrame, schema: Schema) -> DataFrame:
    """Codes back to values, in the format of the input."""
    return df.select(*[(F.col(a.name) + a.low).alias(a.name) if a.kind == "numeric" else F.element_at(F.array(*[F.lit(x) for x in a.labels]), F.col(a.name) + 1).alias(a.name) for a in schema.attributes])


def write_release(df: DataFrame, schema: Schema, path: str, fmt: str = "parquet", run_id: str | None = None) -> None:
    """Released records, attributes only; in a folder of their run where one is named."""
    out = decoded(df.select(*schema.names), schema)
    if run_id is not None:
        out.withColumn("run_id", F.lit(run_id)).write.mode("append").partitionBy("run_id").format(fmt).option("header", True).save(path)
    else:
        out.write.format(fmt).option("header", True).save(path)


def store_model(path: str, spark: SparkSession, schema: Schema, graph: Graph, table: DataFrame) -> None:
    """The conditional tables as Parquet, the schema and graph as one row beside them."""
    table.write.parquet(f"{path}/tables")
    text = json.dumps({"schema": json.loads(schema.to_json()), "parents": graph.parents, "order": graph.order})
    spark.createDataFrame([(text,)], "model string").coalesce(1).write.text(f"{path}/model")


def load_model(path: str, spark: SparkSession) -> tuple[Schema, Graph, DataFrame]:
    x = json.loads(spark.read.text(f"{path}/model").first()[0])
    return Schema.from_json(json.dumps(x["schema"])), Graph(tuple(map(tuple, x["parents"])), tuple(x["order"])), spark.read.parquet(f"{path}/tables")


def read_config(spark: SparkSession, path: str) -> dict:
    """A run's settings from JSON: k, gamma, eps0, omega, max_plausible, max_check, input, metadata, output."""
    x = json.loads("\n".join(r[0] for r in spark.read.text(path).collect()))
    params = DeniabilityParams(x.get("k", 50), x.get("gamma", 4.0), x.get("eps0", 1.0), x.get("max_plausible"), x.get("max_check"))
    return x | {"params": params}


def run_config(spark: SparkSession, path: str) -> int:
    """The run that a configuration file describes: CSV and metadata (a schema as JSON) in, released records as CSV out; returns
    how many. Beside what read_config names: eps of the model (1; null: no noise), omega (a number or a list; all attributes), n
    candidates (as many as seeds), test, min_gain and salt (a secret; drawn anew unless told)."""
    x = read_config(spark, path)
    schema = Schema.from_json("\n".join(r[0] for r in spark.read.text(x["metadata"]).collect()))
    salt, eps, m = x.get("salt") or secrets.token_hex(16), x.get("eps", 1.0), len(schema)
    # every record counts on its own, equal ones too; kept, so that keys stay with their records
    df = prep.clean(read_csv(spark, x["input"], schema), schema).withColumn("rk", F.monotonically_increasing_id().cast("string")).persist()
    t, p, s = (prep.part(df, which, salt=f"{salt}-split") for which in ("T", "P", "S"))
    e_h, e_p = calibrate(eps, m, 2.0**-30) if eps is not None else (None, None)
    graph = structure.learn(t, schema, min_gain=x.get("min_gain", 0.02), eps_entropy=e_h, salt=f"{salt}-structure")
    tables = parameters.learn_tables(parameters.counts_by_set(p, schema, [graph]), schema, graph, estimator="mean" if eps is None else "sampled", eps=e_p, salt=f"{salt}-parameters")
    out = release.release(synth.from_tables(spark, schema, graph, tables), s, x["params"], x.get("n") or s.count(), x.get("omega", m), salt, x.get("test", "randomized")).persist()
    write_release(out, schema, x["output"], "csv")
    released = out.count()
    out.unpersist()
    df.unpersist()
    return released
