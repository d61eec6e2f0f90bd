"""Release of synthetic records as a stream of seeds comes in, and the ledger of what has been spent."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from synthguard.operators.deniability import randomized
from synthguard.operators.synth import Model, synthesize
from synthguard.plans.schema import DeniabilityParams


def stream_release(seeds: DataFrame, index: DataFrame, model: Model, params: DeniabilityParams, omega: int, salt: str) -> DataFrame:
    """Released records of a stream of seeds (cand_id and attributes) against a fixed table of prefix counts (the kept
    attributes and n). Draws and thresholds hang on cand_id, so a replayed batch releases the same records again."""
    names = model.kept(omega)
    cands = synthesize(model, seeds, omega, salt)
    counted = cands.join(index.withColumnRenamed("n", "plausible"), names, "left").withColumn("plausible", F.coalesce("plausible", F.lit(0)))
    return randomized(counted, params.k, params.eps0, salt).where("passed").select(*model.schema.names)


class Ledger:
    """Records released for each data set so far, against a limit; kept as a Parquet table that batches append to."""

    def __init__(self, spark, path: str, limit: int):
        self.spark, self.path, self.limit = spark, path, limit
        self.schema = "dataset string, batch long, released long"

    def spent(self, dataset: str, but: int | None = None) -> int:
        try:
            rows = self.spark.read.schema(self.schema).parquet(self.path).where(F.col("dataset") == dataset)
        except Exception as e:  # nothing was written yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return 0
        rows = rows if but is None else rows.where(F.col("batch") != but)
        # a replayed batch counts once
        return rows.groupBy("batch").agg(F.max("released").alias("r")).agg(F.coalesce(F.sum("r"), F.lit(0))).first()[0]

    def charge(self, dataset: str, batch: int, released: int) -> None:
        if self.spent(dataset, batch) + released > self.limit:
            raise RuntimeError(f"the budget of {dataset} is spent: {self.limit} records")
        self.spark.createDataFrame([(dataset, batch, released)], self.schema).write.mode("append").parquet(self.path)


def start(released: DataFrame, sink: str, checkpoint: str, ledger: Ledger, dataset: str) -> StreamingQuery:
    """Writes each batch to sink once its size is charged to the ledger."""

    def write(batch: DataFrame, number: int) -> None:
        held = batch.persist()
        try:
            n = held.count()
            if n:
                ledger.charge(dataset, number, n)
                held.write.mode("overwrite").parquet(f"{sink}/batch={number}")
        finally:
            held.unpersist()

    return released.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
