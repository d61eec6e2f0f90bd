"""Reading, staging and folds that the text operators share."""

from __future__ import annotations

import tempfile
import uuid
from functools import lru_cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.shipping import ship

#: Characters that count as white space everywhere here: fixed values.
WHITE_SPACE = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def carried(docs: DataFrame, **own: Column) -> DataFrame:
    """An operator's own columns beside `row`, a struct of all of docs: whatever the names in there, they cannot clash."""
    return docs.select(F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("row"), *[c.alias(name) for name, c in own.items()])


def handed_back(done: DataFrame, docs: DataFrame, own: dict[str, str]) -> DataFrame:
    """The columns of docs from `row`, and own (name to column): these replace columns of the same name, in any letter case."""
    told = {n.lower(): c for n, c in own.items()}
    columns = [F.col(told.pop(c.lower()) if c.lower() in told else f"row.`{c}`").alias(c) for c in docs.columns]
    return done.select(*columns, *[F.col(c).alias(n) for n, c in own.items() if n.lower() in told])


@lru_cache(maxsize=1)
def _local_folder() -> str:
    return tempfile.mkdtemp(prefix="synthguard-")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, as spark.checkpoint.dir names it; a temporary one only where it is unset and all run on this machine."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    return named or f"file://{_local_folder()}"


def staged(spark: SparkSession, df: DataFrame, label: str) -> DataFrame:
    """df written once to the shared folder and read back: cuts the lineage, survives lost executors, goes when the driver ends
    unless unstaged() lets it go before."""
    path = f"{shared_folder(spark)}/synthguard/{spark.sparkContext.applicationId}/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    hadoop_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop_path.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(hadoop_path)
    back = spark.read.schema(df.schema).parquet(path)
    back.staged_at = path
    return back


def unstaged(spark: SparkSession, *frames: DataFrame) -> None:
    """Deletes staged frames that nothing reads any more: all that was made of them is staged itself."""
    for df in frames:
        hadoop_path = spark._jvm.org.apache.hadoop.fs.Path(df.staged_at)
        hadoop_path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop_path, True)


def parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def held_out(id_col: str, folds: int, which: int) -> Column:
    """crc32 of the id as text, modulo folds, equals which; a null id counts as held out."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % folds == which, F.lit(True))


def text_or_empty(col: str = "text") -> Column:
    return F.coalesce(F.col(col), F.lit(""))
