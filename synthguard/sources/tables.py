"""The given tables, and views of micro data derived from them: every attribute an INT code 0..card-1, and rk, the row's key."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.plans.schema import Schema, categorical, numeric
from synthguard.shipping import ship

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
# fixed values: the domains of the categories
FLAGS, STATUS = ("A", "N", "R"), ("F", "O")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
EVENTS = ("click", "error", "purchase", "signup", "view")
ROLES, LANGUAGES = ("assistant", "system", "user"), ("de", "en", "es", "fr")


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no table {name}")
    return ship(spark).read.parquet(f"{sf_dir}/{name}.parquet")


@dataclass(frozen=True)
class View:
    schema: Schema
    build: Callable[[SparkSession, str], DataFrame]
    sql: str  # the same rows by DuckDB; columns rk and the attributes


def _code(col: str, labels) -> F.Column:
    return (F.array_position(F.array(*[F.lit(x) for x in labels]), F.col(col)) - 1).cast("int")


def _code_sql(col: str, labels) -> str:
    return f"(list_position([{', '.join(repr(x) for x in labels)}], {col}) - 1)::INTEGER"


def _orderline(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = lambda n: read_table(spark, sf_dir, n)
    joined = (
        t("lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_returnflag", "l_linestatus")
        .join(t("orders").select("o_orderkey", "o_custkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t("customer").select("c_custkey", "c_nationkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
        .join(t("nation").select("n_nationkey", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey"))
    )
    return joined.select(
        F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("rk"),
        (F.col("l_quantity").cast("int") - 1).alias("qty"),
        F.floor(F.col("l_extendedprice") / 5000).cast("int").alias("pband"),
        (F.floor(F.log2(F.col("l_extendedprice") / F.col("l_quantity"))).cast("int") - 4).alias("uband"),
        F.round(100 * F.col("l_discount")).cast("int").alias("disc"),
        _code("l_returnflag", FLAGS).alias("rf"), _code("l_linestatus", STATUS).alias("ls"), _code("c_mktsegment", SEGMENTS).alias("seg"),
        F.col("n_regionkey").cast("int").alias("reg"), F.col("c_nationkey").cast("int").alias("nat"), _code("o_orderpriority", PRIORITIES).alias("op"),
        (F.col("l_extendedprice") * (1 - F.col("l_discount")) > 50000).cast("int").alias("netc"),
    )


ORDERLINE = View(
    Schema("orderline_micro", (
        numeric("qty", 50, 10, 1), numeric("pband", 21, 3), numeric("uband", 13, 2, 4), numeric("disc", 11, 3), categorical("rf", FLAGS), categorical("ls", STATUS),
        categorical("seg", SEGMENTS), categorical("reg", range(5)), categorical("nat", range(25)), categorical("op", PRIORITIES), categorical("netc", ("low", "high")),
    )),
    _orderline,
    f"""SELECT l_orderkey || '|' || l_linenumber || '|' || l_partkey || '|' || l_suppkey AS rk, l_quantity::INTEGER - 1 AS qty, floor(l_extendedprice / 5000)::INTEGER AS pband,
  floor(log2(l_extendedprice / l_quantity))::INTEGER - 4 AS uband, round(100 * l_discount)::INTEGER AS disc, {_code_sql("l_returnflag", FLAGS)} AS rf, {_code_sql("l_linestatus", STATUS)} AS ls,
  {_code_sql("c_mktsegment", SEGMENTS)} AS seg, n_regionkey::INTEGER AS reg, c_nationkey::INTEGER AS nat, {_code_sql("o_orderpriority", PRIORITIES)} AS op,
  (l_extendedprice * (1 - l_discount) > 50000)::INTEGER AS netc
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey""",
)


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").join(read_table(spark, sf_dir, "labels"), "doc_id", "left")
    return docs.select(
        F.col("doc_id").cast("string").alias("rk"), _code("lang", LANGUAGES).alias("lang"), F.regexp_extract("source", "[0-9]+", 0).cast("int").alias("source"),
        F.least(F.floor(F.log2(F.col("n_chars"))), F.lit(19)).cast("int").alias("lb"), F.least(F.lit(9), F.size(F.split("text", "\n", -1)) - 1).alias("nl"),
        F.contains("text", F.lit("@")).cast("int").alias("em"), F.contains(F.lower("text"), F.lit("license")).cast("int").alias("lic"), F.col("quality").cast("int"), F.col("toxic").cast("int"),
    )


DOCUMENT = View(
    Schema("document_micro", (
        categorical("lang", LANGUAGES), categorical("source", range(20)), numeric("lb", 20, 2), numeric("nl", 10, 2), categorical("em", range(2)), categorical("lic", range(2)), categorical("quality", range(2)), categorical("toxic", range(2)),
    )),
    _documents,
    f"""SELECT d.doc_id::VARCHAR AS rk, {_code_sql("lang", LANGUAGES)} AS lang, regexp_extract(source, '[0-9]+')::INTEGER AS source, least(floor(log2(n_chars)), 19)::INTEGER AS lb,
  least(9, len(string_split(text, chr(10))) - 1)::INTEGER AS nl, contains(text, '@')::INTEGER AS em, contains(lower(text), 'license')::INTEGER AS lic, quality::INTEGER AS quality, toxic::INTEGER AS toxic
  FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id""",
)


def _event(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "events").select(
        F.col("event_id").cast("string").alias("rk"), _code("event_type", EVENTS).alias("et"), F.hour("ts").alias("hr"), (F.dayofweek("ts") - 1).alias("dow"), (F.dayofmonth("ts") - 1).alias("dom"),
        F.least(F.floor(F.log2(F.col("value") + 1)), F.lit(11)).cast("int").alias("vb"), F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("int").alias("kk"), (F.col("user_id") % 10).cast("int").alias("ub"),
    )


EVENT = View(
    Schema("event_micro", (categorical("et", EVENTS), numeric("hr", 24, 6), categorical("dow", range(7)), numeric("dom", 31, 7), numeric("vb", 12, 3), numeric("kk", 10, 2), categorical("ub", range(10)))),
    _event,
    f"""SELECT event_id::VARCHAR AS rk, {_code_sql("event_type", EVENTS)} AS et, hour(ts)::INTEGER AS hr, dayofweek(ts)::INTEGER AS dow, day(ts)::INTEGER - 1 AS dom,
  least(floor(log2(value + 1)), 11)::INTEGER AS vb, ((props::JSON ->> '$.k')::INTEGER // 10)::INTEGER AS kk, (user_id % 10)::INTEGER AS ub FROM events""",
)


def _conversation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "conversations").select(
        F.concat_ws("|", "conv_id", "turn").alias("rk"), _code("role", ROLES).alias("role"), (F.least(F.col("turn"), F.lit(9))).cast("int").alias("turn"),
        F.least(F.floor(F.log2(F.length("text") + 1)), F.lit(15)).cast("int").alias("lb"),
    )


CONVERSATION = View(
    Schema("conversation_micro", (categorical("role", ROLES), numeric("turn", 10, 2), numeric("lb", 16, 2))),
    _conversation,
    f"""SELECT conv_id || '|' || turn AS rk, {_code_sql("role", ROLES)} AS role, least(turn, 9)::INTEGER AS turn, least(floor(log2(length(text) + 1)), 15)::INTEGER AS lb FROM conversations""",
)
VIEWS = {v.schema.name: v for v in (ORDERLINE, DOCUMENT, EVENT, CONVERSATION)}


def wide_view(spark: SparkSession, sf_dir: str, width: int = 64) -> tuple[Schema, DataFrame]:
    """Sign bits of the embeddings as width binary attributes."""
    df = read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("rk"), *[(F.col("embedding")[i] > 0).cast("int").alias(f"s{i}") for i in range(width)])
    return Schema("wide_micro", tuple(categorical(f"s{i}", (0, 1)) for i in range(width))), df
