"""The given tables with declared schemas, and the client tables (rid, item, key) built from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import coin, integer_key, string_key
from ..params import COIN, Params

SCHEMAS = {
    "documents": "doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT",
    "conversations": "conv_id BIGINT, turn BIGINT, role STRING, text STRING",
    "events": "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING",
    "lineitem": "l_orderkey BIGINT, l_partkey BIGINT, l_suppkey BIGINT, l_linenumber INT, l_quantity DOUBLE, l_extendedprice DOUBLE, l_discount DOUBLE, l_tax DOUBLE, l_returnflag STRING, l_linestatus STRING, l_shipdate TIMESTAMP_NTZ",
    "orders": "o_orderkey BIGINT, o_custkey BIGINT, o_orderstatus STRING, o_totalprice DOUBLE, o_orderdate TIMESTAMP_NTZ, o_orderpriority STRING",
    "customer": "c_custkey BIGINT, c_name STRING, c_nationkey INT, c_acctbal DOUBLE, c_mktsegment STRING",
    "nation": "n_nationkey INT, n_name STRING, n_regionkey INT",
    "region": "r_regionkey INT, r_name STRING",
    "pages": "page_id BIGINT, url STRING, html STRING",
    "labels": "doc_id BIGINT, quality INT, toxic INT",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    path = f"{sf_dir}/{name}.parquet"
    return spark.read.schema(SCHEMAS[name]).parquet(path) if name in SCHEMAS else spark.read.parquet(path)


def load_items(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """A client file in csv, json, orc, text or parquet with a declared schema."""
    reader = spark.read.format(fmt)
    return (reader if fmt == "text" else reader.schema(schema)).load(path)


def clients(df: DataFrame, rid, item, text: bool) -> DataFrame:
    return df.select(rid.cast("string").alias("rid"), item.alias("item")).withColumn("key", string_key(F.col("item")) if text else integer_key(F.col("item")))


def _words(df: DataFrame, *ids: str) -> DataFrame:
    split = df.select(*ids, F.posexplode(F.split(F.lower("text"), r"[ \t\n\r]+")).alias("pos", "item")).where("item <> ''")
    return clients(split, F.concat_ws("|", *ids, "pos"), F.col("item"), True)


def words(spark: SparkSession, sf_dir: str, parts: int | None = None) -> DataFrame:
    """parts: documents are dealt to so many tasks before they are split, since a file of one row group is read by one task."""
    documents = load(spark, sf_dir, "documents").select("doc_id", "text")
    return _words(documents.repartition(parts) if parts else documents, "doc_id")


def chat_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _words(load(spark, sf_dir, "conversations"), "conv_id", "turn")


LINE_ID = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")


def parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clients(load(spark, sf_dir, "lineitem"), F.concat_ws("|", *LINE_ID), F.col("l_partkey"), False)


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clients(load(spark, sf_dir, "orders"), F.col("o_orderkey"), F.col("o_custkey"), False)


def sensor_fine(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clients(load(spark, sf_dir, "events"), F.col("event_id"), F.round(F.col("value") * 100).cast("bigint"), False)


def sensor_coarse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clients(load(spark, sf_dir, "events"), F.col("event_id"), F.round(F.col("value") * 10).cast("bigint"), False)


def types(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clients(load(spark, sf_dir, "events"), F.col("event_id"), F.col("event_type"), True)


def prop_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clients(load(spark, sf_dir, "events"), F.col("event_id"), F.from_json("props", "k INT")["k"].cast("bigint"), False)


def users(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clients(load(spark, sf_dir, "events"), F.col("event_id"), F.col("user_id"), False)


def hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clients(load(spark, sf_dir, "pages"), F.col("page_id"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1), True)


def zipf_items(spark: SparkSession, sf_dir: str, s: float = 1.1, n_ids: int = 2_000_000, seed: int = 7) -> DataFrame:
    """Rank-numbered ids of a bounded Zipf law, one for each lineitem row, by the inverse of its continuous CDF."""
    u = coin(F.concat_ws("|", *LINE_ID), Params(seed=seed), "zipf") / F.lit(float(COIN))
    item = F.floor(F.pow(1 - u * (1 - n_ids ** (1 - s)), F.lit(-1 / (s - 1)))).cast("bigint")
    return clients(load(spark, sf_dir, "lineitem").select(F.concat_ws("|", *LINE_ID).alias("rid"), *LINE_ID), F.col("rid"), item, False)


FIXTURES = {"words": words, "chat_words": chat_words, "parts": parts, "customers": customers, "sensor_fine": sensor_fine, "sensor_coarse": sensor_coarse, "types": types, "props": prop_values, "users": users, "hosts": hosts, "zipf": zipf_items}


def filter_labels(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Documents labelled as of good quality."""
    return docs.join(labels.where("quality = 1").select("doc_id"), "doc_id", "left_semi")


def bound_contribution(df: DataFrame, user: str, order: str, k: int = 1) -> DataFrame:
    """At most k rows of each user, the first by `order`: needed before privacy can be claimed for a user."""
    if k == 1:  # an aggregate, combined before the shuffle; no user's rows are gathered
        rest = [c for c in df.columns if c != user]
        return df.groupBy(user).agg(F.min_by(F.struct(*rest), order).alias("_r")).select(user, "_r.*").select(*df.columns)
    from pyspark.sql import Window

    return df.withColumn("_n", F.row_number().over(Window.partitionBy(user).orderBy(order))).where(F.col("_n") <= k).drop("_n")
