"""Record frames (unit, key, record_id, values, event_ts) from the star schema and the text tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import synth


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def line_records(spark: SparkSession, sf_dir: str, key: str = "l_suppkey") -> DataFrame:
    """lineitem joined with orders: unit = customer, key = an expression over lineitem.

    Order and line number repeat in the data, so the record id holds part and supplier too.
    """
    rid = F.concat_ws("-", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")])
    items = load(spark, sf_dir, "lineitem").select("l_orderkey", rid.alias("record_id"), F.expr(key).cast("string").alias("key"), "l_quantity", "l_extendedprice", "l_shipdate")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return items.join(orders, items.l_orderkey == orders.o_orderkey).select(F.col("o_custkey").alias("unit"), "key", "record_id", "l_quantity", "l_extendedprice", F.col("l_shipdate").alias("event_ts"))


def brand_type_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Forum-like participation: key = (brand, type)."""
    parts = load(spark, sf_dir, "part").select("p_partkey", F.concat_ws("/", "p_brand", "p_type").alias("brand_type"))
    lines = line_records(spark, sf_dir, "l_partkey")
    return lines.join(parts, lines.key == parts.p_partkey.cast("string")).select("unit", F.col("brand_type").alias("key"), "record_id", "l_quantity", "l_extendedprice", "event_ts")


def event_records(spark: SparkSession, sf_dir: str, key: str = "event_type") -> DataFrame:
    """Clicks by (type, day); `props.k` takes the key out of the JSON column."""
    col = F.get_json_object("props", "$.k") if key == "props.k" else F.expr(key)
    ev = load(spark, sf_dir, "events")
    return ev.select(F.col("user_id").alias("unit"), col.alias("key"), F.col("event_id").alias("record_id"), "value", F.col("ts").alias("event_ts"), F.to_date("ts").alias("day"))


def uniform_key_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders by customer, under as many keys as customers, dealt uniformly by a hash of the order."""
    orders = load(spark, sf_dir, "orders").select(F.col("o_custkey").alias("unit"), F.col("o_orderkey").alias("id"))
    keys = load(spark, sf_dir, "customer").agg(F.count(F.lit(1)).alias("_keys"))
    key = F.floor(synth.uniform(42, "key") * F.col("_keys")).cast("string")
    return orders.crossJoin(F.broadcast(keys)).select("unit", key.alias("key"), F.col("id").cast("string").alias("record_id"))


def token_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Search-term-like: a record for each different lower-cased token of a document; unit = (document, token)."""
    docs = load(spark, sf_dir, "documents").select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)))).alias("key"))
    rid = F.concat_ws("-", F.col("doc_id").cast("string"), "key")
    return docs.select(rid.alias("unit"), "key", rid.alias("record_id"), "doc_id")


def host_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages")
    return pages.select(F.col("page_id").alias("unit"), F.regexp_extract("url", "^[a-z]+://([^/:]+)", 1).alias("key"), F.col("page_id").alias("record_id"))


def role_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    conv = load(spark, sf_dir, "conversations")
    return conv.select(F.col("conv_id").alias("unit"), F.col("role").alias("key"), F.concat_ws("-", F.col("conv_id").cast("string"), F.col("turn").cast("string")).alias("record_id"))
