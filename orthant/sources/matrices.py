"""The matrices that the given tables carry, each as (row_key, col_key, value) with value > 0."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .tables import coo_from, coo_from_array, load, strip_html, term_matrix

FIRST_DOCUMENTS, TERMS = 5000, 1000


def first_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("row_key"), "text")
    return docs.orderBy("row_key").limit(FIRST_DOCUMENTS)


def x_doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return term_matrix(first_documents(spark, sf_dir), TERMS)


def quantized(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells of the vectors, shifted and cut to 256 levels."""
    cells = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_key"), F.posexplode("embedding").alias("col_key", "v"))
    cells = cells.select("row_key", F.col("col_key").cast("bigint"), F.col("v").cast("double").alias("v"))
    ends = cells.agg(F.min("v").alias("lo"), F.max("v").alias("hi"))  # one row
    return cells.crossJoin(F.broadcast(ends)).select("row_key", "col_key", F.floor((F.col("v") - F.col("lo")) / (F.col("hi") - F.col("lo")) * 255).cast("double").alias("value"))


def x_img(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantized(spark, sf_dir).where("value > 0")


def x_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Positive and negative halves side by side."""
    cells = coo_from_array(load(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    return cells.select("row_key", (F.col("col_key") + F.when(F.col("value") < 0, 64).otherwise(0)).cast("bigint").alias("col_key"), F.abs("value").alias("value"))


def x_cust(spark: SparkSession, sf_dir: str) -> DataFrame:
    part, orders, items = (load(spark, sf_dir, t) for t in ("part", "orders", "lineitem"))
    kinds = part.select("p_brand", "p_type").distinct()  # brands x types, a fixed catalogue
    kinds = kinds.withColumn("kind", F.row_number().over(Window.orderBy("p_brand", "p_type")) - 1)
    # a part's kind is found before the join, so that no names travel with the items
    kind = part.join(kinds, ["p_brand", "p_type"]).select("p_partkey", "kind")
    rows = items.join(kind, F.col("l_partkey") == F.col("p_partkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return coo_from(rows, F.col("o_custkey"), F.col("kind"), F.col("l_quantity"))


def x_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return coo_from(load(spark, sf_dir, "lineitem"), F.col("l_partkey"), F.col("l_suppkey"), F.col("l_quantity"))


def x_evt(spark: SparkSession, sf_dir: str) -> DataFrame:
    kind = F.array_position(F.array(*map(F.lit, ("click", "error", "purchase", "signup", "view"))), F.col("event_type")) - 1
    return coo_from(load(spark, sf_dir, "events"), F.col("user_id"), kind * 24 + F.hour("ts"), F.lit(1.0))


def _month() -> F.Column:
    return F.year("l_shipdate") * 12 + F.month("l_shipdate")


def x_ship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return coo_from(load(spark, sf_dir, "lineitem"), F.col("l_suppkey"), _month(), F.col("l_extendedprice"))


def x_shipf(spark: SparkSession, sf_dir: str) -> DataFrame:
    flag = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
    return coo_from(load(spark, sf_dir, "lineitem"), F.col("l_suppkey"), _month() * 3 + flag, F.col("l_extendedprice"))


def x_big(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return coo_from(rows, F.col("o_custkey"), F.col("l_partkey"), F.col("l_quantity"))


def x_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return term_matrix(load(spark, sf_dir, "pages").select(F.col("page_id").alias("row_key"), strip_html(F.col("html")).alias("text")), TERMS)


def x_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    role = F.when(F.col("role") == "assistant", 0).when(F.col("role") == "system", 1).when(F.col("role") == "user", 2).otherwise(3)
    return term_matrix(load(spark, sf_dir, "conversations").select((F.col("conv_id") * 4 + role).alias("row_key"), "text"), TERMS)


MATRICES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (x_doc, x_img, x_split, x_cust, x_part, x_evt, x_ship, x_shipf, x_big, x_pages, x_conversations)}
