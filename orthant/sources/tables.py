"""Readers and writers of tables, matrices in coordinate form (row_key, col_key, value), models and runs."""

from __future__ import annotations

import json
import re
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

COO = "row_key bigint, col_key bigint, value double"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def coo_from(df: DataFrame, row: Column, col: Column, value: Column, agg: str = "sum") -> DataFrame:
    """Cells from rows of a table; several rows of a cell are combined, zero cells dropped."""
    how = {"sum": F.sum, "max": F.max, "avg": F.avg}[agg]
    cells = df.select(row.cast("bigint").alias("row_key"), col.cast("bigint").alias("col_key"), value.cast("double").alias("value"))
    return cells.groupBy("row_key", "col_key").agg(how("value").alias("value")).where("value <> 0")


def coo_from_array(df: DataFrame, row: str, array: str) -> DataFrame:
    return df.select(F.col(row).cast("bigint").alias("row_key"), F.posexplode(array).alias("col_key", "value")).select("row_key", F.col("col_key").cast("bigint"), F.col("value").cast("double")).where("value <> 0")


def coo_from_map(df: DataFrame, row: str, cells: str) -> DataFrame:
    """Cells from a map of column key to value."""
    return coo_from(df.select(F.col(row).alias("r"), F.explode(cells).alias("c", "v")), F.col("r"), F.col("c"), F.col("v"))


def coo_from_json(df: DataFrame, row: str, text: str, field: str, modulus: int) -> DataFrame:
    """Counts of a JSON document's number ``field``, folded by ``modulus``."""
    value = F.get_json_object(text, f"$.{field}").cast("bigint")
    return coo_from(df.where(value.isNotNull()), F.col(row), F.pmod(value, F.lit(modulus)), F.lit(1.0))


def validated(coo: DataFrame) -> DataFrame:
    """Raises on null, non-finite or negative cells when run; makes -0.0 zero and drops zero cells."""
    bad = F.col("row_key").isNull() | F.col("col_key").isNull() | F.col("value").isNull() | F.isnan("value") | (F.abs("value") == float("inf")) | (F.col("value") < 0)
    value = F.when(bad, F.raise_error(F.lit("a cell is null, not finite or negative")).cast("double")).otherwise(F.col("value") + F.lit(0.0))
    return coo.select("row_key", "col_key", value.alias("value")).where("value > 0")


def transpose(coo: DataFrame) -> DataFrame:
    return coo.select(F.col("col_key").alias("row_key"), F.col("row_key").alias("col_key"), "value")


def scaled(coo: DataFrame, by: str = "row", norm: str = "l2") -> DataFrame:
    """Rows or columns divided by their L1, L2 or largest value."""
    key = f"{by}_key"
    size = {"l1": F.sum("value"), "l2": F.sqrt(F.sum(F.col("value") * F.col("value"))), "max": F.max("value")}[norm]
    return coo.join(coo.groupBy(key).agg(size.alias("size")), key).select("row_key", "col_key", (F.col("value") / F.col("size")).alias("value"))


def tf_idf(coo: DataFrame) -> DataFrame:
    rows = coo.select("row_key").distinct().agg(F.count("*").alias("d"))
    seen = coo.groupBy("col_key").agg(F.count("*").alias("df")).crossJoin(F.broadcast(rows))
    return coo.join(seen, "col_key").select("row_key", "col_key", (F.col("value") * F.log((1 + F.col("d")) / (1 + F.col("df"))) + F.lit(0.0)).alias("value")).where("value > 0")


def pack_rows(coo: DataFrame) -> DataFrame:
    """(row_key, idx, val), sorted by column: one shuffle by row, and the form all row-wise passes read."""
    cells = F.array_sort(F.collect_list(F.struct("col_key", "value")))
    return coo.groupBy("row_key").agg(cells.alias("c")).select("row_key", F.col("c.col_key").alias("idx"), F.col("c.value").alias("val"))


def strip_html(html: Column) -> Column:
    plain = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return F.regexp_replace(F.regexp_replace(plain, r"<[^>]*>", " "), r"&[a-z]+;", " ")


def words(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit("[a-z]{2,}"), F.lit(0))


def vocabulary(docs: DataFrame, n_terms: int) -> DataFrame:
    """(word, n, col_key): the most frequent words, ties by word. The numbering window sees ``n_terms`` rows."""
    top = docs.select(F.explode(words(F.col("text"))).alias("word")).groupBy("word").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "word").limit(n_terms)
    from pyspark.sql import Window

    return top.withColumn("col_key", (F.row_number().over(Window.orderBy(F.desc("n"), "word")) - 1).cast("bigint"))


def term_matrix(docs: DataFrame, n_terms: int = 1000) -> DataFrame:
    """Counts of the vocabulary's words in ``docs`` (row_key, text)."""
    tokens = docs.select("row_key", F.explode(words(F.col("text"))).alias("word"))
    # the vocabulary has n_terms rows: a proven bound for the broadcast
    return tokens.join(F.broadcast(vocabulary(docs, n_terms).select("word", "col_key")), "word").groupBy("row_key", "col_key").agg(F.count("*").cast("double").alias("value"))


def read_coo(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    reader = spark.read.schema(COO)
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def write_coo(coo: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = coo.write.mode("overwrite")
    writer.option("header", True).csv(path) if fmt == "csv" else writer.format(fmt).save(path)


def save_model(path: str, rows: DataFrame, cols: DataFrame, config: dict, trace: DataFrame | None = None) -> str:
    """Writes a new version below ``path``; the manifest comes last, so a broken write leaves no version."""
    version = f"{path}/v-{uuid.uuid4().hex}"
    rows.repartitionByRange("key").sortWithinPartitions("key").write.parquet(f"{version}/rows")
    cols.write.parquet(f"{version}/cols")
    if trace is not None:
        trace.write.partitionBy("metric").parquet(f"{version}/trace")
    spark = rows.sparkSession
    spark.createDataFrame([(json.dumps(config, sort_keys=True), version)], "config string, version string").coalesce(1).withColumn("at", F.current_timestamp()).write.mode("append").json(f"{path}/manifest")
    return version


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame, dict]:
    last = spark.read.schema("config string, version string, at timestamp").json(f"{path}/manifest").orderBy(F.desc("at")).first()
    version = f"{path}/{re.sub(r'.*/', '', last['version'])}"
    return spark.read.parquet(f"{version}/rows"), spark.read.parquet(f"{version}/cols"), json.loads(last["config"])
