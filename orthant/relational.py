"""Queries around models and runs in relational operators, each with its SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from .functions.hashing import hash_uniform
from .operators import solvers
from .operators import wide as W
from .sources import matrices as M
from .sources.tables import coo_from_json, load, pack_rows, scaled, tf_idf, vocabulary

K, SEED = 3, 11
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


# models of hashed factors stand for fitted ones, so that SQL has the same numbers
_DOC = (O.vocabulary("x_doc"), "x AS (SELECT row_key, col_key, CAST(count(*) AS DOUBLE) AS value FROM tokens JOIN vocab USING (word) GROUP BY 1, 2)")
_MODEL = (*_DOC, O.start("b0", "col", K, SEED), O.times("h", "b0", K))


def _doc_model(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    x = M.x_doc(spark, sf)
    b = W.uniform_factor(W.keys_of(x, "col"), K, SEED)
    return W.times(x, b, K), b


_BEST = "CASE WHEN f0 >= f1 AND f0 >= f2 THEN 0 WHEN f1 >= f2 THEN 1 ELSE 2 END"


def _best() -> F.Column:
    return F.when((F.col("f0") >= F.col("f1")) & (F.col("f0") >= F.col("f2")), 0).when(F.col("f1") >= F.col("f2"), 1).otherwise(2)


@query(O.query(*_DOC, O.start("b0", "col", K, SEED), select="SELECT component, rank, word, round(weight, 6) AS weight FROM (SELECT component, word, weight, row_number() OVER (PARTITION BY component ORDER BY weight DESC, word) AS rank FROM (SELECT key, 0 AS component, f0 AS weight FROM b0 UNION ALL SELECT key, 1, f1 FROM b0 UNION ALL SELECT key, 2, f2 FROM b0) l JOIN vocab ON key = col_key) t WHERE rank <= 10"))
def top_terms(spark: SparkSession, sf: str) -> DataFrame:
    vocab = vocabulary(M.first_documents(spark, sf), M.TERMS)
    b = W.uniform_factor(vocab.select(F.col("col_key").alias("key")), K, SEED)
    long = b.select("key", F.posexplode(F.array(*W.cols(K))).alias("component", "weight")).join(vocab, F.col("key") == F.col("col_key"))
    return long.withColumn("rank", F.row_number().over(Window.partitionBy("component").orderBy(F.desc("weight"), "word"))).where("rank <= 10").select("component", "rank", "word", F.round("weight", 6).alias("weight"))


@query(O.query(*_MODEL, select=f"SELECT source, lang, {_BEST} AS component, count(*) AS n FROM h JOIN documents ON key = doc_id GROUP BY 1, 2, 3"))
def doc_topics_by_source(spark: SparkSession, sf: str) -> DataFrame:
    h, _ = _doc_model(spark, sf)
    return h.join(load(spark, sf, "documents"), F.col("key") == F.col("doc_id")).groupBy("source", "lang", _best().alias("component")).agg(F.count("*").alias("n"))


@query(O.query(*_MODEL, select=f"SELECT quality, toxic, {_BEST} AS component, count(*) AS n FROM h LEFT JOIN labels ON key = doc_id GROUP BY 1, 2, 3"))
def topics_by_label(spark: SparkSession, sf: str) -> DataFrame:
    h, _ = _doc_model(spark, sf)
    return h.join(load(spark, sf, "labels"), F.col("key") == F.col("doc_id"), "left").groupBy("quality", "toxic", _best().alias("component")).agg(F.count("*").alias("n"))


#: Numbers of a column factor that may be broadcast for scoring.
MOST_SCORED = 20_000_000


def best_columns(a: DataFrame, b: DataFrame, k: int, top: int) -> DataFrame:
    """row_key, col_key, rank, score: each row's ``top`` columns, the least key first among equals. Blocks of rows meet the
    broadcast column factor, whose counted size is checked, so that no product of rows and columns is ever a table."""
    if b.count() * (k + 1) > MOST_SCORED:
        raise ValueError("the column factor is too large to be broadcast")
    got = sorted((r["key"], *(r[c] for c in W.cols(k))) for r in b.collect())
    spread = a.sparkSession.sparkContext.broadcast((np.array([g[0] for g in got], np.int64), np.array([g[1:] for g in got], float).reshape(-1, k)))

    def run(batches):
        keys, f = spread.value
        most = min(top, len(keys))
        for batch in batches:
            for at in range(0, batch.num_rows, step := max(1, 2_000_000 // max(1, len(keys)))):
                part = batch.slice(at, step)
                left = np.stack([part.column(c).to_numpy() for c in W.cols(k)], 1)
                score = np.zeros((len(left), len(keys)))
                for j in range(k):
                    score += left[:, j, None] * f[None, :, j]
                bar = np.partition(score, len(keys) - most, axis=1)[:, len(keys) - most] if most else np.zeros(len(left))
                row, col = np.nonzero(score >= bar[:, None]) if most else (np.zeros(0, int), np.zeros(0, int))
                order = np.lexsort((col, -score[row, col], row))
                row, col = row[order], col[order]
                rank = np.arange(len(row)) - np.searchsorted(row, row) + 1
                row, col, rank = row[rank <= most], col[rank <= most], rank[rank <= most]
                yield pa.RecordBatch.from_arrays([part.column("key").take(pa.array(row)), pa.array(keys[col]), pa.array(rank, pa.int32()), pa.array(score[row, col])], ["row_key", "col_key", "rank", "score"])

    return a.select("key", *W.cols(k)).mapInArrow(run, "row_key bigint, col_key bigint, rank int, score double")


@query(O.query(O.matrix("x_part"), O.start("a0", "row", K, SEED), O.start("b0", "col", K, SEED + 1), select="SELECT row_key, col_key, rank, round(score, 6) AS score FROM (SELECT a.key AS row_key, b.key AS col_key, a.f0 * b.f0 + a.f1 * b.f1 + a.f2 * b.f2 AS score, row_number() OVER (PARTITION BY a.key ORDER BY a.f0 * b.f0 + a.f1 * b.f1 + a.f2 * b.f2 DESC, b.key) AS rank FROM a0 a CROSS JOIN b0 b) t WHERE rank <= 5"))
def recommend_items(spark: SparkSession, sf: str) -> DataFrame:
    """The five columns with the highest model value for every row."""
    x = M.x_part(spark, sf)
    a, b = W.uniform_factor(W.keys_of(x, "row"), K, SEED), W.uniform_factor(W.keys_of(x, "col"), K, SEED + 1)
    return best_columns(a, b, K, 5).select("row_key", "col_key", "rank", F.round("score", 6).alias("score"))


_REGION = "JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


@query(f"SELECT r_name, n_name, round(sum(l_quantity), 2) AS quantity, CAST(grouping(r_name) * 2 + grouping(n_name) AS BIGINT) AS level FROM lineitem JOIN orders ON l_orderkey = o_orderkey {_REGION} GROUP BY ROLLUP (r_name, n_name)")
def cust_by_region_rollup(spark: SparkSession, sf: str) -> DataFrame:
    t = {n: load(spark, sf, n) for n in ("lineitem", "orders", "customer", "nation", "region")}
    rows = t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t["nation"]), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t["region"]), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.rollup("r_name", "n_name").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"), F.grouping_id().alias("level"))


# a relation of runs: a user's events of a type in the order of time, as curves that fall and whose disturbance is the event's value
_RUN = "runs AS (SELECT event_type AS method, user_id AS seed, iter, exp(-0.05 * iter) * (1 + value / 1000) AS value FROM (SELECT event_type, user_id, value, row_number() OVER (PARTITION BY event_type, user_id ORDER BY ts, event_id) AS iter FROM events) t)"


def _runs(spark: SparkSession, sf: str) -> DataFrame:
    place = F.row_number().over(Window.partitionBy("event_type", "user_id").orderBy("ts", "event_id")).cast("bigint")
    rows = load(spark, sf, "events").select(F.col("event_type").alias("method"), F.col("user_id").alias("seed"), place.alias("iter"), "value")
    return rows.withColumn("value", F.exp(F.lit(-0.05) * F.col("iter")) * (1 + F.col("value") / 1000))


@query(f"WITH {_RUN} SELECT method, iter, round(median(value), 6) AS value, count(*) AS starts FROM runs GROUP BY 1, 2")
def run_median(spark: SparkSession, sf: str) -> DataFrame:
    return _runs(spark, sf).groupBy("method", "iter").agg(F.round(F.median("value"), 6).alias("value"), F.count("*").alias("starts"))


@query(f"WITH {_RUN} SELECT method, seed, round(avg(value), 6) AS mean, round(min(value), 6) AS least, CAST(grouping(method) * 2 + grouping(seed) AS BIGINT) AS level FROM runs GROUP BY CUBE (method, seed)")
def run_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _runs(spark, sf).cube("method", "seed").agg(F.round(F.avg("value"), 6).alias("mean"), F.round(F.min("value"), 6).alias("least"), F.grouping_id().alias("level"))


@query(f"WITH {_RUN}, d AS (SELECT method, seed, iter, value, lag(value) OVER (PARTITION BY method, seed ORDER BY iter) AS before, min(value) OVER (PARTITION BY method, seed ORDER BY iter ROWS UNBOUNDED PRECEDING) AS best FROM runs) SELECT method, seed, count(*) FILTER (WHERE value > before) AS rises, round(max(value / best), 6) AS worst_ratio, CASE WHEN count(*) > 1 THEN round(regr_slope(ln(value), iter), 6) END AS rate FROM d GROUP BY 1, 2")
def trace_monotone(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("method", "seed").orderBy("iter")
    d = _runs(spark, sf).withColumn("before", F.lag("value").over(w)).withColumn("best", F.min("value").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return d.groupBy("method", "seed").agg(F.count_if(F.col("value") > F.col("before")).alias("rises"), F.round(F.max(F.col("value") / F.col("best")), 6).alias("worst_ratio"), F.when(F.count("*") > 1, F.round(F.regr_slope(F.log("value"), F.col("iter")), 6)).alias("rate"))


# joins
@query("SELECT p_brand, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def op_join_inner_broadcast(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem").join(F.broadcast(load(spark, sf, "part").select("p_partkey", "p_brand")), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def op_join_shuffle_hash(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem").join(load(spark, sf, "orders").hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def op_join_left_outer(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "customer").join(load(spark, sf, "orders").hint("merge"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND quality = 1)")
def op_join_left_semi(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents").join(load(spark, sf, "labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id")


@query("SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def op_join_left_anti(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id", "left_anti").select("doc_id")


_HALVES = (O.matrix("x_evt"), O.start("p0", "col", K, 1), O.start("q0", "row", K, 2))


@query(O.query(*_HALVES, select="SELECT coalesce(p.key, q.key) AS key, round(coalesce(p.f0, 0) - coalesce(q.f0, 0), 6) AS gap FROM p0 p FULL JOIN q0 q ON p.key = q.key"))
def op_join_full_outer(spark: SparkSession, sf: str) -> DataFrame:
    """The factors of columns and of rows side by side."""
    x = M.x_evt(spark, sf)
    p, q = W.uniform_factor(W.keys_of(x, "col"), K, 1).select("key", F.col("f0").alias("p")), W.uniform_factor(W.keys_of(x, "row"), K, 2).select("key", F.col("f0").alias("q"))
    return p.join(q, "key", "full").select("key", F.round(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0)), 6).alias("gap"))


@query("SELECT a.p_size AS size0, b.p_size AS size1, count(*) AS n FROM (SELECT DISTINCT p_size, p_brand FROM part) a JOIN (SELECT DISTINCT p_size, p_brand FROM part) b ON a.p_brand = b.p_brand AND a.p_size < b.p_size AND b.p_size <= a.p_size + 3 GROUP BY 1, 2")
def op_join_theta_band(spark: SparkSession, sf: str) -> DataFrame:
    """A band join: equal brand, and sizes within three, by buckets of three and their neighbours."""
    part = load(spark, sf, "part").select("p_size", "p_brand").distinct()
    a = part.select(F.col("p_brand"), F.col("p_size").alias("size0"), F.explode(F.array(F.floor(F.col("p_size") / 3), F.floor(F.col("p_size") / 3) + 1)).alias("band"))
    b = part.select("p_brand", F.col("p_size").alias("size1"), F.floor(F.col("p_size") / 3).alias("band"))
    return a.join(b, ["p_brand", "band"]).where("size0 < size1 and size1 <= size0 + 3").groupBy("size0", "size1").agg(F.count("*").alias("n"))


@query("SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM events")
def op_join_as_of(spark: SparkSession, sf: str) -> DataFrame:
    """Each event's last earlier purchase of its user."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return load(spark, sf, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("last_purchase"))


@query(O.query(O.matrix("x_evt"), O.start("a0", "row", K, SEED), select="SELECT l.key, round(l.f0 * r.f0 + l.f1 * r.f1 + l.f2 * r.f2, 6) AS square FROM a0 l JOIN a0 r ON l.key = r.key"))
def op_join_self(spark: SparkSession, sf: str) -> DataFrame:
    a = W.uniform_factor(W.keys_of(M.x_evt(spark, sf), "row"), K, SEED)
    r = a.select("key", *(F.col(c).alias(f"r{c}") for c in W.cols(K)))
    return a.join(r, "key").select("key", F.round(W.total(F.col(c) * F.col(f"r{c}") for c in W.cols(K)), 6).alias("square"))


# windows
@query("SELECT doc_id, rank() OVER w AS r, dense_rank() OVER w AS d, ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS q, round(percent_rank() OVER w, 6) AS p FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars)")
def op_window_ranks(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("lang").orderBy("n_chars")
    return load(spark, sf, "documents").select("doc_id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(Window.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("q"), F.round(F.percent_rank().over(w), 6).alias("p"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def op_window_range(spark: SparkSession, sf: str) -> DataFrame:
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-3_600_000_000, 0)
    return load(spark, sf, "events").withColumn("t", t).select("event_id", F.count("*").over(w).alias("last_hour"))


@query(f"WITH {_RUN} SELECT DISTINCT method, seed, round(first_value(value) OVER w, 6) AS first, round(last_value(value) OVER w, 6) AS last, round(nth_value(value, 3) OVER w, 6) AS third FROM runs WINDOW w AS (PARTITION BY method, seed ORDER BY iter ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def op_window_ends(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("method", "seed").orderBy("iter").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _runs(spark, sf).select("method", "seed", F.round(F.first("value").over(w), 6).alias("first"), F.round(F.last("value").over(w), 6).alias("last"), F.round(F.nth_value("value", 3).over(w), 6).alias("third")).distinct()


# sets, grouping sets, top-k
_LANG = "SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]{{2,}}')) AS word FROM documents WHERE lang = '{}'"


def _words_of(spark: SparkSession, sf: str, lang: str) -> DataFrame:
    from .sources.tables import words

    return load(spark, sf, "documents").where(F.col("lang") == lang).select(F.explode(words(F.col("text"))).alias("word")).distinct()




@query(f"{_LANG.format('en')} INTERSECT {_LANG.format('fr')}")
def op_set_intersect(spark: SparkSession, sf: str) -> DataFrame:
    return _words_of(spark, sf, "en").intersect(_words_of(spark, sf, "fr"))


@query(f"{_LANG.format('es')} EXCEPT {_LANG.format('fr')}")
def op_set_except(spark: SparkSession, sf: str) -> DataFrame:
    return _words_of(spark, sf, "es").exceptAll(_words_of(spark, sf, "fr")).distinct()


@query("SELECT lang AS name, count(*) AS n FROM documents GROUP BY 1 UNION ALL SELECT source, count(*) FROM documents GROUP BY 1")
def op_set_union(spark: SparkSession, sf: str) -> DataFrame:
    d = load(spark, sf, "documents")
    return d.groupBy(F.col("lang").alias("name")).agg(F.count("*").alias("n")).unionByName(d.groupBy(F.col("source").alias("name")).agg(F.count("*").alias("n")))


@query("SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())")
def op_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    load(spark, sf, "documents").createOrReplaceTempView("documents_of_grouping")
    return spark.sql("SELECT lang, source, count(*) AS n, sum(n_chars) AS chars FROM documents_of_grouping GROUP BY GROUPING SETS ((lang, source), (lang), ())")


@query("SELECT l_partkey, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 20")
def op_topk(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem").groupBy("l_partkey").agg(F.round(F.sum("l_quantity"), 2).alias("quantity")).orderBy(F.desc("quantity"), "l_partkey").limit(20)


@query("SELECT s_suppkey, count(*) FILTER (WHERE l_returnflag = 'A') AS a, count(*) FILTER (WHERE l_returnflag = 'N') AS n, count(*) FILTER (WHERE l_returnflag = 'R') AS r FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def op_pivot(spark: SparkSession, sf: str) -> DataFrame:
    rows = load(spark, sf, "lineitem").join(load(spark, sf, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    out = rows.groupBy("s_suppkey").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1)))
    return out.select("s_suppkey", *(F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "ANR"))


@query("SELECT user_id AS row_key, CAST(CAST(json_extract_string(props, '$.k') AS BIGINT) % 32 AS BIGINT) AS col_key, CAST(count(*) AS DOUBLE) AS value FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1, 2")
def op_array_map_json(spark: SparkSession, sf: str) -> DataFrame:
    return coo_from_json(load(spark, sf, "events"), "user_id", "props", "k", 32)


@query("SELECT vec_id AS row_key, CAST(generate_subscripts(embedding, 1) - 1 AS BIGINT) AS col_key, round(CAST(unnest(embedding) AS DOUBLE), 6) AS value FROM embeddings")
def op_udf_udaf_udtf(spark: SparkSession, sf: str) -> DataFrame:
    from .functions.udx import register

    register(spark)
    load(spark, sf, "embeddings").createOrReplaceTempView("vectors_of_udtf")
    return spark.sql("SELECT v.vec_id AS row_key, c.col_key, round(c.value, 6) AS value FROM vectors_of_udtf v, LATERAL explode_cells(v.embedding) c")


@query(O.query(O.matrix("x_part"), "t AS (SELECT row_key, sqrt(sum(value * value)) AS size FROM x GROUP BY 1)", select="SELECT x.row_key, col_key, round(value / size, 6) AS value FROM x JOIN t ON x.row_key = t.row_key"))
def op_scale_rows(spark: SparkSession, sf: str) -> DataFrame:
    return scaled(M.x_part(spark, sf)).select("row_key", "col_key", F.round("value", 6).alias("value"))


@query(O.query(*_DOC, "t AS (SELECT col_key, count(*) AS df FROM x GROUP BY 1)", select="SELECT row_key, x.col_key, round(value * ln((1 + (SELECT count(DISTINCT row_key) FROM x)) / CAST(1 + df AS DOUBLE)), 6) AS value FROM x JOIN t ON x.col_key = t.col_key WHERE value * ln((1 + (SELECT count(DISTINCT row_key) FROM x)) / CAST(1 + df AS DOUBLE)) > 0"))
def op_tf_idf(spark: SparkSession, sf: str) -> DataFrame:
    return tf_idf(M.x_doc(spark, sf)).select("row_key", "col_key", F.round("value", 6).alias("value"))


# streams
def _events_stream(spark: SparkSession, sf: str) -> DataFrame:
    from .streaming.cells import event_stream

    return event_stream(spark, f"{sf}/events.parquet*", load(spark, sf, "events").schema)


@query(O.query(O.matrix("x_evt"), select="SELECT row_key, col_key, value FROM x"))
def stream_cells(spark: SparkSession, sf: str) -> DataFrame:
    from .streaming.cells import cell_counts, run_to_files

    base = f"{solvers.shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    return run_to_files(cell_counts(_events_stream(spark, sf)), f"{base}/out", f"{base}/checkpoint")


@query("SELECT user_id, event_type, date_trunc('hour', ts) AS start, count(*) AS n FROM events GROUP BY 1, 2, 3")
def stream_windows(spark: SparkSession, sf: str) -> DataFrame:
    from .streaming.cells import run_to_files, windowed_counts

    base = f"{solvers.shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    out = run_to_files(windowed_counts(_events_stream(spark, sf)), f"{base}/out", f"{base}/checkpoint")
    return out.select("user_id", "event_type", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query()
def stream_fold_in(spark: SparkSession, sf: str) -> DataFrame:
    """Users' packed rows arrive as a stream and are folded into a fixed model of the event matrix."""
    from .streaming.cells import fold_in_stream

    x = M.x_evt(spark, sf)
    _, b, _ = solvers.factorize(x, 4, 8, 4, 10)
    model = sorted((r["key"], r["f"]) for r in b.collect())
    places = spark.createDataFrame([(int(k), i) for i, (k, _) in enumerate(model)], "col_key bigint, place bigint")
    packed = solvers.held(pack_rows(x.join(F.broadcast(places), "col_key").select("row_key", F.col("place").alias("col_key"), "value")).select("row_key", F.col("idx").cast("array<int>").alias("idx"), "val"))
    base = f"{solvers.shared_folder(spark)}/fold-{uuid.uuid4().hex}"
    packed.write.parquet(f"{base}/in")
    fold_in_stream(spark.readStream.schema(packed.schema).parquet(f"{base}/in"), np.array([f for _, f in model]), f"{base}/out", f"{base}/checkpoint")
    return spark.read.parquet(f"{base}/out").select("key", F.posexplode("f").alias("component", "weight"))
