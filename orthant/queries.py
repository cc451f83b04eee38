"""Registered queries: every method, variant, baseline, measure and workload on the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from . import relational, workloads
from .functions.hashing import hash_normal
from .operators import costs, measures, projection, solvers
from .operators import wide as W
from .operators.kernels import Penalty
from .sources import matrices as M
from .sources.tables import load, pack_rows, vocabulary

K, S, SEED = 2, 3, 7
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def rounded(f: DataFrame, k: int, digits: int = 5, side: str | None = None) -> DataFrame:
    tag = [F.lit(side).alias("side")] if side else []
    return f.select(*tag, "key", *((F.round(c, digits) + F.lit(0.0)).alias(c) for c in W.cols(k)))


def both(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    return rounded(a, k, side="a").unionByName(rounded(b, k, side="b"))


def both_sql(a: str, b: str, k: int = K) -> str:
    return f"{O.rounded(a, k, side='a')} UNION ALL {O.rounded(b, k, side='b')}"


# cells of all matrices
for _name, _build in M.MATRICES.items():
    _sql = O.query(O.matrix(_name), select="SELECT row_key, col_key, round(value, 4) AS value FROM x")
    query(_sql, f"{_name}_cells")(lambda spark, sf, b=_build: b(spark, sf).select("row_key", "col_key", F.round("value", 4).alias("value")))


@query(O.query(O.vocabulary("x_doc"), select="SELECT word, n, col_key FROM vocab"))
def x_doc_vocab(spark: SparkSession, sf: str) -> DataFrame:
    return vocabulary(M.first_documents(spark, sf), M.TERMS)


@query(O.query(O.matrix("x_img"), select="SELECT row_key, col_key, value FROM quantized"))
def x_img_quantized(spark: SparkSession, sf: str) -> DataFrame:
    return M.quantized(spark, sf)


@query(O.query(O.matrix("x_img"), select="SELECT row_key, col_key, value FROM quantized WHERE row_key < 10"))
def x_img_samples(spark: SparkSession, sf: str) -> DataFrame:
    return M.quantized(spark, sf).where("row_key < 10")


_PROFILED = ("x_split", "x_cust", "x_part", "x_evt", "x_big")


def _profile_sql(name: str) -> str:
    return f"SELECT * FROM (WITH {O.matrix(name)} SELECT '{name}' AS matrix, count(DISTINCT row_key) AS d, count(DISTINCT col_key) AS n, count(*) AS nnz, round(count(*) / CAST(count(DISTINCT row_key) * count(DISTINCT col_key) AS DOUBLE), 6) AS density, round(sqrt(sum(value * value)), 3) AS norm, round(sum(value) / CAST(count(DISTINCT row_key) * count(DISTINCT col_key) AS DOUBLE), 6) AS mean FROM x) p"


@query(" UNION ALL ".join(map(_profile_sql, _PROFILED)))
def matrix_profile(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for name in _PROFILED:
        p = M.MATRICES[name](spark, sf).agg(F.count_distinct("row_key").alias("d"), F.count_distinct("col_key").alias("n"), F.count("*").alias("nnz"), F.sum(F.col("value") * F.col("value")).alias("xx"), F.sum("value").alias("mass"))
        cells = (F.col("d") * F.col("n")).cast("double")
        p = p.select(F.lit(name).alias("matrix"), "d", "n", "nnz", F.round(F.col("nnz") / cells, 6).alias("density"), F.round(F.sqrt("xx"), 3).alias("norm"), F.round(F.col("mass") / cells, 6).alias("mean"))
        out = p if out is None else out.unionByName(p)
    return out


# starts and random matrices
_EVT = O.matrix("x_evt")
_STARTS = (_EVT, O.start("a0", "row", K, SEED), O.start("b0", "col", K, SEED + 1))


def _starts(spark: SparkSession, sf: str, name: str = "x_evt") -> tuple[DataFrame, DataFrame, DataFrame]:
    x = M.MATRICES[name](spark, sf)
    return x, W.uniform_factor(W.keys_of(x, "row"), K, SEED), W.uniform_factor(W.keys_of(x, "col"), K, SEED + 1)


@query(O.query(*_STARTS, select=both_sql("a0", "b0")))
def init_factors(spark: SparkSession, sf: str) -> DataFrame:
    _, a, b = _starts(spark, sf)
    return both(a, b, K)


@query(O.query(_EVT, O.gaussian("om", "col", S, SEED), select=O.rounded("om", S)))
def hash_normal_matrix(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(W.normal_factor(W.keys_of(M.x_evt(spark, sf), "col"), S, SEED), S)


# products
@query(O.query(*_STARTS, O.times("h", "b0", K), select=O.rounded("h", K)))
def product_x_b(spark: SparkSession, sf: str) -> DataFrame:
    x, _, b = _starts(spark, sf)
    return rounded(W.times(x, b, K), K)


@query(O.query(*_STARTS, O.times("p", "a0", K, "col"), select=O.rounded("p", K)))
def product_xt_a(spark: SparkSession, sf: str) -> DataFrame:
    x, a, _ = _starts(spark, sf)
    return rounded(W.times_t(x, a, K), K)


@query(O.query(*_STARTS, O.gram("g", "b0", K), select="SELECT round(g0_0, 5) AS g0_0, round(g0_1, 5) AS g0_1, round(g1_0, 5) AS g1_0, round(g1_1, 5) AS g1_1 FROM g"))
def gram_b(spark: SparkSession, sf: str) -> DataFrame:
    g = W.gram(_starts(spark, sf)[2], K)
    return g.select(*(F.round(c, 5).alias(c) for c in g.columns))


# one iteration of the uncompressed methods, side by side
def _iteration(spark: SparkSession, sf: str, update, update_b=None, iterations: int = 1, normal: bool = False) -> DataFrame:
    x, a, b = _starts(spark, sf)
    for _ in range(iterations):
        a = update(a, W.times(x, b, K), W.gram(b, K), K)
        if normal:
            a, b = W.normalise(a, b, K)
        b = (update_b or update)(b, W.times_t(x, a, K), W.gram(a, K), K)
    return both(a, b, K)


def _iteration_sql(update, update_b=None, iterations: int = 1, normal: bool = False) -> str:
    ctes, a, b = list(_STARTS), "a0", "b0"
    for i in range(1, iterations + 1):
        ctes += [O.times(f"h{i}", b, K), O.gram(f"g{i}", b, K), update(f"a{i}", a, f"h{i}", f"g{i}", K)]
        a = f"a{i}"
        if normal:
            ctes.append(O.normalise(f"an{i}", f"bn{i}", a, b, K))
            a, b = f"an{i}", f"bn{i}"
        ctes += [O.times(f"p{i}", a, K, "col"), O.gram(f"w{i}", a, K), (update_b or update)(f"b{i}", b, f"p{i}", f"w{i}", K)]
        b = f"b{i}"
    return O.query(*ctes, select=both_sql(a, b))


def _pointwise(form):
    return lambda name, f, h, g, k: O.pointwise(name, f, h, g, k, form(k))


def _penalised(alpha: float, beta: float):
    return lambda f, h, g, k: W.sweep(f, h, g, k, alpha, beta), lambda name, f, h, g, k: O.sweep(name, f, h, g, k, alpha, beta)


query(_iteration_sql(_pointwise(O.mu_form)), "mu_step")(lambda spark, sf: _iteration(spark, sf, W.multiplicative))
query(_iteration_sql(O.sweep), "gram_hals_sweep")(lambda spark, sf: _iteration(spark, sf, W.sweep))
query(_iteration_sql(O.sweep, iterations=2, normal=True), "gram_hals_normalised")(lambda spark, sf: _iteration(spark, sf, W.sweep, iterations=2, normal=True))
query(_iteration_sql(_pointwise(O.als_form)), "als_step")(lambda spark, sf: _iteration(spark, sf, W.clipped_least_squares))
query(_iteration_sql(_pointwise(O.pgd_form)), "pgd_step")(lambda spark, sf: _iteration(spark, sf, W.projected_gradient))
for _name, _alpha, _beta in (("gram_hals_sparse", 0.5, 0.0), ("gram_hals_smooth", 0.0, 2.0), ("gram_hals_sparse_smooth", 0.5, 2.0)):
    _df, _sq = _penalised(_alpha, _beta)
    query(_iteration_sql(O.sweep, _sq), _name)(lambda spark, sf, u=_df: _iteration(spark, sf, W.sweep, u))


@query(O.query(*_STARTS, O.times("h", "b0", K), O.gram("g", "b0", K), O.times("p", "a0", K, "col"), O.gram("w", "a0", K), O.pointwise("ga", "a0", "h", "g", K, O.gradient_form(K)), O.pointwise("gb", "b0", "p", "w", K, O.gradient_form(K)), select="SELECT 'a' AS side, round(sqrt(sum(f0 * f0 + f1 * f1)), 4) AS norm FROM ga UNION ALL SELECT 'b', round(sqrt(sum(f0 * f0 + f1 * f1)), 4) FROM gb"))
def gradient_norms(spark: SparkSession, sf: str) -> DataFrame:
    x, a, b = _starts(spark, sf)
    size = lambda g, side: g.agg(F.round(F.sqrt(F.sum(W.total(F.col(c) * F.col(c) for c in W.cols(K)))), 4).alias("norm")).select(F.lit(side).alias("side"), "norm")
    return size(W.gradient(a, W.times(x, b, K), W.gram(b, K), K), "a").unionByName(size(W.gradient(b, W.times_t(x, a, K), W.gram(a, K), K), "b"))


# residual forms, component by component; the SQL uses the Gram form, so equality is checked too
def _residual_update(x: DataFrame, f: DataFrame, other: DataFrame, j: int, side: str, alpha: float = 0.0, beta: float = 0.0) -> DataFrame:
    """Component j of ``f`` from the explicit residual over all cells of rows x columns."""
    key, far = (f"{side}_key", "col_key" if side == "row" else "row_key")
    left = f.select(F.col("key").alias(key), *(F.col(c).alias(f"a{c}") for c in W.cols(K)))
    right = other.select(F.col("key").alias(far), *(F.col(c).alias(f"b{c}") for c in W.cols(K)))
    grid = left.crossJoin(F.broadcast(right)).join(x, ["row_key", "col_key"], "left")  # the residual is dense by definition
    rest = F.coalesce("value", F.lit(0.0)) - W.total(F.col(f"af{i}") * F.col(f"bf{i}") for i in range(K)) + F.col(f"af{j}") * F.col(f"bf{j}")
    new = grid.groupBy(F.col(key).alias("key")).agg(F.sum(rest * F.col(f"bf{j}")).alias("up"), F.sum(F.col(f"bf{j}") * F.col(f"bf{j}")).alias("own"))
    return f.join(new, "key").select("key", *((F.greatest(F.col("up") - alpha, F.lit(0.0)) / (F.col("own") + beta)).alias(f"f{j}") if i == j else F.col(f"f{i}") for i in range(K)))


def _hals(spark: SparkSession, sf: str, alpha: float, beta: float) -> DataFrame:
    x, a, b = _starts(spark, sf)
    for j in range(K):
        a = solvers.held(_residual_update(x, a, b, j, "row"))
        b = solvers.held(_residual_update(x, b, a, j, "col", alpha, beta))
    return both(a, b, K)


def _hals_sql(alpha: float, beta: float) -> str:
    ctes, a, b = list(_STARTS), "a0", "b0"
    for j in range(K):
        ctes += [O.times(f"h{j}", b, K), O.gram(f"g{j}", b, K), O.sweep(f"ra{j}", a, f"h{j}", f"g{j}", K, only=j)]
        a = f"ra{j}"
        ctes += [O.times(f"p{j}", a, K, "col"), O.gram(f"w{j}", a, K), O.sweep(f"rb{j}", b, f"p{j}", f"w{j}", K, alpha, beta, only=j)]
        b = f"rb{j}"
    return O.query(*ctes, select=both_sql(a, b))


query(_hals_sql(0.0, 0.0), "hals_residual_sweep")(lambda spark, sf: _hals(spark, sf, 0.0, 0.0))
query(_hals_sql(0.5, 2.0), "hals_penalised")(lambda spark, sf: _hals(spark, sf, 0.5, 2.0))


# projections
_SPLIT = O.matrix("x_split")
_LEFT = (O.gaussian("om", "col", S, SEED), O.times("y0", "om", S), O.times("z1", "y0", S, "col"), O.times("y1", "z1", S), O.orthonormal("l", "y1", S))
_RIGHT = (O.gaussian("om2", "row", S, SEED + 1), O.times("u0", "om2", S, "col"), O.times("v1", "u0", S), O.times("u1", "v1", S, "col"), O.orthonormal("r", "u1", S))
_PROJECTED = (_SPLIT, *_LEFT, *_RIGHT, O.times("xl", "l", S, "col"), O.times("xr", "r", S))


def projected(spark: SparkSession, sf: str) -> dict[str, DataFrame]:
    """x, l (rows), r (columns), xl = X' L (columns), xr = X R' (rows), written."""
    x = solvers.held(M.x_split(spark, sf))
    l = solvers.held(W.orthonormal(solvers.held(W.sample_range(x, W.keys_of(x, "col"), S, 1, SEED)), S))
    t = x.select(F.col("col_key").alias("row_key"), F.col("row_key").alias("col_key"), "value")
    r = solvers.held(W.orthonormal(solvers.held(W.sample_range(t, W.keys_of(t, "col"), S, 1, SEED + 1)), S))
    return {"x": x, "l": l, "r": r, "xl": solvers.held(W.times_t(x, l, S)), "xr": solvers.held(W.times(x, r, S))}


@query(O.query(_SPLIT, O.gaussian("om", "col", S, SEED), O.times("y", "om", S), select=f"SELECT key, {O.f_list(S, 'round(f{j} / sqrt(3.0::DOUBLE), 5) AS f{j}')} FROM y"))
def gaussian_sketch(spark: SparkSession, sf: str) -> DataFrame:
    x = M.x_split(spark, sf)
    return rounded(W.gaussian_sketch(x, W.keys_of(x, "col"), S, SEED), S)


for _w, _y in ((0, "y0"), (1, "y1")):
    query(O.query(_SPLIT, *_LEFT[:-1], select=O.rounded(_y, S, 3)), f"sample_range_w{_w}")(lambda spark, sf, w=_w: rounded(W.sample_range(x := M.x_split(spark, sf), W.keys_of(x, "col"), S, w, SEED), S, 3))

query(O.query(_SPLIT, *_LEFT, select=O.rounded("l", S)), "orthonormal_basis")(lambda spark, sf: rounded(W.orthonormal(solvers.held(W.sample_range(x := solvers.held(M.x_split(spark, sf)), W.keys_of(x, "col"), S, 1, SEED)), S), S))
query(O.query(*_PROJECTED, select=O.rounded("xl", S)), "project_left")(lambda spark, sf: rounded(projected(spark, sf)["xl"], S))
query(O.query(*_PROJECTED, select=O.rounded("xr", S)), "project_right")(lambda spark, sf: rounded(projected(spark, sf)["xr"], S))


@query(O.query(*_PROJECTED, O.gram("gl", "l", S), select="SELECT round(sqrt((g0_0 - 1) * (g0_0 - 1) + (g1_1 - 1) * (g1_1 - 1) + (g2_2 - 1) * (g2_2 - 1) + 2 * (g0_1 * g0_1 + g0_2 * g0_2 + g1_2 * g1_2)), 6) AS distance, round((SELECT sum(f0 * f0 + f1 * f1 + f2 * f2) FROM xl) / (SELECT sum(value * value) FROM x), 6) AS energy FROM gl"))
def projector_quality(spark: SparkSession, sf: str) -> DataFrame:
    """Distance of L' L from the identity, and the share of the squared norm that L' X keeps."""
    p = projected(spark, sf)
    away = W.total((F.col(f"g{i}_{j}") - (1.0 if i == j else 0.0)) * (F.col(f"g{i}_{j}") - (1.0 if i == j else 0.0)) for i in range(S) for j in range(S))
    kept = p["xl"].agg(F.sum(W.total(F.col(c) * F.col(c) for c in W.cols(S))).alias("kept"))
    norm = p["x"].agg(F.sum(F.col("value") * F.col("value")).alias("xx"))
    return W.gram(p["l"], S).crossJoin(kept).crossJoin(norm).select(F.round(F.sqrt(away), 6).alias("distance"), F.round(F.col("kept") / F.col("xx"), 6).alias("energy"))


# one iteration of the compressed methods
_C_STARTS = (*_PROJECTED, O.start("a0", "row", K, SEED), O.start("b0", "col", K, SEED + 1))


def _compressed(spark: SparkSession, sf: str, update, update_b=None) -> DataFrame:
    p = projected(spark, sf)
    a, b = W.uniform_factor(W.keys_of(p["x"], "row"), K, SEED), W.uniform_factor(W.keys_of(p["x"], "col"), K, SEED + 1)
    c = W.cross_gram(p["r"], S, b, K)
    a = solvers.held(update(a, W.small_product(p["xr"], S, c, K), W.small_gram(c, S, K), K))
    c = W.cross_gram(p["l"], S, a, K)
    b = (update_b or update)(b, W.small_product(p["xl"], S, c, K), W.small_gram(c, S, K), K)
    return both(a, b, K)


def _compressed_ctes(update, update_b=None) -> tuple[str, ...]:
    return (
        *_C_STARTS, O.cross("cb", "r", S, "b0", K), O.small_product("h", "xr", S, "cb", K), O.small_gram("g", "cb", S, K), update("a1", "a0", "h", "g", K),
        O.cross("ca", "l", S, "a1", K), O.small_product("p", "xl", S, "ca", K), O.small_gram("w", "ca", S, K), (update_b or update)("b1", "b0", "p", "w", K),
    )


for _name, _df, _sq, _dfb, _sqb in (
    ("cgram_hals_sweep", W.sweep, O.sweep, None, None),
    ("cgram_hals_penalised", W.sweep, O.sweep, *_penalised(0.05, 0.2)),
    ("cmu_step", W.signed_multiplicative, _pointwise(O.signed_form), None, None),
    ("cals_step", W.clipped_least_squares, _pointwise(O.als_form), None, None),
    ("cpgd_step", W.projected_gradient, _pointwise(O.pgd_form), None, None),
):
    query(O.query(*_compressed_ctes(_sq, _sqb), select=both_sql("a1", "b1")), _name)(lambda spark, sf, u=_df, v=_dfb: _compressed(spark, sf, u, v))


def _projected_residual(x: DataFrame, f: DataFrame, c: DataFrame, j: int, alpha: float = 0.0, beta: float = 0.0) -> DataFrame:
    """Component j from the explicit projected residual of each row (S wide)."""
    y = x.select("key", *(F.col(f"f{i}").alias(f"x{i}") for i in range(S)))
    t = f.join(y, "key").crossJoin(F.broadcast(c))
    rest = [F.col(f"x{i}") - W.total(F.col(f"f{m}") * F.col(f"c{i}_{m}") for m in range(K)) + F.col(f"f{j}") * F.col(f"c{i}_{j}") for i in range(S)]
    up, own = W.total(rest[i] * F.col(f"c{i}_{j}") for i in range(S)), W.total(F.col(f"c{i}_{j}") * F.col(f"c{i}_{j}") for i in range(S))
    return t.select("key", *((F.greatest(up - alpha, F.lit(0.0)) / (own + beta)).alias(f"f{j}") if i == j else F.col(f"f{i}") for i in range(K)))


def _chals(spark: SparkSession, sf: str, alpha: float = 0.0, beta: float = 0.0) -> DataFrame:
    p = projected(spark, sf)
    a, b = W.uniform_factor(W.keys_of(p["x"], "row"), K, SEED), W.uniform_factor(W.keys_of(p["x"], "col"), K, SEED + 1)
    for j in range(K):
        a = solvers.held(_projected_residual(p["xr"], a, W.cross_gram(p["r"], S, b, K), j))
        b = solvers.held(_projected_residual(p["xl"], b, W.cross_gram(p["l"], S, a, K), j, alpha, beta))
    return both(a, b, K)


def _chals_sql(alpha: float = 0.0, beta: float = 0.0) -> str:
    ctes, a, b = list(_C_STARTS), "a0", "b0"
    for j in range(K):
        ctes += [O.cross(f"cb{j}", "r", S, b, K), O.small_product(f"h{j}", "xr", S, f"cb{j}", K), O.small_gram(f"g{j}", f"cb{j}", S, K), O.sweep(f"ra{j}", a, f"h{j}", f"g{j}", K, only=j)]
        a = f"ra{j}"
        ctes += [O.cross(f"ca{j}", "l", S, a, K), O.small_product(f"p{j}", "xl", S, f"ca{j}", K), O.small_gram(f"w{j}", f"ca{j}", S, K), O.sweep(f"rb{j}", b, f"p{j}", f"w{j}", K, alpha, beta, only=j)]
        b = f"rb{j}"
    return O.query(*ctes, select=both_sql(a, b))


query(_chals_sql(), "chals_sweep")(_chals)
query(_chals_sql(0.05, 0.2), "chals_penalised")(lambda spark, sf: _chals(spark, sf, 0.05, 0.2))


# measures
_CELL_ERROR = "SELECT 0.5 * sum((coalesce(x.value, 0) - (a.f0 * b.f0 + a.f1 * b.f1)) * (coalesce(x.value, 0) - (a.f0 * b.f0 + a.f1 * b.f1))) AS e FROM a0 a CROSS JOIN b0 b LEFT JOIN x ON x.row_key = a.key AND x.col_key = b.key"


@query(O.query(*_STARTS, select=f"SELECT round(e, 4) AS objective FROM ({_CELL_ERROR}) t"))
def objective_cells(spark: SparkSession, sf: str) -> DataFrame:
    return measures.objective_cells(*_starts(spark, sf), K).select(F.round("objective", 4).alias("objective"))


@query(O.query(*_STARTS, select=f"SELECT round(e, 4) AS objective FROM ({_CELL_ERROR}) t"))
def objective_trace(spark: SparkSession, sf: str) -> DataFrame:
    return measures.objective_trace(*_starts(spark, sf), K).select(F.round("objective", 4).alias("objective"))


@query(O.query(*_STARTS, select=f"SELECT round(sqrt(2 * e / (SELECT sum(value * value) FROM x)), 6) AS relative_error FROM ({_CELL_ERROR}) t"))
def relative_error(spark: SparkSession, sf: str) -> DataFrame:
    return measures.relative_error(measures.objective_trace(*_starts(spark, sf), K)).select(F.round("relative_error", 6).alias("relative_error"))


def _gap_sql(x: str, f: str, c: str) -> str:
    parts = " + ".join(f"({x}.f{i} - (" + " + ".join(f"{f}.f{j} * {c}.c{i}_{j}" for j in range(K)) + f")) * ({x}.f{i} - (" + " + ".join(f"{f}.f{j} * {c}.c{i}_{j}" for j in range(K)) + "))" for i in range(S))
    return f"SELECT 0.5 * sum({parts}) FROM {x} JOIN {f} ON {x}.key = {f}.key, {c}"


@query(O.query(*_C_STARTS, O.cross("cb", "r", S, "b0", K), O.cross("ca", "l", S, "a0", K), select=f"SELECT round(({_gap_sql('xr', 'a0', 'cb')}), 4) AS right_objective, round(({_gap_sql('xl', 'b0', 'ca')}), 4) AS left_objective"))
def projected_objectives(spark: SparkSession, sf: str) -> DataFrame:
    p = projected(spark, sf)
    a, b = W.uniform_factor(W.keys_of(p["x"], "row"), K, SEED), W.uniform_factor(W.keys_of(p["x"], "col"), K, SEED + 1)

    def gap(x: DataFrame, f: DataFrame, c: DataFrame, name: str) -> DataFrame:
        y = x.select("key", *(F.col(f"f{i}").alias(f"x{i}") for i in range(S)))
        t = f.join(y, "key").crossJoin(F.broadcast(c))
        rest = [F.col(f"x{i}") - W.total(F.col(f"f{m}") * F.col(f"c{i}_{m}") for m in range(K)) for i in range(S)]
        return t.agg(F.round(0.5 * F.sum(W.total(r * r for r in rest)), 4).alias(name))

    return gap(p["xr"], a, W.cross_gram(p["r"], S, b, K), "right_objective").crossJoin(gap(p["xl"], b, W.cross_gram(p["l"], S, a, K), "left_objective"))


_LONG = "long AS (SELECT key, 0 AS component, f0 AS v FROM b0 UNION ALL SELECT key, 1, f1 FROM b0)"


@query(O.query(*_STARTS, _LONG, select="SELECT round((2 * sum(i * v) - (count(*) + 1) * sum(v)) / (count(*) * sum(v)), 6) AS gini FROM (SELECT v, row_number() OVER (ORDER BY v) AS i FROM long) t"))
def gini_uniform_factor(spark: SparkSession, sf: str) -> DataFrame:
    return measures.gini(measures.long_factor(_starts(spark, sf)[2], K), "value").select(F.round("gini", 6).alias("gini"))


@query(O.query(*_STARTS, _LONG, select="SELECT component, round((2 * sum(i * v) - (count(*) + 1) * sum(v)) / (count(*) * sum(v)), 6) AS gini FROM (SELECT component, v, row_number() OVER (PARTITION BY component ORDER BY v) AS i FROM long) t GROUP BY component"))
def gini_per_component(spark: SparkSession, sf: str) -> DataFrame:
    from .functions.udx import gini_agg

    return measures.long_factor(_starts(spark, sf)[2], K).groupBy("component").agg(F.round(gini_agg("value"), 6).alias("gini"))


@query(O.query(*_STARTS, O.times("p", "a0", K, "col"), O.gram("w", "a0", K), O.sweep("b1", "b0", "p", "w", K, 40.0, 0.0), select="SELECT round(avg(CASE WHEN abs(v) <= 1e-9 THEN 1.0 ELSE 0.0 END), 6) AS zero_share, round(sum(v * v), 4) AS smoothness FROM (SELECT f0 AS v FROM b1 UNION ALL SELECT f1 FROM b1) t"))
def zero_share(spark: SparkSession, sf: str) -> DataFrame:
    x, a, b = _starts(spark, sf)
    b = W.sweep(b, W.times_t(x, a, K), W.gram(a, K), K, 40.0)
    return measures.zero_share(b, K, 1e-9).select(F.round("zero_share", 6).alias("zero_share"), F.round("smoothness", 4).alias("smoothness"))


_SKETCH = O.query(_SPLIT, O.gaussian("om", "col", 12, SEED), O.times("y", "om", 12), f"few AS (SELECT * FROM x WHERE row_key IN (SELECT DISTINCT row_key FROM x ORDER BY 1 LIMIT {measures.ANCHORS}))", "norms AS (SELECT row_key, sum(value * value) AS xx FROM x GROUP BY 1)", "dots AS (SELECT p.row_key AS r0, q.row_key AS r1, sum(p.value * q.value) AS d FROM few p JOIN x q ON p.col_key = q.col_key AND p.row_key <> q.row_key GROUP BY 1, 2)", select="SELECT a.key AS r0, b.key AS r1, round(sqrt((" + " + ".join(f"(a.f{j} - b.f{j}) * (a.f{j} - b.f{j})" for j in range(12)) + ") / 12.0::DOUBLE / (n0.xx + n1.xx - 2 * coalesce(d, 0))), 5) AS ratio FROM y a JOIN y b ON a.key <> b.key AND a.key IN (SELECT row_key FROM few) JOIN norms n0 ON n0.row_key = a.key JOIN norms n1 ON n1.row_key = b.key LEFT JOIN dots ON r0 = a.key AND r1 = b.key WHERE n0.xx + n1.xx - 2 * coalesce(d, 0) > 0")


@query(_SKETCH)
def distance_distortion(spark: SparkSession, sf: str) -> DataFrame:
    x = M.x_split(spark, sf)
    sketch = W.gaussian_sketch(x, W.keys_of(x, "col"), 12, SEED)
    return measures.distance_distortion(x, sketch, 12).select("r0", "r1", F.round("ratio", 5).alias("ratio"))


# cost models of two matrices of the given tables: X-SHIP stands for the dense published set, X-PART for the sparse one
_MONTH = "year(l_shipdate) * 12 + month(l_shipdate)"
_SHAPES = " UNION ALL ".join(f"SELECT '{data}' AS data, '{kind}' AS kind, CAST(count(DISTINCT {row}) AS DOUBLE) AS d, CAST(count(DISTINCT {col}) AS DOUBLE) AS n, {costs.RANKS[kind][0]} AS k, {costs.RANKS[kind][1]} AS s FROM lineitem" for data, kind, row, col in (("x_ship", "dense", "l_suppkey", _MONTH), ("x_part", "sparse", "l_partkey", "l_suppkey")))
_SHAPES = f"({_SHAPES}) t"
_FLOPS = "CASE method WHEN 'mu' THEN 8.0 * d * n * k WHEN 'hals' THEN 8.0 * d * n * k WHEN 'gram_hals' THEN 4.0 * d * n * k WHEN 'cmu' THEN 4.0 * d * k * s WHEN 'chals' THEN 4.0 * d * n * k * s ELSE 2.0 * d * k * s END"
_COUNTED = f"CASE method WHEN 'cmu' THEN 2.0 * (d + n) * k * (2 * s + k) WHEN 'cgram_hals' THEN 2.0 * (d + n) * k * (s + k) ELSE {_FLOPS} END"
_METHODS = "(VALUES ('mu'), ('hals'), ('gram_hals'), ('cmu'), ('chals'), ('cgram_hals')) m(method)"


def _model(spark: SparkSession, sf: str) -> DataFrame:
    """Model costs by matrix and method; the shapes are counted in the tables."""
    shapes, items = None, load(spark, sf, "lineitem")
    month = F.year("l_shipdate") * 12 + F.month("l_shipdate")
    for data, kind, row, col in (("x_ship", "dense", F.col("l_suppkey"), month), ("x_part", "sparse", F.col("l_partkey"), F.col("l_suppkey"))):
        one = items.agg(F.count_distinct(row).alias("d"), F.count_distinct(col).alias("n"))
        one = one.select(F.lit(data).alias("data"), F.lit(kind).alias("kind"), *(F.col(c).cast("double").alias(c) for c in "dn"), *(F.lit(float(v)).alias(c) for v, c in zip(costs.RANKS[kind], "ks", strict=True)))
        shapes = one if shapes is None else shapes.unionByName(one)
    d, n, k, s = map(F.col, "dnks")
    of = lambda m: (F.lit(m).alias("method"), costs.flops(m, d, n, k, s).alias("theory"), costs.flops(m, d, n, k, s, model="counted").alias("counted"), costs.memory_floats(m, d, n, k, s).alias("floats"), costs.bytes_reduced(m, n, k, s, 8).alias("bytes"))
    return shapes.select("data", "kind", F.inline(F.array(*(F.struct(*of(m)) for m in costs.METHODS))))


_FLOATS = "CASE WHEN method LIKE 'c%' THEN (2 * s + k) * (d + n) ELSE d * n + d * k + n * k END"
query(f"SELECT data, method, CAST({_FLOPS} AS DOUBLE) AS theory, CAST({_COUNTED} AS DOUBLE) AS counted FROM {_SHAPES}, {_METHODS}", "flop_model")(lambda spark, sf: _model(spark, sf).select("data", "method", "theory", "counted"))
query(f"SELECT data, method, CAST({_FLOATS} AS DOUBLE) AS floats FROM {_SHAPES}, {_METHODS}", "memory_model")(lambda spark, sf: _model(spark, sf).select("data", "method", "floats"))
query(f"SELECT data, method, CAST(CASE WHEN method LIKE 'c%' THEN 16.0 * s * k * 8 ELSE 8.0 * n * k * 8 END AS DOUBLE) AS bytes FROM {_SHAPES}, {_METHODS}", "communication_model")(lambda spark, sf: _model(spark, sf).select("data", "method", "bytes"))
_VALUES = ", ".join(f"('{a}', '{b}', {c}, {d}, {e})" for a, b, c, d, e in costs.PUBLISHED)


@query(f"WITH p AS (SELECT * FROM (VALUES {_VALUES}) v(kind, method, mflops, seconds, floats)), m AS (SELECT data, kind, method, CAST({_COUNTED} AS DOUBLE) AS counted, CAST({_FLOATS} AS DOUBLE) AS floats FROM {_SHAPES}, {_METHODS}) SELECT mc.data, mc.method, round(mc.counted / mr.counted, 6) AS model_flop_ratio, round(mc.floats / mr.floats, 6) AS model_memory_ratio, round(CAST(pc.mflops / pr.mflops AS DOUBLE), 6) AS flop_ratio, round(CAST(pc.seconds / pr.seconds AS DOUBLE), 6) AS time_ratio, round(CAST(pc.floats / pr.floats AS DOUBLE), 6) AS memory_ratio FROM m mc JOIN m mr ON mc.data = mr.data AND mc.method = 'c' || mr.method JOIN p pc ON pc.kind = mc.kind AND pc.method = mc.method JOIN p pr ON pr.kind = mr.kind AND pr.method = mr.method")
def published_ratios(spark: SparkSession, sf: str) -> DataFrame:
    """Compressed over plain form: by the model for the given matrices, and as published for the set of their kind."""
    p = spark.createDataFrame(list(costs.PUBLISHED), "kind string, method string, mflops double, seconds double, floats double")
    r = p.select("kind", F.concat(F.lit("c"), "method").alias("method"), F.col("mflops").alias("m0"), F.col("seconds").alias("s0"), F.col("floats").alias("f0"))
    published = p.join(r, ["kind", "method"]).select("kind", "method", F.round(F.col("mflops") / F.col("m0"), 6).alias("flop_ratio"), F.round(F.col("seconds") / F.col("s0"), 6).alias("time_ratio"), F.round(F.col("floats") / F.col("f0"), 6).alias("memory_ratio"))
    m = _model(spark, sf).select("data", "kind", "method", "counted", "floats")
    plain = m.select("data", F.concat(F.lit("c"), "method").alias("method"), F.col("counted").alias("c0"), F.col("floats").alias("f0"))
    ratios = m.join(plain, ["data", "method"]).select("data", "kind", "method", F.round(F.col("counted") / F.col("c0"), 6).alias("model_flop_ratio"), F.round(F.col("floats") / F.col("f0"), 6).alias("model_memory_ratio"))
    return ratios.join(F.broadcast(published), ["kind", "method"]).select("data", "method", "model_flop_ratio", "model_memory_ratio", "flop_ratio", "time_ratio", "memory_ratio")


# full solves and experiments; NumPy tests hold them, as SQL can't iterate
@query()
def cgram_hals_doc(spark: SparkSession, sf: str) -> DataFrame:
    """Top words of each component: cells to factors, all distributed."""
    docs = M.first_documents(spark, sf)
    _, b, _ = solvers.factorize(M.x_doc(spark, sf), 5, 8, 2, 10, placement="distributed")
    words = vocabulary(docs, M.TERMS).select(F.col("col_key").alias("key"), "word")
    long = b.select("key", F.posexplode("f").alias("component", "weight")).join(words, "key")
    rank = F.row_number().over(Window.partitionBy("component").orderBy(F.desc("weight"), "word"))
    return long.withColumn("rank", rank).where("rank <= 10").select("component", "rank", "word", F.round("weight", 6).alias("weight"))


def _trace(spark: SparkSession, trace: list[tuple[int, float]]) -> DataFrame:
    return spark.createDataFrame([(i, float(v)) for i, v in trace], "iter int, objective double")


query(name="cgram_hals_img")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_img(spark, sf), 20, 25, 4, 5, placement="distributed")[2]))
query(name="cgram_hals_big")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_big(spark, sf), 20, 25, 3, 4, placement="distributed")[2]))
query(name="gram_hals_img")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_img(spark, sf), 20, 25, 4, 5, "gram_hals")[2]))
query(name="mu_img")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_img(spark, sf), 20, 25, 4, 5, "mu")[2]))
query(name="cmu_img")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_img(spark, sf), 20, 25, 4, 5, "cmu", placement="distributed")[2]))
query(name="hals_evt")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_evt(spark, sf), 3, 8, 4, 2, "hals")[2]))
query(name="chals_evt")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_evt(spark, sf), 3, 8, 4, 2, "chals", placement="distributed")[2]))
query(name="anls_solve")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_evt(spark, sf), 4, 8, 4, 3, "anls")[2]))
query(name="canls_solve")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_evt(spark, sf), 4, 8, 4, 3, "canls")[2]))
query(name="cgram_hals_cust_penalised")(lambda spark, sf: _trace(spark, solvers.factorize(M.x_cust(spark, sf), 8, 12, 3, 5, penalty=Penalty(0.1, 0.1))[2]))
query(name="method_comparison_img")(lambda spark, sf: workloads.compare_methods(spark, sf, "x_img", 20, 25, 4, 500, methods=("mu", "cmu", "gram_hals", "cgram_hals")))
query(name="residual_comparison_img")(lambda spark, sf: workloads.compare_methods(spark, sf, "x_img", 20, 25, 4, 60, methods=("hals", "chals")))
query(name="method_comparison_ship")(lambda spark, sf: workloads.compare_methods(spark, sf, "x_ship", 20, 25, 4, 60))
query(name="method_comparison_doc")(lambda spark, sf: workloads.compare_methods(spark, sf, "x_doc", 60, 72, 9, 150, methods=("mu", "cmu", "gram_hals", "cgram_hals")))
query(name="residual_comparison_doc")(lambda spark, sf: workloads.compare_methods(spark, sf, "x_doc", 60, 72, 9, 10, 3, ("hals", "chals")))
query(name="deviation_img")(lambda spark, sf: workloads.deviation_from_best(workloads.compare_methods(spark, sf, "x_img", 20, 25, 4, 60)))
query(name="deviation_doc")(lambda spark, sf: workloads.deviation_from_best(workloads.compare_methods(spark, sf, "x_doc", 60, 72, 9, 40, methods=("mu", "cmu", "gram_hals", "cgram_hals"))))
query(name="start_stability_img")(lambda spark, sf: workloads.compare_methods(spark, sf, "x_img", 20, 25, 4, 40, 5, ("gram_hals", "cgram_hals")).where("metric = 'relative_error'").select("method", "iter", "value", "starts", "spread"))
query(name="named_alternatives_img")(lambda spark, sf: workloads.compare_methods(spark, sf, "x_img", 10, 13, 4, 15, 2, ("als", "pgd", "anls", "cals", "cpgd", "canls")))
query(name="kw_sweep_img")(lambda spark, sf: workloads.kw_sweep(spark, sf, "x_img", (5, 10, 20), (0, 1, 2, 3, 4, 6, 9), 1.25, 40))
query(name="kw_sweep_doc")(lambda spark, sf: workloads.kw_sweep(spark, sf, "x_doc", (10, 20, 40, 60), (0, 1, 3, 5, 7, 9, 11, 13), 1.2, 40, 3))
for _which in ("alpha", "beta"):
    query(name=f"gini_{_which}_img")(lambda spark, sf, v=_which: workloads.penalty_grid(spark, sf, "x_img", v, 20, 25, 3, 40, True))
    query(name=f"gini_{_which}_doc")(lambda spark, sf, v=_which: workloads.penalty_grid(spark, sf, "x_doc", v, 60, 72, 9, 40, False, 3))
query(name="cost_table_img")(lambda spark, sf: workloads.cost_table(spark, sf, "x_img", 20, 25, 4))
query(name="cost_table_doc")(lambda spark, sf: workloads.cost_table(spark, sf, "x_doc", 60, 72, 9, 3))
query(name="cost_table_ship")(lambda spark, sf: workloads.cost_table(spark, sf, "x_ship", 20, 25, 4))
query(name="convergence_img")(lambda spark, sf: workloads.convergence(workloads.run_grid(spark, workloads.data_of(spark, sf, "x_img"), [{"method": m, "k": 20, "s": 25, "w": 4, "seed": i} for m in ("mu", "gram_hals", "cgram_hals") for i in range(5)], 40, 1)))


@query()
def gini_approximate(spark: SparkSession, sf: str) -> DataFrame:
    """From a quantile grid, beside the exact value."""
    v = measures.long_factor(_starts(spark, sf)[2], K)
    return measures.gini_approximate(v, "value").withColumnRenamed("gini", "approximate").crossJoin(measures.gini(v, "value"))


@query()
def distance_distortion_projected(spark: SparkSession, sf: str) -> DataFrame:
    """Quantiles of the ratio of distances after and before the structured projection, of every row to the anchors."""
    packed, keys = projection.packed_index(M.x_split(spark, sf))
    p = projection.compress(packed, keys, 24, 2, SEED)
    sketch = p.rows.select("key", *(F.col("x")[j].alias(f"f{j}") for j in range(len(p.r))))
    ratios = measures.distance_distortion(M.x_split(spark, sf), sketch, len(p.r))
    return ratios.agg(*(F.expr(f"percentile(ratio, {q})").alias(f"q{int(100 * q)}") for q in (0.0, 0.05, 0.5, 0.95, 1.0)))


@query()
def early_stop(spark: SparkSession, sf: str) -> DataFrame:
    """The curves of solves that stop on their own, by stop rule."""
    out = None
    for rule, tolerance in (("gain", 1e-3), ("gradient", 0.05), ("stagnation", 1e-2)):
        one = _trace(spark, solvers.factorize(M.x_img(spark, sf), 10, 13, 4, 200, tolerance=tolerance, stop=rule)[2]).withColumn("rule", F.lit(rule))
        out = one if out is None else out.unionByName(one)
    return out


@query()
def component_normalised(spark: SparkSession, sf: str) -> DataFrame:
    return _trace(spark, solvers.factorize(M.x_img(spark, sf), 10, 13, 4, 10, normalize="component")[2])


@query()
def spectrum_decay(spark: SparkSession, sf: str) -> DataFrame:
    """Decay of the first singular values and the advised power, by matrix."""
    rows = []
    for name in ("x_img", "x_doc", "x_split", "x_cust", "x_part", "x_evt", "x_ship"):
        cells = solvers.held(M.MATRICES[name](spark, sf))  # read twice, for the columns and for the rows
        packed, keys = projection.packed_index(cells)
        packed = solvers.held(packed)
        solvers.discard(cells)
        p = measures.spectrum_decay(projection.singular_values(packed, len(keys), 60))
        solvers.discard(packed)
        rows.append((name, p["exponential"], p["power"], measures.advised_power(p["exponential"])))
    return spark.createDataFrame(rows, "matrix string, exponential double, power double, advised int")


@query()
def truncated_svd_error(spark: SparkSession, sf: str) -> DataFrame:
    """The least relative error of any factorization of rank k, by matrix."""
    rows = []
    for name in ("x_img", "x_cust", "x_evt", "x_ship"):
        packed, keys = projection.packed_index(M.MATRICES[name](spark, sf))
        s2 = projection.singular_values(packed, len(keys), len(keys)) ** 2
        rows += [(name, k, float(np.sqrt(max(s2[k:].sum(), 0) / s2.sum()))) for k in (5, 10, 20)]
    return spark.createDataFrame(rows, "matrix string, k int, relative_error double")


@query()
def fold_in_benchmark(spark: SparkSession, sf: str) -> DataFrame:
    """Coefficients of held-out texts in the document model."""
    docs = M.first_documents(spark, sf)
    vocab = vocabulary(docs, M.TERMS).select("word", "col_key")
    _, b, _ = solvers.factorize(M.x_doc(spark, sf), 5, 8, 2, 10)
    model = sorted((r["key"], r["f"]) for r in b.collect())  # TERMS rows
    from .sources.tables import words

    cells = load(spark, sf, "benchmark").select(F.col("item_id").alias("row_key"), F.explode(words(F.col("text"))).alias("word")).join(F.broadcast(vocab), "word").groupBy("row_key", "col_key").agg(F.count("*").cast("double").alias("value"))
    places = spark.createDataFrame([(int(k), i) for i, (k, _) in enumerate(model)], "col_key bigint, place bigint")
    packed = pack_rows(cells.join(F.broadcast(places), "col_key").select("row_key", F.col("place").alias("col_key"), "value")).select("row_key", F.col("idx").cast("array<int>").alias("idx"), "val")
    return solvers.fold_in(packed, np.array([f for _, f in model])).select(F.col("key").alias("item_id"), F.posexplode("f").alias("component", "weight"))


QUERIES |= relational.QUERIES
ORACLES |= relational.ORACLES


def entry(spark: SparkSession) -> DataFrame:
    return cgram_hals_doc(spark, "/root/testdata/sf0.001")
