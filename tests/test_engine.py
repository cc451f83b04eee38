"""The distributed forms against arrays, sources and sinks, the planner, streams and edge cases."""

import numpy as np
import pyarrow as pa
import pytest
from orthant import workloads
from orthant.functions import arrays, udx
from orthant.operators import dense, measures, projection, solvers
from orthant.operators import wide as W
from orthant.operators.kernels import Penalty
from orthant.plans.matrix_plan import MatrixPlan, choose_placement, choose_route
from orthant.sources import tables
from pyspark.sql import functions as F

COO = "row_key bigint, col_key bigint, value double"


@pytest.fixture(scope="module")
def planted():
    order = np.random.default_rng(0)
    x = order.random((40, 4)) @ order.random((4, 15)) + 0.05 * order.random((40, 15))
    x[7] = 0.0
    x[x < 0.3] = 0
    return x


@pytest.fixture(scope="module")
def coo(spark, planted):
    r, c = np.nonzero(planted)
    return spark.createDataFrame([(int(i), int(j) * 10, float(planted[i, j])) for i, j in zip(r, c, strict=True)], COO).repartition(5)


def dense_of(frame, n):
    return {r["key"]: np.array(r["f"]) for r in frame.collect()}


def test_routes_agree(coo, planted):
    packed, keys = projection.packed_index(coo)
    x = planted[planted.any(1)]
    for w in (0, 2):
        a, b = (projection.compress(packed, keys, 6, w, 3, route) for route in ("gram", "iterate"))
        for p in (a, b):
            rows = p.rows.orderBy("key").collect()
            q, xr = np.array([r["q"] for r in rows]), np.array([r["x"] for r in rows])
            assert np.allclose(q.T @ q, np.eye(q.shape[1]), atol=1e-6) and np.allclose(p.r @ p.r.T, np.eye(len(p.r)), atol=1e-8)
            assert np.allclose(q.T @ x, p.left, atol=1e-6) and np.allclose(x @ p.r.T, xr, atol=1e-8)
            assert np.isclose(p.norm2, (x**2).sum()) and p.d == len(x)
        span = a.r @ b.r.T
        assert np.allclose(np.linalg.svd(span, compute_uv=False), 1, atol=1e-5)


@pytest.mark.parametrize("method", ["cgram_hals", "cmu", "cals", "canls", "chals", "gram_hals", "mu", "hals", "anls", "pgd"])
def test_distributed_equals_arrays(coo, planted, method):
    penalty = Penalty(0.01, 0.02) if "hals" in method else Penalty()
    rows, cols, trace = solvers.factorize(coo, 3, 6, 2, 3, method, penalty, placement="distributed" if method.startswith("c") else None)
    got = dense_of(rows, 3)
    assert len(got) == int(planted.any(1).sum()) and all((v >= 0).all() for v in got.values())
    if method.startswith("c"):
        there = solvers.factorize(coo, 3, 6, 2, 3, method, penalty, placement="driver")
        assert np.allclose([v for _, v in trace], [v for _, v in there[2]], rtol=1e-6)
    else:
        assert trace[-1][1] <= trace[0][1] * (1 + 1e-9)
        a = np.array([got[k] for k in sorted(got)])
        b = np.array([r["f"] for r in cols.orderBy("key").collect()])
        assert np.isclose(dense.objective(planted[planted.any(1)], a, b), trace[-1][1], rtol=1e-6)


def test_partitions_do_not_matter(coo):
    a, b = (solvers.factorize(x, 3, 6, 2, 3, placement="distributed")[2] for x in (coo, coo.coalesce(1)))
    assert np.allclose([v for _, v in a], [v for _, v in b], rtol=1e-9)


def test_tall_qr(spark):
    y = np.random.default_rng(1).standard_normal((200, 4))
    frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(y)], "key bigint, y array<double>").repartition(7)
    q, r = projection.tall_qr(frame, "y", 4)
    got = np.array([v["y"] for v in q.orderBy("key").collect()])
    assert np.allclose(got.T @ got, np.eye(4), atol=1e-10) and np.allclose(got @ r, y) and (np.diag(r) > 0).all()


def test_objectives_and_gini_agree(spark, coo, planted):
    a, b = W.uniform_factor(W.keys_of(coo, "row"), 2, 1), W.uniform_factor(W.keys_of(coo, "col"), 2, 2)
    cells, trace = measures.objective_cells(coo, a, b, 2).first()[0], measures.objective_trace(coo, a, b, 2).first()[0]
    assert np.isclose(cells, trace)
    values = [float(v) for v in np.random.default_rng(3).random(500)] + [0.5] * 40 + [0.0] * 30
    frame = spark.createDataFrame([(v,) for v in values], "v double").repartition(6)
    assert np.isclose(measures.gini(frame, "v", 5).first()[0], dense.gini(np.array(values)))
    assert abs(measures.gini_approximate(frame, "v").first()[0] - dense.gini(np.array(values))) < 0.01
    assert measures.gini(frame.where("v < 0"), "v").first()[0] is None


def test_singular_values_and_decay(coo, planted):
    packed, keys = projection.packed_index(coo)
    assert np.allclose(projection.singular_values(packed, len(keys), 5), np.linalg.svd(planted, compute_uv=False)[:5])
    p = measures.spectrum_decay(np.exp(-0.02 * np.arange(50)))
    assert abs(p["exponential"] - 0.02) < 1e-6 and [measures.advised_power(x) for x in (0.0012, 0.0053, 1.0, 1e-9)] == [11, 3, 1, 15]


def test_validation(spark):
    bad = [(1, 1, -1.0), (1, 1, float("nan")), (None, 1, 1.0), (1, 1, None), (1, 1, float("inf"))]
    for cell in bad:
        with pytest.raises(Exception, match="not finite or negative"):
            tables.validated(spark.createDataFrame([cell], COO)).collect()
    assert tables.validated(spark.createDataFrame([(1, 1, -0.0), (1, 2, 2.0)], COO)).count() == 1


def test_sources_and_sinks(spark, coo, tmp_path):
    for fmt in ("parquet", "csv", "json", "orc"):
        tables.write_coo(coo, f"{tmp_path}/{fmt}", fmt)
        assert sorted(tables.read_coo(spark, f"{tmp_path}/{fmt}", fmt).collect()) == sorted(coo.collect())
    rows, cols, trace = solvers.factorize(coo, 2, 5, 1, 2)
    tables.save_model(f"{tmp_path}/model", rows, cols, {"k": 2})
    r, c, config = tables.load_model(spark, f"{tmp_path}/model")
    assert config == {"k": 2} and r.count() == rows.count() and c.count() == cols.count()
    maps = spark.createDataFrame([(1, {3: 2.0, 4: 1.0}), (1, {3: 5.0})], "r bigint, m map<bigint,double>")
    assert sorted(map(tuple, tables.coo_from_map(maps, "r", "m").collect())) == [(1, 3, 7.0), (1, 4, 1.0)]


def test_fold_in(spark, coo, planted):
    rows, cols, _ = solvers.factorize(coo, 3, 6, 2, 20)
    b = np.array([r["f"] for r in cols.orderBy("key").collect()])
    packed, _ = projection.packed_index(coo)
    got = dense_of(solvers.fold_in(packed, b, 200), 3)
    x = planted[planted.any(1)]
    f = np.array([got[k] for k in sorted(got)])
    slack = f @ (b.T @ b) - x @ b
    assert (f >= 0).all() and slack.min() > -1e-3 * np.abs(x @ b).max()


def test_planner():
    assert choose_route(1000, 72, 9) == "gram" and choose_route(10**7, 72, 9) == "iterate"
    assert choose_placement(5000, 1000, 60, 72) == "driver" and choose_placement(10**9, 10**6, 20, 25) == "distributed"
    plain, small = (MatrixPlan.build(m, 10**9, 10**5, 20, 25, 4, 50) for m in ("gram_hals", "cgram_hals"))
    assert small.scans() < plain.scans() and "cgram_hals" in small.explain()


def test_array_expressions_and_functions(spark):
    udx.register(spark)
    frame = spark.createDataFrame([([1.0, 2.0, 2.0], [0.0, 1.0, 3.0])], "a array<double>, b array<double>")
    a, b = F.col("a"), F.col("b")
    row = frame.select(arrays.dot(a, b), arrays.norm2(a), arrays.axpy(F.lit(2.0), a, b), arrays.argmax_component(a), F.expr("vec_dot(a, b)"), F.expr("vec_norm(a)"), F.expr("vec_argmax(a)")).first()
    assert tuple(row) == (8.0, 3.0, [2.0, 5.0, 7.0], 1, 8.0, 3.0, 1)
    assert len(spark.sql("SELECT * FROM reconstruct(array(1D, 2D), array(1D, 0D, 0D, 1D))").collect()) == 2
    g = np.array([[2.0, 0.0], [0.0, 4.0]])
    assert frame.select(udx.gram_sweep_udf(g)(F.array(F.lit(2.0), F.lit(4.0)), F.array(F.lit(0.0), F.lit(0.0)))).first()[0] == [1.0, 1.0]


def test_streams(spark, sf, tmp_path):
    from orthant.streaming import cells as S

    events = spark.read.parquet(f"{sf}/events.parquet")
    events.where("event_id % 2 = 0").coalesce(1).write.parquet(f"{tmp_path}/in")
    events.where("event_id % 2 = 1").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    events.limit(50).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")  # repeated events
    out = S.run_to_memory(S.cell_counts(S.event_stream(spark, f"{tmp_path}/in", events.schema, "60 days")), "t_cells", "complete", f"{tmp_path}/c1")
    want = S.cell_counts(events)
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, want.collect()))
    out = S.run_to_memory(S.windowed_counts(S.event_stream(spark, f"{tmp_path}/in", events.schema, "60 days"), "1 day", "12 hours"), "t_slide", "complete", f"{tmp_path}/c2")
    assert out.agg(F.sum("n")).first()[0] == 2 * events.count()


def test_session_windows_and_late_events(spark, tmp_path):
    from orthant.streaming import cells as S

    rows = [(1, 7, "2024-01-05 10:00:00", "view"), (2, 7, "2024-01-05 10:03:00", "view"), (3, 7, "2024-01-09 00:00:00", "click")]
    late = [(4, 7, "2024-01-05 10:01:00", "view")]  # four days behind the watermark once (3) was seen
    frame = lambda x: spark.createDataFrame(x, "event_id bigint, user_id bigint, ts string, event_type string").withColumn("ts", F.to_timestamp("ts")).coalesce(1)
    frame(rows).write.parquet(f"{tmp_path}/in")
    sessions = S.windowed_counts(S.event_stream(spark, f"{tmp_path}/in", frame(rows).schema), gap="10 minutes")
    sink = sessions.writeStream.outputMode("append").format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/c")
    sink.trigger(availableNow=True).start().awaitTermination()
    frame(late).write.mode("append").parquet(f"{tmp_path}/in")
    sink.trigger(availableNow=True).start().awaitTermination()
    assert [(r["event_type"], r["n"]) for r in spark.read.parquet(f"{tmp_path}/out").collect()] == [("view", 2)]


def test_stateful_user_vectors(spark, sf, tmp_path):
    from orthant.streaming import cells as S

    events = spark.read.parquet(f"{sf}/events.parquet")
    events.coalesce(1).write.parquet(f"{tmp_path}/in")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        stream = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/in").select("user_id", "event_type")
        got = S.run_to_memory(S.user_vectors(stream), "t_vectors", "update", f"{tmp_path}/c3").collect()
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    want = events.groupBy("user_id").pivot("event_type", list(S.KINDS)).agg(F.count(F.lit(1))).na.fill(0).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, want))


def test_grid_runs(spark, planted):
    runs = workloads.run_grid(spark, planted, [{"method": m, "k": 3, "s": 6, "w": 2, "seed": s} for m in ("gram_hals", "cgram_hals") for s in range(3)], 10, 5)
    table = workloads.medians(runs).where("metric = 'relative_error' and iter = 10").collect()
    assert len(table) == 2 and all(r["starts"] == 3 and r["value"] < 0.3 for r in table)
    assert workloads.convergence(runs).count() == 6


def test_entry_and_registry(spark):
    import __spark_entry__

    q, o = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(o) <= set(q) and len(q) > 110
    assert __spark_entry__.entry(spark).count() == 50


@pytest.mark.parametrize("rule", solvers.Stop.RULES)
def test_stop_rules(coo, rule):
    trace = solvers.factorize(coo, 3, 6, 2, 150, tolerance=0.02, stop=rule)[2]
    assert 1 < len(trace) < 150
    assert len(solvers.factorize(coo, 3, 6, 2, 4, tolerance=0.0, stop=rule)[2]) == 4
    with pytest.raises(ValueError, match="no such stop rule"):
        solvers.Stop(0.1, "other")


@pytest.mark.parametrize("method", ["cgram_hals", "gram_hals"])
def test_passes_write_the_factor_alone(spark, coo, tmp_path, monkeypatch, method):
    monkeypatch.setattr(solvers, "shared_folder", lambda spark: str(tmp_path))
    rows, _, _ = solvers.factorize(coo, 3, 6, 2, 5, method, placement="distributed")
    assert rows.count() > 0
    columns = sorted(tuple(sorted(spark.read.parquet(str(p)).columns)) for p in tmp_path.glob("state-*"))
    fixed = ("key", "q", "x") if method == "cgram_hals" else ("idx", "key", "val")
    # the packed rows, the fixed rows in buckets, and the factor's rows of the last two passes
    assert columns == sorted([("idx", "row_key", "val"), fixed, ("f", "key", "part"), ("f", "key", "part")])


def test_passes_need_no_exchange(spark, coo):
    packed, _ = projection.packed_index(coo)
    fixed = solvers.bucketed(packed.withColumnRenamed("row_key", "key"), 4, True)
    states = solvers.States(fixed, lambda r: solvers.with_start(r, 2, 1, 1.0))
    rows = states.rows()
    states.advance(rows.selectExpr("key", "f", "CAST(NULL AS binary) AS part"), (0,))
    plan = states.rows()._jdf.queryExecution().executedPlan().toString()
    assert "ShuffledHashJoin" in plan and "Exchange" not in plan
    assert sorted(map(str, states.rows().collect())) == sorted(map(str, rows.collect()))


@pytest.mark.parametrize("share", [0.0, 0.5, 2.0])
def test_cells_equal_arrays(monkeypatch, share):
    monkeypatch.setattr(projection, "DENSE_SHARE", share)
    order = np.random.default_rng(2)
    x = order.random((70, 30)) * (order.random((70, 30)) < np.linspace(0, 1, 70)[:, None])
    lists = [np.flatnonzero(r) for r in x]
    batch = pa.RecordBatch.from_arrays([pa.array([i.tolist() for i in lists], pa.list_(pa.int32())), pa.array([r[i].tolist() for r, i in zip(x, lists, strict=True)], pa.list_(pa.float64()))], ["idx", "val"])
    m, g = order.random((30, 4)), order.random((70, 4))
    for most in (16, 400, 1 << 16):
        parts = list(projection.cell_chunks([batch.slice(0, 33), batch.slice(33)], 30, most))
        assert sum(p.shape[0] for p in parts) == 70 and all(len(p.val) <= most or p.shape[0] == 1 for p in parts)
        assert np.allclose(np.concatenate([p @ m for p in parts]), x @ m)
        turned, gram, at = np.zeros((30, 4)), np.zeros((30, 30)), 0
        for p in parts:
            p.add_turned(g[at : at + p.shape[0]], turned)
            p.add_gram(gram)
            at += p.shape[0]
        assert np.allclose(turned, x.T @ g) and np.allclose(gram, x.T @ x)
        assert np.allclose(np.concatenate([p.full() for p in parts]), x)


def test_best_columns(spark):
    from orthant.relational import best_columns

    order = np.random.default_rng(5)
    a, b = order.integers(0, 5, (50, 3)) / 4, order.integers(0, 5, (12, 3)) / 4  # exact products, many ties
    frames = [spark.createDataFrame([(i, *map(float, v)) for i, v in enumerate(m)], "key bigint, f0 double, f1 double, f2 double") for m in (a, b)]
    got = {}
    for r in best_columns(*frames, 3, 4).orderBy("row_key", "rank").collect():
        got.setdefault(r["row_key"], []).append(r["col_key"])
    score = a @ b.T
    assert got == {i: sorted(range(12), key=lambda c: (-round(score[i, c], 9), c))[:4] for i in range(50)}


def test_the_driver_never_holds_a_workload_matrix(spark, coo, planted, monkeypatch):
    def no_cells(frame, *_):
        raise AssertionError("cells came to the driver")

    grid = [{"method": m, "k": 3, "s": 6, "w": 2, "seed": s} for m in ("gram_hals", "hals", "cgram_hals") for s in range(2)]
    measure = lambda runs: {(r["run_id"], r["iter"], r["metric"]): r["value"] for r in runs.where("metric <> 'seconds'").collect()}
    want = measure(workloads.run_grid(spark, planted[planted.any(1)], grid, 6, 3))
    monkeypatch.setattr(workloads, "BLOCK_CELLS", 45)  # blocks of three rows
    monkeypatch.setitem(workloads.MATRICES, "x_planted", lambda spark, sf: coo)
    for name in ("toPandas", "toLocalIterator"):
        monkeypatch.setattr(type(coo), name, no_cells)
    matrix = workloads.data_of(spark, "", "x_planted")
    assert matrix.shape == (39, 15) and matrix.blocks.count() >= 13
    got = measure(workloads.run_grid(spark, matrix, grid, 6, 3))
    assert got.keys() == want.keys() and all(abs(got[k] - v) <= 1e-9 * max(1, abs(v)) for k, v in want.items())
    for i, g in enumerate(grid):
        x = planted[planted.any(1)]
        _, _, trace = dense.solve(x, g["method"], 3, 6, 2, 6, g["seed"])
        assert abs(got[(str(i), 6, "objective")] - trace[-1][1]) <= 1e-9 * trace[-1][1]
    unit = workloads.run_grid(spark, workloads.data_of(spark, "", "x_planted", True), grid[:1], 1, 1)
    want = dense.solve(x / x.max(), "gram_hals", 3, 6, 2, 1, 0)[2][-1][1]
    assert abs(measure(unit)[("0", 1, "objective")] - want) <= 1e-9 * want


def test_singular_values_of_many_columns(spark, monkeypatch):
    order = np.random.default_rng(4)
    x = order.random((400, 120)) * (order.random((400, 120)) < 0.2)  # a flat spectrum
    cells = lambda x: spark.createDataFrame([(int(i), int(j), float(x[i, j])) for i, j in zip(*np.nonzero(x), strict=True)], COO).repartition(3)
    packed, keys = projection.packed_index(cells(x))
    wide, columns = projection.packed_index(cells(np.eye(3000)))
    shapes, count = [], projection.partial
    monkeypatch.setattr(projection, "partial", lambda f, add, shape, n: shapes.append(shape) or count(f, add, shape, n))
    assert np.allclose(projection.singular_values(wide, len(columns), 4), 1)
    monkeypatch.setattr(projection, "DRIVER_BYTES", 1000)
    monkeypatch.setattr(projection, "COLLECT_BYTES", 1000)
    got = projection.singular_values(packed, len(keys), 10)
    assert np.allclose(got, np.linalg.svd(x, compute_uv=False)[:10], rtol=1e-4)
    assert max(8 * a * b for a, b in shapes) <= 64 << 20


def test_stream_results_stay_in_files(spark, sf):
    from orthant.relational import QUERIES

    events = spark.read.parquet(f"{sf}/events.parquet")
    kind = F.array_position(F.array(*map(F.lit, ("click", "error", "purchase", "signup", "view"))), F.col("event_type")) - 1
    cells, windows = (QUERIES[n](spark, sf) for n in ("stream_cells", "stream_windows"))
    assert cells.inputFiles() and windows.inputFiles()
    want = events.groupBy("user_id", kind * 24 + F.hour("ts")).agg(F.count("*").cast("double"))
    assert sorted(map(tuple, cells.collect())) == sorted(map(tuple, want.collect()))
    want = events.groupBy("user_id", "event_type", F.date_trunc("hour", F.col("ts").cast("timestamp")).cast("timestamp_ntz")).agg(F.count("*"))
    assert sorted(map(tuple, windows.collect())) == sorted(map(tuple, want.collect()))


@pytest.mark.parametrize("name", ["communication_model", "flop_model", "memory_model", "op_window_ends", "published_ratios", "run_median", "run_rollup", "trace_monotone"])
def test_queries_read_a_given_table_and_equal_sql(spark, sf, name):
    import duckdb
    from orthant import queries

    got = queries.QUERIES[name](spark, sf)
    table = "lineitem" if "model" in name or name == "published_ratios" else "events"
    assert any(f.endswith(f"/{table}.parquet") for f in got.inputFiles())
    db = duckdb.connect()
    db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf}/{table}.parquet'")
    want = db.execute(queries.ORACLES[name])
    names = [c[0] for c in want.description]
    rows = lambda x: sorted((tuple("" if v is None else round(v, 5) if isinstance(v, float) else v for v in r) for r in x), key=str)
    assert got.columns == names and rows(map(tuple, got.collect())) == rows(want.fetchall())


@pytest.mark.parametrize(("method", "iterations"), [("cgram_hals", 2), ("chals", 1)])
def test_columns_in_tables(spark, coo, monkeypatch, method, iterations):
    from orthant.operators import grid
    from orthant.plans import matrix_plan

    args = (coo, 3, 6, 2, iterations, method, Penalty(0.01, 0.02))
    want_a, want_b, want = solvers.factorize(*args, placement="distributed")
    monkeypatch.setattr(matrix_plan, "COLUMN_BYTES", 300)
    monkeypatch.setattr(grid, "BLOCK_BYTES", 16 * 6 * 4)  # blocks of about four keys
    monkeypatch.setattr(grid, "SUM_BYTES", 700)
    monkeypatch.setattr(grid, "MOST_CELLS", 5)
    monkeypatch.setattr(grid, "STEP_CELLS", 3)
    monkeypatch.setattr(solvers, "packed_index", lambda *_: pytest.fail("column keys came to the driver"))
    sums, read = [], grid.sum_arrays
    monkeypatch.setattr(grid, "sum_arrays", lambda parts, shape: sums.append(shape) or read(parts, shape))
    a, b, trace = solvers.factorize(*args)
    assert [i for i, _ in trace] == [i for i, _ in want] and np.allclose([v for _, v in trace], [v for _, v in want], rtol=1e-7)
    for got, right, n in ((a, want_a, 39), (b, want_b, 15)):
        got, right = dense_of(got, 3), dense_of(right, 3)
        assert got.keys() == right.keys() and len(got) == n
        assert all(np.allclose(got[key], f, rtol=1e-5, atol=1e-7) for key, f in right.items())
    assert sums == [(6, 6)]


def test_columns_in_tables_of_low_rank_and_stop_rules(spark, monkeypatch):
    from orthant.operators import grid
    from orthant.plans import matrix_plan

    order = np.random.default_rng(9)
    x = order.random((30, 2)) @ order.random((2, 25))
    cells = spark.createDataFrame([(i, j - 12, float(x[i, j])) for i in range(30) for j in range(25)], COO)
    solve = lambda **more: solvers.factorize(cells, 2, 6, 1, 4, tolerance=0.5, stop="gradient", **more)
    want = solve(placement="distributed")[2]
    monkeypatch.setattr(matrix_plan, "COLUMN_BYTES", 300)
    monkeypatch.setattr(grid, "BLOCK_BYTES", 16 * 6 * 4)
    _, b, trace = solve()
    assert len(trace) == len(want) and np.allclose([v for _, v in trace], [v for _, v in want], rtol=1e-6, atol=1e-9) and b.count() == 25


@pytest.mark.parametrize("name", ["deviation_img", "gini_alpha_img", "gini_beta_img", "kw_sweep_img", "method_comparison_img", "method_comparison_ship"])
def test_workload_queries_leave_the_matrix_with_the_tasks(spark, sf, coo, monkeypatch, name):
    from orthant import queries

    for reader in ("toPandas", "toLocalIterator"):
        monkeypatch.setattr(type(coo), reader, lambda *_, **__: pytest.fail("the matrix came to the driver"))
    out = queries.QUERIES[name](spark, sf)  # runs are made when it is read
    assert "method" in out.columns and any("/state-" in f for f in out.inputFiles())


def test_state_tables_leave_no_shuffle_files(spark):
    import time

    files = lambda: {f.getName() for f in spark.sparkContext._jvm.scala.jdk.javaapi.CollectionConverters.asJava(spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()) if f.getName().startswith("shuffle")}
    cells = spark.range(2000).selectExpr("id as key", "id % 7 as v")
    for write in (solvers.held, lambda f: solvers.bucketed(f, 3, True)):
        before, frame = files(), cells.groupBy("key").agg({"v": "sum"}).withColumnRenamed("sum(v)", "v")
        out = write(frame)
        for _ in range(20):
            left = files() - before
            if not left:
                break
            time.sleep(0.2)
        assert not left and out.count() == 2000


def test_a_grid_deletes_tables_that_it_no_longer_needs(spark, tmp_path, monkeypatch):
    """Of a compression's tables the two results alone stay."""
    from orthant.operators import grid

    monkeypatch.setattr(solvers, "shared_folder", lambda spark: str(tmp_path))
    x = spark.range(400).selectExpr("id % 40 as row_key", "id % 23 as col_key", "1.0D + id % 5 as value").groupBy("row_key", "col_key").agg({"value": "sum"}).withColumnRenamed("sum(value)", "value")
    cells = solvers.held(x)
    p = grid.compress(cells, 5, 1, 3, 7)
    assert {f.name for f in tmp_path.iterdir() if f.is_dir()} == {t._state_path.rsplit("/", 1)[1] for t in (p.rows, p.cols)}


def test_large_sums_are_made_by_all_tasks_at_once(spark, monkeypatch):
    """The driver reads summed slices behind an exchange, not partitions that are made one after the other."""
    from pyspark.sql.classic.dataframe import DataFrame

    monkeypatch.setattr(projection, "COLLECT_BYTES", 1000)
    monkeypatch.setattr(projection, "SLICE_NUMBERS", 64)
    x = np.random.default_rng(5).random((50, 30))
    packed = spark.createDataFrame([(i, list(range(30)), r.tolist()) for i, r in enumerate(x)], "row_key bigint, idx array<int>, val array<double>").repartition(9)
    seen, read = [], DataFrame.toLocalIterator
    monkeypatch.setattr(DataFrame, "toLocalIterator", lambda self, *a, **k: (seen.append(self), read(self, *a, **k))[1])
    assert np.allclose(projection.partial(packed, lambda c, out: c.add_gram(out), (30, 30), 30), x.T @ x)
    plan = seen[0]._jdf.queryExecution().executedPlan().toString()
    assert len(seen) == 1 and plan.index("MapInArrow") < plan.index("Exchange") < plan.rindex("MapInArrow") and "Coalesce" in plan
    assert max(len(r["part"]) for r in read(seen[0])) <= 8 * 64
