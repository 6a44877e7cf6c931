"""Plans, rewrites, back ends, mapper, physical plans, cache, sources, models, balance."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gamat.operators import balance, cache, comm, metrics, models, ops, reorder
from gamat.operators.baselines import mllib_block_mm, numpy_matrix
from gamat.plans import backends, engine, ir, mapper
from gamat.plans.rewrite import rewrite
from gamat.sources import coordinate, fixtures as fx, io
from gamat.types import CATALOGUE, MatrixError, Strategy, VertexState
from test_matrix import array, matrix, state


@pytest.fixture
def small(spark):
    rng = np.random.default_rng(8)
    a, b = rng.integers(-3, 4, (9, 9)), rng.integers(-3, 4, (9, 9))
    return a, b, rng.integers(-3, 4, 9), ir.Load("a", matrix(spark, a)), ir.Load("b", matrix(spark, b))


def test_rewrites(small, spark):
    a, b, x, la, lb = small
    s = ir.State("x", state(spark, x))
    assert rewrite(ir.Transpose(ir.Transpose(la))) == la
    assert rewrite(ir.Transpose(ir.Contract((la, lb)))) == ir.Contract((ir.Transpose(lb), ir.Transpose(la)))
    loose = ir.Load("a", la.graph, summed=False)
    assert rewrite(ir.mv(ir.Sum(loose), s)) == ir.mv(loose, s)
    assert rewrite(ir.mv(ir.Contract((la, lb)), s)) == ir.mv(la, ir.mv(lb, s))
    assert rewrite(ir.MergeEdges((la, ir.Scale(lb, 0)))) == ir.MergeEdges((la,))
    assert rewrite(ir.Scale(ir.Scale(la, 2), 3)) == ir.Scale(la, 6)
    assert rewrite(ir.Contract((ir.Contract((la, lb)), la))) == ir.Contract((la, lb, la))
    assert rewrite(ir.mv(ir.Sum(loose), s)).text() == "Combine(fold=sum)\n  Gather\n    Load(name=a, summed=False)\n    State(name=x)"


@pytest.mark.parametrize("backend", ["S", "B", "V", "hybrid"])
def test_back_ends_agree(small, spark, backend):
    a, b, x, la, lb = small
    s = Strategy(backend=backend, bucket=4)
    assert (array(backends.emit(ir.mv(la, ir.State("x", state(spark, x))), s)) == a @ x).all()
    assert (numpy_matrix(backends.emit(ir.Contract((la, lb)), s)) == a @ b).all()
    assert (numpy_matrix(backends.emit(ir.MergeEdges((la, lb)), s)) == a + b).all()
    out = backends.emit(ir.Iterate(la, ir.State("x", state(spark, x)), 2), s)
    assert (array(out) == a @ a @ x).all()


def test_engine_runs_and_explains(small, spark):
    a, b, x, la, lb = small
    node = ir.mv(ir.Contract((la, lb)), ir.State("x", state(spark, x)))
    assert (array(engine.run(node)) == a @ b @ x).all()
    text = engine.explain(ir.mv(la, ir.State("x", state(spark, x))))
    assert "-- strategy small" in text and "HashAggregate" in text


def test_rules(spark):
    dense = {"n_rows": 10, "n_cols": 10, "nnz": 100, "max_row_deg": 10, "max_col_deg": 10, "kl": 9, "ku": 9, "above": 45, "below": 45, "asymmetric": 5}
    assert mapper.rules("add", dense).unit == "edge"
    assert mapper.rules("mv", dense).join == "broadcast"
    big = dense | {"n_rows": 10**7, "n_cols": 10**7, "nnz": 10**8, "max_col_deg": 10**6}
    assert mapper.rules("mv", big) == CATALOGUE["hub"] and mapper.rules("mv", big | {"max_col_deg": 20}) == CATALOGUE["vertex_pull"]
    assert mapper.rules("mm", dense | {"nnz": 2 * 10**6, "n_rows": 1500, "n_cols": 1500}, "arrow").backend == "B"
    assert mapper.rules("mv", big, "hybrid").backend == "hybrid"


def test_tree_reproduces_its_labels_and_flips_with_density(spark, sf):
    profiles = {d: {"n_rows": 100, "n_cols": 100, "nnz": d * 100, "max_row_deg": d, "max_col_deg": d, "kl": 99, "ku": 99, "above": 1, "below": 1, "asymmetric": 1} for d in (1, 2, 5, 60, 80, 95)}
    rows = []
    from gamat.operators import features

    for d, p in profiles.items():
        for s, t in (("dense_block", 1.0), ("vertex_pull", 0.02 * d)):
            rows.append(("mm", f"m{d}", "arrow", features.vector(p, "mm", "arrow"), s, t))
    runs = spark.createDataFrame(rows, mapper.RUN_SCHEMA)
    tree = mapper.train(runs)
    assert {d: mapper.choose("mm", p, "arrow", tree).name for d, p in profiles.items()} == {d: "dense_block" if d > 50 else "vertex_pull" for d in profiles}
    assert all(r["regret"] == 1.0 and r["chosen"] == r["best"] for r in mapper.evaluate(runs, tree).collect())
    assert tree.branch(features.vector(profiles[95], "mm", "arrow"))[-1] == "dense_block"


def test_physical_plans(spark, sf):
    gm, x = fx.mx1(spark, sf), fx.supplier_cents(spark, sf)
    add = ops.add(gm, gm).edges._jdf.queryExecution().toString()
    assert "CartesianProduct" not in add
    plan = ops.mv(gm, x, strategy=Strategy(join="broadcast")).df._jdf.queryExecution().executedPlan().toString()
    assert "partial_sum" in plan and "BroadcastHashJoin" in plan
    assert metrics.exchanges(gm.edges) == 1
    scan = io.table(spark, sf, "lineitem", ["l_partkey", "l_quantity"]).where("l_quantity > 10")._jdf.queryExecution().executedPlan().toString()
    assert "l_tax" not in scan and "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,10.0)]" in scan


def test_bucketed_graph_needs_no_exchange_of_edges(spark, sf, tmp_path):
    gm, x = fx.mx1(spark, sf), fx.supplier_cents(spark, sf)
    spark.sql("drop table if exists gamat_edges_t")
    spark.sql("drop table if exists gamat_state_t")
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        io.write_graph(gm, "gamat_edges_t", 4)
        x.df.write.bucketBy(4, "id").sortBy("id").saveAsTable("gamat_state_t")
        got = ops.mv(gm.with_edges(spark.table("gamat_edges_t")), VertexState(spark.table("gamat_state_t"), x.n))
        assert metrics.exchanges(got.df) == 1
        assert (array(got) == array(ops.mv(gm, x))).all()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
        spark.sql("drop table if exists gamat_edges_t")
        spark.sql("drop table if exists gamat_state_t")


def test_cache(spark, sf):
    c = cache.GraphCache()
    key = cache.fingerprint(spark, f"{sf}/lineitem.parquet", ["l_partkey"], "coo")
    assert key == cache.fingerprint(spark, f"{sf}/lineitem.parquet", ["l_partkey"], "coo") != cache.fingerprint(spark, f"{sf}/lineitem.parquet", ["l_suppkey"], "coo")
    a = c.get_or_build(key, lambda: fx.mx1(spark, sf))
    assert c.get_or_build(key, lambda: 1 / 0) is a and (c.hits, c.misses) == (1, 1)
    assert c.stats(spark).first()["uses"] == 2
    disk = c.get_or_build(key + "d", lambda: fx.mx1(spark, sf), tier="disk", buckets=2)
    assert disk.edges.count() == a.edges.count()
    c.evict()
    assert not c.entries


def test_sources(spark, tmp_path):
    g = io.generate(spark, "random", 20)
    io.write_coordinate(g, str(tmp_path / "m"))
    back = io.read_coordinate(spark, str(tmp_path / "m"))
    assert (numpy_matrix(back.map_weights(F.col("w").cast("bigint"))) == numpy_matrix(g)).all()
    (tmp_path / "one.mtx").write_text("%%MatrixMarket matrix coordinate real general\n% note\n2 3 2\n1 1 2.5\n2 3 -1\n")
    spark.dataSource.register(coordinate.CoordinateSource)
    rows = spark.read.format("gamat_coordinate").option("path", str(tmp_path / "one.mtx")).load().collect()
    assert sorted(map(tuple, rows)) == [(0, 0, 2.5), (1, 2, -1.0)]
    for fmt in ("json", "orc"):
        io.write_edges(g, fmt, str(tmp_path / fmt))
        assert io.read_edges(spark, fmt, str(tmp_path / fmt), "dst bigint, src bigint, w bigint").exceptAll(g.edges).isEmpty()
    (tmp_path / "d.csv").write_text("1,0\n0,2\n")
    from gamat.operators import ingest

    assert ingest.detect(io.read_dense_text(spark, str(tmp_path / "d.csv")), "cells").matrix
    assert (numpy_matrix(io.generate(spark, "identity", 3)) == np.eye(3)).all()
    with pytest.raises(MatrixError):
        io.generate(spark, "nothing", 3)


def test_models_refuse_what_is_no_matrix():
    for name in models.REFUSED:
        with pytest.raises(MatrixError):
            models.unsupported(name)
    models.unsupported("structured grids")


def test_migration_moves_only_what_pays():
    loads = {0: {1: 50.0, 2: 30.0, 3: 20.0}, 1: {4: 10.0}, 2: {5: 40.0}}
    moves = balance.plan(loads, seconds_per_unit=1.0, seconds_per_byte=0.0)
    total = {p: sum(b.values()) for p, b in loads.items()}
    for m in moves:
        assert m.gain > m.cost
        total[m.source] -= sum(v for b in loads.values() for k, v in b.items() if k == m.bucket)
        total[m.target] += sum(v for b in loads.values() for k, v in b.items() if k == m.bucket)
    assert max(total.values()) < 100 and balance.plan(loads, 1.0, 1.0) == []
    assert balance.plan({0: {1: 5.0}}, 1.0, 0.0) == []


def test_communication(spark, sf):
    gm = fx.mx1(spark, sf)
    own = reorder.even(gm, 4)
    cols = spark.range(gm.meta.n_cols).select("id", (F.col("id") % 4).cast("int").alias("part"))
    t = comm.totals(gm, own, cols).first()
    assert t["merged"] <= t["unmerged"] and t["pairs"] <= 12
    r = comm.replication(gm, own, 5).first()
    assert r["copies_replicated"] >= r["copies"] >= r["states"]
    y = ops.mv(gm, fx.supplier_cents(spark, sf))
    for size in (1, 7, 512):
        assert comm.decode_blocks(comm.encode_blocks(y.df, size), size).exceptAll(y.df).isEmpty()


def test_library_product_agrees(spark):
    a = matrix(spark, np.arange(12).reshape(3, 4))
    got = mllib_block_mm(a, a.T, 2)
    assert metrics.error(got, ops.mm(a, a.T).edges, ["dst", "src"], "w").first()["max_abs"] == 0


def test_measures():
    assert metrics.speedup(6, 2) == 3 and metrics.matrix_share(9, 10) == 0.9
