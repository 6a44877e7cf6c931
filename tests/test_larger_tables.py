"""Queries against their SQL on tables whose matrices have gaps: copies with shifted keys, and odd rows."""

import datetime

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry

KEYS = {"customer": {"c_custkey": "customer"}, "supplier": {"s_suppkey": "supplier"}, "part": {"p_partkey": "part"}, "orders": {"o_orderkey": "orders", "o_custkey": "customer"}, "lineitem": {"l_orderkey": "orders", "l_partkey": "part", "l_suppkey": "supplier"}}


@pytest.fixture(scope="session")
def twice(tmp_path_factory, sf):
    """Every table twice, with shifted keys: nothing of one copy meets the other."""
    out, c = tmp_path_factory.mktemp("twice"), duckdb.connect()
    own = {t: next(iter(k)) for t, k in KEYS.items()}
    for t, keys in KEYS.items():
        shifted = ", ".join(f"({k} + i * (select max({own[t2]}) + 1 from '{sf}/{t2}.parquet'))::bigint as {k}" for k, t2 in keys.items())
        c.execute(f"copy (select * exclude (i) replace ({shifted}) from '{sf}/{t}.parquet', range(2) r(i)) to '{out}/{t}.parquet' (format parquet)")
    for t in ("nation", "region", "events", "embeddings"):
        c.execute(f"copy (select * from '{sf}/{t}.parquet') to '{out}/{t}.parquet' (format parquet)")
    return str(out)


def same(spark, name: str, folder: str) -> list:
    """Rows of the query, which are those of its SQL."""
    c, df = duckdb.connect(), entry.queries()[name](spark, folder)
    for t in ("customer", "supplier", "part", "orders", "lineitem", "nation", "region", "events", "embeddings"):
        c.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
    cols = ", ".join(f'"{x}"' for x in df.columns)
    rows, wanted = sorted(map(tuple, df.collect())), sorted(c.execute(f"select {cols} from ({entry.oracle_sql()[name]})").fetchall())
    assert len(rows) == len(wanted) and rows == wanted
    return rows


@pytest.mark.parametrize("name", ["spr", "spr2", "syr", "syr2"])
def test_rank_updates_keep_the_stored_cells(spark, twice, name):
    assert same(spark, name, twice)


def test_sessions_count_whole_seconds(spark, sf, tmp_path):
    t0 = datetime.datetime(2024, 1, 1)
    at = [(0.9, 1), (3600.1, 1), (7199.95, 1), (0, 2), (3600, 2), (7199, 2), (0.2, 3), (0.7, 3), (3599.9, 3)]
    rows = [(i, t0 + datetime.timedelta(seconds=s), u, "x", 1.0, "") for i, (s, u) in enumerate(at)]
    df = spark.createDataFrame(rows, "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string")
    df.coalesce(1).write.parquet(str(tmp_path / "e"))
    c = duckdb.connect()
    c.execute(f"copy (select * from '{tmp_path}/e/*.parquet') to '{tmp_path}/events.parquet' (format parquet)")
    for t in ("customer", "supplier", "part", "orders", "lineitem", "nation", "region", "embeddings"):
        c.execute(f"copy (select * from '{sf}/{t}.parquet') to '{tmp_path}/{t}.parquet' (format parquet)")
    assert len(same(spark, "window_session", str(tmp_path))) == 5


@pytest.mark.parametrize("dense", [False, True])
def test_bands_equal_numpy_and_keep_cancelled_cells(dense):
    from gamat.operators import bands

    rng = np.random.default_rng(3)
    a, b = (rng.integers(-3, 4, s) * (rng.random(s) < (0.9 if dense else 0.05)) for s in ((60, 40), (40, 50)))
    (ai, ak), (bk, bj) = np.nonzero(a), np.nonzero(b)
    got, met = np.zeros((60, 50), np.int64), np.zeros((60, 50), bool)
    old = bands.STRIP_CELLS, bands.PAIRS
    try:
        bands.STRIP_CELLS, bands.PAIRS = 500, 70
        for rows, cols, values, seen in bands.strips(ai, ak, a[ai, ak], bk, bj, b[bk, bj]):
            got[np.ix_(rows, cols)], met[np.ix_(rows, cols)] = values, seen
    finally:
        bands.STRIP_CELLS, bands.PAIRS = old
    assert (got == a @ b).all() and (met == ((a != 0).astype(int) @ (b != 0).astype(int) > 0)).all()


@pytest.mark.parametrize("name", ["profile_matrix", "model_laplacian", "symm", "symm_right", "trmm", "trmm_unit_right", "mm_hybrid_equals"])
def test_products_in_bands(spark, twice, monkeypatch, name):
    """Neither factor may be held whole; the plan has no fold of products after the task that makes them."""
    from gamat.operators import ops

    monkeypatch.setattr(ops, "LOCAL_CELLS", 10)
    monkeypatch.setattr(ops, "mm_blocks", None)
    assert same(spark, name, twice)


def test_heat_is_applied_in_bands(spark, twice, monkeypatch):
    """The temperatures between species are never written as edges."""
    from gamat.operators import ops

    monkeypatch.setattr(ops, "mm_dense", None)
    for name in ("app_heat", "app_heat_one", "base_heat"):
        assert same(spark, name, twice)


def test_all_pairs_of_points_have_no_bound(spark, twice, monkeypatch):
    from gamat.operators import models, ops

    monkeypatch.setattr(ops, "MOST_PAIRS", 1)
    assert same(spark, "model_nbody", twice)
    one = spark.createDataFrame([(7, 3)], "id bigint, x bigint")
    assert models.nbody(one, lambda x, y: F.abs(x - y)).df.collect() == []
    three = spark.createDataFrame([(1, 5), (2, 5), (3, 9)], "id bigint, x bigint")
    assert sorted(map(tuple, models.nbody(three, lambda x, y: x + 2 * y).df.collect())) == [(1, 15 + 23), (2, 15 + 23), (3, 38)]


@pytest.mark.parametrize("cells", [8_000_000, 16_000])
def test_energy_without_a_written_neighbour_graph(spark, sf, monkeypatch, cells):
    """Whole, and with the rows in several groups."""
    from gamat.operators import ops

    monkeypatch.setattr(ops, "mm_blocks", None)
    for name in ("app_energy", "app_energy_dense", "app_energy_param", "base_energy"):
        monkeypatch.setattr(ops, "LOCAL_CELLS", cells)
        assert same(spark, name, sf)


def test_tree_streams_its_last_product(spark, twice):
    df = entry.queries()["chain_tree"](spark, twice)
    assert same(spark, "chain_tree", twice)
    # One fold for the small factor, one for the result; the product of the facts has none.
    assert df._jdf.queryExecution().optimizedPlan().toString().count("Aggregate [") == 1


def test_powers_beyond_64_bits(spark, sf, monkeypatch):
    from gamat.sources import fixtures as fx

    assert same(spark, "iterate_power", sf)
    real = fx.mx6
    monkeypatch.setattr(fx, "mx6", lambda s, d: real(s, d).map_weights(F.col("w") * 1_000_000))
    small, big = entry.queries(), None
    big = {r["id"]: int(r["s"]) for r in small["iterate_power"](spark, sf).collect()}
    monkeypatch.setattr(fx, "mx6", real)
    assert big == {r["id"]: r["s"] * 10**18 for r in small["iterate_power"](spark, sf).collect()} and max(big.values()) > 2**63


def test_jobs_that_read_given_tables(spark, twice):
    n = duckdb.connect().execute(f"select count(*) from '{twice}/orders.parquet'").fetchone()[0]
    assert len(same(spark, "generated_stencil", twice)) == 3 * n - 2
    best = same(spark, "label_best", twice)
    regret = entry.queries()["mapper_regret"](spark, twice).collect()
    assert {(r["op"], r["matrix"], r["platform"]) for r in regret} == {(r[0], r[1], r[2]) for r in best}
    assert all(r["regret"] is None or r["regret"] >= 1 for r in regret)


def test_outer_product_of_vectors_by_panels(spark, sf, monkeypatch):
    from gamat.operators import ops

    monkeypatch.setattr(ops, "mm_blocks", None)
    assert same(spark, "gemm_outer_block", sf)
