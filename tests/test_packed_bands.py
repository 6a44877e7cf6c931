"""Products in bands: what is sent and written on the way, and what comes out."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gamat.operators import bands, ops
from gamat.types import GraphMatrix, MatrixError, MatrixMeta
from test_larger_tables import same, twice  # noqa: F401


def random_matrix(spark, rows: int, cols: int, n: int, seed: int) -> GraphMatrix:
    rng = np.random.default_rng(seed)
    edges = [(int(i), int(j), int(w)) for i, j, w in zip(rng.integers(0, rows, n), rng.integers(0, cols, n), rng.integers(1, 50, n), strict=True)]
    return GraphMatrix(spark.createDataFrame(edges, "dst bigint, src bigint, w bigint"), MatrixMeta(rows, cols))


@pytest.mark.parametrize("a", [np.array([], np.int64), np.array([5]), np.array([-(2**63), 0, 2**63 - 1]), np.arange(-500, 70_000, 7), np.array([0.5, -1e300])])
def test_packed_numbers_come_back(a):
    for ordered in (False, True):
        back = bands.unpacked(bands.packed(a, ordered), len(a))
        assert back.dtype == a.dtype and (back == a).all()


def test_edges_travel_in_few_bytes(spark):
    """Each band gets all of B here; an edge that goes to a band takes four bytes at most (unpacked rows: 40)."""
    a = random_matrix(spark, 400, 50, 40_000, 1)
    chunks = bands.dealt(a, a.T, 4)
    at = chunks.agg(F.sum("n"), F.sum(F.length("k") + F.length("i") + F.length("w"))).first()
    assert at[0] == 5 * 40_000 and at[1] < 4 * at[0]


def test_nulls_are_refused(spark):
    a = GraphMatrix(spark.createDataFrame([(0, 0, 1), (1, None, 2)], "dst bigint, src bigint, w bigint"), MatrixMeta(2, 2))
    with pytest.raises(Exception, match=MatrixError.__name__):
        bands.mm(a, a.T).edges.collect()


def test_exact_products_in_digits():
    rng = np.random.default_rng(0)
    for top in (10, 2**40, 2**50, 2**55):
        p, q = rng.integers(-9, 10, (30, 200)), rng.integers(-top, top, (200, 2))
        assert (ops.exact_product(p, q) == p @ q).all()


def test_heat_writes_no_matrix_of_edges(spark, twice, monkeypatch):  # noqa: F811
    """The interactions go from the table to the bands; they are not written first."""
    from gamat.plans import queries_relational

    monkeypatch.setattr(queries_relational, "reliable", None)
    for name in ("app_heat_one", "app_heat", "base_heat"):
        assert same(spark, name, twice)
