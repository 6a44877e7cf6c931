"""Dense products by panels, bucketed and migrated supersteps, cached hubs, orders, the shared folder."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from gamat.operators import cache, chain, ops, reorder
from gamat.operators.baselines import numpy_matrix
from gamat.operators.metrics import exchanges
from gamat.operators.superstep import bucketed, find_hubs, gather_apply, migrated
from gamat.plans import mapper
from gamat.sources import fixtures as fx
from gamat.sources.shared import NoSharedFolder, shared_folder
from gamat.types import CATALOGUE, GraphMatrix, MatrixError, MatrixMeta, Strategy, VertexState


def matrix(spark, rows: int, cols: int, fill: float, seed: int, kind: str = "bigint", big: int = 9) -> GraphMatrix:
    rng = random.Random(seed)
    cells = [(i, j, rng.randint(-big, big) if kind == "bigint" else rng.uniform(-1, 1)) for i in range(rows) for j in range(cols) if rng.random() < fill]
    return GraphMatrix(spark.createDataFrame(cells, f"dst bigint, src bigint, w {kind}"), MatrixMeta(rows, cols, kind))


@pytest.mark.parametrize(("kind", "big"), [("bigint", 9), ("double", 0), ("bigint", 2**28)])
def test_panels_equal_numpy(spark, monkeypatch, kind, big):
    monkeypatch.setattr(ops, "PANEL_CELLS", 200)
    a, b = matrix(spark, 13, 17, 0.6, 1, kind, big), matrix(spark, 17, 60, 0.2, 2, kind, big)
    want = numpy_matrix(a) @ numpy_matrix(b)
    for got in (ops.mm_panel(a, b), ops.mm_dense(a, b, True), ops.mm_dense(a, b, False)):
        assert numpy_matrix(got) == pytest.approx(want) if kind == "double" else (numpy_matrix(got) == want).all()
    assert ops.mm_panel(a, b.where("w = 1000000")).edges.count() == 0


def test_dense_and_row_products_agree(spark):
    s, b = matrix(spark, 12, 12, 0.8, 3).tril(), matrix(spark, 12, 20, 0.3, 4)
    for left, right in ((ops.symm(s, b), ops.symm(s, b, dense=False)), (ops.symm(s, b.T, side="R"), ops.symm(s, b.T, side="R", dense=False)), (ops.trmm(s, b, unit=True), ops.trmm(s, b, unit=True, dense=False)), (ops.trmm(s, b.T, side="R"), ops.trmm(s, b.T, side="R", dense=False))):
        assert (numpy_matrix(left) == numpy_matrix(right)).all()


def test_large_matrices_stay_off_the_driver(spark):
    a = GraphMatrix(spark.createDataFrame([(0, 0, 1)], "dst bigint, src bigint, w bigint"), MatrixMeta(10**6, 10**6))
    with pytest.raises(MatrixError):
        ops.local_array(a)
    assert not ops.fits(a) and ops.mm_dense(a, a, True).edges.collect()[0]["w"] == 1


def test_bucketed_superstep_has_one_exchange(spark):
    a = matrix(spark, 50, 40, 0.3, 5)
    x = VertexState(spark.range(40).select("id", (F.col("id") % 7 - 3).alias("s")), 40)
    out = bucketed(a, x, 8)
    assert exchanges(out) <= 1 + exchanges(a.edges.join(x.df, F.col("src") == F.col("id")))
    want = numpy_matrix(a) @ np.array([i % 7 - 3 for i in range(40)])
    assert {r["id"]: r["s"] for r in out.collect()} == {i: int(want[i]) for i in {r["dst"] for r in a.edges.collect()}}


def test_migration_lowers_the_peak_and_keeps_the_result(spark, sf):
    a, x = fx.mx1(spark, sf), fx.supplier_cents(spark, sf)
    out, (before, after) = migrated(a, x, 10, 4, start=lambda b: 0)
    assert sum(before.values()) == sum(after.values()) and max(after.values()) < 0.5 * max(before.values())
    assert sorted(map(tuple, out.df.collect())) == sorted(map(tuple, ops.mv(a, x).df.collect()))
    still, (b, c) = migrated(a, x, 10, 4, start=lambda b: 0, seconds_per_byte=1.0)
    assert b == c and still.df.count() == out.df.count()


def test_cached_graphs_know_their_edges_and_hubs(spark, sf):
    c = cache.GraphCache()
    g = c.get_or_build("m", lambda: fx.mx2(spark, sf), hub_degree=3)
    assert g.meta.nnz == g.edges.count() == g.T.meta.nnz
    assert {r[0] for r in g.hubs.collect()} == {r[0] for r in find_hubs(g.edges, 3).collect()} != set()
    x = fx.part_cents(spark, sf)
    assert sorted(map(tuple, gather_apply(g, x, strategy=Strategy(hub_broadcast=3)).df.collect())) == sorted(map(tuple, ops.mv(g, x).df.collect()))
    assert chain.cheapest([g, g.T])[0] > 0
    c.evict()


def plain_bandwidth_order(edges: list[tuple[int, int]]) -> list[int]:
    """The public order, component by component, as a queue."""
    near = {}
    for a, b in edges:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)

    def levels(start):
        depth, queue = {start: 0}, [start]
        for v in queue:
            for w in sorted(near[v]):
                if w not in depth:
                    depth[w] = depth[v] + 1
                    queue.append(w)
        return depth

    left, out = set(near), []
    while left:
        component = set(levels(min(left)))
        left -= component
        start = min(component, key=lambda v: (len(near[v]), v))
        for _ in range(3):
            d = levels(start)
            start = min(component, key=lambda v: (-d[v], len(near[v]), v))
        order, seen = [start], {start}
        for v in order:
            for w in sorted(near[v] - seen, key=lambda w: (len(near[w]), w)):
                order.append(w)
                seen.add(w)
        out += reversed(order)
    return out


def test_bandwidth_order_equals_the_public_one(spark):
    rng = random.Random(2)
    edges = [(i, i + rng.randint(1, 4)) for i in range(0, 36)] + [(100 + i, 100 + rng.randint(0, 7)) for i in range(8)] + [(100, 107), (101, 107)]
    g = GraphMatrix(spark.createDataFrame([(a, b, 1) for a, b in edges], "dst bigint, src bigint, w bigint"), MatrixMeta(200, 200))
    got = [r["id"] for r in reorder.relabelling(g, "rcm").orderBy("new_id").collect()]
    want = plain_bandwidth_order(edges)
    assert got == [v for v in want if v in set(got)] and set(want) <= set(got)


def test_a_giant_community_is_many_ranges(spark):
    df = spark.range(1000).select("id", F.lit(5).cast("bigint").alias("label"))
    out = reorder.ranges(df, [F.col("label"), F.col("id")], per=50)
    assert out.groupBy("range").count().agg(F.max("count")).first()[0] <= 50
    new = reorder.new_ids(df, [F.col("label"), F.col("id")]).collect()
    assert sorted(r["new_id"] for r in new) == list(range(1000)) and all(r["id"] == r["new_id"] for r in new)


def test_labels_that_do_not_settle_are_no_result(spark):
    g = GraphMatrix(spark.range(40).select((F.col("id") + 1).alias("dst"), F.col("id").alias("src"), F.lit(1).cast("bigint").alias("w")), MatrixMeta(41, 41))
    with pytest.raises(MatrixError):
        reorder.connected(g, most=2)


def test_rules_for_dense_and_irregular():
    big = {"n_rows": 10**7, "n_cols": 10**7, "nnz": 10**8, "max_row_deg": 10**6, "max_col_deg": 10**6, "kl": 9, "ku": 9, "above": 45, "below": 45, "asymmetric": 5}
    assert mapper.rules("mv", big) == CATALOGUE["irregular"]
    assert mapper.rules("mm", big | {"n_rows": 1000, "n_cols": 1000, "nnz": 9 * 10**5}) == CATALOGUE["dense_block"]


def test_a_cluster_without_a_shared_folder_is_refused():
    class Conf:
        def __init__(self, **kv):
            self.kv = kv

        def get(self, key, default=None):
            return self.kv.get(key, default)

    class Session:
        def __init__(self, **kv):
            self.conf = Conf(**kv)

    with pytest.raises(NoSharedFolder):
        shared_folder(Session(**{"spark.master": "spark://host:7077"}))
    with pytest.raises(NoSharedFolder):
        shared_folder(Session(**{"spark.master": "local-cluster[2,1,1024]"}))
    assert shared_folder(Session(**{"spark.master": "yarn", "spark.checkpoint.dir": "hdfs:///x/"})) == "hdfs:///x"
    assert shared_folder(Session(**{"spark.master": "local[4]"})).startswith("file:")
