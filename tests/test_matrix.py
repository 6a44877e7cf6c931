"""Operations against dense NumPy, algebraic identities and edge cases."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gamat.functions import cx
from gamat.operators import chain, deps, features, ingest, ops, reorder, storage
from gamat.operators.baselines import numpy_matrix
from gamat.operators.superstep import MAX_MIN, MIN_PLUS, gather_apply, slots
from gamat.sources import fixtures as fx
from gamat.sources import io
from gamat.types import GraphMatrix, MatrixError, MatrixMeta, Strategy, VertexState


def matrix(spark, a) -> GraphMatrix:
    a = np.asarray(a)
    cells = [(int(i), int(j), int(a[i, j])) for i, j in zip(*np.nonzero(a), strict=True)]
    return GraphMatrix(spark.createDataFrame(cells, "dst bigint, src bigint, w bigint"), MatrixMeta(*a.shape))


def state(spark, x) -> VertexState:
    return VertexState(spark.createDataFrame([(i, int(v)) for i, v in enumerate(x)], "id bigint, s bigint"), len(x))


def array(x: VertexState) -> np.ndarray:
    out = np.zeros(x.n, np.int64)
    for r in x.df.collect():
        out[r["id"]] = r["s"]
    return out


@pytest.fixture(scope="module")
def rng():
    return np.random.default_rng(4)


@pytest.fixture(scope="module")
def abx(rng):
    a, b = (rng.integers(-4, 5, (7, 7)) * (rng.random((7, 7)) < 0.5) for _ in range(2))
    return a, b, rng.integers(-9, 9, 7)


def test_worked_example(spark):
    """Five vertices a to e: one gathers from all of its neighbours, and two graphs merge edge by edge."""
    m = np.array([[2, 3, 5, 7, 11], [0, 1, 0, 0, 0], [0, 0, 1, 0, 0], [0, 0, 0, 1, 0], [1, 0, 0, 0, 1]])
    s = [1, 2, 3, 4, 5]
    assert array(ops.mv(matrix(spark, m), state(spark, s))).tolist() == (m @ s).tolist() and (m @ s)[0] == 2 + 6 + 15 + 28 + 55
    assert (numpy_matrix(ops.add(matrix(spark, m), matrix(spark, m.T))) == m + m.T).all()


def test_identities(spark, abx):
    a, b, x = abx
    ga, gb, gx = matrix(spark, a), matrix(spark, b), state(spark, x)
    assert (array(ops.mv(ops.add(ga, gb), gx)) == a @ x + b @ x).all()
    assert (array(ops.mv(ops.mm(ga, gb), gx)) == array(ops.mv(ga, ops.mv(gb, gx)))).all()
    assert (numpy_matrix(ops.mm(ga, gb).T) == numpy_matrix(ops.mm(gb.T, ga.T))).all()
    assert (numpy_matrix(ops.mm(ga, gb, gb, alpha=2, beta=-3, trans_a="T")) == 2 * a.T @ b - 3 * b).all()
    assert (numpy_matrix(ops.hadamard(ga, gb)) == a * b).all()


STRATEGIES = [Strategy(join=j) for j in ("broadcast", "merge", "shuffle_hash")] + [Strategy(unit="edge"), Strategy(direction="push"), Strategy(merge=False), Strategy(bucket=3), Strategy(hub_broadcast=2)] + [Strategy(split_cap=c, split_mode=m) for c in (1, 2, 10) for m in ("strict", "hash")]


@pytest.mark.parametrize("strategy", STRATEGIES, ids=str)
def test_every_strategy_gives_the_same_state(spark, abx, strategy):
    a, _, x = abx
    assert (array(ops.mv(matrix(spark, a), state(spark, x), strategy=strategy)) == a @ x).all()


def test_structured_products(spark, abx):
    a, b, x = abx
    low, sym = np.tril(a), np.tril(a) + np.tril(a, -1).T
    gl, gb, gx = matrix(spark, low), matrix(spark, b), state(spark, x)
    assert (array(ops.sym_mv(gl, gx)) == sym @ x).all()
    assert (array(ops.sympacked_mv(storage.pack(gl), gx)) == sym @ x).all()
    assert (numpy_matrix(ops.symm(gl, gb)) == sym @ b).all() and (numpy_matrix(ops.symm(gl, gb, "R")) == b @ sym).all()
    assert (numpy_matrix(ops.trmm(matrix(spark, a), gb)) == low @ b).all()
    assert (numpy_matrix(ops.trmm(matrix(spark, a), gb, uplo="U", trans="T")) == np.triu(a).T @ b).all()
    unit = np.tril(a, -1) + np.eye(7, dtype=int)
    assert (array(ops.tri_mv(matrix(spark, a), gx, unit=True)) == unit @ x).all()
    assert (numpy_matrix(ops.rank_k(matrix(spark, a))) == np.tril(a @ a.T)).all()
    assert (numpy_matrix(ops.rank_2k(matrix(spark, a), gb, gl, 2, 3)) == np.tril(2 * (a @ b.T + b @ a.T) + 3 * low)).all()
    assert (numpy_matrix(ops.sym_rank2(gl, gx, state(spark, x[::-1]), 2)) == np.tril(low + 2 * (np.outer(x, x[::-1]) + np.outer(x[::-1], x)))).all()
    for size in (2, 4, 64):
        assert (numpy_matrix(ops.mm_blocks(matrix(spark, a), gb, size)) == a @ b).all()
        assert (numpy_matrix(ops.mm_hybrid(matrix(spark, a), gb, size)) == a @ b).all()


def test_banded(spark, rng):
    n, kl, ku = 23, 3, 2
    a = np.triu(np.tril(rng.integers(-3, 4, (n, n)), ku), -kl)
    x = rng.integers(-5, 5, n)
    band = storage.to_band(matrix(spark, a), kl, ku)
    assert (array(ops.band_mv(band, state(spark, x), n, kl, ku)) == a @ x).all()
    assert (array(ops.band_mv_window(ops.diagonals(band), state(spark, x), kl, ku, range_size=5)) == a @ x).all()
    with pytest.raises(MatrixError):
        storage.from_band(band, n, n, 1, 1)


@pytest.mark.parametrize("uplo", ["L", "U"])
def test_packing_is_a_bijection(spark, rng, uplo):
    a = rng.integers(-4, 5, (40, 40))
    t = np.tril(a) if uplo == "L" else np.triu(a)
    assert (numpy_matrix(storage.unpack(storage.pack(matrix(spark, a), uplo), 40, uplo)) == t).all()
    big = 2**31
    k = big * (big + 1) // 2
    df = spark.createDataFrame([(k - 1, 1), (k, 2), (k + big, 3)], "k bigint, w bigint")
    got = sorted(tuple(r) for r in storage.unpack(df, big + 1).edges.collect())
    assert got == [(big - 1, big - 1, 1), (big, 0, 2), (big, big, 3)]


@pytest.mark.parametrize("method", ["block", "doubling", "level"])
@pytest.mark.parametrize("uplo", ["L", "U"])
def test_solves_undo_products(spark, rng, method, uplo):
    n = 12
    a = rng.integers(-2, 3, (n, n)) * (rng.random((n, n)) < 0.4)
    t = (np.tril(a, -1) if uplo == "L" else np.triu(a, 1)) + np.eye(n, dtype=int)
    x = rng.integers(-5, 6, n)
    got = deps.tri_solve(matrix(spark, t), state(spark, t @ x), uplo, unit=True, method=method, block=5)
    assert (array(got) == x).all()


def test_real_solve_and_singular(spark, rng):
    n = 9
    t = np.tril(rng.integers(1, 5, (n, n)))
    x = rng.integers(-5, 6, n)
    got = {r["id"]: r["s"] for r in deps.tri_solve(matrix(spark, t), state(spark, t @ x), method="block", block=4).df.collect()}
    assert np.allclose([got[i] for i in range(n)], x)
    t[3, 3] = 0
    with pytest.raises(MatrixError):
        deps.tri_solve(matrix(spark, t), state(spark, x))


def test_hermitian(spark, rng):
    a = rng.integers(-3, 4, (5, 5)) + 1j * rng.integers(-3, 4, (5, 5))
    h = a + a.conj().T
    x = rng.integers(-3, 4, 5) + 1j * rng.integers(-3, 4, 5)

    def zm(m):
        rows = [(i, j, int(m[i, j].real), int(m[i, j].imag)) for i in range(5) for j in range(5)]
        e = spark.createDataFrame(rows, "dst bigint, src bigint, re bigint, im bigint").select("dst", "src", F.struct("re", "im").alias("w"))
        return GraphMatrix(e, MatrixMeta(5, 5, "complex"))

    def dense(g):
        out = np.zeros((5, 5), complex)
        for r in g.edges.collect():
            out[r["dst"], r["src"]] = r["w"]["re"] + 1j * r["w"]["im"]
        return out

    zx = VertexState(spark.createDataFrame([(i, int(v.real), int(v.imag)) for i, v in enumerate(x)], "id bigint, re bigint, im bigint").select("id", F.struct("re", "im").alias("s")), 5)
    got = {r["id"]: r["s"]["re"] + 1j * r["s"]["im"] for r in ops.herm_mv(zm(h).tril(), zx).df.collect()}
    assert np.allclose([got[i] for i in range(5)], h @ x)
    assert abs((x.conj() @ h @ x).imag) < 1e-9
    assert np.allclose(dense(ops.herm_mm(zm(h).tril(), zm(a))), h @ a)
    assert np.allclose(dense(ops.herm_rank_k(zm(a))), np.tril(a @ a.conj().T))
    assert np.allclose(dense(ops.herm_rank_2k(zm(a), zm(h))), np.tril(a @ h.conj().T + h @ a.conj().T))
    assert np.allclose(dense(ops.herm_rank1(zm(h).tril(), zx)), np.tril(h + np.outer(x, x.conj())))
    assert dict(zm(a).map_weights(cx.conj(F.col("w"))).edges.dtypes)["w"].startswith("struct")


def test_chain_modes_agree(spark, rng):
    shapes = [(3, 5), (5, 8), (8, 4), (4, 6), (6, 2)]
    dense = [rng.integers(-2, 3, s) for s in shapes]
    series = [matrix(spark, m) for m in dense]
    want = np.linalg.multi_dot(dense)
    for mode in ("paths", "tree", "sequential", "dp"):
        assert (numpy_matrix(chain.product(series, mode)) == want).all()
    x = rng.integers(-3, 4, 2)
    assert (array(chain.product(series, x=state(spark, x))) == want @ x).all()
    assert chain.count_paths(series) == int(np.linalg.multi_dot([(m != 0).astype(int) for m in dense]).sum())
    with pytest.raises(MatrixError):
        chain.paths(series, most_paths=1)
    assert [chain.rounds(m, 5) for m in ("paths", "tree", "sequential")] == [1, 3, 4]


def test_edge_cases(spark):
    empty = GraphMatrix(spark.createDataFrame([], "dst bigint, src bigint, w bigint"), MatrixMeta(3, 3))
    one = state(spark, [1, 2, 3])
    assert array(ops.mv(empty, one)).tolist() == [0, 0, 0]
    assert array(gather_apply(empty, one, total=True, default=7)).tolist() == [7, 7, 7]
    assert ops.mm(empty, empty).edges.count() == 0 and features.profile(empty).first()["nnz"] == 0
    single = matrix(spark, [[5]])
    assert array(ops.mv(single, state(spark, [3]))).tolist() == [15]
    wide, tall = matrix(spark, np.arange(15).reshape(3, 5)), matrix(spark, np.arange(15).reshape(5, 3))
    assert wide.meta.n_vertices == tall.meta.n_vertices == 5 and wide.vertices().count() == 5
    assert (numpy_matrix(ops.mm(wide, tall)) == np.arange(15).reshape(3, 5) @ np.arange(15).reshape(5, 3)).all()
    double = GraphMatrix(spark.createDataFrame([(0, 0, 2), (0, 0, -2), (1, 0, 0)], "dst bigint, src bigint, w bigint"), MatrixMeta(2, 2))
    assert double.summed().edges.count() == 2 and double.summed().compact().edges.count() == 0
    assert ops.add(single, single, 1, -1).edges.count() == 1 and ops.add(single, single, 1, -1, drop_zeros=True).edges.count() == 0
    y = state(spark, [100])
    assert array(ops.mv(single, state(spark, [3]), y, alpha=0, beta=2)).tolist() == [200]
    assert array(ops.mv(single, state(spark, [3]), y, alpha=1, beta=0)).tolist() == [15]


def test_semirings(spark):
    inf = MatrixMeta(4, 4)
    g = GraphMatrix(spark.createDataFrame([(1, 0, 5), (2, 1, 2), (2, 0, 9), (3, 2, 1)], "dst bigint, src bigint, w bigint"), inf)
    x = VertexState(spark.createDataFrame([(0, 0)], "id bigint, s bigint"), 4)
    for _ in range(3):
        new = gather_apply(g, x, MIN_PLUS.times, MIN_PLUS.plus).df.unionByName(x.df)
        x = VertexState(new.groupBy("id").agg(F.min("s").alias("s")), 4)
    assert array(x).tolist() == [0, 5, 7, 8]
    wide = gather_apply(g, state(spark, [9, 4, 3, 1]), MAX_MIN.times, MAX_MIN.plus)
    assert {r["id"]: r["s"] for r in wide.df.collect()} == {1: 5, 2: 9, 3: 1}


def test_validate_and_detect(spark):
    bad = GraphMatrix(spark.createDataFrame([(0, None, 1), (5, 0, 1)], "dst bigint, src bigint, w bigint"), MatrixMeta(3, 3))
    with pytest.raises(MatrixError):
        bad.validate()
    rows = lambda r: spark.createDataFrame([(i, v) for i, v in enumerate(r)], "id bigint, v array<string>")
    assert ingest.detect(rows([["1", "2"], ["3", "4"]]), "v") == ingest.Detection(True, 2, 2, "bigint")
    assert ingest.detect(rows([["1", "2.5"], ["3", "4"]]), "v").dtype == "double"
    assert "elements" in ingest.detect(rows([["1", "2"], ["3"]]), "v").reason
    assert "numeric" in ingest.detect(rows([["1", "x"]]), "v").reason and not ingest.detect(rows([]), "v").matrix
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 2.5])], "id bigint, v array<double>")
    assert sorted(map(tuple, ingest.to_graph(df, "id", "v").edges.collect())) == [(0, 0, 1.0), (1, 1, 2.5)]


@pytest.mark.parametrize("cap", [1, 3, 10])
def test_split_reaches_the_cap(spark, rng, cap):
    a = (rng.random((6, 40)) < 0.6).astype(int)
    s = slots(matrix(spark, a).edges, cap, "strict", bucket=7).groupBy("dst", "slot").agg(F.count("*").alias("n")).collect()
    for i in range(6):
        own = sorted(((r["slot"], r["n"]) for r in s if r["dst"] == i))
        d = int(a[i].sum())
        assert len(own) == -(-d // cap) and all(n == cap for _, n in own[:-1]) and own[-1][1] <= cap


def test_relabelling_is_a_bijection_and_restores(spark):
    g = io.generate(spark, "random", 60, per_row=2)
    for method in ("lpa", "cc", "rcm"):
        perm = reorder.reliable(reorder.relabelling(g, method))
        ids = sorted(r["new_id"] for r in perm.collect())
        assert ids == list(range(len(ids))) and perm.select("id").distinct().count() == len(ids)
    x = state(spark, range(60))
    back = reorder.restore(ops.mv(reorder.relabel(g, perm), reorder.relabel_state(x, perm)), perm)
    assert (array(back) == array(ops.mv(g, x))).all()


def test_communities_and_partitions(spark):
    cliques = np.kron(np.eye(3, dtype=int), np.ones((4, 4), int))
    g = matrix(spark, cliques)
    labels = {r["id"]: r["label"] for r in reorder.label_propagation(g).collect()}
    assert [labels[i] for i in range(12)] == [0] * 4 + [4] * 4 + [8] * 4
    assert {r["id"]: r["label"] for r in reorder.connected(g).collect()} == labels
    parts = {r["id"]: r["part"] for r in reorder.by_community(g, reorder.connected(g), 3).collect()}
    assert len({(labels[i], parts[i]) for i in range(12)}) == 3
    own = reorder.even(g, 5)
    load = [r["n"] for r in own.groupBy("part").agg(F.sum("degree").alias("n")).collect()]
    assert max(load) <= 48 / 5 + 4
    q = reorder.quality(g, own, own.select("id", "part")).first()
    assert q["edges"] == 48 and q["replicas"] <= q["cut"]


def test_profile_and_structures(spark):
    k = io.generate(spark, "stencil", 40)
    row = features.profile(k).first()
    assert features.structures(row) == {"symmetric", "banded"} and row["kl"] == row["ku"] == 1
    assert features.structures(features.profile(k.tril(-1)).first()) >= {"triangular"}


def test_fixture_stiffness_has_no_force_on_constants(spark, sf):
    k = fx.mx8(spark, sf)
    u = VertexState(spark.range(k.meta.n_cols).select("id", F.lit(1).cast("bigint").alias("s")), k.meta.n_cols)
    f = ops.mv(k, u).df.where("s <> 0").collect()
    assert [(r["id"], r["s"]) for r in f] == [(0, 1)]
