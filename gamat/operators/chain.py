"""Products of a series of matrices: by direct dependencies, in a tree, in sequence, in the cheapest order, or onto a vector."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.shared import reliable
from ..types import BROADCAST_ROWS, GraphMatrix, MatrixError, MatrixMeta, VertexState
from . import ops


def paths(series: list[GraphMatrix], most_paths: int | None = None) -> GraphMatrix:
    """Direct dependencies: every path through the series becomes one edge from its end to its start; one fold at the end.

    The number of paths is counted beforehand (a chain of cheap products on the patterns) if a limit is given."""
    if most_paths is not None and (n := count_paths(series)) > most_paths:
        raise MatrixError(f"{n} paths")
    e = series[0].edges.select("dst", F.col("src").alias("k0"), "w")
    for i, m in enumerate(series[1:]):
        r = m.edges.select(F.col("dst").alias(f"k{i}"), F.col("src").alias(f"k{i + 1}"), F.col("w").alias("v"))
        e = e.join(r, f"k{i}").select("dst", f"k{i + 1}", (F.col("w") * F.col("v")).alias("w"))
    last = f"k{len(series) - 1}"
    out = e.groupBy("dst", F.col(last).alias("src")).agg(F.sum("w").alias("w"))
    return GraphMatrix(out, MatrixMeta(series[0].meta.n_rows, series[-1].meta.n_cols))


def count_paths(series: list[GraphMatrix]) -> int:
    x = series[-1].edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").cast("decimal(38,0)").alias("s"))
    for m in reversed(series[:-1]):
        x = m.edges.join(x.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum("s").alias("s"))
    return int(x.agg(F.sum("s")).first()[0] or 0)


def sequential(series: list[GraphMatrix]) -> GraphMatrix:
    out = series[0]
    for m in series[1:]:
        out = ops.mm(out, m)
    return out


def tree(series: list[GraphMatrix]) -> GraphMatrix:
    """Neighbouring pairs are contracted, all pairs of a round independently of each other.

    A last product whose left factor gives every inner id at most one edge cannot multiply what it meets: its right factor
    then streams into it pair by pair, with no fold of its own, and the only fold is the last one."""
    while len(series) > 2:
        last = len(series) == 4
        pairs = [series[i : i + 2] for i in range(0, len(series), 2)]
        if last:
            left = ops.mm(*pairs[0])
            left = left.with_edges(reliable(left.edges))
            if (n := left.edges.count()) <= BROADCAST_ROWS and n == left.edges.select("src").distinct().count():
                return ops.mm(left.with_edges(F.broadcast(left.edges)), ops.mm(*pairs[1], fold=False))
            series = [left, ops.mm(*pairs[1])]
        else:
            series = [ops.mm(*p) if len(p) == 2 else p[0] for p in pairs]
    return ops.mm(*series) if len(series) == 2 else series[0]


def flops(a: GraphMatrix, b: GraphMatrix) -> DataFrame:
    """Multiplications of a product, exactly: column count times row count over the inner id."""
    c = a.edges.groupBy(F.col("src").alias("k")).agg(F.count("*").alias("c"))
    r = b.edges.groupBy(F.col("dst").alias("k")).agg(F.count("*").alias("r"))
    return c.join(r, "k").agg(F.sum(F.col("c") * F.col("r")).alias("flops"))


def cheapest(series: list[GraphMatrix]) -> tuple[float, tuple]:
    """Estimated cost and order (nested tuples of positions) by dynamic programming over exact counts of the given matrices
    and the usual independence estimate for intermediate ones."""
    nnz = [m.meta.nnz or m.edges.count() for m in series]
    k = len(series)
    best: dict[tuple[int, int], tuple[float, float, object]] = {(i, i): (0.0, float(nnz[i]), i) for i in range(k)}
    for span in range(1, k):
        for i in range(k - span):
            j = i + span
            options = []
            for cut in range(i, j):
                ca, na, oa = best[i, cut]
                cb, nb, ob = best[cut + 1, j]
                inner = max(1, series[cut].meta.n_cols)
                work = na * nb / inner
                cells = float(series[i].meta.n_rows) * series[j].meta.n_cols
                options.append((ca + cb + work, min(cells, work), (oa, ob)))
            best[i, j] = min(options, key=lambda o: (o[0], str(o[2])))
    cost, _, order = best[0, k - 1]
    return cost, order


def dp(series: list[GraphMatrix]) -> GraphMatrix:
    def build(order) -> GraphMatrix:
        return series[order] if isinstance(order, int) else ops.mm(build(order[0]), build(order[1]))

    return build(cheapest(series)[1])


def vector(series: list[GraphMatrix], x: VertexState) -> VertexState:
    """The series applied to a vector, right to left: one superstep per matrix."""
    for m in reversed(series):
        x = ops.mv(m, x)
    return x


def product(series: list[GraphMatrix], mode: str = "tree", x: VertexState | None = None, most_paths: int = 10_000_000):
    if x is not None:
        return vector(series, x)
    if mode == "paths":
        return paths(series) if count_paths(series) <= most_paths else dp(series)
    return {"tree": tree, "sequential": sequential, "dp": dp}[mode](series)


def rounds(mode: str, k: int) -> int:
    """Length of the critical path: products that must follow one another."""
    return {"paths": 1, "tree": max(0, (k - 1).bit_length()), "sequential": k - 1, "vector": k}[mode]
