"""Dependencies along directed paths, and triangular solves that follow, contract or block them."""

from __future__ import annotations


import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..types import GraphMatrix, MatrixError, VertexState
from . import ops
from ..sources.shared import reliable


#: Diagonal blocks that are solved one after the other.
MOST_BLOCKS = 256


def levels(gm: GraphMatrix, most: int = 10_000) -> DataFrame:
    """id, level: 0 for vertices that depend on nothing but themselves, else one more than the highest predecessor."""
    e = gm.edges.where("dst <> src").select("dst", "src").distinct()
    everyone = e.select(F.explode(F.array("dst", "src")).alias("id")).distinct()
    level = 0
    frontier = everyone
    out = everyone.select("id", F.lit(0).alias("level"))
    while True:
        frontier = reliable(e.join(frontier.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct())
        if frontier.isEmpty():
            return out
        level += 1
        if level > most:
            raise MatrixError("the dependencies have a cycle")
        out = reliable(out.join(frontier.withColumn("new", F.lit(level)), "id", "left").select("id", F.coalesce("new", "level").alias("level")))


def flipped(a: GraphMatrix) -> GraphMatrix:
    """Upper triangle as a lower one: ids counted from the other end."""
    n = a.meta.n_rows - 1
    return a.with_edges(a.edges.select((n - F.col("dst")).alias("dst"), (n - F.col("src")).alias("src"), "w"), uplo="L")


def flip_state(x: VertexState) -> VertexState:
    return VertexState(x.df.select((x.n - 1 - F.col("id")).alias("id"), *[c for c in x.df.columns if c != "id"]), x.n)


def tri_solve(a: GraphMatrix, b: VertexState, uplo: str = "L", unit: bool = False, method: str = "block", block: int = 256, rounds: int | None = None) -> VertexState:
    """x with A x = b for a triangular A. b may carry a right-hand side column c (several at once).

    block: ranges of `block` ids are solved one after the other, with NumPy on the diagonal block and one product with the
    blocks below; beyond MOST_BLOCKS such ranges doubling takes over, as each is a round of its own. doubling: x = (I + N)(I + N^2)(I + N^4)... D^-1 b with nilpotent N, a logarithmic number of products
    (unit diagonal, or real weights). level: one round per dependency level."""
    if uplo == "U":
        return flip_state(tri_solve(flipped(a.triu()), flip_state(b), "L", unit, method, block, rounds))
    a = a.tril()
    multi = "c" in b.df.columns
    rhs = b.df if multi else b.df.withColumn("c", F.lit(0))
    if not unit:
        stored = a.edges.where("dst = src and w <> 0").select("dst").distinct().count()
        if stored < a.meta.n_rows:
            raise MatrixError(f"singular: {a.meta.n_rows - stored} zeros on the diagonal")
    if method == "block" and a.meta.n_rows > block * MOST_BLOCKS:
        method = "doubling"
    solve = {"block": _block, "doubling": _doubling, "level": _level}[method]
    out = solve(a, rhs, unit, block, rounds)
    return VertexState(out if multi else out.select("id", "s"), b.n)


def _numpy_solve(unit: bool):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        cells, rhs = pdf[pdf["kind"] == 0], pdf[pdf["kind"] == 1]
        if rhs.empty:
            return pd.DataFrame({"id": [], "c": [], "s": []})
        lo, n = int(pdf["lo"].iloc[0]), int(pdf["n"].iloc[0])
        whole = pdf["exact"].iloc[0] and unit
        kind = object if whole else np.float64
        m = np.zeros((n, n), kind)
        for i, j, w in zip(cells["i"], cells["j"], cells["w"], strict=True):
            m[int(i) - lo, int(j) - lo] += int(w) if whole else w
        columns = sorted(set(rhs["j"]))
        x = np.zeros((n, len(columns)), kind)
        for i, c, w in zip(rhs["i"], rhs["j"], rhs["w"], strict=True):
            x[int(i) - lo, columns.index(c)] += int(w) if whole else w
        for i in range(n):
            if i:
                x[i] = x[i] - m[i, :i] @ x[:i]
            if not unit:
                x[i] = x[i] / m[i, i]
        i, c = np.indices(x.shape)
        return pd.DataFrame({"id": i.ravel() + lo, "c": np.array(columns)[c.ravel()], "s": x.ravel()})

    return run


def _block(a: GraphMatrix, rhs: DataFrame, unit: bool, block: int, rounds) -> DataFrame:
    n, whole = a.meta.n_rows, unit and dict(a.edges.dtypes)["w"] == "bigint" and dict(rhs.dtypes)["s"] == "bigint"
    kind = "bigint" if whole else "double"
    out = None
    for lo in range(0, n, block):
        size = min(block, n - lo)
        own = a.edges.where((F.col("dst") >= lo) & (F.col("dst") < lo + size))
        need = rhs.where((F.col("id") >= lo) & (F.col("id") < lo + size)).select("id", "c", F.col("s").cast(kind).alias("s"))
        if out is not None:
            before = own.where(F.col("src") < lo).join(out.select(F.col("id").alias("src"), "c", "s"), "src").select(F.col("dst").alias("id"), "c", (-F.col("w") * F.col("s")).cast(kind).alias("s"))
            need = need.unionByName(before)
        need = need.groupBy("id", "c").agg(F.sum("s").alias("s"))
        rows = own.where((F.col("src") >= lo) & ((F.col("src") != F.col("dst")) if unit else F.lit(True))).select(F.lit(0).alias("kind"), F.col("dst").alias("i"), F.col("src").alias("j"), F.col("w").cast(kind).alias("w"))
        rows = rows.unionByName(need.select(F.lit(1).alias("kind"), F.col("id").alias("i"), F.col("c").cast("bigint").alias("j"), F.col("s").alias("w")))
        rows = rows.withColumn("lo", F.lit(lo)).withColumn("n", F.lit(size)).withColumn("exact", F.lit(whole))
        # One diagonal block: at most block x block cells.
        part = rows.groupBy("lo").applyInPandas(_numpy_solve(unit), f"id bigint, c bigint, s {kind}")
        part = reliable(part) if n > block else part
        out = part if out is None else out.unionByName(part)
    return out


def _doubling(a: GraphMatrix, rhs: DataFrame, unit: bool, block: int, rounds: int | None) -> DataFrame:
    rounds = rounds or max(1, (a.meta.n_rows - 1).bit_length())
    off = a.where("dst <> src")
    x = rhs.select("id", "c", "s")
    if unit:
        power = off.map_weights(-F.col("w"))
    else:
        d = a.edges.where("dst = src").select("dst", F.col("w").alias("d"))
        power = off.with_edges(off.edges.join(d, "dst").select("dst", "src", (-F.col("w") / F.col("d")).alias("w")))
        x = x.join(d.withColumnRenamed("dst", "id"), "id").select("id", "c", (F.col("s") / F.col("d")).alias("s"))
    for r in range(rounds):
        x = ops.mv_multi(power, x).select("id", "c", "s").unionByName(x).groupBy("id", "c").agg(F.sum("s").alias("s"))
        x = reliable(x)
        if r + 1 < rounds:
            power = ops.mm(power, power).compact()
            power = power.with_edges(reliable(power.edges))
            if power.edges.isEmpty():
                break
    return x


def _level(a: GraphMatrix, rhs: DataFrame, unit: bool, block: int, rounds) -> DataFrame:
    off = a.where("dst <> src").edges
    level = reliable(levels(a))
    d = a.edges.where("dst = src").select(F.col("dst").alias("id"), F.col("w").alias("d"))
    everyone = rhs.join(level, "id", "left").select("id", "c", "s", F.coalesce("level", F.lit(0)).alias("level"))
    done = None
    for k in range((level.agg(F.max("level")).first()[0] or 0) + 1):
        now = everyone.where(F.col("level") == k).select("id", "c", "s")
        if done is not None:
            back = off.join(level.where(F.col("level") == k).select(F.col("id").alias("dst")), "dst", "left_semi").join(done.select(F.col("id").alias("src"), "c", "s"), "src")
            now = now.unionByName(back.select(F.col("dst").alias("id"), "c", (-F.col("w") * F.col("s")).alias("s")))
        now = now.groupBy("id", "c").agg(F.sum("s").alias("s"))
        if not unit:
            now = now.join(d, "id").select("id", "c", (F.col("s") / F.col("d")).alias("s"))
        now = reliable(now)
        done = now if done is None else reliable(done.unionByName(now))
    return done


def triband_solve(band: DataFrame, b: VertexState, k: int, uplo: str = "L", unit: bool = False, method: str = "doubling", **how) -> VertexState:
    from . import storage

    kl, ku = (k, 0) if uplo == "L" else (0, k)
    return tri_solve(storage.from_band(band, b.n, b.n, kl, ku), b, uplo, unit, method, **how)


def tripacked_solve(packed: DataFrame, b: VertexState, uplo: str = "L", unit: bool = False, **how) -> VertexState:
    from . import storage

    return tri_solve(storage.unpack(packed, b.n, uplo), b, uplo, unit, **how)
