"""Storage variants and their expansion to edges: symmetric, packed, triangular, banded and Hermitian halves, dense rows, blocks."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import cx
from ..types import GraphMatrix, MatrixError, MatrixMeta


def mirror(gm: GraphMatrix) -> GraphMatrix:
    """Full symmetric matrix from one stored triangle: every edge emits itself and, off the diagonal, its twin."""
    e = gm.edges
    twin = F.array(F.struct("dst", "src"), F.struct(F.col("src").alias("dst"), F.col("dst").alias("src")))
    both = e.select(F.explode(F.when(F.col("dst") == F.col("src"), F.slice(twin, 1, 1)).otherwise(twin)).alias("x"), "w")
    return gm.with_edges(both.select("x.*", "w"), uplo=None, storage="coo")


def mirror_hermitian(gm: GraphMatrix) -> GraphMatrix:
    e = gm.edges
    twin = e.where("dst <> src").select(F.col("src").alias("dst"), F.col("dst").alias("src"), cx.conj(F.col("w")).alias("w"))
    return gm.with_edges(e.select("dst", "src", cx.cx(F.col("w")["re"], F.col("w")["im"]).alias("w")).unionByName(twin), uplo=None, storage="coo")


def pack(gm: GraphMatrix, uplo: str = "L") -> DataFrame:
    """k, w: position in the packed triangle. Lower row by row: k = i (i + 1) / 2 + j; upper: rows and columns swapped."""
    i, j = (F.col("dst"), F.col("src")) if uplo == "L" else (F.col("src"), F.col("dst"))
    return gm.edges.where(j <= i).select((F.shiftright(i * (i + 1), 1) + j).alias("k"), "w")


def unpack(packed: DataFrame, n: int, uplo: str = "L", **meta) -> GraphMatrix:
    """Inverse of `pack`; the row from a square root is corrected by one where rounding misses."""
    k = F.col("k")
    start = lambda r: F.shiftright(r * (r + 1), 1)
    guess = F.floor((F.sqrt(8.0 * k + 1.0) - 1.0) / 2.0)
    row = guess.cast("bigint") + F.when(start(guess + 1) <= k, 1).when(start(guess) > k, -1).otherwise(0)
    d = packed.select(k, row.cast("bigint").alias("i"), "w").select("i", (k - start(F.col("i"))).alias("j"), "w")
    a, b = ("i", "j") if uplo == "L" else ("j", "i")
    return GraphMatrix(d.select(F.col(a).alias("dst"), F.col(b).alias("src"), "w"), MatrixMeta(n, n, storage="packed", uplo=uplo, **meta))


def from_band(band: DataFrame, n_rows: int, n_cols: int, kl: int, ku: int, check: bool = True) -> GraphMatrix:
    """Edges of band storage (i, d = column - row, w). Cells outside the band are an error; the check scans i and d once."""
    bad = (F.col("d") < -kl) | (F.col("d") > ku) | (F.col("i") + F.col("d") < 0) | (F.col("i") + F.col("d") >= n_cols)
    if check and (outside := band.where(bad).count()):
        raise MatrixError(f"{outside} cells outside the band")
    e = band.select(F.col("i").alias("dst"), (F.col("i") + F.col("d")).cast("bigint").alias("src"), "w")
    return GraphMatrix(e, MatrixMeta(n_rows, n_cols, storage="band", kl=kl, ku=ku, structure=frozenset({"banded"})))


def to_band(gm: GraphMatrix, kl: int, ku: int) -> DataFrame:
    e = gm.edges.select(F.col("dst").alias("i"), (F.col("src") - F.col("dst")).cast("int").alias("d"), "w")
    return e.where((F.col("d") >= -kl) & (F.col("d") <= ku))


def with_unit_diagonal(gm: GraphMatrix) -> GraphMatrix:
    """Triangle with an implied diagonal of ones: stored diagonal cells are ignored, ones are added."""
    kind = dict(gm.edges.dtypes)["w"]
    ones = gm.spark.range(gm.meta.n_rows).select(F.col("id").alias("dst"), F.col("id").alias("src"), F.lit(1).cast(kind).alias("w"))
    return gm.with_edges(gm.edges.where("dst <> src").unionByName(ones), unit=False)


def to_blocks(gm: GraphMatrix, size: int) -> DataFrame:
    """bi, bj, cells: sparse lists of blocks of size x size, each bounded by that size."""
    at = lambda c: F.floor(F.col(c) / size).cast("int")
    cell = F.struct((F.col("dst") % size).cast("int").alias("i"), (F.col("src") % size).cast("int").alias("j"), "w")
    return gm.edges.groupBy(at("dst").alias("bi"), at("src").alias("bj")).agg(F.collect_list(cell).alias("cells"))


def csr_rows(gm: GraphMatrix) -> DataFrame:
    """dst, cols, vals: sorted sparse rows."""
    r = gm.edges.groupBy("dst").agg(F.sort_array(F.collect_list(F.struct("src", "w"))).alias("c"))
    return r.select("dst", F.col("c.src").alias("cols"), F.col("c.w").alias("vals"))


def rows_as_maps(gm: GraphMatrix) -> DataFrame:
    return gm.edges.groupBy("dst").agg(F.map_from_entries(F.collect_list(F.struct("src", "w"))).alias("m"))


def expand(df: DataFrame, storage: str, n_rows: int, n_cols: int, **how) -> GraphMatrix:
    """Any stored variant as edges."""
    meta = MatrixMeta(n_rows, n_cols)
    if storage == "coo":
        return GraphMatrix(df.select("dst", "src", "w"), meta)
    if storage == "dense_rows":
        e = df.select("dst", F.posexplode("v").alias("src", "w")).where("w <> 0")
        return GraphMatrix(e.select("dst", F.col("src").cast("bigint").alias("src"), "w"), meta)
    if storage == "csr_rows":
        e = df.select("dst", F.explode(F.arrays_zip(F.col("cols").alias("src"), F.col("vals").alias("w"))).alias("x")).select("dst", "x.*")
        return GraphMatrix(e, meta)
    if storage == "sym":
        return mirror(GraphMatrix(df, meta))
    if storage == "herm":
        return mirror_hermitian(GraphMatrix(df, meta))
    if storage == "packed":
        return unpack(df, n_rows, how.get("uplo", "L"))
    if storage == "tri":
        gm = GraphMatrix(df, replace(meta, uplo=how.get("uplo", "L")))
        return with_unit_diagonal(gm) if how.get("diag") == "U" else gm
    if storage == "band":
        return from_band(df, n_rows, n_cols, how["kl"], how["ku"])
    if storage == "symband":
        return mirror(from_band(df, n_rows, n_cols, how["k"], how["k"]))
    if storage == "perm":
        p = how["relabel"]
        e = df.join(p.select(F.col("id").alias("dst"), F.col("new_id").alias("a")), "dst").join(p.select(F.col("id").alias("src"), F.col("new_id").alias("b")), "src")
        return GraphMatrix(e.select(F.col("a").alias("dst"), F.col("b").alias("src"), "w"), meta)
    raise MatrixError(f"unknown storage {storage}")
