"""Characteristics of a matrix: what the mapper decides on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..types import GraphMatrix


def profile(gm: GraphMatrix) -> DataFrame:
    """One row: n_rows, n_cols, nnz, max_row_deg, max_col_deg, lower/upper violations, bandwidths, asymmetric cells.

    Three folds: everything but the other side's degrees per row and then over the rows, the degrees of the columns, and
    the cells of equal weight at both sides of the diagonal, so that no cell travels more than once per fold."""
    m = gm.meta
    e = gm.edges
    by_row = e.groupBy("dst").agg(
        F.count("*").alias("d"),
        F.count_if(F.col("src") > F.col("dst")).alias("above"),
        F.count_if(F.col("src") < F.col("dst")).alias("below"),
        F.max(F.col("dst") - F.col("src")).alias("kl"),
        F.max(F.col("src") - F.col("dst")).alias("ku"),
    )
    total = lambda c: F.coalesce(F.sum(c), F.lit(0))
    most = lambda c: F.coalesce(F.max(c), F.lit(0))
    base = by_row.agg(total("d").alias("nnz"), most("d").alias("max_row_deg"), total("above").alias("above"), total("below").alias("below"), most("kl").alias("kl"), most("ku").alias("ku"))
    cols = e.groupBy("src").agg(F.count("*").alias("d")).agg(most("d").alias("max_col_deg"))
    odd = odd_cells(gm)
    one = base.crossJoin(F.broadcast(cols)).crossJoin(F.broadcast(odd))
    return one.select(F.lit(m.n_rows).cast("bigint").alias("n_rows"), F.lit(m.n_cols).cast("bigint").alias("n_cols"), "nnz", "max_row_deg", "max_col_deg", "above", "below", "kl", "ku", "asymmetric")


def odd_cells(gm: GraphMatrix) -> DataFrame:
    """asymmetric: how many rows `asymmetric` has, from one fold over (smaller id, larger id, weight)."""
    low, high = F.least("dst", "src").alias("low"), F.greatest("dst", "src").alias("high")
    e = gm.edges.where("dst <> src or w is null").select(low, high, "w", (F.col("src") < F.col("dst")).cast("int").alias("below"))
    both = e.groupBy("low", "high", "w").agg(F.count("*").alias("n"), F.sum("below").alias("below"))
    # Null weights have no twin; on the diagonal a cell is its own.
    alone = F.when(F.col("w").isNull() | (F.col("below") == 0) | (F.col("below") == F.col("n")), F.col("n")).otherwise(0)
    return both.agg(F.coalesce(F.sum(alone), F.lit(0)).alias("asymmetric"))


def asymmetric(gm: GraphMatrix) -> DataFrame:
    """Cells without a twin of equal weight."""
    twin = gm.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    return gm.edges.join(twin, ["dst", "src", "w"], "left_anti")


def structures(row) -> set[str]:
    out = set()
    if row["n_rows"] == row["n_cols"] and row["asymmetric"] == 0:
        out.add("symmetric")
    if row["above"] == 0 or row["below"] == 0:
        out.add("triangular")
    if row["kl"] + row["ku"] + 1 < max(4, min(row["n_rows"], row["n_cols"]) // 4):
        out.add("banded")
    return out or {"general"}


def vector(row, op: str, platform: str = "jvm") -> dict[str, float]:
    """Numbers for the tree, from a profile row."""
    cells = max(1, row["n_rows"] * row["n_cols"])
    mean = max(1e-9, row["nnz"] / max(1, row["n_rows"]))
    s = structures(row)
    log = lambda x: float(len(str(max(1, int(x)))))
    out = {"log_rows": log(row["n_rows"]), "log_cols": log(row["n_cols"]), "log_nnz": log(row["nnz"]), "density": row["nnz"] / cells, "row_skew": row["max_row_deg"] / mean, "col_skew": row["max_col_deg"] / max(1e-9, row["nnz"] / max(1, row["n_cols"]))}
    out |= {f"is_{k}": float(k in s) for k in ("symmetric", "triangular", "banded")}
    out |= {f"op_{k}": float(k == op) for k in ("add", "mv", "mm", "rank", "solve", "chain")}
    return out | {f"on_{k}": float(k == platform) for k in ("jvm", "arrow", "hybrid")}


def degrees(gm: GraphMatrix, side: str = "dst") -> DataFrame:
    return gm.edges.groupBy(F.col(side).alias("id")).agg(F.count("*").alias("degree"), F.count_distinct("src" if side == "dst" else "dst").alias("neighbours"))


def hubs(gm: GraphMatrix, cap: int = 10, side: str = "dst") -> DataFrame:
    return gm.edges.groupBy(F.col(side).alias("id")).agg(F.count("*").alias("degree")).where(F.col("degree") > cap)


def degree_hist(gm: GraphMatrix, side: str = "dst") -> DataFrame:
    return gm.edges.groupBy(side).agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n"))


def norms(gm: GraphMatrix) -> DataFrame:
    """nnz, trace, frob2 (squared Frobenius), max_abs, norm1 (largest column sum of magnitudes), norminf (row)."""
    e = gm.edges
    base = e.agg(F.count("*").alias("nnz"), F.sum(F.when(F.col("dst") == F.col("src"), F.col("w")).otherwise(0)).alias("trace"), F.sum(F.col("w") * F.col("w")).alias("frob2"), F.max(F.abs("w")).alias("max_abs"))
    one = e.groupBy("src").agg(F.sum(F.abs("w")).alias("s")).agg(F.max("s").alias("norm1"))
    inf = e.groupBy("dst").agg(F.sum(F.abs("w")).alias("s")).agg(F.max("s").alias("norminf"))
    return base.crossJoin(F.broadcast(one)).crossJoin(F.broadcast(inf))
