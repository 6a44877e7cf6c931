"""The transformer's front: is a dataset a matrix, of which type, and its edges."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..types import GraphMatrix, MatrixMeta
from . import storage

INTEGERS = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)
REALS = (T.FloatType, T.DoubleType, T.DecimalType)


@dataclass(frozen=True)
class Detection:
    """matrix: whether all rows have one length and are numeric; reason: why not."""

    matrix: bool
    rows: int
    width: int | None
    dtype: str | None
    reason: str = ""


def row_lengths(df: DataFrame, column: str) -> DataFrame:
    """n_rows, shortest, longest: one scan."""
    size = F.size(column).cast("bigint")
    return df.agg(F.count("*").alias("n_rows"), F.min(size).alias("shortest"), F.max(size).alias("longest"))


def is_rectangular(df: DataFrame, column: str) -> bool:
    r = row_lengths(df, column).first()
    return r["n_rows"] > 0 and r["shortest"] == r["longest"]


def numeric_type(df: DataFrame, column: str) -> str | None:
    """bigint, double or None, from the schema alone."""
    t = df.schema[column].dataType
    t = t.elementType if isinstance(t, T.ArrayType) else t
    return "bigint" if isinstance(t, INTEGERS) else "double" if isinstance(t, REALS) else None


def text_type(df: DataFrame, column: str) -> DataFrame:
    """n_cells, integers, numbers: how many cells of an array<string> column read as such; one scan."""
    cells = df.select(F.explode(column).alias("c"))
    return cells.agg(F.count("*").alias("n_cells"), F.count_if(F.expr("try_cast(trim(c) as bigint)").isNotNull()).alias("integers"), F.count_if(F.expr("try_cast(trim(c) as double)").isNotNull()).alias("numbers"))


def detect(df: DataFrame, column: str) -> Detection:
    """Is the array column a matrix, row by row?"""
    r = row_lengths(df, column).first()
    n, a, b = r["n_rows"], r["shortest"], r["longest"]
    if not n:
        return Detection(False, 0, None, None, "no rows")
    if a != b:
        return Detection(False, n, None, None, f"rows of {a} to {b} elements")
    kind = numeric_type(df, column)
    if kind is None and isinstance(df.schema[column].dataType, T.ArrayType) and isinstance(df.schema[column].dataType.elementType, T.StringType):
        t = text_type(df, column).first()
        kind = "bigint" if t["integers"] == t["n_cells"] else "double" if t["numbers"] == t["n_cells"] else None
    if kind is None:
        return Detection(False, n, b, None, "elements are not numeric")
    return Detection(True, n, b, kind)


def to_graph(df: DataFrame, row: str, column: str, detection: Detection | None = None) -> GraphMatrix:
    """Non-zero elements of dense rows as edges."""
    d = detection or detect(df, column)
    if not d.matrix:
        raise ValueError(f"not a matrix: {d.reason}")
    rows = df.select(F.col(row).alias("dst"), F.transform(column, lambda x: x.cast(d.dtype)).alias("v"))
    return storage.expand(rows, "dense_rows", d.rows, d.width)


def from_wide(df: DataFrame, row: str, columns: list[str]) -> GraphMatrix:
    """Wide numeric columns -> edges; column number = position in `columns`."""
    cells = F.array(*[F.struct(F.lit(j).cast("bigint").alias("src"), F.col(c).alias("w")) for j, c in enumerate(columns)])
    e = df.select(F.col(row).alias("dst"), F.explode(cells).alias("x")).select("dst", "x.*").where("w <> 0")
    return GraphMatrix(e, MatrixMeta(df.count(), len(columns)))


def to_wide(gm: GraphMatrix, columns: list[int]) -> DataFrame:
    out = gm.edges.groupBy("dst").pivot("src", columns).agg(F.sum("w"))
    return out.select("dst", *[F.coalesce(F.col(str(c)), F.lit(0)).alias(f"c{c}") for c in columns])


def json_weight(column: str, path: str) -> Column:
    return F.get_json_object(column, path).cast("bigint")


def from_table(df: DataFrame, dst: str, src: str, weight: Column, n_rows: int, n_cols: int, sum_parallel: bool = True) -> GraphMatrix:
    """Edges from a fact table. Parallel edges need no early sum where a linear operation follows."""
    e = df.select(F.col(dst).alias("dst"), F.col(src).alias("src"), weight.alias("w"))
    gm = GraphMatrix(e, MatrixMeta(n_rows, n_cols))
    return gm.summed() if sum_parallel else gm
