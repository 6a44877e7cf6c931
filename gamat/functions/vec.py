"""Vector helpers on vertex states (id, s), and array and map forms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.shared import reliable
from ..types import VertexState


def dot(x: VertexState, y: VertexState) -> DataFrame:
    return x.df.join(y.df.select("id", F.col("s").alias("t")), "id").agg(F.sum(F.col("s") * F.col("t")).alias("dot"))


def sums(x: VertexState) -> DataFrame:
    """nrm2sq (squared 2-norm) and asum (1-norm)."""
    return x.df.agg(F.sum(F.col("s") * F.col("s")).alias("nrm2sq"), F.sum(F.abs("s")).alias("asum"))


def iamax(x: VertexState) -> DataFrame:
    """id of the entry of largest magnitude; the smallest id among equals."""
    return x.df.agg(F.max(F.struct(F.abs("s").alias("a"), (-F.col("id")).alias("i"))).alias("m")).select((-F.col("m.i")).alias("id"), F.col("m.a").alias("s"))


def axpy(alpha, x: VertexState, y: VertexState) -> VertexState:
    """alpha x + y"""
    both = x.df.select("id", (F.lit(alpha) * F.col("s")).alias("s")).unionByName(y.df)
    return VertexState(both.groupBy("id").agg(F.sum("s").alias("s")), max(x.n, y.n))


def scal(alpha, x: VertexState) -> VertexState:
    return VertexState(x.df.select("id", (F.lit(alpha) * F.col("s")).alias("s")), x.n)


def narrowed(x: VertexState) -> VertexState:
    """Whole numbers of up to 38 digits as bigint if all of them fit, else as they are."""
    df = reliable(x.df)
    most = df.agg(F.max(F.abs("s"))).first()[0]
    return VertexState(df if most is not None and most >= 2**63 else df.select("id", F.col("s").cast("bigint").alias("s")), x.n)


def swap(x: VertexState, y: VertexState) -> tuple[VertexState, VertexState]:
    return y, x


def array_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("bigint"), lambda t, v: t + v)


def map_add(a: Column, b: Column) -> Column:
    """Sum of two sparse rows kept as maps."""
    return F.map_zip_with(a, b, lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))


def top_k(x: VertexState, k: int) -> DataFrame:
    return x.df.orderBy(F.desc("s"), "id").limit(k)
