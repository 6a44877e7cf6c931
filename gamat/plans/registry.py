"""Registry of the engine's queries: name -> callable, and the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..types import GraphMatrix, VertexState

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(*names: str, sql: str | None = None):
    """Register fn(spark, sf_dir) under each name; fn may return a matrix, a state or a DataFrame."""

    def wrap(fn):
        for n in names:
            QUERIES[n] = lambda spark, sf_dir, fn=fn: frame(fn(spark, sf_dir))
            if sql:
                ORACLES[n] = sql
        return fn

    return wrap


def frame(x) -> DataFrame:
    if isinstance(x, GraphMatrix):
        if x.meta.dtype == "complex":
            return x.edges.select("dst", "src", F.col("w")["re"].alias("re"), F.col("w")["im"].alias("im"))
        return x.edges.select("dst", "src", "w")
    if isinstance(x, VertexState):
        return x.df.select("id", "s")
    return x
