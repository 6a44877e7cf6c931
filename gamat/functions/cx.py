"""Complex numbers as struct<re, im> columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def cx(re: Column, im: Column) -> Column:
    return F.struct(re.alias("re"), im.alias("im"))


def mul(a: Column, b: Column) -> Column:
    return cx(a["re"] * b["re"] - a["im"] * b["im"], a["re"] * b["im"] + a["im"] * b["re"])


def add(a: Column, b: Column) -> Column:
    return cx(a["re"] + b["re"], a["im"] + b["im"])


def conj(a: Column) -> Column:
    return cx(a["re"], -a["im"])


def abs2(a: Column) -> Column:
    return a["re"] * a["re"] + a["im"] * a["im"]


def fold(value: str) -> Column:
    """Sum of complex values, as an aggregate."""
    return cx(F.sum(F.col(value)["re"]), F.sum(F.col(value)["im"]))
