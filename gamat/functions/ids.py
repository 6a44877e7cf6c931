"""Vertex ids: encoding of strings, dates as indices, prefix sums without a one-partition window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def day_index(ts, origin: str) -> Column:
    return F.datediff(F.to_date(ts), F.lit(origin).cast("date")).cast("bigint")


def hour_index(ts, origin: str) -> Column:
    seconds = F.unix_timestamp(F.col(ts).cast("timestamp") if isinstance(ts, str) else ts.cast("timestamp")) - F.unix_timestamp(F.lit(origin).cast("timestamp"))
    return F.floor(seconds / 3600).cast("bigint")


def prefix_sum(df: DataFrame, key: str, value: str, bucket: Column, name: str = "before") -> DataFrame:
    """df with the sum of `value` over all smaller keys. `bucket` must rise with the key; one row per bucket is sorted
    in a single place, everything else inside its bucket."""
    d = df.withColumn("__b", bucket)
    sums = d.groupBy("__b").agg(F.sum(value).alias("__v"))
    base = F.coalesce(F.sum("__v").over(Window.orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    d = d.join(sums.select("__b", base.alias("__base")), "__b")
    local = F.coalesce(F.sum(value).over(Window.partitionBy("__b").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return d.withColumn(name, (F.col("__base") + local).cast("bigint")).drop("__b", "__base")


def encode(df: DataFrame, column: str, buckets: int = 64) -> DataFrame:
    """column, id: dense ids 0.. of the different values, in hash order, without a global sort."""
    values = df.select(column).where(F.col(column).isNotNull()).distinct().withColumn("h", F.crc32(F.col(column).cast("binary")))
    out = values.withColumn("one", F.lit(1)).withColumn("k", F.struct("h", column))
    return prefix_sum(out, "k", "one", F.floor(F.col("h") * buckets / 2**32), "id").select(column, "id")


def hash_id(column: str) -> Column:
    return F.xxhash64(column)
