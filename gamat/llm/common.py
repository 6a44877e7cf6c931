"""Helpers shared by the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import sys
import types
import uuid

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from ..sources.shared import shared_folder


#: Bytes that go to or from a Python worker at a time, but for single rows that are larger.
BATCH = 4 << 20
BATCH_CONF = "spark.sql.execution.arrow.maxBytesPerBatch"


@contextlib.contextmanager
def small_batches(spark: SparkSession):
    """Actions inside send rows to Python workers in batches of about BATCH bytes.

    A batch is built outside of the JVM's heap, in buffers that double as they grow: one of Spark's 64 MB takes up to three
    times that in each task, and the C library keeps much of it for good."""
    usual = spark.conf.get(BATCH_CONF)
    if spark.sparkContext._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(usual) > BATCH:
        spark.conf.set(BATCH_CONF, str(BATCH))
    try:
        yield
    finally:
        spark.conf.set(BATCH_CONF, usual)


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage: write df as Parquet into the shared folder and read it again.

    The written table survives lost executors; it is replaced by nothing and read at any later time."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/gamat-{uuid.uuid4().hex}"
    # Its buffers are on the heap; those of the default codec stay outside of it until they are collected.
    with small_batches(spark):
        df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(*tables: DataFrame) -> None:
    """Delete tables written by `cut` once everything made of them has been written itself."""
    for df in tables:
        spark = df.sparkSession
        for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            if "/gamat-" in name:
                path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(name)
                path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bounded(df: DataFrame, limit: int) -> tuple[DataFrame, bool]:
    """(df cut off from its lineage, whether it has at most `limit` rows and so may be broadcast)."""
    df = cut(df)
    return df, df.count() <= limit


def join_small(left: DataFrame, right: DataFrame, on, how: str, limit: int) -> DataFrame:
    """Join that broadcasts `right` only if it is counted to have at most `limit` rows; else both sides shuffle."""
    right, small = bounded(right, limit)
    return left.join(F.broadcast(right) if small else right, on, how)


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def worker_store() -> dict:
    """What a Python worker keeps from one task to the next. Functions that travel to workers bring their own globals, so it
    hangs on a module of its own."""
    name = "_gamat_worker"
    if name not in sys.modules:
        sys.modules[name] = types.ModuleType(name)
        sys.modules[name].kept = {}
    return sys.modules[name].kept


def give_back() -> None:
    """Return freed memory to the system: a worker lives on after its task, and what Arrow's pool and the C library hold back
    for it would count beside the next task of the other workers."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # a C library without it
        ctypes.CDLL(None).malloc_trim(0)


def map_slices(df: DataFrame, fn, schema: str, rows: int = 512, keeps: str = "", weight: int = BATCH) -> DataFrame:
    """Like mapInPandas, but fn sees frames of at most `rows` rows and, but for single rows that are larger, `weight` bytes,
    whatever the size of the batches that arrive: only that much text is Python strings at a time. What fn gives goes back in
    batches of about `weight` bytes too. Integer columns keep nulls and all their digits. What earlier operators left in the
    worker is freed, but for the entry named `keeps`."""
    target = to_arrow_schema(StructType.fromDDL(schema))
    names = df.columns

    def run(batches):
        store = worker_store()
        for k in [k for k in store if k != keeps]:
            del store[k]

        def small():
            for b in batches:
                at = 0
                while at < b.num_rows:
                    n = rows
                    while n > 1 and b.slice(at, n).nbytes > weight:
                        n //= 2
                    part = b.slice(at, n).to_pandas(types_mapper={pa.int64(): pd.Int64Dtype(), pa.int32(): pd.Int32Dtype()}.get)
                    part.columns = names
                    at += n
                    yield part

        try:
            for out in fn(small()):
                if len(out):
                    made = pa.RecordBatch.from_pandas(out, schema=target, preserve_index=False)
                    n = max(1, made.num_rows * weight // max(weight, made.nbytes))
                    for at in range(0, made.num_rows, n):
                        yield made.slice(at, n)
        finally:
            out = made = None
            give_back()

    return df.mapInArrow(run, schema)
