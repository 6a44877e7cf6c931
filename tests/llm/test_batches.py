"""What travels between the JVM and its Python workers at a time."""

import pandas as pd
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from gamat.llm import common


def test_cut_sends_small_batches_and_puts_the_setting_back(spark):
    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_pydict({"n": [b.num_rows], "size": [b.nbytes]})

    texts = spark.range(0, 4000, 1, 1).select(F.repeat(F.lit("x"), 5000).alias("text"))
    before = spark.conf.get(common.BATCH_CONF)
    seen = common.cut(texts.mapInArrow(sizes, "n long, size long")).collect()
    assert sum(r["n"] for r in seen) == 4000
    assert max(r["size"] for r in seen) < 1.1 * common.BATCH, seen
    assert spark.conf.get(common.BATCH_CONF) == before
    with pytest.raises(ZeroDivisionError), common.small_batches(spark):
        raise ZeroDivisionError
    assert spark.conf.get(common.BATCH_CONF) == before


def test_a_smaller_setting_stays(spark):
    before = spark.conf.get(common.BATCH_CONF)
    spark.conf.set(common.BATCH_CONF, "1m")
    try:
        with common.small_batches(spark):
            assert spark.conf.get(common.BATCH_CONF) in ("1m", str(1 << 20) + "b")
    finally:
        spark.conf.set(common.BATCH_CONF, before)


class Caught:
    """Stands for a data frame; keeps the function that would travel to the workers."""

    columns = ["k"]

    def mapInArrow(self, run, schema):
        return run


def test_slices_give_all_rows_in_small_batches_and_free_memory(spark, monkeypatch):
    freed, n = [], 1_000_000
    monkeypatch.setattr(common, "give_back", lambda: freed.append(1))
    run = common.map_slices(Caught(), lambda parts: iter([pd.DataFrame({"k": range(n)}) for _ in parts]), "k long")
    out = list(run(iter([pa.RecordBatch.from_pydict({"k": [1, 2]})])))
    assert [k for b in out for k in b.column(0).to_pylist()] == list(range(n))
    assert max(b.nbytes for b in out) <= common.BATCH
    assert freed == [1]
