"""Scans, matrix file formats, sinks and generated matrices."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..types import GraphMatrix, MatrixError, MatrixMeta


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_dense_text(spark: SparkSession, path: str, sep: str = ",") -> DataFrame:
    """line, cells: rows of a delimited text file as arrays of strings, for `ingest.detect_text`."""
    return spark.read.text(path).where(F.trim("value") != "").select(F.split(F.trim("value"), sep).alias("cells"))


def read_coordinate(spark: SparkSession, path: str) -> GraphMatrix:
    """Coordinate exchange format: a %% banner, % comments, a size line, then 1-based "row column value" lines. `path` may be
    a folder of parts; the size line is the first one after the banner in its file."""
    lines = spark.read.text(path).where(F.trim("value") != "").select(F.trim("value").alias("v"), F.input_file_name().alias("f"), F.monotonically_increasing_id().alias("i"))
    banner = lines.where(F.startswith("v", F.lit("%%"))).orderBy("f", "i").first()
    plain = lines.where(~F.startswith("v", F.lit("%")))
    head = banner and plain.where((F.col("f") == banner["f"]) & (F.col("i") > banner["i"])).orderBy("i").first()
    if not head or len(head["v"].split()) < 3:
        raise MatrixError("no banner with a size line")
    rows, cols = map(int, head["v"].split()[:2])
    cells = plain.where((F.col("f") != head["f"]) | (F.col("i") != head["i"])).select(F.split("v", r"\s+").alias("p"))
    at = lambda k: F.element_at("p", k)
    edges = cells.select((at(1).cast("bigint") - 1).alias("dst"), (at(2).cast("bigint") - 1).alias("src"), at(3).cast("double").alias("w"))
    return GraphMatrix(edges, MatrixMeta(rows, cols, "double"))


def write_coordinate(gm: GraphMatrix, path: str) -> None:
    m = gm.meta
    n = gm.edges.count()
    head = gm.spark.range(1).select(F.lit(f"%%MatrixMarket matrix coordinate real general\n{m.n_rows} {m.n_cols} {n}").alias("value"))
    body = gm.edges.select(F.concat_ws(" ", F.col("dst") + 1, F.col("src") + 1, F.col("w").cast("double").cast("string")).alias("value"))
    head.coalesce(1).unionByName(body).write.text(path)


def read_edges(spark: SparkSession, fmt: str, path: str, schema: str = "dst bigint, src bigint, w double", **options) -> DataFrame:
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def write_edges(gm: GraphMatrix, fmt: str, path: str) -> None:
    gm.edges.write.format(fmt).save(path)


def write_graph(gm: GraphMatrix, name: str, buckets: int) -> None:
    """Cached graph: a table bucketed and sorted by source, so that later gathers need no exchange of edges."""
    gm.edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(name)


def generate(spark: SparkSession, kind: str, n: int, seed: int = 1, per_row: int = 4, rows: DataFrame | None = None) -> GraphMatrix:
    """For all of n rows, or those of a table (id): identity, stencil (tridiagonal 2, -1) or random (about per_row hashed columns a row, weights 1 to 9)."""
    ids = (spark.range(n) if rows is None else rows).select(F.col("id").alias("dst"))
    if kind == "identity":
        e = ids.select("dst", F.col("dst").alias("src"), F.lit(1).cast("bigint").alias("w"))
    elif kind == "stencil":
        e = ids.select("dst", F.explode(F.array(*[F.struct((F.col("dst") + d).alias("src"), F.lit(w).cast("bigint").alias("w")) for d, w in ((-1, -1), (0, 2), (1, -1))])).alias("x")).select("dst", "x.*")
        e = e.where((F.col("src") >= 0) & (F.col("src") < n))
    elif kind == "random":
        e = ids.select("dst", F.explode(F.sequence(F.lit(0), F.lit(per_row - 1))).alias("k"))
        e = e.select("dst", F.pmod(F.xxhash64(F.lit(seed), "dst", "k"), F.lit(n)).alias("src"), (F.pmod(F.xxhash64(F.lit(seed + 1), "dst", "k"), F.lit(9)) + 1).alias("w")).groupBy("dst", "src").agg(F.sum("w").alias("w"))
    else:
        raise MatrixError(f"unknown kind {kind}")
    return GraphMatrix(e, MatrixMeta(n, n))
