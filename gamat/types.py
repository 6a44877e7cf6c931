"""Data model: matrices as edge sets, vectors as vertex states."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

STRUCTURES = {"general", "symmetric", "triangular", "banded", "packed", "hermitian"}


class MatrixError(ValueError):
    """Input that is no valid matrix for the operation asked for."""


@dataclass(frozen=True)
class MatrixMeta:
    """What is known about a matrix without reading it again."""

    n_rows: int
    n_cols: int
    dtype: str = "bigint"
    storage: str = "coo"
    uplo: str | None = None
    unit: bool = False
    kl: int | None = None
    ku: int | None = None
    structure: frozenset[str] = frozenset({"general"})
    nnz: int | None = None

    @property
    def n_vertices(self) -> int:
        return max(self.n_rows, self.n_cols)


@dataclass(frozen=True)
class GraphMatrix:
    """Edges (dst = row, src = column, w = weight; complex weights are struct<re, im>) with their metadata."""

    edges: DataFrame
    meta: MatrixMeta
    #: src of the sources with many edges, where a cached graph has counted them.
    hubs: DataFrame | None = field(default=None, compare=False)

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @property
    def T(self) -> GraphMatrix:  # noqa: N802
        """Transposed view: no data moves."""
        m = self.meta
        flip = {"L": "U", "U": "L", None: None}[m.uplo]
        return GraphMatrix(self.edges.select(F.col("src").alias("dst"), F.col("dst").alias("src"), "w"), replace(m, n_rows=m.n_cols, n_cols=m.n_rows, uplo=flip, kl=m.ku, ku=m.kl))

    def with_edges(self, edges: DataFrame, **meta) -> GraphMatrix:
        return GraphMatrix(edges.select("dst", "src", "w"), replace(self.meta, **{"nnz": None, **meta}))

    def vertices(self) -> DataFrame:
        """The vertex set: as many vertices as the larger side of the matrix."""
        return self.spark.range(self.meta.n_vertices)

    def rows(self) -> DataFrame:
        return self.spark.range(self.meta.n_rows)

    def compact(self) -> GraphMatrix:
        """Without explicit zeros."""
        return self.with_edges(self.edges.where(F.col("w") != 0))

    def summed(self) -> GraphMatrix:
        """Parallel edges added up."""
        return self.with_edges(self.edges.groupBy("dst", "src").agg(F.sum("w").alias("w")))

    def where(self, condition) -> GraphMatrix:
        return self.with_edges(self.edges.where(condition))

    def map_weights(self, expression) -> GraphMatrix:
        return self.with_edges(self.edges.select("dst", "src", expression.alias("w")))

    def tril(self, k: int = 0) -> GraphMatrix:
        return self.with_edges(self.edges.where(F.col("src") - F.col("dst") <= k), uplo="L")

    def triu(self, k: int = 0) -> GraphMatrix:
        return self.with_edges(self.edges.where(F.col("src") - F.col("dst") >= k), uplo="U")

    def slice(self, rows: tuple[int, int], cols: tuple[int, int]) -> GraphMatrix:
        """Half-open row and column ranges, renumbered from 0; the predicates reach the scan."""
        e = self.edges.where((F.col("dst") >= rows[0]) & (F.col("dst") < rows[1]) & (F.col("src") >= cols[0]) & (F.col("src") < cols[1]))
        return self.with_edges(e.select((F.col("dst") - rows[0]).alias("dst"), (F.col("src") - cols[0]).alias("src"), "w"), n_rows=rows[1] - rows[0], n_cols=cols[1] - cols[0])

    def sample(self, per_mille: int, seed: int = 7) -> GraphMatrix:
        """Seeded, repeatable sample of the edges, by hash."""
        return self.where(F.pmod(F.xxhash64(F.lit(seed), "dst", "src"), F.lit(1000)) < per_mille)

    def to_rows(self) -> DataFrame:
        """Back to dense rows: dst, v (zeros filled in)."""
        width = self.meta.n_cols
        cells = self.edges.groupBy("dst").agg(F.map_from_entries(F.collect_list(F.struct("src", "w"))).alias("m"))
        zero = F.lit(0).cast(dict(self.edges.dtypes)["w"])
        return cells.select("dst", F.transform(F.sequence(F.lit(0).cast("bigint"), F.lit(width - 1).cast("bigint")), lambda j: F.coalesce(F.element_at("m", j), zero)).alias("v"))

    def validate(self) -> GraphMatrix:
        """Raise MatrixError on null ids or weights, or ids outside the matrix (one scan)."""
        m = self.meta
        bad = self.edges.agg(
            F.count_if(F.col("dst").isNull() | F.col("src").isNull() | F.col("w").isNull()).alias("nulls"),
            F.count_if((F.col("dst") < 0) | (F.col("dst") >= m.n_rows) | (F.col("src") < 0) | (F.col("src") >= m.n_cols)).alias("outside"),
        ).first()
        if bad["nulls"] or bad["outside"]:
            raise MatrixError(f"{bad['nulls']} cells with nulls, {bad['outside']} outside {m.n_rows} x {m.n_cols}")
        return self


@dataclass(frozen=True)
class VertexState:
    """Vertex states (id, s); a missing id counts as zero."""

    df: DataFrame
    n: int

    @classmethod
    def of(cls, df: DataFrame, id_: str, value, n: int) -> VertexState:
        return cls(df.select(F.col(id_).cast("bigint").alias("id"), (F.col(value) if isinstance(value, str) else value).alias("s")), n)


@dataclass(frozen=True)
class Strategy:
    """How a superstep runs. Names of `catalogue` entries are what the mapper's tree predicts."""

    unit: str = "vertex"  # vertex | edge
    direction: str = "pull"  # pull | push
    join: str = "auto"  # auto | broadcast | merge | shuffle_hash
    merge: bool = True  # fold before sending
    split_cap: int | None = None
    split_mode: str = "hash"  # strict | hash
    hub_broadcast: int = 0  # sources with more edges than this are replicated to all executors
    bucket: int | None = None
    reorder: str = "none"  # none | lpa | rcm
    backend: str = "S"  # S | B | V | hybrid
    name: str = field(default="default", compare=False)


CATALOGUE: dict[str, Strategy] = {
    s.name: s
    for s in (
        Strategy(name="small", join="broadcast"),
        Strategy(name="edge_merge", unit="edge"),
        Strategy(name="vertex_pull", join="merge"),
        Strategy(name="split", split_cap=10, split_mode="strict"),
        Strategy(name="hub", hub_broadcast=64),
        Strategy(name="irregular", reorder="lpa", hub_broadcast=64, split_cap=10),
        Strategy(name="dense_block", backend="B", bucket=256),
        Strategy(name="hybrid", backend="hybrid", bucket=64),
        Strategy(name="vertex_program", backend="V", direction="push"),
        Strategy(name="bucketed", bucket=64),
        Strategy(name="coarse", merge=False),
    )
}
#: Largest state (rows of 16 bytes) that a strategy may broadcast; above it the state is shuffled whatever the strategy says.
BROADCAST_ROWS = 4_000_000
