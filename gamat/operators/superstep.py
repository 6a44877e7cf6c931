"""The two user functions, gather and apply, and the superstep that runs them.

gather(w, s_src, s_dst) -> Column is evaluated per edge; apply is split into `combine` (an aggregate that commutes and
associates, so Spark folds before it sends) and `finalize` (per vertex)."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.shared import reliable
from ..types import BROADCAST_ROWS, GraphMatrix, MatrixError, Strategy, VertexState
from . import balance


@dataclass(frozen=True)
class Semiring:
    """times(w, s) per edge, plus as an aggregate, and what a vertex without edges has."""

    times: Callable[[Column, Column], Column]
    plus: Callable[[Column], Column]
    zero: object = 0


PLUS_TIMES = Semiring(lambda w, s: w * s, F.sum, 0)
MIN_PLUS = Semiring(lambda w, s: w + s, F.min, None)
MAX_MIN = Semiring(lambda w, s: F.least(w, s), F.max, None)
OR_AND = Semiring(lambda w, s: (w != 0) & s, F.bool_or, False)
COUNT = Semiring(lambda w, s: F.lit(1), F.count, 0)


def hinted(right: DataFrame, strategy: Strategy, rows: int) -> DataFrame:
    """The state side of the join; a broadcast is only asked for below the row bound."""
    if strategy.join == "broadcast" and rows <= BROADCAST_ROWS:
        return F.broadcast(right)
    if strategy.join == "merge":
        return right.hint("merge")
    if strategy.join == "shuffle_hash":
        return right.hint("shuffle_hash")
    return right


def gather(gm: GraphMatrix, state: VertexState, fn=PLUS_TIMES.times, own: VertexState | None = None, strategy: Strategy = Strategy(), keep: list[str] = ()) -> DataFrame:
    """dst, v (and the `keep` columns of the edges): one contribution per edge."""
    e = gm.edges
    s = state.df.select(F.col("id").alias("src"), F.col("s").alias("s_src"))
    if strategy.hub_broadcast:
        both = hub_join(e, s, strategy, gm.hubs)
    elif strategy.direction == "push":
        both = s.join(e, "src")
    else:
        both = e.join(hinted(s, strategy, state.n), "src")
    s_dst: Column = F.lit(None)
    if own is not None:
        both = both.join(hinted(own.df.select(F.col("id").alias("dst"), F.col("s").alias("s_dst")), strategy, own.n), "dst", "left")
        s_dst = F.col("s_dst")
    value = fn(F.col("w"), F.col("s_src"), s_dst) if fn.__code__.co_argcount == 3 else fn(F.col("w"), F.col("s_src"))
    return both.select("dst", "src", *keep, value.alias("v"))


def find_hubs(edges: DataFrame, degree: int) -> DataFrame:
    """src: sources with more edges than `degree`, at most BROADCAST_ROWS of them (the rest are no hubs)."""
    degrees = edges.groupBy("src").agg(F.count("*").alias("d")).where(F.col("d") > degree)
    return degrees.orderBy(F.desc("d"), "src").limit(BROADCAST_ROWS).select("src")


def hub_join(edges: DataFrame, s: DataFrame, strategy: Strategy, hubs: DataFrame | None = None) -> DataFrame:
    """States of sources with many edges go to every executor, the others meet their edges in a shuffle.

    hubs: what the cached graph knows of them; else they are counted here. Edges of hubs are told by the state they find."""
    hubs = find_hubs(edges, strategy.hub_broadcast) if hubs is None else hubs
    near = F.broadcast(s.join(F.broadcast(hubs), "src", "left_semi").withColumn("hub", F.lit(True)))
    marked = edges.join(near, "src", "left")
    cols = [*edges.columns, "s_src"]
    far = marked.where("hub is null").select(*edges.columns).join(s.hint("merge"), "src")
    return marked.where("hub").select(*cols).unionByName(far.select(*cols))


def slots(edges: DataFrame, cap: int, mode: str = "strict", bucket: int = 4096) -> DataFrame:
    """edges with `slot`: which sub-vertex of dst an edge belongs to.

    strict: at most `cap` edges per slot, and only the last slot is not full. Positions come from counts per bucket of
    src and ranks inside one, so no window holds more than a bucket of one vertex. hash: about cap edges, no sort."""
    if mode == "hash":
        degrees = edges.groupBy("dst").agg(F.ceil(F.count("*") / cap).alias("slots"))
        return edges.join(degrees, "dst").withColumn("slot", F.pmod(F.xxhash64("src"), F.col("slots"))).drop("slots")
    e = edges.withColumn("b", F.floor(F.col("src") / bucket))
    counts = e.groupBy("dst", "b").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("dst").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    e = e.join(counts.select("dst", "b", before.alias("base")), ["dst", "b"])
    rank = F.row_number().over(Window.partitionBy("dst", "b").orderBy("src"))
    return e.withColumn("slot", F.floor((F.col("base") + rank - 1) / cap)).drop("b", "base")


def apply(contributions: DataFrame, combine=F.sum, finalize=None, strategy: Strategy = Strategy(), total: DataFrame | None = None, default=0) -> DataFrame:
    """id, s: contributions (dst, v) folded per vertex. `total`: ids that must all occur, with `default` where nothing came."""
    if strategy.split_cap:
        sub = slots(contributions, strategy.split_cap, strategy.split_mode)
        contributions = sub.groupBy("dst", "slot").agg(combine("v").alias("v")).drop("slot")
    elif strategy.unit == "edge":
        # Edges first fold where they are dealt by their source, then per vertex.
        contributions = contributions.groupBy("dst", F.pmod(F.xxhash64("src"), F.lit(16)).alias("part")).agg(combine("v").alias("v")).drop("part")
    elif not strategy.merge:
        parts = int(contributions.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        contributions = contributions.repartition(parts, "dst")
    out = contributions.groupBy(F.col("dst").alias("id")).agg(combine("v").alias("s"))
    if total is not None:
        out = total.select("id").join(out, "id", "left").select("id", F.coalesce("s", F.lit(default)).alias("s"))
    return out.select("id", finalize(F.col("s")).alias("s")) if finalize else out


def bucketed(gm: GraphMatrix, state: VertexState, size: int, fn=PLUS_TIMES.times) -> DataFrame:
    """Updates of `size` consecutive vertices fold where they arise and travel as one row of sums without ids: the only
    exchange is by bucket, and a bucket's final fold is one task's, as a core owns its buckets.

    For numeric states and sums."""
    position = F.col("dst") % size
    sums = [F.sum(F.when(position == i, F.col("v"))).alias(f"p{i}") for i in range(size)]
    packed = gather(gm, state, fn).groupBy(F.floor(F.col("dst") / size).alias("bucket")).agg(*sums)
    dense = packed.select("bucket", F.posexplode(F.array(*[F.col(f"p{i}") for i in range(size)])).alias("i", "s"))
    return dense.where("s is not null").select((F.col("bucket") * size + F.col("i")).alias("id"), "s")


def migrated(gm: GraphMatrix, state: VertexState, size: int, parts: int, start=None, fn=PLUS_TIMES.times, seconds_per_unit: float = 1e-6, seconds_per_byte: float = 1e-9) -> tuple[VertexState, tuple[dict, dict]]:
    """A superstep after load migration, and the loads (edges) per part before and after.

    Buckets of `size` rows lie on parts (start: bucket -> part; at first, in turn) and move while the time that a move saves
    exceeds its transfer. What is collected is one count per bucket; the contributions then go straight to the parts."""
    start = start or (lambda bucket: bucket % parts)
    bucket = F.floor(F.col("dst") / size).cast("bigint")
    if gm.meta.n_rows // size > BROADCAST_ROWS:
        raise MatrixError(f"{gm.meta.n_rows // size} buckets; take a larger size")
    counts = {r["bucket"]: r["n"] for r in gm.edges.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n")).collect()}
    loads: dict[int, dict[int, float]] = {p: {} for p in range(parts)}
    for b, n in sorted(counts.items()):
        loads[start(b)][b] = float(n)
    before = {p: sum(own.values()) for p, own in loads.items()}
    home = {b: p for p, own in loads.items() for b in own}
    for m in balance.plan(loads, seconds_per_unit, seconds_per_byte):
        home[m.bucket] = m.target
    after = dict.fromkeys(range(parts), 0.0)
    for b, p in home.items():
        after[p] += counts[b]
    homes = F.broadcast(gm.spark.createDataFrame(sorted(home.items()), "bucket bigint, part int"))
    sent = gather(gm, state, fn).withColumn("bucket", bucket).join(homes, "bucket").repartitionById(parts, F.col("part"))
    out = sent.groupBy("part", F.col("dst").alias("id")).agg(F.sum("v").alias("s")).select("id", "s")
    return VertexState(out, gm.meta.n_rows), (before, after)


def gather_apply(gm: GraphMatrix, state: VertexState, fn=PLUS_TIMES.times, combine=F.sum, finalize=None, own: VertexState | None = None, strategy: Strategy = Strategy(), total: bool = False, default=0) -> VertexState:
    """One superstep: new states of the row vertices."""
    if strategy.bucket and strategy.backend == "S":
        out = bucketed(gm, state, strategy.bucket, fn)
        return VertexState(out, gm.meta.n_rows)
    contributions = gather(gm, state, fn, own, strategy)
    out = apply(contributions, combine, finalize, strategy, gm.rows() if total else None, default)
    return VertexState(out, gm.meta.n_rows)


def apply_bag(contributions: DataFrame, fold) -> DataFrame:
    """The literal reading of apply: `fold` sees the whole bag of a vertex as an array. Slow path, no early folding."""
    bag = contributions.groupBy(F.col("dst").alias("id")).agg(F.collect_list("v").alias("bag"))
    return bag.select("id", fold(F.col("bag")).alias("s"))


def gather_edges(graphs: list[GraphMatrix]) -> DataFrame:
    """Edge-centric gather over several graphs: all their weights, by edge."""
    out = graphs[0].edges
    for g in graphs[1:]:
        out = out.unionByName(g.edges)
    return out


def apply_edges(bag: DataFrame, combine=F.sum) -> DataFrame:
    return bag.groupBy("dst", "src").agg(combine("w").alias("w"))


def iterate(step, state: VertexState, times: int, tol: float | None = None, checkpoint_every: int = 5) -> VertexState:
    """state = step(state), `times` times, or until no state moves by more than tol. Lineage is cut by checkpoints."""
    for i in range(times):
        new = step(state)
        if tol is not None or (i + 1) % checkpoint_every == 0:
            new = VertexState(reliable(new.df), new.n)
        if tol is not None:
            gap = new.df.join(state.df.select("id", F.col("s").alias("old")), "id", "left").agg(F.max(F.abs(F.col("s") - F.coalesce("old", F.lit(0))))).first()[0]
            if gap is None or gap <= tol:
                return new
        state = new
    return state
