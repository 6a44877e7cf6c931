"""Communities, traversal order, relabelling and partitions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.ids import prefix_sum
from ..sources.shared import reliable
from ..types import GraphMatrix, MatrixError, VertexState


def undirected(gm: GraphMatrix) -> DataFrame:
    """a, b: both directions of the pattern, without loops."""
    e = gm.edges.where("dst <> src")
    return e.select(F.col("dst").alias("a"), F.col("src").alias("b")).unionByName(e.select(F.col("src").alias("a"), F.col("dst").alias("b"))).distinct()


def nodes(gm: GraphMatrix) -> DataFrame:
    return gm.edges.select(F.explode(F.array("dst", "src")).alias("id")).distinct()


def connected(gm: GraphMatrix, most: int = 200) -> DataFrame:
    """id, label: smallest id of the component; labels spread to neighbours and then jump to the label's own label, so that
    rounds grow with the logarithm of the longest path. Raises if labels still move after `most` rounds."""
    n = reliable(undirected(gm))
    label = reliable(nodes(gm).select("id", F.col("id").alias("label")))
    for _ in range(most):
        near = n.join(label.select(F.col("id").alias("b"), "label"), "b").groupBy(F.col("a").alias("id")).agg(F.min("label").alias("m"))
        step = label.join(near, "id", "left").select("id", F.least("label", F.coalesce("m", "label")).alias("label"))
        jump = step.join(step.select(F.col("id").alias("label"), F.col("label").alias("far")), "label", "left")
        new = reliable(jump.select("id", F.coalesce("far", "label").alias("label")))
        moved = new.join(label.select("id", F.col("label").alias("old")), "id").where("label <> old").isEmpty()
        label = new
        if moved:
            return label
    raise MatrixError(f"components still move after {most} rounds")


def label_propagation(gm: GraphMatrix, most: int = 10) -> DataFrame:
    """id, label: all vertices at once take the most frequent label of their neighbours and themselves, the smallest
    among equals; stops when nothing changes."""
    own = nodes(gm)
    n = reliable(undirected(gm).unionByName(own.select(F.col("id").alias("a"), F.col("id").alias("b"))))
    label = reliable(own.select("id", F.col("id").alias("label")))
    for _ in range(most):
        votes = n.join(label.select(F.col("id").alias("b"), "label"), "b").groupBy("a", "label").agg(F.count("*").alias("c"))
        new = reliable(votes.groupBy(F.col("a").alias("id")).agg((-F.max(F.struct("c", (-F.col("label")).alias("m")))["m"]).alias("label")))
        same = new.join(label.select("id", F.col("label").alias("old")), "id").where("label <> old").isEmpty()
        label = new
        if same:
            break
    return label


def depths(gm: GraphMatrix, communities: DataFrame, most: int = 1000) -> DataFrame:
    """id, label, depth, degree: breadth-first from the vertex of highest degree (smallest id) of each community."""
    n = undirected(gm)
    degree = n.groupBy(F.col("a").alias("id")).agg(F.count("*").alias("degree"))
    c = reliable(communities.join(degree, "id", "left").select("id", "label", F.coalesce("degree", F.lit(0)).alias("degree")))
    inside = n.join(c.select(F.col("id").alias("a"), F.col("label").alias("x")), "a").join(c.select(F.col("id").alias("b"), F.col("label").alias("y")), "b").where("x = y").select("a", "b")
    inside = reliable(inside)
    seen = reliable(c.groupBy("label").agg(F.max(F.struct("degree", (-F.col("id")).alias("m"))).alias("r")).select((-F.col("r.m")).alias("id"), F.lit(0).alias("depth")))
    frontier = seen
    for d in range(1, most):
        frontier = reliable(inside.join(frontier.select(F.col("id").alias("a")), "a", "left_semi").select(F.col("b").alias("id")).distinct().join(seen, "id", "left_anti").select("id", F.lit(d).alias("depth")))
        if frontier.isEmpty():
            break
        seen = reliable(seen.unionByName(frontier))
    else:
        raise MatrixError(f"paths of more than {most} steps inside a community")
    # Label propagation may leave parts of a community that its first vertex does not reach: they follow all others.
    return c.join(seen, "id", "left").select("id", "label", F.coalesce("depth", F.lit(most)).alias("depth"), "degree")


def ranges(order: DataFrame, keys: list[Column], per: int = 4096) -> DataFrame:
    """order with k (a struct of the keys) and range: numbers that rise with the keys, for ranges of about `per` rows cut at
    ranks of k, so that one label with most rows is many ranges."""
    parts = int(order.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    o = reliable(order.withColumn("k", F.struct(*keys)).repartitionByRange(parts, "k").withColumn("pid", F.spark_partition_id()))
    rank = F.row_number().over(Window.partitionBy("pid").orderBy("k"))
    return o.withColumn("range", F.col("pid").cast("bigint") * (1 << 40) + F.floor((rank - 1) / per)).drop("pid")


def new_ids(order: DataFrame, keys: list[Column]) -> DataFrame:
    """id, new_id: consecutive ids in the order of `keys`; communities stay together."""
    o = ranges(order, keys).withColumn("one", F.lit(1))
    return prefix_sum(o, "k", "one", F.col("range"), "new_id").select("id", "new_id")


def peripheral(inside: DataFrame, vertices: DataFrame, most: int = 1000, rounds: int = 3) -> DataFrame:
    """label, id: a vertex of each component (vertices: id, label, degree) far from all others: of the last level of a
    breadth-first walk the one of lowest degree starts the next walk, a few times over."""
    first = F.min(F.struct("degree", "id"))
    start = reliable(vertices.groupBy("label").agg(first.alias("r")).select("label", F.col("r.id").alias("id")))
    for _ in range(rounds):
        seen = walk(inside, start.select("id"), most)
        far = seen.join(vertices, "id").groupBy("label").agg(F.min(F.struct((-F.col("depth")).alias("d"), "degree", "id")).alias("r"))
        start = reliable(far.select("label", F.col("r.id").alias("id")))
    return start


def walk(inside: DataFrame, start: DataFrame, most: int) -> DataFrame:
    """id, depth from the start vertices over inside(a, b)."""
    seen = frontier = reliable(start.select("id", F.lit(0).alias("depth")))
    for d in range(1, most):
        frontier = reliable(inside.join(frontier.select(F.col("id").alias("a")), "a", "left_semi").select(F.col("b").alias("id")).distinct().join(seen, "id", "left_anti").select("id", F.lit(d).alias("depth")))
        if frontier.isEmpty():
            return seen
        seen = reliable(seen.unionByName(frontier))
    raise MatrixError(f"paths of more than {most} steps")


def bandwidth_order(gm: GraphMatrix, most: int = 1000) -> DataFrame:
    """id, new_id: the traditional order against wide bands. Each component is walked breadth-first from a peripheral vertex;
    a vertex follows the first of its neighbours in the level before (its parent), and siblings go by degree and id; the
    whole order is then reversed. A round per level, as positions of a level follow from those of the level before."""
    n = reliable(undirected(gm))
    degree = n.groupBy(F.col("a").alias("id")).agg(F.count("*").alias("degree"))
    v = reliable(connected(gm).join(degree, "id", "left").select("id", "label", F.coalesce("degree", F.lit(0)).alias("degree")))
    seen = walk(n, peripheral(n, v, most).select("id"), most)
    v = reliable(v.join(seen, "id"))
    levels = v.agg(F.max("depth")).first()[0] or 0
    placed = None
    for d in range(levels + 1):
        level = v.where(F.col("depth") == d)
        if placed is None:
            level = level.withColumn("parent", F.lit(0).cast("bigint"))
        else:
            last = placed.where(F.col("depth") == d - 1).select(F.col("id").alias("b"), F.col("at"))
            parent = n.join(last, "b").groupBy(F.col("a").alias("id")).agg(F.min("at").alias("parent"))
            level = level.join(parent, "id")
        at = prefix_sum(ranges(level, [F.col("label"), F.col("parent"), F.col("degree"), F.col("id")]).withColumn("one", F.lit(1)), "k", "one", F.col("range"), "at")
        at = reliable(at.select("id", "label", "depth", "at"))
        placed = at if placed is None else placed.unionByName(at)
    return new_ids(placed, [F.col("label"), (-F.col("depth")).alias("depth"), (-F.col("at")).alias("at")])


def relabelling(gm: GraphMatrix, method: str = "lpa") -> DataFrame:
    """id, new_id for all vertices that have edges.

    lpa: communities by label propagation, each in breadth-first order. cc: the same with components. rcm: the traditional
    baseline, see `bandwidth_order`."""
    if method == "rcm":
        return bandwidth_order(gm)
    d = depths(gm, label_propagation(gm) if method == "lpa" else connected(gm))
    return new_ids(d, [F.col("label"), F.col("depth"), (-F.col("degree")).alias("degree"), F.col("id")])


def bandwidth(gm: GraphMatrix) -> DataFrame:
    """bandwidth (largest |row - column|), profile (sum over rows of how far the row reaches left of the diagonal)."""
    rows = gm.edges.groupBy("dst").agg(F.max(F.abs(F.col("dst") - F.col("src"))).alias("far"), F.greatest(F.lit(0), F.max(F.col("dst") - F.col("src"))).alias("left"))
    return rows.agg(F.max("far").alias("bandwidth"), F.sum("left").alias("profile"))


def relabel(gm: GraphMatrix, perm: DataFrame) -> GraphMatrix:
    e = gm.edges.join(perm.select(F.col("id").alias("dst"), F.col("new_id").alias("a")), "dst").join(perm.select(F.col("id").alias("src"), F.col("new_id").alias("b")), "src")
    return gm.with_edges(e.select(F.col("a").alias("dst"), F.col("b").alias("src"), "w"))


def relabel_state(x: VertexState, perm: DataFrame) -> VertexState:
    return VertexState(x.df.join(perm, "id").select(F.col("new_id").alias("id"), "s"), x.n)


def restore(x: VertexState, perm: DataFrame) -> VertexState:
    back = perm.select(F.col("new_id").alias("id"), F.col("id").alias("old"))
    return VertexState(x.df.join(back, "id").select(F.col("old").alias("id"), "s"), x.n)


# Partitions ----------------------------------------------------------------------------------------------------------


def even(gm: GraphMatrix, parts: int, per: int = 4096) -> DataFrame:
    """id, degree, part: consecutive row vertices with about equally many edges per part."""
    degree = gm.edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("degree"))
    total = gm.edges.count()
    d = prefix_sum(degree, "id", "degree", F.floor(F.col("id") / per))
    return d.select("id", "degree", F.least(F.lit(parts - 1), F.floor(F.lit(parts) * F.col("before") / max(1, total))).cast("int").alias("part"))


def by_community(gm: GraphMatrix, communities: DataFrame, parts: int) -> DataFrame:
    """id, part: whole communities in order of their label, cut where a part is full; a community larger than a part is
    spread over several."""
    degree = gm.edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("degree"))
    c = communities.join(degree, "id", "left").select("id", "label", F.coalesce("degree", F.lit(0)).alias("degree"))
    total = gm.edges.count()
    d = prefix_sum(ranges(c, [F.col("label"), F.col("id")]), "k", "degree", F.col("range"))
    size = c.groupBy("label").agg(F.sum("degree").alias("size"))
    start = d.groupBy("label").agg(F.min("before").alias("start"))
    d = d.join(size, "label").join(start, "label")
    at = F.when(F.col("size") > total / parts, F.col("before")).otherwise(F.col("start"))
    return d.select("id", F.least(F.lit(parts - 1), F.floor(F.lit(parts) * at / max(1, total))).cast("int").alias("part"))


def with_parts(gm: GraphMatrix, dst_parts: DataFrame, src_parts: DataFrame) -> DataFrame:
    """Edges with the part of their row (p) and of their column vertex (q)."""
    return gm.edges.join(dst_parts.select(F.col("id").alias("dst"), F.col("part").alias("p")), "dst").join(src_parts.select(F.col("id").alias("src"), F.col("part").alias("q")), "src")


def quality(gm: GraphMatrix, dst_parts: DataFrame, src_parts: DataFrame) -> DataFrame:
    """edges, cut (edges between parts), replicas (column vertices per foreign part), heaviest, parts."""
    e = with_parts(gm, dst_parts, src_parts)
    load = e.groupBy("p").agg(F.count("*").alias("n"))
    return e.agg(F.count("*").alias("edges"), F.count_if(F.col("p") != F.col("q")).alias("cut"), F.count_distinct(F.when(F.col("p") != F.col("q"), F.struct("p", "src"))).alias("replicas")).crossJoin(F.broadcast(load.agg(F.max("n").alias("heaviest"), F.count("*").alias("parts"))))


def locality(gm: GraphMatrix, perm: DataFrame) -> DataFrame:
    """gap_before, gap_after: summed |row - column| under the old and the new ids."""
    new = relabel(gm, perm).edges.agg(F.sum(F.abs(F.col("dst") - F.col("src"))).alias("gap_after"))
    return gm.edges.agg(F.sum(F.abs(F.col("dst") - F.col("src"))).alias("gap_before")).crossJoin(new)


def by_degree(gm: GraphMatrix) -> DataFrame:
    """id, new_id by descending degree and id: a plain deterministic order."""
    degree = undirected(gm).groupBy(F.col("a").alias("id")).agg(F.count("*").alias("degree"))
    high = degree.agg(F.max("degree")).first()[0] or 1
    d = degree.withColumn("one", F.lit(1)).withColumn("k", F.struct((-F.col("degree")).alias("m"), "id"))
    return prefix_sum(d, "k", "one", F.lit(high) - F.col("degree"), "new_id").select("id", "new_id")
