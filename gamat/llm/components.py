"""Connected components of a link table, wholly on the executors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, discard


def components(links: DataFrame) -> DataFrame:
    """node, root for every node of links(a, b); root is the same number within a component, and one of its nodes.

    Each round every node moves to the smallest of its neighbours and itself, twice over, and the links between moved
    nodes are the next round's. Node numbers should be digests, so that this ends after a logarithmic number of rounds.
    """
    links = cut(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct())
    nodes = links.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    roots = cut(nodes.select("node", F.col("node").alias("root")))
    while not links.isEmpty():
        step = links.select(F.explode(F.array(F.struct(F.col("a").alias("v"), F.col("a").alias("p")), F.struct(F.col("b").alias("v"), F.col("a").alias("p")))).alias("x")).select("x.*")
        step = cut(step.groupBy("v").agg(F.min("p").alias("p")))
        # The smaller end of a link may have a smaller neighbour itself: go there at once.
        jump = cut(step.join(step.select(F.col("v").alias("p"), F.col("p").alias("q")), "p", "left").select("v", F.coalesce("q", "p").alias("p")))
        move = lambda df, c: df.join(jump.select(F.col("v").alias(c), F.col("p").alias("moved")), c, "left").withColumn(c, F.coalesce("moved", c)).drop("moved")  # noqa: E731,B023
        old = roots, links, step, jump
        roots = cut(move(roots, "root"))
        links = move(move(links, "a"), "b")
        links = cut(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct())
        discard(*old)
    return roots
