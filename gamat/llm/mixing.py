"""Mixing sources to target weights by hierarchical budgeting.

Leaves of the tree are (domain, language, source). The token budget of the root goes down by the weights of the
children; a child that cannot use its share (its whole subtree holds fewer tokens than that, times the epochs allowed)
takes what it has, and the shortage goes to its siblings by weight; only what a full set of siblings cannot take
goes back to their parent's siblings. Each leaf then takes whole epochs of its documents and, of the next epoch, the
longest prefix in seeded order that fits into the rest of its budget.

The prefix is found without sorting a leaf: token sums per hash bucket (the number of buckets follows the number of
documents, so a bucket stays small), running sums over the buckets, and a sort of the one bucket in which the budget
ends. What reaches the driver is one row per leaf.

Null language, source or domain are leaves of their own, "<null>"; null text has no tokens. Repeated rows are
documents of their own in the counts; they stand side by side in the seeded order and are chosen together, if the budget
holds all of them. Ties in the seeded order go by doc_id. Very long texts are whole documents: one that does not fit ends the
prefix. Other columns are kept by `choose`. An empty table gives an empty result. A weight that is not given counts `other`.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import cut

LEAF = ["domain", "lang", "source"]
#: Leaves up to which tables with a row per leaf are broadcast.
LEAVES = 200_000
WORD = r"[^ \t\n\x0B\f\r]+"
#: Which sources make up the domains of the synthetic corpus; all others are "web".
DOMAINS = {"books": ["src1", "src2", "src3", "src4"], "reference": ["src5", "src6", "src7"], "forum": ["src8", "src9"]}


@dataclass(frozen=True)
class Weights:
    """Relative weights of domains, of languages in each domain, and of sources in each of those."""

    domain: dict[str, float] = field(default_factory=lambda: {"web": 0.5, "books": 0.25, "reference": 0.15, "forum": 0.1})
    lang: dict[str, float] = field(default_factory=lambda: {"en": 0.55, "de": 0.17, "fr": 0.17, "es": 0.11})
    source: dict[str, float] = field(default_factory=dict)
    other: float = 0.05
    other_source: float = 1.0

    def of(self, level: int, name: str) -> float:
        return (self.domain.get(name, self.other), self.lang.get(name, self.other), self.source.get(name, self.other_source))[level]


def share(budget: int, capacity: dict, weight: dict) -> dict:
    """Split the budget by weight; nobody gets more than its capacity, and shortages go to the others by weight."""
    out, open_ = dict.fromkeys(capacity, 0), {k for k in capacity if capacity[k] > 0 and weight[k] > 0}
    left = min(budget, sum(capacity[k] for k in open_))
    while open_ and left > 0:
        total = sum(weight[k] for k in open_)
        full = {k for k in open_ if capacity[k] <= left * weight[k] / total}
        if not full:
            given = {k: int(left * weight[k] / total) for k in sorted(open_)}
            for k in sorted(open_, key=lambda k: (-weight[k], k)):  # what rounding leaves over
                more = min(left - sum(given.values()), capacity[k] - given[k])
                given[k] += max(0, more)
            out.update(given)
            break
        for k in full:
            out[k] = capacity[k]
            left -= capacity[k]
        open_ -= full
    return out


def budgets(tokens: dict[tuple[str, str, str], int], total: int, weights: Weights, max_epochs: int) -> dict[tuple[str, str, str], int]:
    """Token budget of each leaf."""
    tree: dict = {}
    for (domain, lang, source), n in tokens.items():
        tree.setdefault(domain, {}).setdefault(lang, {})[source] = n * max_epochs
    out = dict.fromkeys(tokens, 0)

    def holds(node) -> int:
        return sum(map(holds, node.values())) if isinstance(node, dict) else node

    def down(path: tuple, node, budget: int) -> None:
        if len(path) == 3:
            out[path] = budget
            return
        parts = share(budget, {k: holds(child) for k, child in node.items()}, {k: weights.of(len(path), k) for k in node})
        for name, part in parts.items():
            down((*path, name), node[name], part)

    down((), tree, total)
    return out


def domain_of(source: Column, domains: dict[str, list[str]]) -> Column:
    out = F.when(source.isNull(), F.lit("<null>"))
    for name, sources in domains.items():
        out = out.when(source.isin(sources), F.lit(name))
    return out.otherwise(F.lit("web"))


def leaf_columns(domains: dict[str, list[str]]) -> list[Column]:
    return [domain_of(F.col("source"), domains).alias("domain"), F.coalesce("lang", F.lit("<null>")).alias("lang"), F.coalesce("source", F.lit("<null>")).alias("source")]


def order_hash(seed: int, epoch: Column, doc_id: Column) -> Column:
    return F.xxhash64(F.lit(seed), epoch.cast("int"), doc_id)


def small(per_leaf: DataFrame) -> DataFrame:
    """Asks for a broadcast of a table with a row per leaf, if it is counted to have at most LEAVES rows."""
    return F.broadcast(per_leaf) if per_leaf.count() <= LEAVES else per_leaf


@dataclass
class Choice:
    """leaves: domain, lang, source, tokens, budget, full (whole epochs), and the last (h, doc) chosen of the next epoch."""

    leaves: DataFrame
    slim: DataFrame
    seed: int
    domains: dict[str, list[str]]


def decide(docs: DataFrame, weights: Weights | None = None, fraction: float = 1.0, max_epochs: int = 1, seed: int = 17, domains: dict[str, list[str]] | None = None, per_bucket: int = 20_000) -> Choice:
    """Budgets and cut-offs for docs(doc_id, text, lang, source); the whole budget is `fraction` of all tokens."""
    spark, weights, domains = docs.sparkSession, weights or Weights(), DOMAINS if domains is None else domains
    tokens = F.regexp_count(F.coalesce("text", F.lit("")), F.lit(WORD)).cast("long")
    slim = cut(docs.select("doc_id", *leaf_columns(domains), tokens.alias("tokens")))
    sums = {tuple(r[c] for c in LEAF): (r["tokens"], r["n"]) for r in slim.groupBy(*LEAF).agg(F.sum("tokens").alias("tokens"), F.count("*").alias("n")).collect()}
    have = {k: v[0] for k, v in sums.items()}
    given = budgets(have, int(fraction * sum(have.values())), weights, max_epochs)
    rows = []
    for k in sorted(sums):
        full = min(max_epochs, given[k] // have[k]) if have[k] else 0
        rows.append((*k, have[k], given[k], full, given[k] - full * have[k]))
    plan = spark.createDataFrame(rows, "domain string, lang string, source string, leaf_tokens long, budget long, full int, rest long")
    buckets = max(64, sum(v[1] for v in sums.values()) // per_bucket)
    h = order_hash(seed, F.col("full"), F.col("doc_id"))
    some = slim.join(small(plan.where("rest > 0")), LEAF).select(*LEAF, "rest", "doc_id", "tokens", h.alias("h"))
    bucket = F.least(F.floor((F.col("h").cast("double") / 2.0**64 + 0.5) * buckets), F.lit(buckets - 1)).cast("int")
    some = some.withColumn("bucket", bucket)
    by = some.groupBy(*LEAF, "bucket").agg(F.sum("tokens").alias("t"), F.max("rest").alias("rest"))
    over = Window.partitionBy(*LEAF).orderBy("bucket")
    by = by.withColumn("upto", F.sum("t").over(over)).withColumn("before", F.col("upto") - F.col("t"))
    edge = by.where("upto > rest").groupBy(*LEAF).agg(F.min(F.struct("bucket", "before")).alias("e")).select(*LEAF, "e.bucket", "e.before")
    edge = cut(edge)  # one row per leaf
    inside = some.join(small(edge), [*LEAF, "bucket"])
    inside = inside.withColumn("sum", F.col("before") + F.sum("tokens").over(Window.partitionBy(*LEAF, "bucket").orderBy("h", "doc_id")))
    last = inside.where("sum <= rest").groupBy(*LEAF).agg(F.max(F.struct("h", "doc_id")).alias("last"))
    # Without a document that fits in its bucket, everything before that bucket is chosen.
    low = (F.col("bucket").cast("double") / buckets - 0.5) * 2.0**64
    leaves = plan.join(small(edge), LEAF, "left").join(small(cut(last)), LEAF, "left")
    leaves = leaves.select(*LEAF, "leaf_tokens", "budget", "full", "rest", F.col("bucket").alias("edge"), F.lit(buckets).alias("buckets"), "last", low.alias("low"))
    return Choice(cut(leaves), slim, seed, domains)


def copies(choice: Choice, rows: DataFrame, doc_id: str) -> DataFrame:
    """rows (with the leaf columns) with `copies`: in how many epochs each document is chosen."""
    h = order_hash(choice.seed, F.col("full"), F.col(doc_id))
    both = rows.join(small(choice.leaves), LEAF).withColumn("h", h)
    bucket = F.least(F.floor((F.col("h").cast("double") / 2.0**64 + 0.5) * F.col("buckets")), F.col("buckets") - 1).cast("int")
    part = F.when(F.col("rest") <= 0, False).when(F.col("edge").isNull(), True).when(bucket < F.col("edge"), True).when((bucket > F.col("edge")) | F.col("last").isNull(), False)
    part = part.otherwise((F.col("h") < F.col("last.h")) | ((F.col("h") == F.col("last.h")) & (F.coalesce(F.col(doc_id) <= F.col("last.doc_id"), F.col(doc_id).isNull()))))
    return both.withColumn("copies", F.col("full") + part.cast("int"))


def choose(docs: DataFrame, **how) -> DataFrame:
    """All columns of docs, each chosen document once per epoch that holds it."""
    choice = decide(docs.select("doc_id", "text", "lang", "source"), **how)
    rows = docs.select(F.struct("*").alias("__row"), F.col("doc_id").alias("__id"), *leaf_columns(choice.domains))
    out = copies(choice, rows, "__id").where("copies > 0")
    if how.get("max_epochs", 1) > 1:
        out = out.withColumn("__epoch", F.explode(F.sequence(F.lit(1), "copies")))
    return out.select("__row.*")


def op10_source_mixing(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang", "source")
    choice = decide(docs, max_epochs=3)
    out = copies(choice, choice.slim, "doc_id").where("copies > 0")
    return out.select("doc_id", *LEAF, F.col("tokens").alias("n_tokens"), "leaf_tokens", F.col("budget").alias("leaf_budget"), F.explode(F.sequence(F.lit(1), "copies")).alias("epoch"))
