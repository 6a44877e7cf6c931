"""Quality classifier: interpolated modified Kneser-Ney model of the characters of trusted text.

Trusted are all documents with a label quality = 1 and toxic = 0. Per language, every 4-gram of their characters (three
begin marks before each text) is counted on the executors; continuation counts, the three discounts of each order, back-off
weights and the interpolated probabilities come from aggregations and joins of those sharded count tables. Nothing is
sampled, pruned or capped: what is gathered grows with the trusted text.

Scoring: every different 4-gram of the documents is joined, order by order, with the shards of the count tables, which
gives it one logarithm with back-off. The most frequent ones (up to SMALL) are then broadcast and summed in blocks of
text; the rare rest is joined shard by shard with the n-gram counts of the documents. See `score`.

A document is rejected if its perplexity exceeds the threshold of its language and length: the logarithm of perplexity may
lie above the median of the language's trusted documents by the QUANTILE of what theirs do, scaled by the root of the
length (SLACK 1: nothing is added). The trusted documents behind a threshold are scored by models that have not seen them:
they are dealt into FOLDS by digest, and a fold's documents are scored by the counts of the other folds. Words with a digit
or "@" count as one sign. Languages without trusted text, and empty texts, have no perplexity and are kept; a perplexity
that equals its threshold is kept.

Null text counts as empty; null lang is a language of its own, "<null>". Repeated rows share one fate. Characters
beyond the basic plane count as one character. Very long texts are scored whole, in arrays of 8 bytes a character. Other
columns are kept by `keep_good`, whatever their names. An empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from statistics import NormalDist

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, map_slices

ORDER, BITS, BEGIN, OTHER = 4, 16, 0, 0xFFFD
QUANTILE, SLACK, TAIL = 0.99, 1.0, 1.5
FOLDS, MARK = 4, "\x01"
#: Largest tables that are broadcast, in rows (16 bytes each); texts are scored about CHUNK characters at a time.
SMALL, CHUNK = 2_000_000, 500_000
#: Different n-grams that a counting task holds, and new ones that are worth a merge.
HELD, MERGE = 2_000_000, 100_000
HINT, FIELD = re.compile("[0-9@]"), re.compile(r"(?<!\S)[^\s0-9@]*+[0-9@]\S*+")


def plain(text: str) -> str:
    """The text as the model reads it: a word with a digit or "@" (number, address, key) is one sign, as its characters say
    nothing of the prose around it."""
    return FIELD.sub("0", text) if HINT.search(text) else text


def gram_keys(text: str) -> np.ndarray:
    """One packed 4-gram per character, in order: three predecessors and the character itself."""
    cp = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    cp = np.where(cp > 0xFFFF, OTHER, cp).astype(np.uint64)
    full = np.concatenate((np.full(ORDER - 1, BEGIN, np.uint64), cp))
    n = len(cp)
    out = np.zeros(n, np.uint64)
    for j in range(ORDER):
        out = out << np.uint64(BITS) | full[j : j + n]
    return out


def trusted_ids(labels: DataFrame) -> DataFrame:
    return labels.where("quality = 1 and toxic = 0 and doc_id is not null").select("doc_id").distinct()


def cut_model(df: DataFrame) -> DataFrame:
    """`cut` for tables of the model: they are far smaller than the documents, so an eighth of the tasks writes them, into an
    eighth of the files."""
    return cut(df.coalesce(max(8, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")) // 8)))


def language() -> Column:
    return F.translate(F.coalesce("lang", F.lit("<null>")), MARK, " ")


class Counter:
    """Counts of keys, as sorted arrays that are merged when what is new has grown as large as what is held."""

    def __init__(self):
        self.keys, self.counts, self.new, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int64), [], 0

    def add(self, keys: np.ndarray) -> None:
        self.new.append(np.unique(keys, return_counts=True))
        self.size += len(self.new[-1][0])
        if self.size > max(len(self.keys), MERGE):
            self.merge()

    def merge(self) -> None:
        keys, counts = zip((self.keys, self.counts), *self.new, strict=True)
        self.keys, at = np.unique(np.concatenate(keys), return_inverse=True)
        self.counts = np.bincount(at, weights=np.concatenate(counts), minlength=len(self.keys)).astype(np.int64)
        self.new, self.size = [], 0


def count_grams(docs: DataFrame) -> DataFrame:
    """lang, k, c: counts of the 4-grams of docs(lang, text).

    A task sends each different n-gram once, or again each time it holds more than HELD of them."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        text_of: dict[str, list[np.ndarray]] = {}
        size: dict[str, int] = {}
        counters: dict[str, Counter] = {}

        def take(lang: str) -> None:
            counters.setdefault(lang, Counter()).add(np.concatenate(text_of.pop(lang)))
            size.pop(lang)

        def sent() -> Iterator[pd.DataFrame]:
            for lang in list(counters):
                c = counters.pop(lang)
                c.merge()
                yield pd.DataFrame({"lang": lang, "k": c.keys.view(np.int64), "c": c.counts})

        for b in batches:
            for lang, text in zip(b["lang"], b["text"], strict=True):
                if text:
                    text = plain(text)
                    text_of.setdefault(lang, []).append(gram_keys(text))
                    size[lang] = size.get(lang, 0) + len(text)
                    if size[lang] >= CHUNK:
                        take(lang)
            if sum(len(c.keys) + c.size for c in counters.values()) > HELD:
                yield from sent()
        for lang in list(text_of):
            take(lang)
        yield from sent()

    return map_slices(docs.select("lang", "text"), run, "lang string, k long, c long").groupBy("lang", "k").agg(F.sum("c").alias("c"))


def low(k: str, n: int) -> Column:
    """The last n characters of a packed gram."""
    return F.col(k).bitwiseAND(F.lit((1 << (BITS * n)) - 1)) if n < ORDER else F.col(k)


def train(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The model of docs(lang, text), see `train_counts`."""
    return train_counts(count_grams(docs))


def train_counts(top: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(grams: n, lang, k, lp) and (contexts: n, lang, k, lg), natural logarithms, of 4-gram counts top(lang, k, c).

    contexts with n = 0: the logarithm of an unseen character's probability, k = 0."""
    counts = {ORDER: cut_model(top)}
    for n in range(ORDER - 1, 0, -1):
        counts[n] = cut_model(counts[n + 1].select("lang", low("k", n).alias("k")).groupBy("lang", "k").agg(F.count("*").alias("c")))
    below, grams, contexts = None, [], []
    for n in range(1, ORDER + 1):
        c = counts[n]
        of = c.groupBy("lang").agg(*[F.count_if(F.col("c") == i).cast("double").alias(f"n{i}") for i in (1, 2, 3, 4)], F.count("*").alias("types"))
        y = F.col("n1") / (F.col("n1") + 2 * F.col("n2"))

        def discount(i: int, y=y) -> Column:
            ready = (F.col("n1") > 0) & (F.col(f"n{i}") > 0)
            value = F.when(ready, i - (i + 1) * y * F.col(f"n{i + 1}") / F.nullif(F.col(f"n{i}"), F.lit(0.0)))
            return F.greatest(F.lit(0.05), F.least(F.lit(float(i)) * 0.95, F.coalesce(value, F.lit(0.5 * i))))

        d = of.select("lang", "types", discount(1).alias("d1"), discount(2).alias("d2"), discount(3).alias("d3"))
        seen = c.select("lang", "k", "c", F.shiftrightunsigned("k", BITS).alias("ctx"))
        sums = seen.groupBy("lang", "ctx").agg(F.sum("c").alias("total"), *[F.count_if(F.col("c") == i).alias(f"t{i}") for i in (1, 2)], F.count_if(F.col("c") >= 3).alias("t3"))
        sums = sums.join(F.broadcast(d), "lang").withColumn("gamma", (F.col("d1") * F.col("t1") + F.col("d2") * F.col("t2") + F.col("d3") * F.col("t3")) / F.col("total"))
        sums = cut_model(sums)
        own = F.when(F.col("c") == 1, F.col("d1")).when(F.col("c") == 2, F.col("d2")).otherwise(F.col("d3"))
        p = seen.join(sums, ["lang", "ctx"]).withColumn("p", (F.col("c") - own) / F.col("total"))
        if below is None:
            p = p.withColumn("p", F.col("p") + F.col("gamma") / (F.col("types") + 1))
            contexts.append(sums.select(F.lit(0).alias("n"), "lang", F.lit(0).cast("long").alias("k"), F.log(F.col("gamma") / (F.col("types") + 1)).alias("lg")))
        else:
            p = p.withColumn("suffix", low("k", n - 1)).join(below.select("lang", F.col("k").alias("suffix"), F.col("p").alias("q")), ["lang", "suffix"]).withColumn("p", F.col("p") + F.col("gamma") * F.col("q"))
            contexts.append(sums.select(F.lit(n - 1).alias("n"), "lang", F.col("ctx").alias("k"), F.log("gamma").alias("lg")))
        below = cut_model(p.select("lang", "k", "p"))
        grams.append(below.select(F.lit(n).alias("n"), "lang", "k", F.log("p").alias("lp")))
    union = lambda xs: xs[0] if len(xs) == 1 else xs[0].unionByName(union(xs[1:]))
    return cut_model(union(grams)), cut_model(union(contexts))


def resolve(asked: DataFrame, grams: DataFrame, contexts: DataFrame) -> DataFrame:
    """lang, k, c, v: natural logarithm of the probability of each 4-gram of asked(lang, k, c), with back-off.

    Joins of count shards: each different n-gram that is asked for is one row, whatever the number of documents that hold
    it, so no key is hot - a suffix has as many rows as there are characters before it."""
    levels = {ORDER: asked.select("lang", "k")}
    for n in range(ORDER - 1, 0, -1):
        levels[n] = levels[n + 1].select("lang", low("k", n).alias("k")).distinct()
    value = None
    for n in range(1, ORDER + 1):
        g = grams.where(F.col("n") == n).select("lang", "k", "lp")
        h = contexts.where(F.col("n") == n - 1).select("lang", F.col("k").alias("ctx"), "lg")
        x = levels[n].join(g, ["lang", "k"], "left").withColumn("ctx", F.shiftrightunsigned("k", BITS) if n > 1 else F.lit(0).cast("long"))
        x = x.join(F.broadcast(h) if n == 1 else h, ["lang", "ctx"], "left")  # n = 1: one row per language
        below = F.lit(0.0)
        if value is not None:
            x = x.withColumn("suffix", low("k", n - 1)).join(value.select("lang", F.col("k").alias("suffix"), F.col("v").alias("below")), ["lang", "suffix"])
            below = F.col("below")
        value = cut_model(x.select("lang", "k", F.coalesce(F.col("lp"), F.coalesce("lg", F.lit(0.0)) + below).alias("v")))
    return value.join(asked, ["lang", "k"])


def score(rows: DataFrame, grams: DataFrame, contexts: DataFrame, small: int = SMALL) -> DataFrame:
    """id, lang, n, nats: one row per different (id, lang) of rows(id, lang, text).

    The logarithms of all 4-grams of the rows come from joins of count shards (`resolve`). The `small` most frequent of
    them are broadcast and summed where the texts are; the rare rest is sent to its shards as (id, lang, k, c), joined
    and summed per document. Nothing is left out: with `small` = 0 everything takes the second way."""
    langs = grams.select("lang").distinct()
    asked = cut_model(count_grams(rows.join(F.broadcast(langs), "lang", "left_semi")))
    table = cut_model(resolve(asked, grams, contexts))
    total = table.count()
    edge = -1 if total <= small else table.agg(F.percentile_approx("c", max(0.0, 1 - small / total), 10000)).first()[0] if small else None
    head = table.where(F.col("c") > edge if edge is not None else F.lit(False)).select("lang", "k", "v")
    found, tables = head.toArrow(), {}
    names = found["lang"].combine_chunks().dictionary_encode()
    code, k, v = names.indices.to_numpy(), found["k"].to_numpy().view(np.uint64), found["v"].to_numpy()
    for j, lang in enumerate(names.dictionary.to_pylist()):
        own = np.flatnonzero(code == j)
        own = own[np.argsort(k[own])]
        tables[lang] = (k[own], v[own])
    known = {r["lang"] for r in langs.collect()}  # one row per language and fold
    shared = rows.sparkSession.sparkContext.broadcast((known, tables))
    del found, names, code, k, v, tables

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        models, held = shared.value
        empty = (np.zeros(0, np.uint64), np.zeros(0))
        for b in batches:
            ids, langs_, n, sums = b["id"].to_numpy(), b["lang"].to_numpy(), np.zeros(len(b), np.int64), np.full(len(b), np.nan)
            queue: dict[str, list] = {}
            rare: list[pd.DataFrame] = []

            def settle(lang: str) -> None:
                some = queue.pop(lang)
                keys, values = held.get(lang, empty)
                all_, at_row = np.concatenate([x for _, x in some]), np.array([i for i, _ in some])
                lengths = np.array([len(x) for _, x in some])
                at = np.minimum(np.searchsorted(keys, all_), max(0, len(keys) - 1))
                hit = keys[at] == all_ if len(keys) else np.zeros(len(all_), bool)
                nats = np.zeros(len(all_))
                nats[hit] = -values[at[hit]]
                sums[at_row] = np.add.reduceat(nats, np.cumsum(lengths) - lengths)
                if not hit.all():
                    miss = pd.DataFrame({"id": ids[np.repeat(at_row, lengths)[~hit]], "lang": lang, "k": all_[~hit].view(np.int64)})
                    rare.append(miss.groupby(["id", "lang", "k"], sort=False).size().rename("c").reset_index())

            size: dict[str, int] = {}
            for i, (lang, text) in enumerate(zip(langs_, b["text"], strict=True)):
                text = plain(text)
                n[i] = len(text)
                if text and lang in models:
                    queue.setdefault(lang, []).append((i, gram_keys(text)))
                    size[lang] = size.get(lang, 0) + len(text)
                    if size[lang] > CHUNK:
                        settle(lang)
                        size[lang] = 0
            for lang in list(queue):
                settle(lang)
            yield pd.DataFrame({"id": ids, "lang": langs_, "n": n, "nats": sums, "k": None, "c": None})
            for r in rare:
                yield pd.DataFrame({"id": r["id"], "lang": r["lang"], "n": None, "nats": None, "k": r["k"], "c": r["c"]})

    out = map_slices(rows.select("id", "lang", "text"), run, f"id {dict(rows.dtypes)['id']}, lang string, n long, nats double, k long, c long")
    if edge == -1:
        return out.dropDuplicates(["id", "lang"]).select("id", "lang", "n", "nats")
    out = cut(out)
    here = out.where("k is null").groupBy("id", "lang").agg(F.first("n").alias("n"), F.first("nats").alias("nats"), F.count("*").alias("copies"))
    # A row that is there so many times sends its rare n-grams so many times.
    there = out.where("k is not null").select("id", "lang", "k", "c").join(table.select("lang", "k", "v"), ["lang", "k"])
    there = there.groupBy("id", "lang").agg(F.sum(-F.col("v") * F.col("c")).alias("more"))
    return here.join(there, ["id", "lang"], "left").select("id", "lang", "n", (F.col("nats") + F.coalesce("more", F.lit(0.0)) / F.col("copies")).alias("nats"))


def score_blocks(rows: DataFrame, grams: DataFrame, contexts: DataFrame) -> DataFrame:
    """id, lang, n, nats, frequent n-grams from a broadcast table."""
    return score(rows, grams, contexts)


def score_shards(rows: DataFrame, grams: DataFrame, contexts: DataFrame) -> DataFrame:
    """id, lang, n, nats, all n-grams by joins."""
    return score(rows, grams, contexts, small=0)


def split_counts(rows: DataFrame, folds: int) -> DataFrame:
    """Counts of the models of each language: of all rows(lang, fold, text), under its own name, and of all folds but one."""
    fold = F.concat("lang", F.lit(MARK), F.col("fold").cast("string"))
    counted = cut_model(count_grams(rows.select(fold.alias("lang"), "text")))
    parts = F.split("lang", MARK)
    counted = counted.select(F.element_at(parts, 1).alias("lang"), F.element_at(parts, 2).cast("int").alias("fold"), "k", "c")
    models = F.array(F.col("lang"), *[F.when(F.col("fold") != f, F.concat("lang", F.lit(f"{MARK}{f}"))) for f in range(folds)])
    spread = counted.select(F.explode(models).alias("lang"), "k", "c").where("lang is not null")
    return spread.groupBy("lang", "k").agg(F.sum("c").alias("c"))


def classify(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE, slack: float = SLACK, small: int = SMALL, folds: int = FOLDS) -> DataFrame:
    """id (digest of the row), doc_id, lang, n, perplexity, threshold, keep: for every row of docs(doc_id, lang, text)."""
    trusted = cut_model(trusted_ids(labels))
    mark = trusted.withColumn("good", F.lit(True))
    rows = docs.select(row_id().alias("id"), "doc_id", language().alias("lang"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.join(F.broadcast(mark) if trusted.count() <= SMALL else mark, "doc_id", "left")
    fold = F.pmod(F.xxhash64("id"), F.lit(folds)).cast("int")
    grams, contexts = train_counts(split_counts(rows.where("good").select("lang", fold.alias("fold"), "text"), folds))
    # Trusted documents are scored twice: by the model of all of them, and by the one that has not seen their fold.
    models = F.array(F.col("lang"), F.when(F.col("good"), F.concat("lang", F.lit(MARK), fold.cast("string"))))
    asked = rows.select("id", F.explode(models).alias("lang"), "text").where("lang is not null")
    perplexity = F.when(F.col("n") > 0, F.exp(F.when(~F.isnan("nats"), F.col("nats")) / F.col("n")))
    found = cut(score(asked, grams, contexts, small).withColumn("perplexity", perplexity))
    unseen = found.where(F.col("lang").contains(MARK)).select("id", F.col("perplexity").alias("unseen"))
    scored = cut(rows.select("id", "doc_id", "lang", "good").join(found.select("id", "lang", "n", "perplexity"), ["id", "lang"]).join(unseen, "id", "left"))
    return scored.join(F.broadcast(thresholds(scored, quantile)), "lang", "left").select(
        "id", "doc_id", "lang", "n", "perplexity", (slack * F.exp(F.col("center") + F.col("excess") / F.sqrt("n"))).alias("threshold"),
    ).withColumn("keep", F.coalesce(F.col("perplexity") <= F.col("threshold"), F.lit(True)))


def thresholds(scored: DataFrame, quantile: float) -> DataFrame:
    """lang, center, excess of scored(lang, good, n, perplexity, unseen): one row per language.

    center: median logarithm of the unseen perplexity of trusted documents; excess: the quantile of what lies above it, times
    the root of the length, as chance moves the mean of n characters by one part in that root. Where few documents leave the
    quantile to single outliers, it ends at TAIL times the quantile of a normal distribution with the same quartiles."""
    # A language with trusted documents in one fold only has no other model: its own stands in.
    good = scored.where("good and perplexity is not null and n > 0").select("lang", "n", F.log(F.coalesce("unseen", "perplexity")).alias("h"))
    center = good.groupBy("lang").agg(F.percentile_approx("h", 0.5, 10000).alias("center"))
    above = good.join(F.broadcast(center), "lang").withColumn("z", (F.col("h") - F.col("center")) * F.sqrt("n"))
    found = above.groupBy("lang").agg(F.first("center").alias("center"), F.percentile_approx("z", [quantile, 0.25, 0.75], 10000).alias("q"))
    normal = (F.get("q", F.lit(2)) - F.get("q", F.lit(1))) * (TAIL * NormalDist().inv_cdf(quantile) / (2 * NormalDist().inv_cdf(0.75)))
    return found.select("lang", "center", F.when(normal > 0, F.least(F.get("q", F.lit(0)), normal)).otherwise(F.get("q", F.lit(0))).alias("excess"))


def row_id() -> Column:
    """Digest of a row; a null differs from every value."""
    part = lambda c: F.coalesce(F.concat(F.lit("="), F.col(c).cast("string")), F.lit("-"))
    return F.md5(F.concat_ws("\0", part("doc_id"), part("lang"), part("text")).cast("binary"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """All columns of the documents that are not rejected."""
    bad = classify(docs.select("doc_id", "lang", "text"), labels).where(~F.col("keep")).select(F.col("id").alias("__bad")).distinct()
    bad = cut(bad)
    rows = docs.select(F.struct("*").alias("__row"), row_id().alias("__bad"))
    return rows.join(F.broadcast(bad) if bad.count() <= SMALL else bad, "__bad", "left_anti").select("__row.*")


def op5_quality_classifier(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang", "text")
    return classify(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")).drop("id")
