"""Language identification by prediction by partial matching.

Per language a tree of byte contexts of variable order (0 to DEPTH) with escape probabilities (method C: a context seen n
times with q different successors gives q / (n + q) to an escape and c / (n + q) to a successor seen c times). The
statistics are frozen after training, so the exact code length of every (context, byte) is a number: all of them are
computed once, for all languages together, and a text's code length under each language is a sum of table rows. The
language with the shortest code wins.

Training reads rows with a language outside the held-out fifth: all of them up to about SAMPLE rows per language, above
that a hash sample of that expected size (a documented bound). Counting is distributed; the driver gets one row per
(language, 5 bytes) seen.

Null or letterless text is "und" with score 0. Very long texts are scored whole. Ties go to the alphabetically first language. Repeated rows are treated
alike; other columns are ignored; an empty table gives an empty result; without training rows every text is "und".
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_slices

DEPTH, SAMPLE, CHUNK = 4, 1500, 1 << 20
LETTER = re.compile(r"[^\W\d_]")


def held_out() -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def contexts(data: bytes) -> np.ndarray:
    """One packed 5-byte key per byte: its DEPTH predecessors (zeros before the start) and itself."""
    raw = np.frombuffer(b"\0" * DEPTH + data, np.uint8).astype(np.uint64)
    out = np.zeros(len(data), np.uint64)
    for j in range(DEPTH + 1):
        out = out << np.uint64(8) | raw[j : j + len(data)]
    return out


def count_bytes(docs: DataFrame) -> DataFrame:
    """lang, k, c over docs(lang, text)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict[str, list] = {}
        size: dict[str, int] = {}

        def flush(lang):
            k, c = np.unique(np.concatenate(held.pop(lang)), return_counts=True)
            size.pop(lang)
            return pd.DataFrame({"lang": lang, "k": k.view(np.int64), "c": c.astype(np.int64)})

        for b in batches:
            for lang, text in zip(b["lang"], b["text"], strict=True):
                held.setdefault(lang, []).append(contexts(text.encode("utf-8", "surrogatepass")))
                size[lang] = size.get(lang, 0) + len(text)
                if size[lang] > CHUNK:
                    yield flush(lang)
        for lang in list(held):
            yield flush(lang)

    return map_slices(docs.select("lang", "text"), run, "lang string, k long, c long").groupBy("lang", "k").agg(F.sum("c").alias("c"))


class HashIndex:
    """Position of 64-bit keys in a table, for whole arrays at once; -1 where absent."""

    def __init__(self, keys: np.ndarray):
        self.bits = max(4, int(len(keys) * 3).bit_length())
        size = 1 << self.bits
        self.slots, self.where = np.zeros(size, np.uint64), np.full(size, -1, np.int32)
        todo, at = np.arange(len(keys)), self.home(keys)
        while len(todo):
            free = self.where[at] < 0
            first = np.unique(at[free], return_index=True)[1]
            put = np.flatnonzero(free)[first]
            self.where[at[put]], self.slots[at[put]] = todo[put], keys[todo[put]]
            stay = np.ones(len(todo), bool)
            stay[put] = False
            todo, at = todo[stay], (at[stay] + 1) & (size - 1)

    def home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        at = self.home(keys)
        out = self.where[at]
        wrong = np.flatnonzero((out >= 0) & (self.slots[at] != keys))
        while len(wrong):
            at[wrong] = (at[wrong] + 1) & (len(self.where) - 1)
            out[wrong] = self.where[at[wrong]]
            wrong = wrong[(out[wrong] >= 0) & (self.slots[at[wrong]] != keys[wrong])]
        return out


class ContextTrees:
    """Code lengths (bits) of every known (context, byte) and of every context's escape, a column per language."""

    def __init__(self, langs: list[str], counts: dict[str, tuple[np.ndarray, np.ndarray]]):
        self.langs, self.grams, self.escapes = langs, [], []
        n = len(langs)
        level = counts
        levels = [level]
        for size in range(DEPTH, 0, -1):
            mask, less = np.uint64((1 << (8 * size)) - 1), {}
            for lang, (k, c) in level.items():
                short, at = np.unique(k & mask, return_inverse=True)
                less[lang] = (short, np.bincount(at, weights=c, minlength=len(short)).astype(np.int64))
            level = less
            levels.append(level)
        lower = None
        for size, level in enumerate(reversed(levels), 1):  # size: bytes of a gram, context and symbol
            keys = np.unique(np.concatenate([k for k, _ in level.values()]))
            ctx = np.unique(keys >> np.uint64(8)) if size > 1 else np.zeros(1, np.uint64)
            if lower is None:
                bits = np.full((len(keys), n), 8.0)
            else:
                bits = lower[1][lower[0].find(keys & np.uint64((1 << (8 * (size - 1))) - 1))].copy()
            escape = np.zeros((len(ctx), n))
            own = np.searchsorted(ctx, keys >> np.uint64(8) if size > 1 else np.zeros(len(keys), np.uint64))
            for j, lang in enumerate(langs):
                k, c = level[lang]
                seen = np.zeros(len(keys))
                seen[np.searchsorted(keys, k)] = c
                total, kinds = np.bincount(own, weights=seen, minlength=len(ctx)), np.bincount(own, weights=seen > 0, minlength=len(ctx))
                known = total > 0
                escape[known, j] = -np.log2(kinds[known] / (total[known] + kinds[known]))
                hit = seen > 0
                bits[:, j] = np.where(hit, -np.log2(np.maximum(seen, 1) / np.maximum((total + kinds)[own], 1)), bits[:, j] + escape[own, j])
            lower = (HashIndex(keys), bits)
            self.grams.append((lower[0], bits.astype(np.float32)))
            self.escapes.append((HashIndex(ctx), escape.astype(np.float32)))

    def lengths(self, keys: np.ndarray) -> np.ndarray:
        """Code length of each 5-byte key's last byte, a column per language."""
        out = np.zeros((len(keys), len(self.langs)), np.float32)
        todo = np.arange(len(keys))
        for size in range(DEPTH + 1, 0, -1):
            k = keys[todo] & np.uint64((1 << (8 * size)) - 1) if size <= DEPTH else keys[todo]
            index, bits = self.grams[size - 1]
            at = index.find(k)
            hit = at >= 0
            if hit.all() and len(todo) == len(keys):
                return bits[at]
            out[todo[hit]] += bits[at[hit]]
            todo, k = todo[~hit], k[~hit]
            if not len(todo):
                return out
            index, escape = self.escapes[size - 1]
            at = index.find(k >> np.uint64(8) if size > 1 else np.zeros(len(k), np.uint64))
            out[todo[at >= 0]] += escape[at[at >= 0]]
        out[todo] += 8.0
        return out


def train(docs: DataFrame, sample: int = SAMPLE) -> ContextTrees | None:
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    sizes = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}
    if not sizes:
        return None
    share = F.create_map(*[x for lang, n in sorted(sizes.items()) for x in (F.lit(lang), F.lit(min(1.0, sample / n)))])
    draw = F.pmod(F.xxhash64(F.lit("language sample"), "doc_id"), F.lit(1 << 30)) / float(1 << 30)
    t = count_bytes(rows.where(draw < F.element_at(share, F.col("lang")))).toArrow()
    lang, k, c = np.array(t["lang"].to_pylist(), object), t["k"].to_numpy().view(np.uint64), t["c"].to_numpy()
    langs = sorted(set(lang.tolist()))
    return ContextTrees(langs, {x: (k[lang == x], c[lang == x]) for x in langs}) if langs else None


def identify(docs: DataFrame, model: ContextTrees | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score (posterior of the winner), bits_per_byte of docs(doc_id, text)."""
    shared = docs.sparkSession.sparkContext.broadcast(cloudpickle.dumps(model))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m = cloudpickle.loads(shared.value)
        for b in batches:
            pred, score, rate = ["und"] * len(b), np.zeros(len(b)), np.full(len(b), np.nan)
            held: list[tuple[int, np.ndarray]] = []
            size = 0

            def settle() -> None:
                if not held:
                    return
                bits = m.lengths(np.concatenate([k for _, k in held]))
                starts = np.cumsum([0] + [len(k) for _, k in held[:-1]])
                total = np.add.reduceat(bits, starts, axis=0, dtype=np.float64)
                best = total.argmin(axis=1)
                for (i, k), j, row in zip(held, best, total, strict=True):
                    pred[i], rate[i] = m.langs[j], row[j] / len(k)
                    score[i] = 1 / np.exp2(np.maximum(-1000.0, row[j] - row)).sum()
                held.clear()

            for i, text in enumerate(b["text"]):
                if m is not None and text and LETTER.search(text):
                    held.append((i, contexts(text.encode("utf-8", "surrogatepass"))))
                    size += len(text)
                    if size > CHUNK:
                        settle()
                        size = 0
            settle()
            yield pd.DataFrame({"doc_id": b["doc_id"], "held_out": b["held_out"], "lang_pred": pred, "score": score, "bits_per_byte": rate})

    return map_slices(docs.select("doc_id", held_out().alias("held_out"), "text"), run, "doc_id long, held_out boolean, lang_pred string, score double, bits_per_byte double")


def op9_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    return identify(docs.select("doc_id", "text"), train(docs))
