"""Best-fit packing by minimum bin slack.

1. Tokenise in `mapInPandas`; only (doc_id, piece, start, length, crc) leave the workers. Documents longer than a
   sequence are cut into whole sequences and a rest.
2. Count pieces per length: at most `capacity` rows, whatever the size of the corpus. On that histogram the driver
   fills bin after bin: the longest piece left opens the bin, a bitset subset-sum (one big integer whose bit s says
   that s tokens can be reached) finds the fullest feasible combination of the remaining lengths, and the combination
   is removed - as many times at once as the counts allow, so the number of searches follows the number of lengths
   and not the number of bins.
3. Every piece gets its rank among the pieces of its length, from counts per input partition and ranks inside one,
   so no length is gathered in one task, and looks up the bin and offset of that rank in the broadcast plan (its
   size is bounded by the number of lengths).

Null text counts as empty (one piece that holds the end id alone). Repeated rows are packed as often as they occur.
Other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import re
import unicodedata
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import cut, map_slices, worker_store

CAPACITY, END_ID = 4096, 1
STORE = "tokenizer"


class WordTokenizer:
    """Ids of a text as little-endian unsigned 32-bit bytes, equal to the library's own, with a word cache of at most
    `cache` words of at most `longest` letters (about 200 bytes a word).

    The vocabulary's rules split at white space, letter runs, single digits and runs of other signs after lower-casing,
    and no merge crosses such a part. So a text of well-known characters is the concatenation of its parts, each of
    them encoded once; any other text goes to the library whole."""

    KNOWN = re.compile("[\x00-\x7fÀ-ÖØ-öø-ÿ]*")
    PARTS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^\sa-zß-öø-ÿ0-9]+", re.ASCII)

    def __init__(self, path: str, cache: int = 250_000, longest: int = 64):
        from tokenizers import Tokenizer

        self.library, self.size, self.longest, self.cache = Tokenizer.from_file(path), cache, longest, {}
        vocabulary = self.library.get_vocab(True)
        self.last = np.zeros(max(vocabulary.values()) + 1, bool)
        self.last[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True

    def whole(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.library.encode_batch(texts, add_special_tokens=False)]

    def encode(self, text: str) -> bytes:
        if not self.KNOWN.fullmatch(text) or "<|" in text:
            text = unicodedata.normalize("NFC", text)
            if not self.KNOWN.fullmatch(text) or "<|" in text:
                return self.whole([text])[0]
        parts = self.PARTS.findall(text.lower())
        cache = self.cache
        try:
            return b"".join(map(cache.__getitem__, parts))
        except KeyError:
            pass
        missing = list({p for p in parts if p not in cache})
        if len(cache) + len(missing) > self.size:
            # The words met first are the frequent ones: they stay, the younger half goes.
            for p in list(cache)[self.size // 2 :]:
                del cache[p]
            missing = list({p for p in parts if p not in cache})
        ids = np.array(self.library.encode(" ".join(missing), add_special_tokens=False).ids, np.uint32)
        ends = ((np.flatnonzero(self.last[ids]) + 1) * 4).tolist()
        raw, at, rare = ids.tobytes(), 0, {}
        for p, end in zip(missing, ends, strict=True):
            # Long words and what goes beyond the bound serve this text only.
            (cache if len(p) <= self.longest and len(cache) < self.size else rare)[p] = raw[at:end]
            at = end
        return b"".join([cache[p] if p in cache else rare[p] for p in parts] if rare else map(cache.__getitem__, parts))


def shared_tokenizer(path: str) -> WordTokenizer:
    """One tokenizer, with its word cache, for all tasks of this operator that a Python worker runs."""
    held = worker_store().setdefault(STORE, {})
    if path not in held:
        held[path] = WordTokenizer(path)
    return held[path]


def public_tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def pieces(docs: DataFrame, tokenizer_path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: one row per piece of docs(doc_id, text)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tok = shared_tokenizer(tokenizer_path or public_tokenizer_path("word_bpe_49k.json"))
        end, step = np.uint32(end_id).tobytes(), capacity * 4
        for b in batches:
            rows = []
            for i, text in zip(b["doc_id"], b["text"], strict=True):
                ids = tok.encode(text or "") + end
                for k, at in enumerate(range(0, len(ids), step)):
                    part = ids[at : at + step]
                    rows.append((i, k, at // 4, len(part) // 4, zlib.crc32(part)))
            yield pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32"])

    return map_slices(docs.select("doc_id", "text"), run, "doc_id long, piece int, start long, length long, ids_crc32 long", keeps=STORE)


def fullest(lengths: list[int], counts: dict[int, int], room: int) -> list[tuple[int, int]]:
    """The combination of lengths (descending, with counts) with the largest sum of at most `room`.

    Bit s of `reach` says that the sum s can be reached. Longer pieces come first, so that on the way back the sum is
    explained by the shortest pieces only where nothing longer can."""
    mask, reach, trail = (1 << (room + 1)) - 1, 1, []
    for w in lengths:
        if w > room:
            continue
        left, take = min(counts[w], room // w), 1
        while left > 0:
            take = min(take, left)
            new = (reach | reach << (w * take)) & mask
            if new != reach:
                trail.append((w, take, reach))
                reach = new
            left -= take
            take *= 2
        if reach >> room & 1:
            break
    goal, out = reach.bit_length() - 1, {}
    for w, take, before in reversed(trail):
        if not before >> goal & 1:
            out[w] = out.get(w, 0) + take
            goal -= w * take
    return list(out.items())


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> dict[str, np.ndarray]:
    """Bins for a histogram length -> number of pieces.

    Result: rows (length, first rank, pieces per bin, first bin, offset of the first such piece in its bin), sorted by
    length and first rank: piece number `rank` of its length lies in bin first_bin + (rank - first) // per."""
    counts = {w: n for w, n in histogram.items() if n > 0}
    order, used, rows, bins = sorted(counts, reverse=True), dict.fromkeys(counts, 0), [], 0
    while order:
        top = order[0]
        counts[top] -= 1
        chosen = dict(fullest(order, counts, capacity - top))
        counts[top] += 1
        chosen[top] = chosen.get(top, 0) + 1
        copies, offset = min(counts[w] // n for w, n in chosen.items()), 0
        for w, n in sorted(chosen.items(), reverse=True):
            rows.append((w, used[w], n, bins, offset))
            used[w] += n * copies
            counts[w] -= n * copies
            offset += n * w
        bins += copies
        order = [w for w in order if counts[w]]
    table = np.array(sorted(rows), np.int64).reshape(-1, 5)
    return {"length": table[:, 0], "first": table[:, 1], "per": table[:, 2], "bin": table[:, 3], "offset": table[:, 4], "bins": np.array([bins])}


def place(plan_: dict[str, np.ndarray], length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    keys = plan_["length"].astype(np.float64) * 2.0**40 + plan_["first"]
    at = np.searchsorted(keys, length.astype(np.float64) * 2.0**40 + rank, side="right") - 1
    inside = rank - plan_["first"][at]
    return plan_["bin"][at] + inside // plan_["per"][at], plan_["offset"][at] + inside % plan_["per"][at] * length


def pack(docs: DataFrame, tokenizer_path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for all of docs(doc_id, text)."""
    spark = docs.sparkSession
    found = cut(pieces(docs, tokenizer_path, capacity, end_id).withColumn("block", F.spark_partition_id()))
    per = found.groupBy("length", "block").agg(F.count("*").alias("n"))
    histogram = {r["length"]: r["n"] for r in per.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    made = spark.sparkContext.broadcast(plan(histogram, capacity))
    before = F.sum("n").over(Window.partitionBy("length").orderBy("block").rowsBetween(Window.unboundedPreceding, -1))
    offsets = per.select("length", "block", F.coalesce(before, F.lit(0)).alias("base"))
    local = F.row_number().over(Window.partitionBy("block", "length").orderBy("doc_id", "piece", "ids_crc32"))
    ranked = found.withColumn("rank", local - 1).join(offsets, ["block", "length"]).withColumn("rank", F.col("rank") + F.col("base"))

    @F.pandas_udf("sequence_id long, offset long")
    def locate(length: pd.Series, rank: pd.Series) -> pd.DataFrame:
        where, offset = place(made.value, length.to_numpy(), rank.to_numpy())
        return pd.DataFrame({"sequence_id": where, "offset": offset})

    return ranked.withColumn("at", locate("length", "rank")).select("doc_id", "piece", "start", "length", "ids_crc32", "at.sequence_id", "at.offset")


def op4_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
