"""N-gram Jaccard join by prefix trees: classes of documents that are linked by Jaccard similarity >= 3/4.

Documents with equal shingle sets make one class; everything below works on classes.

Global order. Shingles are ordered by (how often their bucket was seen more than once in a block of the input, digest).
The bucket counts are an array of fixed size, filled from all documents; passages that many documents share come last.

Prefix tree. `PrefixTree` stores sets in that order, sorted, with the length each shares with its predecessor - a trie
without node objects. A query walks it once: overlaps of a shared beginning are counted once, and as soon as the
overlap so far plus what can still come (of the query or of the longest set below) is too small, the whole subtree goes.

Which sets meet in a tree:
  1. Stars: classes with the same two minima under a pair of hash functions meet one of them. Whatever is linked there
     becomes one group, so large groups of near copies are never paired with each other.
  2. The rest, exactly: two linked sets share a shingle within the first n - ceil(3n/4) + 1 of their global order.
     Classes of different groups that do, and pass the length and remaining-length bounds there, meet in a tree.
In the second step the classes of the smaller group walk the tree of the whole other group, so what is sent grows with
classes and groups, not with pairs of them. Shingles with more than HOT classes are dealt out in blocks of classes, and
pairs of blocks are tasks of their own. Trees come in parts of about BLOCK members and at most about TREE_BYTES. Groups are
the components of the links found, computed on the executors. `class_links` gives all links between classes instead.

Null or blank text: empty set, linked with nothing, its own component. Repeated rows are copies of each other; a null
doc_id never names a component unless it is alone. Very long texts are shingled whole, one at a time. Other columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, discard, map_slices
from .components import components
from .word_sets import GOLD, Shingler, mix, set_digest

SIZE, BLOCK, SALT = 5, 256, 32
#: Pairs of hash functions whose two minima make a key: unrelated sets hardly ever share one.
KEYS = ((0, 1), (2, 3), (0, 3), (1, 2))
BUCKETS, FLUSH = 1 << 20, 2_000_000
#: Classes of a shingle that are paired in one task, and bytes of the sets of one tree.
HOT, TREE_BYTES = 4096, 16 << 20
#: Largest tables that are broadcast, in rows (up to 40 bytes each); beyond that the same rows are joined by a shuffle.
SMALL = 1_000_000
#: Stands for a null doc_id in arrays.
NOBODY = -(2**63)


def needed(n: int, m: np.ndarray) -> np.ndarray:
    """Least overlap of linked sets of n and m shingles: 100 * overlap >= 75 * union."""
    return -(-3 * (n + m) // 7)


def close(n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Whether sets of these sizes can be linked at all."""
    return 4 * np.minimum(n, m) >= 3 * np.maximum(n, m)


def prefix(n: int) -> int:
    return n - (3 * n + 3) // 4 + 1


def ordered(s: np.ndarray, order: np.ndarray) -> np.ndarray:
    return s[np.lexsort((s, order[(s & np.uint64(len(order) - 1)).astype(np.int64)]))]


class PrefixTree:
    """Trie over globally ordered sets, kept as their sorted list and the beginnings they share."""

    def __init__(self, sets: list[np.ndarray]):
        self.at = sorted(range(len(sets)), key=lambda i: sets[i].astype(">u8").tobytes())
        self.sets = [sets[i] for i in self.at]
        self.shared = [0] * len(sets)
        for i in range(1, len(sets)):
            a, b = self.sets[i - 1], self.sets[i]
            n = min(len(a), len(b))
            differ = np.flatnonzero(a[:n] != b[:n])
            self.shared[i] = int(differ[0]) if len(differ) else n

    def linked(self, query: np.ndarray, first_only: bool = False) -> list[tuple[int, int]]:
        """(index, overlap) of all stored sets that are linked with the query, or of one of them."""
        out, sorted_query, i, n = [], np.sort(query), 0, len(query)
        sizes = np.array([len(s) for s in self.sets])
        need = needed(n, sizes)
        able = close(np.array(n), sizes)
        partial = np.zeros(1, np.int64)  # overlap of each beginning of the current path
        while i < len(self.sets):
            s, keep = self.sets[i], self.shared[i]
            if not able[i]:
                # A skipped set leaves the path as far as the next one shares it with what is known.
                if i + 1 < len(self.sets):
                    self_next = min(self.shared[i + 1], keep, len(partial) - 1)
                    partial = partial[: self_next + 1]
                i += 1
                continue
            known = min(keep, len(partial) - 1)
            tail = s[known:]
            where = np.searchsorted(sorted_query, tail)
            hit = (where < n) & (sorted_query[np.minimum(where, n - 1)] == tail)
            partial = np.concatenate((partial[: known + 1], partial[known] + np.cumsum(hit)))
            if partial[-1] >= need[i]:
                out.append((self.at[i], int(partial[-1])))
                if first_only:
                    return out
            j = i + 1
            while j < len(self.sets):  # subtrees below a beginning that already lacks too much
                k = min(self.shared[j], len(partial) - 1)
                if partial[k] + min(n - partial[k], sizes[j] - k) >= need[j]:
                    break
                partial = partial[: min(k, self.shared[j + 1] if j + 1 < len(self.sets) else k) + 1]
                j += 1
            if j < len(self.sets):
                partial = partial[: min(self.shared[j], len(partial) - 1) + 1]
            i = j
        return out


def joined(minima: list[np.uint64]) -> list[int]:
    """The keys of a set from its minima."""
    m = np.array(minima)
    return [int(x) for x in mix(m[[i for i, _ in KEYS]] * np.uint64(GOLD) + m[[j for _, j in KEYS]]).view(np.int64)]


def first_pass(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, th (digest of the text), klass, n, keys; and, in rows of their own, bucket and hits of shingles
    seen repeatedly."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, held, size, known = Shingler(SIZE), [], 0, set()
        salts = [mix(np.array([j + 1], np.uint64) * np.uint64(GOLD))[0] for j in range(4)]

        def flush():
            values, counts = np.unique(np.concatenate(held), return_counts=True)
            many = counts > 1
            hits = np.bincount((values[many] & np.uint64(BUCKETS - 1)).astype(np.int64), weights=counts[many], minlength=0)
            at = np.flatnonzero(hits)
            return pd.DataFrame({"doc_id": None, "th": None, "klass": None, "n": None, "keys": None, "bucket": at, "hits": hits[at].astype(np.int64)})

        for b in batches:
            sets = shingler.sets(b["text"].tolist())
            classes = [set_digest(s) for s in sets]
            keys = [joined([mix(s ^ k).min() for k in salts]) if len(s) else [] for s in sets]
            yield pd.DataFrame({"doc_id": b["doc_id"], "th": b["th"], "klass": classes, "n": [len(s) for s in sets], "keys": keys, "bucket": None, "hits": None})
            for s, c in zip(sets, classes, strict=True):
                if len(s) and c not in known:
                    known.add(c)
                    held.append(s)
                    size += len(s)
                    if size >= FLUSH:
                        yield flush()
                        held, size = [], 0
            if len(known) > 1_000_000:
                known.clear()
        if held:
            yield flush()

    return map_slices(docs.select("doc_id", "text", F.xxhash64("text").alias("th")), run, "doc_id long, th long, klass long, n long, keys array<long>, bucket long, hits long")


def lookup(df: DataFrame, key: str, *values: str):
    """Broadcast of (sorted keys, their values ...) if there are at most SMALL rows; else None."""
    df = cut(df)
    if df.count() > SMALL:
        return df, None
    t = df.toArrow()
    keys = t[key].to_numpy()
    at = np.argsort(keys, kind="stable")
    return df, df.sparkSession.sparkContext.broadcast((keys[at], *[t[v].to_numpy()[at] for v in values]))


def find(shared, klass: np.ndarray) -> np.ndarray:
    """Positions in the broadcast keys, or -1."""
    keys = shared.value[0]
    if not len(keys):
        return np.full(len(klass), -1)
    at = np.minimum(np.searchsorted(keys, klass), len(keys) - 1)
    return np.where(keys[at] == klass, at, -1)


def fetch_sets(docs: DataFrame, wanted: DataFrame, order) -> DataFrame:
    """klass, members (ordered set as bytes) of the classes in wanted(klass)."""
    wanted, shared = lookup(wanted, "klass")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, known = Shingler(SIZE), set()
        for b in batches:
            sets = shingler.sets(b["text"].tolist())
            classes = np.array([set_digest(s) for s in sets], np.int64)
            take = find(shared, classes) >= 0 if shared else np.ones(len(sets), bool)
            rows = []
            for i in np.flatnonzero(take):
                if len(sets[i]) and int(classes[i]) not in known:
                    known.add(int(classes[i]))
                    rows.append((int(classes[i]), ordered(sets[i], order.value).tobytes()))
            yield pd.DataFrame(rows, columns=["klass", "members"])

    sets = map_slices(docs.select("text"), run, "klass long, members binary")
    if not shared:
        sets = sets.join(wanted, "klass", "left_semi")
    return sets.dropDuplicates(["klass"])


def deliveries(docs: DataFrame, places: DataFrame, classes: DataFrame, order) -> DataFrame:
    """tree, part, kind, klass, members: the set of each class in places(tree, part, kind, klass), once per place.

    Up to SMALL places they are broadcast, and the documents that stand for the classes send their sets straight there.
    Beyond that, sets and places are joined."""
    if places.count() > SMALL:
        return places.join(fetch_sets(docs, places.select("klass").distinct(), order), "klass").select("tree", "part", "kind", "klass", "members")
    t = places.join(classes.select("klass", F.coalesce("doc_id", F.lit(NOBODY)).alias("doc_id")), "klass").toArrow()
    at = np.argsort(t["klass"].to_numpy(), kind="stable")
    shared = docs.sparkSession.sparkContext.broadcast(tuple(t[c].to_numpy()[at] for c in ("klass", "doc_id", "tree", "part", "kind")))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, (klass, doc_id, tree, part, kind) = Shingler(SIZE), shared.value
        stands = np.unique(doc_id)
        for b in batches:
            ids = b["doc_id"].fillna(NOBODY).to_numpy(np.int64)
            known = np.minimum(np.searchsorted(stands, ids), max(0, len(stands) - 1))
            able = np.flatnonzero(stands[known] == ids) if len(stands) else []
            rows = []
            for i, s in zip(able, shingler.sets([b["text"].iloc[i] for i in able]), strict=True):
                c = set_digest(s)
                lo, hi = np.searchsorted(klass, c, "left"), np.searchsorted(klass, c, "right")
                if lo < hi and len(s) and doc_id[lo] == ids[i]:
                    data = ordered(s, order.value).tobytes()
                    for k in range(lo, hi):
                        rows.append((tree[k], part[k], kind[k], c, data))
                        if len(rows) == 2000:
                            yield pd.DataFrame(rows, columns=["tree", "part", "kind", "klass", "members"])
                            rows = []
            yield pd.DataFrame(rows, columns=["tree", "part", "kind", "klass", "members"])

    return map_slices(docs.select("doc_id", "text"), run, "tree long, part long, kind int, klass long, members binary")


MEMBER, QUERY = 0, 1


def walked(docs: DataFrame, places: DataFrame, classes: DataFrame, order, first_only: bool) -> DataFrame:
    """a, b: links of queries a with members b of their trees; with first_only one per query and part of a tree."""
    places = cut(places)
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = deliveries(docs, places, classes, order).repartition(parts, "tree", "part").sortWithinPartitions("tree", "part", "kind", "klass")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        key, held, tree, names, last, out = None, {}, None, [], None, []
        for b in batches:
            for t, part, kind, klass, members in b.itertuples(index=False, name=None):
                if key != (t, part):
                    key, held, tree, last = (t, part), {}, None, None
                s = np.frombuffer(members, np.uint64)
                if kind == MEMBER:
                    held[klass] = s
                    continue
                if klass == last:
                    continue
                last = klass
                if tree is None:
                    names, tree = list(held), PrefixTree(list(held.values()))
                found = [names[i] for i, _ in tree.linked(s, first_only)]
                out += [(klass, x) for x in found if x != klass]
            if len(out) > 10_000:
                yield pd.DataFrame(out, columns=["a", "b"])
                out = []
        yield pd.DataFrame(out, columns=["a", "b"], dtype=np.int64)

    out = cut(rows.mapInPandas(run, "a long, b long"))
    discard(places)
    return out


def tree_parts(size: str) -> Column:
    """Parts of a tree of all rows of a group, with `size` shingles each."""
    return F.ceil(F.greatest(F.count("*") / BLOCK, F.sum(F.coalesce(size, F.lit(0))) * 8 / TREE_BYTES))


def star_places(pairs: DataFrame) -> DataFrame:
    """A tree of all b for each a of pairs(a, b, size), in parts, and a as the query of every part."""
    pairs = cut(pairs)
    sizes = cut(pairs.groupBy("a").agg(tree_parts("size").alias("parts")))
    queries = sizes.select(F.col("a").alias("tree"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(QUERY).alias("kind"), F.col("a").alias("klass"))
    members = pairs.join(sizes, "a").select(F.col("a").alias("tree"), F.pmod(F.xxhash64("b"), F.col("parts")).alias("part"), F.lit(MEMBER).alias("kind"), F.col("b").alias("klass"))
    return queries.unionByName(members)


def group_places(requests: DataFrame, groups: DataFrame, classes: DataFrame) -> DataFrame:
    """A tree of each group that requests(x, root) ask for, in parts, with the queries x of all of them. A tree with many
    queries is repeated, and its queries are dealt out over the copies."""
    asked = cut(requests.groupBy("root").agg(F.ceil(F.count("*") / (8 * BLOCK)).alias("copies")))
    own = groups.select("node", "root").join(asked, "root").join(classes.select(F.col("klass").alias("node"), "n"), "node", "left")
    sizes = own.groupBy("root").agg(tree_parts("n").alias("parts"))
    asked = cut(asked.join(sizes, "root", "left").select("root", "copies", F.coalesce("parts", F.lit(1)).alias("parts")))
    own = own.select("node", "root").unionByName(asked.join(groups.select("root").distinct(), "root", "left_anti").select(F.col("root").alias("node"), "root"))
    members = own.join(asked, "root").select(F.col("root").alias("tree"), F.pmod(F.xxhash64("node"), F.col("parts")).alias("p"), "copies", "parts", F.col("node").alias("klass"))
    members = members.select("tree", F.explode(F.sequence(F.lit(0), F.col("copies") - 1)).alias("c"), "p", "parts", "klass")
    members = members.select("tree", (F.col("c") * F.col("parts") + F.col("p")).alias("part"), F.lit(MEMBER).alias("kind"), "klass")
    queries = requests.join(asked, "root").select(F.col("root").alias("tree"), F.pmod(F.xxhash64("x"), F.col("copies")).alias("c"), "parts", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("p"), F.col("x").alias("klass"))
    return members.unionByName(queries.select("tree", (F.col("c") * F.col("parts") + F.col("p")).alias("part"), F.lit(QUERY).alias("kind"), "klass"))


def star_pairs(classes: DataFrame) -> DataFrame:
    """a, b, size (of b): each class with one class that has the same key, for each key; which one is drawn anew for each
    key, so that a class meets several members of a large group."""
    keyed = classes.where("n > 0").select("klass", "n", F.posexplode("keys").alias("j", "key"))
    first = keyed.groupBy("j", "key").agg(F.min(F.struct(F.xxhash64("klass", "j").alias("h"), "klass", "n")).alias("f"), F.count("*").alias("c")).where("c > 1")
    first = first.select("j", "key", F.col("f.klass").alias("a"), F.col("f.n").alias("m"), F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))).alias("salt"))
    keyed = keyed.withColumn("salt", F.pmod("klass", F.lit(SALT)).cast("int"))
    both = keyed.join(first, ["j", "key", "salt"]).where("a <> klass and 4 * least(n, m) >= 3 * greatest(n, m)")
    return both.select(F.least("a", "klass").alias("a"), F.greatest("a", "klass").alias("b"), F.when(F.col("klass") > F.col("a"), F.col("n")).otherwise(F.col("m")).alias("size")).distinct()


def prefix_rows(docs: DataFrame, groups: DataFrame, order) -> DataFrame:
    """token, klass, root and group (0: alone; else the size of its group), size (n, position): each class under the first
    shingles of its set. salt: 0, or for tokens that the order knows to be frequent how their rows are dealt out."""
    counts = groups.groupBy("root").agg(F.count("*").alias("group"))
    groups, shared = lookup(groups.join(counts, "root").select("node", "root", "group"), "node", "root", "group")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, known = Shingler(SIZE), set()
        for b in batches:
            sets = shingler.sets(b["text"].tolist())
            classes = np.array([set_digest(s) for s in sets], np.int64)
            at = find(shared, classes) if shared else np.full(len(sets), -1)
            out, held = [], 0
            for i, s in enumerate(sets):
                c = int(classes[i])
                if not len(s) or c in known:
                    continue
                known.add(c)
                p = prefix(len(s))
                root, group = (shared.value[1][at[i]], shared.value[2][at[i]]) if at[i] >= 0 else (0, 0)
                token = ordered(s, order.value)[:p]
                often = order.value[(token & np.uint64(BUCKETS - 1)).astype(np.int64)] > HOT
                out.append((token.view(np.int64), np.full(p, c), np.full(p, root), np.full(p, group), (len(s) << 32) + np.arange(p), np.where(often, 1 + c % SALT, 0)))
                held += p
                if held > 200_000:
                    yield pd.DataFrame(dict(zip(PREFIX, map(np.concatenate, zip(*out, strict=True)), strict=True)))
                    out, held = [], 0
            if out:
                yield pd.DataFrame(dict(zip(PREFIX, map(np.concatenate, zip(*out, strict=True)), strict=True)))

    rows = map_slices(docs.select("text"), run, ", ".join(f"{c} long" for c in PREFIX))
    if not shared:
        rows = rows.drop("root", "group").join(groups, rows["klass"] == groups["node"], "left").select("token", "klass", F.coalesce("root", F.lit(0)).alias("root"), F.coalesce("group", F.lit(0)).alias("group"), "size", "salt")
    return rows


PREFIX = ["token", "klass", "root", "group", "size", "salt"]


def asking(cell: np.ndarray, klass: np.ndarray, root: np.ndarray, group: np.ndarray, size: np.ndarray, block: np.ndarray, same: np.ndarray) -> Iterator[pd.DataFrame]:
    """x, root of all pairs of different groups in a cell that pass the bounds; rows come in order of cell and klass.

    All cells advance together: step k holds every row against the k-th row after it. In cells that are not `same`, only
    rows of different blocks make pairs."""
    if len(cell) < 2:
        return
    fresh = np.concatenate(([True], (cell[1:] != cell[:-1]) | (klass[1:] != klass[:-1])))
    cell, klass, root, group, size, block, same = (x[fresh] for x in (cell, klass, root, group, size, block, same))
    own, n = np.where(group == 0, klass, root), size >> 32
    rest = n - (size & 0xFFFFFFFF)
    first = np.concatenate(([True], cell[1:] != cell[:-1]))
    end = np.append(np.flatnonzero(first)[1:], len(cell))[np.cumsum(first) - 1]
    i, step, x_out, r_out, held = np.arange(len(cell)), 1, [], [], 0
    while True:
        i = i[i + step < end[i]]
        if not len(i):
            break
        j = i + step
        ok = (own[i] != own[j]) & close(n[i], n[j]) & (np.minimum(rest[i], rest[j]) >= needed(n[i], n[j])) & (same[i] | (block[i] != block[j]))
        a, b = i[ok], j[ok]
        asks = (group[a] < group[b]) | ((group[a] == group[b]) & (own[a] < own[b]))
        x_out.append(np.where(asks, klass[a], klass[b]))
        r_out.append(np.where(asks, own[b], own[a]))
        held, step = held + len(a), step + 1
        if held > 200_000:
            yield pd.DataFrame({"x": np.concatenate(x_out), "root": np.concatenate(r_out)}).drop_duplicates()
            x_out, r_out, held = [], [], 0
    if held:
        yield pd.DataFrame({"x": np.concatenate(x_out), "root": np.concatenate(r_out)}).drop_duplicates()


def prefix_requests(rows: DataFrame) -> DataFrame:
    """x, root: classes that must be held against another group, because they share a token with one of its members where
    the length and remaining-length bounds still allow a link. Of two groups, the members of the smaller one ask.

    Tokens meet where they are dealt; those with more than HOT rows are not paired there but passed on (no task holds
    them all), and meet in cells, a cell for every two blocks of about HOT / 2 of their classes."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.repartition(parts, "token", "salt").sortWithinPartitions("token", "klass")
    later = PREFIX[:5]

    def some(rows: list[np.ndarray]) -> Iterator[pd.DataFrame]:
        yes = np.ones(len(rows[0]), bool)
        for out in asking(*rows[:5], np.zeros(len(yes), np.int64), yes):
            yield out.assign(token=None, klass=None, group=None, size=None)

    def passed(rows: list[np.ndarray]) -> pd.DataFrame:
        return pd.DataFrame({"x": None, **dict(zip(later, rows[:5], strict=True))})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rest, hot, columns = None, None, ["x", "root", "token", "klass", "group", "size"]
        for b in batches:
            now = [b[c].to_numpy() for c in PREFIX]
            far = (now[5] > 0) | (now[0] == hot if hot is not None else False)
            if far.any():
                yield passed([x[far] for x in now])[columns]
                now = [x[~far] for x in now]
            if rest is not None:
                now = [np.concatenate(x) for x in zip(rest, now, strict=True)]
            if not len(now[0]):
                continue
            cut_at = int(np.searchsorted(now[0], now[0][-1]))
            rest = [x[cut_at:] for x in now]
            for out in some([x[:cut_at] for x in now]):
                yield out[columns]
            if len(rest[0]) > HOT:
                hot = rest[0][0]
                yield passed(rest)[columns]
                rest = None
        if rest is not None:
            for out in some(rest):
                yield out[columns]

    found = cut(dealt.mapInPandas(run, "x long, root long, token long, klass long, group long, size long"))
    near, far = found.where("x is not null").select("x", "root"), found.where("x is null").select(*later)
    if far.isEmpty():
        return near.distinct()
    blocks = far.groupBy("token").agg(F.ceil(2 * F.count("*") / HOT).cast("int").alias("blocks"))
    far = far.join(blocks, "token").withColumn("block", F.pmod(F.xxhash64("klass"), F.col("blocks")).cast("int"))
    far = far.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    far = far.withColumn("cell", F.xxhash64("token", F.least("block", "other"), F.greatest("block", "other")))
    # A cell of a block with itself comes once, with all of its pairs.
    far = far.withColumn("same", F.col("block") == F.col("other")).select("cell", "klass", "root", "group", "size", "block", "same")
    cells = far.repartition(parts, "cell").sortWithinPartitions("cell", "klass")

    def meet(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rest = None
        for b in batches:
            now = [b[c].to_numpy() for c in b.columns]
            if rest is not None:
                now = [np.concatenate(x) for x in zip(rest, now, strict=True)]
            if len(now[0]):
                cut_at = int(np.searchsorted(now[0], now[0][-1]))
                rest = [x[cut_at:] for x in now]
                yield from asking(*[x[:cut_at] for x in now])
        if rest is not None:
            yield from asking(*rest)

    return near.unionByName(cells.mapInPandas(meet, "x long, root long")).distinct()


def class_order(spark: SparkSession, all_rows: DataFrame):
    """Broadcast of the hits of each bucket: an array of fixed size."""
    order = np.zeros(BUCKETS, np.int32)
    seen = all_rows.where("bucket is not null").groupBy("bucket").agg(F.sum("hits").alias("hits")).toArrow()
    order[seen["bucket"].to_numpy()] = np.minimum(seen["hits"].to_numpy(), 2**31 - 1)
    return spark.sparkContext.broadcast(order)


def first_row() -> Column:
    """By which the rows of a component are ordered: a null doc_id comes last, equal ones by the digest of their text."""
    return F.struct(F.col("doc_id").isNull().alias("no"), F.col("doc_id"), F.col("th"))


def classes_of(slim: DataFrame) -> DataFrame:
    """klass, n, keys, first, doc_id (the smallest) of all classes of rows."""
    out = slim.groupBy("klass").agg(F.max("n").alias("n"), F.first("keys").alias("keys"), F.min(first_row()).alias("first"))
    return cut(out.withColumn("doc_id", F.col("first.doc_id")))


def rows_of_components(docs: DataFrame) -> DataFrame:
    """doc_id, th, n, first (the row that names the component: no, doc_id, th) for every row of docs(doc_id, text)."""
    all_rows = cut(first_pass(docs))
    slim = all_rows.where("klass is not null").select("doc_id", "th", "klass", "n", "keys")
    order = class_order(docs.sparkSession, all_rows)
    classes = classes_of(slim)
    links = walked(docs, star_places(star_pairs(classes)), classes, order, first_only=False)
    groups = components(links)
    requests = cut(prefix_requests(prefix_rows(docs, groups, order)))
    more = walked(docs, group_places(requests, groups, classes), classes, order, first_only=True)
    discard(requests)
    if not more.isEmpty():
        groups = components(links.unionByName(more))
    firsts = classes.join(groups, classes["klass"] == groups["node"]).groupBy("root").agg(F.min("first").alias("first"))
    firsts = cut(firsts).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))))
    named = cut(groups.withColumn("salt", F.pmod("node", F.lit(SALT)).cast("int")).join(firsts, ["root", "salt"]).select(F.col("node").alias("klass"), F.col("first").alias("all")))
    named = cut(classes.where("n > 0").select("klass", "first").join(named, "klass", "left").select("klass", F.coalesce("all", "first").alias("first")))
    return slim.select("doc_id", "th", "klass", "n").join(named, "klass", "left").drop("klass")


def linked_classes(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of docs(doc_id, text)."""
    return rows_of_components(docs).select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("first.doc_id", "doc_id").alias("component_id"))


def class_links(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(links a, b: all pairs of linked classes, a < b; members klass, doc_id, n): the join itself, copies not expanded.

    Every class is a group of its own here, so all candidates of the prefix filter walk a tree."""
    all_rows = cut(first_pass(docs))
    slim = all_rows.where("klass is not null").select("doc_id", "th", "klass", "n", "keys")
    order, classes = class_order(docs.sparkSession, all_rows), classes_of(slim)
    alone = classes.select(F.col("klass").alias("node"), F.col("klass").alias("root")).limit(0)
    requests = cut(prefix_requests(prefix_rows(docs, alone, order)))
    found = walked(docs, group_places(requests, alone, classes), classes, order, first_only=False)
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), slim.select("klass", "doc_id", "n")


def keep_one(docs: DataFrame) -> DataFrame:
    """All columns of docs; of each component one row, of the smallest doc_id. Rows without words all stay."""
    rows = rows_of_components(docs.select("doc_id", "text")).where("n > 0")
    stays = F.col("first").eqNullSafe(first_row())
    counted = cut(rows.groupBy("doc_id", "th", stays.alias("stays")).agg(F.count("*").alias("n")).where("not stays or n > 1"))
    # A row is told by its doc_id and text; of repeated ones, any stays.
    key = ["__no", "__id", "__th"]
    told = [F.col("doc_id").isNull().alias("__no"), F.coalesce("doc_id", F.lit(0)).alias("__id")]
    gone, repeated = (counted.where(c).select(*told, F.col("th").alias("__th")) for c in ("not stays", "stays"))
    small = lambda df: F.broadcast(df) if df.count() <= SMALL else df
    every = docs.select(F.struct("*").alias("__row"), *told, F.xxhash64("text").alias("__th"))
    if repeated.isEmpty():
        return every.join(small(gone), key, "left_anti").select("__row.*")
    single = every.join(small(counted.select(*told, F.col("th").alias("__th"))), key, "left_anti").select("__row.*")
    return single.unionByName(every.join(small(repeated), key, "left_semi").dropDuplicates(key).select("__row.*"))


def op6_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return linked_classes(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


SQL = r"""
with recursive w as (select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') l from documents),
s as (select distinct doc_id, x from (select doc_id, unnest(case when len(l) = 0 then [] when len(l) < 5 then [array_to_string(l, ' ')] else [array_to_string(l[i : i + 4], ' ') for i in range(1, len(l) - 3)] end) x from w)),
n as (select doc_id, count(*) n from s group by doc_id),
o as (select a.doc_id a, b.doc_id b, count(*) c from s a join s b on a.x = b.x and a.doc_id <> b.doc_id group by all),
e as (select o.a, o.b from o join n p on p.doc_id = o.a join n q on q.doc_id = o.b where 100 * c >= 75 * (p.n + q.n - c)),
r(id, other) as (select doc_id, doc_id from documents union select r.id, e.b from r join e on r.other = e.a)
select d.doc_id, coalesce(n.n, 0)::bigint n_shingles, m.c component_id from documents d left join n using (doc_id) join (select id, min(other) c from r group by id) m on m.id = d.doc_id
"""
