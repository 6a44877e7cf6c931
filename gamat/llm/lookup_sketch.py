"""Document fingerprints by invertible Bloom lookup sketches, as DataFrame expressions only.

A text's blocks (runs of up to 40 words within a paragraph) are digested to 64 bits; each digest is added to one cell of
each of three subtables, and a cell keeps a count, the exclusive-or of its digests and that of their checksums. The
sketch is the fingerprint. Two sketches are subtracted cell by cell; cells that hold one digest are then peeled until
nothing is left, which yields the digests by which the texts differ. If peeling gets stuck, the two are sketched and
subtracted again with four times the cells. Where the largest table is stuck too, or the next table takes more than WORK
steps (cells times digests, as sketches and peeling are quadratic), the digests are compared directly, which counts the
same differences. likeness = shared / all different digests of both.

Texts of all lengths have the same blocks, so texts of any two lengths can share digests. Tables with fewer cells than
the numbers of digests differ by are left out: each digest that is peeled empties a cell, so they would get stuck.

The next document in descending order is found inside ranges of documents, with one shuffle of the texts; the first
document of every range is also dealt to the range before it. Ranges are cut by rank, not by the values of ids.

Null text counts as empty; an empty text has no blocks, and two of those are alike (1). Ties in doc_id are ordered by
the text's digest; a null doc_id comes last. Repeated rows stay separate rows. A single document is its own successor.
Very long texts are taken whole; beyond WORK their digests are compared directly. Other columns are ignored; an empty
table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import cut
from .line_templates import bind

CELLS, GROW, TRIES = 24, 4, 5
WORDS, WORK = 40, 65_536
#: Documents in a range, and how many ranges there are at most (beyond that, ranges grow); documents in a task likewise.
RANGE_ROWS, MOST_RANGES = 200, 200_000
PART_ROWS, MOST_PARTS = 3000, 50_000


def blocks(text: Column) -> Column:
    """Different 64-bit digests of the blocks of a text."""
    found = F.regexp_extract_all(text, F.lit(rf"(?:[^ \n]++ *+){{1,{WORDS}}}+"), F.lit(0))
    return F.array_distinct(F.transform(found, lambda x: F.xxhash64(F.rtrim(x))))


def spots(digest: Column, cells: int) -> list[Column]:
    third = cells // 3
    return [(F.pmod(F.xxhash64(digest, F.lit(j)), F.lit(third)) + j * third).cast("int") for j in range(3)]


def check(digest: Column) -> Column:
    return F.xxhash64(digest, F.lit(-1)).bitwiseAND(F.lit(0xFFFFFFFF))


def cell(i: Column, c: Column, k: Column, h: Column) -> Column:
    return F.struct(i.cast("int").alias("i"), c.cast("int").alias("c"), k.cast("long").alias("k"), h.cast("long").alias("h"))


def sketch(digests: Column, cells: int) -> Column:
    """All cells of the sketch of a set of digests."""

    def entry(d: Column) -> Column:
        a, b, c = spots(d, cells)
        return F.struct(d.alias("k"), check(d).alias("h"), a.alias("s0"), b.alias("s1"), c.alias("s2"))

    def table(e: Column) -> Column:
        def subtable(j: int):
            return lambda i: F.aggregate(F.filter(e, lambda x: x[f"s{j}"] == i), cell(i, F.lit(0), F.lit(0), F.lit(0)), lambda acc, x: cell(acc["i"], acc["c"] + 1, acc["k"].bitwiseXOR(x["k"]), acc["h"].bitwiseXOR(x["h"])))

        third = cells // 3
        return F.flatten(F.array(*[F.transform(F.sequence(F.lit(j * third), F.lit((j + 1) * third - 1)), subtable(j)) for j in range(3)]))

    return bind(F.transform(digests, entry), table)


def subtract(a: Column, b: Column) -> Column:
    """Cells of a - b that are not empty."""
    both = F.zip_with(a, b, lambda x, y: cell(x["i"], x["c"] - y["c"], x["k"].bitwiseXOR(y["k"]), x["h"].bitwiseXOR(y["h"])))
    return F.filter(both, lambda x: (x["c"] != 0) | (x["k"] != 0) | (x["h"] != 0))


def peel(cells_left: Column, cells: int, rounds: int) -> Column:
    """struct(left, found): what cannot be peeled, and the digests that could."""

    def step(acc: Column, _: Column) -> Column:
        pure = F.filter(acc["left"], lambda x: (F.abs(x["c"]) == 1) & (check(x["k"]) == x["h"]))
        keys = F.array_distinct(F.transform(pure, lambda x: F.struct(x["k"].alias("k"), x["c"].alias("c"), x["h"].alias("h"))))

        def located(x: Column) -> Column:
            a, b, c = spots(x["k"], cells)
            return F.struct(x["k"].alias("k"), x["c"].alias("c"), x["h"].alias("h"), a.alias("s0"), b.alias("s1"), c.alias("s2"))

        def without(p: Column) -> Column:
            def one(x: Column) -> Column:
                own = F.filter(p, lambda y: (y["s0"] == x["i"]) | (y["s1"] == x["i"]) | (y["s2"] == x["i"]))
                return F.aggregate(own, cell(x["i"], x["c"], x["k"], x["h"]), lambda t, y: cell(t["i"], t["c"] - y["c"], t["k"].bitwiseXOR(y["k"]), t["h"].bitwiseXOR(y["h"])))

            left = F.filter(F.transform(acc["left"], one), lambda x: (x["c"] != 0) | (x["k"] != 0) | (x["h"] != 0))
            return F.struct(left.alias("left"), F.concat(acc["found"], F.transform(p, lambda y: y["k"])).alias("found"))

        return F.when((F.size(acc["left"]) == 0), acc).otherwise(bind(F.transform(keys, located), without))

    return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), F.struct(cells_left.alias("left"), F.array().cast("array<long>").alias("found")), step)


def difference(a: Column, b: Column, cells: int, sketches: tuple[Column, Column] | None = None) -> Column:
    """Number of differing digests, or null if the peeling of sketches with so many cells gets stuck."""
    fa, fb = sketches or (sketch(a, cells), sketch(b, cells))
    return bind(peel(subtract(fa, fb), cells, 8 + cells.bit_length()), lambda s: F.when(F.size(s["left"]) == 0, F.size(F.array_distinct(s["found"]))))


def likeness(a: Column, b: Column, fa: Column, fb: Column) -> Column:
    """Likeness of two sketches (of CELLS cells) whose digests are a and b, with larger ones on failure."""
    apart = F.abs(F.size(a) - F.size(b))
    tries = [F.when(apart <= CELLS, difference(a, b, CELLS, (fa, fb)))]
    # Where even the differences of half the digests could not be peeled, the next larger table is tried at once.
    most = F.size(a) + F.size(b)
    for t in range(1, TRIES):
        cells = CELLS * GROW**t
        tries.append(F.when((most <= 8 * cells) & (apart <= cells) & (most * cells <= WORK), difference(a, b, cells)))
    exact = F.size(F.array_except(a, b)) + F.size(F.array_except(b, a))
    return bind(F.coalesce(*tries, exact), lambda d: F.when(most == 0, F.lit(1.0)).otherwise((most - d) / (most + d)))


def written(cells: Column) -> Column:
    """The sketch as a string: count, digests and checksums of each cell."""
    return F.array_join(F.transform(cells, lambda x: F.when(x["c"] == 0, F.lit("")).otherwise(F.concat_ws(":", x["c"].cast("string"), F.lower(F.hex(x["k"])), F.lower(F.hex(x["h"]))))), ",")


def place(cuts: Column, key: Column) -> Column:
    """How many of the sorted cuts are at most key: a binary search in as many steps as a table of MOST_RANGES needs."""
    steps = F.array(*[F.lit(1 << j) for j in range(MOST_RANGES.bit_length() + 1, -1, -1)])

    def step(low: Column, by: Column) -> Column:
        return F.when((low + by <= F.size(cuts)) & (F.get(cuts, low + by - 1) <= key), low + by).otherwise(low)

    return F.aggregate(steps, F.lit(0), step)


def order_key() -> Column:
    """What documents are ordered by; a null doc_id comes first in rising order."""
    return F.struct(F.col("doc_id").isNotNull().alias("p"), F.coalesce("doc_id", F.lit(0)).cast("long").alias("i"), F.col("th").alias("t"))


def in_ranges(docs: DataFrame) -> DataFrame:
    """docs(doc_id, text, th) with `bucket` (rising with doc_id and text digest) and `halo` (rows dealt a second time).

    Buckets hold about RANGE_ROWS documents each, whatever the ids are: their cuts are every so manieth key of all
    documents, from ranks within ranges of keys. Within a bucket, the row after the last in descending order is the halo row:
    the first one of the next lower bucket in use, or, for the lowest, the very first document."""
    spark = docs.sparkSession
    slim = cut(docs.select(order_key().alias("key")))
    total = slim.count()
    every = max(RANGE_ROWS, total // MOST_RANGES)
    ranged = slim.repartitionByRange(int(spark.conf.get("spark.sql.shuffle.partitions")), "key").withColumn("pid", F.spark_partition_id())
    ranked = ranged.withColumn("rank", F.row_number().over(Window.partitionBy("pid").orderBy("key")))
    # At most MOST_RANGES keys and one for each partition; one row with all of them from here on.
    cuts = cut(ranked.where((F.col("rank") % every) == 1).agg(F.array_sort(F.collect_set("key")).alias("cuts")))
    bucketed = lambda df, key: df.withColumn("cuts", cuts.scalar()).withColumn("bucket", place(F.col("cuts"), key)).drop("cuts")
    tops = bucketed(slim, F.col("key")).groupBy("bucket").agg(F.max("key").alias("top"))
    up = Window.orderBy("bucket")
    tops = tops.withColumn("to", F.lead("bucket").over(up)).withColumn("lowest", F.min("bucket").over(Window.partitionBy()))
    tops = cut(tops.select("top", F.coalesce("to", "lowest").alias("to")))
    rows = docs.withColumn("key", order_key())
    halo = rows.join(F.broadcast(tops), F.col("key") == F.col("top")).dropDuplicates(["to"])
    halo = halo.select("doc_id", "text", "th", F.col("to").alias("bucket"), F.lit(True).alias("halo"))
    rows = bucketed(rows, F.col("key")).select("doc_id", "text", "th", "bucket", F.lit(False).alias("halo"))
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(MOST_PARTS, total // PART_ROWS))
    return rows.unionByName(halo).repartition(parts, "bucket")


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next of docs(doc_id, text)."""
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("th", F.xxhash64("text"))
    order = Window.partitionBy("bucket").orderBy("halo", F.col("doc_id").desc_nulls_last(), F.col("th").desc())
    dealt = in_ranges(rows).withColumn("a", blocks(F.col("text")))
    dealt = dealt.withColumn("next", F.lead(F.struct("text", "a")).over(order)).where(~F.col("halo"))
    n = F.char_length("text")
    k = F.floor(n / 3).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n - k), F.substring("next.text", F.lit(1), k))
    out = dealt.select("doc_id", n.cast("long").alias("n_chars"), F.sha2(edited.cast("binary"), 256).alias("edited_sha256"), "a", blocks(edited).alias("b"), F.col("next.a").alias("x"))
    three = F.transform(F.array("a", "b", "x"), lambda s: sketch(s, CELLS))
    out = out.withColumn("s", three)
    s = [F.element_at("s", i) for i in (1, 2, 3)]
    a, b, x = F.col("a"), F.col("b"), F.col("x")
    return out.select("doc_id", "n_chars", "edited_sha256", written(s[0]).alias("fingerprint"), written(s[1]).alias("edited_fingerprint"), likeness(a, b, s[0], s[1]).alias("near_edited"), likeness(a, x, s[0], s[2]).alias("near_next"))


def op8_lookup_sketch(spark, sf_dir: str) -> DataFrame:
    return fingerprints(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
