"""Line dedup by a log-template tree.

Each line becomes a token sequence in which variable fields (tokens with digits or "@") are wildcards. The tree has a
fixed depth: token count, then the first DEPTH tokens; below such a leaf a line belongs to its full template and, if it
has at least WIDE tokens, to the four templates in which one quarter of the remaining positions is generalised to
wildcards too. So two lines share a template if they agree, field by field, outside one such quarter. Paths through the
tree are 64-bit digests, which makes the tree a plain aggregation: no line is compared with another one, and no leaf
is gathered.

A template recurs if it occurs in at least `min_docs` documents, or in two for lines of `long_line` tokens or more.
Recurring lines stay in the document with the smallest doc_id and are dropped everywhere else. Lines of fewer than
`min_tokens` tokens always stay.

Null text stays null; a null doc_id leaves its row as it is; empty text has one empty line. Repeated rows (one doc_id
twice) count twice, but a template needs two different doc_ids to recur. Very long texts are parsed whole; a line of theirs is
looked up among the lines that they lose. Other columns are kept, whatever their names. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, discard

MIN_TOKENS, MIN_DOCS, LONG_LINE = 4, 3, 50
DEPTH, WIDE, SALT = 2, 8, 32
BLANK = r"[ \t\x0B\f\r]+"
FIELD = r"(?<![^ \t\n\x0B\f\r])[^ \t\n\x0B\f\r0-9@]*[0-9@][^ \t\n\x0B\f\r]*"


def masked(line: Column) -> Column:
    """The line with single blanks and wildcards for variable fields; most lines have neither and stay as they are."""
    odd = F.rlike(line, F.lit(r"[0-9@\t\x0B\f\r]| (?: |$)|^ "))
    return F.when(odd, F.trim(F.regexp_replace(F.regexp_replace(line, BLANK, " "), FIELD, "<*>"))).otherwise(line)


def bind(value: Column, use) -> Column:
    """use(value), with the value computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def tree_path(line: Column, long_line: int = LONG_LINE) -> Column:
    """n: token count of a line; keys: digests of its templates, the first one being the full template.

    The last bit of a digest says whether the template's lines are long: all of them have the same token count."""

    def of(t: Column) -> Column:
        n, rest = F.size(t), F.size(t) - DEPTH
        edge = lambda j: F.lit(DEPTH) + F.floor(rest * j / 4).cast("int")
        quarter = lambda j: F.xxhash64(F.slice(t, edge(j) + 1, edge(j + 1) - edge(j)))
        lead = F.xxhash64(n, F.slice(t, 1, DEPTH))

        def wide(q: Column) -> Column:
            part = [F.element_at(q, j + 1) for j in range(5)]
            without = [F.xxhash64(F.lit(j), *[x for k, x in enumerate(part) if k != j + 1]) for j in range(4)]
            return F.array(F.xxhash64(F.lit(-1), *part), *without)

        keys = F.when(n >= WIDE, bind(F.array(lead, *map(quarter, range(4))), wide)).otherwise(F.array(F.xxhash64(F.lit(-2), t)))
        mark = F.when(n >= long_line, 1).otherwise(0).cast("long")
        return F.struct(n.alias("n"), F.transform(keys, lambda k: k.bitwiseAND(F.lit(-2)).bitwiseOR(mark)).alias("keys"))

    return bind(F.split(masked(line), " "), of)


def marked(docs: DataFrame, min_tokens: int, long_line: int) -> DataFrame:
    """doc_id and, for each different line that is long enough, its token count and templates."""
    lines = F.filter(F.transform(F.array_distinct(F.split("text", "\n")), lambda x: tree_path(x, long_line)), lambda x: x["n"] >= min_tokens)
    return docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()).select("doc_id", lines.alias("lines"))


def recurring(found: DataFrame, min_docs: int = MIN_DOCS) -> DataFrame:
    """key, first: digests of the recurring templates of found(doc_id, lines) and the document that keeps them."""
    # One row per template and document, so that rows are documents.
    keys = found.select("doc_id", F.explode(F.array_distinct(F.flatten("lines.keys"))).alias("key"))
    by = keys.groupBy("key").agg(F.count("*").alias("n"), F.min("doc_id").alias("first"), F.max("doc_id").alias("last"))
    long = F.col("key").bitwiseAND(F.lit(1)) == 1
    return by.where((F.col("first") != F.col("last")) & ((F.col("n") >= min_docs) | long)).select("key", "first")


def dropped_lines(docs: DataFrame, min_tokens: int = MIN_TOKENS, min_docs: int = MIN_DOCS, long_line: int = LONG_LINE) -> DataFrame:
    """doc_id, drop: full-template digests of the lines that each document loses."""
    found = cut(marked(docs, min_tokens, long_line))
    # A hot template is dealt out by document, SALT ways; the recurring templates are repeated for that.
    again = recurring(found, min_docs).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))))
    lines = found.select("doc_id", F.explode("lines").alias("l"))
    lines = lines.select("doc_id", F.col("l.keys")[0].alias("line"), F.explode("l.keys").alias("key"), F.pmod(F.xxhash64("doc_id"), F.lit(SALT)).cast("int").alias("salt"))
    hits = lines.join(again, ["key", "salt"]).where(F.col("doc_id") != F.col("first"))
    drop = cut(hits.groupBy("doc_id").agg(F.collect_set("line").alias("drop")))
    discard(found)
    return drop


def dedup_lines(docs: DataFrame, min_tokens: int = MIN_TOKENS, min_docs: int = MIN_DOCS, long_line: int = LONG_LINE) -> DataFrame:
    """All rows and columns of docs(doc_id, text, ...) in __row, with __lines, __dropped and the remaining __text."""
    drop = dropped_lines(docs.select("doc_id", "text"), min_tokens, min_docs, long_line)
    # Rows without an id lose nothing, and are dealt out by their texts.
    deal = F.when(F.col("doc_id").isNull(), F.xxhash64("text")).otherwise(F.lit(0)).alias("__deal")
    lost = drop.select(F.col("doc_id").alias("__id"), F.lit(0).cast("long").alias("__deal"), F.col("drop").alias("__drop"))
    both = docs.select(F.struct("*").alias("__row"), F.col("doc_id").alias("__id"), deal).join(lost, ["__id", "__deal"], "left")
    text, none = F.col("__row.text"), F.col("__drop").isNull()

    def stays(line: Column) -> Column:
        return ~bind(tree_path(line, long_line), lambda p: (p["n"] >= min_tokens) & F.array_contains("__drop", F.element_at(p["keys"], 1)))

    kept = F.when(~none, F.filter(F.split(text, "\n"), stays))
    both = both.withColumn("__kept", kept).withColumn("__lines", F.when(text.isNull(), 0).otherwise(F.size(F.split(text, "\n"))))
    return both.select(
        "__row",
        "__lines",
        F.when(none, 0).otherwise(F.col("__lines") - F.size("__kept")).alias("__dropped"),
        F.when(none, text).otherwise(F.array_join("__kept", "\n")).alias("__text"),
    )


def op3_line_templates(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = dedup_lines(docs)
    return out.select("__row.doc_id", F.col("__lines").cast("long").alias("n_lines"), F.col("__dropped").cast("long").alias("n_dropped"), F.col("__text").alias("text"))


SQL = r"""
with d as (select doc_id, text, [trim(x) for x in string_split(regexp_replace(regexp_replace(text, '[ \t\x0B\f\r]+', ' ', 'g'), '[^ \t\n\x0B\f\r0-9@]*[0-9@][^ \t\n\x0B\f\r]*', '<*>', 'g'), chr(10))] m from documents),
l as (select distinct doc_id, string_split(u.x, ' ') t, u.x from d, unnest(m) u(x)),
g as (select doc_id, x, t, len(t) n, len(t) - 2 r from l where len(t) >= 4),
k as (select doc_id, x, n, concat('-1|', x) as key from g
  union all select doc_id, x, n, concat(j, '|', n, '|', array_to_string(t[1 : 2 + (r * j) // 4], ' '), '|', array_to_string(t[3 + (r * (j + 1)) // 4 : n], ' ')) from g, range(4) s(j) where n >= 8),
a as (select key, count(distinct doc_id) c, min(doc_id) f, max(n) n from k group by key having count(distinct doc_id) >= 2 and (count(distinct doc_id) >= 3 or max(n) >= 50)),
b as (select distinct doc_id, x from k join a using (key) where doc_id <> f),
z as (select doc_id, i, string_split(text, chr(10))[i] s, m[i] x from d, range(1, 1000000) r(i) where i <= len(m)),
w as (select z.doc_id, count(*) n_lines, count(b.x) n_dropped, string_agg(z.s, chr(10) order by i) filter (b.x is null) t from z left join b on z.doc_id = b.doc_id and z.x = b.x group by z.doc_id)
select doc_id, n_lines::bigint n_lines, n_dropped::bigint n_dropped, coalesce(t, '') as text from w
"""
