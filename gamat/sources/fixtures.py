"""The matrices of the experiments, as views of the given tables, with the SQL that defines each of them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..types import GraphMatrix, MatrixMeta, VertexState
from .io import table

BIG = "bigint"


def size(spark: SparkSession, sf_dir: str, name: str, key: str) -> int:
    """Number of ids 0..max of a key: read from one column (and answered from file statistics where Spark can)."""
    top = table(spark, sf_dir, name, [key]).agg(F.max(key)).first()[0]
    return 0 if top is None else top + 1


def lineitem_edges(spark, sf_dir, dst: str, src: str, condition=None, folded: bool = True) -> DataFrame:
    """Edges from the fact table; not folded, parallel edges stay apart, which linear operations add up by themselves."""
    df = table(spark, sf_dir, "lineitem")
    df = df if condition is None else df.where(condition)
    if not folded:
        return df.where(F.col("l_quantity").isNotNull()).select(F.col(dst).alias("dst"), F.col(src).alias("src"), F.col("l_quantity").cast(BIG).alias("w"))
    return df.groupBy(F.col(dst).alias("dst"), F.col(src).alias("src")).agg(F.sum("l_quantity").cast(BIG).alias("w"))


def mx1(spark, sf_dir, condition=None, folded: bool = True) -> GraphMatrix:
    """part x supplier, summed quantity."""
    return GraphMatrix(lineitem_edges(spark, sf_dir, "l_partkey", "l_suppkey", condition, folded), MatrixMeta(size(spark, sf_dir, "part", "p_partkey"), size(spark, sf_dir, "supplier", "s_suppkey")))


def mx2(spark, sf_dir, folded: bool = True) -> GraphMatrix:
    """customer x part, summed quantity."""
    li = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"])
    o = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    both = li.join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    if folded:
        e = both.groupBy(F.col("o_custkey").alias("dst"), F.col("l_partkey").alias("src")).agg(F.sum("l_quantity").cast(BIG).alias("w"))
    else:
        e = both.where(F.col("l_quantity").isNotNull()).select(F.col("o_custkey").alias("dst"), F.col("l_partkey").alias("src"), F.col("l_quantity").cast(BIG).alias("w"))
    return GraphMatrix(e, MatrixMeta(size(spark, sf_dir, "customer", "c_custkey"), size(spark, sf_dir, "part", "p_partkey")))


def mx3(spark, sf_dir) -> GraphMatrix:
    """order x part, summed quantity."""
    return GraphMatrix(lineitem_edges(spark, sf_dir, "l_orderkey", "l_partkey"), MatrixMeta(size(spark, sf_dir, "orders", "o_orderkey"), size(spark, sf_dir, "part", "p_partkey")))


def mx4(spark, sf_dir, scale: int = 1000) -> GraphMatrix:
    """embeddings as integers (rounded after scaling): vector x dimension, dense."""
    df = table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    e = df.select(F.col("vec_id").alias("dst"), F.posexplode("embedding").alias("src", "v"))
    e = e.select("dst", F.col("src").cast(BIG).alias("src"), F.round(F.col("v").cast("double") * scale).cast(BIG).alias("w")).where("w <> 0")
    return GraphMatrix(e, MatrixMeta(size(spark, sf_dir, "embeddings", "vec_id"), 64))


def mx5(spark, sf_dir) -> GraphMatrix:
    """supplier Gram matrix of mx1, in bands: a product adds parallel edges up by itself."""
    from ..operators import bands

    a = mx1(spark, sf_dir, folded=False)
    return bands.mm(a.T, a)


def mx6(spark, sf_dir) -> GraphMatrix:
    """nation flow: customer nation x supplier nation, summed quantity."""
    li = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_suppkey", "l_quantity"])
    by = li.groupBy("l_orderkey", "l_suppkey").agg(F.sum("l_quantity").alias("q"))
    o = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    c = table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"])
    s = table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"])
    e = by.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    e = e.groupBy(F.col("c_nationkey").cast(BIG).alias("dst"), F.col("s_nationkey").cast(BIG).alias("src")).agg(F.sum("q").cast(BIG).alias("w"))
    return GraphMatrix(e, MatrixMeta(25, 25))


def days(spark, sf_dir) -> DataFrame:
    """day (days since the first ship date, from 0), k: summed quantity; days without shipments have 0."""
    return counted_days(spark, sf_dir)[0]


def counted_days(spark, sf_dir) -> tuple[DataFrame, int]:
    """`days` and how many there are."""
    df = table(spark, sf_dir, "lineitem", ["l_shipdate", "l_quantity"])
    k = df.groupBy(F.datediff(F.to_date("l_shipdate"), F.lit("1992-01-01").cast("date")).cast(BIG).alias("t")).agg(F.sum("l_quantity").cast(BIG).alias("k"))
    lo, hi = k.agg(F.min("t"), F.max("t")).first()
    every = spark.range(lo, hi + 1).withColumnRenamed("id", "t")
    return every.join(k, "t", "left").select((F.col("t") - lo).alias("t"), F.coalesce("k", F.lit(0).cast(BIG)).alias("k")), hi - lo + 1


def mx8(spark, sf_dir, springs: DataFrame | None = None, n: int | None = None, ground: int = 1) -> GraphMatrix:
    """Day stiffness: element graphs of springs between n consecutive days, added up; one spring to ground at day 0."""
    s, n = counted_days(spark, sf_dir) if springs is None else (springs, n)
    n = s.agg(F.max("t")).first()[0] + 1 if n is None else n
    cell = lambda i, j, w: F.struct((F.col("t") + i).alias("dst"), (F.col("t") + j).alias("src"), w.alias("w"))
    e = s.where(F.col("t") < n - 1).select(F.explode(F.array(cell(0, 0, F.col("k")), cell(1, 1, F.col("k")), cell(0, 1, -F.col("k")), cell(1, 0, -F.col("k")))).alias("x")).select("x.*")
    e = e.unionByName(spark.range(1).select(F.lit(0).cast(BIG).alias("dst"), F.lit(0).cast(BIG).alias("src"), F.lit(ground).cast(BIG).alias("w")))
    e = e.groupBy("dst", "src").agg(F.sum("w").alias("w")).where("w <> 0")
    return GraphMatrix(e, MatrixMeta(n, n, kl=1, ku=1, structure=frozenset({"symmetric", "banded"})))


def mx9(spark, sf_dir) -> DataFrame:
    """page_id, href, w: links of raw pages (ids of the links by `ids.encode`)."""
    p = table(spark, sf_dir, "pages", ["page_id", "html"])
    return p.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).groupBy("page_id", "href").agg(F.count("*").alias("w"))


def terms(df: DataFrame, key: str) -> DataFrame:
    """key, term, w: counts of the lower-case terms of df(key, text)."""
    return df.select(key, F.explode(F.split(F.lower("text"), " ")).alias("term")).groupBy(key, "term").agg(F.count("*").alias("w"))


def mx13(spark, sf_dir, tau: float = 0.3) -> GraphMatrix:
    """Neighbour graph of the embeddings: pairs a <> b whose integer cosine is at least tau; weight: rounded distance x 1000."""
    from ..operators import ops

    a = mx4(spark, sf_dir)
    g = ops.mm_blocks(a, a.T).where(F.col("dst") != F.col("src"))
    e = g.edges.where(F.col("w") >= int(tau * 1_000_000)).select("dst", "src", F.round(F.sqrt(F.greatest(F.lit(0.0), 2.0 - 2.0 * F.col("w") / 1e6)) * 1000).cast(BIG).alias("w"))
    n = a.meta.n_rows
    return GraphMatrix(e, MatrixMeta(n, n, structure=frozenset({"symmetric"})))


def mx14(spark, sf_dir) -> GraphMatrix:
    """Hermitian 2H = (T + T') + i (T - T') of the nation flow T."""
    t = mx6(spark, sf_dir).edges
    both = t.select("dst", "src", F.col("w").alias("re"), F.col("w").alias("im")).unionByName(t.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.col("w").alias("re"), (-F.col("w")).alias("im")))
    e = both.groupBy("dst", "src").agg(F.sum("re").alias("re"), F.sum("im").alias("im")).select("dst", "src", F.struct("re", "im").alias("w"))
    return GraphMatrix(e, MatrixMeta(25, 25, "complex", structure=frozenset({"hermitian"})))


def mx15(spark, sf_dir) -> GraphMatrix:
    """segment x customer one-hot: five rows of very high degree."""
    c = table(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"])
    names = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
    e = c.select((F.array_position(F.array(*map(F.lit, names)), F.col("c_mktsegment")) - 1).cast(BIG).alias("dst"), F.col("c_custkey").alias("src"), F.lit(1).cast(BIG).alias("w"))
    return GraphMatrix(e, MatrixMeta(5, size(spark, sf_dir, "customer", "c_custkey")))


def supplier_cents(spark, sf_dir) -> VertexState:
    return VertexState.of(table(spark, sf_dir, "supplier", ["s_suppkey", "s_acctbal"]), "s_suppkey", F.round(F.col("s_acctbal") * 100).cast(BIG), size(spark, sf_dir, "supplier", "s_suppkey"))


def part_cents(spark, sf_dir) -> VertexState:
    return VertexState.of(table(spark, sf_dir, "part", ["p_partkey", "p_retailprice"]), "p_partkey", F.round(F.col("p_retailprice") * 100).cast(BIG), size(spark, sf_dir, "part", "p_partkey"))


def customer_cents(spark, sf_dir) -> VertexState:
    return VertexState.of(table(spark, sf_dir, "customer", ["c_custkey", "c_acctbal"]), "c_custkey", F.round(F.col("c_acctbal") * 100).cast(BIG), size(spark, sf_dir, "customer", "c_custkey"))


#: The same matrices and states in SQL, for the oracles.
SQL = {
    "mx1": "select l_partkey dst, l_suppkey src, cast(sum(l_quantity) as bigint) w from lineitem group by 1, 2",
    "mx2": "select o_custkey dst, l_partkey src, cast(sum(l_quantity) as bigint) w from lineitem join orders on l_orderkey = o_orderkey group by 1, 2",
    "mx3": "select l_orderkey dst, l_partkey src, cast(sum(l_quantity) as bigint) w from lineitem group by 1, 2",
    "mx4": "select vec_id dst, cast(i - 1 as bigint) src, cast(round(cast(embedding[i] as double) * 1000) as bigint) w from embeddings, range(1, 65) r(i) where cast(round(cast(embedding[i] as double) * 1000) as bigint) <> 0",
    "mx6": "select cast(c_nationkey as bigint) dst, cast(s_nationkey as bigint) src, cast(sum(l_quantity) as bigint) w from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by 1, 2",
    "d0": "select date_diff('day', date '1992-01-01', cast(l_shipdate as date)) t, cast(sum(l_quantity) as bigint) k from lineitem group by 1",
    "days": "select r.t - (select min(t) from d0) t, coalesce(d0.k, 0) k from (select unnest(range((select min(t) from d0), (select max(t) from d0) + 1)) t) r left join d0 on d0.t = r.t",
    "x8": "select t dst, t src, k w from days where t < (select max(t) from days) union all select t + 1, t + 1, k from days where t < (select max(t) from days) union all select t, t + 1, -k from days where t < (select max(t) from days) union all select t + 1, t, -k from days where t < (select max(t) from days) union all select 0, 0, 1",
    "mx8": "select dst, src, cast(sum(w) as bigint) w from x8 group by 1, 2 having sum(w) <> 0",
    "sup": "select s_suppkey id, cast(round(s_acctbal * 100) as bigint) s from supplier",
    "par": "select p_partkey id, cast(round(p_retailprice * 100) as bigint) s from part",
    "cus": "select c_custkey id, cast(round(c_acctbal * 100) as bigint) s from customer",
    "mx5": "select a.src dst, b.src src, cast(sum(a.w * b.w) as bigint) w from mx1 a join mx1 b on a.dst = b.dst group by 1, 2",
    "mx7": "select * from mx5 where src <= dst",
    "mx13": "select a.dst dst, b.dst src, cast(round(sqrt(greatest(0.0, 2.0 - 2.0 * cast(sum(a.w * b.w) as bigint) / 1e6)) * 1000) as bigint) w from mx4 a join mx4 b on a.src = b.src and a.dst <> b.dst group by 1, 2 having sum(a.w * b.w) >= 300000",
    "mx15": "select cast(list_position(['AUTOMOBILE', 'BUILDING', 'FURNITURE', 'HOUSEHOLD', 'MACHINERY'], c_mktsegment) - 1 as bigint) dst, c_custkey src, cast(1 as bigint) w from customer",
    "mx14": "select dst, src, cast(sum(re) as bigint) re, cast(sum(im) as bigint) im from (select dst, src, w re, w im from mx6 union all select src, dst, w, -w from mx6) group by 1, 2",
}
NEEDS = {"days": ["d0"], "x8": ["days"], "mx8": ["x8"], "mx5": ["mx1"], "mx7": ["mx5"], "mx13": ["mx4"], "mx14": ["mx6"]}


def with_sql(*names: str, recursive: bool = False) -> str:
    """A WITH clause that defines the named fixtures and what they need."""
    order: list[str] = []

    def add(n: str) -> None:
        for m in NEEDS.get(n, []):
            add(m)
        if n not in order:
            order.append(n)

    for n in names:
        add(n)
    return ("with recursive " if recursive else "with ") + ", ".join(f"{n} as ({SQL[n]})" for n in order)
