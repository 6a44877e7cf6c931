"""URL rules, mixing, the pipeline, and the wiring of all of them."""

import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from gamat.llm import mixing, queries, url_filters


def brute_url(url):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    n = min([len(rest)] + [rest.index(c) for c in "/?#" if c in rest])
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in rest[:n])
    path = rest[n:]
    path = path[: min([len(path)] + [path.index(c) for c in "?#" if c in path])]
    fits = [(len(r), r, v) for v, r in url_filters.LISTED if (host == r.split("/")[0] or host.endswith("." + r.split("/")[0])) and path.startswith(r[len(r.split("/")[0]) :])]
    best = max(fits, default=None)
    import re

    word = any(re.search(rf"(^|[.-]){w}[.-]", host) for w in url_filters.BLOCKED_WORDS)
    return host, path, best and best[1], best[2] if best else "block" if word else "allow"


@pytest.mark.parametrize("inline", [2000, 0])
def test_urls_equal_brute_force(spark, inline):
    rng = random.Random(2)
    hosts = ["example.com", "www.example.com", "WWW.Example.COM", "a.b.net", "net", "anet", "com", "spam-farm.example.org", "x.spam.org", "example.com:80", "", "myexample.com", "t\nx.com"]
    paths = ["", "/", "/en/", "/en", "/en/1", "/es/2", "/fr/", "/EN/", "?q=/en/", "#x", "/es/?a#b", "//en/", "/en/x?y"]
    urls = [f"{rng.choice(['http://', 'https://', '', 'ftp://', '://'])}{h}{p}" for h in hosts for p in paths] + [None, "", "http://", "plain", "http://example.com/en/", "http://example.com/en/"]
    df = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id bigint, url string, html string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filters.judge(df, inline_limit=inline).collect()}
    assert got == {i: brute_url(u) for i, u in enumerate(urls)}
    assert url_filters.judge(df.where("page_id < 0")).count() == 0


def test_rules_are_filed_under_their_rarest_token(spark):
    df = spark.createDataFrame([(["com", "en"],), (["com", "example"],), (["com"],)], "tokens array<string>")
    index = url_filters.rarest(df, url_filters.RULES)
    assert [r.name for r in index["www"]] == ["www.example.com/en/"] and "com" in index


def test_share_fills_by_weight_and_passes_shortages_on():
    assert mixing.share(100, {"a": 1000, "b": 1000}, {"a": 3, "b": 1}) == {"a": 75, "b": 25}
    assert mixing.share(100, {"a": 10, "b": 1000, "c": 1000}, {"a": 2, "b": 1, "c": 1}) == {"a": 10, "b": 45, "c": 45}
    assert mixing.share(100, {"a": 10, "b": 20}, {"a": 1, "b": 1}) == {"a": 10, "b": 20}
    assert sum(mixing.share(101, {"a": 1000, "b": 1000, "c": 1000}, {"a": 1, "b": 1, "c": 1}).values()) == 101


def test_budgets_redistribute_among_siblings_first():
    w = mixing.Weights(domain={"d": 1, "e": 1}, lang={"x": 1, "y": 1})
    tokens = {("d", "x", "s"): 10, ("d", "y", "s"): 1000, ("e", "x", "s"): 1000}
    assert mixing.budgets(tokens, 200, w, 1) == {("d", "x", "s"): 10, ("d", "y", "s"): 90, ("e", "x", "s"): 100}
    tokens[("d", "y", "s")] = 20
    assert mixing.budgets(tokens, 200, w, 1) == {("d", "x", "s"): 10, ("d", "y", "s"): 20, ("e", "x", "s"): 170}


def brute_mix(spark, docs, fraction, max_epochs, seed=17):
    import re

    h = {}
    for e in range(max_epochs + 1):
        for r in docs.select("doc_id", mixing.order_hash(seed, F.lit(e), F.col("doc_id")).alias("h")).collect():
            h[e, r["doc_id"]] = r["h"]
    leaves = {}
    for r in docs.select("doc_id", "text", *mixing.leaf_columns(mixing.DOMAINS)).collect():
        leaves.setdefault((r["domain"], r["lang"], r["source"]), []).append((r["doc_id"], len(re.findall(r"[^ \t\n\x0B\f\r]+", r["text"] or ""))))
    have = {k: sum(n for _, n in v) for k, v in leaves.items()}
    given = mixing.budgets(have, int(fraction * sum(have.values())), mixing.Weights(), max_epochs)
    out = []
    for k, rows in leaves.items():
        full = min(max_epochs, given[k] // have[k]) if have[k] else 0
        rest, total = given[k] - full * have[k], 0
        taken = {i: full for i, _ in rows}
        for i, n in sorted(rows, key=lambda r: (h[full, r[0]], r[0] is not None, r[0] or 0)):
            total += n
            if rest > 0 and total <= rest:
                taken[i] += 1
        out += [(i, c) for i, c in taken.items() if c]
    return sorted(out)


@pytest.mark.parametrize(("fraction", "epochs", "per_bucket"), [(0.5, 1, 20_000), (1.0, 3, 20_000), (0.9, 1, 1), (2.5, 2, 3)])
def test_mixing_equals_brute_force(spark, sf, fraction, epochs, per_bucket):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    choice = mixing.decide(docs, fraction=fraction, max_epochs=epochs, per_bucket=per_bucket)
    got = mixing.copies(choice, choice.slim, "doc_id").where("copies > 0").select("doc_id", "copies").collect()
    assert sorted((r["doc_id"], r["copies"]) for r in got) == brute_mix(spark, docs, fraction, epochs)


def test_mixing_edge_rows(docs, none):
    out = mixing.choose(docs, fraction=1.0)
    assert out.columns == docs.columns and out.count() <= docs.count()
    assert mixing.choose(none).count() == 0


def test_stages_keep_columns_and_take_edge_rows(spark, sf, docs, none):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality", "lines", "near_duplicates", "mixture", "sequences"]
    for table in (docs, none):
        x = table
        for _, stage in corpus_pipeline.STAGES[:-1]:
            x = stage(spark, x, sf)
            assert x.columns == table.columns
        assert corpus_pipeline.STAGES[-1][1](spark, x, sf).count() >= x.count()


def test_pipeline_decisions(spark, sf):
    """Each stage by itself: what goes, goes for the stage's reason."""
    from gamat.llm import jaccard_join, kneser_ney

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    kept = corpus_pipeline.quality(spark, docs, sf)
    bad = kneser_ney.classify(docs, labels).where("not keep")
    assert kept.count() == docs.count() - bad.count()
    one = corpus_pipeline.near_duplicates(spark, docs, sf)
    groups = jaccard_join.linked_classes(docs).select("component_id").distinct().count()
    assert one.count() == groups
    lines = corpus_pipeline.lines(spark, docs, sf)
    assert lines.where("n_chars <> length(text)").count() == docs.where("n_chars <> length(text)").count()
    assert corpus_pipeline.run(spark, sf).count() > 0


def test_queries_are_registered():
    assert sorted(int(n[2:].split("_")[0]) for n in queries.QUERIES) == list(range(1, 11))
