"""Skewed and repeated input, bounds of tasks, and brute force for what the other files leave out."""

import hashlib
import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from gamat.llm import jaccard_join, kneser_ney, lookup_sketch, mixing, packing, skip_chain, url_filters

from test_text_operators import brute_components, mutated, shingles


# op1 -----------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("links", [50_000, 1])
def test_messages_give_exact_marginals_on_trees(monkeypatch, links):
    monkeypatch.setattr(skip_chain, "LINKS", links)
    rng, k = np.random.default_rng(4), len(skip_chain.LABELS)
    field = skip_chain.Field(np.zeros((1, k)), rng.normal(size=(k, k)), 1.7)
    unary = rng.normal(size=(5, k)) * 2
    chain, skip = [(0, 1), (1, 2)], [(1, 3), (0, 4)]
    belief = field.beliefs(unary, np.array(chain + skip), len(chain), rounds=6)
    exact = np.zeros((5, k))
    for y in itertools.product(range(k), repeat=5):
        p = np.exp(sum(unary[i, y[i]] for i in range(5)) + sum(field.chain[y[a], y[b]] for a, b in chain) + sum(1.7 * (y[a] == y[b]) for a, b in skip))
        for i in range(5):
            exact[i, y[i]] += p
    got = np.exp(belief - belief.max(axis=1, keepdims=True))
    assert got / got.sum(axis=1, keepdims=True) == pytest.approx(exact / exact.sum(axis=1, keepdims=True), rel=1e-9)


def codes(rng, n):
    return ["".join(rng.choice("abcdefghkmnpqrstuvwxyz23456789") for _ in range(9)) + str(i % 10) for i in range(n)]


def test_skip_links_make_repeats_agree(spark):
    """Secrets look like order numbers here; only the words before them, and their repeats, tell them apart."""
    rng, filler = random.Random(9), "we met and talked about it for a while "
    texts = []
    for a, b, c in zip(codes(rng, 400), codes(rng, 400), codes(rng, 400), strict=True):
        texts += [f"{filler} password = {a} {filler}{filler} order {b} {filler}{filler}", f"{filler} order {c} {filler}{filler} parcel {c} {filler}"]
    train = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    model = skip_chain.train(train)
    quiet = skip_chain.Field(model.node, model.chain, 0.0)
    new = codes(rng, 40)
    rows = [(i, f"{filler} password = {w} {filler}{filler} beside {w.upper()} {filler}" if i % 2 else f"{filler} order {w} {filler}{filler} beside {w.upper()} {filler}") for i, w in enumerate(new)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")

    def secrets(m):
        out = {}
        for r in skip_chain.find_entities(df, m).collect():
            spans = [s for s in r["spans"].split(",") if s]
            assert r["n_spans"] == len(spans) == r["n_added"] + r["n_email"] + r["n_ip"] + r["n_card"] + r["n_phone"]
            out[r["doc_id"]] = sum(s.startswith("secret") for s in spans)
        return out

    linked, alone = secrets(model), secrets(quiet)
    # A repeat after a word that training has not seen has its shape alone and goes its own way; linked, both are the same.
    apart = [sum(n == 1 for n in found.values()) for found in (linked, alone)]
    assert apart[1] >= 15 and apart[0] <= 2, (linked, alone)


# op2 -----------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("inline", [10_000, 100])
def test_thousands_of_rules_on_both_ways(spark, inline):
    rng = random.Random(8)
    words = [f"w{i}" for i in range(120)]
    listed = list({f"{rng.choice(words)}.{rng.choice(['com', 'net', 'org'])}/{rng.choice(['', 'en/', 'a/b/', 'x'])}": rng.choice(["allow", "block"]) for _ in range(2500)}.items())
    rules = [url_filters.host_rule(v, r) for r, v in listed]
    assert len(rules) > 700
    urls = [f"http://{rng.choice(['', 'www.', 'q.'])}{rng.choice(words)}.{rng.choice(['com', 'net', 'org', 'xyz'])}/{rng.choice(['', 'en/', 'en', 'a/b/c', 'xy', 'x'])}" for _ in range(400)]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id bigint, url string")
    got = {r["page_id"]: (r["rule"], r["verdict"]) for r in url_filters.judge(df, rules, inline_limit=inline).collect()}
    for i, u in enumerate(urls):
        host, _, path = u[7:].partition("/")
        path = "/" + path
        fits = [(len(r), r, v) for r, v in listed if (host == r.split("/")[0] or host.endswith("." + r.split("/")[0])) and path.startswith(r[len(r.split("/")[0]) :])]
        best = max(fits, default=None)
        assert got[i] == ((best[1], best[2]) if best else (None, "allow")), u


# op4 -----------------------------------------------------------------------------------------------------------------


def test_word_cache_stays_within_its_bound():
    tok = packing.WordTokenizer(packing.public_tokenizer_path("word_bpe_49k.json"), cache=20, longest=6)
    for t in ("a b c", " ".join(f"u{chr(97 + i % 26)}{'x' * (i % 9)}" for i in range(300)), "again a b c longerword"):
        assert tok.encode(t) == tok.whole([t])[0]
        assert len(tok.cache) <= 20 and all(len(w) <= 6 for w in tok.cache)


# op5 -----------------------------------------------------------------------------------------------------------------


def test_thresholds_equal_plain_quantiles(spark):
    rng = np.random.default_rng(3)
    rows = [("en" if i % 3 else "de", True if i % 5 else None, int(rng.integers(1, 4000)), float(np.exp(1 + rng.normal() / 9)), float(np.exp(1.1 + rng.normal() / 9)) if i % 7 else None) for i in range(900)]
    rows.append(("fr", None, 5, 2.0, None))
    got = {r["lang"]: r for r in kneser_ney.thresholds(spark.createDataFrame(rows, "lang string, good boolean, n long, perplexity double, unseen double"), 0.9).collect()}
    assert set(got) == {"en", "de"}
    for lang in got:
        h = np.array([(np.log(u if u is not None else p), n) for x, g, n, p, u in rows if x == lang and g])
        center = np.sort(h[:, 0])[-(-len(h) // 2) - 1]
        z = np.sort((h[:, 0] - center) * np.sqrt(h[:, 1]))
        at = lambda q, z=z: z[int(np.ceil(q * len(z))) - 1]
        assert got[lang]["center"] == pytest.approx(center)
        assert got[lang]["excess"] == pytest.approx(min(at(0.9), (at(0.75) - at(0.25)) * 1.5 * 1.2815515655446004 / (2 * 0.6744897501960817)))


def test_each_fold_is_scored_by_the_others(spark):
    rows = [(lang, f, f"the {w} sat on {w}") for lang in ("en", "fr") for f, w in enumerate(["cat", "dog", "rat", "cow"])]
    counts = {(r["lang"], r["k"]): r["c"] for r in kneser_ney.split_counts(spark.createDataFrame(rows, "lang string, fold int, text string"), 4).collect()}
    for f in (None, 0, 1, 2, 3):
        name = "en" if f is None else f"en{kneser_ney.MARK}{f}"
        keys, n = np.unique(np.concatenate([kneser_ney.gram_keys(t) for lang, g, t in rows if lang == "en" and g != f]), return_counts=True)
        assert {k: c for (x, k), c in counts.items() if x == name} == dict(zip(keys.view(np.int64).tolist(), n.tolist(), strict=True))


def test_keep_follows_from_perplexity_and_threshold(spark):
    d, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    out = kneser_ney.classify(d, labels, small=3000).collect()
    whole = {(r["doc_id"]): r for r in kneser_ney.classify(d, labels).collect()}
    assert len(out) == d.count() and {r["doc_id"] for r in out} == set(whole)
    for r in out:
        assert r["keep"] == (r["perplexity"] is None or r["threshold"] is None or r["perplexity"] <= r["threshold"])
        if r["perplexity"] is not None:
            assert r["perplexity"] == pytest.approx(whole[r["doc_id"]]["perplexity"], rel=1e-9)


def test_numbers_keys_and_addresses_are_one_sign():
    assert kneser_ney.plain("see 192.168.0.1, or a@b.example.com now") == "see 0 or 0 now"
    assert kneser_ney.plain("no such word") == "no such word" and len(kneser_ney.plain("x" * 300_000 + "1")) == 1


def test_row_digests_tell_nulls_apart(spark):
    rows = [(1, None, "x"), (1, "x", None), (None, "1", "x"), (1, "", "x"), (1, "x", "")]
    ids = spark.createDataFrame(rows, "doc_id bigint, lang string, text string").select(kneser_ney.row_id().alias("i")).collect()
    assert len({r["i"] for r in ids}) == len(rows)


# op6 -----------------------------------------------------------------------------------------------------------------


def similar_rows(seed: int) -> list[tuple]:
    rng, rows = random.Random(seed), []
    common = [f"c{i}" for i in range(30)]
    for g in range(10):
        words = [f"g{g}w{i}" for i in range(rng.choice([8, 20, 40]))] + (common if g % 2 else [])
        rows += [(len(rows) + k, mutated(rng, words, rng.randint(0, 2))) for k in range(rng.randint(2, 9))]
    # Short texts out of very few words: their shingles are frequent wherever they stand.
    rows += [(500 + i, " ".join(rng.choice("ab") for _ in range(rng.randint(5, 9)))) for i in range(60)]
    return rows


@pytest.mark.parametrize(("hot", "tree"), [(4, 1), (1, 1 << 20), (4096, 200)])
def test_frequent_shingles_in_blocks_lose_no_link(spark, monkeypatch, hot, tree):
    monkeypatch.setattr(jaccard_join, "HOT", hot)
    monkeypatch.setattr(jaccard_join, "TREE_BYTES", tree)
    rows = similar_rows(hot)
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(5)
    got = jaccard_join.linked_classes(df).collect()
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=repr) == brute_components(rows)


def test_class_links_equal_all_pairs(spark):
    rows = similar_rows(2) + [(900, "a b c d e f g"), (901, "A b c d e f g"), (902, None)]
    links, members = jaccard_join.class_links(spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3))
    ids = {}
    for r in members.collect():
        ids.setdefault(r["klass"], []).append(r["doc_id"])
    got = {frozenset((min(ids[r["a"]]), min(ids[r["b"]]))) for r in links.collect()}
    first = {}
    for i, t in sorted(rows, key=lambda r: r[0]):
        first.setdefault(frozenset(shingles(t)), i)
    sets = [(s, i) for s, i in first.items() if s]
    want = {frozenset((i, j)) for (a, i), (b, j) in itertools.combinations(sets, 2) if 100 * len(a & b) >= 75 * len(a | b)}
    assert got == want and len(want) > 10


def test_one_row_of_repeated_ones_stays(spark):
    t, u = "one two three four five six", "quite another text of some words"
    rows = [(1, t, 1), (1, t, 1), (2, t, 2), (None, t, 3), (None, u, 4), (None, u, 5), (3, "", 6), (3, "", 6), (None, None, 7), (4, u + " x", 8)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, `a.b` int")
    out = jaccard_join.keep_one(df)
    assert out.columns == df.columns
    got = sorted(((r[0], r[1]) for r in out.collect()), key=repr)
    assert got == sorted([(1, t), (None, u), (3, ""), (3, ""), (None, None), (4, u + " x")], key=repr)


# op8 -----------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("most", [200_000, 3])
def test_ranges_are_cut_by_rank(spark, monkeypatch, most):
    monkeypatch.setattr(lookup_sketch, "RANGE_ROWS", 40)
    monkeypatch.setattr(lookup_sketch, "MOST_RANGES", most)
    rng = random.Random(6)
    rows = [(i, f"d{i} " + " ".join(str(rng.randrange(50)) for _ in range(60))) for i in range(400)] + [(10**15, "far away from all")] + [(None, f"no id {i}") for i in range(300)] + [(7, "tie")] * 2
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(4)
    dealt = lookup_sketch.in_ranges(df.withColumn("th", F.xxhash64("text")))
    sizes = dealt.where("not halo").groupBy("bucket").count().collect()
    assert sum(r["count"] for r in sizes) == len(rows)
    if most > 3:
        assert max(r["count"] for r in sizes) <= 42 and len(sizes) >= len(rows) // 45
    th = {r["text"]: r["th"] for r in df.select("text", F.xxhash64("text").alias("th")).collect()}
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, th[r[1]]), reverse=True)
    want = {}
    for i, (doc, t) in enumerate(order):
        n, k = order[(i + 1) % len(order)][1], len(t) // 3
        want.setdefault((doc, len(t)), set()).add(hashlib.sha256((t[: len(t) - k] + n[:k]).encode()).hexdigest())
    got = {}
    for r in lookup_sketch.fingerprints(df).collect():
        got.setdefault((r["doc_id"], r["n_chars"]), set()).add(r["edited_sha256"])
    assert got == want


# op10 ----------------------------------------------------------------------------------------------------------------


def test_mixing_without_broadcasts_is_the_same(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")

    def chosen():
        choice = mixing.decide(docs, fraction=0.8)
        return {(r["doc_id"], r["copies"]) for r in mixing.copies(choice, choice.slim, "doc_id").collect()}

    one = chosen()
    monkeypatch.setattr(mixing, "LEAVES", 0)
    assert one == chosen()


def test_repeated_rows_stay_within_the_budget(spark):
    rows = [(i % 7, "w " * 10, "en", "s") for i in range(21)]
    choice = mixing.decide(spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string"), fraction=0.5)
    out = mixing.copies(choice, choice.slim, "doc_id").where("copies > 0").agg(F.sum("tokens"), F.first("budget")).first()
    assert 0 < out[0] <= out[1]
