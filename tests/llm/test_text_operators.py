"""Brute force, exact round trips and edge cases of the operators on texts."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest

from gamat.llm import byte_contexts, jaccard_join, kneser_ney, line_templates, lookup_sketch, packing, skip_chain, transport_stream, word_sets
from pyspark.sql import functions as F


def brute_base(t):
    out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = [int(c) for c in m.group() if c.isdigit()]
        if 13 <= len(d) <= 19 and sum(x if i % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x) for i, x in enumerate(d[::-1])) % 10 == 0:
            out.append(("card", *m.span()))
    out += [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= sum(c.isdigit() for c in m.group()) <= 15]
    return out


def test_base_spans_equal_plain_patterns():
    rng = random.Random(1)
    for _ in range(6000):
        s = "".join(rng.choice("a1.@-+ (9é%2") for _ in range(rng.randint(0, 28)))
        assert brute_base(s) == skip_chain.base_spans(s)
    for _ in range(3000):
        s = "".join(rng.choice("0123456789- +") for _ in range(rng.randint(10, 45)))
        assert brute_base(s) == skip_chain.base_spans(s)
    assert skip_chain.base_spans("1" * 5000 + ".1.1.1") == []
    assert skip_chain.base_spans("x" * 200_000 + "@") == []


def test_entities_keep_base_spans_and_add_repeated_secrets(spark):
    texts = [f"word password=ab{i}cdef{i * 37 % 1000}99 and mail a{i}@b.example.com then {i}.1.2.3 or AKIA{'Q7Z' * 5}{i % 10}" for i in range(80)]
    texts += ["see zz81k2m3n4p5q6 token = \"0641917ea4e9feb9cda83477b57ac2654884f485\" and later 0641917ea4e9feb9cda83477b57ac2654884f485 here", None, "", "version 2.0 only"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    model = skip_chain.train(spark.read.parquet("/root/testdata/sf0.1/documents.parquet"))
    out = {r["doc_id"]: r for r in skip_chain.find_entities(df, model).collect()}
    assert len(out) == len(texts)
    for i, t in enumerate(texts):
        base = skip_chain.spans_text(brute_base(t or ""))
        assert out[i]["base_sha256"] == hashlib.sha256(base.encode()).hexdigest()
        assert set(filter(None, base.split(","))) <= set(out[i]["spans"].split(","))
    key = "0641917ea4e9feb9cda83477b57ac2654884f485"
    found = [texts[80][int(a) : int(b)] for k, a, b in (s.split(":") for s in out[80]["spans"].split(",") if s) if k == "secret"]
    assert found.count(key) == 2
    assert out[83]["spans"] == ""


def test_entities_edge_rows(docs, none):
    assert skip_chain.find_entities(docs, skip_chain.train(docs)).count() == docs.count()
    assert skip_chain.train(none) is None and skip_chain.find_entities(none, None).count() == 0


def test_transport_stream_round_trip_and_faults():
    for n in (0, 1, 63, 64, 175, 176, 177, 360, 32767, 32768, 32769, 150_000):
        data = bytes(i * 7 % 251 for i in range(n))
        media = transport_stream.mux(data)
        s = transport_stream.parse(media)
        assert s.payload() == data and s.gaps == 0 and s.bad_tables == 0 and s.programs == {1: 0x100} and s.streams == {0x101: 6} and len(media) % 188 == 0
        assert [u[1] for u in s.units] == [3600 * i for i in range(max(1, -(-n // 32768)))]
    media = transport_stream.mux(bytes(5000))
    broken = media[: 188 * 6] + media[188 * 7 :]
    assert transport_stream.parse(broken).gaps == 1
    assert transport_stream.parse(b"\x00" * 400).lost_sync == 3 and transport_stream.parse(b"").packets == 0
    spoiled = bytearray(media)
    spoiled[10] ^= 1
    assert transport_stream.parse(bytes(spoiled)).bad_tables == 1


def test_transport_stream_rows(docs, none):
    rows = transport_stream.stored(docs.select("doc_id", "text")).collect()
    assert len(rows) == docs.count()
    texts = {(r["doc_id"], r["text"]) for r in docs.collect()}
    digests = {(i, hashlib.sha256(transport_stream.pad((t or "").encode())).hexdigest()) for i, t in texts}
    assert {(r["doc_id"], r["payload_sha256"]) for r in rows} == digests
    assert all(transport_stream.parse(bytes(r["media"])).payload() is not None and r["payload_bytes"] % 64 == 0 for r in rows)
    assert transport_stream.stored(none.select("doc_id", "text")).count() == 0


def reference_templates(text):
    out = []
    for raw in text.split("\n"):
        line = re.sub(r"[ \t\x0B\f\r]+", " ", raw)
        line = re.sub(r"(?<![^ \t\n\x0B\f\r])[^ \t\n\x0B\f\r0-9@]*[0-9@][^ \t\n\x0B\f\r]*", "<*>", line).strip(" ")
        t, keys = line.split(" "), []
        n, r = len(line.split(" ")), len(line.split(" ")) - 2
        if n >= 4:
            keys = [("full", line)]
            if n >= 8:
                keys += [(j, n, tuple(t[: 2 + r * j // 4]), tuple(t[2 + r * (j + 1) // 4 :])) for j in range(4)]
        out.append((n, keys))
    return out


def reference_dedup(rows):
    seen = {}
    for i, t in rows:
        if i is not None and t is not None:
            for k, n in {(k, n) for n, ks in reference_templates(t) for k in ks}:
                seen.setdefault(k, []).append((i, n))
    out = []
    for i, t in rows:
        if i is None or t is None:
            out.append((i, t))
            continue
        kept = []
        for raw, (n, keys) in zip(t.split("\n"), reference_templates(t), strict=True):
            drop = any(len({d for d, _ in seen[k]}) > 1 and (len(seen[k]) >= 3 or n >= 50) and i != min(d for d, _ in seen[k]) for k in keys)
            if not drop:
                kept.append(raw)
        out.append((i, "\n".join(kept)))
    return sorted(out, key=repr)


def test_line_templates_equal_reference(spark, docs, none):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    got = line_templates.dedup_lines(docs).select("__row.*", F.col("__text").alias("rest"))
    assert set(docs.columns) <= set(got.columns)
    assert sorted(((r["doc_id"], r["rest"]) for r in got.collect()), key=repr) == reference_dedup(rows)
    assert line_templates.dedup_lines(none).count() == 0
    log = [(i, f"job {i} started on node{i} with {i * 3} workers at level high today\nown line {'abcdefgh'[i]} " + "z" * i + " of this file only") for i in range(6)]
    df = spark.createDataFrame(log, "doc_id bigint, text string")
    out = {r["doc_id"]: r["__text"] for r in line_templates.dedup_lines(df).select("__row.doc_id", "__text").collect()}
    assert "job 0" in out[0] and all("job" not in out[i] and "own line" in out[i] for i in range(1, 6))


def test_line_templates_field_in_the_middle(spark):
    words = ["Report", "of", "the", "day", "by", "NAME", "was", "filed", "and", "closed", "in", "time"]
    rows = [(i, " ".join(words).replace("NAME", n)) for i, n in enumerate(["anna", "berta", "carla", "dora"])]
    out = {r["doc_id"]: r["__text"] for r in line_templates.dedup_lines(spark.createDataFrame(rows, "doc_id bigint, text string")).select("__row.doc_id", "__text").collect()}
    assert out == {0: rows[0][1], 1: "", 2: "", 3: ""}


def test_tokenizer_equals_library():
    tok = packing.WordTokenizer(packing.public_tokenizer_path("word_bpe_49k.json"), cache=50)
    for t in ["", " ", "DON'T it's É éx l'll a\x1cb \x0bq ÀÉ×÷ 12,3 _a_ 's''d", "a\xa0b µ ª", "a <|endoftext|> b", "ΑΣ é é 漢字", "x" * 5000, " ".join(f"q{i}z" for i in range(300)), "İstanbul ǅ ſt"]:
        assert tok.encode(t) == tok.whole([t])[0]


def check_packing(rows, texts):
    tok = packing.WordTokenizer(packing.public_tokenizer_path("word_bpe_49k.json"))
    want = []
    for i, t in texts:
        ids = tok.whole([t or ""])[0] + np.uint32(1).tobytes()
        for k, at in enumerate(range(0, len(ids), 4096 * 4)):
            want.append((i, k, at // 4, len(ids[at : at + 4096 * 4]) // 4, zlib.crc32(ids[at : at + 4096 * 4])))
    assert sorted(((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows), key=repr) == sorted(want, key=repr)
    bins = {}
    for r in rows:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 4096
    return len(bins), -(-sum(r["length"] for r in rows) // 4096)


def test_packing_whole_gapless_and_tight(spark, docs, none):
    rows = packing.pack(docs).collect()
    check_packing(rows, [(r["doc_id"], r["text"]) for r in docs.collect()])
    assert packing.pack(none).count() == 0
    d = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    bins, least = check_packing(packing.pack(d).collect(), [(r["doc_id"], r["text"]) for r in d.collect()])
    assert bins <= least + 1


def test_plan_is_as_good_as_exhaustive_search():
    assert packing.fullest([5, 4, 3], {5: 1, 4: 2, 3: 1}, 8) in ([(4, 2)], [(5, 1), (3, 1)])
    rng = random.Random(3)
    for _ in range(200):
        h = {rng.randint(1, 30): rng.randint(1, 9) for _ in range(rng.randint(1, 8))}
        p = packing.plan(h, 30)
        for w, n in h.items():
            rank = np.arange(n)
            where, offset = packing.place(p, np.full(n, w), rank)
            assert len(set(zip(where.tolist(), offset.tolist(), strict=True))) == n
        assert int(p["bins"][0]) >= -(-sum(w * n for w, n in h.items()) // 30)


def shingles(t):
    w = re.findall("[^\x20\x09-\x0D]+", (t or "").translate({i: i + 32 for i in range(65, 91)}))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def brute_components(rows):
    sets = [(i, shingles(t)) for i, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            x, y = sets[a][1], sets[b][1]
            if x and y and 100 * len(x & y) >= 75 * len(x | y):
                root[find(a)] = find(b)
    low = {}
    for a, (i, _) in enumerate(rows):
        if i is not None:
            low[find(a)] = min(low.get(find(a), i), i)
    return sorted(((i, len(sets[a][1]), low.get(find(a)) if sets[a][1] else i) for a, (i, _) in enumerate(rows)), key=repr)


def mutated(rng, words, edits):
    w = list(words)
    for _ in range(edits):
        w[rng.randrange(len(w))] = f"n{rng.randrange(10**6)}"
    return " ".join(w)


@pytest.mark.parametrize("small", [4_000_000, 0])
def test_jaccard_components_equal_all_pairs(spark, docs, none, monkeypatch, small):
    monkeypatch.setattr(jaccard_join, "SMALL", small)
    rng = random.Random(11)
    rows = []
    for g in range(12):
        words = [f"g{g}w{rng.randrange(40)}" if g % 3 else f"w{rng.randrange(4000)}" for _ in range(rng.choice([4, 7, 30, 90]))]
        rows += [(len(rows) + k, mutated(rng, words, rng.randint(0, 3))) for k in range(rng.randint(1, 12))]
    rows += [(1000 + i, None if i % 2 else "") for i in range(4)]
    got = jaccard_join.linked_classes(spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)).collect()
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=repr) == brute_components(rows)
    got = jaccard_join.linked_classes(docs).collect()
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=repr) == brute_components([(r["doc_id"], r["text"]) for r in docs.collect()])
    assert jaccard_join.linked_classes(none).count() == 0


def test_prefix_tree_equals_brute_force():
    rng = random.Random(5)
    for _ in range(120):
        base = [set(rng.sample(range(400), rng.choice([1, 3, 8, 20, 60]))) for _ in range(4)]
        sets = []
        for _ in range(rng.randint(1, 25)):
            b = set(rng.choice(base))
            for _ in range(rng.randint(0, max(1, len(b) // 5))):
                b = b | {rng.randrange(400)} if rng.random() < 0.5 or len(b) < 2 else b - {rng.choice(sorted(b))}
            sets.append(np.array(sorted(b), np.uint64))
        order = np.array([rng.choice([0, 0, 0, 2, 9]) for _ in range(512)])
        stored = [jaccard_join.ordered(s, order) for s in sets]
        tree = jaccard_join.PrefixTree(stored)
        for s, q in zip(sets, stored, strict=True):
            common = [len(np.intersect1d(s, x)) for x in sets]
            want = {(j, c) for j, c in enumerate(common) if 100 * c >= 75 * (len(s) + len(sets[j]) - c)}
            assert set(tree.linked(q)) == want


def test_shingle_digests_tell_sets_apart():
    sh = word_sets.Shingler(chunk=50)
    texts = ["a b c d e f", "A b  c\td e f", "", None, "a b", "b a", "x " * 40, "one two three four five"]
    got = sh.sets(texts)
    assert [len(x) for x in got] == [len(shingles(t)) for t in texts]
    assert (got[0] == got[1]).all() and got[4] != got[5]


def test_lookup_sketch_equals_sets(spark, docs, none):
    rows = sorted(((r["doc_id"], r["text"] or "") for r in docs.collect()), key=lambda r: (r[0] is not None, r[0] or 0), reverse=True)
    out = lookup_sketch.fingerprints(docs).collect()
    assert len(out) == len(rows) and lookup_sketch.fingerprints(none).count() == 0
    got = {}
    for r in out:
        got.setdefault(r["doc_id"], []).append(r)
    assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in out)
    same = {}
    for r in out:
        same.setdefault(r["doc_id"], set()).add(r["fingerprint"])
    assert len(same[2]) == 1 and same[1] == same[2]
    for i, (doc, t) in enumerate(rows):
        if doc is None or doc in (2,):
            continue
        nxt = rows[(i + 1) % len(rows)]
        if nxt[0] is None:
            continue
        k = len(t) // 3
        edited = t[: len(t) - k] + nxt[1][:k]
        assert got[doc][0]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest(), doc


def test_lookup_sketch_has_one_block_rule_for_all_lengths(spark):
    def text(seed, n):
        words = " ".join(f"v{seed}x{i}" for i in range(n // 5)).split(" ")
        return "\n".join(" ".join(words[i : i + 100]) for i in range(0, len(words), 100))[:n]

    def sets(t):
        return {b.rstrip(" ") for b in re.findall(r"(?:[^ \n]+ *){1,40}", t)}

    rows, want = [], {}
    for i, at in enumerate((16384, 32768, 65536)):
        long = text(i, at + 60)
        rows += [(3 * i + 2, long), (3 * i + 1, long[: at - 60]), (3 * i, "short one")]
    by = dict(rows)
    for i in (8, 7, 5, 4, 2, 1):
        a, nxt = by[i], by[i - 1]
        k = len(a) // 3
        for name, t in (("near_edited", a[: len(a) - k] + nxt[:k]), ("near_next", nxt)):
            want[i, name] = len(sets(a) & sets(t)) / len(sets(a) | sets(t))
    got = {r["doc_id"]: r for r in lookup_sketch.fingerprints(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert all(want[i, "near_next"] > 0.9 for i in (8, 5, 2)) and all(want[i, "near_edited"] > 0.3 for i in (8, 7, 5, 4, 2, 1))
    for (i, name), x in want.items():
        assert got[i][name] == pytest.approx(x), (i, name)


@pytest.mark.parametrize("n", [0, 1, 5, 20, 60, 200])
def test_peeling_recovers_differences(spark, n):
    rng = random.Random(n)
    common = [rng.randrange(-(2**63), 2**63) for _ in range(30)]
    a = common + [rng.randrange(-(2**63), 2**63) for _ in range(n)]
    b = common + [rng.randrange(-(2**63), 2**63) for _ in range(n // 2)]
    df = spark.createDataFrame([(a, b)], "a array<bigint>, b array<bigint>")
    fa, fb = lookup_sketch.sketch(F.col("a"), lookup_sketch.CELLS), lookup_sketch.sketch(F.col("b"), lookup_sketch.CELLS)
    got = df.select(lookup_sketch.likeness(F.col("a"), F.col("b"), fa, fb).alias("x"), lookup_sketch.difference(F.col("a"), F.col("b"), 1536).alias("d")).first()
    assert got["x"] == pytest.approx(30 / (30 + n + n // 2)) and got["d"] == n + n // 2


def test_context_trees_give_exact_code_lengths():
    langs = {"x": b"abracadabra abracadabra", "y": b"the cat sat on the mat"}
    counts = {k: np.unique(byte_contexts.contexts(v), return_counts=True) for k, v in langs.items()}
    m = byte_contexts.ContextTrees(sorted(langs), counts)

    def brute(data, text):
        padded, train, total = b"\0" * 4 + text, b"\0" * 4 + data, 0.0
        for i in range(4, len(padded)):
            for k in range(4, -1, -1):
                ctx = padded[i - k : i]
                nexts = [train[j] for j in range(4, len(train)) if train[j - k : j] == ctx]
                if not nexts:
                    continue
                q, c = len(set(nexts)), nexts.count(padded[i])
                if c:
                    total -= np.log2(c / (len(nexts) + q))
                    break
                total -= np.log2(q / (len(nexts) + q))
            else:
                total += 8
        return total

    for t in (b"abra", b"the dog", b"zzz", b"cat abracadabra"):
        got = m.lengths(byte_contexts.contexts(t)).sum(axis=0)
        assert got == pytest.approx([brute(langs["x"], t), brute(langs["y"], t)], abs=1e-3)


def test_hash_index_finds_what_is_there():
    rng = np.random.default_rng(1)
    keys = np.unique(rng.integers(0, 2**60, 5000).astype(np.uint64))
    h = byte_contexts.HashIndex(keys)
    assert (h.find(keys) == np.arange(len(keys))).all()
    other = np.setdiff1d(rng.integers(0, 2**60, 5000).astype(np.uint64), keys)
    assert (h.find(other) == -1).all()


def test_language_edge_rows_and_held_out_accuracy(spark, docs, none):
    rows = byte_contexts.identify(docs.select("doc_id", "text"), byte_contexts.train(docs)).collect()
    assert len(rows) == docs.count()
    by = {r["doc_id"]: r for r in rows}
    assert by[4]["lang_pred"] == by[5]["lang_pred"] == by[9]["lang_pred"] == by[13]["lang_pred"] == "und" and by[13]["score"] == 0
    assert by[1]["held_out"] == (zlib.crc32(b"1") % 5 == 0)
    assert byte_contexts.train(none) is None and byte_contexts.identify(none.select("doc_id", "text"), None).count() == 0
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    r = byte_contexts.identify(d.select("doc_id", "text"), byte_contexts.train(d)).join(d.select("doc_id", "lang"), "doc_id").where("held_out")
    hit, n = r.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int")), F.count("*")).first()
    assert n > 100 and hit > 0.97


def brute_kneser_ney(texts):
    """Probabilities of a 4-gram model by the textbook recursion, from plain dictionaries."""
    top = {}
    for t in texts:
        s = "\0\0\0" + t
        for i in range(3, len(s)):
            top[s[i - 3 : i + 1]] = top.get(s[i - 3 : i + 1], 0) + 1
    counts = {4: top}
    for n in (3, 2, 1):
        counts[n] = {}
        for g in counts[n + 1]:
            counts[n][g[1:]] = counts[n].get(g[1:], 0) + 1
    cut = {}
    for n, c in counts.items():
        m = [sum(v == i for v in c.values()) for i in range(6)]
        y = m[1] / (m[1] + 2 * m[2]) if m[1] + 2 * m[2] else 0
        cut[n] = [max(0.05, min(i * 0.95, i - (i + 1) * y * m[i + 1] / m[i] if m[1] and m[i] else 0.5 * i)) for i in (1, 2, 3)]

    def p(g):
        n = len(g)
        if n == 0:
            return 1 / (len(counts[1]) + 1)
        own = {k: v for k, v in counts[n].items() if k[:-1] == g[:-1]}
        if not own:
            return p(g[1:])
        total = sum(own.values())
        gamma = sum(cut[n][min(v, 3) - 1] for v in own.values()) / total
        c = own.get(g, 0)
        return (max(0, c - cut[n][min(c, 3) - 1]) / total if c else 0) + gamma * p(g[1:])

    return p


def test_kneser_ney_equals_textbook(spark):
    trusted = ["the cat sat on the mat", "a cat and a rat", "the the the rat"]
    p = brute_kneser_ney(trusted)
    df = spark.createDataFrame([("en", t) for t in trusted], "lang string, text string")
    grams, contexts = kneser_ney.train(df)
    tests = ["the cat", "zebra", "a", "rat sat \U0001f642", "q"]
    rows = spark.createDataFrame([(i, "en", t) for i, t in enumerate([*tests, "", "x"])], "id bigint, lang string, text string").withColumn("lang", F.when(F.col("id") == 6, "xx").otherwise(F.col("lang")))
    for score in (kneser_ney.score_blocks, kneser_ney.score_shards):
        got = {r["id"]: (r["n"], r["nats"]) for r in score(rows, grams, contexts).collect()}
        for i, t in enumerate(tests):
            s = "\0\0\0" + t.replace("\U0001f642", "�")
            assert got[i][1] == pytest.approx(-sum(np.log(p(s[j - 3 : j + 1])) for j in range(3, len(s))), rel=1e-9)
        assert all(got[i][1] is None or np.isnan(got[i][1]) for i in (5, 6))


def test_quality_keeps_trusted_and_drops_noise(spark, docs, none):
    d, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    out = kneser_ney.classify(d, labels).join(labels, "doc_id")
    good, bad = (out.where(c).agg(F.avg(F.col("keep").cast("int"))).first()[0] for c in ("quality = 1 and toxic = 0", "quality = 0"))
    assert good > 0.98 and bad < 0.3
    few = labels.where("doc_id < 0")
    assert kneser_ney.keep_good(docs, few).count() == docs.count() and kneser_ney.keep_good(docs, few).columns == docs.columns
    assert kneser_ney.keep_good(docs, labels).count() <= docs.count() and kneser_ney.keep_good(none, labels).count() == 0


def test_quality_of_repeated_rows_is_that_of_one(spark):
    rows = [(i, "en", f"the cat number {i} sat on the mat by the rat") for i in range(6)]
    rows += [rows[0]] * 3 + [(9, "en", "zzz qqq the")] * 2
    d = spark.createDataFrame(rows, "doc_id bigint, lang string, text string")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(6)], "doc_id bigint, quality int, toxic int")
    big, small = (sorted((r["doc_id"], r["perplexity"], r["threshold"], r["keep"]) for r in kneser_ney.classify(d, labels, small=n).collect()) for n in (kneser_ney.SMALL, 0))
    assert len(big) == len(rows) and [r[0] for r in big] == [r[0] for r in small]
    for b, s in zip(big, small, strict=True):
        assert s[1:3] == pytest.approx(b[1:3], rel=1e-9) and s[3] == b[3]


def test_quality_rejects_labelled_junk(spark):
    d, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    out = kneser_ney.classify(d, labels).join(labels, "doc_id")
    good, bad, toxic = (out.where(c).agg(F.avg(F.col("keep").cast("int"))).first()[0] for c in ("quality = 1 and toxic = 0", "quality = 0", "quality = 1 and toxic = 1"))
    assert good > 0.98 and bad < 0.08 and toxic < 0.75, (good, bad, toxic)
