"""Personal data: base patterns, and a skip-chain conditional random field that adds what they miss.

Base spans (e-mail, IP address, card, phone) come from exact patterns over the whole text. The field's nodes are the
tokens that hold a digit or "@"; its labels are "none", the four base kinds and "secret" (keys, passwords, tokens).
Node potentials are a softmax regression on shape and left context; neighbouring nodes are linked by learned
transitions; and occurrences of the same or a similar token (equal but for case and signs), however distant, are linked
one to the next and share a learned potential for equal labels. Loopy belief propagation runs over the graphs of
many documents at once; tokens inside base spans are clamped to their kind. Tokens outside base spans that end with
another label than "none" are added.

Training: base spans and a few secret formats label the tokens of about SAMPLE documents with candidates (a documented
bound, drawn by hash), and repeats of such a secret in the same document count as secrets too; every token is also shown
without its context, so that shape alone must do.

Null text counts as empty. Repeated rows are treated alike; other columns are ignored; an empty table gives an empty
result. Without training rows only base spans are returned. Of labels that tie, the first listed wins. Very long texts are
read whole: memory grows with their candidate tokens, not with pairs of them.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_slices

KINDS = ["email", "ip", "card", "phone"]
LABELS = ["none", *KINDS, "secret"]
SAMPLE, STEPS, ROUNDS, LINKS = 6000, 300, 8, 50_000
CUES = 128

# Patterns.
LOCAL = re.compile(r"[A-Za-z0-9._%+-]")
LOCAL_RUN = re.compile(r"[A-Za-z0-9._%+-]*+")
HOST = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
SECRET = re.compile(r"(?:password|passwd|secret|token|api[_-]?key)[\x20]*[=:][\x20]*\"?([A-Za-z0-9+/_-]{8,})|(?<![A-Za-z0-9])(AKIA[0-9A-Z]{16})(?![A-Za-z0-9])")
TOKEN = re.compile(r"(?<![^\s\"'<>(),;|=])[^\s\"'<>(),;|=0-9@]*+[0-9@][^\s\"'<>(),;|=]*+")
HINT = re.compile(r"[0-9@]")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = ord(d) - 48
        if i % 2:
            n = n * 2 - 9 if n > 4 else n * 2
        total += n
    return total % 10 == 0


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost non-overlapping matches, found from their "@" (a plain search is quadratic on long runs)."""
    at, free = text.find("@"), 0
    while at >= 0:
        start = at
        while start > free and LOCAL.match(text, start - 1):
            start -= 1
        m = HOST.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            free = m.end()
            at = text.find("@", free)
        else:
            at = text.find("@", at + 1)


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """All base spans, by kind as listed and then by start; offsets in code points."""
    if not HINT.search(text):
        return []
    out = [("email", a, b) for a, b in emails(text)]
    for m in IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split(".")):
            out.append(("ip", *m.span()))
    for m in CARD.finditer(text):
        digits = re.sub("[^0-9]", "", m.group())
        if 13 <= len(digits) <= 19 and luhn(digits):
            out.append(("card", *m.span()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 9 <= sum(c in "0123456789" for c in m.group()) <= 15:
                out.append(("phone", *m.span()))
    return out


def spans_text(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def candidates(text: str) -> list[tuple[int, int]]:
    out = []
    for m in TOKEN.finditer(text):
        a, b = m.span()
        while b > a and text[b - 1] in ".,:!?":
            b -= 1
        if b > a and HINT.search(text, a, b):
            out.append((a, b))
    return out


def features(text: str, a: int, b: int) -> list[int]:
    """Indices of the binary features of a token that hold."""
    t = text[a:b]
    n = len(t)
    digit = sum(c in "0123456789" for c in t) / n
    upper = sum("A" <= c <= "Z" for c in t) / n
    low = sum("a" <= c <= "z" for c in t) / n
    hexa = all(c in "0123456789abcdef" for c in t)
    length = min(11, int(np.log2(n) * 2))
    kinds = len(set(t)) / n
    cue = text[max(0, a - 24) : a].rstrip(" \"'(").lower()
    words = cue.split(" ")
    # A sign by itself, such as "=", says something only with the word before it.
    word = re.sub("[^a-z+=:]", "", words[-1] if re.search("[a-z]", words[-1]) else "".join(words[-2:]))[-10:]
    out = [0, 1 + length, 13 + int(digit * 4.99), 18 + int(upper * 4.99), 23 + int(low * 4.99), 28 + min(3, int(kinds * 4))]
    out += [32 + i for i, c in enumerate(".-@+:/_") if c in t]
    out += [40 + min(3, t.count("."))]
    out += [44] * hexa + [45] * (hexa and digit < 1 and n >= 12) + [46] * (upper > 0 and digit > 0 and low == 0 and n >= 16) + [47] * (digit == 1)
    return [*out, 48 + zlib.crc32(word.encode("utf-8", "surrogatepass")) % CUES]


WIDTH = 48 + CUES


def sameness(token: str) -> str:
    return re.sub("[^0-9a-z]", "", token.lower())


def nodes_of(text: str, spans: list[tuple[str, int, int]]) -> tuple[list[tuple[int, int]], np.ndarray]:
    """Candidate tokens and their clamped label (0: free)."""
    tokens = candidates(text)
    clamp = np.zeros(len(tokens), np.int64)
    if tokens and spans:
        starts, ends = np.array(tokens).T
        for kind, a, b in spans:
            i = int(np.searchsorted(ends, a, side="right"))
            while i < len(tokens) and starts[i] < b:
                clamp[i] = LABELS.index(kind)
                i += 1
    return tokens, clamp


def links_of(text: str, tokens: list[tuple[int, int]]) -> tuple[list[tuple[int, int]], list[tuple[int, int]]]:
    """Chain links between neighbours, and skip links from each token to the next similar one."""
    chain = [(i, i + 1) for i in range(len(tokens) - 1) if tokens[i + 1][0] - tokens[i][1] <= 40]
    last: dict[str, int] = {}
    skip = []
    for i, (a, b) in enumerate(tokens):
        key = sameness(text[a:b])
        if len(key) >= 5:
            if key in last:
                skip.append((last[key], i))
            last[key] = i
    return chain, skip


class Field:
    """Weights: node (features x labels), chain (labels x labels), skip (one number)."""

    def __init__(self, node: np.ndarray, chain: np.ndarray, skip: float):
        self.node, self.chain, self.skip = node, chain, skip

    def decode(self, feats: list[list[int]], clamp: np.ndarray, chain: list[tuple[int, int]], skip: list[tuple[int, int]]) -> np.ndarray:
        """Labels of all nodes after ROUNDS of loopy message passing."""
        n, k = len(feats), len(LABELS)
        sizes = np.array([len(f) for f in feats])
        unary = np.add.reduceat(self.node[np.concatenate(feats)], np.cumsum(np.concatenate(([0], sizes[:-1]))), axis=0)
        unary[clamp > 0] = -50.0
        unary[clamp > 0, clamp[clamp > 0]] = 50.0
        links = np.array(chain + skip, np.int64).reshape(-1, 2)
        if not len(links):
            return unary.argmax(axis=1)
        return self.beliefs(unary, links, len(chain)).argmax(axis=1)

    def beliefs(self, unary: np.ndarray, links: np.ndarray, chained: int, rounds: int = ROUNDS) -> np.ndarray:
        """Logarithms, up to a constant per node, of the marginals after so many rounds; the first `chained` links are chain
        links. Messages are made LINKS at a time, so that a very long document needs no more than its nodes and links."""
        k = unary.shape[1]
        a, b = links.T
        same = self.skip * np.eye(k)
        to_b, to_a = np.zeros((len(links), k)), np.zeros((len(links), k))
        belief = unary
        cuts = sorted({0, chained, len(links), *range(0, len(links), LINKS)})
        for _ in range(rounds):
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                pair = self.chain if lo < chained else same
                out_a, out_b = belief[a[lo:hi]] - to_a[lo:hi], belief[b[lo:hi]] - to_b[lo:hi]
                to_b[lo:hi], to_a[lo:hi] = lse(out_a[:, :, None] + pair, 1), lse(out_b[:, None, :] + pair, 2)
            to_b -= to_b.max(axis=1, keepdims=True)
            to_a -= to_a.max(axis=1, keepdims=True)
            belief = unary.copy()
            np.add.at(belief, b, to_b)
            np.add.at(belief, a, to_a)
        return belief


def lse(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return (top + np.log(np.exp(x - top).sum(axis=axis, keepdims=True))).squeeze(axis)


def train(docs: DataFrame, sample: int = SAMPLE) -> Field | None:
    """Fit on about `sample` documents that hold a digit or "@"."""
    rows = docs.where(F.col("text").rlike("[0-9@]"))
    total = rows.count()
    if not total:
        return None
    draw = F.pmod(F.xxhash64(F.lit("entity sample"), "text"), F.lit(1 << 30)) / float(1 << 30)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for text in b["text"]:
                tokens, label = nodes_of(text, base_spans(text))
                known = {m.span(1) if m.group(1) else m.span(2) for m in SECRET.finditer(text)}
                for i, (s, e) in enumerate(tokens):
                    if label[i] == 0 and any(x <= s and e <= y for x, y in known):
                        label[i] = LABELS.index("secret")
                # What is a secret at one place is one wherever it stands in the document.
                keys = [sameness(text[s:e]) for s, e in tokens]
                shared = {key for key, y in zip(keys, label, strict=True) if y == LABELS.index("secret") and len(key) >= 5}
                label = np.array([LABELS.index("secret") if not y and key in shared else y for key, y in zip(keys, label, strict=True)], np.int64)
                chain, skip = links_of(text, tokens)
                out += [("node", int(y), 0, 0, features(text, s, e)) for (s, e), y in zip(tokens, label, strict=True)]
                out += [("chain", int(label[i]), int(label[j]), 0, []) for i, j in chain]
                out += [("skip", int(label[i]), int(label[j]), 0, []) for i, j in skip]
            yield pd.DataFrame(out, columns=["what", "y", "z", "m", "f"])

    found = map_slices(rows.where(draw < min(1.0, sample / total)).select("text"), run, "what string, y int, z int, m int, f array<int>")
    # Equal rows are counted, so that what comes to the driver is bounded by the sample and far smaller.
    t = found.groupBy("what", "y", "z", "f").agg(F.count("*").alias("m")).toPandas()
    k = len(LABELS)
    node = t[t["what"] == "node"].sort_values(["y", "f"], key=lambda c: c.map(str))
    if node.empty:
        return None
    x = np.zeros((len(node), WIDTH), np.float32)
    for i, f in enumerate(node["f"]):
        x[i, f] = 1
    y, m = node["y"].to_numpy(), np.sqrt(node["m"].to_numpy())
    # Each token also without its left context, so that its shape alone must be enough.
    bare = x.copy()
    bare[:, 48:] = 0
    x, y, m = np.concatenate((x, bare)), np.concatenate((y, y)), np.concatenate((m, m))
    m = m / np.bincount(y, m, minlength=k)[y] ** 0.5
    m /= m.sum()
    w, target = np.zeros((WIDTH, k), np.float32), np.eye(k, dtype=np.float32)[y]
    for _ in range(STEPS):
        s = x @ w
        p = np.exp(s - s.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        w += 8.0 * (x.T @ (m[:, None] * (target - p))).astype(np.float32) - 1e-4 * w
    count = np.ones((k, k))
    np.add.at(count, (t[t["what"] == "chain"]["y"].to_numpy(), t[t["what"] == "chain"]["z"].to_numpy()), t[t["what"] == "chain"]["m"].to_numpy())
    chain = np.log(count / count.sum()) - np.log(count.sum(axis=1, keepdims=True) / count.sum()) - np.log(count.sum(axis=0, keepdims=True) / count.sum())
    skips = t[t["what"] == "skip"]
    agree = skips[skips["y"] == skips["z"]]["m"].sum()
    return Field(w.astype(np.float64), np.clip(chain, -2, 2), float(np.clip(np.log((agree + 1) / (skips["m"].sum() - agree + 1)), 0.5, 8)))


def find_entities(docs: DataFrame, model: Field | None, block: int = 4000) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone (base spans), base_sha256, spans (base and added), n_added, n_spans (all)."""
    shared = docs.sparkSession.sparkContext.broadcast(cloudpickle.dumps(model))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        field = cloudpickle.loads(shared.value)
        for b in batches:
            base = [base_spans(t or "") for t in b["text"]]
            added: list[list[tuple[str, int, int]]] = [[] for _ in base]
            feats, clamp, chain, skip, owner = [], [], [], [], []

            def settle() -> None:
                if feats:
                    for (i, s, e), c, y in zip(owner, np.concatenate(clamp), field.decode(feats, np.concatenate(clamp), chain, skip), strict=True):
                        if y and not c:
                            added[i].append((LABELS[y], s, e))
                for x in (feats, clamp, chain, skip, owner):
                    x.clear()

            for i, text in enumerate(b["text"]):
                if field is None or not text or not HINT.search(text):
                    continue
                tokens, fixed = nodes_of(text, base[i])
                if tokens:
                    at = len(owner)
                    own, far = links_of(text, tokens)
                    chain += [(x + at, y + at) for x, y in own]
                    skip += [(x + at, y + at) for x, y in far]
                    feats += [features(text, s, e) for s, e in tokens]
                    clamp.append(fixed)
                    owner += [(i, s, e) for s, e in tokens]
                    if len(owner) > block:
                        settle()
            settle()
            rows = []
            for own, more in zip(base, added, strict=True):
                every = sorted(own + more, key=lambda x: (LABELS.index(x[0]), x[1]))
                rows.append((*[sum(k == x[0] for x in own) for k in KINDS], hashlib.sha256(spans_text(own).encode()).hexdigest(), spans_text(every), len(more), len(every)))
            out = pd.DataFrame(rows, columns=["n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_added", "n_spans"])
            out.insert(0, "doc_id", b["doc_id"])
            yield out

    return map_slices(docs.select("doc_id", "text"), run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long, n_spans long")


def op1_skip_chain(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return find_entities(docs, train(docs))
