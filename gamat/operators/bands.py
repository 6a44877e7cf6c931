"""Products in bands of rows: every cell is whole where it arises, so no partial product is sent or folded afterwards.

A band gets its rows of A, and of B the rows that one of its cells asks for. Edges travel in packed chunks, as the same
rows of B may go to several bands. A task holds the edges of its band and goes through it in strips: a strip's cells are
accumulated in a dense array over those columns only that its rows can reach, by matrix products where its factors are
dense and pair by pair where they are sparse. What happens to a finished strip is up to `consume`; a matrix that is only
needed for its effect on a vector is never written."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..types import GraphMatrix, MatrixError, MatrixMeta

#: Cells of a strip's accumulator, and of one that is filled pair by pair; pairs that are multiplied at once; how many cells
#: of a dense product cost one pair; edges of a chunk; parts of a band whose columns are looked for anew.
STRIP_CELLS, SPARSE_CELLS, PAIRS, DENSE_GAIN, CHUNK, PARTS = 4_000_000, 500_000, 200_000, 200, 1_000_000, 6
#: Sums below this are exact in doubles.
EXACT = 2.0**52

Consume = Callable[[np.ndarray, np.ndarray, np.ndarray, np.ndarray], Iterator[pa.RecordBatch]]

#: A chunk of edges sorted by k and i: to is the task it goes to. side 0: rows of A; 1: of B; 2: the k that band n asks for.
PACKED = "to int, side int, n int, k binary, i binary, w binary"


def packed(a: np.ndarray, sorted_: bool = False) -> bytes:
    """Numbers in few bytes: differences where the order helps, of as many bytes as the largest needs, byte by byte."""
    if a.dtype == np.int64:
        if sorted_ and len(a) and float(a.max()) - float(a.min()) < 2.0**62:
            a, head = np.diff(a, prepend=0), b"d"
        else:
            head = b"i"
        lo, hi = (int(a.min()), int(a.max())) if len(a) else (0, 0)
        a = a.astype(next(t for t in (np.int8, np.int16, np.int32, np.int64) if np.iinfo(t).min <= lo and hi <= np.iinfo(t).max))
    else:
        head = b"f"
    size = a.dtype.itemsize
    return head + bytes([size]) + pa.compress(np.ascontiguousarray(a).view(np.uint8).reshape(-1, size).T.tobytes(), codec="zstd", asbytes=True)


def unpacked(b: bytes, n: int) -> np.ndarray:
    size = b[1]
    raw = np.frombuffer(pa.decompress(b[2:], n * size, codec="zstd"), np.uint8).reshape(size, n).T
    a = np.ascontiguousarray(raw).view(np.float64 if b[:1] == b"f" else f"i{size}").reshape(-1)
    return a if b[:1] == b"f" else np.cumsum(a, dtype=np.int64) if b[:1] == b"d" else a.astype(np.int64)


def chunk_rows(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["to", "side", "n", "k", "i", "w"])


def runs(ids: np.ndarray) -> Iterator[tuple[int, int]]:
    """Begin and end of each run of equal ids."""
    cuts = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
    return ((lo, hi) for lo, hi in zip(cuts, cuts[1:], strict=False) if hi > lo)


def by_target(to: np.ndarray, k: np.ndarray, i: np.ndarray, w: np.ndarray, side: int) -> Iterator[tuple]:
    order = np.lexsort((i, k, to))
    to, k, i, w = to[order], k[order], i[order], w[order]
    for lo, hi in runs(to):
        yield int(to[lo]), side, hi - lo, packed(k[lo:hi], True), packed(i[lo:hi], True), packed(w[lo:hi])


def in_chunks(edges: DataFrame, target: Callable[[np.ndarray, np.ndarray], np.ndarray], side: int, kind) -> DataFrame:
    """Edges k, i, w as chunks for the tasks target(k, i)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def out():
            k, i, w = (np.concatenate(c) for c in zip(*held, strict=True))
            return chunk_rows(list(by_target(target(k, i), k, i, w, side)))

        for b in batches:
            columns = [b.column(c) for c in ("k", "i", "w")]
            if any(c.null_count for c in columns):
                raise MatrixError("cells with nulls")
            if b.num_rows:
                # A batch's memory is used again for the next one.
                held.append([c.to_numpy(zero_copy_only=False).astype(t) for c, t in zip(columns, (np.int64, np.int64, kind), strict=True)])
                n += b.num_rows
            if n >= CHUNK:
                yield out()
                held, n = [], 0
        if held:
            yield out()

    return edges.select("k", "i", "w").mapInArrow(run, PACKED)


def gathered(batches: Iterator[pa.RecordBatch]) -> dict[tuple[int, int], list[tuple]]:
    """(to, side): its chunks (n, k, i, w)."""
    found: dict[tuple[int, int], list[tuple]] = {}
    for b in batches:
        for to, side, *chunk in zip(*(c.to_pylist() for c in b.columns), strict=True):
            found.setdefault((to, side), []).append(tuple(chunk))
    return found


def edges_of(chunks: list[tuple], kind) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    if not chunks:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, kind)
    return tuple(np.concatenate([unpacked(c[at], c[0]) for c in chunks]) for at in (1, 2, 3))


def exact_kind(a: GraphMatrix, b: GraphMatrix):
    return np.int64 if dict(a.edges.dtypes)["w"] == "bigint" and dict(b.edges.dtypes)["w"] == "bigint" else np.float64


def dealt(a: GraphMatrix, b: GraphMatrix, bands: int | None = None, size: int = 1) -> DataFrame:
    """The chunks that each band needs, one band to a partition. A is read once: which inner ids a band asks for is seen
    where its rows have arrived, and told to the tasks that hold B by groups of inner ids."""
    bands = bands or int(a.spark.conf.get("spark.sql.shuffle.partitions"))
    height = -(-max(1, a.meta.n_rows) // (bands * size)) * size
    group = -(-max(1, a.meta.n_cols, b.meta.n_rows) // bands)
    kind = exact_kind(a, b)

    def asks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (band, _), chunks in gathered(batches).items():
            k = np.unique(np.concatenate([np.unique(unpacked(c[1], c[0])) for c in chunks]))
            yield chunk_rows([(int(k[lo] // group), 2, band, packed(k[lo:hi], True), (hi - lo).to_bytes(8, "big"), b"") for lo, hi in runs(k // group)])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = gathered(batches)
        for to in [t for t, side in found if side == 2]:
            k, j, w = edges_of(found.get((to, 1), []), kind)
            order = np.lexsort((j, k))
            k, j, w = k[order], j[order], w[order]
            for band, ids, n, _ in found[to, 2] if len(k) else []:
                ids = unpacked(ids, int.from_bytes(n, "big"))
                lo, hi = np.searchsorted(k, ids), np.searchsorted(k, ids, side="right")
                c = hi - lo
                at = np.repeat(lo - (np.cumsum(c) - c), c) + np.arange(int(c.sum()))
                if len(at):
                    yield chunk_rows([(band, 1, len(at), packed(k[at], True), packed(j[at], True), packed(w[at]))])

    left = in_chunks(a.edges.select(F.col("src").alias("k"), F.col("dst").alias("i"), "w"), lambda k, i: i // height, 0, kind).repartitionById(bands, F.col("to"))
    right = in_chunks(b.edges.select(F.col("dst").alias("k"), F.col("src").alias("i"), "w"), lambda k, i: k // group, 1, kind)
    some = right.unionByName(left.mapInArrow(asks, PACKED)).repartitionById(bands, F.col("to")).mapInArrow(meet, PACKED)
    return left.unionByName(some).repartitionById(bands, F.col("to"))


def cells(rows: np.ndarray, cols: np.ndarray, values: np.ndarray, seen: np.ndarray) -> Iterator[pa.RecordBatch]:
    """dst, src, w of the cells that a pair has met."""
    at, col = np.nonzero(seen)
    for lo in range(0, len(at), 1 << 18):
        i, j = at[lo : lo + (1 << 18)], col[lo : lo + (1 << 18)]
        yield pa.RecordBatch.from_arrays([pa.array(rows[i]), pa.array(cols[j]), pa.array(values[i, j])], ["dst", "src", "w"])


def strips(ai, ak, aw, bk, bj, bw, density: float | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, columns, values, seen) strip by strip: the cells of A B for edges (row, inner id, weight), (inner id, column, weight)."""
    kind = np.result_type(aw.dtype, bw.dtype)
    order = np.argsort(bk, kind="stable")
    bk, bj, bw = bk[order], bj[order], bw[order]
    inner, first, count = np.unique(bk, return_index=True, return_counts=True)
    if not len(inner) or not len(ak):
        return
    at = np.minimum(np.searchsorted(inner, ak), len(inner) - 1)
    met = inner[at] == ak
    ai, ak, aw = ai[met], at[met], aw[met]
    order = np.lexsort((ak, ai))
    ai, ak, aw = ai[order], ak[order], aw[order]
    rows, ai = np.unique(ai, return_inverse=True)
    if not len(rows):
        return
    signs = min(aw.min(), bw.min()) <= 0
    most = float(np.abs(aw).max()) * float(np.abs(bw).max())
    share = max(1, -(-len(rows) // PARTS), min(len(rows), STRIP_CELLS // max(1, len(bj))))
    for lo in range(0, len(rows), share):
        s = slice(*np.searchsorted(ai, (lo, lo + share)))
        used, k = np.unique(ak[s], return_inverse=True)
        c = count[used]
        b = spread(first[used], c)
        cols, j = np.unique(bj[b], return_inverse=True)
        yield from part(rows[lo : lo + share], ai[s] - lo, k, aw[s], np.cumsum(c) - c, c, cols, j, bw[b], kind, signs, most, len(inner), density)


def spread(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Positions first, first + 1, ... of each run, one run after the other."""
    return np.repeat(first - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))


def part(rows, ai, ak, aw, first, count, cols, bj, bw, kind, signs, most, all_inner, density):
    """`strips` of rows and columns that are numbered from 0."""
    inner, width = len(count), len(cols)
    per_row = np.bincount(ai, weights=count[ak], minlength=len(rows))
    if kind == np.int64 and most * per_row.max() >= 2.0**63:
        raise OverflowError("sums of a product may exceed 64 bits")
    # Whole numbers go through doubles where no sum can lose a digit.
    kept = np.float64 if most * per_row.max() < EXACT else kind
    aw, bw = aw.astype(kept, copy=False), bw.astype(kept, copy=False)
    height = max(1, STRIP_CELLS // width)
    for lo in range(0, len(rows), height):
        n = min(height, len(rows) - lo)
        s = slice(*np.searchsorted(ai, (lo, lo + n)))
        i, k, w = ai[s] - lo, ak[s], aw[s]
        if len(k) > density * n * all_inner if density is not None else per_row[lo : lo + n].sum() * DENSE_GAIN > float(n) * width * inner:
            out, seen = np.zeros((n, width), kept), np.zeros((n, width), bool) if signs else None
            step = max(1, min(2048, STRIP_CELLS // max(width, n)))
            for k0 in range(0, inner, step):
                k1 = min(inner, k0 + step)
                p, q = np.zeros((n, k1 - k0), kept), np.zeros((k1 - k0, width), kept)
                own = (k >= k0) & (k < k1)
                np.add.at(p, (i[own], k[own] - k0), w[own])
                b, at = slice(first[k0], first[k1 - 1] + count[k1 - 1]), np.repeat(np.arange(k1 - k0), count[k0:k1])
                np.add.at(q, (at, bj[b]), bw[b])
                out += p @ q
                if signs:
                    x, y = np.zeros(p.shape, np.float32), np.zeros(q.shape, np.float32)
                    x[i[own], k[own] - k0] = 1
                    y[at, bj[b]] = 1
                    seen |= x @ y > 0
            out = out.astype(kind, copy=False)
            yield rows[lo : lo + n], cols, out, seen if signs else out != 0
            continue
        few = max(1, SPARSE_CELLS // width)
        for r0 in range(0, n, few):
            m = min(few, n - r0)
            t = slice(*np.searchsorted(i, (r0, r0 + m)))
            out, seen = np.zeros((m, width), kept), np.zeros((m, width), bool) if signs else None
            pair_by_pair(out, seen, i[t] - r0, k[t], w[t], first, count, bj, bw)
            out = out.astype(kind, copy=False)
            yield rows[lo + r0 : lo + r0 + m], cols, out, seen if signs else out != 0


def pair_by_pair(out, seen, i, k, w, first, count, bj, bw) -> None:
    """Adds the pairs of edges (i, k, w), sorted by i, to the cells."""
    width, ends, e0 = out.shape[1], np.cumsum(count[k]), 0
    while e0 < len(k):
        e1 = max(e0 + 1, int(np.searchsorted(ends, (ends[e0 - 1] if e0 else 0) + PAIRS, side="right")))
        c, f = count[k[e0:e1]], first[k[e0:e1]]
        total, r0, r1 = int(c.sum()), i[e0], i[e1 - 1] + 1
        if total > 64 * len(c):
            at = [slice(x, y) for x, y in zip(f.tolist(), (f + c).tolist(), strict=True)]
            col, v = np.concatenate([bj[x] for x in at]), np.concatenate([bw[x] for x in at])
        else:
            b = spread(f, c)
            col, v = bj[b], bw[b]
        cell = np.repeat((i[e0:e1] - r0) * width, c) + col
        v = np.repeat(w[e0:e1], c) * v
        if out.dtype == np.float64:
            out[r0:r1] += np.bincount(cell, weights=v, minlength=(r1 - r0) * width).reshape(-1, width)
        else:
            np.add.at(out[r0:r1].reshape(-1), cell, v)
        if seen is not None:
            seen[r0:r1].reshape(-1)[cell] = True
        e0 = e1


def product(a: GraphMatrix, b: GraphMatrix, consume: Consume = cells, schema: str | None = None, bands: int | None = None, size: int = 1, density: float | None = None, chunks: DataFrame | None = None) -> DataFrame:
    """What `consume` makes of A B, by default its edges; parallel edges of the factors add up. chunks: as `dealt` has made them."""
    kind = exact_kind(a, b)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = gathered(batches)
        for band in sorted(to for to, side in found if side == 0):
            ak, ai, aw = edges_of(found.pop((band, 0)), kind)
            bk, bj, bw = edges_of(found.pop((band, 1), []), kind)
            for strip in strips(ai, ak, aw, bk, bj, bw, density):
                yield from consume(*strip)

    chunks = dealt(a, b, bands, size) if chunks is None else chunks
    return chunks.mapInArrow(run, schema or f"dst bigint, src bigint, w {'bigint' if kind == np.int64 else 'double'}")


def mm(a: GraphMatrix, b: GraphMatrix, **how) -> GraphMatrix:
    return GraphMatrix(product(a, b, **how), MatrixMeta(a.meta.n_rows, b.meta.n_cols))
