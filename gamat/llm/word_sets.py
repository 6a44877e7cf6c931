"""Sets of word shingles as sorted arrays of 64-bit digests, computed for whole batches of texts at once."""

from __future__ import annotations

import numpy as np

#: Odd multipliers of the digests (golden ratio, and the two of a public 64-bit finaliser).
GOLD, MIX1, MIX2 = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB
SPACES = np.zeros(256, bool)
SPACES[[32, 9, 10, 11, 12, 13]] = True


def mix(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(MIX1)
    x ^= x >> np.uint64(27)
    x *= np.uint64(MIX2)
    x ^= x >> np.uint64(31)
    return x


def powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.cumprod(out)


BYTE = mix((np.arange(256, dtype=np.uint64) + np.uint64(1)) * np.uint64(GOLD))
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def inverse(base: int) -> int:
    return pow(base, -1, 1 << 64)


class Shingler:
    """Shingle digests of texts: A-Z lower-cased, words between blanks, `size` words each.

    A word's digest is a polynomial in 64-bit arithmetic over random byte values, read off prefix sums; a shingle's is
    a polynomial over its words' digests."""

    def __init__(self, size: int = 5, chunk: int = 1 << 18):
        self.size, self.chunk = size, chunk
        self.up, self.down = powers(GOLD, chunk + 1), powers(inverse(GOLD), chunk + 1)

    def words(self, data: bytes) -> tuple[np.ndarray, np.ndarray]:
        """Digests and start offsets of the words of one buffer."""
        raw = np.frombuffer(data, np.uint8)
        if len(raw) + 1 > len(self.up):
            self.up, self.down = powers(GOLD, len(raw) + 1), powers(inverse(GOLD), len(raw) + 1)
        word = np.concatenate(([False], ~SPACES[raw], [False]))
        edge = np.flatnonzero(word[1:] != word[:-1])
        start, end = edge[::2], edge[1::2]
        sums = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum(BYTE[LOWER[raw]] * self.up[: len(raw)], out=sums[1:])
        return mix((sums[end] - sums[start]) * self.down[start] + (end - start).astype(np.uint64)), start

    def sets(self, texts: list[str | None]) -> list[np.ndarray]:
        """The sorted set of each text; empty without words. Fewer than `size` words make one shingle."""
        out: list[np.ndarray] = []
        group: list[bytes] = []
        held = 0
        for t in texts:
            b = (t or "").encode("utf-8", "surrogatepass")
            if group and held + len(b) >= self.chunk:
                out += self._sets(group)
                group, held = [], 0
            group.append(b)
            held += len(b) + 1
        return out + self._sets(group) if group else out

    def _sets(self, group: list[bytes]) -> list[np.ndarray]:
        digest, start = self.words(b"\n".join(group))
        bounds = np.cumsum([0] + [len(b) + 1 for b in group])
        first = np.searchsorted(start, bounds)
        k, n = self.size, len(digest)
        factor = powers(MIX1, k)
        if n >= k:
            rolled = digest[: n - k + 1] * factor[0]
            for j in range(1, k):
                rolled = rolled + digest[j : n - k + 1 + j] * factor[j]
            rolled = mix(rolled)
        out = []
        for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
            if b - a >= k:
                out.append(np.unique(rolled[a : b - k + 1]))
            elif b > a:
                out.append(mix(np.array([(digest[a:b] * factor[: b - a]).sum(dtype=np.uint64)]) + np.uint64(b - a)))
            else:
                out.append(np.empty(0, np.uint64))
        return out


def set_digest(s: np.ndarray) -> int:
    """Signed 64-bit digest of a set: equal sets, equal digests."""
    if not len(s):
        return 0
    a = mix(s).sum(dtype=np.uint64)
    b = np.bitwise_xor.reduce(mix(s ^ np.uint64(GOLD)))
    return int(mix(np.array([a]) * np.uint64(GOLD) + np.array([b]) + np.uint64(len(s)))[0].astype(np.int64))
