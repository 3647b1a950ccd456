"""Sketches that the local fold builds with numpy, in the formats of the engine's own aggregates.

HyperLogLog: images that `hll_union_agg` and `hll_sketch_estimate` read, with the registers that `hll_sketch_agg` has for
the same 64-bit hashes. Bloom filters: bitmap blocks for `bitmap_or_agg`; a value's block comes from some bits of its hash
and its places inside the block from others, so a path with few values has few blocks, and filters of one size merge by
OR. Histograms: bins joined nearest first, many pairs a round, until the asked number is left.
"""

from __future__ import annotations

import math

import numpy as np

LG_K = 12
#: Distinct coupons that an image lists one by one; with more it holds all registers.
LISTED = 256
#: Bits of a Bloom filter's block: what one bitmap of the engine holds.
BLOCK_BITS = 32768
_MASK = (1 << 64) - 1


def hash_texts(texts: list[str]) -> np.ndarray:
    """64-bit hashes of texts, those of the engine's xxhash64."""
    from xxhash import xxh64_intdigest

    return np.fromiter((xxh64_intdigest(t.encode(), 42) for t in texts), np.uint64, len(texts))


def _fmix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def coupons(hashes: np.ndarray) -> np.ndarray:
    """(rank << 26 | address) of each 64-bit key, as the engine's sketch of longs has them (Murmur3 128, its fixed seed)."""
    with np.errstate(over="ignore"):
        k = hashes * np.uint64(0x87C37B91114253D5)
        k = ((k << np.uint64(31)) | (k >> np.uint64(33))) * np.uint64(0x4CF5AD432745937F)
        a = (k ^ np.uint64(9001)) ^ np.uint64(8)
        b = np.uint64(9001 ^ 8)
        a = a + b
        b = b + a
        a, b = _fmix(a), _fmix(b)
        a = a + b
        b = b + a
    high, low = (b >> np.uint64(32)).astype(np.float64), (b & np.uint64(0xFFFFFFFF)).astype(np.float64)
    bits = np.where(high > 0, np.frexp(high)[1] + 32, np.frexp(low)[1])
    rank = np.minimum(64 - bits, 62) + 1
    return (rank.astype(np.uint32) << np.uint32(26)) | (a & np.uint64((1 << 26) - 1)).astype(np.uint32)


class Hll:
    """Coupons while they are few, then one register a byte."""

    __slots__ = ("few", "registers")

    def __init__(self):
        self.few, self.registers = np.zeros(0, np.uint32), None

    def add(self, hashes: np.ndarray) -> None:
        new = coupons(hashes)
        if self.registers is None:
            self.few = np.unique(np.concatenate((self.few, new)))
            if len(self.few) <= LISTED:
                return
            new, self.registers = self.few, np.zeros(1 << LG_K, np.uint8)
        np.maximum.at(self.registers, new & np.uint32((1 << LG_K) - 1), (new >> np.uint32(26)).astype(np.uint8))

    def image(self) -> bytes:
        if self.registers is None:
            n = len(self.few)
            head = bytes([2, 1, 7, LG_K, 3, 8, n, 8]) if n < 8 else bytes([3, 1, 7, LG_K, 0, 8, 0, 9]) + n.to_bytes(4, "little")
            return head + self.few.astype("<u4").tobytes()
        r = self.registers
        share = np.ldexp(1.0, -r.astype(np.int32))
        sums = np.array([0.0, share[r < 32].sum(), share[r >= 32].sum()], "<f8")
        # flag 16: registers came out of order, so the estimate is of the registers alone
        return bytes([10, 1, 7, LG_K, 0, 16, 0, 10]) + sums.tobytes() + int((r == 0).sum()).to_bytes(4, "little") + bytes(4) + r.tobytes()


def bloom_size(expected: int, fpp: float) -> tuple[int, int]:
    """Blocks (a power of two) and places a value, for `expected` values at a false positive rate."""
    bits = math.ceil(-expected * math.log(fpp) / math.log(2) ** 2)
    return 1 << max(0, math.ceil(math.log2(bits / BLOCK_BITS))), max(1, round(-math.log2(fpp)))


class Bloom:
    """Blocks of a filter, by number."""

    __slots__ = ("blocks", "size", "places")

    def __init__(self, size: int, places: int):
        self.blocks, self.size, self.places = {}, size, places

    def add(self, hashes: np.ndarray) -> None:
        block = (hashes >> np.uint64(40)) & np.uint64(self.size - 1)
        a, b = hashes & np.uint64(BLOCK_BITS - 1), (hashes >> np.uint64(15)) & np.uint64(BLOCK_BITS - 1) | np.uint64(1)
        at = (a[:, None] + b[:, None] * np.arange(self.places, dtype=np.uint64)) & np.uint64(BLOCK_BITS - 1)
        order = np.argsort(block, kind="stable")
        block, at = block[order], at[order].astype(np.int64)
        first = np.flatnonzero(np.concatenate(([True], block[1:] != block[:-1])))
        for i, j in zip(first.tolist(), [*first[1:].tolist(), len(block)], strict=True):
            bits = self.blocks.get(int(block[i]))
            if bits is None:
                bits = self.blocks[int(block[i])] = np.zeros(BLOCK_BITS // 8, np.uint8)
            p = at[i:j].ravel()
            np.bitwise_or.at(bits, p >> 3, (1 << (p & 7)).astype(np.uint8))


def shrunk(x: np.ndarray, y: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Bins (values, counts) in order of value, `most` at most: the nearest neighbours are joined, each bin once a round."""
    order = np.argsort(x, kind="stable")
    x, y = x[order], y[order]
    if len(x):
        first = np.flatnonzero(np.concatenate(([True], x[1:] != x[:-1])))
        x, y = x[first], np.add.reduceat(y, first)
    while len(x) > most:
        gaps = np.diff(x)
        take = max(1, min(len(x) - most, len(gaps) // 4))
        at = np.sort(np.argpartition(gaps, take - 1)[:take])
        # of gaps in a row every other one
        start = np.concatenate(([True], np.diff(at) > 1))
        place = np.arange(len(at))
        at = at[(place - np.maximum.accumulate(np.where(start, place, 0))) % 2 == 0]
        n = y[at] + y[at + 1]
        x[at], y[at] = (x[at] * y[at] + x[at + 1] * y[at + 1]) / n, n
        keep = np.ones(len(x), bool)
        keep[at + 1] = False
        x, y = x[keep], y[keep]
    return x, y


class Bins:
    """A histogram; values wait until enough of them are there."""

    __slots__ = ("x", "y", "wait", "n", "most")

    def __init__(self, most: int = 100):
        self.x, self.y, self.wait, self.n, self.most = np.zeros(0), np.zeros(0), [], 0, most

    def add(self, values: np.ndarray) -> None:
        values = values[np.isfinite(values)]
        self.wait.append(values)
        self.n += len(values)
        if self.n > 20_000:
            self.settle()

    def settle(self) -> tuple[np.ndarray, np.ndarray]:
        if self.wait:
            new, counts = np.unique(np.concatenate(self.wait), return_counts=True)
            self.x, self.y = shrunk(np.concatenate((self.x, new)), np.concatenate((self.y, counts.astype(float))), self.most)
            self.wait, self.n = [], 0
        return self.x, self.y
