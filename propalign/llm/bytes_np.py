"""Hashes over the bytes of many texts at once, for use inside Arrow batches."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute

#: Bytes of text that a worker takes at a time; what it derives from them is some fifty times as large.
AT_A_TIME = 1_000_000


def slices(batch: pa.RecordBatch, column: int, most: int = AT_A_TIME) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows, each with at most so many bytes in a column of texts, or one row."""
    upto = np.cumsum(pa.compute.fill_null(pa.compute.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False))
    at = 0
    while at < batch.num_rows:
        k = max(1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + most, side="right")) - at)
        yield batch.slice(at, k)
        at += k


def give_back() -> None:
    """Hands memory that a task no longer uses back to the system: workers stay for later tasks, idle ones beside busy ones."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


_rng = np.random.default_rng(20240229)
#: A random 64-bit number for each byte, twice; and odd bases whose powers weigh the places.
TABLES = _rng.integers(1, 2**63, size=(2, 256), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
BASES = [int(x) | 1 for x in _rng.integers(2**40, 2**63, size=2)]
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}
_M64 = (1 << 64) - 1


def powers(which: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The powers of a base modulo 2**64, and of its inverse, up to n of each at least."""
    found = _powers.get(which)
    if found is None or len(found[0]) < n:
        size = max(n, 1 << 20)
        out = []
        for base in (BASES[which], pow(BASES[which], -1, 1 << 64)):
            p = np.ones(size, dtype=np.uint64)
            step, done = base, 1
            while done < size:  # doubling: p[done:2*done] = p[:done] * base**done
                m = min(done, size - done)
                p[done : done + m] = p[:m] * np.uint64(pow(base, done, 1 << 64))
                done += m
            out.append(p)
        found = _powers[which] = (out[0], out[1])
    return found


class Prefix:
    """Prefix hashes of an array of bytes, or of words' hashes: the hash of any stretch in constant time, equal for equal
    stretches wherever they stand."""

    def __init__(self, data: np.ndarray, which: int = 0):
        self.up, self.down = powers(which, len(data) + 1)
        self.sums = np.zeros(len(data) + 1, dtype=np.uint64)
        symbols = TABLES[which][data] if data.dtype == np.uint8 else data
        np.cumsum(symbols * self.up[: len(data)], out=self.sums[1:])

    def of(self, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        return (self.sums[stop] - self.sums[start]) * self.down[start]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit (the finaliser of splitmix64)."""
    x = x.copy()
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_space = np.zeros(256, dtype=bool)
_space[[32, 9, 10, 11, 12, 13]] = True
_lower = np.arange(256, dtype=np.uint8)
_lower[65:91] += 32


def word_hashes(raw: list[bytes], lower: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(hash, start, stop) of every word of all texts, places counted as if a space stood behind each text; and the number of
    words before the end of each text."""
    data = np.frombuffer(b" ".join(raw) + b" ", dtype=np.uint8)
    if lower:
        data = _lower[data]
    inside = ~_space[data]
    edge = np.flatnonzero(np.diff(np.concatenate([[False], inside, [False]])))
    start, stop = edge[0::2], edge[1::2]
    word = mix(Prefix(data).of(start, stop) + (stop - start).astype(np.uint64))
    return word, start, stop, np.searchsorted(start, np.cumsum([len(r) + 1 for r in raw]))


def word_codes(raw: list[bytes]) -> list[bytes]:
    """Each text as the hashes of its words, 8 bytes a word."""
    word, _, _, upto = word_hashes(raw)
    return [word[a:b].tobytes() for a, b in zip([0, *upto[:-1]], upto, strict=True)] if raw else []


def shingle_sets(texts: list[str | None], words: int = 5) -> list[np.ndarray]:
    """For each text, the sorted distinct 64-bit hashes of its runs of so many words, A-Z in lower case.

    A text with fewer words has one, for all of them; one without words has none.
    """
    raw = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
    word, _, _, upto = word_hashes(raw, True)
    factor = [np.uint64(pow(0x9E3779B97F4A7C15, j + 1, 1 << 64)) for j in range(words)]
    n = len(word) - words + 1
    runs = mix(sum(word[j : j + n] * factor[j] for j in range(words))) if n > 0 else np.zeros(0, dtype=np.uint64)
    out, before = [], 0
    for last in upto:
        k = last - before
        if k >= words:
            out.append(np.unique(runs[before : last - words + 1]))
        elif k:
            own = (word[before:last] * np.array(factor[:k], dtype=np.uint64)).sum(dtype=np.uint64, keepdims=True)
            out.append(mix(own + np.full(1, k * 7919, dtype=np.uint64)))
        else:
            out.append(np.zeros(0, dtype=np.uint64))
        before = last
    return out
