"""Words of many texts at once as numpy arrays: positions, 64-bit hashes of words and of runs of words.

Hashes are polynomials modulo 2**64 with odd bases, so a hash of any run of words is a difference of two prefix sums times the inverse of a
power; they are mixed afterwards. A hash depends on the words alone, not on where they stand or in which batch.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
BYTE_BASE, WORD_BASE = 0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93


def mixed(x: np.ndarray) -> np.ndarray:
    """Finaliser of splitmix64."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64; kept and grown."""
    if (have := _powers.get(base)) is None or len(have) < n:
        steps = np.full(max(n, 1 << 16), base, U)
        steps[0] = 1
        have = _powers[base] = np.multiply.accumulate(steps)
    return have[:n]


class Prefixes:
    """Hashes of runs of ``values``: ``of(starts, ends)``."""

    def __init__(self, values: np.ndarray, base: int):
        self.sums = np.zeros(len(values) + 1, U)
        np.cumsum(values * powers(base, len(values)), out=self.sums[1:])
        self.inverse = powers(pow(base, -1, 1 << 64), len(values) + 1)

    def of(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mixed((self.sums[ends] - self.sums[starts]) * self.inverse[starts] + (ends - starts).astype(U))


def _release() -> None:
    """Gives freed memory back to the system: workers stay alive between tasks, beside the executor's heap."""
    pa.default_memory_pool().release_unused()
    if _libc is not None:
        _libc.malloc_trim(0)


try:
    _libc = ctypes.CDLL("libc.so.6")
    _libc.malloc_trim  # noqa: B018
except (OSError, AttributeError):  # another C library: it keeps what it keeps
    _libc = None


def slices(texts: pa.Array, most: int = 1 << 19) -> Iterator[tuple[int, list[bytes]]]:
    """(first row, texts as UTF-8) of parts of about ``most`` bytes; a longer text is a part of its own. Null is empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
    ends = np.cumsum(sizes)
    first = 0
    while first < len(sizes):
        before = int(ends[first - 1]) if first else 0
        stop = max(first + 1, int(np.searchsorted(ends, before + most, "right")))
        yield first, [x or b"" for x in texts.slice(first, stop - first).cast(pa.binary()).to_pylist()]
        first = stop
    _release()


class Words:
    """The words of some texts. ``counts``: per text; ``doc``: text of each word; ``first``: its first word; ``hashes`` as asked."""

    def __init__(self, texts: list[bytes], lower: bool = False):
        self.parts = [(x.lower() if lower else x).split() for x in texts]
        self.counts = np.fromiter(map(len, self.parts), np.int64, len(texts))
        self.first = np.concatenate(([0], np.cumsum(self.counts)))
        self.n = int(self.first[-1])
        self.raw = b" ".join(chain.from_iterable(self.parts))
        self.bytes = np.frombuffer(self.raw, np.uint8)
        gaps = np.flatnonzero(self.bytes == 32)
        self.starts = np.concatenate(([0], gaps + 1)) if self.n else gaps
        self.ends = np.concatenate((gaps, [len(self.bytes)])) if self.n else gaps
        self.doc = np.repeat(np.arange(len(texts)), self.counts)

    def letters(self) -> Prefixes:
        """For hashes of parts of words."""
        return Prefixes(self.bytes.astype(U) + U(1), BYTE_BASE)

    def hashes(self) -> np.ndarray:
        return self.letters().of(self.starts, self.ends)


def leftmost_minima(values: np.ndarray, width: int) -> np.ndarray:
    """For each window of ``width`` values the index of its smallest, the leftmost of equal ones."""
    n = len(values) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    at, span = np.arange(len(values)), 1
    while span < width:
        step = min(span, width - span)
        left, right = at[: len(at) - step], at[step:]
        at = np.where(values[right] < values[left], right, left)
        span += step
    return at[:n]
