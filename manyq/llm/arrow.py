"""Arrow batches as byte slabs: whole texts, nulls as empty, in pieces that fit a cache and a worker's memory."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def text_bytes(column: pa.Array) -> list[bytes]:
    """The UTF-8 of every row; null is empty."""
    return pc.fill_null(column, "").cast(pa.binary() if column.type == pa.string() else pa.large_binary()).to_pylist()


def slabs(texts: list[bytes], most: int = 1 << 19) -> Iterator[tuple[int, int, np.ndarray]]:
    """(first row, last row + 1, start offsets and the end) of runs of rows that hold about `most` bytes; a longer row goes alone."""
    at, n = 0, len(texts)
    while at < n:
        size, to = len(texts[at]), at + 1
        while to < n and size + len(texts[to]) <= most:
            size += len(texts[to])
            to += 1
        yield at, to, np.concatenate([[0], np.cumsum([len(t) for t in texts[at:to]])]).astype(np.int64)
        at = to


def give_back() -> None:
    """Return freed memory to the system at a partition's end: workers live on, idle, beside those at work."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)


def random_table(seed: int, n: int = 256, dtype=np.uint64) -> np.ndarray:
    """n fixed pseudo-random odd numbers, from a rule, so that all workers and runs agree."""
    return np.random.Generator(np.random.PCG64(seed)).integers(1, np.iinfo(dtype).max, n, dtype=dtype, endpoint=True) | dtype(1)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit over all."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BASE_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_powers: dict[str, np.ndarray] = {}


def _powers_to(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers["up"]) < n:
        size = max(n, 1 << 19) + 1
        _powers["up"], _powers["down"] = (np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(size, b)])) for b in (_BASE, _BASE_INVERSE))
    return _powers["up"], _powers["down"]


class Words:
    """Word hashes of many texts at once: a polynomial over the bytes from running sums, spread by `mix`.

    parts: for every byte whether it belongs to a word. Texts are joined by a newline, which must not.
    """

    def __init__(self, parts: np.ndarray, seed: int = 11):
        self.parts, self.values = parts, random_table(seed)

    def located(self, texts: list[bytes], prefixes: tuple[int, ...] = ()) -> tuple[bytes, np.ndarray, np.ndarray, np.ndarray, list[np.ndarray]]:
        """(the joined texts, starts and ends of all words there, the first word of each text and the end, hashes); the hashes of whole words, then of their first so many bytes for each of prefixes."""
        joined = b"\n".join(texts) + b"\n"
        slab = np.frombuffer(joined, np.uint8)
        starts_of_texts = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])])
        edge = np.diff(self.parts[slab].view(np.int8), prepend=np.int8(0))
        starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        up, down = _powers_to(len(slab))
        sums = np.zeros(len(slab) + 1, np.uint64)
        np.cumsum(self.values[slab] * up[: len(slab)], out=sums[1:])
        before, shrink = sums[starts], down[starts]
        hashes = [mix((sums[stops] - before) * shrink + np.uint64(p)) for p, stops in ((0, ends), *((p, np.minimum(ends, starts + p)) for p in prefixes))]
        return joined, starts, ends, np.searchsorted(starts, starts_of_texts), hashes

    def of(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(hashes of all words in order, the first word of each text and the end)."""
        _, _, _, first, hashes = self.located(texts)
        return hashes[0], first


#: Words between ASCII white space, as bytes.split() has them.
NOT_BLANK = np.array([chr(b) not in " \t\n\x0b\x0c\r" for b in range(256)])
#: Words of ASCII letters and digits, and of all other characters.
LETTERS = np.array([b >= 128 or chr(b).isalnum() for b in range(256)])
