"""Whole-text tokenising and hashing with numpy, shared by the corpus operators.

Texts are handled as UTF-8 bytes.  A-Z count as a-z.  Words are maximal runs of bytes of one class:

* ``SPACED``: everything but ``\\x20 \\x09-\\x0D``;
* ``ALNUM``: digits, letters a-z and every byte from 0x80 on (so all non-ASCII characters).

Multi-byte characters only hold bytes from 0x80 on, so byte runs and character runs are the same.
A word's 64-bit hash is a polynomial over random byte values, read off wrapped prefix sums, so that a
whole block of texts is hashed without a Python loop.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SPACE_BYTES = np.array([0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D])
SPACED = np.ones(256, bool)
SPACED[SPACE_BYTES] = False
ALNUM = np.zeros(256, bool)
ALNUM[0x30:0x3A] = ALNUM[0x41:0x5B] = ALNUM[0x61:0x7B] = ALNUM[0x80:] = True

LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32

ODD = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit (in place where it can)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


#: A random value for every byte; upper and lower case of a letter share one.
BYTE_VALUE = mix(np.arange(1, 257, dtype=np.uint64) * ODD)[LOWER]

#: Bytes that are hashed at once.
PIECE = 1 << 18
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the polynomial's base and of its inverse modulo 2^64, grown to at least n entries."""
    if len(_POWERS.get("up", ())) < n:
        size = max(1 << 16, 1 << int(n - 1).bit_length())
        base = int(ODD)
        for name, b in (("up", base), ("down", pow(base, -1, 1 << 64))):
            steps = np.full(size, b, np.uint64)
            steps[0] = 1
            _POWERS[name] = np.multiply.accumulate(steps)
    return _POWERS["up"], _POWERS["down"]


def text_blocks(column: pa.Array, most: int = 2 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``most`` bytes each; a longer text is a range of its own."""
    sizes = np.fromiter((0 if x is None else len(x) for x in column), np.int64, len(column)) if isinstance(column, list) else lengths(column)
    start = filled = 0
    for i, size in enumerate(sizes.tolist()):
        if i > start and filled + size > most:
            yield start, i
            start, filled = i, 0
        filled += size
    if len(sizes) > start:
        yield start, len(sizes)


def lengths(column: pa.Array) -> np.ndarray:
    import pyarrow.compute as pc

    return pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)


def joined(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The column's bytes, each text followed by a space, and the offsets of the texts in them."""
    texts = [x or b"" for x in column.cast(pa.binary()).to_pylist()]
    ends = np.cumsum([len(x) + 1 for x in texts], dtype=np.int64)
    buffer = np.frombuffer(b" ".join(texts) + b" ", np.uint8) if texts else np.zeros(0, np.uint8)
    return buffer, np.concatenate([[0], ends]).astype(np.int64)


class Words:
    """The words of a block of texts.

    start, end: byte ranges; hash: 64 bits each; offset: text i has words offset[i] to offset[i+1].
    """

    def __init__(self, column: pa.Array, kind: np.ndarray = SPACED, values: np.ndarray = BYTE_VALUE):
        buffer, texts = joined(column)
        self.buffer, self.texts = buffer, texts
        inside = kind[buffer]
        edge = np.flatnonzero(np.diff(inside.view(np.int8), prepend=0, append=0))
        self.start, self.end = edge[0::2], edge[1::2]
        self.hash = np.zeros(len(self.start), np.uint64)
        # In pieces that stay in the processor's cache: a hash doesn't depend on where a piece begins.
        cuts = np.unique(np.append(np.searchsorted(self.start, np.arange(0, len(buffer), PIECE)), len(self.start)))
        for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            first = self.start[i]
            begin, end = self.start[i:j] - first, self.end[i:j] - first
            up, down = _powers(int(end[-1]) + 1)
            total = np.zeros(end[-1] + 1, np.uint64)
            np.cumsum(values[buffer[first : first + end[-1]]] * up[: end[-1]], out=total[1:])
            self.hash[i:j] = mix((total[end] - total[begin]) * down[begin] + (end - begin).astype(np.uint64))
        self.offset = np.searchsorted(self.start, texts)

    def counts(self) -> np.ndarray:
        return np.diff(self.offset)

    def owner(self) -> np.ndarray:
        """The text of every word."""
        return np.repeat(np.arange(len(self.offset) - 1), self.counts())

    def spelled(self, i: int) -> bytes:
        return self.buffer[self.start[i] : self.end[i]].tobytes().lower()


def windows(hashes: np.ndarray, size: int) -> np.ndarray:
    """Hashes of the runs of ``size`` words that start at each word (the last size-1 are missing)."""
    n = len(hashes) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for k in range(size):
        out *= ODD
        out += hashes[k : k + n]
    return mix(out)


def segment_sum(values: np.ndarray, offset: np.ndarray) -> np.ndarray:
    """Sums of values[offset[i]:offset[i+1]]; empty ranges give 0."""
    total = np.concatenate([[0], np.cumsum(values)])
    return total[offset[1:]] - total[offset[:-1]]


def ship(context, thing):
    """Broadcasts any object; its class goes along, so workers need no copy of the repository."""
    from pyspark import cloudpickle

    return context.broadcast(cloudpickle.dumps(thing))


def opened(shipped):
    return pickle.loads(shipped.value)
