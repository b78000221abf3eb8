"""Byte-level BPE with frozen ranks: length-bucketed matrices of pieces, merged a pair per row and round.

Distinct pieces of a block are encoded once.  Pieces of like length form a padded matrix of token numbers, row by
row in one array.  In each round every row looks up the ranks of its neighbouring pairs in a hash table, merges its
leftmost pair of least rank, and closes the gap; rows without a pair in the table leave the matrix.
Very long pieces (over ``LONG`` bytes) take a heap instead, as a matrix needs as many rounds as a piece has bytes.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.llm.bytewords import opened, ship, text_blocks

CODED = "doc_id long, ids array<int>, decoded binary"
DIGESTS = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
LONG = 2048
NONE = np.int32(2**31 - 1)


class PairTable:
    """(left id, right id) -> id of the joined token, which is its rank: open addressing in numpy arrays."""

    def __init__(self, left: np.ndarray, right: np.ndarray, joined: np.ndarray):
        self.bits = max(4, int(4 * max(1, len(left)) - 1).bit_length())
        self.keys = np.full(1 << self.bits, -1, np.int64)
        self.joined = np.full(1 << self.bits, NONE, np.int32)
        key = left.astype(np.int64) << 32 | right
        slot, todo = self._slot(key), np.arange(len(key))
        self.most = 1
        while len(todo):
            free = self.keys[slot[todo]] == -1
            first = np.zeros(len(todo), bool)
            first[np.unique(slot[todo], return_index=True)[1]] = True
            put = todo[free & first]
            self.keys[slot[put]], self.joined[slot[put]] = key[put], joined[put]
            todo = todo[~(free & first)]
            slot[todo] = (slot[todo] + 1) & ((1 << self.bits) - 1)
            self.most += 1

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def look_up(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left.astype(np.int64) << 32 | right
        slot = self._slot(key)
        out = np.full(key.shape, NONE, np.int32)
        todo = np.arange(key.size)
        flat, found = key.reshape(-1), out.reshape(-1)
        slot = slot.reshape(-1)
        for _ in range(self.most):
            there = self.keys[slot]
            hit = there == flat[todo]
            found[todo[hit]] = self.joined[slot[hit]]
            more = ~hit & (there != -1)
            todo, slot = todo[more], (slot[more] + 1) & ((1 << self.bits) - 1)
            if not len(todo):
                break
        return out


class Merges:
    """Vocabulary of a rank file (its bytes) and the pairs that can be merged with it."""

    def __init__(self, lines: bytes, pattern: str):
        import regex

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines.splitlines())}
        self.ranks, self.pattern = ranks, regex.compile(pattern)
        self.spelled = {i: token for token, i in ranks.items()}
        self.byte = np.array([ranks.get(bytes([b]), -1) for b in range(256)], np.int32)
        if (self.byte < 0).any():
            raise ValueError("a byte has no rank")
        split = [(ranks[t[:k]], ranks[t[k:]], r) for t, r in ranks.items() for k in range(1, len(t)) if t[:k] in ranks and t[k:] in ranks]
        self.pairs = PairTable(*np.array(split, np.int64).T) if split else PairTable(*np.zeros((3, 0), np.int64))

    def encode(self, pieces: list[bytes]) -> list[list[int]]:
        """The tokens of every piece."""
        out: list[list[int]] = [[self.ranks[p]] if p in self.ranks else [] for p in pieces]
        bucket: dict[int, list[int]] = {}
        for i, p in enumerate(pieces):
            if not out[i] and p:
                bucket.setdefault(0 if len(p) > LONG else max(8, 1 << (len(p) - 1).bit_length()), []).append(i)
        for width, rows in bucket.items():
            if not width:
                for i in rows:
                    out[i] = self._by_heap(pieces[i])
                continue
            per = max(1, (1 << 21) // width)
            for a in range(0, len(rows), per):
                for i, ids in zip(rows[a : a + per], self._by_rounds([pieces[i] for i in rows[a : a + per]], width), strict=True):
                    out[i] = ids
        return out

    def _by_rounds(self, pieces: list[bytes], width: int) -> list[list[int]]:
        size = np.array([len(p) for p in pieces])
        ids = np.full((len(pieces), width), -1, np.int32)
        ids[np.arange(width) < size[:, None]] = self.byte[np.frombuffer(b"".join(pieces), np.uint8)]
        rank = self._ranked(ids)
        done: list[list[int]] = [[]] * len(pieces)
        live = np.arange(len(pieces))
        while len(live):
            at = rank.argmin(axis=1)
            row = np.arange(len(live))
            best = rank[row, at]
            over = best == NONE
            if over.any():
                for k in np.flatnonzero(over):
                    done[live[k]] = ids[k, : size[live[k]]].tolist()
                keep = ~over
                live, ids, rank, at, best = live[keep], ids[keep], rank[keep], at[keep], best[keep]
                row = np.arange(len(live))
                if not len(live):
                    break
            column = np.arange(width)
            source = np.minimum(column + (column > at[:, None]), width - 1)
            ids = np.take_along_axis(ids, source, axis=1)
            ids[:, -1] = -1
            ids[row, at] = best
            rank = np.take_along_axis(rank, source, axis=1)
            rank[:, -1] = NONE
            size[live] -= 1
            left = np.maximum(at - 1, 0)
            rank[row, left] = np.where(at > 0, self._pair(ids[row, left], ids[row, at]), rank[row, left])
            right = np.minimum(at + 1, width - 1)
            rank[row, at] = np.where(at + 1 < width, self._pair(ids[row, at], ids[row, right]), NONE)
        return done

    def _pair(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        return np.where((left < 0) | (right < 0), NONE, self.pairs.look_up(np.maximum(left, 0), np.maximum(right, 0)))

    def _ranked(self, ids: np.ndarray) -> np.ndarray:
        rank = np.full(ids.shape, NONE, np.int32)
        rank[:, :-1] = self._pair(ids[:, :-1], ids[:, 1:])
        return rank

    def _by_heap(self, piece: bytes) -> list[int]:
        ids: list[int] = self.byte[np.frombuffer(piece, np.uint8)].tolist()
        n = len(ids)
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        text = [self.spelled[i] for i in ids]
        heap = [(r, i, text[i + 1]) for i in range(n - 1) if (r := self.ranks.get(text[i] + text[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            r, i, _ = heapq.heappop(heap)
            j = after[i] if text[i] is not None else -1
            if j < 0 or self.ranks.get(text[i] + text[j]) != r:
                continue
            ids[i], text[i], text[j], after[i] = r, text[i] + text[j], None, after[j]
            if after[i] >= 0:
                before[after[i]] = i
            for k in (before[i], i):
                if k >= 0 and after[k] >= 0 and (r := self.ranks.get(text[k] + text[after[k]])) is not None:
                    heapq.heappush(heap, (r, k, text[after[k]]))
        return [i for i, t in zip(ids, text, strict=True) if t is not None]


def _texts(batches: Iterator[pa.RecordBatch], shipped, pattern: str, most_cached: int = 300_000):
    """Blocks of rows with, for each text, its pieces; and the tokens of all pieces seen."""
    merges = Merges(opened(shipped), pattern)
    known: dict[str, tuple] = {}
    for batch in batches:
        for a, b in text_blocks(batch.column("text")):
            part = batch.slice(a, b - a)
            cut = [merges.pattern.findall(t) if t else [] for t in part.column("text").to_pylist()]
            fresh = list({p for pieces in cut for p in pieces}.difference(known))
            if len(known) + len(fresh) > most_cached:
                known = {}
                fresh = list({p for pieces in cut for p in pieces})
            ids = merges.encode([p.encode() for p in fresh])
            known.update((p, (" ".join(map(str, x)), x)) for p, x in zip(fresh, ids, strict=True))
            yield part, cut, known, merges


def _digester(shipped, pattern: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, cut, known, merges in _texts(batches, shipped, pattern):
            size, ids_hash, text_hash = [], [], []
            for pieces in cut:
                own = [known[p] for p in pieces]
                ids = [i for _, x in own for i in x]
                size.append(len(ids))
                ids_hash.append(hashlib.sha256(" ".join([s for s, _ in own]).encode()).hexdigest())
                text_hash.append(hashlib.sha256(b"".join(map(merges.spelled.__getitem__, ids))).hexdigest())
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(size, pa.int64()), pa.array(ids_hash, pa.string()), pa.array(text_hash, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return run


def _coder(shipped, pattern: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, cut, known, merges in _texts(batches, shipped, pattern):
            ids = [[i for p in pieces for i in known[p][1]] for pieces in cut]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(ids, pa.list_(pa.int32())), pa.array([b"".join(map(merges.spelled.__getitem__, x)) for x in ids], pa.binary())], ["doc_id", "ids", "decoded"])

    return run


def _shipped(docs: DataFrame, path: str):
    """The rank file's bytes (about a megabyte), read where the path is known."""
    with open(path, "rb") as lines:
        return ship(docs.sparkSession.sparkContext, lines.read())


def _narrow(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def encoded(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, ids, decoded (bytes made from the ids) for each row of ``docs``.  Null and empty texts have no ids."""
    return _narrow(docs).mapInArrow(_coder(_shipped(docs, path), pattern), CODED)


def code_digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """n_tokens and hashes of the ids and of the bytes decoded from them, for each row of ``docs``."""
    return _narrow(docs).mapInArrow(_digester(_shipped(docs, path), pattern), DIGESTS)
