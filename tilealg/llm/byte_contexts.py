"""Language identification by partial matching over byte contexts.

Each language has counts of bytes after contexts of 0 to ``ORDER`` bytes, learned from a bounded sample of labelled
documents and then frozen.  A byte's probability follows the escape rule of method C: seen after the longest context
c / (n + t), else t / (n + t) times that after the next shorter one; n counts all bytes after the context and t the
distinct ones; below order 0 all 256 bytes are alike.  The code length of a text is the exact sum of -log2 of these.
As statistics are frozen, log probabilities are worked out once for each context and byte seen in any language:
texts then only look up a row per byte.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.llm.bytewords import LOWER, opened, ship, text_blocks

ORDER = 3
GUESSED = "doc_id long, held_out boolean, lang_pred string, score double, bits_per_byte double"


def _grams(buffer: np.ndarray, order: int) -> np.ndarray:
    """Code of each byte with the ``order`` bytes before it; the buffer starts with ``ORDER`` more bytes."""
    code = np.zeros(len(buffer) - ORDER, np.int64)
    for k in range(order, -1, -1):
        code = code << 8 | buffer[ORDER - k : len(buffer) - k]
    return code


def _buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased bytes with ``ORDER`` spaces before and behind every text, so that no context holds another text's bytes;
    and for each text the places of its first byte and behind its closing space, counted without the first spaces."""
    texts, gap = [x or b"" for x in column.cast(pa.binary()).to_pylist()], b" " * ORDER
    size = np.array([len(x) for x in texts], np.int64)
    start = np.cumsum(size + ORDER) - size - ORDER
    return LOWER[np.frombuffer(gap + b"".join(y for x in texts for y in (x, gap)), np.uint8)], np.stack([start, start + size + 1], axis=1)


def _inside(buffer: np.ndarray, spans: np.ndarray) -> np.ndarray:
    """Codes of the bytes of texts and their closing spaces."""
    edge = np.zeros(len(buffer) - ORDER + 1, np.int64)
    np.add.at(edge, spans[:, 0], 1)
    np.add.at(edge, spans[:, 1], -1)
    return _grams(buffer, ORDER)[np.cumsum(edge[:-1]) > 0]


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        langs = np.array(batch.column("lang").to_pylist(), object)
        for lang in sorted(set(langs)):
            for a, b in text_blocks(own := batch.column("text").filter(pa.array(langs == lang)), 8 << 20):
                code, n = np.unique(_inside(*_buffer(own.slice(a, b - a))), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(code)), pa.array(code), pa.array(n)], ["lang", "code", "n"])


@dataclass
class Contexts:
    """Frozen tables.  For order k: codes seen in any language, their rows of log2 probabilities, and escapes.

    slots: places of order-``ORDER`` codes in an open hash table; the rare rest goes down the orders.
    """

    langs: list[str]
    codes: list[np.ndarray]
    logs: list[np.ndarray]
    contexts: list[np.ndarray]
    escapes: list[np.ndarray]
    slots: np.ndarray

    @classmethod
    def of(cls, langs: list[str], tables: list[tuple[np.ndarray, np.ndarray]]) -> Contexts:
        """tables: for each language the codes of order ``ORDER`` and their counts."""
        codes, logs, contexts, escapes = [], [], [], []
        for k in range(ORDER + 1):
            by = [_reduced(code & ((1 << 8 * (k + 1)) - 1), n) for code, n in tables]
            seen = np.unique(np.concatenate([c for c, _ in by]))
            above = np.unique(seen >> 8)
            lower = np.full((len(seen), len(langs)), -8.0) if k == 0 else _descend(codes, logs, contexts, escapes, seen & ((1 << 8 * k) - 1), k - 1)
            log, esc = np.zeros((len(seen), len(langs))), np.zeros((len(above), len(langs)))
            for j, (c, n) in enumerate(by):
                ctx = np.searchsorted(above, c >> 8)
                total, kinds = np.bincount(ctx, n, len(above)), np.bincount(ctx, minlength=len(above))
                esc[:, j] = np.where(kinds > 0, np.log2(np.maximum(kinds, 1) / np.maximum(total + kinds, 1)), 0.0)
                log[:, j] = lower[:, j] + esc[np.searchsorted(above, seen >> 8), j]
                log[np.searchsorted(seen, c), j] = np.log2(n / (total + kinds)[ctx])
            codes.append(seen)
            logs.append(log)
            contexts.append(above)
            escapes.append(esc)
        return cls(langs, codes, logs, contexts, escapes, _slotted(codes[ORDER]))

    def rows(self, buffer: np.ndarray) -> np.ndarray:
        """log2 probabilities [byte, language]."""
        code = _grams(buffer, ORDER)
        at = _looked_up(self.slots, self.codes[ORDER], code)
        known = at >= 0
        out = self.logs[ORDER][np.maximum(at, 0)]
        miss = np.flatnonzero(~known)
        if len(miss):
            out[miss] = _descend(self.codes, self.logs, self.contexts, self.escapes, code[miss], ORDER)
        return out


def _reduced(code: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    seen, at = np.unique(code, return_inverse=True)
    return seen, np.bincount(at, n, len(seen))


def _descend(codes, logs, contexts, escapes, code: np.ndarray, k: int) -> np.ndarray:
    """Rows for codes of order k: their own, or the escape of their context and the rows of the next order."""
    if k < 0:
        return np.full((len(code), logs[0].shape[1]), -8.0)
    at = np.minimum(np.searchsorted(codes[k], code), len(codes[k]) - 1)
    out = logs[k][at]
    miss = np.flatnonzero(codes[k][at] != code)
    if len(miss):
        context = code[miss] >> 8
        up = np.minimum(np.searchsorted(contexts[k], context), len(contexts[k]) - 1)
        here = np.where((contexts[k][up] == context)[:, None], escapes[k][up], 0.0)
        out[miss] = here + _descend(codes, logs, contexts, escapes, code[miss] & ((1 << 8 * k) - 1), k - 1)
    return out


def _slotted(codes: np.ndarray) -> np.ndarray:
    bits = max(4, int(4 * max(1, len(codes)) - 1).bit_length())
    slots = np.full(1 << bits, -1, np.int32)
    todo, slot = np.arange(len(codes)), _slot(codes, bits)
    while len(todo):
        first = np.zeros(len(todo), bool)
        first[np.unique(slot, return_index=True)[1]] = True
        put = first & (slots[slot] < 0)
        slots[slot[put]] = todo[put]
        todo, slot = todo[~put], (slot[~put] + 1) & ((1 << bits) - 1)
    return slots


def _slot(code: np.ndarray, bits: int) -> np.ndarray:
    return ((code.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - bits)).astype(np.int64)


def _looked_up(slots: np.ndarray, codes: np.ndarray, code: np.ndarray) -> np.ndarray:
    bits = len(slots).bit_length() - 1
    slot = _slot(code, bits)
    place = slots[slot]
    out = np.where((place >= 0) & (codes[place] == code), place, -1)
    todo = np.flatnonzero((out < 0) & (place >= 0))
    slot = slot[todo]
    while len(todo):
        slot = (slot + 1) & ((1 << bits) - 1)
        place = slots[slot]
        hit = (place >= 0) & (codes[place] == code[todo])
        out[todo[hit]] = place[hit]
        more = ~hit & (place >= 0)
        todo, slot = todo[more], slot[more]
    return out


def fit(train: DataFrame, most_docs: int = 4000) -> Contexts | None:
    """Learns from the ``most_docs`` documents of each language with the smallest id hashes (whole texts).

    ``train`` has doc_id, text, lang; null labels and texts are left out.  None if nothing is left.
    """
    from pyspark.sql import Window

    train = train.where("lang is not null and text is not null").withColumn("place", F.xxhash64("doc_id"))
    # The bound on each language's hash keeps the rest out before rows are ranked.
    share = train.groupBy("lang").agg(F.count(F.lit(1)).alias("n"))
    near = train.join(F.broadcast(share), "lang").where(F.expr(f"n <= {4 * most_docs} or (place / 1.8446744073709552e19D + 0.5D) * n <= {2 * most_docs}"))
    ranked = near.withColumn("rank", F.row_number().over(Window.partitionBy("lang").orderBy("place", "doc_id"))).where(F.col("rank") <= most_docs)
    found = ranked.select("lang", "text").mapInArrow(_counted, "lang string, code long, n long").groupBy("lang", "code").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(found["lang"].unique())
    if not langs:
        return None
    groups = {k: g for k, g in found.groupby("lang")}
    return Contexts.of(langs, [(groups[x]["code"].to_numpy(np.int64), groups[x]["n"].to_numpy(np.float64)) for x in langs])


def _guesser(shipped):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model: Contexts | None = opened(shipped)
        for batch in batches:
            for a, b in text_blocks(batch.column("text"), 1 << 20):
                part = batch.slice(a, b - a)
                column = part.column("text")
                buffer, spans = _buffer(column)
                lettered = [bool(t) and any(map(str.isalpha, t)) for t in column.to_pylist()]
                if model is None:
                    best, score, bits = ["und"] * len(lettered), [0.0] * len(lettered), [0.0] * len(lettered)
                else:
                    total = np.add.reduceat(model.rows(buffer), spans.reshape(-1), axis=0)[::2]
                    top = total.argmax(axis=1)
                    gap = np.exp2(np.maximum(total - total.max(axis=1, keepdims=True), -1000.0))
                    best = [model.langs[t] if ok else "und" for t, ok in zip(top, lettered, strict=True)]
                    score = np.where(lettered, 1 / gap.sum(axis=1), 0.0)
                    bits = -total.max(axis=1) / (spans[:, 1] - spans[:, 0])
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(best, pa.string()), pa.array(score, pa.float64()), pa.array(bits, pa.float64())], ["doc_id", "held_out", "lang_pred", "score", "bits_per_byte"])

    return run


def guess(docs: DataFrame, model: Contexts | None) -> DataFrame:
    """lang_pred, score (posterior under equal priors) and bits per byte for each row of ``docs`` (doc_id, held_out, text).

    ``und`` for null texts, texts without letters, and if nothing was learned.
    """
    shipped = ship(docs.sparkSession.sparkContext, model)
    return docs.select("doc_id", "held_out", "text").mapInArrow(_guesser(shipped), GUESSED)


def identified(docs: DataFrame) -> DataFrame:
    """Learns from labelled documents with crc32(doc_id) mod 5 other than 0 and predicts all."""
    held = F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(5)) == 0
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"), held.alias("held_out"))
    return guess(docs, fit(docs.where("not held_out")))
