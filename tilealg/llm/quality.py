"""Quality classifier: heuristic labellers weighed by expectation maximisation, and a hashed linear scorer.

Labellers vote good (1), bad (-1) or nothing (0) on a document.  The counts of vote patterns over all documents (at
most 3 to the number of labellers) are all that estimation needs: a latent class model with a good and a bad class,
votes independent within a class, is fitted by expectation maximisation.  It gives every pattern a posterior.
These posteriors are the soft labels of a logistic scorer, fitted on a bounded sample of documents; the scorer then
judges every whole document.  Its features are the shares of hashed word shapes (runs of upper case, lower case, digits
and each other byte) and of hashed words, and which of the steps in ``STEPS`` each of the labellers' figures exceeds.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.llm.bytewords import ALNUM, BYTE_VALUE, SPACED, Words, mix, opened, segment_sum, ship, text_blocks, windows

LABELLERS = ("long_enough", "plain_words", "symbols", "capitals", "bars", "shouts", "same_lines", "same_passages", "same_words", "word_length")
BUCKETS, WORD_BUCKETS = 1024, 2048
#: Steps of the figures of ``measures``, those that labellers vote by among them.
STEPS = {
    "words": (2.5, 9.5, 19.5, 49.5, 99.5, 499.5, 1999.5),
    "odd_words": (0.05, 0.1, 0.25, 0.5),
    "symbols": (0.05, 0.1, 0.25, 0.5),
    "upper": (0.1, 0.2, 0.4, 0.6),
    "bars": (0.05, 0.1, 0.2, 0.4),
    "shouts": (0.1, 0.2, 0.3, 0.6),
    "same_lines": (0.1, 0.2, 0.3, 0.5, 0.8),
    "same_passages": (0.1, 0.2, 0.3, 0.5, 0.8),
    "same_words": (0.05, 0.1, 0.2, 0.4),
    "length": (1.2, 3, 8, 14),
}
FEATURES = BUCKETS + WORD_BUCKETS + sum(map(len, STEPS.values()))

_SHAPE = np.arange(256)
_SHAPE[0x41:0x5B] = 0x41
_SHAPE[0x61:0x7B] = _SHAPE[0x80:] = 0x61
_SHAPE[0x30:0x3A] = 0x30
_PLAIN = ALNUM | np.isin(np.arange(256), np.frombuffer(b".,;:'\"()-?/", np.uint8))
_SYMBOL = np.isin(np.arange(256), np.frombuffer(b"#*$%&<>|^~_={}[]\\@", np.uint8))


def measures(words: Words) -> dict[str, np.ndarray]:
    """Figures of every text of a block; all are 0 for texts without words."""
    buffer, texts = words.buffer, words.texts
    n = words.counts()
    per_word = lambda x: x / np.maximum(n, 1)
    in_text = lambda flag: segment_sum(flag.astype(np.int64), texts)
    upper, lower = in_text((buffer >= 0x41) & (buffer < 0x5B)), in_text((buffer >= 0x61) & (buffer < 0x7B))
    odd = np.concatenate([[0], np.cumsum(~_PLAIN[buffer] & SPACED[buffer])])
    fives = windows(words.hash, 5)
    repeated, lines, dull = (np.zeros(len(n)) for _ in range(3))
    newline = np.flatnonzero(buffer == 10)
    for i, (a, b) in enumerate(zip(words.offset[:-1].tolist(), words.offset[1:].tolist(), strict=True)):
        if b - a >= 5:
            repeated[i] = 1 - len(np.unique(fives[a : b - 4])) / (b - a - 4)
        low, high = np.searchsorted(newline, texts[i : i + 2])
        if high > low:
            own = [x for x in buffer[texts[i] : texts[i + 1]].tobytes().split(b"\n") if x.strip()]
            lines[i], dull[i] = len(own), len(own) - len(set(own))
    return {
        "words": n,
        "odd_words": per_word(segment_sum((odd[words.end] > odd[words.start]).astype(np.int64), words.offset)),
        "symbols": per_word(in_text(_SYMBOL[buffer])),
        "upper": upper / np.maximum(upper + lower, 1),
        "bars": per_word(in_text(buffer == 0x7C)),
        "shouts": per_word(in_text(buffer == 0x21)),
        "same_lines": dull / np.maximum(lines, 1),
        "same_passages": repeated,
        "same_words": per_word(segment_sum(again(words).astype(np.int64), words.offset)),
        "length": per_word(words.texts[1:] - words.texts[:-1] - 1 - n),
    }


def again(words: Words) -> np.ndarray:
    """Words that equal the one before them in their text."""
    same = np.zeros(len(words.hash), bool)
    same[1:] = words.hash[1:] == words.hash[:-1]
    same[words.offset[:-1][words.counts() > 0]] = False
    return same


def votes(m: dict[str, np.ndarray]) -> np.ndarray:
    """A row of votes for each text."""

    def vote(bad, good=False):
        return np.where(bad, -1, np.where(good, 1, 0))

    return np.stack(
        [
            vote(m["words"] < 3, m["words"] >= 20),
            vote(m["odd_words"] > 0.25),
            vote(m["symbols"] > 0.25),
            vote(m["upper"] > 0.4),
            vote(m["bars"] > 0.2),
            vote(m["shouts"] > 0.3),
            vote(m["same_lines"] > 0.3),
            vote(m["same_passages"] > 0.3),
            vote(m["same_words"] > 0.2),
            vote((m["words"] > 0) & ((m["length"] < 1.2) | (m["length"] > 14))),
        ],
        axis=1,
    ).astype(np.int8)


def shapes(words: Words) -> np.ndarray:
    """The bucket of every word's shape: its byte classes with runs of one class drawn together, and whether it repeats the word before."""
    kind = _SHAPE[words.buffer]
    inside = SPACED[words.buffer]
    fresh = inside & ~(np.append(False, (kind[1:] == kind[:-1]) & inside[:-1]))
    rank = np.concatenate([[0], np.cumsum(fresh)])
    at = rank[:-1] - np.repeat(rank[words.start], np.diff(np.append(words.start, len(kind)))) if len(words.start) and words.start[0] == 0 else None
    if at is None:
        lead = words.start[0] if len(words.start) else len(kind)
        at = np.concatenate([np.zeros(lead, np.int64), rank[lead:-1] - np.repeat(rank[words.start], np.diff(np.append(words.start, len(kind))))])
    value = np.where(fresh, mix(BYTE_VALUE[kind] + at.astype(np.uint64)), np.uint64(0))
    total = np.concatenate([[np.uint64(0)], np.cumsum(value, dtype=np.uint64)])
    return (mix(total[words.end] - total[words.start] + again(words)) % np.uint64(BUCKETS)).astype(np.int64)


def steps(m: dict[str, np.ndarray]) -> np.ndarray:
    """1 for every step that a figure exceeds, else 0; rows of texts."""
    return np.stack([m[name] > edge for name, edges in STEPS.items() for edge in edges], axis=1).astype(np.float32)


def word_buckets(words: Words) -> np.ndarray:
    return (mix(words.hash) % np.uint64(WORD_BUCKETS)).astype(np.int64)


def _features(words: Words, m: dict[str, np.ndarray]) -> np.ndarray:
    """Share of each bucket among a text's words, and the steps; rows of texts."""
    n, owner = len(words.offset) - 1, words.owner()
    shares = [np.bincount(owner * size + at, minlength=n * size).reshape(n, size) / np.maximum(words.counts(), 1)[:, None] for size, at in ((BUCKETS, shapes(words)), (WORD_BUCKETS, word_buckets(words)))]
    return np.hstack([*shares, steps(m)]).astype(np.float32)


def _observer(with_features: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in text_blocks(batch.column("text"), 1 << 20):
                part = batch.slice(a, b - a)
                words = Words(part.column("text"), SPACED)
                m = measures(words)
                own = votes(m)
                pattern = (own.astype(np.int64) + 1) @ 3 ** np.arange(own.shape[1])
                if with_features:
                    rows = [x.tobytes() for x in _features(words, m)]
                    yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(pattern), pa.array(rows, pa.binary())], ["doc_id", "pattern", "features"])
                else:
                    code, n = np.unique(pattern, return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(code), pa.array(n.astype(np.int64))], ["pattern", "n"])

    return run


@dataclass
class Labels:
    """good: share of good documents; given[class, labeller, vote + 1]: chances of votes."""

    good: float
    given: np.ndarray

    def posterior(self, own: np.ndarray) -> np.ndarray:
        log = np.log([1 - self.good, self.good])[:, None] + np.log(self.given)[:, np.arange(own.shape[1])[None, :], own.astype(int) + 1].sum(axis=2)
        log -= log.max(axis=0)
        p = np.exp(log)
        return p[1] / p.sum(axis=0)

    def accuracy(self) -> dict[str, float]:
        """How often each labeller is right when it votes."""
        share = np.array([1 - self.good, self.good])[:, None]
        right = share[0] * self.given[0, :, 0] + share[1] * self.given[1, :, 2]
        said = (share * (self.given[:, :, 0] + self.given[:, :, 2])).sum(axis=0)
        return dict(zip(LABELLERS, (right / said).tolist(), strict=True))


def estimate(own: np.ndarray, n: np.ndarray, rounds: int = 80, least_right: float = 0.9) -> Labels:
    """Expectation maximisation over distinct vote rows ``own`` with counts ``n``.

    It starts from any bad vote counting as bad.  A labeller's bad votes are taken to be right at least
    ``least_right`` of the time: else the largest group of like votes would become a class of its own.
    """
    p = np.where((own < 0).any(axis=1), 0.1, 0.95)
    good, given = 0.5, np.full((2, own.shape[1], 3), 1 / 3)
    for _ in range(rounds):
        weight = np.stack([(1 - p) * n, p * n])
        good = float(np.clip(weight[1].sum() / max(n.sum(), 1), 1e-3, 1 - 1e-3))
        cast = np.stack([((own == v)[None] * weight[:, :, None]).sum(axis=1) for v in (-1, 0, 1)], axis=2)
        moved = np.maximum(cast[1, :, 0] - (1 - least_right) * cast[:, :, 0].sum(axis=0), 0)
        cast[1, :, 0] -= moved
        cast[0, :, 0] += moved
        given = cast + 0.5
        given /= given.sum(axis=2, keepdims=True)
        p = Labels(good, given).posterior(own)
    return Labels(good, given)


def fit_linear(x: np.ndarray, y: np.ndarray, rounds: int = 400, rate: float = 2.0, shrink: float = 1e-4) -> np.ndarray:
    """Logistic weights for soft labels y by gradient steps with per-weight scaling; the last weight is the constant."""
    x = np.hstack([np.sqrt(x), np.ones((len(x), 1), np.float32)])
    y = y.astype(np.float32)
    w, seen = np.zeros(x.shape[1], np.float32), np.full(x.shape[1], 1e-8, np.float32)
    for _ in range(rounds):
        slope = x.T @ (1 / (1 + np.exp(-np.clip(x @ w, -30, 30))) - y) / max(1, len(x)) + np.float32(shrink) * w
        seen += slope**2
        w -= np.float32(rate) * slope / np.sqrt(seen)
    return w


def fit(docs: DataFrame, most_docs: int = 3000) -> tuple[Labels, np.ndarray]:
    """Labeller accuracies from all documents; scorer weights from the ``most_docs`` with the smallest id hashes."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    found = docs.mapInArrow(_observer(False), "pattern long, n long").groupBy("pattern").agg(F.sum("n").alias("n")).orderBy("pattern").toPandas()
    own = _unpacked(found["pattern"].to_numpy(np.int64))
    n = found["n"].to_numpy(np.int64)
    labels = estimate(own, n)
    total = max(1, int(n.sum()))
    near = docs.where(F.expr(f"{total} <= {4 * most_docs} or (xxhash64(doc_id) / 1.8446744073709552e19D + 0.5D) * {total} <= {2 * most_docs}"))
    sample = near.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_docs).repartition(max(1, most_docs // 500)).mapInArrow(_observer(True), "doc_id long, pattern long, features binary").orderBy("doc_id").toPandas()
    if not len(sample):
        return labels, np.zeros(FEATURES + 1)
    x = np.stack([np.frombuffer(f, np.float32) for f in sample["features"]])
    return labels, fit_linear(x, labels.posterior(_unpacked(sample["pattern"].to_numpy(np.int64))))


def _unpacked(pattern: np.ndarray) -> np.ndarray:
    return (pattern[:, None] // 3 ** np.arange(len(LABELLERS)) % 3 - 1).astype(np.int8)


JUDGED = "doc_id long, n_words long, bad_votes int, posterior double, score double, kept boolean"


def _verdicts(column: pa.Array, labels: Labels, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words, votes and scores of texts."""
    words = Words(column, SPACED)
    n = words.counts()
    m = measures(words)
    sums = steps(m) @ weights[BUCKETS + WORD_BUCKETS : -1]
    for first, buckets, at in ((0, BUCKETS, shapes(words)), (BUCKETS, WORD_BUCKETS, word_buckets(words))):
        code, size = np.unique(words.owner() * buckets + at, return_counts=True)
        owner = code // buckets
        sums = sums + np.bincount(owner, np.sqrt(size / n[owner]) * weights[first + code % buckets], len(n))
    return n, votes(m), np.where(n > 0, 1 / (1 + np.exp(-np.clip(sums + weights[-1], -30, 30))), 0.0)


def _judge(shipped, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labels, weights = opened(shipped)
        for batch in batches:
            for a, b in text_blocks(batch.column("text"), 2 << 20):
                part = batch.slice(a, b - a)
                n, own, score = _verdicts(part.column("text"), labels, weights)
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(n), pa.array((own < 0).sum(axis=1).astype(np.int32)), pa.array(labels.posterior(own)), pa.array(score), pa.array(score >= least)],
                    ["doc_id", "n_words", "bad_votes", "posterior", "score", "kept"],
                )

    return run


def _sift(shipped, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labels, weights = opened(shipped)
        for batch in batches:
            text = batch.column("text").cast(pa.string())
            for a, b in text_blocks(text, 2 << 20):
                score = _verdicts(text.slice(a, b - a), labels, weights)[2]
                yield batch.slice(a, b - a).filter(pa.array(score >= least))

    return run


def _scorer(docs: DataFrame, most_docs: int):
    return ship(docs.sparkSession.sparkContext, fit(docs, most_docs))


def judged(docs: DataFrame, least: float = 0.5, most_docs: int = 3000) -> DataFrame:
    """n_words, bad_votes, posterior of the votes, the scorer's score and kept, for each row of ``docs`` (doc_id, text).

    Texts without words (null ones too) score 0.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(_judge(_scorer(docs, most_docs), least), JUDGED)


def good_documents(docs: DataFrame, least: float = 0.5, most_docs: int = 3000) -> DataFrame:
    """``docs`` without the rows that the scorer rejects.  Keeps all columns; no shuffle of texts."""
    return docs.mapInArrow(_sift(_scorer(docs, most_docs), least), docs.schema)
