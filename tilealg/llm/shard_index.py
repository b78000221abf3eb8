"""Benchmark decontamination with an FM-index per shard of documents.

The word sequences of a shard (a bounded block of whole texts) become one string of word numbers.  Words that no
test item holds, and words in no pair of neighbours that an item holds, cannot be part of an occurrence: they are
left out, as borders between runs.  Over the rest a suffix array is sorted, its Burrows-Wheeler transform is kept
in a wavelet matrix with prefix counts, and every ``STEP``-th position of a run is sampled.  All test windows are
then searched backwards at once, their occurrences located by walking to sampled positions, and the spans merged.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.llm.bytewords import ALNUM, Words, opened, segment_sum, ship, text_blocks

STEP, SHARD = 8, 6 << 20
FOUND = "doc_id long, n_words long, n_hit long, n_items long, item_ids array<string>, span_start array<int>, span_end array<int>"


@dataclass
class Phrases:
    """Distinct windows of test items as rows of word numbers (1, 2, ...), padded with 0 on the left."""

    vocabulary: np.ndarray  # sorted word hashes; number = place + 1
    pairs: np.ndarray  # sorted codes of neighbouring words in items
    rows: np.ndarray
    size: np.ndarray
    item_at: np.ndarray  # window w is of the items item_of[item_at[w]:item_at[w + 1]]
    item_of: np.ndarray  # places in names
    names: list[str]
    shortest: int

    @classmethod
    def of(cls, items: list[tuple[str, str | None]], width: int) -> Phrases:
        words = Words(pa.array([t for _, t in items], pa.string()), ALNUM)
        vocabulary = np.unique(words.hash)
        number = np.searchsorted(vocabulary, words.hash) + 1
        names = sorted({i for i, _ in items})
        place = {x: k for k, x in enumerate(names)}
        seen: dict[tuple, set[int]] = {}
        pairs = [np.zeros(0, np.int64)]
        for (item, _), a, b in zip(items, words.offset[:-1].tolist(), words.offset[1:].tolist(), strict=True):
            own = number[a:b]
            pairs.append(own[:-1] * (len(vocabulary) + 1) + own[1:])
            for i in range(max(1, b - a - width + 1) if b > a else 0):
                seen.setdefault(tuple(own[i : i + width].tolist()), set()).add(place[item])
        rows = np.zeros((len(seen), width), np.int32)
        size = np.array([len(k) for k in seen], np.int64)
        for r, k in enumerate(seen):
            rows[r, width - len(k) :] = k
        item_at = np.concatenate([[0], np.cumsum([len(v) for v in seen.values()])]).astype(np.int64)
        item_of = np.fromiter((i for v in seen.values() for i in sorted(v)), np.int32, int(item_at[-1]))
        return cls(vocabulary, np.unique(np.concatenate(pairs)), rows, size, item_at, item_of, names, int(size.min()) if len(size) else 0)


class Wavelet:
    """Ranks over a string of numbers: one bit vector with prefix counts per binary digit."""

    def __init__(self, symbols: np.ndarray, digits: int):
        self.levels, self.zeros = [], []
        for d in reversed(range(digits)):
            bit = (symbols >> d) & 1
            self.levels.append((d, np.concatenate([[0], np.cumsum(bit)]).astype(np.int32)))
            self.zeros.append(len(bit) - int(bit.sum()))
            symbols = np.concatenate([symbols[bit == 0], symbols[bit == 1]])

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Occurrences of each symbol before each place."""
        low = np.zeros_like(at)
        for (d, ones), zeros in zip(self.levels, self.zeros, strict=True):
            bit = ((symbol >> d) & 1).astype(bool)
            low = np.where(bit, zeros + ones[low], low - ones[low])
            at = np.where(bit, zeros + ones[at], at - ones[at])
        return at - low


class ShardIndex:
    """FM-index of runs of numbers; ``text`` has a 0 before every run and one at the end."""

    def __init__(self, text: np.ndarray, top: int):
        n = len(text)
        border = text == 0
        self.text = text
        order = self._sorted(text, border)
        self.order_size = n
        before = text[order - 1]  # text[-1] is a border: the first suffix has one before it
        self.total = np.searchsorted(text[order], np.arange(top + 2))
        self.bwt = before
        self.wavelet = Wavelet(before.astype(np.int64), max(1, int(top).bit_length()))
        run_start = np.maximum.accumulate(np.where(border, np.arange(n), 0)) + 1
        within = np.arange(n) - run_start
        self.sampled = np.where(border[order] | (within[order] % STEP == 0), order, -1)

    @staticmethod
    def _sorted(text: np.ndarray, border: np.ndarray) -> np.ndarray:
        """All suffixes in order, by doubling.  Each border sorts by its place, so no comparison passes one."""
        n = len(text)
        key = np.where(border, np.cumsum(border) - 1, text + int(border.sum()))
        order = np.argsort(key, kind="stable")
        ranked = np.cumsum(np.diff(key[order], prepend=key[order[:1]]) > 0)
        rank = np.empty(n, np.int64)
        rank[order] = ranked
        reach = 1
        while n and ranked[-1] < n - 1:
            after = np.zeros(n, np.int64)
            after[:-reach] = rank[reach:] + 1
            both = rank * (n + 1) + after
            order = np.argsort(both, kind="stable")
            ranked = np.cumsum(np.diff(both[order], prepend=both[order[:1]]) > 0)
            rank[order] = ranked
            reach *= 2
        return order

    def search(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ranges of suffixes that start with each row (rows are padded with 0 on the left)."""
        low, high = np.zeros(len(rows), np.int64), np.full(len(rows), self.order_size, np.int64)
        for k in reversed(range(rows.shape[1])):
            live = np.flatnonzero((rows[:, k] > 0) & (low < high))
            if len(live):
                symbol = rows[live, k].astype(np.int64)
                low[live] = self.total[symbol] + self.wavelet.rank(symbol, low[live])
                high[live] = self.total[symbol] + self.wavelet.rank(symbol, high[live])
        return low, high

    def locate(self, at: np.ndarray) -> np.ndarray:
        """Text positions of suffix ranks: step back to a sampled position.  The start of a run is sampled."""
        out, steps = np.full(len(at), -1), 0
        todo, row = np.arange(len(at)), at.copy()
        while len(todo):
            known = self.sampled[row] >= 0
            out[todo[known]] = self.sampled[row[known]] + steps
            todo, row = todo[~known], row[~known]
            symbol = self.bwt[row].astype(np.int64)
            row = self.total[symbol] + self.wavelet.rank(symbol, row)
            steps += 1
        return out


def _occurrences(words: Words, phrases: Phrases) -> tuple[np.ndarray, np.ndarray]:
    """Word places and window numbers of all occurrences in a block of texts."""
    none = np.zeros(0, np.int64), np.zeros(0, np.int64)
    if not len(phrases.size) or not len(words.hash):
        return none
    near = np.minimum(np.searchsorted(phrases.vocabulary, words.hash), len(phrases.vocabulary) - 1)
    number = np.where(phrases.vocabulary[near] == words.hash, near + 1, 0)
    owner = words.owner()
    keep = number > 0
    if phrases.shortest > 1:
        same = (owner[1:] == owner[:-1]) & keep[1:] & keep[:-1]
        code = number[:-1] * (len(phrases.vocabulary) + 1) + number[1:]
        spot = np.minimum(np.searchsorted(phrases.pairs, code[same]), len(phrases.pairs) - 1)
        follows = np.zeros(len(number), bool)
        follows[1:][same] = phrases.pairs[spot] == code[same]
        keep = follows | np.append(follows[1:], False)
        starts = np.flatnonzero(keep & ~follows)
    else:
        starts = np.flatnonzero(keep & np.append(True, (owner[1:] != owner[:-1]) | ~keep[:-1]))
        follows = keep.copy()
        follows[starts] = False
    # Runs too short for the shortest window can't hold one.
    run = np.cumsum(np.isin(np.arange(len(keep)), starts, assume_unique=True)) - 1
    kept = np.flatnonzero(keep)
    if not len(kept):
        return none
    long = np.bincount(run[kept], minlength=len(starts)) >= phrases.shortest
    kept = kept[long[run[kept]]]
    if not len(kept):
        return none
    new = np.append(True, np.diff(run[kept]) > 0)
    place = np.arange(len(kept)) + np.cumsum(new)
    text = np.zeros(len(kept) + int(new.sum()) + 1, np.int64)
    origin = np.full(len(text), -1)
    text[place], origin[place] = number[kept], kept
    index = ShardIndex(text, len(phrases.vocabulary))
    low, high = index.search(phrases.rows)
    hits = np.maximum(high - low, 0)
    window = np.repeat(np.arange(len(hits)), hits)
    at = np.arange(int(hits.sum())) - np.repeat(np.cumsum(hits) - hits, hits) + np.repeat(low, hits)
    return origin[index.locate(at)], window


class Blocks:
    """Blocks of items in a worker: one stays open; of several only one at a time is, and its bytes are let go."""

    def __init__(self, shipped: list):
        self.shipped, self.only = shipped, opened(shipped[0]) if len(shipped) == 1 else None

    def __iter__(self) -> Iterator[Phrases]:
        if self.only is not None:
            yield self.only
            return
        for x in self.shipped:
            yield opened(x)
            if hasattr(x, "_path") and hasattr(x, "_value"):
                del x._value  # read again from the worker's file when it is next asked for


def _marks(column: pa.Array, opens: Blocks) -> tuple[Words, np.ndarray, list[set[str]]]:
    """The words of texts, which of them are hit, and the items found in each text."""
    words = Words(column, ALNUM)
    n = len(words.hash)
    owner, edges = words.owner(), np.zeros(n + 1, np.int64)
    names: list[set[str]] = [set() for _ in range(len(words.offset) - 1)]
    for phrases in opens:
        place, window = _occurrences(words, phrases)
        np.add.at(edges, place, 1)
        np.add.at(edges, place + phrases.size[window], -1)
        for code in np.unique(owner[place] * max(1, len(phrases.size)) + window).tolist():
            doc, w = divmod(code, len(phrases.size))
            names[doc].update(phrases.names[i] for i in phrases.item_of[phrases.item_at[w] : phrases.item_at[w + 1]])
    return words, np.cumsum(edges[:n]) > 0, names


def _scanner(blocks: list):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        opens = Blocks(blocks)
        for batch in batches:
            for a, b in text_blocks(batch.column("text"), SHARD):
                part = batch.slice(a, b - a)
                words, hit, names = _marks(part.column("text"), opens)
                owner = words.owner()
                # Spans end where the text does, though hits of neighbouring texts may touch.
                fresh = np.append(True, owner[1:] != owner[:-1])[: len(hit)]
                starts = np.flatnonzero(hit & (fresh | ~np.append(False, hit[:-1])[: len(hit)]))
                ends = np.flatnonzero(hit & (np.append(fresh[1:], True)[: len(hit)] | ~np.append(hit[1:], False)[: len(hit)])) + 1
                span = np.searchsorted(starts, words.offset).astype(np.int32)
                base = words.offset[owner[starts]]
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column("doc_id"),
                        pa.array(words.counts()),
                        pa.array(segment_sum(hit.astype(np.int64), words.offset)),
                        pa.array([len(x) for x in names], pa.int64()),
                        pa.array([sorted(x) for x in names], pa.list_(pa.string())),
                        pa.ListArray.from_arrays(pa.array(span), pa.array((starts - base).astype(np.int32))),
                        pa.ListArray.from_arrays(pa.array(span), pa.array((ends - base).astype(np.int32))),
                    ],
                    ["doc_id", "n_words", "n_hit", "n_items", "item_ids", "span_start", "span_end"],
                )

    return run


def _sift(blocks: list, least_share: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        opens = Blocks(blocks)
        for batch in batches:
            text = batch.column("text").cast(pa.string())
            for a, b in text_blocks(text, SHARD):
                words, hit, _ = _marks(text.slice(a, b - a), opens)
                n_hit = segment_sum(hit.astype(np.int64), words.offset)
                yield batch.slice(a, b - a).filter(pa.array((n_hit == 0) | (least_share * n_hit < words.counts())))

    return run


def _shipped(items: DataFrame, width: int, block_bytes: int, most_bytes: int) -> list:
    context = items.sparkSession.sparkContext
    items = items.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text"))
    total = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if total > most_bytes:
        raise ValueError(f"test items have {total} bytes; at most {most_bytes} are shipped: pass them in parts")
    blocks, part, filled = [], [], 0
    for item_id, text in items.toLocalIterator():
        part.append((item_id or "", text))
        filled += len(text or "")
        if filled > block_bytes:
            blocks.append(ship(context, Phrases.of(part, width)))
            part, filled = [], 0
    if part:
        blocks.append(ship(context, Phrases.of(part, width)))
    return blocks


def contaminated_spans(docs: DataFrame, items: DataFrame, width: int = 13, block_bytes: int = 4 << 20, most_bytes: int = 256 << 20) -> DataFrame:
    """For each row of ``docs`` (doc_id, text): n_words, n_hit, n_items, item_ids and merged spans of hit words.

    ``items`` has item_id and text.  A window is ``width`` words in a row of an item, or the whole item if it has
    fewer; items without words have none.  Null texts have no words.  Items are test sets, so they are shipped
    to the workers, in blocks of ``block_bytes``; over ``most_bytes`` in all is an error, before anything is sent.
    A worker holds one block at a time (about 100 MB for 4 MB of items, whose windows take 52 bytes each).
    Repeated item ids count as one item; a null id counts as the empty string.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(_scanner(_shipped(items, width, block_bytes, most_bytes)), FOUND)


def decontaminated(docs: DataFrame, items: DataFrame, width: int = 13, least_share: int = 20, block_bytes: int = 4 << 20, most_bytes: int = 256 << 20) -> DataFrame:
    """``docs`` without contaminated rows: n_hit > 0 and ``least_share`` * n_hit >= n_words.

    Keeps all columns; no shuffle of texts.
    """
    return docs.mapInArrow(_sift(_shipped(items, width, block_bytes, most_bytes), least_share), docs.schema)
