"""Language-model scores from a hierarchical Pitman-Yor process with sampled seating.

Restaurants.  Every token that precedes another in a training text is a context with a restaurant of its own (a
text's first word follows the end token); its dishes are all tokens seen behind it.  All context restaurants share one
parent, whose customers are their tables and whose base is uniform over the known tokens and one unknown.  A context
that was never seen gives what the parent gives.

Seating.  Gibbs sampling in terms of the tables of a dish: given the tables of all others, a dish with c customers has
t tables with odds S(c, t) * prod_{i<t} (strength + discount * (others + i)) * p^t, S the generalised Stirling numbers
and p the parent's probability.  Dishes are seated one after the other with running totals; a restaurant of more than
``STEPS`` dishes of like size seats them in that many groups, whose members share the total before the group.  Dishes of
one customer have one table.  For dishes of more than ``EXACT`` customers S is worked out by its saddle point, or the
first terms of its alternating sum up to ``FEW`` tables.
Rounds alternate between levels: the parent is sampled given the tables of the contexts (words with equal counts are
exchangeable there, so its state is the histogram of counts), then all contexts given the parent.  Predictive
probabilities are averages over the sweeps of the last round after ``burn``.

Plan.  A *block* is about ``BLOCK`` bytes of whole texts; a *bucket* holds the restaurants of the contexts that hash to
it, contexts with a large share of all tokens spread over several.  One exchange brings the distinct pairs of every
block, with their counts, to the buckets, and the blocks' token numbers to where they are scored; each round reads it
again.  Tables of a word under all contexts are summed where the word has its home: buckets send each other packed rows of
words, and get totals back in the same order.  Buckets then answer every block with what it asked for.  All of this grows with the corpus; the driver only holds contexts above a
share of 2^-16 of all tokens (so at most 2^16), and the histogram has at most sqrt(2 * tables) rows.
"""

from __future__ import annotations

import math
import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.llm.bytewords import ODD, SPACED, Words, mix, opened, segment_sum, ship, text_blocks

#: Stands for the end of a text; no word hash is likelier to equal it than any other.
END = np.uint64(0x5EED_0F_7E57_E4)
#: Marks the key under which a spread context's tables are summed.
SPREAD = np.uint64(0x7AB1_E5)
#: Words go by 56 bits of their hash, which travel as 7 bytes.
BITS = np.uint64((1 << 56) - 1)
BLOCK, BUCKET = 10 << 20, 12 << 20
EXACT, FEW, STEPS, WIDTHS = 1024, 32, 24, (4, 8, 16, 64, 256, 1024)
ASKED = "pid int, block long, payload boolean, data binary"
TOLD = "kid int, pid int, data binary"
SCORED = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _tokens(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of every text, each followed by END, and offsets."""
    words = Words(column, SPACED)
    n = len(words.offset) - 1
    out = np.full(len(words.hash) + n, END, np.uint64)
    out[np.arange(len(words.hash)) + words.owner()] = words.hash & BITS
    return out, words.offset + np.arange(n + 1)


def _codes(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values in order, and the place of each value among them; by hashing, as most values repeat."""
    coded = pa.array(values).dictionary_encode()
    seen = coded.dictionary.to_numpy()
    order = np.argsort(seen)
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    return seen[order], place[coded.indices.to_numpy()]


def _hash_bytes(words: np.ndarray) -> bytes:
    return np.ascontiguousarray(np.ascontiguousarray(words, np.uint64).view(np.uint8).reshape(-1, 8)[:, :7]).tobytes()


def _hashes(data: bytes, n: int, at: int = 0) -> np.ndarray:
    out = np.zeros((n, 8), np.uint8)
    out[:, :7] = np.frombuffer(data, np.uint8, 7 * n, at).reshape(n, 7)
    return out.reshape(-1).view(np.uint64)


# --- Seating --------------------------------------------------------------------------------------------------

_STIRLING: dict[float, np.ndarray] = {}


def log_stirling(discount: float) -> np.ndarray:
    """Row c, column t - 1: log S(c, t) for up to EXACT customers."""
    if discount not in _STIRLING:
        out = np.full((EXACT + 1, EXACT), -np.inf)
        out[1, 0] = 0.0
        for c in range(1, EXACT):
            t = np.arange(1, c + 1)
            out[c + 1, :c] = out[c, :c] + np.log(c - discount * t)
            out[c + 1, 1 : c + 1] = np.logaddexp(out[c + 1, 1 : c + 1], out[c, :c])
        _STIRLING[discount] = out
    return _STIRLING[discount]


def table_odds(c: np.ndarray, others: np.ndarray, p: np.ndarray, discount: float, strength: float, width: int) -> np.ndarray:
    """Cumulated odds of 1, 2, ... ``width`` tables for dishes of c customers (at most width), a row each."""
    step = np.arange(width)
    log = log_stirling(discount)[c, :width] + np.cumsum(np.log(strength + discount * (others[:, None] + step)), axis=1) + np.log(p)[:, None] * (step + 1)
    log -= log.max(axis=1, keepdims=True)
    return np.cumsum(np.exp(log), axis=1)


def _saddle(c: np.ndarray, t: np.ndarray, discount: float, halvings: int = 30) -> np.ndarray:
    """y with discount * (1 - e^-y) * e^(y (1 - discount)) / (1 - e^-(discount y)) = c / t, by halving."""
    low, high = np.zeros(np.broadcast(c, t).shape), (np.log(c / t) + 5 - np.log(discount)) / (1 - discount)
    for _ in range(halvings):
        y = (low + high) / 2
        over = np.log(-np.expm1(-y)) + y * (1 - discount) - np.log(-np.expm1(-discount * y)) > np.log(c / t / discount)
        low, high = np.where(over, low, y), np.where(over, y, high)
    return (low + high) / 2


def _log_factorial(n: np.ndarray) -> np.ndarray:
    return n * np.log(n) - n + 0.5 * np.log(2 * np.pi * n) + 1 / (12 * n) - 1 / (360 * n**3) + 1 / (1260 * n**5)


def log_stirling_saddle(c: np.ndarray, t: np.ndarray, discount: float) -> np.ndarray:
    """log S(c, t), less log c!, by the saddle point of S's generating function ((1 - (1 - x)^discount) / discount)^t / t!."""
    y = _saddle(c, t, discount)
    bend = 1 / np.expm1(y) + 1 - discount - discount / np.expm1(discount * y)
    return -_log_factorial(t) + t * np.log(-np.expm1(-discount * y) / discount) - (c + 0.5) * np.log(-np.expm1(-y)) - 0.5 * (np.log(2 * np.pi * c * np.maximum(bend, 1e-300)) + y)


def log_stirling_few(c: np.ndarray, t: np.ndarray, discount: float, terms: int = 12) -> np.ndarray:
    """log S(c, t), less log c!, for few tables of many customers: the first terms of its alternating sum."""
    total, choose = np.zeros(np.broadcast(c, t).shape), np.ones(np.broadcast(c, t).shape)
    for k in range(1, terms + 1):
        choose = choose * np.maximum(t - k + 1, 0) / k
        whole = abs(k * discount - round(k * discount)) < 1e-12
        total += 0.0 if whole else (-1) ** k * choose / math.gamma(-k * discount) * np.exp(_log_gamma(c - k * discount) - _log_gamma(c - discount))
    return np.log(np.maximum(total, 1e-300)) + _log_gamma(c - discount) - _log_gamma(c + 1) - t * np.log(discount) - _log_factorial(t)


def drawn_large(c: np.ndarray, others: np.ndarray, p: np.ndarray, discount: float, strength: float, rng: np.random.Generator, points: int = 128) -> np.ndarray:
    """Tables of dishes with many customers, from the same odds with S by its saddle point.

    Odds are taken at up to ``points`` places within seven deviations of the likeliest number.
    """
    if not len(c):
        return np.zeros(0)
    c = c.astype(float)
    slope = lambda t: np.log(-np.expm1(-discount * _saddle(c, t, discount, 14)) / discount) - np.log(t) + np.log((strength + discount * (others + t)) * p)
    low, high = np.ones(len(c)), np.maximum(c * 0.999, 2)
    for _ in range(24):
        t = np.sqrt(low * high)
        up = slope(t) > 0
        low, high = np.where(up, t, low), np.where(up, high, t)
    far = np.maximum(0.5, 0.01 * t)
    deviation = 1 / np.sqrt(np.maximum((slope(np.maximum(t - far, 1)) - slope(np.minimum(t + far, c * 0.9995))) / (2 * far), 1e-9))
    first, last = np.maximum(1, np.floor(t - 7 * deviation - 2)), np.minimum(np.ceil(c * 0.999), np.ceil(t + 7 * deviation + 8))
    at = np.rint(first[:, None] + (last - first)[:, None] * np.linspace(0, 1, points))
    from_first = _log_gamma(strength / discount + others[:, None] + at) - _log_gamma(strength / discount + others[:, None] + first[:, None])
    log = np.where(at <= FEW, log_stirling_few(c[:, None], np.minimum(at, FEW), discount), log_stirling_saddle(c[:, None], at, discount)) + from_first + at * (np.log(discount) + np.log(p)[:, None])
    odds = np.exp(log - log.max(axis=1, keepdims=True))
    odds[:, 1:][np.diff(at, axis=1) == 0] = 0
    odds = np.cumsum(odds, axis=1)
    pick = (odds < (rng.random(len(c)) * odds[:, -1])[:, None]).sum(axis=1)
    return at[np.arange(len(c)), pick]


def _log_gamma(x: np.ndarray) -> np.ndarray:
    """log Gamma(x)."""
    return _log_factorial(x + 8) - np.log(np.stack([x + k for k in range(9)])).sum(axis=0)


@dataclass
class Seats:
    """Dishes of two customers or more: restaurant, customers, the parent's probability, and tables.

    total: tables of every restaurant, those of dishes with one customer and those held elsewhere among them.
    """

    room: np.ndarray
    c: np.ndarray
    p: np.ndarray
    total: np.ndarray
    discount: float
    strength: float

    def __post_init__(self):
        self.t = np.ones(len(self.c))
        self.groups = []
        low = 0
        for width in (2, *WIDTHS, None):
            own = np.flatnonzero((self.c > low) & (self.c <= width)) if width else np.flatnonzero(self.c > low)
            low = width
            if not len(own):
                continue
            own = own[np.argsort(self.room[own], kind="stable")]
            first = np.flatnonzero(np.diff(self.room[own], prepend=-1))
            size = np.diff(np.append(first, len(own)))
            place = np.arange(len(own)) - np.repeat(first, size)
            steps = STEPS if width else 2
            step = np.where(np.repeat(size, size) > steps, place * steps // np.repeat(size, size), place)
            order = np.argsort(step, kind="stable")
            cuts = np.flatnonzero(np.diff(step[order], prepend=-1))[1:]
            for part in np.split(own[order], cuts):
                for piece in np.array_split(part, -(-len(part) * (width or 128) // (1 << 21))):
                    self.groups.append((width, piece))

    def sweep(self, rng: np.random.Generator) -> None:
        d, s = self.discount, self.strength
        for width, at in self.groups:
            room, c, p = self.room[at], self.c[at], self.p[at]
            others = self.total[room] - self.t[at]
            if width == 2:
                two = (s + d * (others + 1)) * p
                new = 1.0 + (rng.random(len(at)) * (1 - d + two) < two)
            elif width:
                odds = table_odds(c, others, p, d, s, width)
                new = 1.0 + (odds < (rng.random(len(at)) * odds[:, -1])[:, None]).sum(axis=1)
            else:
                new = drawn_large(c, others, p, d, s, rng)
            self.total += np.bincount(room, new - self.t[at], len(self.total))
            self.t[at] = new


def sample_parent(count: np.ndarray, words: np.ndarray, sweeps: int, burn: int, discount: float, strength: float, seed: int) -> np.ndarray:
    """Averaged probability of a word by its count; count[0] = 0 stands for the one unknown word.

    ``words`` have each count; as they are exchangeable, the tables of all of them are one multinomial draw.
    """
    rng = np.random.default_rng(seed)
    count, words = count[1:], words[1:].astype(float)
    base = 1 / (words.sum() + 1)
    small = count <= EXACT
    mean_t = np.ones(len(count))
    tables = words.copy()
    out = np.zeros(len(count) + 1)
    for sweep in range(sweeps if len(count) else 0):
        total = tables.sum()
        for k in np.flatnonzero(small & (count > 1)):
            each = tables[k] / words[k]
            odds = np.diff(table_odds(count[k : k + 1], np.array([total - each]), np.array([base]), discount, strength, int(count[k]))[0], prepend=0)
            odds /= odds.sum()
            mean_t[k] = odds @ np.arange(1, count[k] + 1)
            now = float(rng.multinomial(int(words[k]), odds) @ np.arange(1, count[k] + 1))
            total += now - tables[k]
            tables[k] = now
        large = np.flatnonzero(~small)
        each = np.repeat(large, words[large].astype(np.int64))
        drawn = drawn_large(count[each], total - (tables / words)[each], np.full(len(each), base), discount, strength, rng)
        tables[large] = np.bincount(each, drawn, len(count))[large]
        mean_t[large] = tables[large] / words[large]
        if sweep >= burn:
            back = (strength + discount * (mean_t * words).sum()) * base
            out += np.append(back, count - discount * mean_t + back) / (strength + (count * words).sum())
    return out / max(1, sweeps - burn) if len(count) else np.ones(1)


# --- Blocks ---------------------------------------------------------------------------------------------------


@dataclass
class Layout:
    """Buckets, and the spread contexts (sorted hashes) with the number of buckets of each."""

    buckets: int
    spread: np.ndarray
    parts: np.ndarray

    def home(self, word: np.ndarray, part: np.ndarray | int = 0) -> np.ndarray:
        return (mix(word + np.asarray(part, np.uint64) * ODD) % np.uint64(self.buckets)).astype(np.int64)

    def spread_at(self, word: np.ndarray) -> np.ndarray:
        """Place among the spread contexts, else -1."""
        if not len(self.spread):
            return np.full(len(word), -1)
        at = np.minimum(np.searchsorted(self.spread, word), len(self.spread) - 1)
        return np.where(self.spread[at] == word, at, -1)


class Block:
    """Token numbers of a block, its words by bucket, and its distinct pairs in the order in which they are asked for."""

    def __init__(self, words: np.ndarray, number: np.ndarray, offset: np.ndarray, layout: Layout):
        self.words, self.number, self.offset = words, number, offset
        self.home = layout.home(words)
        before = np.empty_like(number)
        before[1:] = number[:-1]
        before[offset[:-1]] = np.flatnonzero(words == END)[0]
        pair, self.pair_of = np.unique(before * len(words) + number, return_inverse=True)
        self.context, self.word = np.divmod(pair, len(words))
        bucket, away = self.home[self.context], np.zeros(len(pair), bool)
        at = layout.spread_at(words)[self.context]
        if (wide := np.flatnonzero(at >= 0)).size:
            part = mix(words[self.word[wide]]) % layout.parts[at[wide]].astype(np.uint64)
            bucket[wide] = layout.home(words[self.context[wide]], part)
            away[wide] = bucket[wide] != self.home[self.context[wide]]
            self.order = np.argsort(bucket * 2 + away, kind="stable")
        else:
            self.order = np.arange(len(pair))
        self.bucket, self.away = bucket[self.order], away[self.order]

    @classmethod
    def of(cls, tokens: np.ndarray, offset: np.ndarray, layout: Layout) -> Block:
        return cls.numbered(*_codes(tokens), offset, layout)

    @classmethod
    def numbered(cls, words: np.ndarray, number: np.ndarray, offset: np.ndarray, layout: Layout) -> Block:
        """From token numbers among ``words`` in any order; here they go by bucket and hash."""
        order = np.lexsort((words, layout.home(words)))
        place = np.empty(len(words), np.int64)
        place[order] = np.arange(len(words))
        return cls(words[order], place[number], offset, layout)

    def by_frequency(self) -> tuple[np.ndarray, np.ndarray]:
        """Words from the most frequent on, and token numbers among them, which compress better."""
        order = np.argsort(-np.bincount(self.number, minlength=len(self.words)), kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        return self.words[order], place[self.number]


@dataclass
class Asked:
    """What one block asks of one bucket: its words there with their training counts and numbers of pairs; spread contexts
    that only have pairs there; the second words of the pairs and their training counts."""

    words: np.ndarray
    own: np.ndarray
    pairs: np.ndarray
    away: np.ndarray
    away_pairs: np.ndarray
    second: np.ndarray
    count: np.ndarray

    def packed(self) -> bytes:
        """Hashes don't compress; the numbers beside them do."""
        hashes = (self.words, self.away, self.second)
        numbers = _pressed([_split(x) for x in (self.own, self.pairs, self.away_pairs, self.count)])
        return np.array([len(x) for x in hashes], np.int32).tobytes() + b"".join(map(_hash_bytes, hashes)) + numbers

    @classmethod
    def opened(cls, data: bytes) -> Asked:
        sizes = np.frombuffer(data, np.int32, 3)
        ends = 12 + 7 * np.cumsum(np.append(0, sizes.astype(np.int64)))
        words, away, second = (_hashes(data, n, at) for n, at in zip(sizes.tolist(), ends[:3].tolist(), strict=True))
        own, pairs, away_pairs, count = map(_joined, _unpressed(data[int(ends[3]) :]))
        return cls(words, own, pairs, away, away_pairs, second, count)

    def contexts(self) -> np.ndarray:
        """The first word of every pair."""
        return np.concatenate([np.repeat(self.words, self.pairs), np.repeat(self.away, self.away_pairs)])


def _split(number: np.ndarray) -> list[np.ndarray]:
    """Bytes of numbers, lowest first; such planes compress better than whole numbers."""
    return [(number >> 8 * k & 255).astype(np.uint8) for k in range(max(1, (int(number.max(initial=0)).bit_length() + 7) // 8))]


def _joined(planes: list[np.ndarray]) -> np.ndarray:
    return sum(x.astype(np.int64) << 8 * k for k, x in enumerate(planes))


def _pressed(thing) -> bytes:
    raw = pickle.dumps(thing)
    return len(raw).to_bytes(8, "little") + pa.compress(raw, "zstd", asbytes=True)


def _unpressed(data: bytes):
    return pickle.loads(pa.decompress(data[8:], int.from_bytes(data[:8], "little"), "zstd", asbytes=True))


def _ask(shipped):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        layout: Layout = opened(shipped)
        made = TaskContext.get().partitionId() << 32
        for batch in batches:
            for a, b in text_blocks(batch.column("text"), BLOCK):
                part = batch.slice(a, b - a)
                tokens, offset = _tokens(part.column("text"))
                block = Block.of(tokens, offset, layout)
                held = part.column("held_out").to_numpy(zero_copy_only=False).astype(bool)
                learned = np.repeat(~held, np.diff(offset))
                own = np.bincount(block.number[learned], minlength=len(block.words))
                count = np.bincount(block.pair_of[learned], minlength=len(block.order))[block.order]
                context, second = block.context[block.order], block.words[block.word[block.order]]
                pairs = np.bincount(context[~block.away], minlength=len(block.words))
                edges = np.arange(layout.buckets + 1)
                w, p = np.searchsorted(block.home, edges), np.searchsorted(block.bucket, edges)
                pids, data = [], []
                for k in np.flatnonzero((np.diff(w) > 0) | (np.diff(p) > 0)).tolist():
                    i, j = p[k], p[k + 1]
                    away, size = np.unique(context[i:j][block.away[i:j]], return_counts=True)
                    pids.append(k)
                    data.append(Asked(block.words[w[k] : w[k + 1]], own[w[k] : w[k + 1]], pairs[w[k] : w[k + 1]], block.words[away], size, second[i:j], count[i:j]).packed())
                often, number = block.by_frequency()
                data.append(_pressed((part.column("doc_id").to_pylist(), held, np.diff(offset).astype(np.int32), _hash_bytes(often), _split(number))))
                n = len(data)
                pids.append(int(mix(np.array([made], np.uint64))[0] % np.uint64(layout.buckets)))
                yield pa.RecordBatch.from_arrays([pa.array(pids, pa.int32()), pa.array([made] * n, pa.int64()), pa.array([False] * (n - 1) + [True]), pa.array(data, pa.binary())], ["pid", "block", "payload", "data"])
                made += 1

    return run


# --- Buckets --------------------------------------------------------------------------------------------------


class Bucket:
    """All that blocks ask of one bucket: training counts of its words and of the pairs of its contexts."""

    def __init__(self, blocks: list[int], asked: list[Asked], layout: Layout):
        self.blocks, self.asked = blocks, asked
        self.words, self.word_of = _codes(np.concatenate([x.words for x in asked]))
        self.own = np.bincount(self.word_of, np.concatenate([x.own for x in asked]), len(self.words)).astype(np.int64)
        self.rooms, room = _codes(np.concatenate([y for x in asked for y in (x.words, x.away)]))
        room = np.repeat(room, np.concatenate([y for x in asked for y in (x.pairs, x.away_pairs)]))
        second, at = _codes(np.concatenate([x.second for x in asked]))
        pair, self.pair_of = np.unique(room * max(1, len(second)) + at, return_inverse=True)
        self.count = np.bincount(self.pair_of, np.concatenate([x.count for x in asked]), len(pair)).astype(np.int64)
        self.room, which = np.divmod(pair, max(1, len(second)))
        self.spread = np.flatnonzero(layout.spread_at(self.rooms) >= 0)
        self.spread = self.spread[layout.parts[layout.spread_at(self.rooms[self.spread])] > 1]
        # All words, by their homes; own words have theirs here.
        self.key = np.union1d(second, self.words)
        self.kid = layout.home(self.key)
        order = np.argsort(self.kid, kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        self.second_at, self.word_at = place[np.searchsorted(self.key, second)][which], place[np.searchsorted(self.key, self.words)]
        self.key, self.kid = self.key[order], self.kid[order]
        self.need = np.zeros(len(self.key), bool)
        self.need[self.word_at] = self.need[self.second_at[self.count > 1]] = True
        # Spread contexts, by the homes of the keys under which their tables are summed.
        self.mark = mix(self.rooms[self.spread] ^ SPREAD)
        self.spread = self.spread[np.argsort(layout.home(self.mark), kind="stable")]
        self.mark = mix(self.rooms[self.spread] ^ SPREAD)
        self.mark_kid = layout.home(self.mark)

    def told(self, pid: int, tables: np.ndarray, first: bool) -> pa.Table:
        """Tables of every word under this bucket's contexts and of its spread contexts, a packed row for each home.

        first: also the words' own counts, and which totals the bucket needs; else only words with tables.
        """
        sums = np.bincount(self.second_at, tables, len(self.key)).astype(np.int64)
        n = np.zeros(len(self.key), np.int64)
        n[self.word_at] = self.own
        keep = np.flatnonzero(self.need | (sums > 0)) if first else np.flatnonzero(sums > 0)
        rooms = np.bincount(self.room, tables, len(self.rooms)).astype(np.int64)[self.spread]
        kids, rows = [], []
        for k in np.union1d(self.kid[keep], self.mark_kid).tolist():
            own = keep[slice(*np.searchsorted(self.kid[keep], [k, k + 1]))]
            m = slice(*np.searchsorted(self.mark_kid, [k, k + 1]))
            kids.append(k)
            rows.append(_hash_bytes(self.key[own]) + _pressed((_split(sums[own]), _split(n[own]) if first and k == pid else None, np.packbits(self.need[own]) if first else None, self.mark[m], rooms[m])) + len(own).to_bytes(4, "little"))
        return pa.table([pa.array(kids, pa.int32()), pa.array([pid] * len(kids), pa.int32()), pa.array(rows, pa.binary())], names=["kid", "pid", "data"])


def _heard(data: bytes) -> tuple:
    """What ``told`` packed: words, tables, own counts, needs; marks and tables of spread contexts."""
    size = int.from_bytes(data[-4:], "little")
    sums, n, need, mark, rooms = _unpressed(data[7 * size : -4])
    return _hashes(data, size), _joined(sums), np.zeros(size, np.int64) if n is None else _joined(n), None if need is None else np.unpackbits(need, count=size).astype(bool), mark, rooms


class Home:
    """Totals of the words that are at home in one bucket."""

    def __init__(self, told: pa.Table, moved: pa.Table | None):
        told = told.sort_by("pid")
        self.pids, self.rows = told.column("pid").to_pylist(), [_heard(x) for x in told.column("data").to_pylist()]
        self.key, self.at = _codes(np.concatenate([r[0] for r in self.rows]))
        self.total = np.bincount(self.at, np.concatenate([r[1] for r in self.rows]), len(self.key)).astype(np.int64)
        self.n = np.bincount(self.at, np.concatenate([r[2] for r in self.rows]), len(self.key)).astype(np.int64)
        self.rooms: dict[int, int] = {}
        self.own: dict[tuple[int, int], int] = {}
        later = moved.to_pylist() if moved is not None else []
        for r in later:
            key, more, *_ = _heard(r["data"])
            self.total[np.searchsorted(self.key, key)] += more
        for pid, r in [*zip(self.pids, self.rows, strict=True), *((x["pid"], _heard(x["data"])) for x in later)]:
            for mark, tables in zip(r[4].tolist(), r[5].tolist(), strict=True):
                self.rooms[mark] = self.rooms.get(mark, 0) + tables
                self.own[mark, pid] = self.own.get((mark, pid), 0) + tables

    def histogram(self) -> pa.Table:
        count, at = np.unique(self.total, return_inverse=True)
        return pa.table({"tables": count, "words": np.bincount(at, minlength=len(count)), "n": np.bincount(at, self.n, len(count)).astype(np.int64), "known": np.bincount(at, self.n > 0, len(count)).astype(np.int64)})

    def replies(self, kid: int) -> pa.Table:
        """Totals of the words that each bucket needs, in its order, and of its spread contexts with those of its own."""
        at, data = 0, []
        for pid, r in zip(self.pids, self.rows, strict=True):
            own = self.at[at : at + len(r[0])]
            at += len(r[0])
            marks = r[4].tolist()
            data.append(_pressed((_split(self.total[own[r[3]]]), [self.rooms[m] for m in marks], [self.own[m, pid] for m in marks])))
        return pa.table([pa.array(self.pids, pa.int32()), pa.array([kid] * len(data), pa.int32()), pa.array(data, pa.binary())], names=["pid", "kid", "data"])


REPLIED, HISTOGRAM = "pid int, kid int, data binary", "tables long, words long, n long, known long"


def _replies_after(told: pa.Table, moved: pa.Table | None) -> pa.Table:
    if not told.num_rows:
        return pa.table([pa.array([], pa.int32()), pa.array([], pa.int32()), pa.array([], pa.binary())], names=["pid", "kid", "data"])
    return Home(told, moved).replies(told.column("kid")[0].as_py())


def _histogram_after(told: pa.Table, moved: pa.Table | None) -> pa.Table:
    return Home(told, moved).histogram() if told.num_rows else pa.table({x: pa.array([], pa.int64()) for x in ("tables", "words", "n", "known")})


def _replies(told: pa.Table) -> pa.Table:
    return _replies_after(told, None)


def _histogram(told: pa.Table) -> pa.Table:
    return _histogram_after(told, None)


def _buckets(table: pa.Table, layout: Layout) -> Iterator[tuple[int, Bucket]]:
    rows = table.filter(pa.compute.invert(table.column("payload")))
    if rows.num_rows:
        # In order of the blocks, so that a task that runs again seats alike.
        rows = rows.sort_by("block")
        yield rows.column("pid")[0].as_py(), Bucket(rows.column("block").to_pylist(), [Asked.opened(x) for x in rows.column("data").to_pylist()], layout)


@dataclass
class How:
    sweeps: int
    burn: int
    discount: tuple[float, float]
    strength: tuple[float, float]
    seed: int


def _tell(shipped):
    def run(table: pa.Table) -> pa.Table:
        layout, _ = opened(shipped)
        for pid, bucket in _buckets(table, layout):
            return bucket.told(pid, (bucket.count > 0).astype(np.int64), True)
        return pa.table([pa.array([], pa.int32()), pa.array([], pa.int32()), pa.array([], pa.binary())], names=["kid", "pid", "data"])

    return run


class Answers:
    """The parent's probability of all words that a bucket needs (elsewhere 0), and its spread contexts' other tables."""

    def __init__(self, table: pa.Table, bucket: Bucket):
        table = table.sort_by("kid")
        count, p, self.tokens, self.distinct = _unpressed(table.column("data")[0].as_py())
        told = [_unpressed(x) for x in table.column("data")[1:].to_pylist()]
        total = np.concatenate([np.zeros(0, np.int64), *(_joined(x[0]) for x in told)])
        self.p = np.zeros(len(bucket.key))
        self.p[bucket.need] = p[np.searchsorted(count, total)]
        rooms, own = (np.array([y for x in told for y in x[k]], float) for k in (1, 2))
        self.elsewhere = rooms - own


def _seated(bucket: Bucket, told: Answers, how: How, pid: int, sweeps: int, burn: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Tables of every pair: mean and last; and mean tables of every context."""
    many = np.flatnonzero(bucket.count > 1)
    start = (bucket.count > 0).astype(float)
    total = np.bincount(bucket.room, start, len(bucket.rooms))
    total[bucket.spread] += told.elsewhere
    seats = Seats(bucket.room[many], bucket.count[many], told.p[bucket.second_at[many]], total, how.discount[1], how.strength[1])
    rng = np.random.default_rng([how.seed, pid])
    mean, rooms = np.zeros(len(many)), np.zeros(len(total))
    for sweep in range(sweeps):
        seats.sweep(rng)
        if sweep >= burn:
            mean += seats.t
            rooms += seats.total
    kept = max(1, sweeps - burn)
    average, last = start.copy(), start.copy()
    average[many], last[many] = mean / kept, seats.t
    return average, last, rooms / kept


def _seat(shipped, sweeps: int):
    """A round before the last: tables beyond one of every pair."""

    def run(asked: pa.Table, told: pa.Table) -> pa.Table:
        layout, how = opened(shipped)
        for pid, bucket in _buckets(asked, layout):
            _, last, _ = _seated(bucket, Answers(told, bucket), how, pid, sweeps, 0)
            return bucket.told(pid, last - (bucket.count > 0), False)
        return _tell(shipped)(asked)

    return run


ANSWERED = "pid int, block long, bucket int, tokens long, distinct long, data binary"


def _answer(shipped):
    """The last round: what every block asked for."""

    def run(asked: pa.Table, told: pa.Table) -> pa.Table:
        layout, how = opened(shipped)
        out = []
        for pid, bucket in _buckets(asked, layout):
            answers = Answers(told, bucket)
            tables, _, rooms = _seated(bucket, answers, how, pid, how.sweeps, how.burn)
            left = np.where(bucket.count > 0, bucket.count - how.discount[1] * tables, 0.0).astype(np.float32)
            room = rooms[np.searchsorted(bucket.rooms, bucket.words)]
            back = np.where(bucket.own > 0, (how.strength[1] + how.discount[1] * room) / (how.strength[1] + bucket.own), 1.0)
            w = p = 0
            for block, x in zip(bucket.blocks, bucket.asked, strict=True):
                own, pair = bucket.word_of[w : w + len(x.words)], bucket.pair_of[p : p + len(x.second)]
                w, p = w + len(x.words), p + len(x.second)
                data = _pressed((bucket.own[own], answers.p[bucket.word_at[own]], back[own], left[pair]))
                to = int(mix(np.array([block], np.uint64))[0] % np.uint64(layout.buckets))
                out.append((to, block, pid, answers.tokens, answers.distinct, data))
        names = [x.split()[0] for x in ANSWERED.split(", ")]
        kinds = [pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary()]
        return pa.table([pa.array([r[k] for r in out], kind) for k, kind in enumerate(kinds)], names=names)

    return run


def _score(shipped):
    def run(asked: pa.Table, answered: pa.Table) -> pa.Table:
        layout, how = opened(shipped)
        rows = asked.filter(asked.column("payload"))
        answered = answered.sort_by([("block", "ascending"), ("bucket", "ascending")])
        which = answered.column("block").to_numpy()
        tables = []
        for name, data in zip(rows.column("block").to_pylist(), rows.column("data").to_pylist(), strict=True):
            ids, held, size, words, planes = _unpressed(data)
            i, j = np.searchsorted(which, [name, name + 1])
            own, p, back, left = (np.concatenate(x) for x in zip(*[_unpressed(x) for x in answered.column("data")[i:j].to_pylist()], strict=True))
            tokens, distinct = (answered.column(c)[int(i)].as_py() for c in ("tokens", "distinct"))
            number = _joined(planes)
            offset = np.concatenate([[0], np.cumsum(size)]).astype(np.int64)
            block = Block.numbered(_hashes(words, len(words) // 7), number, offset, layout)
            number = block.number
            context, word = block.context[block.order], block.word[block.order]
            log = np.empty(len(left))
            log[block.order] = np.log10(left / (how.strength[1] + own[context]) + back[context] * p[word])
            base = np.log10((own + 1) / (tokens + distinct + 1))
            tables.append(pa.table({
                "doc_id": pa.array(ids, pa.int64()), "held_out": pa.array(held), "n_tokens": np.diff(offset), "n_known": segment_sum((own > 0).astype(np.int64)[number], offset), "train_tokens": np.full(len(ids), tokens),
                "base_score": segment_sum(base[number], offset), "score": segment_sum(log[block.pair_of], offset),
            }))
        return pa.concat_tables(tables) if tables else pa.table({n: pa.array([], k) for n, k in (("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64()))})

    return run


# --- The corpus -----------------------------------------------------------------------------------------------


def _common(share: float):
    """Training counts of words with at least half the share in a block; the block's tokens under END's complement."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in text_blocks(batch.column("text"), BLOCK):
                tokens, _ = _tokens(batch.column("text").slice(a, b - a))
                word, at = _codes(tokens)
                n = np.bincount(at)
                often = n >= max(2, share / 2 * len(tokens))
                yield pa.RecordBatch.from_arrays([pa.array(np.append(word[often], ~END).view(np.int64)), pa.array(np.append(n[often], len(tokens)))], ["word", "n"])

    return run


def _layout(docs: DataFrame, bucket_bytes: int) -> Layout:
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    buckets = max(1, -(-int(size) // bucket_bytes))
    share = max(2.0**-16, 1 / buckets)
    if buckets == 1:
        return Layout(1, np.zeros(0, np.uint64), np.zeros(0, np.int64))
    found = docs.where("not held_out").select("text").mapInArrow(_common(share), "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))
    total = found.where(F.col("word") == int(np.array([~END]).view(np.int64)[0]))
    often = found.join(F.broadcast(total.select(F.col("n").alias("all"))), F.col("n") >= F.col("all") * share).where("n < all").select("word", "n", "all").toPandas()
    word = often["word"].to_numpy(np.int64).view(np.uint64)
    order = np.argsort(word)
    return Layout(buckets, word[order], np.ceil(often["n"].to_numpy(float) / np.maximum(often["all"].to_numpy(float), 1) * buckets).astype(np.int64)[order])


def _root(how: How):
    """Probabilities of words by their count of tables, from the histogram of these, and the corpus' totals, in one row."""

    def run(table: pa.Table) -> pa.Table:
        tables, words, n, known = (table.column(c).to_numpy() for c in ("tables", "words", "n", "known"))
        order = np.argsort(tables)
        count, many = np.append(0, tables[order][tables[order] > 0]), np.append(1, words[order][tables[order] > 0])
        p = sample_parent(count, many, how.sweeps, how.burn, how.discount[0], how.strength[0], how.seed)
        return pa.table({"data": pa.array([_pressed((count, p, int(n.sum()), int(known.sum())))], pa.binary())})

    return run


def scores(docs: DataFrame, rounds: int = 2, sweeps: int = 6, burn: int = 2, discount: tuple[float, float] = (0.75, 0.75), strength: tuple[float, float] = (20.0, 4.0), seed: int = 7, bucket_bytes: int = BUCKET) -> DataFrame:
    """Log10 probabilities of whole texts under the model of those that aren't held out.

    ``docs`` has doc_id, text, held_out; one row for each row of it, rows with equal ids too.  A null text is empty: its
    only token is the end.  discount and strength: of the parent and of the contexts.
    """
    docs = docs.select("doc_id", "text", "held_out")
    layout = _layout(docs, bucket_bytes)
    n, how = layout.buckets, How(sweeps, burn, discount, strength, seed)
    spark = docs.sparkSession
    shipped = ship(spark.sparkContext, (layout, how))
    # Exchanges that are read more than once only feed Python, so that no reader's columns make another one of them.
    asked = docs.mapInArrow(_ask(ship(spark.sparkContext, layout)), ASKED).repartitionById(n, "pid")
    told = asked.groupBy("pid").applyInArrow(_tell(shipped), TOLD).repartitionById(n, "kid")
    moved = None
    for r in range(rounds):
        if moved is None:
            counted, replied = told.groupBy("kid").applyInArrow(_histogram, HISTOGRAM), told.groupBy("kid").applyInArrow(_replies, REPLIED)
        else:
            counted, replied = (told.groupBy("kid").cogroup(moved.groupBy("kid")).applyInArrow(f, kind) for f, kind in ((_histogram_after, HISTOGRAM), (_replies_after, REPLIED)))
        histogram = counted.groupBy("tables").agg(*[F.sum(c).alias(c) for c in ("words", "n", "known")])
        root = histogram.withColumn("one", F.lit(0)).groupBy("one").applyInArrow(_root(how), "data binary")
        everywhere = spark.range(n).crossJoin(F.broadcast(root)).select(F.col("id").cast("int").alias("pid"), F.lit(-1).alias("kid"), "data")
        answers = replied.union(everywhere).repartitionById(n, "pid").groupBy("pid")
        if r + 1 < rounds:
            moved = asked.groupBy("pid").cogroup(answers).applyInArrow(_seat(shipped, sweeps), TOLD).repartitionById(n, "kid")
    answered = asked.groupBy("pid").cogroup(answers).applyInArrow(_answer(shipped), ANSWERED).repartitionById(n, "pid")
    return asked.groupBy("pid").cogroup(answered.groupBy("pid")).applyInArrow(_score(shipped), SCORED)


def perplexity(scored: DataFrame) -> DataFrame:
    """Held-out and training perplexity by token of the model and of the base."""
    return scored.groupBy("held_out").agg(F.sum("n_tokens").alias("n_tokens"), F.pow(F.lit(10.0), -F.sum("score") / F.sum("n_tokens")).alias("perplexity"), F.pow(F.lit(10.0), -F.sum("base_score") / F.sum("n_tokens")).alias("base_perplexity"))


def held_out(docs: DataFrame, modulus: int = 7, remainder: int = 2) -> DataFrame:
    """doc_id, text, held_out; a null id counts as the empty string."""
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), (F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(modulus)) == remainder).alias("held_out")
    )


def scored_documents(docs: DataFrame, **how) -> DataFrame:
    """Fits on the documents that are not held out and scores all."""
    return scores(held_out(docs), **how)
