"""Every corpus operator against plain Python, on odd and on ordinary texts."""

import base64
import hashlib
import sys
from pathlib import Path

import numpy as np
import pytest

sys.path.insert(0, str(Path(__file__).parent))
import brute  # noqa: E402

from tilealg.llm import byte_contexts, byte_pairs, license_scan, line_rules, near_copies, pitman_yor, private_data, quality, shard_index, url_filter  # noqa: E402

PASSAGE = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron"
LONG = " ".join(f"w{(i * 7919) % 997}" for i in range(6000))
TEXTS = [
    None, "", "   \n\t ", "one", "Two words", PASSAGE, PASSAGE.upper() + " extra tail words here now", f"start {PASSAGE} end", LONG, LONG + " z", LONG,
    "a b c d e a b c d e a b c d e", "line one here.\nline one here.\n\nother", "Released Under THE  mit-license. Apache License, Version 2.0; CC BY-NC 4.0 under the mit license",
    "This work is licensed under the GNU General Public License", "ünï çödé words ÀÉ under thé mit license", "x\x0by\x0cz\x1fq \x00", "😀 😀 😀 emoji", "aaaa " * 50, "b" * 5000, "<|endoftext|> it's 12345 \n\n  x",
    "same five words in this text " * 4 + "and a tail of other words to follow it",
]
ROWS = [(k * 3, t) for k, t in enumerate(TEXTS)]


@pytest.fixture(scope="module")
def docs(spark):
    """With columns whose names clash with those that operators make."""
    return spark.createDataFrame([(d, t, "en", "s", 1.0, "k") for d, t in ROWS], "doc_id long, text string, lang string, source string, score double, kept string")


@pytest.fixture(scope="module")
def empty(docs):
    return docs.limit(0)


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_licences(docs, empty):
    got = by_id(license_scan.licences(docs))
    for d, t in ROWS:
        r = got[d]
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == brute.licence(t)
        assert set(r.base_labels.split(",")) <= set(r.labels.split(",")) | {""} and 0 <= r.score <= 1
    assert got[42].labels == "gpl"
    assert license_scan.licences(empty).count() == 0


def test_near_copies(spark, docs, empty):
    got = by_id(near_copies.near_copies(docs))
    assert {d: (r.n_shingles, r.component_id) for d, r in got.items()} == brute.near(ROWS)
    assert near_copies.near_copies(empty).count() == 0


def test_near_copies_with_equal_and_null_ids(spark):
    """Rows of one id are told apart by their texts; a null id takes part through another row with its set."""
    rng = np.random.default_rng(12)
    a, b, c = (" ".join(f"w{int(x)}" for x in rng.integers(0, 9999, 80)) for _ in range(3))
    rows = [(5, a), (5, b), (3, a + " tail"), (4, b + " tail"), (5, a), (None, c), (None, c + " tail"), (8, c), (9, None), (None, "")]
    got = sorted(((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in near_copies.near_copies(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    want = [(5, 76, 3, False), (5, 76, 4, False), (3, 77, 3, True), (4, 77, 4, True), (5, 76, 3, False), (None, 76, 8, False), (None, 77, 8, False), (8, 76, 8, True), (9, 0, 9, True), (None, 0, None, True)]
    assert {x[:3] for x in got if x[0] is not None} == {x[:3] for x in want if x[0] is not None}
    assert [x for x in got if x[0] is not None] == sorted((x for x in want if x[0] is not None), key=str) and len(got) == len(want)


def test_near_copies_of_copies(spark):
    """Chains of changed copies, of which only neighbours are linked."""
    rng = np.random.default_rng(3)
    words = [f"v{i}" for i in range(160)]
    rows = []
    for k in range(60):
        if k % 3 == 0:
            words = list(words)
            words[int(rng.integers(160))] = f"n{k}"
        own = list(words)
        own[int(rng.integers(160))] = f"m{k}"
        rows.append((k, " ".join(own)))
    got = by_id(near_copies.near_copies(spark.createDataFrame(rows, "doc_id long, text string")))
    assert {d: (r.n_shingles, r.component_id) for d, r in got.items()} == brute.near(rows)


def test_language_model(docs, empty):
    got = by_id(pitman_yor.scored_documents(docs))
    for d, want in brute.unigram(ROWS).items():
        r = got[d]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == want[:4]
        assert abs(r.base_score - want[4]) < 1e-6 and r.score < 0
    assert pitman_yor.scored_documents(empty).count() == 0


def exact_tables(rooms, p, discount, strength):
    """Mean tables of every dish under the exact posterior, by going through all numbers of tables; rooms: lists of counts."""
    from functools import lru_cache
    from itertools import product

    @lru_cache
    def stirling(c, t):
        if c == t:
            return 1.0
        return 0.0 if t < 1 or t > c else stirling(c - 1, t - 1) + (c - 1 - t * discount) * stirling(c - 1, t)

    out = []
    for counts, odds in zip(rooms, p, strict=True):
        total, mean = 0.0, np.zeros(len(counts))
        for t in product(*[range(1, c + 1) for c in counts]):
            w = np.prod([strength + discount * i for i in range(sum(t))]) * np.prod([stirling(c, k) * q**k for c, k, q in zip(counts, t, odds, strict=True)])
            total += w
            mean += w * np.array(t)
        out.extend(mean / total)
    return np.array(out)


def test_seating_has_the_exact_posterior():
    rooms, p = [[5, 2, 3], [7, 4], [2]], [[0.2, 0.05, 0.1], [0.3, 0.02], [0.4]]
    room = np.repeat(np.arange(3), [3, 2, 1])
    seats = pitman_yor.Seats(room, np.concatenate(rooms), np.concatenate(p), np.array([3.0, 2.0, 1.0]), 0.6, 2.0)
    rng, mean = np.random.default_rng(1), np.zeros(6)
    for _ in range(20_000):
        seats.sweep(rng)
        mean += seats.t
        assert (np.bincount(room, seats.t) == seats.total).all()
    assert np.allclose(mean / 20_000, exact_tables(rooms, p, 0.6, 2.0), atol=0.03)


def test_draws_for_many_customers_have_the_exact_odds():
    """Tables of 1,024 customers, by the whole row of Stirling numbers and by the saddle point."""
    for p in (0.9, 0.5, 0.01, 0.0001, 1e-9):
        others = np.full(1500, 300.0)
        odds = pitman_yor.table_odds(np.array([1024]), others[:1], np.array([p]), 0.75, 4.0, 1024)[0]
        weight, t = np.diff(odds / odds[-1], prepend=0), np.arange(1, 1025)
        exact = weight @ t
        drawn = pitman_yor.drawn_large(np.full(1500, 1024), others, np.full(1500, p), 0.75, 4.0, np.random.default_rng(2))
        assert abs(drawn.mean() / exact - 1) < 0.02 and abs(drawn.var() - weight @ (t - exact) ** 2) < 0.15 * drawn.var() + 0.05, (p, drawn.mean(), exact)


def test_parent_probabilities_sum_to_one():
    count, words = np.array([0, 1, 2, 9, 3000]), np.array([1, 50, 10, 1, 1])
    p = pitman_yor.sample_parent(count, words, 6, 2, 0.75, 4.0, 1)
    assert abs((p * words).sum() - 1) < 1e-9 and (np.diff(p) > 0).all()
    assert pitman_yor.sample_parent(count[:1], words[:1], 6, 2, 0.75, 4.0, 1).tolist() == [1.0]


def test_language_model_by_hand(spark):
    """One training text of distinct words: every dish has one customer and one table, so scores have a closed form."""
    import math

    words = [f"w{k}" for k in range(9)]
    texts = {True: [" ".join(words[:3]), "w1 w0 new", "w8", "new w5 w6", ""], False: [" ".join(words)]}
    docs = spark.createDataFrame([(k, t, h) for k, (h, t) in enumerate((h, t) for h in texts for t in texts[h])], "doc_id long, text string, held_out boolean")
    d, s = (0.7, 0.8), (3.0, 2.0)
    known = {*words, None}
    parent = lambda w: ((1 - d[0] if w in known else 0) + (s[0] + d[0] * 10) / 11) / (s[0] + 10)
    follows = dict(zip([None, *words], [*words, None], strict=True))
    for bucket_bytes in (1 << 20, 8):
        for r in pitman_yor.scores(docs, discount=d, strength=s, bucket_bytes=bucket_bytes).join(docs.select("doc_id", "text"), "doc_id").collect():
            want, u = 0.0, None
            for w in [*r.text.split(), None]:
                want += math.log10(((1 - d[1]) * (follows[u] == w) + (s[1] + d[1]) * parent(w)) / (s[1] + 1) if u in known else parent(w))
                u = w
            assert abs(r.score - want) < 1e-5 and r.train_tokens == 10


def test_language_model_over_many_buckets(spark):
    """The same counts however restaurants are dealt; contexts that hold a third of all tokens are spread."""
    rng = np.random.default_rng(8)
    rows = [(k, " ".join(f"x{int(x)}" if i % 3 else "the" for i, x in enumerate(rng.zipf(1.5, 90) % 500))) for k in range(120)]
    docs = pitman_yor.held_out(spark.createDataFrame(rows, "doc_id long, text string"))
    one, many = (by_id(pitman_yor.scores(docs, bucket_bytes=b)) for b in (1 << 30, 2000))
    assert len(pitman_yor._layout(docs, 2000).spread) and len(one) == len(many) == 120
    for d, r in one.items():
        assert (r.n_tokens, r.n_known, r.base_score) == (many[d].n_tokens, many[d].n_known, many[d].base_score)
        assert abs(many[d].score / r.score - 1) < 0.03
    for r in pitman_yor.perplexity(spark.createDataFrame(list(one.values()))).collect():
        assert r.perplexity < r.base_perplexity


def test_line_rules(docs, empty):
    got = by_id(line_rules.cleaned_lines(docs))
    for d, t in ROWS:
        r = got[d]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == brute.lines(t)
        assert not (r.base_failed and r.kept)
    assert line_rules.cleaned_lines(empty).count() == 0


def test_language(spark, empty):
    rows = [(k, ["the cat and the dog were there", "der hund und die katze waren da"][k % 2] + f" {k}", ["en", "de"][k % 2]) for k in range(60)] + [(900, None, "en"), (901, "12 34", None), (902, "", None)]
    got = by_id(byte_contexts.identified(spark.createDataFrame(rows, "doc_id long, text string, lang string")))
    assert all(got[d].lang_pred == lang for d, _, lang in rows[:60])
    assert {got[d].lang_pred for d in (900, 901, 902)} == {"und"}
    assert byte_contexts.identified(empty).count() == 0


def test_context_probabilities_are_exact():
    """Method C escapes by hand for a two-letter language."""
    import pyarrow as pa

    buffer, spans = byte_contexts._buffer(pa.array(["abab"]))
    code, n = np.unique(byte_contexts._inside(buffer, spans), return_counts=True)
    model = byte_contexts.Contexts.of(["x"], [(code, n.astype(float))])
    rows = model.rows(buffer)[:, 0]
    # After three spaces "a" was seen once: 1 / (1 + 1).
    assert abs(rows[0] + 1) < 1e-12


def test_language_by_brute_force(spark):
    """Code lengths by dictionaries of counts, text by text."""
    import math
    import zlib
    from collections import Counter, defaultdict

    words = {"en": "the a of house cat and dog ran over hill stone".split(), "de": "der die das haus katze und hund lief über berg stein".split(), "fr": "le la les maison chat et chien courut été colline".split()}
    rng = np.random.default_rng(9)
    rows = [(k, " ".join(rng.choice(words[lang], int(rng.integers(1, 25)))), lang) for k in range(90) for lang in [("en", "de", "fr")[k % 3]]] + [(200, "xyz \x00 ß", "en"), (201, "CAT", "de"), (202, "cat", "de"), (203, "42", "fr")]
    counts = {lang: [defaultdict(Counter) for _ in range(4)] for lang in words}
    spell = lambda t: b"   " + t.encode().translate(brute.UP) + b" "
    for d, t, lang in rows:
        if zlib.crc32(str(d).encode()) % 5:
            x = spell(t)
            for i in range(3, len(x)):
                for k in range(4):
                    counts[lang][k][x[i - k : i]][x[i]] += 1

    def bits(tables, x, i):
        out = 0.0
        for k in (3, 2, 1, 0):
            seen = tables[k].get(x[i - k : i])
            if seen:
                n, kinds = sum(seen.values()), len(seen)
                if x[i] in seen:
                    return out - math.log2(seen[x[i]] / (n + kinds))
                out -= math.log2(kinds / (n + kinds))
        return out + 8

    got = by_id(byte_contexts.identified(spark.createDataFrame(rows, "doc_id long, text string, lang string")))
    for d, t, _ in rows:
        x = spell(t)
        cost = {lang: sum(bits(counts[lang], x, i) for i in range(3, len(x))) for lang in words}
        best = min(sorted(cost), key=cost.get)
        if any(map(str.isalpha, t)):
            assert got[d].lang_pred == best and abs(got[d].bits_per_byte - cost[best] / (len(x) - 3)) < 1e-9
            assert abs(got[d].score - 1 / sum(2.0 ** (cost[best] - c) for c in cost.values())) < 1e-9
        else:
            assert got[d].lang_pred == "und"


def test_byte_pairs(docs, empty):
    import public_tokenizers as P
    import tiktoken

    path = P.path("byte_bpe_50k.tiktoken")
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, Path(path).read_bytes().splitlines())}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got, full = by_id(byte_pairs.code_digests(docs, path, P.PATTERN)), by_id(byte_pairs.encoded(docs, path, P.PATTERN))
    for d, t in ROWS:
        ids = enc.encode_ordinary(t or "")
        assert full[d].ids == ids and bytes(full[d].decoded) == (t or "").encode()
        assert (got[d].n_tokens, got[d].ids_sha256, got[d].decoded_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest())
    assert byte_pairs.code_digests(empty, path, P.PATTERN).count() == 0


def test_benchmark_passages(spark, docs, empty):
    items = [(1, PASSAGE), (2, "two WORDS"), (3, None), (4, ""), (5, "one"), (6, PASSAGE), (7, " ".join(LONG.split()[40:60])), (8, "a b c d e a b c d e a b c d"), (8, "never there at all")]
    table = spark.createDataFrame(items, "item_id long, text string")
    for block in (4 << 20, 30):
        got = by_id(shard_index.contaminated_spans(docs, table, block_bytes=block))
        for d, want in brute.passages(ROWS, items).items():
            r = got[d]
            assert (r.n_words, r.n_hit, r.n_items, hashlib.sha256(",".join(r.item_ids).encode()).hexdigest()) == want[:4]
            assert sum(e - s for s, e in zip(r.span_start, r.span_end, strict=True)) == r.n_hit
        left = {r["doc_id"] for r in shard_index.decontaminated(docs, table, block_bytes=block).collect()}
        assert left == {d for d, w in brute.passages(ROWS, items).items() if not w[4]}
    assert shard_index.contaminated_spans(empty, table).count() == 0
    assert shard_index.contaminated_spans(docs, table.limit(0)).where("n_hit > 0").count() == 0
    with pytest.raises(ValueError):
        shard_index.contaminated_spans(docs, table, most_bytes=1)


luhn = brute.luhn


def test_private_data(spark, empty):
    text = "mail Ann.B@mail7.example.com card 4111 1111 1111 1111 and 4111-1111-1111-1111, no 123456789012 ip 10.20.30.40 bad 999.1.1.1 tel +1 (743) 555-3824 born 2001-02-28 or 31.12.1999 not 2001-02-30 ssn 123-45-6789 end 7"
    rows = [(1, text), (2, text), (3, "nothing 12 to see"), (4, None), (5, "")]
    got = by_id(private_data.pseudonymised(spark.createDataFrame([(*r, 9) for r in rows], "doc_id long, text string, n_private long")))
    a = got[1].text
    assert a == got[2].text and got[3].text == rows[2][1] and got[4].text is None and got[5].text == ""
    assert (got[1].n_private, got[3].n_private, got[4].n_private) == (9, 0, 0)
    for gone in ("Ann.B", "4111 1111", "123456789012", "10.20.30.40", "555-3824", "2001-02-28", "31.12.1999", "123-45-6789"):
        assert gone not in a
    for kept in ("999.1.1.1", "2001-02-30", "@", "example.com", "+1 (", "end 7"):
        assert kept in a
    import re

    spaced, dashed = re.search(r"card ([\d ]+) and ([\d-]+),", a).groups()
    assert luhn(spaced) and spaced.replace(" ", "") == dashed.replace("-", "") and len(spaced) == 19
    assert private_data.pseudonymised(empty).count() == 0


def test_secret_alone_in_a_text(spark):
    """Its digits all stand between letters."""
    secret = "a1b2c3d4e5f6" * 2 + "a1b2c3d4"
    rows = [(1, f"key {secret} end"), (2, f"key {secret} of ann@example.com")]
    got = by_id(private_data.pseudonymised(spark.createDataFrame(rows, "doc_id long, text string")))
    assert (got[1].n_private, got[2].n_private) == (1, 2)
    assert got[1].text.split()[1] == got[2].text.split()[1] != secret and len(got[1].text) == len(rows[0][1])


def test_month_first_dates_stay_month_first(spark):
    from pyspark.sql import functions as F

    days = spark.sql("select explode(sequence(date'1996-01-01', date'1997-12-31', interval 1 day)) d").where("day(d) > 12").selectExpr("date_format(d, 'MM/dd/yyyy') v")
    got = days.select("v", private_data.pseudonym(F.col("v"), F.lit("k")).alias("p")).selectExpr("v", "p", "to_date(p, 'MM/dd/yyyy') d").cache()
    assert got.where("day(d) <= 12 or d is null or length(p) <> 10").count() == 0
    assert got.select("p").distinct().count() == got.count() and got.where("v = p").count() < 3
    both = spark.createDataFrame([("03/04/1999",), ("04/25/1999",), ("13/13/1999",)], "v string").select("v", private_data.pseudonym(F.col("v"), F.lit("k")).alias("p")).collect()
    assert [r.v == r.p for r in both] == [False, False, True]


def test_long_numbers_and_short_dates(spark):
    import re
    from datetime import date

    iban, long_ = "89370400440532013000", "7" * 70
    card = next(c for k in range(10) if luhn(c := f"630400000000000000{k}"))
    spaced = lambda d: " ".join(d[i : i + 4] for i in range(0, len(d), 4))
    dates = ["5.3.1999", "3/14/2021", "14.3.2021", "7/11/2020", "5.03.1999", "1.1.1800"]
    rows = [(1, f"DE{iban}"), (2, f"DE{spaced(iban)}"), (3, card), (4, spaced(card)), (5, long_), (6, spaced(long_) + " end"), *[(10 + k, d) for k, d in enumerate([*dates, "31.2.1999"])]]
    got = by_id(private_data.pseudonymised(spark.createDataFrame(rows, "doc_id long, text string")))
    shape = lambda t: re.sub("[0-9]", "0", t)
    for a, b in ((1, 2), (3, 4), (5, 6)):
        x, y = (re.sub("[^0-9]", "", got[k].text) for k in (a, b))
        assert x == y != re.sub("[^0-9]", "", rows[a - 1][1]) and (got[a].n_private, got[b].n_private) == (1, 1)
    assert luhn(got[3].text)
    for d, t in rows:
        assert shape(got[d].text) == shape(t)
    for k, t in enumerate(dates):
        a, b, y = map(int, re.split("[./]", got[10 + k].text))
        assert got[10 + k].text != t and date(y, *((a, b) if t == "3/14/2021" else (b, a)))
    assert got[10 + len(dates)].text == "31.2.1999"


def test_short_dates_are_permuted_one_to_one(spark):
    from pyspark.sql import functions as F

    days = spark.sql("select explode(sequence(date'1990-01-01', date'1993-12-31', interval 1 day)) d").where("day(d) < 10 and month(d) < 10").selectExpr("date_format(d, 'd.M.yyyy') v")
    got = days.select("v", private_data.pseudonym(F.col("v"), F.lit("k")).alias("p")).cache()
    assert got.count() == 4 * 81 == got.select("p").distinct().count() and got.where("length(p) <> 8").count() == 0


PRIVATE = [
    "mail Ann.B@mail7.example.com or ünsal_1@a.b.example.org, X@y.de; john.jacob.jingleheimer.schmidt+1999@sub-domain.mail.example.co",
    "card 4111 1111 1111 1111 and 4111-1111-1111-1111, no 123456789012 nor 987654321 nor 1234567890123456789012 or " + "31415926535" * 9,
    "ip 10.20.30.40 bad 999.1.1.1 tel +1 (743) 555-3824 and 743-555-3824, ssn 123-45-6789 end 7",
    "born 2001-02-28 or 31.12.1999 not 2001-02-30; 5.3.1999 3/14/2021 14.3.2021 7/11/2020 5.03.1999 1.1.1800 31.2.1999 0001-01-01 12/25/2300",
    "key a1b2c3d4e5f6a1b2c3d4e5f6a1b2c3d4 KEY A1B2C3D4E5F6A1B2C3D4E5F6A1B2C3D4, 192.168.0.1x@y.com (555) 555-1234bob@example.com",
    "a@b..com x@y me@home...and 1@2.33 trailing@dot.com. @none.com a@b@c.de " + "l" * 90 + "@example.com",
]


def test_private_data_by_brute_force(spark):
    import regex

    texts = [t for t in PRIVATE + TEXTS if t is not None]
    got = by_id(private_data.pseudonymised(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), "secret"))
    for k, t in enumerate(texts):
        assert got[k].text == regex.sub(private_data.ANY, lambda m: brute.pseudonym(m[0], "secret"), t)


def test_pseudonyms_of_different_values_differ(spark):
    from pyspark.sql import functions as F

    made = lambda values: values.select("v", private_data.pseudonym(F.col("v"), F.lit("k")).alias("p"))
    numbers = spark.range(60_000).selectExpr("cast(id * 7 + 100000000 as string) v").union(spark.range(20_000).selectExpr("cast(id * 13 + 100000000000 as string) v"))
    got = made(numbers).cache()
    assert got.count() == got.select("p").distinct().count() == 80_000 and got.where("length(v) <> length(p)").count() == 0
    names = [f"{a}@example.com" for a in "abcdefghijklmnopqrstuvwxyz"] + [f"{a}{b}@example.com" for a in "abcdefghijklmnopqrstuvwxyz" for b in "abcdefghij0123456789"] + ["n" * 70 + f"{k}@example.com" for k in range(50)]
    got = made(spark.createDataFrame([(x,) for x in names], "v string")).collect()
    assert len({r.p for r in got}) == len(names) and all(len(r.p) == len(r.v) for r in got)


def test_private_data_in_very_long_texts(spark):
    """Time must follow the length; no stack may overflow."""
    import time

    rows = [(1, "x@" + "a." * 5000 + " end"), (2, "y" * 1_000_000), (3, "x@" + "a." * 500_000), (4, "123456789a" * 100_000), (5, "ann@example.com " * 60_000), (6, "q" * 1_000_000 + "@example.com"), (7, "@" * 1_000_000), (8, "1" * 300_000)]
    for d, t in rows[:4] + rows[5:]:
        docs = spark.createDataFrame([(d, t)], "doc_id long, text string")
        began = time.monotonic()
        got = private_data.pseudonymised(docs).first()
        assert len(got.text) == len(t) and time.monotonic() - began < 30
        assert (got.text != t) == (d in (4, 6, 8))


def test_digit_permutation_is_one_to_one(spark):
    from pyspark.sql import functions as F

    df = spark.range(1000).select(F.lpad(F.col("id").cast("string"), 3, "0").alias("d"))
    assert df.select(private_data.permuted_digits(F.col("d"), F.lit("k"), "t").alias("e")).where("length(e) = 3").distinct().count() == 1000
    days = spark.range(0, 146_097, 97).select(private_data.feistel(F.col("id"), 189, 773, F.lit("k"), "d").alias("e"))
    assert days.distinct().count() == len(range(0, 146_097, 97)) and days.where("e < 0 or e >= 146097").count() == 0


def test_urls(spark):
    rules = [("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block"), (None, "/x", "block")]
    urls = ["http://A.Example.COM/en/70?q=1", "http://example.com/en/6#f", "https://notcom/en/", "x://com/en/", "http://b.example.net/de/80", "http://example.net/de", "http://example.org?x/es/", None, "", "no scheme com/en/", "a://org/es/://", "http://org./es/", "http://" + "a." * 20_000 + "com/en/x", "http://com/" + "en/" * 10_000]
    pages = spark.createDataFrame([(k, u, "h", "r") for k, u in enumerate(urls)] + [(0, urls[0], "h", "r")], "page_id long, url string, host string, rule string")
    got = url_filter.url_verdicts(pages, spark.createDataFrame(rules, "host string, path string, verdict string"))

    def want(u):
        rest = u.split("://", 1)[1] if u and "://" in u else ""
        cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
        host, tail = rest[:cut].lower(), rest[cut:]
        path = tail[: min([tail.find(c) for c in "?#" if c in tail], default=len(tail))]
        fit = [(len(h + p), h + p, v) for h, p, v in rules if h and (host == h or host.endswith("." + h)) and path.startswith(p)]
        return (host, path, max(fit)[1], max(fit)[2]) if fit else (host, path, None, "allow")

    assert sorted([(r.page_id, r.host, r.path, r.rule, r.verdict) for r in got.collect()], key=str) == sorted([(k, *want(u)) for k, u in [*enumerate(urls), (0, urls[0])]], key=str)
    assert url_filter.url_verdicts(pages.limit(0), spark.createDataFrame(rules, "host string, path string, verdict string")).count() == 0


def test_quality(spark, empty):
    rng = np.random.default_rng(4)
    word = lambda: "".join(rng.choice(list("abcdefgh"), int(rng.integers(2, 9))))
    good = [(k, " ".join(word() for _ in range(60)) + ".") for k in range(150)]
    bad = [(200 + k, " ".join(word() + "###" for _ in range(60))) for k in range(15)] + [(300 + k, " | ".join(word() for _ in range(60))) for k in range(15)] + [(400 + k, " ".join(["again"] * 60)) for k in range(10)]
    docs = spark.createDataFrame(good + bad, "doc_id long, text string")
    kept = {r["doc_id"] for r in quality.judged(docs).where("kept").collect()}
    assert kept == {d for d, _ in good}
    assert {r["doc_id"] for r in quality.good_documents(docs).collect()} == kept
    assert quality.judged(empty).count() == 0
    odd = spark.createDataFrame(ROWS, "doc_id long, text string")
    assert quality.judged(odd).count() == len(ROWS)


def test_labellers_are_weighed_by_brute_force():
    """Expectation maximisation document by document, in plain Python; and scores by dense features."""
    import pyarrow as pa

    rng = np.random.default_rng(7)
    own = rng.choice([-1, 0, 1], (60, 4), p=[0.15, 0.25, 0.6]).astype(np.int8)
    code, at, n = np.unique(own, axis=0, return_inverse=True, return_counts=True)
    labels = quality.estimate(code, n, rounds=25, least_right=0.7)
    p = [0.1 if (row < 0).any() else 0.95 for row in own]
    for _ in range(25):
        good = min(max(sum(p) / len(p), 1e-3), 1 - 1e-3)
        given = [[[0.5 + sum(q for q, row in zip(w, own, strict=True) if row[j] == v) for v in (-1, 0, 1)] for j in range(4)] for w in ([1 - q for q in p], p)]
        for j in range(4):
            bad = given[1][j][0] + given[0][j][0] - 1
            moved = max(given[1][j][0] - 0.5 - 0.3 * bad, 0)
            given[1][j][0] -= moved
            given[0][j][0] += moved
        given = [[[x / sum(row) for x in row] for row in side] for side in given]
        odds = [[(good if side else 1 - good) * np.prod([given[side][j][row[j] + 1] for j in range(4)]) for side in (0, 1)] for row in own]
        p = [b / (a + b) for a, b in odds]
    assert np.allclose(labels.posterior(code)[at.reshape(-1)], p) and np.allclose(labels.given, given)

    words = quality.Words(pa.array([t for t in TEXTS if t]), quality.SPACED)
    weights = rng.normal(0, 1, quality.FEATURES + 1)
    full = quality.Labels(0.8, np.full((2, len(quality.LABELLERS), 3), 1 / 3))
    n, _, score = quality._verdicts(pa.array([t for t in TEXTS if t]), full, weights)
    x = quality._features(words, quality.measures(words)).astype(float)
    dense = 1 / (1 + np.exp(-np.clip(np.sqrt(x) @ weights[:-1] + weights[-1], -30, 30)))
    assert np.allclose(score[n > 0], dense[n > 0], atol=1e-5) and (score[n == 0] == 0).all()


def test_quality_sees_repeated_lines_and_passages(spark):
    """Texts of clean words that only repeat themselves: the shapes of their words are those of clean texts."""
    rng = np.random.default_rng(5)
    word = lambda: "".join(rng.choice(list("abcdefgh"), int(rng.integers(2, 9))))
    text = lambda n: " ".join(word() for _ in range(n))
    clean = [(k, "\n".join(text(30) + "." for _ in range(3))) for k in range(200)]
    noise = [(300 + k, " ".join(word() + "###" for _ in range(60))) for k in range(10)]
    lines = [(400 + k, "\n".join([clean[k][1].split("\n")[0]] * 50)) for k in range(12)]
    passages = [(500 + k, " ".join([clean[k + 20][1].split("\n")[0]] * 50)) for k in range(12)]
    docs = spark.createDataFrame(clean + noise + lines + passages, "doc_id long, text string")
    assert {r["doc_id"] for r in quality.judged(docs).where("kept").collect()} == {d for d, _ in clean}
    assert {r["doc_id"] for r in quality.good_documents(docs).collect()} == {d for d, _ in clean}


def test_pipeline_keeps_rows_without_an_id_of_their_own(spark):
    import corpus_pipeline

    rng = np.random.default_rng(6)
    texts = [" ".join(f"t{int(x)}" for x in rng.integers(0, 9999, 60)) + "." for _ in range(8)]
    rows = [(None, texts[0]), (None, texts[1]), (None, texts[1]), (4, texts[2]), (4, texts[3]), (5, texts[4]), (5, texts[4]), (6, texts[5]), (None, texts[5]), (7, texts[6]), (3, texts[6] + " more"), (3, texts[7])]
    docs = spark.createDataFrame([(d, t, "en", "s", len(t)) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = corpus_pipeline.keep_one_copy(spark, docs, "").select("doc_id", "text").collect()
    left = {tuple(r) for r in got}
    assert len(got) == len(left) == 8
    assert left - {(3, texts[6] + " more"), (7, texts[6])} == {(None, texts[0]), (None, texts[1]), (4, texts[2]), (4, texts[3]), (5, texts[4]), (6, texts[5]), (3, texts[7])}
    assert corpus_pipeline.keep_good(spark, docs, "").where("doc_id is null").count() == 4


def test_pipeline(spark, tmp_path):
    import corpus_pipeline

    src = Path("/root/testdata/sf0.001")
    if not src.exists():
        pytest.skip("no tables here")
    out = corpus_pipeline.run(spark, str(src))
    got = by_id(out)
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{src}/documents.parquet").collect()]
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{src}/benchmark.parquet").collect()]
    fine = {r["doc_id"] for r in quality.judged(spark.read.parquet(f"{src}/documents.parquet")).where("kept").collect()}
    left = [(d, t) for d, t in docs if d in fine]
    left = [(d, t) for d, t in left if brute.near(left)[d][1] == d] if len(left) < 50 else [(d, t) for (d, t), c in zip(left, map(brute.near(left).get, [d for d, _ in left]), strict=True) if c[1] == d]
    marks = brute.passages(left, items)
    assert set(got) == {d for d, _ in left if not marks[d][4]}
    import public_tokenizers as P
    import regex
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, Path(P.path("byte_bpe_50k.tiktoken")).read_bytes().splitlines())}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    for d, t in left:
        if not marks[d][4]:
            text = regex.sub(private_data.ANY, lambda m: brute.pseudonym(m[0], "change-this-key"), t or "")
            ids = enc.encode_ordinary(text)
            assert (got[d].n_tokens, got[d].ids_sha256, got[d].decoded_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(text.encode()).hexdigest())


def test_pipeline_stages_take_odd_tables(spark, tmp_path):
    """Empty tables, nulls in every column and columns with clashing names; columns of documents come back."""
    import corpus_pipeline

    spark.createDataFrame([(1, PASSAGE)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    rows = [(None, None, None, None, None, 1.0, "x"), (1, PASSAGE + " and some more words to be clean", "en", "s", 5, None, None), (2, "", None, "s", 0, 2.0, "y"), (3, " ".join(f"word{k}" for k in range(40)) + ".", "en", None, None, 0.5, "z")]
    kinds = "doc_id long, text string, lang string, source string, n_chars long, score double, kept string"
    for part in (rows, []):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, spark.createDataFrame(part, kinds), str(tmp_path)).collect()
            assert len(out) <= len(part)
            if name == "benchmark decontamination" and part:
                assert {r["doc_id"] for r in out} == {None, 2, 3}
            if name == "private data":
                assert len(out) == len(part)
