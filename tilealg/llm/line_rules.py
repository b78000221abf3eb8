"""Line-first cleaning with SQL functions only: lines that break a rule go, then texts that lose too much go.

Rules for a line: *punctuation* (symbols and marks of shouting, by its words), *navigation* (cells or crumbs between
separators) and *boilerplate* (stock phrases of web pages).  A document is rejected if fewer than ``least`` of its
word characters are left.  Beside that, whole-text figures are kept: words, symbols, repeated lines, and words in
windows of five that stand in the text twice or more.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPACES = " \t\n\x0b\x0c\r"
SPACE_RUN = r"[\x20\x09-\x0D]+"
SYMBOLS = "#*$%&|<>"
WINDOW = 5

# Stock phrases of web pages.
BOILERPLATE = (
    "accept cookies", "all rights reserved", "click here", "cookie policy", "enable javascript", "follow us on", "lorem ipsum", "privacy policy",
    "read more", "share this", "sign up", "skip to content", "subscribe to", "terms of service", "terms of use", "log in",
)


def _without(text: Column, chars: str) -> Column:
    return F.translate(text, chars, "")


def word_list(text: Column) -> Column:
    bare = F.btrim(text, F.lit(SPACES))
    return F.when(bare == "", F.expr("cast(array() as array<string>)")).otherwise(F.split(bare, SPACE_RUN))


def repeated_window_words(words: Column) -> Column:
    """Words that lie in a window of five words whose like stands in the list again; windows are compared by 64-bit hashes."""
    hashes = F.transform(words, lambda w: F.xxhash64(w))
    n = F.size(words)

    def counted(pair: Column) -> Column:
        """pair: word hashes h; windows w."""
        return F.transform(F.array(F.sort_array(F.transform(pair, lambda x, i: F.struct(x.alias("x"), i.alias("i"))))), lambda s: F.aggregate(
            F.sort_array(F.transform(F.filter(F.transform(s, lambda e, k: F.struct(
                e["i"].alias("i"),
                ((F.coalesce(F.try_element_at(s, k + 2)["x"] == e["x"], F.lit(False))) | F.when(k > 0, s[k - 1]["x"] == e["x"]).otherwise(False)).alias("twice"),
            )), lambda e: e["twice"]), lambda e: e["i"])),
            F.struct(F.lit(-WINDOW).alias("last"), F.lit(0).cast("long").alias("total")),
            lambda acc, i: F.struct(i.alias("last"), (acc["total"] + F.least(F.lit(WINDOW), i - acc["last"])).alias("total")),
            lambda acc: acc["total"],
        ))[0]

    runs = F.transform(F.array(hashes), lambda h: F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*[h[i + k] for k in range(WINDOW)])))[0]
    return F.when(n < WINDOW, F.lit(0).cast("long")).otherwise(F.transform(F.array(runs), lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0).cast("long")).otherwise(counted(w)))[0])


def keeps_line(line: Column) -> Column:
    """Whether a line passes all rules."""
    words = F.length(line) - F.length(F.replace(line, F.lit(" "), F.lit(""))) + 1
    marks = F.length(line) - F.length(_without(line, SYMBOLS + "!^~_={}"))
    bars = F.length(line) - F.length(_without(line, "|>»›•"))
    punctuation = marks * 10 > words * 3
    navigation = (bars >= 2) & (bars * 4 > words)
    return ~(punctuation | navigation | line.rlike("(?i)" + "|".join(BOILERPLATE)))


def cleaned_lines(docs: DataFrame, least: float = 0.5, least_words: int = 10, most_repeated: int = 20) -> DataFrame:
    """Figures, cleaned text and verdict for each row of ``docs`` (doc_id, text).

    Null texts count as empty: no words, base_failed.  ``most_repeated``: per cent of words in repeated windows.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    docs = docs.withColumn("words", word_list(F.col("text"))).withColumn("lines", F.filter(F.split("text", "\n", -1), lambda x: F.btrim(x, F.lit(SPACES)) != ""))
    docs = docs.select(
        "doc_id",
        F.size("words").cast("long").alias("n_words"),
        F.length(_without(F.col("text"), SPACES)).cast("long").alias("word_chars"),
        (F.length("text") - F.length(_without(F.col("text"), SYMBOLS))).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        repeated_window_words(F.col("words")).alias("n_repeat_words"),
        F.size("lines").alias("n_lines"),
        F.filter("lines", keeps_line).alias("left"),
    )
    docs = docs.withColumn("clean_text", F.array_join("left", "\n"))
    docs = docs.withColumn("clean_chars", F.length(_without(F.col("clean_text"), SPACES)).cast("long"))
    failed = (F.col("n_words") < least_words) | (100 * F.col("n_repeat_words") > most_repeated * F.col("n_words"))
    return docs.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), (~failed & (F.col("clean_chars") >= least * F.col("word_chars"))).alias("kept"),
        (F.col("n_lines") - F.size("left")).cast("long").alias("n_lines_removed"), "clean_chars", "clean_text",
    )


def lines_sql(least: float = 0.5, least_words: int = 10, most_repeated: int = 20) -> str:
    """The figures and verdicts as SQL for DuckDB."""
    spaces, space_run = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)", r"[\x20\x09-\x0D]"
    bare = lambda x, chars: f"length({x}) - length(translate({x}, {chars}, ''))"
    return rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS w, list_filter(string_split(text, chr(10)), lambda x: trim(x, {spaces}) <> '') AS lines FROM d),
r AS (SELECT doc_id, unnest(range(len(w) - {WINDOW - 1})) AS i, unnest(list_transform(range(1, len(w) - {WINDOW - 2}), lambda i: array_to_string(w[i:i + {WINDOW - 1}], ' '))) AS x FROM w WHERE len(w) >= {WINDOW}),
m AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, x) AS n FROM r) WHERE n > 1),
u AS (SELECT doc_id, count(DISTINCT spot) AS n_repeat_words FROM (SELECT doc_id, unnest(range(i, i + {WINDOW})) AS spot FROM m) GROUP BY doc_id),
l AS (SELECT doc_id, line, length(line) - length(replace(line, ' ', '')) + 1 AS n, {bare("line", f"'{SYMBOLS}!^~_={{}}'")} AS marks, {bare("line", "'|>»›•'")} AS bars FROM (SELECT doc_id, unnest(lines) AS line FROM w)),
k AS (SELECT doc_id, count(*) AS n_lines, count(*) FILTER (good) AS n_good, CAST(coalesce(sum(length(regexp_replace(line, '{space_run}', '', 'g'))) FILTER (good), 0) AS BIGINT) AS clean_chars
  FROM (SELECT doc_id, line, NOT (marks * 10 > n * 3 OR (bars >= 2 AND bars * 4 > n) OR regexp_matches(line, '(?i){"|".join(BOILERPLATE)}')) AS good FROM l) GROUP BY doc_id),
f AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, length(regexp_replace(text, '{space_run}', '', 'g')) AS word_chars, {bare("text", f"'{SYMBOLS}'")} AS n_symbols, CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
  coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(n_lines - n_good, 0) AS n_lines_removed, coalesce(clean_chars, 0) AS clean_chars FROM w LEFT JOIN u USING (doc_id) LEFT JOIN k USING (doc_id))
SELECT *, n_words < {least_words} OR 100 * n_repeat_words > {most_repeated} * n_words AS base_failed,
  NOT (n_words < {least_words} OR 100 * n_repeat_words > {most_repeated} * n_words) AND clean_chars >= {least} * word_chars AS kept FROM f
"""
