"""Licence scan with a positional index of rare template words; SQL functions only.

Every template is a sequence of words with a label and a key phrase that must stand in it word for word.  The number
of documents that hold each template word is counted over all documents (the table has a row for each template
word, so its size is bounded by the templates).  The index lists, for each template, the places of its ``RARE``
highest-IDF key words.  A document's licence words are looked up with their positions; each posting gives a start of a
template (position less the word's place in it), and the starts of a template's postings are intersected.  What is
left is verified: the key phrase must be complete there, and the template's other words are compared by relative
position, weighed by IDF.  A start counts if the agreement reaches ``least``.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

RARE = 2
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BORDER = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


@dataclass(frozen=True)
class Template:
    label: str
    words: tuple[str, ...]
    key: tuple[str, ...]
    base: bool = False

    @property
    def key_at(self) -> int:
        n = len(self.key)
        return next(i for i in range(len(self.words) - n + 1) if self.words[i : i + n] == self.key)


def template(label: str, words: str, key: str | None = None, base: bool = False) -> Template:
    return Template(label, tuple(words.split()), tuple((key or words).split()), base)


# Base phrases first, then templates of the method's own, as published licence notices word them.
TEMPLATES = (
    template("mit", "under the mit license", base=True),
    template("apache-2", "apache license version 2", base=True),
    template("cc-by-nc", "cc by nc", base=True),
    template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", "permission is hereby granted free of charge"),
    template("apache-2", "licensed under the apache license version 2 0", "apache license"),
    template("cc-by-nc", "creative commons attribution noncommercial", "creative commons attribution noncommercial"),
    template("cc-by", "licensed under cc by 4 0", "cc by 4"),
    template("gpl", "this work is licensed under the gnu general public license", "gnu general public license"),
    template("lgpl", "under the terms of the gnu lesser general public license", "gnu lesser general public license"),
    template("agpl", "under the terms of the gnu affero general public license", "gnu affero general public license"),
    template("mpl", "subject to the terms of the mozilla public license", "mozilla public license"),
    template("mit", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", "the above copyright notice and this permission notice shall be included"),
    template("apache-2", "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied", "unless required by applicable law or agreed to in writing software"),
    template("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version", "gnu general public license as published by the free software foundation"),
    template("lgpl", "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation", "gnu lesser general public license as published by the free software foundation"),
    template("mpl", "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at", "subject to the terms of the mozilla public license"),
    template("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    template("bsd", "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution", "redistributions in binary form must reproduce the above copyright notice"),
    template("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software", "in no event will the authors be held liable for any damages"),
    template("boost", "boost software license version 1 0", "boost software license"),
    template("isc", "permission to use copy modify and or distribute this software for any purpose", "permission to use copy modify"),
    template("unlicense", "this is free and unencumbered software released into the public domain", "unencumbered software released into the public domain"),
)


def spaced_words(text: Column) -> Column:
    """The words of a text as written, one space between them and none at the ends."""
    return F.trim(F.regexp_replace(F.coalesce(text.cast("string"), F.lit("")), BORDER, " "))


def document_counts(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES) -> tuple[int, dict[str, int]]:
    """Documents in all, and for each template word those that hold it."""
    vocabulary = sorted({w for t in templates for w in t.words})
    held = F.array_intersect(F.split(F.translate(spaced_words(F.col("text")), UPPER, LOWER), " "), F.array(*map(F.lit, vocabulary)))
    rows = docs.select(F.explode(F.concat(held, F.array(F.lit("")))).alias("word")).groupBy("word").count().collect()
    found = {r["word"]: r["count"] for r in rows}
    return found.pop("", 0), found


def _weights(n: int, found: dict[str, int], words: tuple[str, ...]) -> list[float]:
    return [round(math.log((n + 1) / (found.get(w, 0) + 0.5)), 6) for w in words]


def licences(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES, least: float = 0.8) -> DataFrame:
    """For each row of ``docs`` (doc_id, text): n_words, places of base phrases, labels and score.

    n_base, first_word, last_word: places of base templates (0 and null if there are none); base_labels and labels:
    distinct, sorted, comma-joined; score: the best agreement of a template that counts.  Null texts have no words.
    """
    n, found = document_counts(docs, templates)
    weights = [_weights(n, found, t.words) for t in templates]
    rare = []
    for t, weight in zip(templates, weights, strict=True):
        inside = sorted(range(t.key_at, t.key_at + len(t.key)), key=lambda i: (-weight[i], i))  # noqa: B023
        rare.append(sorted(inside[:RARE]))
    names = sorted({t.words[i] for t, places in zip(templates, rare, strict=True) for i in places})
    told = docs.select(F.col("doc_id").cast("long").alias("doc_id"), spaced_words(F.col("text")).alias("plain"))
    told = told.select("doc_id", F.when(F.col("plain") == "", 0).otherwise(F.length("plain") - F.length(F.replace("plain", F.lit(" "), F.lit(""))) + 1).cast("long").alias("n_words"), F.when(F.col("plain").rlike(r"(?i)(?:^| )(?:" + "|".join(names) + r")(?: |$)"), F.split(F.translate("plain", UPPER, LOWER), " ")).alias("words"))
    seen = F.filter(F.transform("words", lambda w, i: F.struct(i.alias("at"), w.alias("word"))), lambda x: x["word"].isin(names))
    told = told.withColumn("rare", seen)

    def word(at: Column) -> Column:
        """The document's word at a place; null before its start and past its end."""
        return F.try_element_at("words", F.when(at >= 0, at + 1).otherwise(F.lit(2**31 - 1)))

    def starts(t: Template, weight: list[float], places: list[int]) -> Column:
        """Structs (at, score, label, base) of the template's places."""
        from_posting = lambda i: F.transform(F.filter("rare", lambda x: x["word"] == t.words[i]), lambda x: x["at"] - i)
        met = from_posting(places[0])
        for i in places[1:]:
            met = F.array_intersect(met, from_posting(i))
        own, key = (F.split(F.lit(" ".join(x)), " ") for x in (t.words, t.key))
        holds = lambda s: F.when(s + t.key_at >= 0, F.slice("words", s + t.key_at + 1, F.lit(len(t.key))) == key).otherwise(False)
        good = F.filter(met, holds)
        if t.key == t.words:
            agreement = lambda s: F.lit(1.0)
        else:
            value = F.split(F.lit(" ".join(map(repr, weight))), " ")
            total = sum(weight) or 1.0
            agreement = lambda s: F.least(F.lit(1.0), F.round(F.aggregate(F.sequence(F.lit(0), F.lit(len(weight) - 1)), F.lit(0.0), lambda a, i: a + F.when(word(s + i) == own[i], value[i].cast("double")).otherwise(0.0)) / total, 9))
        told = F.transform(good, lambda s: F.struct(s.cast("long").alias("at"), agreement(s).alias("score"), F.lit(t.label).alias("label"), F.lit(t.base).alias("base")))
        return told if t.base else F.filter(told, lambda g: g["score"] >= least)

    none = F.expr("cast(array() as array<struct<at:bigint,score:double,label:string,base:boolean>>)")
    everything = F.when(F.size("rare") > 0, F.concat(*[starts(*x) for x in zip(templates, weights, rare, strict=True)]))
    told = told.withColumn("found", F.coalesce(everything, none)).drop("words", "rare")
    base = F.filter("found", lambda g: g["base"])
    labels = lambda x: F.concat_ws(",", F.array_sort(F.array_distinct(F.transform(x, lambda g: g["label"]))))
    at = F.transform(base, lambda g: g["at"])
    return told.select(
        "doc_id", "n_words", F.size(base).cast("long").alias("n_base"), F.array_min(at).alias("first_word"), F.array_max(at).alias("last_word"), labels(base).alias("base_labels"), labels("found").alias("labels"),
        F.coalesce(F.array_max(F.transform("found", lambda g: g["score"])), F.lit(0.0)).alias("score"),
    )


def licence_sql(templates: tuple[Template, ...] = TEMPLATES, least: float = 0.8) -> str:
    """The same rows as flat joins for DuckDB: every word of a template against every word of a document, without index."""
    rows = ", ".join(f"({k}, '{t.label}', {str(t.base).lower()}, {i}, '{w}', {str(t.key_at <= i < t.key_at + len(t.key)).lower()}, {str(t.key == t.words).lower()}, {len(t.key)})" for k, t in enumerate(templates) for i, w in enumerate(t.words))
    return rf"""
WITH t(t, label, base, place, word, keyed, whole, n_key) AS (VALUES {rows}),
d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
p AS MATERIALIZED (SELECT doc_id, spot, word FROM (SELECT doc_id, unnest(range(len(w))) AS spot, unnest(w) AS word FROM d) WHERE word IN (SELECT word FROM t)),
i AS (SELECT word, round(ln(((SELECT count(*) FROM documents) + 1) / (coalesce(n, 0) + 0.5)), 6) AS idf FROM (SELECT DISTINCT word FROM t) LEFT JOIN (SELECT word, count(DISTINCT doc_id) AS n FROM p GROUP BY word) USING (word)),
s AS (SELECT t, sum(idf) AS total FROM t JOIN i USING (word) GROUP BY t),
f AS (SELECT doc_id, t, spot - place AS spot, any_value(label) AS label, any_value(base) AS base, CASE WHEN any_value(whole) THEN 1.0 ELSE least(1.0, round(sum(idf) / any_value(total), 9)) END AS score
  FROM p JOIN t USING (word) JOIN i USING (word) JOIN s USING (t) GROUP BY doc_id, t, spot - place HAVING count(*) FILTER (keyed) = any_value(n_key)),
g AS (SELECT doc_id, count(*) FILTER (base) AS n_base, min(spot) FILTER (base) AS first_word, max(spot) FILTER (base) AS last_word,
  string_agg(DISTINCT label, ',' ORDER BY label) FILTER (base) AS base_labels, string_agg(DISTINCT label, ',' ORDER BY label) AS labels, max(score) AS score FROM f WHERE base OR score >= {least} GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_base, 0) AS n_base, CAST(first_word AS BIGINT) AS first_word, CAST(last_word AS BIGINT) AS last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels,
  CAST(coalesce(score, 0) AS DOUBLE) AS score FROM d LEFT JOIN g USING (doc_id)
"""
