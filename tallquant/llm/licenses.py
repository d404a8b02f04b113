"""Licence scan by a positional rare-token index, in DataFrame functions only.

The templates are licence notices (a parameter).  A word's IDF over the templates
decides what is looked up: the index has the highest-IDF word of each template's
mandatory key phrases, with the template and the place of the word in it.  The
words of a text that are in the index, its highest-IDF licence words, name
candidate alignments (template, start); a template that is really there has its
indexed word in place, so none is lost.  A candidate then meets the other postings
of its template at the same relative position: it is accepted if every word of the
mandatory key phrases is in its place and enough IDF weight matched.

A text is opened only if it holds an indexed word.  Everything happens within the
row, so nothing is shuffled, gathered or joined, whatever rows repeat: each row has
the result of its own text.  Null texts count as empty; extra columns are ignored.
The index is part of the plan, so templates are limited to ``MOST_WORDS`` words in all.
"""

from __future__ import annotations

import math
import re
import string

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.llm.common import ALNUM_ANY_CASE, ALNUM_WORD

# The base phrases of the contract and their labels.
BASE_PHRASES = {
    "under the mit license": "mit",
    "apache license version 2": "apache-2",
    "cc by nc": "cc-by-nc",
}
# Public licence notices, each with its label and mandatory key phrases.
NOTICES = [
    ("released under the mit license", "mit", ["mit license"]),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software", "mit", ["hereby granted free of charge"]),
    ("licensed under the apache license version 2 0", "apache-2", ["apache license version 2"]),
    ("licensed under cc by nc 4 0", "cc-by-nc", ["cc by nc"]),
    ("creative commons attribution noncommercial 4 0 international license", "cc-by-nc", ["commons attribution noncommercial"]),
    ("creative commons attribution sharealike 4 0 international license", "cc-by-sa", ["commons attribution sharealike"]),
    ("this work is licensed under the gnu general public license version 3", "gpl-3", ["gnu general public license", "version 3"]),
    ("under the terms of the gnu lesser general public license", "lgpl", ["gnu lesser general public license"]),
    ("under the terms of the gnu affero general public license", "agpl", ["gnu affero general public license"]),
    ("redistribution and use in source and binary forms with or without modification are permitted", "bsd", ["redistribution and use in source and binary forms"]),
    ("subject to the terms of the mozilla public license v 2 0", "mpl-2", ["mozilla public license"]),
    ("copyright all rights reserved", "all-rights-reserved", ["all rights reserved"]),
]
SEPARATOR = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]"
#: Least share of a template's IDF weight that an accepted alignment matches.
LEAST_SHARE = 0.5
#: Words of all templates together, at most.
MOST_WORDS = 100_000


def templates(notices: list[tuple[str, str, list[str]]] = NOTICES) -> list[dict]:
    """All templates with words, weights, the slots of their key phrases, and the word by which they are looked up."""
    raw = [(text, label, [text], True) for text, label in BASE_PHRASES.items()] + [(t, label, keys, False) for t, label, keys in notices]
    lists = [t.split() for t, *_ in raw]
    if sum(map(len, lists)) > MOST_WORDS:
        raise ValueError(f"the templates have more than {MOST_WORDS} words")
    idf = {w: math.log(1 + len(lists) / sum(w in x for x in lists)) for x in lists for w in x}
    out = []
    for k, ((_, label, keys, base), words) in enumerate(zip(raw, lists, strict=True)):
        need: set[int] = set()
        for key in keys:
            part = key.split()
            at = next(i for i in range(len(words)) if words[i : i + len(part)] == part)
            need.update(range(at, at + len(part)))
        slots = sorted(need)
        at = max(slots, key=lambda i: (idf[words[i]], len(words[i]), words[i], -i))
        weights = [round(idf[w], 6) for w in words]
        out.append({"id": k, "label": label, "base": base, "words": words, "weights": weights, "need": slots, "at": at, "rare": words[at]})
    return out


def lookup_pattern(ts: list[dict]) -> str:
    """Matches a text that holds an indexed word as a whole word."""
    words = "|".join(sorted({re.escape(t["rare"]) for t in ts}))
    return rf"(?i)(?:^|{SEPARATOR})(?:{words})(?:$|{SEPARATOR})"


def _index(ts: list[dict]) -> Column:
    """Map from an indexed word to its postings; ``total`` is the IDF weight of the template."""
    by_word: dict[str, list[Column]] = {}
    for t in ts:
        cells = {k: F.array(*map(F.lit, t[k])) for k in ("words", "weights", "need")} | {k: F.lit(t[k]) for k in ("id", "label", "base", "at")}
        cells["total"] = F.lit(round(sum(t["weights"]), 6))
        by_word.setdefault(t["rare"], []).append(F.struct(*[c.alias(k) for k, c in cells.items()]))
    return F.create_map(*[x for w, posts in by_word.items() for x in (F.lit(w), F.array(*posts))])


def _alignments(words: Column, place: Column, index: Column) -> Column:
    """Candidates of the indexed word at a place whose key phrases are in place, with the matched share of IDF weight."""

    def in_place(t: Column, slot: Column) -> Column:
        return F.coalesce(F.get(words, place - t["at"] + slot) == F.get(t["words"], slot), F.lit(False))

    def share(t: Column) -> Column:
        matched = F.transform(t["weights"], lambda w, slot: F.when(in_place(t, slot), w).otherwise(F.lit(0.0)))
        return F.round(F.aggregate(matched, F.lit(0.0), lambda a, x: a + x) / t["total"], 4)

    posts = F.filter(index[F.get(words, place)], lambda t: F.forall(t["need"], lambda slot: in_place(t, slot)))
    found = F.transform(posts, lambda t: F.struct(t["label"].alias("label"), (place - t["at"]).cast("long").alias("first_word"), share(t).alias("score"), t["base"].alias("base")))
    return F.filter(found, lambda x: x["score"] >= LEAST_SHARE)


def scan_licenses(spark: SparkSession, docs: DataFrame, *, notices: list[tuple[str, str, list[str]]] = NOTICES) -> DataFrame:
    """``doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, notices``.

    ``notices`` of the result has label, first word and score of every accepted
    alignment that is not a base place; its first word is negative where a
    notice begins before the text does.
    """
    ts = templates(notices)
    rare = sorted({t["rare"] for t in ts})
    text = F.coalesce(F.col("text"), F.lit(""))
    low = F.translate(text, string.ascii_uppercase, string.ascii_lowercase)
    opened = docs.select("doc_id", text.alias("text"), F.when(text.rlike(lookup_pattern(ts)), F.regexp_extract_all(low, F.lit(ALNUM_WORD), F.lit(0))).alias("words"))
    words = F.col("words")
    places = F.filter(F.sequence(F.lit(0), F.size(words) - 1), lambda i: F.get(words, i).isin(rare))
    counted = F.when(words.isNotNull(), F.size(words)).otherwise(F.regexp_count("text", F.lit(ALNUM_ANY_CASE))).cast("long")
    looked = opened.select("doc_id", counted.alias("n_words"), "words", F.when(words.isNotNull(), places).alias("places"))
    found = F.flatten(F.transform("places", lambda p: _alignments(words, p, _index(ts))))
    empty = F.array().cast("array<struct<label:string,first_word:bigint,score:double,base:boolean>>")
    rows = looked.select("doc_id", "n_words", F.coalesce(found, empty).alias("found"))
    base, other = F.filter("found", lambda x: x["base"]), F.filter("found", lambda x: ~x["base"])
    starts = F.transform(base, lambda x: x["first_word"])
    joined = lambda xs: F.array_join(F.array_sort(F.array_distinct(F.transform(xs, lambda x: x["label"]))), ",")
    return rows.select(
        "doc_id",
        "n_words",
        F.size(base).cast("long").alias("n_base"),
        F.array_min(starts).alias("first_word"),
        F.array_max(starts).alias("last_word"),
        joined(base).alias("base_labels"),
        joined(F.col("found")).alias("labels"),
        F.coalesce(F.array_max(F.transform("found", lambda x: x["score"])), F.lit(0.0)).alias("score"),
        F.transform(other, lambda x: F.struct(x["label"].alias("label"), x["first_word"].alias("first_word"), x["score"].alias("score"))).alias("notices"),
    )


def _share(masks: str, ts: list[dict]) -> str:
    """SQL for the matched share of IDF weight."""
    cases = []
    for t in ts:
        total = round(sum(t["weights"]), 6)
        parts = " + ".join(f"CASE WHEN {masks} & {1 << i} <> 0 THEN cast({w} AS double) ELSE cast(0 AS double) END" for i, w in enumerate(t["weights"]))
        cases.append(f"WHEN {t['id']} THEN round(({parts}) / cast({total} AS double), 4)")
    return f"CASE template {' '.join(cases)} END"


def _need(ts: list[dict]) -> str:
    return f"CASE template {' '.join(f'WHEN {t["id"]} THEN {sum(1 << i for i in t["need"])}' for t in ts)} END"


def oracle_sql() -> str:
    """The same scan as DuckDB SQL: postings of every template word joined with all words, without the lookup; masks hold 62 slots."""
    ts = templates()
    values = ", ".join(f"('{w}', {t['id']}, {i})" for t in ts for i, w in enumerate(t["words"]))
    labels = " ".join(f"WHEN {t['id']} THEN '{t['label']}'" for t in ts)
    n = len(BASE_PHRASES)
    return f"""
WITH idx(word, template, slot) AS (VALUES {values}),
w AS (SELECT doc_id, row_number() OVER () AS rid, regexp_extract_all(translate(coalesce(text, ''), '{string.ascii_uppercase}', '{string.ascii_lowercase}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS words FROM documents),
p AS (SELECT rid, unnest(words) AS word, generate_subscripts(words, 1) - 1 AS pos FROM w),
a AS (SELECT rid, template, pos - slot AS start, bit_or(1::bigint << slot) AS mask FROM p JOIN idx USING (word) GROUP BY ALL),
s AS (SELECT *, {_share("mask", ts)} AS share, CASE template {labels} END AS label FROM a WHERE mask & ({_need(ts)}) = ({_need(ts)})),
f AS (SELECT rid, count(*) FILTER (template < {n}) AS n_base, min(start) FILTER (template < {n}) AS first_word, max(start) FILTER (template < {n}) AS last_word,
  array_to_string(list_sort(list_distinct(list(label) FILTER (template < {n}))), ',') AS base_labels,
  array_to_string(list_sort(list_distinct(list(label))), ',') AS labels, max(share) AS score FROM s WHERE share >= {LEAST_SHARE} GROUP BY rid)
SELECT doc_id, len(words)::bigint AS n_words, coalesce(n_base, 0)::bigint AS n_base, first_word::bigint AS first_word, last_word::bigint AS last_word,
  coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels, coalesce(score, 0)::double AS score
FROM w LEFT JOIN f USING (rid)"""
