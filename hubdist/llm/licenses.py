"""Licence scans by a positional index of rare tokens, in DataFrame functions only.

Document frequencies of the licence words over the whole corpus give their IDF.
In each file the words of highest IDF of every template are looked up: if its key
phrase stands there, they are in the file. An occurrence at word p of a file and
q of a template posts the start p - q, and the posted starts of a template's words
are intersected. At what is left the file's words are laid beside the template's;
the key phrase must stand there in full, and the share of agreeing words is the
score.
"""

from __future__ import annotations

import math
import string
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed value: what parts words once A-Z are folded; here with A-Z as word characters.
PARTS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


@dataclass(frozen=True)
class Template:
    """A label's wording; ``key`` is the phrase in it that must be there."""

    label: str
    words: str
    key: str
    base: bool = False


RARE = 2  # words of highest IDF whose postings are intersected

#: Base phrases first, then longer wordings of the method's own.
TEMPLATES = (
    Template("mit", "under the mit license", "under the mit license", True),
    Template("apache-2", "apache license version 2", "apache license version 2", True),
    Template("cc-by-nc", "cc by nc", "cc by nc", True),
    Template("gpl-3", "this work is licensed under the gnu general public license version 3", "gnu general public license version 3"),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    Template("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0", "mozilla public license"),
    Template("all-rights-reserved", "all rights reserved", "all rights reserved"),
)


def low(word: Column) -> Column:
    return F.translate(word, string.ascii_uppercase, string.ascii_lowercase)


def file_words(text: Column) -> tuple[Column, Column]:
    """Words of a text as written (with an empty one at either end where a parting stands there), and the number of leading empties."""
    parts = F.split(F.coalesce(text, F.lit("")), PARTS, -1)
    return parts, F.when(parts[0] == "", 1).otherwise(0)


def word_frequencies(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES) -> tuple[dict[str, int], int]:
    """Documents that hold each licence word, and all documents, in one pass; as many rows as the templates have words, and one."""
    vocabulary = sorted({w for t in templates for w in t.words.split()})
    words = F.array_intersect(F.transform(file_words(F.col("text"))[0], low), F.array(*map(F.lit, vocabulary)))
    held = docs.select(F.explode(F.concat(F.array(F.lit("")), words)).alias("w"))  # the empty word stands for the document
    df = {r[0]: r[1] for r in held.groupBy("w").count().collect()}
    n = df.pop("", 0)
    return dict.fromkeys(vocabulary, 0) | df, n


def anchors(df: dict[str, int], n: int, templates: tuple[Template, ...] = TEMPLATES) -> list[tuple[Template, list[tuple[str, int, float]]]]:
    """Per template: its key phrase's words of highest IDF, rarest first, each with its place in the template and its IDF."""
    out = []
    for t in templates:
        key, first = t.key.split(), key_place(t)
        best = sorted(range(len(key)), key=lambda i: (df[key[i]], i))[:RARE]
        out.append((t, [(key[k], first + k, math.log((n + 1) / (df[key[k]] + 1))) for k in best]))
    return out


def key_place(t: Template) -> int:
    """Place of the key phrase's first word in the template."""
    words, key = t.words.split(), t.key.split()
    return next(i for i in range(len(words)) if words[i : i + len(key)] == key)


def _hits(no: int, t: Template, rare: list[tuple[str, int, float]]) -> Column:
    """Places of the template among the postings ``at`` (w, i) of a file's words ``p``."""
    words, first = t.words.split(), key_place(t)
    last = first + len(t.key.split())

    def starts(word: str, q: int) -> Column:
        return F.transform(F.filter("at", lambda x: x.w == word), lambda x: x.i - q)

    def beside(start: Column) -> Column:
        begin = F.greatest(start, F.lit(0))
        return F.struct(start.alias("start"), begin.alias("begin"), F.transform(F.slice("p", begin + 1, F.lit(len(words))), low).alias("near"))

    def stands(x: Column, k: int) -> Column:
        return (x.start + k >= 0) & F.coalesce(F.get(x.near, x.start - x.begin + k) == F.lit(words[k]), F.lit(False))

    def hit(x: Column) -> Column:
        agree = sum((F.when(stands(x, k), 1).otherwise(0) for k in range(len(words))), F.lit(0))
        return F.struct(F.lit(no).alias("template"), F.lit(t.label).alias("label"), F.lit(t.base).alias("base"), (x.start - F.col("lead")).cast("long").alias("start"), (agree / F.lit(float(len(words)))).alias("score"))

    common = reduce(F.array_intersect, [starts(w, q) for w, q, _ in rare])
    whole = F.filter(F.transform(common, beside), lambda x: reduce(lambda a, b: a & b, [stands(x, k) for k in range(first, last)]))
    return F.transform(whole, hit)


def places(docs: DataFrame, index: list[tuple[Template, list[tuple[str, int, float]]]]) -> DataFrame:
    """(doc_id, n_words, hits) of every row; hits: {template, label, base, start, score} for each place where a key phrase stands.

    Null text is empty. Start is the place of the template's first word and may lie
    before the text if its key phrase stands near the beginning.
    """
    parts, lead = file_words(F.col("text"))
    listed = lambda words: F.array(*[F.lit(w) for w in sorted(words)])
    rarest = listed({rare[0][0] for _, rare in index})
    posted = listed({w for _, rare in index for w, *_ in rare})
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), parts.alias("p"), lead.alias("lead"))
    n = F.size("p") - F.col("lead") - F.when((F.size("p") > 1) & (F.element_at("p", -1) == ""), 1).otherwise(0)
    at = F.filter(F.transform("p", lambda w, i: F.struct(low(w).alias("w"), i.alias("i"))), lambda x: F.array_contains(posted, x.w))
    some = F.arrays_overlap(F.transform("p", low), rarest)  # without its rarest word no key phrase stands
    rows = rows.withColumn("at", F.when(some, at))
    hits = F.concat(*[_hits(no, t, rare) for no, (t, rare) in enumerate(index)])
    none = F.array().cast("array<struct<template:int,label:string,base:boolean,start:bigint,score:double>>")
    return rows.select("doc_id", n.cast("long").alias("n_words"), F.when(F.size("at") > 0, hits).otherwise(none).alias("hits"))


def licenses(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES, least: float = 0.5) -> DataFrame:
    """One row per document: n_words, base places and labels, all labels and the best score (0 without any).

    A label of the method's own needs a score of ``least`` besides its key phrase.
    Empty tables give no rows; null ids and repeated rows stay as they are.
    """
    found = places(docs, anchors(*word_frequencies(docs, templates), templates))
    good = F.filter("hits", lambda h: h.base | (h.score >= least))
    base = F.filter("hits", lambda h: h.base)
    starts = F.transform(base, lambda h: h.start)
    labels = lambda a: F.array_join(F.array_sort(F.array_distinct(F.transform(a, lambda h: h.label))), ",")
    return found.select(
        "doc_id", "n_words", F.size(base).cast("long").alias("n_base"), F.array_min(starts).alias("first_word"), F.array_max(starts).alias("last_word"),
        labels(base).alias("base_labels"), labels(good).alias("labels"), F.coalesce(F.array_max(F.transform(good, lambda h: h.score)), F.lit(0.0)).alias("score"),
    )


def licenses_sql(templates: tuple[Template, ...] = TEMPLATES, least: float = 0.5) -> str:
    """The same result for DuckDB by trying every template at every word."""
    arms = []
    for no, t in enumerate(templates):
        words, key = t.words.split(), t.key.split()
        first = next(i for i in range(len(words)) if words[i : i + len(key)] == key)
        same = " + ".join(f"coalesce((w[i + {k - first}] = '{x}' and i + {k - first} >= 1)::int, 0)" for k, x in enumerate(words))
        arms.append(f"select id, '{t.label}' as label, {t.base} as base, (i - 1 - {first})::bigint b, ({same}) / {float(len(words))} as score from u where " + " and ".join(f"w[i + {k}] = '{x}'" for k, x in enumerate(key)))
    return (
        "with t as (select row_number() over () id, doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '') w from documents), "
        "u as (select id, w, unnest(generate_series(1, len(w))) i from t), h as (" + " union all ".join(arms) + "), "
        f"g as (select id, count(*) filter (base) n_base, min(b) filter (base) b0, max(b) filter (base) b1, string_agg(distinct label, ',' order by label) filter (base) bl, string_agg(distinct label, ',' order by label) filter (base or score >= {least}) l, max(score) filter (base or score >= {least}) s from h group by id) "
        "select doc_id::bigint doc_id, len(w)::bigint n_words, coalesce(n_base, 0)::bigint n_base, b0 first_word, b1 last_word, coalesce(bl, '') base_labels, coalesce(l, '') labels, coalesce(s, 0)::double score from t left join g using (id)"
    )
