"""Licence scans with a positional rare-token index of licence templates.

The index has one posting (template, position) for each template: the word of its mandatory key phrase that
fewest documents contain (highest IDF, counted over all documents). All places of these words in a file are
looked up; a posting at template position o met at file position p proposes the template starting
at p - o. There the key phrase must stand in full and AGREE licence words of the template in their
places. As the phrase stands nowhere without its rarest word, no start is missed. A template
gives its label and the share of its words that match.

Base phrases are counted wherever their words stand consecutively and always give their labels.

Native: DataFrame functions only; the driver collects one count for each licence word.

Rows. Null, empty and wordless texts have 0 words, no labels and score 0. Repeated rows are each scanned. An empty table
gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import re
import string

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Base phrases and their labels.
BASE = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))

# Fixed values: (label, template, mandatory key phrase), all in words of the contract's kind.
TEMPLATES = (
    ("agpl", "gnu affero general public license", "affero general public license"),
    ("apache", "licensed under the apache license version 2 0", "apache license version"),
    ("artistic", "released under the artistic license 2 0", "artistic license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    ("bsd", "licensed under the bsd license", "bsd license"),
    ("bsl", "boost software license version 1 0", "boost software license"),
    ("cc-by", "licensed under cc by 4 0", "cc by 4"),
    ("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    ("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    ("cc0", "cc0 1 0 universal public domain dedication", "cc0 1 0"),
    ("creative-commons", "licensed under a creative commons attribution international license", "creative commons attribution"),
    ("epl", "eclipse public license v 2 0", "eclipse public license"),
    ("gpl", "licensed under the gnu general public license version 3", "gnu general public license"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "permission to use copy modify and"),
    ("lgpl", "gnu lesser general public license", "lesser general public license"),
    ("mit", "licensed under the mit license", "the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", "permission is hereby granted free of charge"),
    ("mpl", "subject to the terms of the mozilla public license v 2 0", "mozilla public license"),
    ("proprietary", "all rights reserved", "all rights reserved"),
    ("unlicense", "this is free and unencumbered software released into the public domain", "free and unencumbered software"),
    ("zlib", "this software is provided as is without any express or implied warranty", "provided as is without any express or implied warranty"),
)
#: Licence words of a template that must stand in their places.
AGREE = 2
#: Words that no template is looked up by.
COMMON = ("0", "1", "2", "3", "4", "a", "all", "and", "any", "are", "as", "by", "for", "in", "into", "is", "of", "or", "the", "this", "to", "under", "use", "v", "with")
#: What ends a word; A-Z count as letters, and only they are lowered.
BREAKS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
SHIFT = 1 << 20
MOST_TEMPLATES = 2000
LOWER = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)


def vocabulary(templates=TEMPLATES) -> list[str]:
    used = {w for _, t, _ in templates for w in t.split()} | {w for p, _ in BASE for w in p.split()}
    return sorted(used - set(COMMON))


def templates_of(table: DataFrame) -> tuple[tuple[str, str, str], ...]:
    """(label, template, key) rows as the scan takes them, in words of the contract's kind. They are compiled into the plan, so there are MOST_TEMPLATES at most.

    Each key phrase must stand in its template and hold a licence word; a row that does not is an error, as is a null.
    """
    split = lambda t: " ".join(re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", t.translate(LOWER)))
    rows = table.select("label", "template", "key").distinct().limit(MOST_TEMPLATES + 1).collect()
    if len(rows) > MOST_TEMPLATES:
        raise ValueError(f"more than {MOST_TEMPLATES} templates")
    out = tuple(sorted((r["label"], split(r["template"]), split(r["key"])) for r in rows))
    for label, template, key in out:
        if f" {key} " not in f" {template} " or not set(key.split()) - set(COMMON):
            raise ValueError(f"the key phrase of a template of {label} is not in it or has common words alone")
    return out


def barrier(df: DataFrame, *named: tuple[str, Column]) -> DataFrame:
    """``df`` with columns that later expressions read and never compute again."""
    return df.select(*df.columns, F.inline(F.array(F.struct(*[v.alias(n) for n, v in named]))))


def lowered(word: Column) -> Column:
    """The word with A-Z lowered; ``lower`` also maps some other letters onto a-z, so only ASCII words go through it."""
    return F.when(F.octet_length(word) == F.length(word), F.lower(word)).otherwise(word)


def with_hits(documents: DataFrame, templates=TEMPLATES) -> DataFrame:
    """doc_id, words (lowered), hits: array of (p, w), the licence words and their places."""
    words = F.filter(F.split(F.coalesce(F.col("text").cast("string"), F.lit("")), BREAKS), lambda w: w != "")
    df = barrier(documents.select("doc_id", "text"), ("words", words)).drop("text")
    known = vocabulary(templates)
    found = F.filter(F.transform("words", lambda w, i: F.when(lowered(w).isin(known), F.struct(i.alias("p"), lowered(w).alias("w")))), lambda x: x.isNotNull())
    return barrier(df, ("hits", found))


def document_frequencies(hits: DataFrame) -> dict[str, int]:
    rows = hits.select(F.explode(F.array_distinct(F.transform("hits", lambda h: h["w"]))).alias("w")).groupBy("w").count().collect()
    return {r["w"]: r["count"] for r in rows}


def word_at(i: Column) -> Column:
    return lowered(F.get("words", i))


def stands(phrase: list[str], start: Column) -> Column:
    out = F.lit(True)
    for j, w in enumerate(phrase):
        out = out & F.coalesce(word_at(start + j) == w, F.lit(False))
    return out


def phrase_offset(words: list[str], phrase: list[str]) -> int:
    return next(o for o in range(len(words)) if words[o : o + len(phrase)] == phrase)


def scan(documents: DataFrame, templates=TEMPLATES) -> DataFrame:
    """``templates``: (label, template, key phrase); see ``templates_of``. Gives doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score and matches (label, start, share)."""
    hits = with_hits(documents, templates)
    seen = document_frequencies(hits)
    known = vocabulary(templates)
    order = {w: r for r, w in enumerate(sorted(known, key=lambda w: (seen.get(w, 0), w)))}
    posted: dict[str, list[int]] = {}
    for t, (_, template, key) in enumerate(templates):
        rarest = min((w for w in key.split() if w in order), key=order.__getitem__)
        posted.setdefault(rarest, []).append(t * SHIFT + phrase_offset(template.split(), key.split()) + key.split().index(rarest))
    index = F.create_map(*[x for w, places in sorted(posted.items()) for x in (F.lit(w), F.array(*[F.lit(x) for x in places]))])
    rare = F.filter("hits", lambda h: h["w"].isin(sorted(posted)))
    # a start names template t and place p - o as one number; starts before the text are left out
    starts = F.flatten(F.transform(rare, lambda h: F.transform(F.filter(F.element_at(index, h["w"]), lambda x: x % SHIFT <= h["p"]), lambda x: F.floor(x / SHIFT) * F.lit(1 << 40) + h["p"] - x % SHIFT)))
    df = barrier(hits, ("starts", F.array_distinct(starts)))

    def share(template: list[str], start: Column) -> Column:
        total = F.lit(0)
        for j, w in enumerate(template):
            total = total + F.when(word_at(start + j) == w, 1).otherwise(0)
        return total / len(template)

    def checked(t: int, label: str, words: list[str], phrase: list[str]) -> Column:
        """Verified starts of template t."""
        offset = phrase_offset(words, phrase)
        at = F.transform(F.filter("starts", lambda v: F.floor(v / (1 << 40)) == t), lambda v: (v % (1 << 40)).cast("int"))
        full = F.filter(at, lambda s: stands(phrase, s + offset))
        if sum(w in order for w in phrase) < AGREE:
            full = F.filter(full, lambda s: sum(F.when(word_at(s + j) == w, 1).otherwise(0) for j, w in enumerate(words) if w in order) >= AGREE)
        return F.transform(full, lambda s: F.struct(F.lit(label).alias("label"), s.alias("start"), share(words, s).alias("share")))

    def places(words: list[str], label: str) -> Column:
        at = F.filter("hits", lambda h: (h["w"] == words[0]) & stands(words[1:], h["p"] + 1))
        return F.transform(at, lambda h: F.struct(h["p"].alias("p"), F.lit(label).alias("label")))

    none = F.array().cast("array<struct<label:string,start:int,share:double>>")
    matches = F.when(F.size("starts") > 0, F.concat(*[checked(t, label, template.split(), key.split()) for t, (label, template, key) in enumerate(templates)])).otherwise(none)

    base = F.when(F.size("hits") > 0, F.concat(*[places(phrase.split(), label) for phrase, label in BASE])).otherwise(F.array().cast("array<struct<p:int,label:string>>"))
    df = barrier(df, ("matches", matches), ("base", base))
    labels = lambda xs: F.array_distinct(F.transform(xs, lambda x: x["label"]))
    best = F.coalesce(F.array_max(F.transform("matches", lambda m: m["share"])), F.lit(0.0))
    return df.select(
        "doc_id",
        F.size("words").cast("long").alias("n_words"),
        F.size("base").cast("long").alias("n_base"),
        F.array_min(F.transform("base", lambda b: b["p"])).cast("long").alias("first_word"),
        F.array_max(F.transform("base", lambda b: b["p"])).cast("long").alias("last_word"),
        F.array_join(F.sort_array(labels("base")), ",").alias("base_labels"),
        F.array_join(F.sort_array(F.array_union(labels("base"), labels("matches"))), ",").alias("labels"),
        # a base phrase without its template is half sure
        F.greatest(best, F.when(F.size("base") > 0, 0.5).otherwise(0.0)).alias("score"),
        "matches",
    )


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")).drop("matches")
