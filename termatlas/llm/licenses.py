"""Licences by a positional rare-token index of templates (operator 10).

TEMPLATES holds short wordings of common licences, each with the key phrases that must
stand in a text for the licence to be named. Their words make a lexicon of bounded size; a
first pass counts, over all documents, in how many each of its words occurs. A template is
looked up by its own words of highest inverse document frequency, one more than may fail
to align: wherever LEAST_SHARE of its words stand, one of these stands too, so no place is
lost, however long the text or many its licences. A looked-up word's place in the text
gives an offset, the difference of both positions. There the key phrases are verified,
moved by SLACK at most, and the template is aligned word for word. The share of a
template's words that align is the match's score.

Null and empty texts have no words, no labels and score 0. Rows with equal keys stay
separate rows.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from termatlas.llm.tables import bounded_batches

# fixed values: words, base phrases, and wordings of public licences with their key phrases
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
BASE = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))
TEMPLATES = (
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ("permission is hereby granted", "free of charge")),
    ("mit", "released under the mit license", ("mit license",)),
    ("mit", "licensed under the mit license", ("mit license",)),
    ("apache-2.0", "licensed under the apache license version 2 0", ("apache license", "2 0")),
    ("apache-2.0", "you may not use this file except in compliance with the license you may obtain a copy of the license at", ("except in compliance with the license",)),
    ("gpl-3.0", "this work is licensed under the gnu general public license version 3", ("gnu general public license", "version 3")),
    ("gpl", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", ("gnu general public license",)),
    ("lgpl", "under the terms of the gnu lesser general public license as published by the free software foundation", ("gnu lesser general public license",)),
    ("agpl", "under the terms of the gnu affero general public license as published by the free software foundation", ("gnu affero general public license",)),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ("redistribution and use", "are permitted provided that")),
    ("cc-by-nc-4.0", "licensed under cc by nc 4 0", ("cc by nc", "4 0")),
    ("cc-by-4.0", "this work is licensed under a creative commons attribution 4 0 international license", ("creative commons attribution", "4 0")),
    ("cc-by-sa-4.0", "this work is licensed under a creative commons attribution sharealike 4 0 international license", ("creative commons attribution sharealike", "4 0")),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", ("mozilla public license",)),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ("permission to use copy modify", "is hereby granted")),
    ("unlicense", "this is free and unencumbered software released into the public domain", ("released into the public domain",)),
    ("reserved", "copyright all rights reserved", ("all rights reserved",)),
)
SLACK, LEAST_SHARE = 2, 0.7
_UPPER = {c: c + 32 for c in range(ord("A"), ord("Z") + 1)}


def words(text: str | None) -> list[str]:
    return WORD.findall((text or "").translate(_UPPER))


@dataclass
class Index:
    templates: list[tuple[str, list[str], list[tuple[int, list[str]]]]]
    needed: list[frozenset[str]]  # by template: the words of its key phrases
    rare: list[list[int]]  # by template: the places of its rarest words
    known: frozenset[str]


def lexicon(templates=TEMPLATES) -> list[str]:
    return sorted({w for _, t, _ in templates for w in t.split()})


def index(templates=TEMPLATES, counts: dict[str, int] | None = None, total: int = 0) -> Index:
    """counts: documents with each lexicon word, of total."""
    rows, needed, rare = [], [], []
    for label, text, keys in templates:
        own = text.split()
        places = []
        for key in keys:
            part = key.split()
            at = next(i for i in range(len(own)) if own[i : i + len(part)] == part)
            places.append((at, part))
        rows.append((label, own, places))
        needed.append(frozenset(w for _, part in places for w in part))
        # of so many places one at least aligns wherever LEAST_SHARE of the words do
        missing = max(n for n in range(len(own)) if (len(own) - n) / len(own) >= LEAST_SHARE)
        idf = [math.log((1 + total) / (1 + (counts or {}).get(w, 0))) + 1e-9 * len(w) for w in own]
        rare.append(sorted(range(len(own)), key=lambda i: (-idf[i], i))[: missing + 1])
    return Index(rows, needed, rare, frozenset(lexicon(templates)))


def document_frequencies(docs: DataFrame, templates=TEMPLATES, text: str = "text") -> tuple[dict[str, int], int]:
    """Documents with each word of the lexicon, and all documents, by one pass and a sum of vectors."""
    order = lexicon(templates)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, seen, n = set(order), Counter(), 0
        for batch in batches:
            n += batch.num_rows
            for value in batch.column(0):
                seen.update(known.intersection(words(value.as_py())))
        yield pa.RecordBatch.from_arrays([pa.array(["", *order], pa.string()), pa.array([n, *(seen[w] for w in order)], pa.int64())], names=["word", "n"])

    got = {r.word: r.n for r in bounded_batches(docs).select(text).mapInArrow(run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()}
    return got, got.pop("", 0)


def _consecutive(own: list[str], phrase: list[str], at: dict[str, list[int]]) -> list[int]:
    return [i for i in at.get(phrase[0], ()) if own[i : i + len(phrase)] == phrase]


def match(own: list[str], at: dict[str, list[int]], ix: Index) -> list[tuple[str, float, int]]:
    """(label, score, first word) of each template that stands in the words; at: places of the lexicon's words."""
    found = []
    for (label, template, keys), needed, rare in zip(ix.templates, ix.needed, ix.rare, strict=True):
        if not needed <= at.keys():
            continue
        best = (0.0, 0)
        for offset in {p - i for i in rare for p in at.get(template[i], ())}:
            if not all(any(own[s : s + len(part)] == part for s in range(max(0, offset + i - SLACK), offset + i + SLACK + 1)) for i, part in keys):
                continue
            lo = max(0, -offset)
            share = sum(a == b for a, b in zip(template[lo:], own[max(0, offset) : max(0, offset + len(template))], strict=False)) / len(template)
            if share >= LEAST_SHARE:
                best = max(best, (share, -max(0, offset)))
        if best[0]:
            found.append((label, best[0], -best[1]))
    return found


def scan(docs: DataFrame, ix: Index, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_words, base (array of label, word), matches (array of label, score, word) of each row."""
    kind = docs.schema[key].dataType.simpleString()
    base_type = pa.list_(pa.struct([("label", pa.string()), ("word", pa.int64())]))
    match_type = pa.list_(pa.struct([("label", pa.string()), ("score", pa.float64()), ("word", pa.int64())]))
    phrases = [(p.split(), label) for p, label in BASE]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = set(ix.known).union(p[0] for p, _ in phrases)
        for batch in batches:
            n, base, found = [], [], []
            for value in batch.column(1):
                own = words(value.as_py())
                at: dict[str, list[int]] = {}
                if not known.isdisjoint(own):
                    for i, w in enumerate(own):
                        if w in known:
                            at.setdefault(w, []).append(i)
                n.append(len(own))
                base.append(sorted(({"label": label, "word": i} for p, label in phrases for i in _consecutive(own, p, at)), key=lambda x: x["word"]))
                found.append([{"label": a, "score": s, "word": i} for a, s, i in match(own, at, ix)])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(base, base_type), pa.array(found, match_type)], names=[key, "n_words", "base", "matches"])

    return bounded_batches(docs).select(key, text).mapInArrow(run, f"`{key}` {kind}, n_words long, base array<struct<label:string,word:long>>, matches array<struct<label:string,score:double,word:long>>")


def licenses(docs: DataFrame, templates=TEMPLATES, key: str = "doc_id", text: str = "text") -> DataFrame:
    counts, total = document_frequencies(docs, templates, text)
    return scan(docs, index(templates, counts, total), key, text)


def digests(found: DataFrame, key: str = "doc_id") -> DataFrame:
    """The contract's columns. A base phrase alone scores 0.5, a match its share."""
    named = F.array_join(F.array_sort(F.array_distinct(F.col("base.label"))), ",")
    both = F.array_join(F.array_sort(F.array_distinct(F.concat("base.label", "matches.label"))), ",")
    score = F.greatest(F.when(F.size("base") > 0, 0.5).otherwise(0.0), F.coalesce(F.array_max("matches.score"), F.lit(0.0)))
    return found.select(
        key, "n_words", F.size("base").cast("long").alias("n_base"), F.array_min("base.word").alias("first_word"), F.array_max("base.word").alias("last_word"),
        named.alias("base_labels"), both.alias("labels"), score.alias("score"),
    )
