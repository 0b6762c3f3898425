"""Licence scan by a positional index of rare tokens.

Templates are word sequences of licence texts. The index holds the postings (template, place) of each template's rarest
words by inverse document frequency over the templates; those of mandatory key phrases, which have to stand. In a file the
words that the index knows are looked up from the rarest down, and a template's postings are intersected by relative
position: a word at place i of the file and at place j of the template means a start at i - j, and only starts that all
looked-up words of the template agree on are left. There the key phrases are verified word for word, and enough of the
other words, weighed by their frequency, must stand within a few places of where the template has them.

A template of one phrase (the base phrases are such) is mandatory as a whole, so each place where it stands is found.

Defined cases: a null or empty text has no words, no labels and score 0; overlapping places all count; repeated rows
are scanned each; an empty table gives no rows; whole texts are read; only named columns are read.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.llm.common import LOWER, UPPER, ship, table

#: Phrases that must be found, and their labels.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
#: Passages of well-known licence texts; what is in brackets are mandatory key phrases.
TEXTS = {
    "0bsd": "[permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted] the software is provided as is and the author disclaims all warranties",
    "afl": "[academic free license]",
    "agpl": "[gnu affero general public license]",
    "apache-2.0": "[licensed under the apache license version 2 0] the license you may not use this file except in compliance with the license you may obtain a copy of the license at",
    "apache-2.0-text": "[unless required by applicable law or agreed to in writing software distributed under the license] is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "artistic": "[artistic license]",
    "boost": "[boost software license version 1 0] permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation",
    "bsd": "[redistribution and use in source and binary forms] with or without modification are permitted provided that the [following conditions are met]",
    "bsd-text": "[redistributions of source code must retain the above copyright notice] this list of conditions and the following disclaimer",
    "cc0": "[cc0 1 0 universal]",
    "cc-by-nc": "[cc by nc]",
    "cc-by-nd": "[cc by nd]",
    "cc-by-sa": "[cc by sa]",
    "cc-text": "[licensed under a creative commons] attribution",
    "epl": "[eclipse public license]",
    "gpl-text": "[is free software you can redistribute it and or modify it under the terms of the gnu] general public license as published by the free software foundation either version 2 of the license or at your option any later version",
    "gpl-warranty": "[is distributed in the hope that it will be useful but without any warranty] without even the implied warranty of merchantability or fitness for a particular purpose see the gnu general public license for more details",
    "isc": "[permission to use copy modify and or distribute this software] for any purpose with or without fee is hereby granted [provided that the above copyright notice and this permission notice appear in all copies]",
    "lgpl": "[gnu lesser general public license]",
    "mit-notice": "[the above copyright notice and this permission notice shall be included in all copies] or substantial portions of the software",
    "mit-text": "[permission is hereby granted free of charge to any person obtaining a copy] of this software and associated documentation files the software to deal in the software without restriction",
    "mpl": "[mozilla public license]",
    "ofl": "[sil open font license]",
    "public-domain": "[released into the public domain]",
    "unlicense": "[this is free and unencumbered software released into the public domain] anyone is free to copy modify publish use compile sell or distribute this software",
    "warranty-text": "[the software is provided as is without warranty of any kind] express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
    "wtfpl": "[do what the fuck you want to public license]",
    "zlib": "[this software is provided as is without any express or implied warranty] in no event will the authors be held liable for any damages arising from the use of this software",
}
#: Share of a template's words, weighed by inverse document frequency, that must agree.
AGREE = 0.6
#: The rarest mandatory words of a template that are looked up, and by how many places other words may be off.
ANCHORS, SHIFT = 4, 3

WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+").findall
_TABLE = str.maketrans(UPPER, LOWER)


@dataclass(frozen=True)
class Template:
    label: str
    words: tuple[str, ...]
    keys: tuple[tuple[int, int], ...]  # places of key phrases: from, to
    base: bool


def template(label: str, text: str, base: bool = False) -> Template:
    """Words in brackets are mandatory; without any, all are."""
    words: list[str] = []
    keys: list[tuple[int, int]] = []
    for i, part in enumerate(re.split(r"[\[\]]", text)):
        own = WORDS(part.translate(_TABLE))
        if i % 2 and own:
            keys.append((len(words), len(words) + len(own)))
        words += own
    return Template(label, tuple(words), tuple(keys) or ((0, len(words)),), base)


TEMPLATES = tuple(template(v, k, True) for k, v in BASE.items()) + tuple(template(k, v) for k, v in TEXTS.items())


class Index:
    """Postings of the templates' rarest mandatory words."""

    def __init__(self, templates: tuple[Template, ...], agree: float = AGREE, anchors: int = ANCHORS, shift: int = SHIFT):
        self.templates, self.agree, self.shift = templates, agree, shift
        with_word: dict[str, int] = {}
        for t in templates:
            for w in {*t.words}:
                with_word[w] = with_word.get(w, 0) + 1
        self.idf = {w: math.log(1 + len(templates) / n) for w, n in with_word.items()}
        self.anchors: list[list[tuple[str, int]]] = []  # of each template: word, place; the rarest first
        self.known: set[str] = set()
        for t in templates:
            must = [i for a, b in t.keys for i in range(a, b)]
            order = sorted(must, key=lambda i: (-self.idf[t.words[i]], -len(t.words[i]), i))[:anchors]
            self.anchors.append([(t.words[i], i) for i in order])
            self.known |= {t.words[i] for i in order}
        # by the rarest anchor: a file without it can't hold the template
        self.by_first: dict[str, list[int]] = {}
        for k, a in enumerate(self.anchors):
            self.by_first.setdefault(a[0][0], []).append(k)
        self.firsts = self.by_first.keys()

    def scan(self, words: list[str]) -> list[tuple[int, int]]:
        """All (template, start) that stand in the words."""
        here = {*words}
        firsts = self.firsts & here
        if not firsts:
            return []
        known = self.known & here
        places: dict[str, list[int]] = {w: [] for w in known}
        for i, w in enumerate(words):
            if w in known:
                places[w].append(i)
        out: list[tuple[int, int]] = []
        for first in sorted(firsts, key=lambda w: (-self.idf[w], w)):
            for k in self.by_first[first]:
                out += [(k, s) for s in self.starts(k, places) if self.stands(words, k, s)]
        return sorted(out)

    def starts(self, k: int, places: dict[str, list[int]]) -> set[int]:
        """Starts of a template that all its looked-up words agree on, from the word with the fewest places on."""
        found: set[int] | None = None
        for w, j in sorted(self.anchors[k], key=lambda a: (len(places.get(a[0], ())), a[1])):
            if w not in places:
                return set()
            if found is None:
                found = {i - j for i in places[w] if i >= j}
            else:
                found.intersection_update([i - j for i in places[w]])
            if not found:
                return found
        return found or set()

    def stands(self, words: list[str], k: int, start: int) -> bool:
        t = self.templates[k]
        if any(tuple(words[start + a:start + b]) != t.words[a:b] for a, b in t.keys):
            return False
        must = {i for a, b in t.keys for i in range(a, b)}
        total = agreed = 0.0
        for i, w in enumerate(t.words):
            total += self.idf[w]
            at = start + i
            if i in must or w in words[max(0, at - self.shift):at + self.shift + 1]:
                agreed += self.idf[w]
        return agreed >= self.agree * total


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", templates: tuple[Template, ...] = TEMPLATES) -> DataFrame:
    """Per row: key, n_words, n_base, first_word, last_word, base_labels, labels, score, spans (label, start, words).

    ``score`` is 1 - 0.5 ** (distinct labels): 0 without any. One pass, no shuffle.
    """
    ship(docs.sparkSession)
    schema = f"{key} {docs.schema[key].dataType.simpleString()}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans array<struct<label: string, start: long, words: int>>"
    span = pa.list_(pa.struct([("label", pa.string()), ("start", pa.int64()), ("words", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = Index(templates)
        for batch in batches:
            rows = []
            for x in batch["__text"]:
                words = WORDS((x.as_py() or "").translate(_TABLE))
                found = index.scan(words)
                base = [s for k, s in found if templates[k].base]
                labels = sorted({templates[k].label for k, _ in found})
                rows.append((len(words), len(base), min(base, default=None), max(base, default=None), ",".join(sorted({templates[k].label for k, _ in found if templates[k].base})), ",".join(labels), 1 - 0.5 ** len(labels), [{"label": templates[k].label, "start": s, "words": len(templates[k].words)} for k, s in found]))
            columns = [*zip(*rows)] if rows else [()] * 8
            kinds = [pa.int64()] * 4 + [pa.string(), pa.string(), pa.float64(), span]
            yield pa.RecordBatch.from_arrays([batch["__key"], *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names=[key, "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans"])

    return docs.select(F.col(key).alias("__key"), F.col(text).alias("__text")).mapInArrow(run, schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents")).drop("spans")
