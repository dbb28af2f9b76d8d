"""License scan: an exact set-similarity join of text blocks with license templates.

Words are runs of ASCII digits, lower-cased ASCII letters and non-ASCII characters. A block is a
window of consecutive words of a text, as the set of its words; it may run over line ends and has
the template's number of words over the threshold, so that other words in between have some room. A
template, as the set of its words, is contained in a block to the share of its words that the block
holds. A block matches if that share reaches the threshold, it holds all words that set the license
apart from others, and none that only its relatives have ("sa" in a plain attribution license). All windows
that start at a word of the template are judged, and the best share per line in which windows start is kept:

- words of the templates are ordered by their frequency in the whole corpus, rarest first;
- prefix filter: an index leads from rare words to templates. A template with words that set it apart
  is indexed by the rarest of these; another, with n words of which a block must hold o, by its
  n - o + 1 rarest. Only windows around an occurrence of an indexed word are looked at, so a
  template costs nothing in texts without one;
- length filter: a window with fewer than o places that hold words of the template is dropped;
- positional filter: words are counted in their order, and after j of them a window that holds h
  can't hold more than h + n - j; it is dropped when that falls below o.

Phrases of the base labels are templates to be contained wholly and in order: their rarest word is the
prefix, its place in the phrase gives the place where the phrase has to start, and the neighbours
decide. Places may run over line ends.

The vocabulary is that of the templates, so what is counted over the corpus and sent to the
tasks has a fixed bound.

Edge cases: null and empty texts have no words; repeated rows are scanned one by one; texts
are scanned whole; columns beside id and text are ignored, whatever their names, and these two
match in any case.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.llm import words
from kgflow.llm.frames import id_and_text

#: Base phrases and their labels (fixed values).
PHRASES = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))


@dataclass(frozen=True)
class Template:
    label: str
    text: str
    must: tuple[str, ...] = ()  # words without which no block is this license
    never: tuple[str, ...] = ()  # words that a block of this license doesn't have

    @property
    def words(self) -> list[str]:
        return self.text.split()


#: Short statements, notices and grants of common licenses (fixed values).
TEMPLATES = (
    Template("mit", "released under the mit license", ("mit",)),
    Template(
        "mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without "
        "restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the "
        "software is furnished to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
        ("sublicense", "merge"),
    ),
    Template("apache", "licensed under the apache license version 2 0", ("apache",)),
    Template(
        "apache",
        "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org "
        "licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
        ("apache", "compliance"),
    ),
    Template("gpl", "this work is licensed under the gnu general public license version 3", ("gnu", "general"), ("lesser", "affero")),
    Template(
        "gpl",
        "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of "
        "the license or at your option any later version this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
        ("gnu", "redistribute"),
        ("lesser", "affero"),
    ),
    Template(
        "lgpl",
        "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version",
        ("gnu", "lesser"),
    ),
    Template(
        "agpl",
        "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version",
        ("gnu", "affero"),
    ),
    Template("bsd", "released under the bsd license", ("bsd",)),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ("redistribution", "binary")),
    Template(
        "bsd-3-clause",
        "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
        ("neither", "endorse"),
    ),
    Template("mpl", "this source code form is subject to the terms of the mozilla public license", ("mozilla",)),
    Template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies", ("fee", "appear")),
    Template("unlicense", "this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software", ("unencumbered",)),
    Template("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software", ("authors", "arising")),
    Template("cc0", "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work", ("waived", "neighboring")),
    Template("cc-by", "licensed under cc by 4 0", ("cc", "by"), ("nc", "sa", "nd")),
    Template("cc-by-sa", "licensed under cc by sa 4 0", ("cc", "by", "sa"), ("nc", "nd")),
    Template("cc-by-nc", "licensed under cc by nc 4 0", ("cc", "by", "nc"), ("sa", "nd")),
    Template("cc-by-nd", "licensed under cc by nd 4 0", ("cc", "by", "nd"), ("nc", "sa")),
    Template("cc-by-nc-sa", "licensed under cc by nc sa 4 0", ("cc", "by", "nc", "sa"), ("nd",)),
    Template("cc-by", "this work is licensed under a creative commons attribution 4 0 international license", ("creative", "commons", "attribution"), ("sharealike", "noncommercial", "noderivatives")),
    Template("cc-by-sa", "this work is licensed under a creative commons attribution sharealike 4 0 international license", ("creative", "commons", "sharealike"), ("noncommercial", "noderivatives")),
    Template("cc-by-nc", "this work is licensed under a creative commons attribution noncommercial 4 0 international license", ("creative", "commons", "noncommercial"), ("sharealike", "noderivatives")),
    Template("all-rights-reserved", "all rights reserved no part of this publication may be reproduced", ("reserved", "reproduced")),
)
#: Share of a template's words that a block has to hold.
CONTAINMENT = 0.8


def needed(t: Template, containment: float) -> int:
    """How many of the template's distinct words a block has to hold."""
    return math.ceil(containment * len(set(t.words)) - 1e-9)


def reach(t: Template, containment: float) -> int:
    """Words in a block."""
    return math.ceil(len(t.words) / containment - 1e-9)


def word_hash(texts: list[str]) -> np.ndarray:
    """Hashes of single words, as the scan makes them."""
    return np.concatenate([c.hashes() for c in words.chunks(pa.array(texts), words.ALNUM, lower=True)]) if texts else np.zeros(0, np.uint64)


def vocabulary(phrases, templates) -> list[str]:
    return sorted({w for t, _ in phrases for w in t.split()} | {w for t in templates for w in (*t.words, *t.must, *t.never)})


def frequencies(src: DataFrame, vocab: list[str]) -> dict[str, int]:
    """How often each word of the vocabulary occurs in the whole corpus."""
    lookup = words.Lookup(word_hash(vocab))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(len(vocab), np.int64)
        for b in batches:
            for c in words.chunks(b.column(0), words.ALNUM, lower=True):
                n += np.bincount(lookup.found(c.hashes())[1], minlength=len(vocab))
        yield pa.RecordBatch.from_arrays([pa.array(range(len(vocab)), pa.int32()), pa.array(n)], ["w", "n"])

    counted = src.select("text").mapInArrow(run, "w int, n long").groupBy("w").agg(F.sum("n").alias("n"))
    found = {r["w"]: r["n"] for r in counted.collect()}  # one row per word of the templates
    return {w: found.get(i, 0) for i, w in enumerate(vocab)}


class Index:
    """Templates by the rank of their words, rarest first, with the words that lead to them."""

    def __init__(self, rank: dict[str, int], templates, containment: float):
        self.templates = templates
        self.sets = [np.array(sorted({rank[w] for w in t.words})) for t in templates]
        self.need = [needed(t, containment) for t in templates]
        self.reach = [reach(t, containment) for t in templates]
        self.must = [np.array(sorted(rank[w] for w in t.must), np.int64) for t in templates]
        self.never = [np.array(sorted(rank[w] for w in t.never), np.int64) for t in templates]
        size = (len(templates), len(rank) + 1)  # the last column is for words outside the vocabulary
        self.member, self.leads, self.bars = (np.zeros(size, bool) for _ in range(3))
        for i, (s, o, must, never) in enumerate(zip(self.sets, self.need, self.must, self.never, strict=True)):
            self.member[i, s] = True
            self.leads[i, must[:1] if len(must) else s[: len(s) - o + 1]] = True
            self.bars[i, never] = True
        self.any_lead = self.leads.any(0)

    def matches(self, code: np.ndarray, own: np.ndarray, first: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(template, first words of its matching windows, words held): code is the rank of every word or -1."""
        coded = np.flatnonzero(code >= 0)
        lead = coded[self.any_lead[code[coded]]]
        for i in np.flatnonzero(self.leads[:, np.unique(code[lead])].any(1)):
            s, o, wide = self.sets[i], self.need[i], self.reach[i]
            rare = lead[self.leads[i, code[lead]]]
            at = coded[self.member[i, code[coded]]]
            # prefix: windows that start at a word of the template and hold an indexed word
            near = np.zeros(len(at) + 1, np.int64)
            np.add.at(near, np.searchsorted(at, rare - wide + 1), 1)
            np.add.at(near, np.searchsorted(at, rare, "right"), -1)
            which = np.flatnonzero(np.cumsum(near[:-1]) > 0)
            stop = np.minimum(at[which] + wide, first[own[at[which]] + 1])
            # length: enough places with words of the template
            ok = np.searchsorted(at, stop) - which >= o
            which, stop = which[ok], stop[ok]
            for w in self.must[i]:
                spot = coded[code[coded] == w]
                ok = np.searchsorted(spot, at[which]) < np.searchsorted(spot, stop)
                which, stop = which[ok], stop[ok]
            if len(self.never[i]) and len(which):
                spot = coded[self.bars[i, code[coded]]]
                ok = np.searchsorted(spot, at[which]) == np.searchsorted(spot, stop)
                which, stop = which[ok], stop[ok]
            # positional: after j words, rarest first, the rest can't add more than n - j
            held = np.zeros(len(which), np.int64)
            for j, w in enumerate(s, 1):
                if not len(which):
                    break
                spot = at[code[at] == w]
                held += np.searchsorted(spot, at[which]) < np.searchsorted(spot, stop)
                ok = held + len(s) - j >= o
                which, stop, held = which[ok], stop[ok], held[ok]
            if len(which):
                yield int(i), at[which], held


PLACES = pa.list_(pa.struct([("word", pa.int64()), ("label", pa.string())]))
BLOCKS = pa.list_(pa.struct([("line", pa.int64()), ("label", pa.string()), ("share", pa.float64())]))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", phrases=PHRASES, templates=TEMPLATES, containment: float = CONTAINMENT) -> DataFrame:
    """(id, n_words, phrases found, blocks found) per row: places array<struct<word, label>>,
    blocks array<struct<line, label, share>>."""
    src = id_and_text(docs, id_col, text_col)
    vocab = vocabulary(phrases, templates)
    often = frequencies(src, vocab)
    rank = {w: i for i, w in enumerate(sorted(vocab, key=lambda w: (often[w], w)))}
    in_rank = sorted(rank, key=rank.get)
    lookup = words.Lookup(word_hash(in_rank))
    index = Index(rank, templates, containment)

    def phrase_places(c: words.Chunk, code: np.ndarray, own: np.ndarray) -> list[tuple[int, int, str]]:
        out = []
        for text, label in phrases:
            seq = [rank[w] for w in text.split()]
            rare = int(np.argmin(seq))
            start = np.flatnonzero(code == seq[rare]) - rare
            start = start[(start >= 0) & (start + len(seq) <= len(code))]
            for d, w in enumerate(seq):
                start = start[(code[start + d] == w) & (own[start + d] == own[start])]
            sure = [i for i in start.tolist() if [c.word(i + d) for d in range(len(seq))] == [w.encode() for w in text.split()]]
            out += [(int(own[i]), i - int(c.first[own[i]]), label) for i in sure]
        return out

    def block_matches(c: words.Chunk, code: np.ndarray, own: np.ndarray) -> list[tuple[int, int, str, float]]:
        feeds = np.flatnonzero(c.buf == 0x0A)
        best: dict[tuple[int, int, str], float] = {}
        for i, start, held in index.matches(code, own, c.first):
            line = np.searchsorted(feeds, c.start[start]) - np.searchsorted(feeds, c.at[own[start]])
            for t, n, h in zip(own[start].tolist(), line.tolist(), held.tolist(), strict=True):
                key = (t, n, templates[i].label)
                best[key] = max(best.get(key, 0.0), h / len(index.sets[i]))
        return [(*key, share) for key, share in best.items()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in words.chunks(b.column(1), words.ALNUM, lower=True):
                code = np.full(len(c.start), -1)
                at, which = lookup.found(c.hashes())
                code[at] = which
                own = c.owners()
                found: list[list] = [[] for _ in range(c.hi - c.lo)]
                lines: list[list] = [[] for _ in range(c.hi - c.lo)]
                for t, i, label in sorted(phrase_places(c, code, own)):
                    found[t].append({"word": i, "label": label})
                for t, i, label, share in sorted(block_matches(c, code, own)):
                    lines[t].append({"line": i, "label": label, "share": share})
                yield pa.RecordBatch.from_arrays([b.column(0).slice(c.lo, c.hi - c.lo), pa.array(c.counts(), pa.int64()), pa.array(found, PLACES), pa.array(lines, BLOCKS)], ["id", "n_words", "places", "blocks"])

    out = src.mapInArrow(run, "id long, n_words long, places array<struct<word:long,label:string>>, blocks array<struct<line:long,label:string,share:double>>")
    return out.withColumnRenamed("id", id_col)


def digest(scanned: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """One line per document: counts, first and last places, labels, and the best share as score."""
    base = F.array_sort(F.array_distinct(F.col("places.label")))
    both = F.array_sort(F.array_distinct(F.concat(F.col("places.label"), F.col("blocks.label"))))
    score = F.when(F.size("places") > 0, F.lit(1.0)).otherwise(F.coalesce(F.array_max("blocks.share"), F.lit(0.0)))
    return scanned.select(
        id_col, "n_words", F.size("places").cast("long").alias("n_base"), F.array_min("places.word").alias("first_word"), F.array_max("places.word").alias("last_word"),
        F.array_join(base, ",").alias("base_labels"), F.array_join(both, ",").alias("labels"), score.alias("score"),
    )


def oracle() -> str:
    """The same windows in SQL; texts that don't hold enough of a template's words anywhere are left out first."""
    quote = lambda rows: ", ".join("('{}', '{}')".format(*r) for r in rows)
    many = lambda ws: "[" + ", ".join(f"'{w}'" for w in sorted(set(ws))) + "]::VARCHAR[]"
    rows = ", ".join(f"('{t.label}', {many(t.words)}, {needed(t, CONTAINMENT)}, {reach(t, CONTAINMENT)}, {many(t.must)}, {many(t.never)})" for t in TEMPLATES)
    return rf"""
WITH phrase(t, label) AS (VALUES {quote(PHRASES)}),
template(label, s, need, wide, must, never) AS (VALUES {rows}),
d AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS x FROM documents),
w AS (SELECT doc_id, regexp_extract_all(x, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM d),
starts AS (SELECT doc_id, ws, string_split(t, ' ') AS ts, t, label, unnest(range(1, len(ws) + 1)) AS p FROM w JOIN phrase ON list_has_all(ws, string_split(t, ' '))),
places AS (SELECT doc_id, p - 1 AS p, label FROM starts WHERE ws[p] = ts[1] AND array_to_string(ws[p:p + len(ts) - 1], ' ') = t),
maybe AS (SELECT doc_id, ws, template.* FROM w, template WHERE list_has_all(ws, must) AND len(list_intersect(list_distinct(ws), s)) >= need),
windows AS (SELECT doc_id, label, s, need, must, never, ws[p:p + wide - 1] AS x FROM (SELECT *, unnest(range(1, len(ws) + 1)) AS p FROM maybe) WHERE list_contains(s, ws[p])),
shares AS (SELECT *, len(list_intersect(list_distinct(x), s)) AS held FROM windows WHERE list_has_all(x, must) AND NOT list_has_any(x, never)),
blocks AS (SELECT doc_id, label, held / len(s) AS share FROM shares WHERE held >= need),
a AS (SELECT doc_id, count(*) AS n_base, min(p) AS first_word, max(p) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS base_labels FROM places GROUP BY doc_id),
b AS (SELECT doc_id, max(share) AS share FROM blocks GROUP BY doc_id),
l AS (SELECT doc_id, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM (SELECT doc_id, label FROM places UNION SELECT doc_id, label FROM blocks) GROUP BY doc_id)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(n_base, 0)::BIGINT AS n_base, first_word::BIGINT AS first_word, last_word::BIGINT AS last_word,
  coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels,
  CASE WHEN n_base > 0 THEN 1.0::DOUBLE ELSE coalesce(share, 0.0)::DOUBLE END AS score
FROM w LEFT JOIN a USING (doc_id) LEFT JOIN b USING (doc_id) LEFT JOIN l USING (doc_id)
"""
