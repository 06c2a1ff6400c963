"""License scan: exact set-similarity join of text blocks with license templates.

Base: places where one of three phrases stands word for word. The method's own labels: every block (the words of one
line, of each two neighbouring lines, and of longer runs up to the template's length, so that line breaks inside a
notice do not hide it) is joined with every template of which it holds at least `threshold` of the distinct words, in
whatever order:

* tokens are ordered by how many lines of the whole corpus hold them, rarest first (one counting pass over all
  documents, over the bounded vocabulary of the templates);
* prefix filter: a block that reaches the threshold holds one of a template's first |T| - need + 1 tokens;
* length filter: it has at least `need` distinct words;
* positional filter: with the first common token at place p of the template and at place q of the block's own tokens
  in that order, at most min(|T| - p, |B| - q) can be common;
* the rest is counted exactly, and all matches are returned (`blocks`).

Which matches give a label is chosen afterwards: the words that name the license must be among the block's (notices
share most of their words), and a template whose common words all lie inside a better match does not count.

Templates are a short fixed list, so they travel with the tasks; documents are never shuffled. Null or empty texts
have no words, no labels and score 0; repeated rows are scanned alike; an empty table gives an empty result.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator
from math import ceil

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import _ALNUM, alnum_words, map_arrow, table, text_bytes

# The phrases of the base scan and their labels.
PHRASES = {
    "under the mit license": "mit",
    "apache license version 2": "apache-2",
    "cc by nc": "cc-by-nc",
}

# Notices and license texts by label, and the words without which it is another license.
TEMPLATES = [
    ("mit", "Released under the MIT License", "mit license"),
    ("mit", "Licensed under the MIT License", "mit license"),
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files", "permission is hereby granted"),
    ("apache-2", "Licensed under the Apache License, Version 2.0", "apache license"),
    ("apache-2", "you may not use this file except in compliance with the License. You may obtain a copy of the License at apache.org", "compliance"),
    ("gpl-2", "licensed under the GNU General Public License, version 2", "public license version 2"),
    ("gpl-3", "licensed under the GNU General Public License, version 3", "general public license version 3"),
    ("lgpl", "licensed under the GNU Lesser General Public License", "lesser general public license"),
    ("agpl-3", "licensed under the GNU Affero General Public License, version 3", "affero general public license"),
    ("mpl-2", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", "mozilla public license"),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", "source and binary forms"),
    ("cc-by", "Licensed under a Creative Commons Attribution 4.0 International License", "commons attribution 4"),
    ("cc-by-sa", "Licensed under a Creative Commons Attribution ShareAlike 4.0 International License", "attribution sharealike"),
    ("cc-by-nc", "Licensed under CC BY-NC 4.0", "cc by nc"),
    ("cc-by-nc", "Licensed under a Creative Commons Attribution NonCommercial 4.0 International License", "attribution noncommercial"),
    ("cc0", "To the extent possible under law, the author has waived all copyright and related rights to this work CC0", "has waived all copyright"),
    ("unlicense", "This is free and unencumbered software released into the public domain", "unencumbered"),
    ("all-rights-reserved", "Copyright. All rights reserved.", "all rights reserved"),
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED AS IS, WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.", "sublicense noninfringement"),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.", "purpose fee"),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.", "redistributions binary"),
    ("apache-2", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.", "apache license"),
    ("gpl-3", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.", "gnu general public version 3"),
]


def lines_of(raw: bytes) -> list[tuple[int, list[bytes]]]:
    """(first word's number, words) of each line that has words."""
    lines, n = [], 0
    for line in raw.split(b"\n"):
        words = alnum_words(line)
        if words:
            lines.append((n, words))
        n += len(words)
    return lines


def blocks(raw: bytes, longest: int, seeds: frozenset[bytes] | None = None) -> Iterator[tuple[int, list[bytes], int]]:
    """(first word's number, words, words of inner lines) of each line, of each two neighbouring ones, and of each run of
    more lines whose inner lines leave room for words of both outer ones in `longest` words; with `seeds` only of runs
    that hold one."""
    lines = lines_of(raw)
    held = [seeds is None or not seeds.isdisjoint(words) for _, words in lines]
    for i, (at, words) in enumerate(lines):
        run, inner, good = list(words), 0, held[i]
        if good:
            yield at, run, 0
        for j in range(i + 1, len(lines)):
            run = run + lines[j][1]
            good = good or held[j]
            if j > i + 1:
                inner += len(lines[j - 1][1])
                if inner + 2 > longest:
                    break
            if good:
                yield at, run, inner


def line_frequencies(docs: DataFrame, vocabulary: set[bytes], text_col: str = "text") -> dict[bytes, int]:
    """How many lines of all documents hold each word of the templates."""

    def batch(b: pa.RecordBatch) -> dict:
        n: dict[bytes, int] = {}
        for raw in text_bytes(b.column(0)):
            if vocabulary.isdisjoint(raw.translate(_ALNUM).split()):
                continue
            for _, words in lines_of(raw):
                for w in vocabulary.intersection(words):
                    n[w] = n.get(w, 0) + 1
        return {"word": [w.decode() for w in n], "n": list(n.values())}

    got = map_arrow(docs.select(F.col(text_col).cast("string")), batch, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return {r["word"].encode(): r["n"] for r in got.collect()}


class TemplateIndex:
    """Prefix index of templates whose tokens are in global frequency order."""

    def __init__(self, templates: list[tuple[str, str, str]], frequency: dict[bytes, int], threshold: float) -> None:
        self.entries: list[tuple[str, list[bytes], int, frozenset[bytes], int]] = []
        self.prefix: dict[bytes, list[tuple[int, int]]] = {}
        order = lambda w: (frequency.get(w, 0), w)
        self.rank = {w: k for k, w in enumerate(sorted({w for _, t, _ in templates for w in alnum_words(t.encode())}, key=order))}
        for label, text, names in templates:
            words = alnum_words(text.encode())
            tokens = sorted(set(words), key=order)
            need = ceil(threshold * len(tokens) - 1e-9)
            for place, w in enumerate(tokens[: len(tokens) - need + 1]):
                self.prefix.setdefault(w, []).append((len(self.entries), place))
            self.entries.append((label, tokens, need, frozenset(alnum_words(names.encode())), len(words)))
        self.seeds = frozenset(self.prefix)

    def joined(self, words: list[bytes], inner: int = 0) -> list[tuple[int, frozenset[bytes]]]:
        """(template, common words) of every template that the block reaches; a run with `inner` words between its outer
        lines meets only templates that are long enough for it."""
        have = frozenset(words)
        mine = sorted(self.rank[w] for w in have if w in self.rank)
        first: dict[int, tuple[int, bytes]] = {}
        for w in self.seeds.intersection(have):
            for k, place in self.prefix[w]:
                first[k] = min((place, w), first.get(k, (place, w)))
        out = []
        for k, (place, w) in sorted(first.items()):
            _, tokens, need, _, length = self.entries[k]
            if len(have) < need or inner and inner + 2 > length:
                continue
            if min(len(tokens) - place, len(mine) - bisect_left(mine, self.rank[w])) < need:
                continue
            common = have.intersection(tokens)
            if len(common) >= need:
                out.append((k, common))
        return out

    def containment(self, k: int, common: frozenset[bytes]) -> float:
        return len(common) / len(self.entries[k][1])

    def labelled(self, matches: list[tuple[int, frozenset[bytes]]]) -> list[int]:
        """Templates of one block's matches that give their label."""
        named = [(k, c) for k, c in matches if self.entries[k][3] <= c]
        return [k for k, c in named if not any(self.containment(o, other) > self.containment(k, c) and c <= other for o, other in named)]


def phrase_places(words: list[bytes], joined: bytes, phrases: list[tuple[list[bytes], str]]) -> list[tuple[int, str]]:
    out = []
    for phrase, label in phrases:
        if b" " + b" ".join(phrase) + b" " not in joined:
            continue
        at = -1
        while True:
            try:
                at = words.index(phrase[0], at + 1)
            except ValueError:
                break
            if words[at : at + len(phrase)] == phrase:
                out.append((at, label))
    return out


def scan(docs: DataFrame, threshold: float = 0.8, templates: list[tuple[str, str, str]] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, and blocks: every match
    of the join (start, label, containment, labels: whether it gives its label)."""
    templates = TEMPLATES if templates is None else templates
    vocabulary = {w for _, t, _ in templates for w in alnum_words(t.encode())}
    longest = max((len(alnum_words(t.encode())) for _, t, _ in templates), default=0)
    index = TemplateIndex(templates, line_frequencies(docs, vocabulary, text_col), threshold)
    phrases = [(p.encode().split(), label) for p, label in PHRASES.items()]

    def batch(b: pa.RecordBatch) -> dict:
        out: dict[str, list] = {k: [] for k in ("n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "blocks")}
        for raw in text_bytes(b.column(1)):
            words = alnum_words(raw)
            base = phrase_places(words, b" " + b" ".join(words) + b" ", phrases)
            found = []
            if not index.seeds.isdisjoint(words):
                for at, block, inner in blocks(raw, longest, index.seeds):
                    if matches := index.joined(block, inner):
                        given = index.labelled(matches)
                        found += [(at, index.entries[k][0], index.containment(k, c), k in given) for k, c in matches]
            labels = sorted({x for _, x in base})
            said = [(c, x) for _, x, c, given in found if given]
            row = (len(words), len(base), min((p for p, _ in base), default=None), max((p for p, _ in base), default=None), ",".join(labels), ",".join(sorted({*labels, *(x for _, x in said)})), 1.0 if base else max((c for c, _ in said), default=0.0), [{"start": a, "label": x, "containment": c, "labels": g} for a, x, c, g in sorted(found)])
            for k, v in zip(out, row, strict=True):
                out[k].append(v)
        return out | {"doc_id": b.column(0)}

    schema = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, blocks array<struct<start:long,label:string,containment:double,labels:boolean>>"
    return map_arrow(docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string")), batch, schema)


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query: every document with its phrases and license labels."""
    return scan(table(spark, sf_dir, "documents")).drop("blocks")


def _sql_list(words: list[bytes]) -> str:
    return "[" + ", ".join(f"'{w.decode()}'" for w in words) + "]"


def oracle(threshold: float = 0.8) -> str:
    """The contract query in DuckDB's SQL: every block against every template, without the index."""
    rows = []
    for label, text, names in TEMPLATES:
        words = alnum_words(text.encode())
        tokens = sorted(set(words))
        rows.append(f"('{label}', {_sql_list(tokens)}, {_sql_list(sorted(set(alnum_words(names.encode()))))}, {ceil(threshold * len(tokens) - 1e-9)}, {len(words)})")
    phrases = ", ".join(f"('{label}', {_sql_list(p.encode().split())})" for p, label in PHRASES.items())
    words = r"regexp_extract_all(translate({0}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
    return f"""
WITH t0(label, toks, names, need, len) AS (VALUES {", ".join(rows)}), t AS (SELECT *, row_number() OVER () AS t FROM t0), ph(label, ws) AS (VALUES {phrases}),
d AS (SELECT doc_id, {words.format("coalesce(text, '')")} AS w, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
dt AS MATERIALIZED (SELECT doc_id, t.*, w FROM d JOIN t ON len(list_intersect(w, toks)) >= need),
l0 AS (SELECT doc_id, unnest(ls) AS l, unnest(range(len(ls))) AS k FROM d WHERE doc_id IN (SELECT doc_id FROM dt)),
l1 AS (SELECT doc_id, k, len({words.format("l")}) AS n FROM l0),
l AS MATERIALIZED (SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY k) AS k, sum(n) OVER (PARTITION BY doc_id ORDER BY k) - n AS a, sum(n) OVER (PARTITION BY doc_id ORDER BY k) AS e FROM l1 WHERE n > 0),
b AS (SELECT dt.doc_id, x.k AS i, y.k AS j, label, t, names, need, toks, list_intersect(w[x.a + 1:y.e], toks) AS common FROM dt JOIN l x ON x.doc_id = dt.doc_id
      JOIN l y ON y.doc_id = x.doc_id AND y.k >= x.k AND (y.k <= x.k + 1 OR y.a - x.e + 2 <= dt.len)),
m AS MATERIALIZED (SELECT doc_id, i, j, t, label, common, len(common) / CAST(len(toks) AS DOUBLE) AS c FROM b WHERE len(common) >= need AND list_has_all(common, names)),
mt AS (SELECT doc_id, label, c FROM m WHERE NOT EXISTS (SELECT 1 FROM m o WHERE o.doc_id = m.doc_id AND o.i = m.i AND o.j = m.j AND o.c > m.c AND list_has_all(o.common, m.common))),
f AS (SELECT doc_id, label, place - 1 AS place FROM (SELECT doc_id, w, ph.label, ws, unnest(range(1, len(w) + 1)) AS place FROM d JOIN ph ON contains(' ' || array_to_string(w, ' ') || ' ', ' ' || array_to_string(ws, ' ') || ' ')) z
      WHERE w[place:place + len(ws) - 1] = ws),
fb AS (SELECT doc_id, count(*) AS n_base, min(place) AS first_word, max(place) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS base_labels FROM f GROUP BY 1),
al AS (SELECT doc_id, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM (SELECT doc_id, label FROM f UNION ALL SELECT doc_id, label FROM mt) z GROUP BY 1),
sc AS (SELECT doc_id, max(c) AS c FROM mt GROUP BY 1)
SELECT d.doc_id, len(w) AS n_words, coalesce(n_base, 0) AS n_base, first_word, last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels,
  CASE WHEN n_base > 0 THEN 1.0 ELSE coalesce(c, 0.0) END::DOUBLE AS score
FROM d LEFT JOIN fb ON fb.doc_id = d.doc_id LEFT JOIN al ON al.doc_id = d.doc_id LEFT JOIN sc ON sc.doc_id = d.doc_id
"""
