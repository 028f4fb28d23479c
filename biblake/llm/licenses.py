"""License scan with a positional index of rare words.

Templates are names, notices and whole texts of licenses. Document frequencies of all their words are counted over the whole corpus; each
template is indexed under its words of the highest IDF, as many as any match must hold one of. A file's words are looked up in the
index, and the postings of a template's words are intersected by relative position: each says where the template would
start, from the rarest word on. A name must have all its words in their places. A notice or text may have words put in, left out or
changed: a word counts if it stands within ``drift`` words of its place, and those that do must hold a given share of the template's
IDF. Its key phrases must stand unbroken inside.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biblake.llm.base import batch, over_batches, slices

#: ASCII letters and digits and all bytes of other characters make words; A-Z are lowered.
_KEEP = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


@dataclass(frozen=True)
class Template:
    label: str
    text: str
    keys: tuple[str, ...] = ()
    #: of the IDF of all its words, what a match must hold; 1: every word in its place
    share: float = 1.0
    #: how far a word may stand from its place
    drift: int = 0
    base: bool = False

    @property
    def words(self) -> list[bytes]:
        return self.text.encode().split()


# The phrases that the base labels are defined by.
BASE = (Template("mit", "mit license", base=True), Template("apache", "apache license", base=True), Template("gpl", "general public license", base=True))
# Names and notices of public licenses, with the words that may not be missing.
NAMES = (
    Template("mit", "released under the mit license", ("mit license",), 0.8, 1),
    Template("apache", "licensed under the apache license version 2 0", ("apache license",), 0.75, 1),
    Template("gpl", "gnu general public license"),
    Template("lgpl", "gnu lesser general public license"),
    Template("agpl", "gnu affero general public license"),
    Template("bsd", "bsd license"),
    Template("mpl", "mozilla public license"),
    Template("epl", "eclipse public license"),
    Template("cc", "creative commons attribution"),
)
NOTICES = (
    Template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ("free of charge", "this software"), 0.85, 3),
    Template("apache", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at", ("apache license", "compliance with the license"), 0.8, 4),
    Template("gpl", "under the terms of the gnu general public license as published by the free software foundation", ("general public license",), 0.8, 2),
    Template("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version", ("free software", "general public license"), 0.8, 4),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ("source and binary forms",), 0.8, 2),
    Template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ("any purpose", "hereby granted"), 0.8, 3),
    Template("unlicense", "free and unencumbered software released into the public domain", ("public domain",), 0.8, 2),
)
TEXTS = (
    Template(
        "mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without "
        "limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions "
        "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software the software is provided as is without warranty of any kind express or implied "
        "including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages or other "
        "liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
        ("this permission notice", "as is"), 0.75, 12,
    ),
    Template(
        "isc",
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies "
        "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness in no event shall the author be liable for any "
        "special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of or in "
        "connection with the use or performance of this software",
        ("any purpose", "disclaims all warranties"), 0.75, 12,
    ),
    Template(
        "bsd",
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met redistributions of source code must retain the above copyright notice "
        "this list of conditions and the following disclaimer redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or "
        "other materials provided with the distribution",
        ("source and binary forms", "list of conditions"), 0.75, 12,
    ),
    Template(
        "zlib",
        "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software permission is granted to anyone to use "
        "this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions",
        ("held liable", "commercial applications"), 0.75, 12,
    ),
)
MORE = NAMES + NOTICES + TEXTS
TEMPLATES = BASE + MORE


def words(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(_KEEP).split()


def document_counts(documents: DataFrame, vocabulary: frozenset[bytes], text: str = "text") -> tuple[int, dict[bytes, int]]:
    """The number of documents, and of those that hold each word of a bounded vocabulary, over the whole table."""
    out = pa.schema([("word", pa.string()), ("n", pa.int64())])

    def work(batches):
        seen: dict[bytes, int] = {b"": 0}
        for b in slices(batches):
            for t in b.column(0).to_pylist():
                seen[b""] += 1
                for w in vocabulary.intersection(words(t)):
                    seen[w] = seen.get(w, 0) + 1
        yield batch(out, [[w.decode() for w in seen], list(seen.values())])

    rows = over_batches(documents.select(text), work, "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n")).collect()
    counts = {r.word.encode(): r.n for r in rows}
    return counts.pop(b"", 0), counts


class Index:
    def __init__(self, n: int, counts: dict[bytes, int], templates: tuple[Template, ...] = TEMPLATES):
        self.templates = [(t, t.words, [k.encode().split() for k in t.keys]) for t in templates]
        self.vocabulary = frozenset(w for _, ws, _ in self.templates for w in ws)
        self.idf = {w: math.log((n + 1) / (counts.get(w, 0) + 1)) + 1 for w in self.vocabulary}
        self.weight = [sum(self.idf[w] for w in ws) for _, ws, _ in self.templates]
        #: template positions from the rarest word on
        self.rare = [sorted(range(len(ws)), key=lambda p, ws=ws: (-self.idf[ws[p]], ws[p], p)) for _, ws, _ in self.templates]
        #: for the words that a match must hold one of: the templates, and the positions there
        self.postings: dict[bytes, dict[int, list[int]]] = {}
        for i, (t, ws, _) in enumerate(self.templates):
            rest = self.weight[i]
            for p in self.rare[i]:
                if rest < t.share * self.weight[i] - _EPS:
                    break
                self.postings.setdefault(ws[p], {}).setdefault(i, []).append(p)
                rest -= self.idf[ws[p]]

    def places(self, ws: list[bytes]) -> dict[tuple[int, int], float]:
        """{(template, start): share of its IDF that matches} of one file's words; of starts within a template's drift the best."""
        hits: dict[bytes, list[int]] = {}
        for i, w in enumerate(ws):
            if w in self.vocabulary:
                hits.setdefault(w, []).append(i)
        found: dict[tuple[int, int], float] = {}
        for i in sorted({i for w in hits if w in self.postings for i in self.postings[w]}):
            t = self.templates[i][0]
            starts = self._exact(i, hits) if t.share >= 1 else self._near(i, hits)
            if starts:
                starts = {s: x for s, x in starts.items() if self._keys(i, ws, s)}
                found |= {(i, s): x for s, x in (best(starts, t.drift) if t.drift else starts).items()}
        return found

    def _exact(self, i: int, hits: dict[bytes, list[int]]) -> dict[int, float]:
        """Starts at which every word stands in its place: the intersection of what the words' postings say."""
        ws = self.templates[i][1]
        starts: set[int] | None = None
        for p in self.rare[i]:
            say = {at - p for at in hits.get(ws[p], ())}
            starts = say if starts is None else starts & say
            if not starts:
                return {}
        return dict.fromkeys(sorted(starts or ()), 1.0)

    def _near(self, i: int, hits: dict[bytes, list[int]]) -> dict[int, float]:
        """Starts that a word of the index gives, where the words within drift of their places hold the template's share."""
        t, ws, _ = self.templates[i]
        starts = {at - p for w in set(ws) & hits.keys() for p in self.postings.get(w, {}).get(i, ()) for at in hits[w]}
        spare, out = (1 - t.share) * self.weight[i] + _EPS, {}
        for s in sorted(starts):
            lost = 0.0
            for p in self.rare[i]:
                at = hits.get(ws[p], ())
                k = bisect_left(at, s + p - t.drift)
                if k == len(at) or at[k] > s + p + t.drift:
                    lost += self.idf[ws[p]]
                    if lost > spare:
                        break
            else:
                out[s] = 1 - lost / self.weight[i]
        return out

    def _keys(self, i: int, ws: list[bytes], start: int) -> bool:
        t, tw, keys = self.templates[i]
        part = ws[max(0, start - t.drift) : start + len(tw) + t.drift]
        return all(_holds(part, key) for key in keys)


_EPS = 1e-9


def best(starts: dict[int, float], drift: int) -> dict[int, float]:
    """Of starts within ``drift`` of each other the one of the greatest share, the first of these."""
    kept: dict[int, float] = {}
    near: dict[int, int] = {}  # one kept start for each drift + 1 words at the most
    for s in sorted(starts, key=lambda s: (-starts[s], s)):
        cell = s // (drift + 1)
        if all(abs(s - near.get(c, s + drift + 1)) > drift for c in (cell - 1, cell, cell + 1)):
            kept[s] = starts[s]
            near[cell] = s
    return kept


def _holds(ws: list[bytes], key: list[bytes]) -> bool:
    n = len(key)
    return any(ws[i : i + n] == key for i in range(len(ws) - n + 1))


def index_for(documents: DataFrame, templates: tuple[Template, ...] = TEMPLATES) -> Index:
    return Index(*document_counts(documents, frozenset(w for t in templates for w in t.words)), templates)


def spans(documents: DataFrame, index: Index, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, label, base, start, end, score): a row for each place, in words from 0. Files without one have no row."""
    kind = documents.schema[key].dataType.simpleString()

    def work(batches):
        for b in slices(batches):
            rows = []
            for doc, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                for (i, start), score in index.places(words(t)).items():
                    x = index.templates[i]
                    rows.append((doc, x[0].label, x[0].base, start, start + len(x[1]), score))
            out = pa.schema([("key", b.schema.field(0).type), ("label", pa.string()), ("base", pa.bool_()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())])
            if rows:
                yield batch(out, list(zip(*rows)))

    return over_batches(documents.select(key, text), work, f"key {kind}, label string, base boolean, start bigint, end bigint, score double").withColumnRenamed("key", key)


_OUT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64())])


def scan(documents: DataFrame, index: Index | None = None) -> DataFrame:
    """The query's row for each document. No labels are empty strings. A null text is empty; rows that repeat repeat.

    Two passes: one counts the vocabulary's document frequencies (a few hundred rows come to the driver), one scans.
    """
    index = index or index_for(documents)

    def work(batches):
        for b in slices(batches):
            rows = []
            for doc, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                ws = words(t)
                found = index.places(ws)
                starts = [s for i, s in found if index.templates[i][0].base]
                base = {index.templates[i][0].label for i, _ in found if index.templates[i][0].base}
                labels = {index.templates[i][0].label for i, _ in found}
                rows.append((doc, len(ws), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(base)), ",".join(sorted(labels)), min(1.0, max(found.values(), default=0.0))))
            yield batch(_OUT, list(zip(*rows)))

    return over_batches(documents.select(F.col("doc_id").cast("bigint"), "text"), work, "doc_id bigint, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, labels string, score double")
