"""License scans with a positional index of rare template words.

Templates are passages of well-known licences, or a table of the caller's.  The rarity (IDF) of each template word is measured over
all scanned files, and a template's ``rare`` rarest words are indexed by their positions.  Of a file, those of its words that are in
the index are looked up; a posting and a word's place in the file agree on a shift.  At a shift, the rare positions of the
template that have their word there, up to ``SLACK`` places off, make up a share of the template's rarity.  Every shift with
``min_share`` or more is a candidate, best first, until at one the template's mandatory phrases stand in the file near that place:
then the template's label is the file's.
Apart from that, three base phrases label a file wherever they stand.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: The phrases that label a file by themselves.
BASE = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

#: Label, passage, mandatory phrases.
TEMPLATES = [
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software", ("permission is hereby granted free of charge", "associated documentation files")),
    ("mit", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software", ("shall be included in all copies or substantial portions of the software",)),
    ("apache", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at", ("licensed under the apache license", "in compliance with the license")),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version", ("free software", "gnu general public license")),
    ("lgpl", "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version", ("gnu lesser general public license",)),
    ("agpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version", ("gnu affero general public license",)),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer", ("redistribution and use in source and binary forms", "following conditions are met")),
    ("bsd", "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission", ("neither the name of", "endorse or promote products derived from this software")),
    ("mpl", "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at", ("mozilla public license",)),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies", ("permission to use copy modify", "with or without fee is hereby granted")),
    ("unlicense", "this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software", ("free and unencumbered software", "public domain")),
    ("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely", ("permission is granted to anyone to use this software for any purpose", "alter it and redistribute it freely")),
    ("bsl", "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license the software to use reproduce display distribute execute and transmit the software and to prepare derivative works of the software", ("accompanying documentation covered by this license",)),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license to view a copy of this license visit", ("licensed under a creative commons attribution",)),
    ("cc0", "the person who associated a work with this deed has dedicated the work to the public domain by waiving all of his or her rights to the work worldwide under copyright law", ("dedicated the work to the public domain",)),
]
#: Places by which a word may be off its position at a shift: words put in or left out move the rest.
SLACK = 2
#: Words around a candidate in which the mandatory phrases may stand.
MARGIN = 8


def _word_table() -> bytes:
    """A-Z to a-z; what no word holds to a blank."""
    keep = {*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)}
    return bytes(b + 32 if 0x41 <= b <= 0x5A else b if b in keep else 0x20 for b in range(256))


TABLE = _word_table()


def words_of(text: bytes) -> list[bytes]:
    return text.translate(TABLE).split()


Template = tuple[str, list[bytes], list[bytes]]


def templates_of(rows=None) -> list[Template]:
    """(label, words, mandatory phrases) of rows (label, passage, phrases), such as a collected table; None: TEMPLATES.

    Passages and phrases are cut into words as files are.  A passage without words is an error; no phrases: the alignment
    alone decides.
    """
    out = []
    for label, passage, phrases in TEMPLATES if rows is None else rows:
        words = words_of(passage.encode())
        if not words:
            raise ValueError(f"a template of {label} without words")
        out.append((label, words, [b" ".join(words_of(p.encode())) for p in phrases or ()]))
    return out


@dataclass
class Index:
    """``postings``: word -> (template, position), of each template's rarest words; ``weights`` and ``full``: by template, the rarity of
    its indexed positions and their sum."""

    templates: list[Template]
    postings: dict[bytes, list[tuple[int, int]]]
    weights: list[dict[int, float]]
    full: list[float]
    min_share: float = 0.6


def document_counts(df: DataFrame, templates: list[Template], text_col: str = "text") -> dict[str, int]:
    """In how many texts each template word stands, and under "" the number of texts; as many rows as template words."""
    known = {w for _, words, _ in templates for w in words}

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        raw, seen = common.text_bytes(part.column(0)), Counter()
        for x in raw:
            seen.update(known.intersection(words_of(x)))
        seen[b""] = len(raw)
        return pa.RecordBatch.from_arrays([pa.array([w.decode() for w in seen], pa.string()), pa.array(list(seen.values()), pa.int64())], names=["word", "n"])

    some = common.map_arrow(df.select(F.col(text_col).cast("string").alias("text")), run, "word string, n long")
    return {r["word"]: r["n"] for r in some.groupBy("word").agg(F.sum("n").alias("n")).collect()}


def build(counts: dict[str, int], templates: list[Template] | None = None, rare: int = 16, min_share: float = 0.6) -> Index:
    """Every template is indexed by its own ``rare`` rarest words, however common they or the licence are."""
    templates = templates_of() if templates is None else templates
    total = counts.get("", 0)
    idf = {w: math.log((total + 1) / (counts.get(w.decode(), 0) + 1)) + 1 for _, words, _ in templates for w in words}
    postings, weights = defaultdict(list), []
    for k, (_, words, _) in enumerate(templates):
        own = set(sorted(set(words), key=lambda w: (-idf[w], w))[:rare])
        weights.append({pos: idf[w] for pos, w in enumerate(words) if w in own})
        for pos in weights[-1]:
            postings[words[pos]].append((k, pos))
    return Index(templates, dict(postings), weights, [sum(w.values()) for w in weights], min_share)


def _base(words: list[bytes], flat: bytes) -> tuple[list[int], set[str]]:
    """Starts of the base phrases, and their labels; ``flat`` is the words with a blank before and after each."""
    starts, labels = [], set()
    for phrase, label in BASE.items():
        parts = phrase.encode().split()
        if b" " + phrase.encode() + b" " not in flat:
            continue
        labels.add(label)
        starts += [i for i in range(len(words) - len(parts) + 1) if words[i] == parts[0] and words[i : i + len(parts)] == parts]
    return starts, labels


def matches(words: list[bytes], index: Index) -> list[tuple[str, int, float, int]]:
    """(label, shift, share, template) of each template found: its best shift at which the mandatory phrases stand nearby."""
    present = index.postings.keys() & set(words)
    # A template whose present words cannot make up the share has no shift that does.
    room: dict[int, float] = defaultdict(float)
    for w in present:
        for k, pos in index.postings[w]:
            room[k] += index.weights[k][pos]
    able = {k for k, got in room.items() if got >= index.min_share * index.full[k] - 1e-9}
    if not able:
        return []
    lookup = {w: [(k, pos) for k, pos in index.postings[w] if k in able] for w in present}
    votes: dict[int, dict[int, int]] = {k: defaultdict(int) for k in able}  # shift -> the positions that agree on it, as bits
    for place, w in enumerate(words):
        for k, pos in lookup.get(w, ()):
            votes[k][place - pos] |= 1 << pos
    out = []
    for k in sorted(able):
        label, passage, phrases = index.templates[k]
        weights, need, at = index.weights[k], index.min_share * index.full[k] - 1e-9, votes[k]
        heaviest = max(weights.values())
        found = []
        for shift in {s + d for s in at for d in range(-SLACK, SLACK + 1)}:
            hit = 0
            for d in range(-SLACK, SLACK + 1):
                hit |= at.get(shift + d, 0)
            if hit.bit_count() * heaviest >= need:
                got = sum(x for pos, x in weights.items() if hit >> pos & 1)
                if got >= need:
                    found.append((-got, shift))
        for got, shift in sorted(found):
            lo, hi = max(0, shift - MARGIN), max(0, shift + len(passage) + MARGIN)
            part = b" " + b" ".join(words[lo:hi]) + b" "
            if all(b" " + p + b" " in part for p in phrases):
                out.append((label, shift, min(1.0, -got / index.full[k]), k))
                break
    return out


OUT = {"n_words": "long", "n_base": "long", "first_word": "long", "last_word": "long", "base_labels": "string", "labels": "string", "score": "double", "template_word": "long"}


def scan_text(text: bytes, index: Index) -> tuple:
    """One file's row of OUT."""
    words = words_of(text)
    flat = b" " + b" ".join(words) + b" "
    starts, base = _base(words, flat)
    found = matches(words, index)
    labels = base | {m[0] for m in found}
    score = max([1.0 if base else 0.0, *(m[2] for m in found)])
    place = min((max(0, m[1]) for m in found), default=None)
    return len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(base)), ",".join(sorted(labels)), score, place


def scan(df: DataFrame, keep: tuple[str, ...] = ("doc_id",), rare: int = 16, min_share: float = 0.6, text_col: str = "text", templates=None) -> DataFrame:
    """``keep`` beside OUT for every whole text.

    ``score`` is 1 where a base phrase stands, else the best verified template's share; ``template_word`` is the first
    verified template's place.  ``templates``: rows (label, passage, phrases) instead of TEMPLATES; they are few, and sent to
    every task.  Null and empty texts have no words, no label and score 0; of equal shares the smallest shift counts; repeated rows
    give equal results; texts of any length are read whole; an empty table gives no rows; kept columns come back under free names.
    """
    known = templates_of(templates)
    index = build(document_counts(df, known, text_col), known, rare, min_share)

    def run(column: pa.Array) -> dict[str, pa.Array]:
        rows = [scan_text(x, index) for x in common.text_bytes(column)]
        kinds = {"long": pa.int64(), "string": pa.string(), "double": pa.float64()}
        return {c: pa.array([r[i] for r in rows], kinds[t]) for i, (c, t) in enumerate(OUT.items())}

    return common.annotate(df, run, OUT, list(keep), text_col)
