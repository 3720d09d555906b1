"""Licence scans with a positional index of rare tokens.

The index holds postings (form, position) of the rarest words, by document frequency over the whole corpus, of every licence template and every one-line notice that
names a licence: two words of its mandatory key phrase.  In a document each place of an indexed word says, by its postings, where a form would begin.
The beginnings that the postings of a form's rare words have in common are those by relative position; there the key phrase is verified as a whole, and the share of
the words of the form found in order around it is the score.  Short phrases of their own are counted exactly.

A form without its key phrase does not count, and the indexed words are of that phrase, so intersecting loses nothing: every place of every form is verified.

Edge cases: NULL and empty texts have no words, no labels and score 0; repeated rows are scanned each by itself; an empty table gives an empty
result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Words of phrases and of well-known licence headers, with the phrase that must not be missing.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
TEMPLATES = {
    "mit": ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "permission is hereby granted free of charge"),
    "apache-2.0": ("licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", "apache license version 2 0"),
    "bsd": ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "redistribution and use in source and binary forms"),
    "gpl-header": ("this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "gnu general public license"),
    "mpl-2.0": ("this source code form is subject to the terms of the mozilla public license v 2 0", "mozilla public license"),
    "isc": ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "with or without fee is hereby granted"),
    "cc-by-text": ("this work is licensed under a creative commons attribution 4 0 international license", "creative commons attribution"),
    "unlicense": ("this is free and unencumbered software released into the public domain", "released into the public domain"),
}
# One-line notices that name a licence instead of quoting it: label, words, phrase that must not be missing and is enough for the label.
NOTICES = (
    ("mit", "the mit license", "mit license"),
    ("apache-2.0", "licensed under the apache license version 2 0", "apache license version 2 0"),
    ("apache-2.0", "under the apache license 2 0", "apache license 2 0"),
    ("apache-2.0", "under the apache 2 0 license", "apache 2 0 license"),
    ("bsd", "the bsd license", "bsd license"),
    ("gpl", "under the gnu general public license", "gnu general public license"),
    ("mpl-2.0", "licensed under the mozilla public license version 2 0", "mozilla public license version 2 0"),
    ("mpl-2.0", "licensed under the mozilla public license 2 0", "mozilla public license 2 0"),
    ("isc", "the isc license", "isc license"),
    ("cc-by-text", "licensed under creative commons attribution 4 0", "creative commons attribution 4 0"),
    ("unlicense", "under the unlicense", "the unlicense"),
)
#: Every text that is looked for: label, words, mandatory phrase.
FORMS = (*((label, t, key) for label, (t, key) in TEMPLATES.items()), *NOTICES)
#: Letters A-Z to lower case; ASCII that is neither letter nor digit to a space.
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_TABLE).split()


class Index:
    """Postings (form, position in it) of the rarest words of each key phrase."""

    def __init__(self, df: dict[str, int], n_docs: int, least: float = 0.6, rare: int = 2):
        self.idf = {w: math.log((1 + n_docs) / (1 + df.get(w.decode(), 0))) for _, t, _ in FORMS for w in t.encode().split()}
        self.forms: list[tuple[str, dict[bytes, int], int, list[bytes], int]] = []
        self.postings: dict[bytes, list[tuple[int, int]]] = defaultdict(list)
        for f, (label, t, key) in enumerate(FORMS):
            ws, k = t.encode().split(), key.encode().split()
            picked = sorted(range(len(k)), key=lambda i: (-self.idf[k[i]], i))[:rare]
            self.forms.append((label, _masks(ws), len(ws), k, len(picked)))
            for at in picked:
                self.postings[k[at]].append((f, at))
        self.indexed = frozenset(self.postings)
        self.least = least

    def begins(self, ws: list[bytes]) -> dict[int, list[int]]:
        """Places where the rare words of a form's key phrase all stand as far from each other as in it."""
        votes: Counter[tuple[int, int]] = Counter()
        for w in self.indexed.intersection(ws):
            i = -1
            for _ in range(ws.count(w)):
                i = ws.index(w, i + 1)
                votes.update((f, i - at) for f, at in self.postings[w] if i >= at)
        out: dict[int, list[int]] = defaultdict(list)
        for (f, at), n in votes.items():
            if n == self.forms[f][4]:
                out[f].append(at)
        return out

    def match(self, ws: list[bytes]) -> dict[str, float]:
        """Score of each label of which a text is verified."""
        out: dict[str, float] = {}
        for f, places in self.begins(ws).items():
            label, _, _, key, _ = self.forms[f]
            for at in places:
                if out.get(label, 0) < 1 and ws[at : at + len(key)] == key:
                    score = self._score(f, ws, at, out.get(label, 0.0))
                    if score >= self.least:
                        out[label] = score
        return out

    def _score(self, f: int, ws: list[bytes], at: int, known: float) -> float:
        """Best share of a text's words in order in a stretch, longer by 6 words, that holds the key phrase at this place."""
        _, masks, n, key, _ = self.forms[f]
        width = n + 6
        first = max(0, at + len(key) - width)
        # No stretch has more than all of them together.
        if _in_order(masks, n, ws[first : at + width]) / n <= max(known, self.least - 1e-9):
            return known
        return max(known, *(_in_order(masks, n, ws[s : s + width]) / n for s in range(first, at + 1)))


def _masks(ws: list[bytes]) -> dict[bytes, int]:
    """Places of each word as bits."""
    out: dict[bytes, int] = defaultdict(int)
    for i, w in enumerate(ws):
        out[w] |= 1 << i
    return dict(out)


def _in_order(masks: dict[bytes, int], n: int, b: list[bytes]) -> int:
    """Length of the longest common subsequence, a row of the table as the bits of one number."""
    full = (1 << n) - 1
    row = full
    for y in b:
        if y in masks:
            u = row & masks[y]
            row = (row + u | row - u) & full
    return n - row.bit_count()


def places(ws: list[bytes]) -> tuple[int, int | None, int | None, set[str]]:
    """Places of the short phrases, first and last word, labels."""
    line = b" " + b" ".join(ws) + b" "
    at, labels = [], set()
    for phrase, label in PHRASES.items():
        p = f" {phrase} ".encode()
        i = line.find(p)
        while i >= 0:
            at.append(i)
            labels.add(label)
            i = line.find(p, i + 1)
    if not at:
        return 0, None, None, labels
    gaps = lambda i: line.count(b" ", 0, i)
    return len(at), gaps(min(at)), gaps(max(at)), labels


def document_frequency(docs: DataFrame) -> tuple[dict[str, int], int]:
    """Documents that hold each licence word, and documents; as many numbers as the templates and notices have words."""
    vocabulary = frozenset(w.encode() for _, t, _ in FORMS for w in t.split())

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c: Counter = Counter()
        for batch in batches:
            for text in batch.column(0).to_pylist():
                c.update(vocabulary.intersection(words_of(text)))
                c[b""] += 1
        yield pa.RecordBatch.from_arrays([pa.array([w.decode() for w in c]), pa.array(list(c.values()), pa.int64())], names=["w", "n"])

    got = docs.select(F.col("text").cast("string").alias("text")).mapInArrow(count, "w string, n long").groupBy("w").agg(F.sum("n").alias("n")).collect()
    df = {r.w: r.n for r in got}
    return df, df.pop("", 0)


_OUT = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    df, n = document_frequency(docs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = Index(df, n)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                part, rows = batch.slice(lo, 1024), []
                for doc_id, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    ws = words_of(text)
                    n_base, first, last, base = places(ws)
                    more = index.match(ws)
                    score = max([0.5 if base else 0.0, *more.values()])
                    rows.append((doc_id, len(ws), n_base, first, last, ",".join(sorted(base)), ",".join(sorted(base | set(more))), score))
                types = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.float64()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=[x.split()[0] for x in _OUT.split(", ")])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, _OUT)
