"""License scan by a positional rare-token index.

Templates are short licence notices.  Each is looked up by its anchor, the word of its mandatory phrases that is
rarest (highest inverse document frequency over all documents): an occurrence at word p proposes the alignments
p - q, give or take ``slack``, on which all words of the template vote; one with votes of several different words
is kept if every mandatory phrase of the template stands at its place, give or take ``slack``.
The base phrases, which need no alignment, are reported wherever they stand.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binlens.llm.common import narrow, slices, text_buffers
from binlens.llm.words import ALNUM, hash_of, words

#: Fixed values of the task: phrase and label.
BASE = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))

#: Public licence notices: label, notice, phrases that must stand in it.
TEMPLATES = (
    ("mit-notice", "released under the mit license", ("mit license",)),
    ("mit-text", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files",
        ("free of charge", "obtaining a copy")),
    ("apache-2.0", "licensed under the apache license version 2 0", ("apache license", "version 2 0")),
    ("gpl-2.0", "this work is licensed under the gnu general public license version 2", ("general public license version 2",)),
    ("gpl-3.0", "this work is licensed under the gnu general public license version 3", ("general public license version 3",)),
    ("gpl-text", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license",
        ("free software", "general public license")),
    ("lgpl", "under the terms of the gnu lesser general public license", ("lesser general public license",)),
    ("agpl", "under the terms of the gnu affero general public license", ("affero general public license",)),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ("source and binary forms",)),
    ("mpl-2.0", "subject to the terms of the mozilla public license v 2 0", ("mozilla public license",)),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ("for any purpose",)),
    ("cc-by-nc-4.0", "licensed under cc by nc 4 0", ("cc by nc 4 0",)),
    ("cc-by-sa-4.0", "licensed under cc by sa 4 0", ("cc by sa 4 0",)),
    ("cc-by-4.0", "licensed under cc by 4 0", ("cc by 4 0",)),
    ("unlicense", "this is free and unencumbered software released into the public domain", ("unencumbered software", "public domain")),
)
SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"


@dataclass
class Index:
    vocabulary: np.ndarray  # sorted hashes of template words
    idf: np.ndarray
    texts: list[np.ndarray]  # word hashes of each template
    phrases: list[list[tuple[int, np.ndarray]]]  # for each template: place and hashes of each mandatory phrase
    labels: list[str]
    base: list[tuple[np.ndarray, str]]


def _hashes(text: str) -> np.ndarray:
    return np.array([hash_of(w, ALNUM) for w in text.split()], np.uint64)


def template_index(templates=TEMPLATES, base=BASE) -> Index:
    texts = [_hashes(t) for _, t, _ in templates]
    vocabulary = np.unique(np.concatenate(texts))
    phrases = []
    for _, text, must in templates:
        parts = text.split()
        own = []
        for phrase in must:
            p = phrase.split()
            own.append((next(q for q in range(len(parts)) if parts[q : q + len(p)] == p), _hashes(phrase)))
        phrases.append(own)
    return Index(vocabulary, np.zeros(len(vocabulary)), texts, phrases, [x for x, _, _ in templates], [(_hashes(p), x) for p, x in base])


def _places(h: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.minimum(np.searchsorted(known, h), len(known) - 1)
    where = np.flatnonzero(known[at] == h)
    return where, at[where]


def document_frequencies(docs: DataFrame, index: Index) -> Index:
    """Fill in idf from all documents: one narrow pass, then at most one row for each licence word."""
    shared = docs.sparkSession.sparkContext.broadcast(index.vocabulary)

    def run(batches):
        known, total, rows = shared.value, np.zeros(len(shared.value) + 1, np.int64), 0
        for b in batches:
            data, off = text_buffers(b.column(0))
            for i, j in slices(off):
                w = words(data[off[i] : off[j]], off[i : j + 1] - off[i], ALNUM)
                where, word = _places(w.hashes, known)
                row = np.searchsorted(w.first, where, "right") - 1
                total[:-1] += np.bincount(np.unique(row * len(known) + word) % len(known), minlength=len(known))
                total[-1] += j - i
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total)), pa.int32()), pa.array(total)], ["word", "df"])

    counted = narrow(docs.select("text"), run, "word int, df long").groupBy("word").agg(F.sum("df").alias("df")).collect()
    df = np.zeros(len(index.vocabulary) + 1)
    for r in counted:
        df[r.word] = r.df
    index.idf = np.log((df[-1] + 1) / (df[:-1] + 1))
    return index


def anchors(index: Index) -> list[tuple[np.uint64, int]]:
    """The rarest word of each template's mandatory phrases and its place; a file without it doesn't hold the template."""
    out = []
    for phrases in index.phrases:
        h = np.concatenate([p for _, p in phrases])
        places = np.concatenate([np.arange(len(p)) + q for q, p in phrases])
        k = int(index.idf[np.searchsorted(index.vocabulary, h)].argmax())
        out.append((h[k], int(places[k])))
    return out


def align(h: np.ndarray, index: Index, votes: int = 2, slack: int = 2) -> dict[str, float]:
    """Labels found in one file, each with the share of its template's words that stand in place.

    Each template is looked up by its own anchor, so one notice never takes the place of another.  A kept alignment
    has every mandatory phrase within ``slack`` of its place, hence the anchor too: no other alignment can be kept.
    """
    found: dict[str, float] = {}
    for t, (word, q) in enumerate(anchors(index)):
        at = np.flatnonzero(h == word)
        if not len(at):
            continue
        text = index.texts[t]
        for start in np.unique(at[:, None] - q + np.arange(-slack, slack + 1)).tolist():
            if not all(any(_stands(h, start + place + d, p) for d in range(-slack, slack + 1)) for place, p in index.phrases[t]):
                continue
            where = np.arange(len(text)) + start
            ok = (where >= 0) & (where < len(h))
            same = text[ok][h[where[ok]] == text[ok]]
            if len(np.unique(same)) >= min(votes, len(np.unique(text))):
                found[index.labels[t]] = max(found.get(index.labels[t], 0.0), len(same) / len(text))
    return found


def _stands(h: np.ndarray, at: int, phrase: np.ndarray) -> bool:
    return 0 <= at and at + len(phrase) <= len(h) and bool((h[at : at + len(phrase)] == phrase).all())


def scan(docs: DataFrame, votes: int = 2, slack: int = 2) -> DataFrame:
    """One row for each document: SCHEMA.  score: best share of a template in place, 1 for a base phrase alone, 0 for none.

    Null and empty texts have no words, no labels ("") and score 0.  Repeated rows repeat.  Only doc_id and text
    are read; an empty table gives no rows.
    """
    index = document_frequencies(docs.select("text"), template_index())
    shared = docs.sparkSession.sparkContext.broadcast(index)

    def run(batches):
        ix = shared.value
        rare = np.unique(np.array([word for word, _ in anchors(ix)], np.uint64))
        for b in batches:
            data, off = text_buffers(b.column(1))
            for i, j in slices(off):
                w = words(data[off[i] : off[j]], off[i : j + 1] - off[i], ALNUM)
                n = j - i
                n_base, first, last = np.zeros(n, np.int64), np.full(n, 1 << 62, np.int64), np.full(n, -1, np.int64)
                base: list[set[str]] = [set() for _ in range(n)]
                for phrase, label in ix.base:
                    m = len(phrase)
                    if len(w.hashes) < m:
                        continue
                    hit = w.hashes[: len(w.hashes) - m + 1] == phrase[0]
                    for k in range(1, m):
                        hit &= w.hashes[k : len(w.hashes) - m + 1 + k] == phrase[k]
                    at = np.flatnonzero(hit)
                    row = np.searchsorted(w.first, at, "right") - 1
                    inside = at + m <= w.first[row + 1]
                    at, row = at[inside], row[inside]
                    np.add.at(n_base, row, 1)
                    np.minimum.at(first, row, at - w.first[row])
                    np.maximum.at(last, row, at - w.first[row])
                    for r in np.unique(row).tolist():
                        base[r].add(label)
                labels, score = [set(x) for x in base], np.array([1.0 if x else 0.0 for x in base])
                where, _ = _places(w.hashes, rare)
                for r in np.unique(np.searchsorted(w.first, where, "right") - 1).tolist():
                    got = align(w.hashes[w.first[r] : w.first[r + 1]], ix, votes, slack)
                    if got:
                        labels[r] |= set(got)
                        score[r] = max(score[r], *got.values())
                none = n_base == 0
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(0)[i:j], pa.array(w.counts), pa.array(n_base), pa.array(first, mask=none), pa.array(last, mask=none),
                        pa.array([",".join(sorted(x)) for x in base]), pa.array([",".join(sorted(x)) for x in labels]), pa.array(score),
                    ],
                    ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"],
                )

    return narrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, SCHEMA)
