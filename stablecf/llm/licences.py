"""Licence scan by a positional index of rare licence words.

Templates are one-line notices (below) and whole licence texts or headers
(``licence_texts.txt``).  The index holds, for every template's rarest words
(highest IDF over the templates; a text has one for every eight of its words),
their postings (template, position).  Of a file's words those with postings are
looked up, each at all its places, and vote for (template, start = file position
- template position).  Votes whose starts are near count together, and an
alignment's starts may drift by the slack and an eighth of the template in all,
so that small edits do not break a match and repetitive text does not make one.  A candidate is a licence if enough of its rare words agree
and each of its mandatory key phrases stands in the file word for word.  Exact
base phrases are looked up in the same pass.

Defined results: null text is empty (no words); repeated rows are scanned one
by one; ties between templates all count; an empty table gives no rows.
"""

from __future__ import annotations

import math
import os
import re
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from stablecf.llm import kernels as K
from stablecf.llm.common import LOWER, NO_ID, UPPER, ids_and_texts, ship

# fixed values: base phrases and their labels
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}

# fixed values: (label, notice, mandatory key phrases)
TEMPLATES = [
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ["permission is hereby granted free of charge"]),
    ("mit", "released under the mit license", ["mit license"]),
    ("mit", "licensed under the mit license", ["mit license"]),
    ("apache-2", "licensed under the apache license version 2 0", ["apache license version 2"]),
    ("apache-2", "you may not use this file except in compliance with the license you may obtain a copy of the license at", ["except in compliance with the license", "apache"]),
    ("gpl-3", "licensed under the gnu general public license version 3", ["gnu general public license version 3"]),
    ("gpl-3", "under the terms of the gnu general public license as published by the free software foundation either version 3 of the license", ["gnu general public license", "version 3"]),
    ("gpl-2", "licensed under the gnu general public license version 2", ["gnu general public license version 2"]),
    ("gpl-2", "under the terms of the gnu general public license as published by the free software foundation either version 2 of the license", ["gnu general public license", "version 2"]),
    ("lgpl", "licensed under the gnu lesser general public license", ["gnu lesser general public license"]),
    ("agpl-3", "licensed under the gnu affero general public license version 3", ["gnu affero general public license"]),
    ("mpl-2", "subject to the terms of the mozilla public license v 2 0", ["mozilla public license"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ["redistribution and use in source and binary forms"]),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ["with or without fee is hereby granted"]),
    ("unlicense", "this is free and unencumbered software released into the public domain", ["unencumbered software released into the public domain"]),
    ("cc0", "cc0 1 0 universal public domain dedication", ["cc0 1 0"]),
    ("cc-by-nc", "licensed under cc by nc 4 0", ["cc by nc"]),
    ("cc-by-nc", "creative commons attribution noncommercial 4 0 international license", ["creative commons attribution noncommercial"]),
    ("cc-by-sa", "licensed under cc by sa 4 0", ["cc by sa"]),
    ("cc-by-sa", "creative commons attribution sharealike 4 0 international license", ["creative commons attribution sharealike"]),
    ("cc-by", "creative commons attribution 4 0 international license", ["creative commons attribution 4 0"]),
]

SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, matches array<struct<label:string, word:long, share:double>>"


def words_of(text: str) -> str:
    """A text as its lower-case words, blank between them."""
    return " ".join(re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text.translate(str.maketrans(UPPER, LOWER))))


def whole_texts(path: str = os.path.join(os.path.dirname(os.path.abspath(__file__)), "licence_texts.txt")) -> list[tuple[str, str, list[str]]]:
    """(label, text, mandatory phrases) of a file of sections: a line ``== label | phrase | phrase``, then the text."""
    out = []
    with open(path, encoding="utf-8") as f:
        for part in f.read().split("\n== "):
            head, _, body = part.removeprefix("== ").partition("\n")
            label, *phrases = [x.strip() for x in head.split("|")]
            out.append((label, words_of(body), phrases))
    return out


class LicenceIndex:
    def __init__(self, templates=None, base=BASE, rare_words: int = 6, need: float = 0.75, slack: int = 3) -> None:
        templates = [*TEMPLATES, *whole_texts()] if templates is None else templates
        self.templates, self.base, self.need = templates, base, need
        words = [t[1].split() for t in templates]
        self.slack = np.array([max(slack, len(ws) // 20) for ws in words])
        self.drift = np.array([max(slack, len(ws) // 8) for ws in words])
        df = Counter(w for ws in words for w in set(ws))
        self.idf = {w: math.log((1 + len(words)) / n) for w, n in df.items()}
        self.rare: list[int] = []  # each template's number of rare places
        postings: dict[str, list[tuple[int, int]]] = defaultdict(list)
        for t, ws in enumerate(words):
            top = set(sorted(set(ws), key=lambda w: (-self.idf[w], ws.index(w)))[: max(rare_words, len(ws) // 8)])
            places = [(p, w) for p, w in enumerate(ws) if w in top]
            self.rare.append(len(places))
            for p, w in places:
                postings[w].append((t, p))
        phrases = [p.split() for p in base] + [p.split() for t in templates for p in t[2]]
        vocab = sorted({*postings, *(w for p in phrases for w in p)}, key=lambda w: K.hash_text(w.encode()))
        self.keys = np.array([K.hash_text(w.encode()) for w in vocab], dtype=np.uint64)
        code = {w: i for i, w in enumerate(vocab)}
        self.code = code
        self.n_post = np.array([len(postings.get(w, ())) for w in vocab], dtype=np.int64)
        self.p_at = np.cumsum(self.n_post) - self.n_post
        flat = [x for w in vocab for x in postings.get(w, ())]
        self.p_template, self.p_pos = np.array([x[0] for x in flat], dtype=np.int64), np.array([x[1] for x in flat], dtype=np.int64)
        self.phrases = {" ".join(p): [code[w] for w in p] for p in phrases}

    def codes(self, hashes: np.ndarray) -> np.ndarray:
        """Vocabulary number of each word, -1 for words of no template."""
        at = np.minimum(np.searchsorted(self.keys, hashes), len(self.keys) - 1)
        return np.where(self.keys[at] == hashes, at, -1)

    def places(self, phrase: str, codes: np.ndarray, where: list[np.ndarray], doc: np.ndarray) -> np.ndarray:
        """Starts of the phrase, found from its rarest word here; where[c]: the places of code c."""
        want = self.phrases[phrase]
        rare = min(range(len(want)), key=lambda j: len(where[want[j]]))
        s = where[want[rare]] - rare
        s = s[(s >= 0) & (s + len(want) <= len(codes))]
        for j, c in enumerate(want):
            s = s[codes[s + j] == c]
        return s[doc[s] == doc[s + len(want) - 1]] if len(s) else s

    def scan(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> list[tuple]:
        """Per text: (words, base places, first, last, base labels, labels, score, matches)."""
        buf, starts, ends = K.spaced(data, starts, ends)
        buf = K.LOWER[buf]
        ws, we = K.word_spans(buf, K.ALNUM)
        lo, hi = np.searchsorted(ws, starts), np.searchsorted(ws, ends)
        codes = self.codes(K.word_hashes(buf, ws, we))
        hit = np.flatnonzero(codes >= 0)
        doc = np.repeat(np.arange(len(starts)), hi - lo)
        order = hit[np.argsort(codes[hit], kind="stable")]
        edge = np.searchsorted(codes[order], np.arange(len(self.keys) + 1))
        where = [order[edge[c] : edge[c + 1]] for c in range(len(self.keys))]
        base: dict[int, list[tuple[int, str]]] = defaultdict(list)
        for p, label in self.base.items():
            for s in self.places(p, codes, where, doc).tolist():
                base[int(doc[s])].append((s - int(lo[doc[s]]), label))
        found = self.candidates(codes, hit, doc, lo)
        keys = {p: np.sort(self.places(p, codes, where, doc)) for p in {p for t in found for p in self.templates[t][2]}}
        edges = [*lo.tolist(), len(codes)]

        def holds(p: str, t: int, d: int, start: int) -> bool:
            """Whether the phrase lies in the aligned notice; one that the notice itself doesn't have may be anywhere in the text."""
            a, b, notice, room = edges[d], edges[d + 1], self.templates[t][1], int(self.drift[t])
            if f" {p} " in f" {notice} ":
                a, b = max(a, edges[d] + start - room), min(b, edges[d] + start + len(notice.split()) + room)
            i = np.searchsorted(keys[p], a)
            return bool(i < len(keys[p]) and keys[p][i] + len(self.phrases[p]) <= b)

        more: dict[int, list[tuple[str, int, float]]] = defaultdict(list)
        for t, hits in found.items():
            label, _, mandatory = self.templates[t]
            for d, start, share in hits:
                if all(holds(p, t, d, start) for p in mandatory):
                    more[d].append((label, max(0, start), share))
        out = []
        for d, n in enumerate((hi - lo).tolist()):
            b, m = base.get(d, []), more.get(d, [])
            bl, at = {x[1] for x in b}, [x[0] for x in b]
            out.append((n, len(b), min(at, default=None), max(at, default=None), ",".join(sorted(bl)), ",".join(sorted(bl | {x[0] for x in m})), 1.0 if b else max((x[2] for x in m), default=0.0), sorted(set(m))))
        return out

    def candidates(self, codes: np.ndarray, hit: np.ndarray, doc: np.ndarray, lo: np.ndarray) -> dict[int, list[tuple[int, int, float]]]:
        """template -> (text, start, share of its rare words that agree on the start)."""
        n = self.n_post[codes[hit]]
        total = np.cumsum(n) - n
        post = np.repeat(self.p_at[codes[hit]] - total, n) + np.arange(int(n.sum()))
        at = np.repeat(hit, n)
        t, start = self.p_template[post], at - self.p_pos[post]
        rel, d = start - lo[doc[at]], doc[at]
        order = np.lexsort((self.p_pos[post], rel, d, t))
        t, rel, d, pos = t[order], rel[order], d[order], self.p_pos[post][order]
        found: dict[int, list[tuple[int, int, float]]] = defaultdict(list)
        if not len(t):
            return found
        # votes whose starts are at most the slack apart are one chain
        new = np.ones(len(t), bool)
        new[1:] = (t[1:] != t[:-1]) | (d[1:] != d[:-1]) | (rel[1:] - rel[:-1] > self.slack[t[1:]])
        first = np.flatnonzero(new)
        last = np.append(first[1:], len(t))
        need = np.array(self.rare)[t[first]] * self.need
        for a, b in zip(first[last - first >= need].tolist(), last[last - first >= need].tolist(), strict=True):
            name, doc_, rare = int(t[a]), int(d[a]), self.rare[int(t[a])]
            for start, k in _alignments(rel[a:b].tolist(), pos[a:b].tolist(), int(self.drift[name]), self.need * rare):
                found[name].append((doc_, start, k / rare))
        return found


def _alignments(rel: list[int], pos: list[int], drift: int, need: float) -> list[tuple[int, int]]:
    """(start, different places) of the stretches of a chain, at most ``drift`` long, on which at least ``need`` places of the template agree."""
    out, held, i = [], Counter(), 0
    for j, (r, p) in enumerate(zip(rel, pos, strict=True)):
        held[p] += 1
        while r - rel[i] > drift:
            held[pos[i]] -= 1
            if not held[pos[i]]:
                del held[pos[i]]
            i += 1
        full = j + 1 == len(rel) or rel[j + 1] - rel[i] > drift
        if full and len(held) >= need:
            out.append((rel[i], len(held)))
            held, i = Counter(), j + 1
    return out


def scan_documents(spark: SparkSession, df: DataFrame, id_col: str = "doc_id", text_col: str = "text", index: LicenceIndex | None = None) -> DataFrame:
    """One row per document, as ``SCHEMA`` says.  The index is a few kilobytes whatever the input."""
    ship(spark)
    index = index or LicenceIndex()
    names = [c.split()[0] for c in SCHEMA.split(", matches")[0].split(", ")]

    def run(batches):
        for b in batches:
            data, starts, ends = K.as_bytes(b.column(1))
            ids = b.column(0).to_pylist()
            for i, j in K.blocks(starts, ends):
                rows = index.scan(data, starts[i:j], ends[i:j])
                cols = [[None if x == NO_ID else x for x in ids[i:j]], *zip(*(r[:7] for r in rows), strict=True)]
                kinds = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.float64()]
                arrays = [pa.array(c, k) for c, k in zip(cols, kinds, strict=True)]
                m = pa.array([[{"label": a, "word": w, "share": s} for a, w, s in r[7]] for r in rows], pa.list_(pa.struct([("label", pa.string()), ("word", pa.int64()), ("share", pa.float64())])))
                yield pa.RecordBatch.from_arrays([*arrays, m], [*names, "matches"])

    return ids_and_texts(df, id_col, text_col).mapInArrow(run, SCHEMA)
