"""Licence scan: base columns against a loop, labels on whole, edited and repetitive texts."""

import re
from collections import Counter

import numpy as np
import pyarrow.parquet as pq

from stablecf.llm import licences

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def scan(spark, rows):
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, label string").repartition(3)
    return licences.scan_documents(spark, df).collect()


def test_base_columns_by_brute_force(spark):
    t = pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["doc_id", "text"])
    rows = list(zip(t["doc_id"].to_pylist(), t["text"].to_pylist())) + [(None, None), (None, "under the MIT license, under the mit License"), (3, "CC BY NC " * 20000), (4, "")]
    want = Counter()
    for i, x in rows:
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (x or "").translate(LOW))
        at = []
        for p, label in licences.BASE.items():
            p = p.split()
            at += [(j, label) for j in range(len(w) - len(p) + 1) if w[j : j + len(p)] == p]
        want[(i, len(w), len(at), min((a[0] for a in at), default=None), max((a[0] for a in at), default=None), ",".join(sorted({a[1] for a in at})))] += 1
    got = scan(spark, rows)
    assert Counter((r.doc_id, r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) for r in got) == want
    assert all(set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1 for r in got)


def test_whole_and_edited_texts(spark):
    rng = np.random.default_rng(1)
    rows, want = [], {}
    for n, (label, text, phrases) in enumerate(licences.whole_texts()):
        ws, keep = text.split(), set()
        for p in phrases:
            p = p.split()
            keep |= {j + o for j in range(len(ws) - len(p) + 1) if ws[j : j + len(p)] == p for o in range(len(p))}
        assert keep, label
        rows.append((n, "A file.\n" + text.upper() + "\nIts code."))
        edited = [f"edit{j}" if j not in keep and rng.random() < 0.04 else w for j, w in enumerate(ws)]
        for j in sorted((j for j in range(len(ws)) if j not in keep and rng.random() < 0.02), reverse=True):
            edited.insert(j, "inserted")
        edited_ok = keep <= set(range(len(ws)))
        rows.append((100 + n, "word " * 50 + " ".join(edited) + " word" * 50))
        want[n] = label
        want[100 + n] = label if edited_ok else None
        rows.append((200 + n, " ".join(rng.permutation(ws))))
    got = {r.doc_id: r.labels.split(",") for r in scan(spark, rows)}
    assert all(want[i] in got[i] for i in range(len(licences.whole_texts())))
    near = [want[i] in got[i] for i in want if i >= 100]
    assert sum(near) >= 0.7 * len(near)
    assert all(not any(x for x in got[i]) for i in got if i >= 200)


def test_repetitive_text_is_no_match(spark):
    words = next(t for label, t, _ in licences.whole_texts() if label == "unlicense").split()
    spread = " ".join(f"{w} " + "filler " * 6 for w in words) + " unencumbered software released into the public domain"
    again = " ".join(w for w in words for _ in range(9))
    got = {r.doc_id: r.labels for r in scan(spark, [(1, spread), (2, again), (3, "software " * 50000)])}
    assert got == {1: "", 2: "", 3: ""}
    assert licences._alignments([0, 1, 2, 9, 10, 11], [1, 2, 3, 1, 2, 3], 3, 3) == [(0, 3), (9, 3)]
