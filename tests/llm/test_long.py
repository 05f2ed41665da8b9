"""Texts of megabytes, and copies of them, through the operators that read whole texts."""

import hashlib

import numpy as np
import pytest

from stablecf.llm import exact_dedup, jaccard, licences, packing, ppm, repeats, toxicity


@pytest.fixture(scope="module")
def long(spark):
    rng = np.random.default_rng(3)
    words = [f"word{i}" for i in range(3000)]
    a = " ".join(rng.choice(words, 200_000))
    b = a[: len(a) // 2] + " changed " + a[len(a) // 2 :]
    rows = [(1, a), (2, b), (3, a), (4, "x" * 1_200_000), (5, " " * 1_000_000)]
    return rows, spark.createDataFrame(rows, "doc_id long, text string").repartition(3)


def test_long_texts(spark, long):
    rows, df = long
    text = dict(rows)
    assert {r.doc_id: r.component_id for r in jaccard.similar(spark, df).collect()} == {1: 1, 2: 1, 3: 1, 4: 4, 5: 5}
    assert {r.doc_id: r.keep_id for r in exact_dedup.exact_dedup(spark, df).collect()} == {1: 1, 2: 2, 3: 1, 4: 4, 5: 5}
    got = {r.doc_id: r for r in repeats.remove_repeats(spark, df, with_text=False).collect()}
    # the later copy goes whole; of the changed one what is not within 49 bytes of the change
    seen = {text[1][i : i + 50] for i in range(len(text[1]) - 49)}
    kept = bytearray(b"\1" * len(text[2]))
    for i in range(len(text[2]) - 49):
        if text[2][i : i + 50] in seen:
            kept[i : i + 50] = bytes(50)
    left = "".join(c for c, k in zip(text[2], kept) if k)
    assert got[3].n_removed == len(text[3]) and got[1].n_removed == got[4].n_removed == got[5].n_removed == 0
    assert got[2].kept_sha256 == hashlib.sha256(left.encode()).hexdigest() and got[2].n_removed == len(text[2]) - len(left)
    packed = packing.pack_documents(spark, df).groupBy("doc_id").agg({"length": "sum", "doc_tokens": "max"}).collect()
    assert len(packed) == 5 and all(r["sum(length)"] == r["max(doc_tokens)"] for r in packed)
    scored = {r.doc_id: r for r in ppm.score_documents(spark, df).collect()}
    assert scored[1].n_tokens == 200_001 and scored[1].score == pytest.approx(scored[3].score) and scored[5].n_bytes == 1
    assert {r.doc_id: r.n_words for r in licences.scan_documents(spark, df).collect()}[1] == 200_000
    labels = spark.createDataFrame([(1, 0, 0), (4, 0, 1)], "doc_id long, quality int, toxic int")
    assert toxicity.toxicity(spark, df, labels).count() == 5
