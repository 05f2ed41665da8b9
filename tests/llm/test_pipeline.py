"""The corpus pipeline, stage by stage and as a whole, against plain loops on a small corpus with planted cases."""

import re
import zlib
from collections import Counter

import numpy as np
import pytest

import corpus_pipeline
from stablecf.llm import packing

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def corpus():
    rng = np.random.default_rng(2)
    words = [f"w{i}" for i in range(400)]
    say = lambda n: " ".join(rng.choice(words, n))
    item = " ".join(f"item{i}" for i in range(14))
    rows, labels = [], []
    for i in range(200):
        bad = i % 4 == 0
        rows.append((i, say(40) + (" vile scum" if bad else "")))
        labels.append((i, 1, int(bad)))
    a, b = say(80), say(80)
    rows += [(300, a), (301, a.replace(" ", "  ")), (302, a + " w1"), (303, b), (304, b.replace("w", "W", 3)), (305, "an " + item + " here"), (306, "short"), (307, ""), (308, None), (309, " "), (310, "short "), (311, "vile scum all of it")]
    rows += [(None, say(30)), (None, "vile scum"), (320, say(20)), (320, say(20)), (330, say(9000))]
    return rows, labels, [(1, item), (2, None), (3, "")]


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW))


def key(i):
    return (1 << 63) - 1 if i is None else i


def kept_by_hand(rows, item):
    toxic = {i for i, t in rows if "vile" in (t or "")}
    rows = [r for r in rows if r[0] not in toxic]
    first = {}
    for i, t in rows:
        n = re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
        first[n] = min(first.get(n, key(i)), key(i))
    kept = set(first.values())
    rows = [r for r in rows if key(r[0]) in kept]
    sets = [(key(i), {tuple(w[j : j + 5]) for j in range(len(w) - 4)} if len(w := words(t)) >= 5 else {tuple(w)} if w else set()) for i, t in rows]
    comp = {i: i for i, _ in sets}
    for _ in range(4):
        for i, x in sets:
            for j, y in sets:
                if x and y and 100 * len(x & y) >= 75 * len(x | y):
                    comp[i] = comp[j] = min(comp[i], comp[j])
    rows = [r for r in rows if comp[key(r[0])] == key(r[0])]
    win = [tuple(item.split()[j : j + 10]) for j in range(5)]
    hit = {i for i, t in rows if any(tuple(w[j : j + 10]) in win for w in [words(t)] for j in range(len(w) - 9))}
    return [r for r in rows if r[0] not in hit]


@pytest.fixture(scope="module")
def sf(spark, tmp_path_factory):
    rows, labels, bench = corpus()
    d = tmp_path_factory.mktemp("corpus")
    spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], SCHEMA).repartition(3).write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    spark.createDataFrame(bench, "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    return str(d)


def test_pipeline_equals_loops(spark, sf):
    from tokenizers import Tokenizer

    rows, _, bench = corpus()
    want = kept_by_hand(rows, bench[0][1])
    assert 0 < len(want) < len(rows) - 50
    tok = Tokenizer.from_file(packing.vocabulary_path(None))
    texts = Counter()
    for i, t in want:
        ids = np.array(tok.encode(t or "", add_special_tokens=False).ids + [1], "<u4")
        texts[(i, len(ids), zlib.crc32(ids.tobytes()) if len(ids) <= 2048 else None)] += 1
    pieces = corpus_pipeline.run(spark, sf).collect()
    got = Counter()
    for p in pieces:
        if p.start == 0:
            got[(p.doc_id, p.doc_tokens, p.ids_crc32 if p.length == p.doc_tokens else None)] += 1
    whole = lambda c: Counter({(i, n): m for (i, n, _), m in c.items()})
    assert whole(got) == whole(texts)
    assert all(texts[k] for k in got if k[2] is not None)
    for i, n in {(p.doc_id, p.doc_tokens) for p in pieces if p.doc_id not in (None, 320)}:
        mine = sorted((p.start, p.length) for p in pieces if p.doc_id == i)
        assert [s for s, _ in mine] == [0, *np.cumsum([x for _, x in mine])[:-1].tolist()] and sum(x for _, x in mine) == n


def test_stages_take_empty_null_and_clashing_tables(spark, sf):
    docs = spark.createDataFrame([(None, None, "x", None, None, 1, "k"), (None, "", "x", None, None, 2, "k"), (3, "one two three", None, None, None, 3, "k"), (3, "one two three", None, None, None, 3, "k")], SCHEMA + ", component_id long, row string")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns and out.count() in (2, 3, 4), name
        assert stage(spark, docs.where("false"), sf).count() == 0, name
    assert corpus_pipeline.pack(spark, docs.where("false"), sf).count() == 0
    assert corpus_pipeline.pack(spark, docs, sf).groupBy("doc_id").agg({"doc_tokens": "max"}).count() == 2
