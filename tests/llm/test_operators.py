import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from stablecf.llm import decontaminate, deepshallow, exact_dedup, jaccard, licences, merkle_audit, packing, ppm, repeats, sanitise, toxicity
from stablecf.llm.components import components

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
BASE = "the quick brown fox jumps over the lazy dog while seven ancient wizards quietly brew potions under a pale winter moon tonight "
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n long, key string, chunk int"


def texts():
    rng = np.random.default_rng(4)
    words = [f"w{i}" for i in range(300)] + ["über", "été"]
    out = [(0, None), (1, ""), (2, " \t\n"), (3, "One two"), (4, BASE * 3), (5, BASE * 3), (6, (BASE * 3).replace("fox", "cat")), (7, (BASE * 3).replace(" ", "  ")), (8, "a" * 5000), (9, "a" * 200)]
    out += [(20 + i, " ".join(rng.choice(words, 40))) for i in range(12)]
    out += [(40, "x " * 30000), (41, "mail bob@example.org or +1 (555) 010-9999, 10.0.0.1, 300.1.1.1 card 4111 1111 1111 1111"), (42, "Licensed under the GNU General Public License, version 3. Released under the MIT License."), (None, BASE * 3), (3, "One two")]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "en", None, None, 5, "k", 9) for i, t in texts()], SCHEMA).repartition(5).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def key(i):
    return (1 << 62) if i is None else i


def test_exact_dedup(spark, docs, empty):
    norm = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    least, size = {}, Counter()
    for i, t in texts():
        least[norm(t)] = min(least.get(norm(t), 1 << 62), key(i))
        size[norm(t)] += 1
    want = Counter((i, least[norm(t)], size[norm(t)], key(i) == least[norm(t)], hashlib.sha256(norm(t).encode()).hexdigest()) for i, t in texts())
    assert Counter(map(tuple, exact_dedup.exact_dedup(spark, docs).collect())) == want
    weak = exact_dedup.exact_dedup(spark, docs, bucket_keys=2, key=lambda c: F.pmod(F.xxhash64(c), F.lit(3)).cast("long"))
    assert Counter(map(tuple, weak.collect())) == want
    assert exact_dedup.exact_dedup(spark, empty).count() == 0


def test_buckets_split_and_the_directory_covers(spark):
    rng = np.random.default_rng(6)
    keys = [int(k) for k in rng.integers(-(1 << 63), 1 << 63, 300)] + [int(k) >> 8 for k in rng.integers(0, 1 << 63, 60)] + [7] * 40
    keyed = spark.createDataFrame([(k, i % 3) for i, k in enumerate(keys)], "key long, salt int")
    for cap, deep in ((10, 12), (40, 3), (1000, 5)):
        entries, depth = exact_dedup.build_index(spark, keyed, cap, deep)
        held = {}
        for r in entries.collect():
            assert (r.key % (1 << 64)) >> (64 - r.depth) == r.prefix if r.depth else r.prefix == 0
            held.setdefault((r.depth, r.prefix), set()).add(r.key)
        assert entries.agg(F.sum("n")).first()[0] == len(keys) and sum(map(len, held.values())) == len(set(keys))
        assert all(len(v) <= cap or d == deep for (d, _), v in held.items()) and depth == max(d for d, _ in held) <= deep
        cells = {r.cell: (r.bucket_depth, r.bucket_prefix) for r in exact_dedup.directory(entries, depth).collect()}
        assert all(cells[(k % (1 << 64)) >> (64 - depth) if depth else 0] == b for b, v in held.items() for k in v)
    assert len(exact_dedup.build_index(spark, keyed, 10, 12)[0].select("depth").distinct().collect()) > 1


def test_jaccard(spark, docs, empty):
    sets = []
    for i, t in texts():
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW))
        sets.append((i, {tuple(w[j : j + 5]) for j in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()))
    up = {key(i): key(i) for i, _ in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in sets:
        for j, b in sets:
            if a and b and 100 * len(a & b) >= 75 * len(a | b):
                x, y = root(key(i)), root(key(j))
                up[max(x, y)] = min(x, y)
    want = Counter((i, len(s), None if root(key(i)) == key(None) else root(key(i))) for i, s in sets)
    assert Counter(map(tuple, jaccard.similar(spark, docs).collect())) == want
    assert jaccard.similar(spark, empty).count() == 0


def test_repeats(spark, docs, empty):
    first = {}
    for i, t in texts():
        b = (t or "").encode()
        for p in range(len(b) - 49):
            first[b[p : p + 50]] = min(first.get(b[p : p + 50], 1 << 62), key(i))
    want = Counter()
    for i, t in texts():
        b = (t or "").encode()
        gone = np.zeros(len(b) + 1, bool)
        for p in range(len(b) - 49):
            if first[b[p : p + 50]] < key(i):
                gone[p : p + 50] = True
        kept = bytes(x for x, g in zip(b, gone) if not g)
        want[(i, len(b), int(gone.sum()), int((gone[1:] & ~gone[:-1]).sum()) + int(gone[0]), hashlib.sha256(kept).hexdigest())] += 1
    got = repeats.remove_repeats(spark, docs, with_text=False).drop("kept")
    assert Counter(map(tuple, got.collect())) == want
    assert repeats.remove_repeats(spark, empty).count() == 0


def test_deep_shallow_sort():
    rng = np.random.default_rng(1)
    buf = np.append(rng.integers(97, 99, 3000).astype(np.uint8), np.zeros(8, np.uint8))
    buf[1000:1100] = buf[:100]
    starts = np.arange(2900)
    order, cls = deepshallow.sort_strings(buf, starts, 50, shallow=8)
    s = [buf[starts[i] : starts[i] + 50].tobytes() for i in order]
    assert s == sorted(s)
    assert all((s[i] == s[i + 1]) == (cls[i] == cls[i + 1]) for i in range(len(s) - 1))


def test_decontaminate(spark, docs, empty):
    items = [(1, "jumps over the lazy dog while seven ancient wizards quietly brew potions"), (2, "two"), (3, None), (4, "never seen words at all here"), (5, "jumps over the lazy dog while seven ancient wizards quietly")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    tok = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOW))
    want = Counter()
    for i, t in texts():
        w, hit, found = tok(t), set(), set()
        for k, it in items:
            b = tok(it)
            n = min(10, len(b))
            for win in {tuple(b[j : j + n]) for j in range(len(b) - n + 1)} if b else ():
                for p in range(len(w) - n + 1):
                    if tuple(w[p : p + n]) == win:
                        hit |= set(range(p, p + n))
                        found.add(k)
        ids = ",".join(sorted(map(str, found)))
        want[(i, len(w), len(hit), len(found), hashlib.sha256(ids.encode()).hexdigest(), bool(hit))] += 1
    run = lambda d, b, **x: Counter(map(tuple, decontaminate.digest(decontaminate.decontaminate(spark, d, b, **x)).collect()))
    assert run(docs, bench) == want
    assert run(docs, bench, broadcast_bytes=-1) == want
    assert not run(empty, bench)
    assert all(not r[5] for r in run(docs, bench.where("false")))
    hot = spark.createDataFrame([(None, "a hot text two " + str(i % 3)) for i in range(500)] + [(None, "clean")], "doc_id long, text string")
    assert sorted((r[1], r[2]) for r in run(hot, bench).elements()) == [(1, 0)] + [(5, 1)] * 500


def test_jaccard_hot_tokens_in_blocks(spark):
    """A passage that all documents have, in documents that link in chains only: every round works, tokens are dealt to blocks of three."""
    rng = np.random.default_rng(8)
    common = " ".join(f"c{i}" for i in range(12))
    rows = []
    for g in range(6):
        words = [f"g{g}w{i}" for i in range(60)]
        for v in range(5):
            for x in rng.integers(0, 60, 2):
                words[x] = f"g{g}v{v}x{x}"
            rows.append((100 * g + v, f"{common} {' '.join(words)}"))
    sets = {}
    for i, t in rows:
        w = t.split()
        sets[i] = {tuple(w[j : j + 5]) for j in range(len(w) - 4)}
    comp = {i: i for i in sets}
    for _ in sets:
        for i in sets:
            for j in sets:
                if 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                    comp[i] = comp[j] = min(comp[i], comp[j])
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert len(set(comp.values())) > 6
    for hot in (3, 512):
        assert {r.doc_id: r.component_id for r in jaccard.similar(spark, df, hot=hot).collect()} == comp


def test_jaccard_rows_that_share_an_id(spark):
    word = lambda p, n: " ".join(f"{p}{i}" for i in range(n))
    for ids in ((None, None), (90, 90)):
        rows = []
        for g in range(4):  # rows of ids share an id, each linked with its own two documents, which link through it alone
            x, y = word(f"g{g}x", 200), f" {word(f'g{g}y', 20)}"
            rows += [(ids[0], x + f" own{g}"), (10 * g + 5, x + y + f" {word(f'p{g}', 20)}"), (10 * g + 6, f"{word(f'q{g}', 40)} {x}")]
        rows.append((70, "nothing of this is anywhere else in any text"))
        got = {(r.doc_id, r.component_id) for r in jaccard.similar(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()}
        assert got == {(i, 5) for i, _ in rows if i != 70} | {(70, 70)}


def test_sanitise(spark, docs, empty):
    got = {r.doc_id: r for r in sanitise.digest(sanitise.sanitise(spark, docs, with_text=False)).collect()}
    r = got[41]
    assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == (1, 1, 1, 1)
    t = dict(texts())[41]
    e, p, ip, c = (t.index(x) for x in ("bob@", "+1", "10.0.0.1", "4111"))
    assert r.spans == f"email:{e}:{e + 15},phone:{p}:{p + 17},ip:{ip}:{ip + 8},card:{c}:{c + 19}"
    assert len(got) == len({i for i, _ in texts()}) and sanitise.sanitise(spark, empty).count() == 0
    rows = [(i, f"filler{i} words{i} Zorblax writes to zed@corp.example today") for i in range(6)] + [(100 + i, "other people write to nobody today, words only") for i in range(60)]
    found = {r.doc_id: r for r in sanitise.sanitise(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert any(s["value"] == "zorblax" for s in found[0]["spans"]) and "[EMAIL]" in found[0]["sanitised"] and "Zorblax" not in found[0]["sanitised"]
    assert not found[100]["spans"]


def test_sanitise_rare_entity(spark):
    rows = [(0, "other people write: Zorblax writes to zed@corp.example today")] + [(100 + i, "other people write to nobody today, words only") for i in range(400)]
    found = {r.doc_id: r for r in sanitise.sanitise(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    values = {s["value"] for s in found[0]["spans"]}
    assert "zorblax" in values and not values & {"other", "people", "today"} and "Zorblax" not in found[0]["sanitised"] and not found[100]["spans"]


def test_sanitise_whole_documents(spark):
    rows = [(0, "ZORBLAX head. " + "other people write words today " * 60 + "mail zed@corp.example " + "other people write " * 60 + "signed Zorblax"), (1, "Zorblax has no address here"), (None, "zorblax"), (None, "zorblaxes")]
    d = spark.createDataFrame(rows + [(100 + i, "other people write to nobody today, words only, mail address here") for i in range(6000)], "doc_id long, text string")
    found = sanitise.sanitise(spark, d).where("doc_id < 100 or doc_id is null").collect()
    at = {i: sorted((s["start"], s["end"]) for r in found if r.doc_id == i for s in r["spans"] if s["value"] == "zorblax") for i in (0, 1, None)}
    n = len(rows[0][1])
    assert at == {0: [(0, 7), (n - 7, n)], 1: [(0, 7)], None: [(0, 7)]}
    assert {r.sanitised for r in found if r.doc_id is None} == {"[TERM]", "zorblaxes"} and "zorblax" not in "".join(r.sanitised.lower() for r in found if r.doc_id is not None)


def test_licences(spark, docs, empty):
    got = {r.doc_id: r for r in licences.scan_documents(spark, docs).collect()}
    assert got[42].base_labels == "mit" and got[42].labels == "gpl-3,mit" and got[42].n_base == 1 and got[42].score == 1
    assert got[0].n_words == 0 and got[0].first_word is None and got[4].labels == ""
    assert licences.scan_documents(spark, empty).count() == 0


def test_licence_phrases_stand_in_their_notice(spark):
    notice = "under the terms of the GNU General Public License as published by the Free Software Foundation; either version {} of the License"
    far = " filler" * 60 + " this needs version 3 of another program"
    apache = "Licensed under the Apache License, Version 2.0. You may not use this file except in compliance with the License. You may obtain a copy of the License at"
    rows = [(0, notice.format(2) + far), (1, notice.format(3)), (2, far + " " + notice.format(2)), (3, "x " * 9 + notice.format(2) + " " + notice.format(3)), (4, apache)]
    got = {r.doc_id: r.labels for r in licences.scan_documents(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {0: "gpl-2", 1: "gpl-3", 2: "gpl-2", 3: "gpl-2,gpl-3", 4: "apache-2"}


def test_packing(spark, docs, empty):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.vocabulary_path(None))
    want = Counter()
    for i, t in texts():
        ids = np.array(tok.encode(t or "", add_special_tokens=False).ids + [1], "<u4")
        want[(i, len(ids))] += 1
    rows = packing.pack_documents(spark, docs).collect()
    assert Counter({k: n for k, n in Counter((r.doc_id, r.doc_tokens) for r in rows if r.start == 0).items()}) == want
    seen = Counter(i for i, _ in texts())
    each = {i: np.array(tok.encode(t or "", add_special_tokens=False).ids + [1], "<u4") for i, t in texts() if seen[i] == 1}
    for r in rows:
        if r.doc_id in each:
            assert zlib.crc32(each[r.doc_id][r.start : r.start + r.length].tobytes()) == r.ids_crc32
    at = {}
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == at.get(r.sequence_id, 0)
        at[r.sequence_id] = r.offset + r.length
    assert max(at.values()) <= 2048 and packing.pack_documents(spark, empty).count() == 0


def test_first_fit_decreasing_by_scan():
    rng = np.random.default_rng(2)
    sizes = rng.integers(1, 100, 300).tolist()
    room, want = [], []
    for i in sorted(range(300), key=lambda i: -sizes[i]):
        b = next((b for b, r in enumerate(room) if r >= sizes[i]), None)
        if b is None:
            room.append(100)
            want.append([])
            b = len(room) - 1
        room[b] -= sizes[i]
        want[b].append(i)
    assert packing.first_fit_decreasing(sizes, 100) == want


def test_ppm(spark, docs, empty):
    tok = lambda t: re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW))
    held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 5 == 1
    count, trie = Counter(), ppm.BytePPM()
    for i, t in texts():
        if not held(i):
            count.update([*tok(t), "\0end"])
            trie.train(ppm.stream_of(t or ""))
    n, v = sum(count.values()), len(count)
    got = {}
    for r in ppm.score_documents(spark, docs).collect():
        got[r.doc_id] = r
    for i, t in texts():
        w, r = [*tok(t), "\0end"], got[i]
        assert (r.n_tokens, r.n_known, r.train_tokens, r.held_out) == (len(w), sum(count[x] > 0 for x in w), n, held(i))
        assert r.base_score == pytest.approx(sum(math.log10((count[x] + 0.5) / (n + 0.5 * (v + 1))) for x in w), rel=1e-9)
        if i != 40:
            assert r.score == pytest.approx(trie.code(ppm.stream_of(t or "")), rel=1e-4, abs=1e-4)
    assert ppm.score_documents(spark, empty).count() == 0 and ppm.adaptive_documents(spark, empty).count() == 0
    few = spark.createDataFrame([(1, "abab abab"), (None, None), (2, "a\0b")], "doc_id long, text string")
    got = {r.doc_id: r for r in ppm.adaptive_documents(spark, few).collect()}
    assert got[1].score == pytest.approx(ppm.BytePPM().code(b"abab abab\0", adapt=True)) and got[2].n_bytes == 4
    for order in (2, 6):
        trie = ppm.BytePPM(order)
        for t in ("abab abab", "", "a\0b"):
            trie.train(ppm.stream_of(t))
        for r in ppm.score_documents(spark, few, fold=9, order=order).collect():
            assert r.score == pytest.approx(trie.code(ppm.stream_of({1: "abab abab", None: "", 2: "a\0b"}[r.doc_id])), rel=1e-5)
    assert ppm.BytePPM().code(b"abab" * 20, adapt=True) > 2 * ppm.BytePPM().code(b"abab" * 5, adapt=True)


def test_toxicity(spark, empty):
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in range(50)]
    rows = [(i, " ".join(rng.choice(words, 30)) + (" vile scum" if i % 4 == 0 else "")) for i in range(400)] + [(1000, None)]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    lab = spark.createDataFrame([(i, 0, int(i % 4 == 0)) for i in range(300)] + [(None, 0, 1), (5, None, None)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.toxicity(spark, d, lab).collect()}
    assert len(got) == 401 and all(got[i].predicted == (i % 4 == 0) for i in range(400)) and got[1000].predicted == 0
    assert got[0].evidence[0]["label"] == 1 and all(0 <= r.score <= 1 for r in got.values())
    assert toxicity.toxicity(spark, empty, lab).count() == 0 and toxicity.toxicity(spark, d, lab.where("false")).count() == 401
    # the pruned search finds what a scan of all examples finds
    vec = [(i, i % 2, np.unique(rng.integers(0, 40, 6)), None) for i in range(300)]
    ix = toxicity.BlockMaxIndex([(i, y, f, np.ones(len(f))) for i, y, f, _ in vec], np.linspace(1, 2, 40), 0.5, 7)
    of = {i: (f, ix.weights(f, np.ones(len(f)))) for i, _, f, _ in vec}
    dense = np.zeros((len(ix.ids), 40))
    for e, i in enumerate(ix.ids.tolist()):
        dense[e, of[i][0]] = of[i][1]
    for _, _, f, _ in vec[:40]:
        w = ix.weights(f, np.ones(len(f)))
        want = np.sort(dense[:, f] @ w)[::-1][:7]
        assert ix.nearest(f, w)[1] == pytest.approx(want, abs=1e-5)


def test_merkle(spark):
    a = spark.createDataFrame([(i, f"u{i}", None if i == 5 else "x" * i) for i in range(300)] + [(7, "again", "z"), (None, None, None)], "page_id long, url string, html string")
    b = a.where("page_id <> 100 or page_id is null").withColumn("html", F.when(F.col("page_id") == 200, F.lit("bad")).otherwise(F.col("html"))).unionByName(spark.createDataFrame([(999, "e", "e")], a.schema))
    run = lambda x, y: {(r.rid, r.status) for r in merkle_audit.audit(spark, x, y, "page_id", ["url", "html"], span=8, fanout=4).collect()}
    assert run(a, b) == {(100, "missing"), (200, "corrupt"), (999, "extra")}
    assert run(a, a) == set() and len(run(a, a.where("false"))) == 301


def test_merkle_empty_hot_and_far_ids(spark):
    schema = "page_id long, url string, html string, rid long, hash string, node long, leaf string"
    row = lambda i, u, h: (i, u, h, 5, "clash", 6, "leaf")
    rows = [row(i, f"u{i}", "é" * (i % 7)) for i in range(50)] + [row(None, f"n{i}", "z" * i) for i in range(3000)] + [row(10**7 + i, "far", None) for i in range(5)] + [row(-(10**5), "low", ""), row(9, "u9", "more" * 500000)]
    a = spark.createDataFrame(rows, schema).repartition(5)
    b = spark.createDataFrame([r for r in rows if r[1] != "n77"] + [row(None, "n5", "z" * 5)], schema)
    none = a.where("false")
    run = lambda x, y: merkle_audit.audit(spark, x, y, "page_id", ["url", "html"], span=8).collect()
    assert [(r.rid, r.status, r.left_copies, r.right_copies) for r in run(a, b)] == [(None, "corrupt", 3000, 3000)]
    extra = run(none, b)
    assert {r.status for r in extra} == {"extra"} and len(extra) == 57
    got = {r.rid: r.offset for r in run(a, none)}
    at, want = 0, {}
    size = {}
    for r in rows:
        size[r[0]] = size.get(r[0], 0) + len(r[1].encode()) + len((r[2] or "").encode())
    # null ids are the first of range -1; the others in order
    for i in sorted(size, key=lambda i: (-8 if i is None else i)):
        want[i], at = at, at + size[i]
    assert got == want


def test_merkle_root_and_copies(spark):
    a = spark.createDataFrame([(i * 100_000, "u", "h") for i in range(20)] + [(0, "u", "h")], "page_id long, url string, html string")
    b = a.where("page_id <> 500000").dropDuplicates()
    x, y = (merkle_audit.leaves(d, "page_id", ["url", "html"], 64) for d in (a, b))
    n = merkle_audit.height(x, y, 64)
    assert n == 3 and merkle_audit.tree(spark, x, 64, n)[-1].count() == 1
    got = {(r.rid, r.status, r.left_copies, r.right_copies) for r in merkle_audit.audit(spark, a, b, "page_id", ["url", "html"]).collect()}
    assert got == {(0, "corrupt", 2, 1), (500_000, "missing", 1, 0)}


def test_components(spark):
    rng = np.random.default_rng(5)
    e = [(int(x), int(y)) for x, y in rng.integers(0, 200, (120, 2))] + [(300 + i, 301 + i) for i in range(20)]
    up = {x: x for p in e for x in p}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for x, y in e:
        a, b = root(x), root(y)
        up[max(a, b)] = min(a, b)
    got = {r.node: r.component for r in components(spark, spark.createDataFrame(e, "a long, b long")).collect()}
    assert got == {x: root(x) for p in e if p[0] != p[1] for x in p}


def test_pipeline_small(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    assert [n for n, _ in corpus_pipeline.STAGES][0] == "toxicity" and len(corpus_pipeline.STAGES) == 5
    d = spark.read.parquet(f"{sf}/documents.parquet")
    kept = corpus_pipeline.drop_contaminated(spark, corpus_pipeline.drop_copies(spark, d, sf), sf)
    assert kept.columns == d.columns and 0 < kept.count() < d.count()
    assert corpus_pipeline.run(spark, sf).select("doc_id").distinct().count() <= kept.count()


def test_components_of_chains_loops_and_stars(spark):
    import random

    from stablecf.llm.components import components

    rng = random.Random(3)
    chain = [(i, i + 1) for i in range(100, 140)]
    edges = chain + chain[:5] + [(7, 7), (1, 50), (1, 51), (1, 52), (60, 61), (62, 61), (62, 60)]
    rng.shuffle(edges)
    got = {r.node: r.component for r in components(spark, spark.createDataFrame(edges, "a long, b long")).collect()}
    want = {i: 100 for i in range(100, 141)} | {1: 1, 50: 1, 51: 1, 52: 1, 60: 60, 61: 60, 62: 60}
    assert got == want
    assert components(spark, spark.createDataFrame([], "a long, b long")).count() == 0
