"""Sanitisation against a brute-force version: patterns by ``re``, counts and shares by loops over whole documents."""

import hashlib
import math
import re
from collections import Counter

from stablecf.llm import sanitise

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
WORD = re.compile(r"[0-9A-Za-z\u0080-\U0010FFFF]{4,}")


def luhn(s):
    total = 0
    for i, c in enumerate(reversed(s)):
        v = int(c) * (1 + i % 2)
        total += v - 9 if v > 9 else v
    return total % 10 == 0


def base(t):
    out = []
    digits = lambda m: re.sub("[^0-9]", "", m)
    for k, (name, pattern) in enumerate((("email", EMAIL), ("ip", IP), ("card", CARD), ("phone", PHONE))):
        for m in pattern.finditer(t):
            d = digits(m[0])
            ok = {"email": True, "ip": all(int(x) <= 255 for x in m[0].split(".")) if name == "ip" else False, "card": 12 <= len(d) <= 19 and luhn(d), "phone": 9 <= len(d) <= 15}[name]
            if ok:
                out.append((m.start(), k, m.end(), name, m[0]))
    return sorted(out)


def brute(rows, disclosure=0.8, prior=2.0):
    docs = [(i, t or "") for i, t in rows]
    n = len(docs)
    spans = [base(t) for _, t in docs]
    terms = [{w.lower() for w in WORD.findall(t)} for _, t in docs]
    ents = [{f"{s[3]}:{s[4].lower()}" for s in x} for x in spans]
    nt, ne = Counter(x for s in terms for x in s), Counter(x for s in ents for x in s)
    nte = Counter((t, e) for ts, es in zip(terms, ents) for e in es for t in ts)
    leaks = set()
    for (t, e), c in nte.items():
        if ne[e] < n:
            info = math.log2(n / ne[e])
            if (math.log2((c + prior * ne[e] / n) / (nt[t] + prior)) + info) / info >= disclosure:
                leaks.add(t)
    out = Counter()
    for (i, t), mine in zip(docs, spans):
        more = [(m.start(), 4, m.end(), "term", m[0].lower()) for m in WORD.finditer(t) if m[0].lower() in leaks]
        more = [x for x in more if not any(x[0] < s[2] and s[0] < x[2] for s in mine)]
        text = lambda ss: ",".join(f"{s[3]}:{s[0]}:{s[2]}" for s in ss)
        count = Counter(s[3] for s in mine)
        out[(i, count["email"], count["ip"], count["card"], count["phone"], hashlib.sha256(text(mine).encode()).hexdigest(), text(sorted(mine + more)))] += 1
    return out, leaks


def rows():
    import pyarrow.parquet as pq

    t = pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["doc_id", "text"])
    out = list(zip(t["doc_id"].to_pylist(), t["text"].to_pylist()))
    out += [(5, "an id again: zed@corp.example"), (5, "and again Quorvex\x01\x02 a@b.co\x02 4111 1111 1111 1111"), (None, None), (None, ""), (None, "Quorvex ZED@corp.example"), (None, "Quorvex")]
    return out + [(90000, "éa\U0001F600 Straße 10.0.0.1 +49 (30) 1234-5678 " + "filler words " * 40000 + "1.2.3.4")]


def test_sanitise_equals_brute_force(spark):
    data = rows()
    df = spark.createDataFrame([(i, t, "x", 1) for i, t in data], "doc_id long, text string, row string, words int").repartition(4)
    want, leaks = brute(data)
    assert Counter(map(tuple, sanitise.digest(sanitise.sanitise(spark, df, with_text=False)).collect())) == want
    assert leaks and any(",term:" in k[-1] or k[-1].startswith("term:") for k in want)


def test_nothing_protected_is_left(spark):
    data = [(0, "Z filler0 zed@corp.example words"), (0, "mail Z zed@corp.example to zed@corp.example today"), (None, "call +1 555 010 9999 now"), (None, "nothing here"), (3, None)]
    data += [(10 + i, "other people write to nobody today, words only, mail call") for i in range(500)]
    out = sanitise.sanitise(spark, spark.createDataFrame(data, "doc_id long, text string")).collect()
    assert len(out) == len(data)
    assert not any("@" in r.sanitised or "555" in r.sanitised for r in out)
    assert sorted(r.sanitised for r in out if r.doc_id is None) == ["call [PHONE] now", "nothing here"]
    assert Counter(r.sanitised for r in out if r.doc_id == 0) == Counter(["Z [TERM] [EMAIL] words", "mail Z [EMAIL] to [EMAIL] today"])
