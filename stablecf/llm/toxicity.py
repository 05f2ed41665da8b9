"""Toxicity by nearest labelled examples under exact TF-IDF cosine, found in a block-max inverted index.

Fit: up to ``per_class`` labelled documents of each class (the ones with the
smallest hash of their id: a bound, not a share) are the examples.  Words whose
presence depends on the label (chi-square of their document counts, at most
``features`` of them) span the vectors; over all words the cosine of long texts is
that of their topics, and most toxic texts are missed (README).  Document
frequencies are those of all documents.  The index keeps, for each word, its
postings (block of examples, example, weight) and the largest weight of each
block: a bound on any score in the block.

Query: blocks are visited by falling bound, and only while the bound reaches
the k-th best cosine, so the neighbours are the exact ones.  Their votes are
weighted by cosine and by the classes' true shares, and an isotonic fit of
leave-one-out votes on the examples turns a vote into a probability.

Defined results: a text without any of the words (null and empty texts too) has
no neighbour and gets the examples' rate of such texts; ties go to the earlier
example; rows that repeat are scored one by one; an id labelled both ways counts as
label 1, and of several texts of a labelled id the least is the example; without
examples of both classes every score is the share of label 1, or 0 without labels.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm import kernels as K
from stablecf.llm.common import NO_ID, ids_and_texts, ship, staged

BLOCK = 64
SCHEMA = "doc_id long, score double, vote double, evidence array<struct<doc_id:long, cosine:double, label:int>>"


class BlockMaxIndex:
    """Inverted index of unit vectors: postings by word and block of ``BLOCK`` examples, with the largest weight of each word in each block."""

    def __init__(self, rows: list[tuple[int, int, np.ndarray, np.ndarray]], idf: np.ndarray, share: float, k: int) -> None:
        self.k, self.idf = k, idf
        vectors = [(i, y, f, self.weights(f, tf)) for i, y, f, tf in rows]
        vectors = [v for v in vectors if len(v[2])]
        vectors.sort(key=lambda v: (int(v[2][np.argmax(v[3])]), v[1], v[0]))  # alike examples share a block, which sharpens the bounds
        n = len(vectors)
        self.ids, self.labels = np.array([v[0] for v in vectors], np.int64), np.array([v[1] for v in vectors], np.int64)
        self.blocks = -(-n // BLOCK)
        word = np.concatenate([v[2] for v in vectors]) if n else np.zeros(0, np.int64)
        who = np.repeat(np.arange(n), [len(v[2]) for v in vectors])
        weight = np.concatenate([v[3] for v in vectors]) if n else np.zeros(0, np.float32)
        order = np.lexsort((who, word))
        self.who, self.weight = who[order], weight[order]
        run = word[order] * max(1, self.blocks) + self.who // BLOCK  # a list of one word in one block
        self.run_at = np.flatnonzero(np.append(True, run[1:] != run[:-1])) if n else np.zeros(0, np.int64)
        self.run_end = np.append(self.run_at[1:], len(run))
        self.peak = np.maximum.reduceat(self.weight, self.run_at) if n else np.zeros(0, np.float32)
        self.block = (run % max(1, self.blocks))[self.run_at] if n else np.zeros(0, np.int64)
        self.first = np.searchsorted((run // max(1, self.blocks))[self.run_at] if n else np.zeros(0), np.arange(len(idf) + 1))
        every = np.array([r[1] for r in rows], dtype=float)
        self.share = share
        # examples are drawn class by class; votes count with the classes' true shares
        self.vote = {1: share / max(1, every.sum()), 0: (1 - share) / max(1, (1 - every).sum())}
        bare = np.array([r[1] for r in rows if not len(r[2])], dtype=np.int64)
        w = np.array([self.vote[0], self.vote[1]])
        ones, none = (bare == 1).sum() * w[1], (bare == 0).sum() * w[0]
        self.bare = float((ones + share * w.mean()) / (ones + none + w.mean())) if len(rows) else share
        self.cuts, self.rates = np.array([0.0]), np.array([share])
        if n:
            loo = np.array([self.poll(f, self.weights(f, tf), skip=i)[0] for i, _, f, tf in rows if len(f)])
            y = np.array([r[1] for r in rows if len(r[2])])
            self.cuts, self.rates = isotonic(loo, y, np.where(y == 1, self.vote[1], self.vote[0]), share)

    def weights(self, f: np.ndarray, tf: np.ndarray) -> np.ndarray:
        w = (1 + np.log(tf)) * self.idf[f]
        return (w / max(1e-12, float(np.sqrt((w * w).sum())))).astype(np.float32)

    def nearest(self, f: np.ndarray, w: np.ndarray, skip: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(examples, cosines) of the k nearest with a positive cosine, nearest first."""
        n = self.first[f + 1] - self.first[f]
        runs = np.repeat(self.first[f] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
        mine = np.repeat(w.astype(np.float64), n)
        bound = np.bincount(self.block[runs], weights=mine * self.peak[runs], minlength=self.blocks)
        order = np.argsort(-bound, kind="stable")
        order = order[bound[order] > 0]
        who, cos, at, step = np.zeros(0, np.int64), np.zeros(0), 0, 2
        while at < len(order):
            if len(cos) >= self.k and bound[order[at]] < cos[self.k - 1] - 1e-6:
                break
            place = np.full(self.blocks, -1)
            place[order[at : at + step]] = np.arange(len(order[at : at + step]))
            use = place[self.block[runs]] >= 0
            r, x = runs[use], mine[use]
            size = self.run_end[r] - self.run_at[r]
            post = np.repeat(self.run_at[r] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
            local = place[self.who[post] // BLOCK] * BLOCK + self.who[post] % BLOCK
            c = np.bincount(local, weights=np.repeat(x, size) * self.weight[post], minlength=BLOCK * step)
            e = (order[at : at + step][:, None] * BLOCK + np.arange(BLOCK)).ravel()
            c = c[: len(e)]
            ok = (c > 0) & (e < len(self.ids))
            if skip is not None:
                ok &= self.ids[np.minimum(e, len(self.ids) - 1)] != skip
            who, cos = np.concatenate([who, e[ok]]), np.concatenate([cos, c[ok]])
            top = np.lexsort((who, -cos))[: self.k]
            who, cos = who[top], cos[top]
            at, step = at + step, step * 2
        return who, cos

    def poll(self, f: np.ndarray, w: np.ndarray, skip: int | None = None) -> tuple[float, np.ndarray, np.ndarray]:
        who, cos = self.nearest(f, w, skip)
        if not len(who):
            return self.share, who, cos
        v = cos * np.where(self.labels[who] == 1, self.vote[1], self.vote[0])
        return float(v[self.labels[who] == 1].sum() / v.sum()), who, cos

    def score(self, vote: float) -> float:
        return float(self.rates[max(0, np.searchsorted(self.cuts, vote, side="right") - 1)])


def isotonic(x: np.ndarray, y: np.ndarray, w: np.ndarray, prior: float) -> tuple[np.ndarray, np.ndarray]:
    """Pool-adjacent-violators steps of P(y | x): (left ends, values).  A step carries one average example of the prior."""
    u, back = np.unique(x, return_inverse=True)  # equal votes are one point before any pooling
    mass, ones = np.bincount(back, weights=w), np.bincount(back, weights=w * y)
    pools: list[list[float]] = []  # left end, sum of w, sum of w*y
    for left, m, o in zip(u.tolist(), mass.tolist(), ones.tolist(), strict=True):
        pools.append([left, m, o])
        while len(pools) > 1 and pools[-2][2] * pools[-1][1] >= pools[-1][2] * pools[-2][1]:
            a = pools.pop()
            pools[-1][1] += a[1]
            pools[-1][2] += a[2]
    one = float(w.mean())
    return np.array([p[0] for p in pools]), np.array([(p[2] + one * prior) / (p[1] + one) for p in pools])


def word_counts(texts, keys: np.ndarray | None):
    """Per text: (word hashes or, with sorted ``keys``, their numbers; counts)."""
    data, starts, ends = K.as_bytes(texts)
    for i, j in K.blocks(starts, ends):
        buf, s, e = K.spaced(data, starts[i:j], ends[i:j])
        buf = K.LOWER[buf]
        ws, we = K.word_spans(buf, K.ALNUM)
        h = K.word_hashes(buf, ws, we)
        lo, hi = np.searchsorted(ws, s), np.searchsorted(ws, e)
        if keys is None:
            for a, z in zip(lo.tolist(), hi.tolist(), strict=True):
                yield np.unique(h[a:z], return_counts=True)
            continue
        at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
        hit = np.flatnonzero(keys[at] == h)
        doc = np.repeat(np.arange(j - i), hi - lo)[hit]
        code, n = np.unique(doc * len(keys) + at[hit], return_counts=True)
        edge = np.searchsorted(code, np.arange(j - i + 1) * len(keys))
        for a, z in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
            yield code[a:z] % len(keys), n[a:z]


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, per_class: int = 2048, features: int = 1024, min_docs: int = 5, chi2: float = 30.0, k: int = 15) -> tuple[np.ndarray, BlockMaxIndex]:
    """(feature hashes, index).  ``docs``: doc_id, text; ``labels``: doc_id, label 0/1, the rows that may be learnt from."""
    order = [F.xxhash64("doc_id"), F.col("doc_id")]
    share = {int(r["label"]): int(r["count"]) for r in labels.groupBy("label").count().collect()}
    total = sum(share.values())
    rate = share.get(1, 0) / total if total else 0.0
    ids = labels.where("label = 1").orderBy(*order).limit(per_class).unionByName(labels.where("label = 0").orderBy(*order).limit(per_class))
    # the ids are at most 2 * per_class
    sample = docs.join(F.broadcast(ids), "doc_id").groupBy("doc_id", "label").agg(F.min("text").alias("text"))

    def bags(batches):
        for b in batches:
            bag = [x[0].view(np.int64) for x in word_counts(b.column(1), None)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(bag, pa.list_(pa.int64()))], ["doc_id", "label", "words"])

    sample = staged(spark, sample.select("doc_id", "text", F.col("label").cast("int").alias("label")), "toxicity-sample")
    words = staged(spark, sample.mapInArrow(bags, "doc_id long, label int, words array<long>"), "toxicity-words")
    n = {int(r["label"]): int(r["count"]) for r in words.groupBy("label").count().collect()}
    n1, n0 = n.get(1, 0), n.get(0, 0)
    if not n1 or not n0:
        return np.zeros(1, np.uint64), BlockMaxIndex([], np.zeros(1), rate, k)
    counts = words.select("label", F.explode("words").alias("word")).groupBy("word").agg(F.sum("label").alias("a"), F.count(F.lit(1)).alias("df"))
    a, b = F.col("a").cast("double"), (F.col("df") - F.col("a")).cast("double")
    c, d = F.lit(float(n1)) - a, F.lit(float(n0)) - b
    all_ = float(n1 + n0)
    stat = F.lit(all_) * (a * d - b * c) * (a * d - b * c) / ((a + b) * (c + d) * float(n1) * float(n0))
    top = counts.where((F.col("df") >= min_docs) & (F.col("df") < all_)).withColumn("chi2", stat).where(F.col("chi2") >= chi2).orderBy(F.desc("chi2"), "word").limit(features).collect()
    keys = np.sort(np.array([r["word"] for r in top], dtype=np.int64).view(np.uint64)) if top else np.zeros(1, np.uint64)

    def held_by(batches):
        n, seen = 0, np.zeros(len(keys), np.int64)
        for b in batches:
            n += b.num_rows
            for f, _ in word_counts(b.column(1), keys):
                seen[f] += 1
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(-1, len(keys)), pa.int32()), pa.array(np.append(n, seen), pa.int64())], ["f", "n"])

    # document frequencies of the words over all documents: at most ``features`` + 1 rows
    df = np.zeros(len(keys) + 1)
    for r in docs.mapInArrow(held_by, "f int, n long").groupBy("f").agg(F.sum("n").alias("n")).collect():
        df[r["f"] + 1] = r["n"]
    idf = np.log((df[0] + 1) / (df[1:] + 0.5))

    def vectors(batches):
        for b in batches:
            got = list(word_counts(b.column(1), keys))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array([g[0] for g in got], pa.list_(pa.int64())), pa.array([g[1] for g in got], pa.list_(pa.int64()))], ["doc_id", "label", "f", "n"])

    rows = sample.mapInArrow(vectors, "doc_id long, label int, f array<long>, n array<long>").collect()
    rows = [(r["doc_id"], r["label"], np.array(r["f"], np.int64), np.array(r["n"], np.int64)) for r in sorted(rows, key=lambda r: r["doc_id"])]
    return keys, BlockMaxIndex(rows, idf, rate, k)


def score(spark: SparkSession, docs: DataFrame, keys: np.ndarray, index: BlockMaxIndex, evidence: int = 3) -> DataFrame:
    """One row per document, as ``SCHEMA`` says.  The index is bounded by its parameters, so it is broadcast."""
    held = spark.sparkContext.broadcast((keys, index))

    def run(batches):
        keys, index = held.value
        for b in batches:
            ids, out, seen = b.column(0).to_pylist(), [], {}
            for f, n in word_counts(b.column(1), keys):
                if not len(f) or not index.blocks:
                    out.append((index.bare, None, []))
                    continue
                key = f.tobytes() + n.tobytes()
                if key not in seen:
                    vote, who, cos = index.poll(f, index.weights(f, n))
                    near = [{"doc_id": int(index.ids[e]), "cosine": float(c), "label": int(index.labels[e])} for e, c in zip(who[:evidence].tolist(), cos[:evidence].tolist(), strict=True)]
                    seen[key] = (index.score(vote) if len(who) else index.bare, vote, near)
                out.append(seen[key])
            cols = list(zip(*out, strict=True)) if out else [(), (), ()]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([None if x == NO_ID else x for x in ids], pa.int64()),
                    pa.array(cols[0], pa.float64()),
                    pa.array(cols[1], pa.float64()),
                    pa.array(cols[2], pa.list_(pa.struct([("doc_id", pa.int64()), ("cosine", pa.float64()), ("label", pa.int32())]))),
                ],
                ["doc_id", "score", "vote", "evidence"],
            )

    return docs.mapInArrow(run, SCHEMA)


def toxicity(spark: SparkSession, df: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", fold: int = 0, of: int = 5, **fit_args) -> DataFrame:
    """(doc_id, held_out, score, predicted, vote, evidence); labels of ids whose crc32 mod ``of`` is ``fold`` are not learnt from."""
    ship(spark)
    docs = ids_and_texts(df, id_col, text_col)
    fold_of = lambda c: F.crc32(F.col(c).cast("string")) % of
    known = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("label")).where("doc_id is not null and label in (0, 1)").groupBy("doc_id").agg(F.max("label").alias("label"))
    keys, index = fit(spark, docs, known.where(fold_of("doc_id") != fold), **fit_args)
    out = score(spark, docs, keys, index)
    return out.select("doc_id", F.coalesce(fold_of("doc_id") == fold, F.lit(False)).alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"), "vote", "evidence")
