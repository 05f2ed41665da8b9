"""N-gram Jaccard self-join: rare-first prefix filter with length, positional and suffix filters, one verification per pair.

1. A census gives every shingle a rarity class (the bit length of its document
   count).  A shingle of class 0 is in one document only and can't be shared.
2. A document whose shared shingles are fewer than ``threshold`` of its set links
   with nothing (its rare-first prefix holds unshared shingles only) and ends here.
3. The others order their shared shingles rare first, and the prefix of
   ``n - ceil(t n) + 1`` shingles, less the unshared ones, is joined.  Equal sets are
   joined once, through the smallest id.
4. No pair is made of documents already known to be connected: documents are
   first paired with one leader for each of four smallest hashes of their sets, then
   in two rounds with one leader, of few unshared shingles, for each prefix token
   whose documents are still in different components; what then remains so is paired
   in full, token by token.  A token of many documents is dealt to several tasks: its
   documents to blocks of about ``HOT``, joined with copies of the leader or, in full,
   block by block.  Length, positional and
   suffix (parity sketch) filters drop pairs that can't reach the threshold.
5. Each different pair is verified once on the whole shared sets.

Defined results: null or wordless texts have an empty set and link with nothing,
themselves their component; fewer than ``n`` words are one shingle; repeated rows
come back one by one, with equal results; shingles are compared by 64-bit hashes.
"""

from __future__ import annotations

from functools import reduce
from operator import add

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm import census
from stablecf.llm import kernels as K
from stablecf.llm.common import NO_ID, chunked, id_back, ids_and_texts, ship, staged, text_bytes
from stablecf.llm.components import components

HEADS = 4
#: Keys of an id's further sets start here; stored ids are smaller.
MORE = 1 << 62
#: Longs of a parity sketch: bit i is the parity of how many shared shingles hash to i.
WORDS = 8
#: Rounds with one leader a token before the exhaustive one.
ROUNDS = 2
#: Documents of one prefix token that one task pairs, and the most tokens above that which are broadcast (a megabyte).
HOT, FEW = 512, 1 << 16
SETS = "doc_id long, n_shingles long, tokens array<long>, sketch array<long>, heads array<long>"


def parity_sketch(h: np.ndarray) -> np.ndarray:
    """Two sets' sketches differ in at most as many bits as the sets differ in items, whatever they share."""
    odd = np.bincount((h >> np.uint64(55)).astype(np.int64), minlength=64 * WORDS) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def shingle_sets(t: pa.Table, n: int) -> list[np.ndarray]:
    """Sorted different shingle hashes of each text."""
    data, starts, ends = K.as_bytes(t["text"])
    out = []
    for i, j in K.blocks(starts, ends):
        buf, s, e = K.spaced(data, starts[i:j], ends[i:j])
        buf = K.LOWER[buf]
        ws, we = K.word_spans(buf, K.NONBLANK)
        h = K.word_hashes(buf, ws, we)
        lo, hi = np.searchsorted(ws, s).tolist(), np.searchsorted(ws, e).tolist()
        out += [np.unique(K.shingle_hashes(h[a:z], n)) for a, z in zip(lo, hi, strict=True)]
    return out


def _send(chunk: int, t: pa.Table, n: int, buckets: int) -> pa.Table:
    K.trim()
    sets = shingle_sets(t, n)
    keys, count = np.unique(census.reduced(np.concatenate(sets), buckets), return_counts=True) if sets else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
    return census.blob_rows(census.sent(chunk, keys, np.minimum(count, 0xFFFFFFFF).astype(np.uint32)))


def _rare_first(t: pa.Table, told: pa.Table, n: int, buckets: int, percent: int) -> pa.Table:
    """Sets of the documents that may link; of the others the size alone."""
    K.trim()
    sets = shingle_sets(t, n)
    every = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
    keys, back = np.unique(census.reduced(every, buckets), return_inverse=True)
    cls = census.answers(told, keys, np.uint8)[back]
    out, sketches, heads, at = [], [], [], 0
    for s in sets:
        c = cls[at : at + len(s)]
        at += len(s)
        shared = c > 0
        if len(s) and 100 * int(shared.sum()) >= percent * len(s):
            h, c = s[shared], c[shared]
            out.append(h[np.lexsort((h, c))].view(np.int64))
            sketches.append(parity_sketch(h))
            heads.append(np.array([K.mix(h ^ np.uint64(0x9E3779B97F4A7C15 * (i + 1) % (1 << 64))).min() for i in range(HEADS)]).view(np.int64))
        else:
            out.append(None)
            sketches.append(None)
            heads.append(None)
    return pa.table({"doc_id": t["doc_id"], "n_shingles": pa.array([len(s) for s in sets], pa.int64()), "tokens": pa.array(out, pa.list_(pa.int64())), "sketch": pa.array(sketches, pa.list_(pa.int64())), "heads": pa.array(heads, pa.list_(pa.int64()))})


def with_groups(entries: DataFrame, groups: DataFrame) -> DataFrame:
    """Entries joined with their token's row of ``groups`` (token, blocks).  Documents of a token of many blocks stay where they are,
    as such tokens are broadcast while they are few; beyond that all are joined by shuffle."""
    many = groups.where("blocks > 1")
    if not 0 < many.count() <= FEW:
        return entries.join(groups, "token")
    rest = entries.join(F.broadcast(many.select("token")), "token", "left_anti").join(groups.where("blocks = 1"), "token")
    return entries.join(F.broadcast(many), "token").unionByName(rest)


def links(spark: SparkSession, sets: DataFrame, percent: int, hot: int = HOT) -> DataFrame:
    """(node, component) of the linked representatives among ``sets`` (rid, n, tokens)."""
    need = lambda a, b: F.ceil(F.lit(percent) * (a + b) / F.lit(100 + percent))
    prefix = F.col("n") - F.ceil(F.lit(percent) * F.col("n") / F.lit(100)) + 1 - (F.col("n") - F.size("tokens"))
    entries = sets.select("rid", "n", F.size("tokens").alias("m"), "sketch", F.slice("tokens", F.lit(1), F.greatest(prefix, F.lit(0)).cast("int")).alias("head"))
    entries = entries.select("rid", "n", "m", "sketch", F.posexplode("head").alias("pos", "token"))
    entries = staged(spark, entries, "prefix-entries")
    blocks = F.ceil(F.count(F.lit(1)) / hot).cast("int").alias("blocks")
    groups = staged(spark, entries.groupBy("token").agg(F.count(F.lit(1)).alias("size"), blocks).where("size > 1").select("token", "blocks"), "shared-tokens")
    entries = staged(spark, with_groups(entries, groups).drop("blocks"), "shared-entries")

    def may(x: str, y: str, placed: bool) -> Column:
        a, b = F.col(f"{x}.n"), F.col(f"{y}.n")
        length = (F.lit(100) * F.least(a, b) >= F.lit(percent) * F.greatest(a, b))
        left = F.least(F.col(f"{x}.m") - F.col(f"{x}.pos"), F.col(f"{y}.m") - F.col(f"{y}.pos"))  # of the first common token, so some token of a link passes
        differ = reduce(add, (F.bit_count(F.col(f"{x}.sketch")[i].bitwiseXOR(F.col(f"{y}.sketch")[i])) for i in range(WORDS)))
        both = F.col(f"{x}.m") + F.col(f"{y}.m") - differ  # at least twice what the sets share
        return length & (both >= 2 * need(a, b)) & ((left >= need(a, b)) if placed else F.lit(True))

    def verified(pairs: DataFrame) -> DataFrame:
        body = sets.select("rid", "n", "tokens")
        x = pairs.join(body.select(F.col("rid").alias("b"), F.col("n").alias("nb"), F.col("tokens").alias("tb")), "b")
        x = x.join(body.select(F.col("rid").alias("a"), F.col("n").alias("na"), F.col("tokens").alias("ta")), "a")
        both = F.size(F.array_intersect("ta", "tb"))
        return x.where(F.lit(100) * both >= F.lit(percent) * (F.col("na") + F.col("nb") - both)).select(F.col("ca").alias("a"), F.col("cb").alias("b"))

    def pair(x: DataFrame, y: DataFrame, on: Column, placed: bool = True) -> DataFrame:
        ends = [F.struct(F.col(f"{s}.rid").alias("rid"), F.col(f"{s}.comp").alias("comp")) for s in ("x", "y")]
        out = x.join(y, on).where(may("x", "y", placed)).select(F.least(*ends).alias("a"), F.greatest(*ends).alias("b"))
        return out.select(F.col("a.rid").alias("a"), F.col("b.rid").alias("b"), F.col("a.comp").alias("ca"), F.col("b.comp").alias("cb")).where("a <> b").distinct()

    def joined(pairs: DataFrame, label: DataFrame | None) -> DataFrame:
        """``label`` after the links of ``pairs``: only the components they join are worked on."""
        found = staged(spark, verified(pairs), "links")
        if label is not None and not found.take(1):
            return label
        more = components(spark, found)
        if label is None:
            return staged(spark, more, "labels")
        more = staged(spark, more, "joined-components")
        old = label.join(more.select(F.col("node").alias("component"), F.col("component").alias("to")), "component", "left").select("node", F.coalesce("to", "component").alias("component"))
        return staged(spark, old.unionByName(more.join(label, "node", "left_anti")), "labels")

    # a dense group shares the smallest hash of its sets: one pair a document and hash joins most of it before prefixes are paired
    heads = sets.select("rid", F.col("rid").alias("comp"), "n", F.size("tokens").alias("m"), "sketch", F.posexplode("heads").alias("pos", "token"))
    lead = heads.groupBy("pos", "token").agg(F.min_by(F.struct("rid", "comp", "n", "m", "sketch"), F.struct(F.col("n") - F.col("m"), "rid")).alias("l"), F.count(F.lit(1)).alias("size")).where("size > 1").select("pos", "token", "l.*")
    pairs = pair(heads.alias("x"), lead.alias("y"), (F.col("x.pos") == F.col("y.pos")) & (F.col("x.token") == F.col("y.token")), placed=False)
    label = joined(pairs, None)
    for r in range(ROUNDS + 1):
        now = entries.join(label.withColumnRenamed("node", "rid"), "rid", "left").withColumn("comp", F.coalesce("component", "rid")).drop("component")
        open_groups = now.groupBy("token").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), blocks).where("lo <> hi").select("token", "blocks")
        now = staged(spark, with_groups(now, staged(spark, open_groups, "open-tokens")).withColumn("block", F.pmod(F.xxhash64("rid"), F.col("blocks")).cast("int")), "open-entries")
        entries = now.drop("comp", "blocks", "block")
        if not now.take(1):
            break
        if r < ROUNDS:
            # a document with few shingles of its own lies amid its group and links with most of it
            order = F.struct(F.ceil(F.log2(F.col("n") - F.col("m") + 1)), F.xxhash64("rid", F.lit(r)), "rid")
            lead = now.groupBy("token", "blocks").agg(F.min_by(F.struct("rid", "n", "m", "sketch", "pos", "comp"), order).alias("l"))
            lead = lead.select("token", "l.*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"))
            pairs = pair(now.alias("x"), lead.alias("y"), (F.col("x.token") == F.col("y.token")) & (F.col("x.block") == F.col("y.block")) & (F.col("x.comp") != F.col("y.comp")))
        else:
            # every two blocks of a token meet once: the one as the first, the other as the second
            x = now.withColumn("other", F.explode(F.sequence(F.col("block"), F.col("blocks") - 1)))
            y = now.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("block"))))
            met = (F.col("x.token") == F.col("y.token")) & (F.col("x.block") == F.col("y.other")) & (F.col("x.other") == F.col("y.block"))
            pairs = pair(x.alias("x"), y.alias("y"), met & (F.col("x.comp") != F.col("y.comp")))
        label = joined(pairs, label)
    return label


def similar(spark: SparkSession, df: DataFrame, n: int = 5, percent: int = 75, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> DataFrame:
    """(doc_id, n_shingles, component_id), one row per document; component_id is null only for null ids."""
    ship(spark)
    docs = ids_and_texts(df, id_col, text_col)
    size, buckets = census.sizes(total := text_bytes(docs), 6.5)
    chunks, _, _ = chunked(spark, docs, size, total)

    def send(key: tuple, t: pa.Table) -> pa.Table:
        return _send(key[0].as_py(), t, n, buckets)

    def order(t: pa.Table, told: pa.Table) -> pa.Table:
        return _rare_first(t, told, n, buckets, percent)

    told = census.owners(chunks.groupBy("chunk").applyInArrow(send, census.BLOB), census.chunk_counts)
    sets = staged(spark, chunks.groupBy("chunk").cogroup(told.groupBy("chunk")).applyInArrow(order, SETS), "sets")
    whole = F.col("n_shingles") == F.size("tokens")
    # a document with shingles of its own stands for itself: its id and set are its key, as rows that share an id may differ
    digest = F.sha2(F.to_binary(F.array_join(F.transform("tokens", lambda x: F.lpad(F.hex(x), 16, "0")), ""), F.lit("hex")), 256)
    some = sets.where("tokens is not null").select("doc_id", "n_shingles", "tokens", "sketch", "heads", F.when(whole, digest).otherwise(F.concat(F.lit("doc "), F.col("doc_id").cast("string"), F.concat_ws(" ", F.lit(""), "n_shingles", digest))).alias("sig"))
    ids = some.select("doc_id", "sig")
    rep = staged(spark, ids.groupBy("sig").agg(F.min("doc_id").alias("doc_id")), "keys")
    # the first set of an id has the id as its key; more sets of it have keys above all ids
    repeated = staged(spark, rep.groupBy("doc_id").agg(F.min("sig").alias("first"), F.count(F.lit(1)).alias("sets")).where("sets > 1"), "repeated-ids")
    key = F.when(F.coalesce(F.col("sig") == F.col("first"), F.lit(True)), F.col("doc_id")).otherwise(F.pmod(F.xxhash64("sig"), F.lit(MORE - 1)) + F.lit(MORE))
    rep = rep.join(repeated, "doc_id", "left").select("sig", "doc_id", key.alias("rid"))
    reps = some.join(rep.select("doc_id", "rid", F.col("sig").alias("s2")), "doc_id").where("sig = s2").dropDuplicates(["rid"])
    reps = staged(spark, reps.select("rid", F.col("n_shingles").cast("int").alias("n"), "tokens", "sketch", "heads"), "representatives")
    label = links(spark, reps, percent, hot)
    member = staged(spark, ids.distinct().join(rep.select("sig", "rid"), "sig").select("doc_id", "rid"), "members")
    at = member.join(label.withColumnRenamed("node", "rid"), "rid", "left").select("doc_id", F.coalesce("component", "rid").alias("component"))
    several = at.groupBy("doc_id").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo <> hi").select("doc_id", "lo")
    several = staged(spark, at.join(several, "doc_id").select(F.col("component").alias("a"), F.col("lo").alias("b")).distinct(), "sets-of-an-id")
    if several.take(1):
        # sets of one id belong together, and so do the documents that each of them links
        more = staged(spark, components(spark, several), "components-of-ids")
        at = at.join(more.select(F.col("node").alias("component"), F.col("component").alias("to")), "component", "left").select("doc_id", F.coalesce("to", "component").alias("component"))
    at = at.groupBy("doc_id").agg(F.min("component").alias("component"))
    # a key above all ids is the smallest only where null ids link with nothing else
    out = sets.select("doc_id", "n_shingles").join(at.select("doc_id", F.when(F.col("component") >= MORE, F.lit(NO_ID)).otherwise(F.col("component")).alias("component")), "doc_id", "left")
    comp = F.coalesce("component", "doc_id")
    return out.select(id_back(), "n_shingles", F.when(comp != NO_ID, comp).alias("component_id"))
