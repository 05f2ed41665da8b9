"""Benchmark decontamination by a prefix-filtered set join, DataFrame functions only.

A window (ten consecutive item words, or a shorter item whole) occurs in a
document only if every two-word shingle of it does.  For exact containment the
necessary prefix of a window is one shingle; the rarest by its number of
occurrences in the documents is taken, as it brings the fewest candidates.
Documents are joined on that shingle's hash; the shingle's place in the window
fixes where the window must start, and the document's length bounds it; the
words themselves are then compared, so hashes never decide.

Defined results: null texts have no words; an item without words has no
window; rows that repeat an id are judged one by one; empty tables give empty
or clean results; only id and text columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm.common import ascii_lower, id_back, ids_and_texts, staged

NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words(text: str | Column) -> Column:
    c = F.col(text) if isinstance(text, str) else text
    return F.filter(F.split(ascii_lower(c), NOT_WORD), lambda w: w != "")


def _pairs(ws: str) -> Column:
    """Hashes of the two-word shingles of an array of words."""
    n = F.greatest(F.size(ws) - 1, F.lit(0))
    return F.zip_with(F.slice(ws, 1, n), F.slice(ws, 2, n), lambda a, b: F.xxhash64(a, b))


def _singles(ws: str) -> Column:
    return F.transform(ws, lambda a: F.xxhash64(a))


def windows_of(items: DataFrame, length: int) -> DataFrame:
    """(window words, item_ids, shingle hashes): one row per different window."""
    n = F.least(F.lit(length), F.size("ws"))
    starts = F.when(F.size("ws") > 0, F.sequence(F.lit(1), F.size("ws") - n + 1))
    each = items.select("item_id", "ws", n.alias("len"), F.explode(starts).alias("i")).select("item_id", F.expr("slice(ws, i, len)").alias("win"))
    return each.groupBy("win").agg(F.collect_set("item_id").alias("items")).withColumn("shingles", F.when(F.size("win") > 1, _pairs("win")).otherwise(_singles("win")))


def decontaminate(
    spark: SparkSession,
    docs: DataFrame,
    items: DataFrame,
    length: int = 10,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    broadcast_bytes: int = 8 << 20,
) -> DataFrame:
    """(doc_id, n_words, n_hit, hits, item_ids): hits are (start, words, items) of every occurring window.

    The prefixes are broadcast if the item texts, which bound them, are at most ``broadcast_bytes``; else they are joined by shuffle.
    """
    # a row is known by its id and text, so that repeated or missing ids don't make one group of many rows
    texts = ids_and_texts(docs, id_col, text_col).select(F.xxhash64("doc_id", "text").alias("row"), "doc_id", "text")
    d = texts.select("row", words("text").alias("ws"))
    raw = items.select(F.col(item_col).alias("item_id"), F.coalesce(F.col(item_text_col), F.lit("")).alias("text"))
    wins = staged(spark, windows_of(raw.select("item_id", words("text").alias("ws")), length), "windows")
    total, single = raw.agg(F.sum(F.octet_length("text"))).first()[0] or 0, bool(wins.where(F.size("win") == 1).take(1))
    small = F.broadcast if total <= broadcast_bytes else lambda x: x
    place = d.select("row", F.posexplode(_pairs("ws")).alias("pos", "h"))
    if single:
        place = place.unionByName(d.select("row", F.posexplode(_singles("ws")).alias("pos", "h")))
    vocabulary = wins.select(F.explode("shingles").alias("h")).distinct()
    # the places of the benchmark's shingles in the documents, stored, as they are counted and then joined
    place = staged(spark, place.join(small(vocabulary), "h").select("row", "pos", "h"), "places")
    seen = place.groupBy("h").agg(F.count(F.lit(1)).alias("n"))
    ranked = wins.select(F.xxhash64("win").alias("wid"), "win", "items", F.posexplode("shingles").alias("at", "h")).join(seen, "h")
    # a window with a shingle that no document has cannot occur; of the others the rarest shingle is the prefix
    first = ranked.groupBy("win").agg(F.min_by(F.struct("at", "h"), F.struct("n", "at")).alias("p"), F.count(F.lit(1)).alias("found"), F.first("items").alias("items"))
    prefix = first.where(F.col("found") == F.when(F.size("win") > 1, F.size("win") - 1).otherwise(F.size("win"))).select(F.col("p.h").alias("h"), F.col("p.at").alias("at"), "win", "items")
    prefix = staged(spark, prefix, "prefixes")
    near = place.join(small(prefix), "h").where("pos >= at")
    cands = near.groupBy("row").agg(F.collect_set(F.struct((F.col("pos") - F.col("at")).alias("start"), "win", "items")).alias("cands"))
    # whole texts are joined, as they are smaller than their arrays of words
    out = texts.join(cands, "row", "left").select("doc_id", words("text").alias("ws"), "cands")
    hits = F.filter(F.coalesce("cands", F.expr("cast(array() as array<struct<start:int, win:array<string>, items:array<bigint>>>)")), lambda c: F.slice(F.col("ws"), c["start"] + 1, F.size(c["win"])) == c["win"])
    out = out.select("doc_id", F.size("ws").cast("long").alias("n_words"), hits.alias("hits"))
    covered = F.array_distinct(F.flatten(F.transform("hits", lambda c: F.sequence(c["start"], c["start"] + F.size(c["win"]) - 1))))
    return out.select(id_back(), "n_words", F.size(covered).cast("long").alias("n_hit"), "hits", F.array_distinct(F.flatten(F.transform("hits", lambda c: c["items"]))).alias("item_ids"))


def digest(found: DataFrame) -> DataFrame:
    ids = F.array_sort(F.transform("item_ids", lambda x: x.cast("string")))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.array_join(ids, ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated")
    )


ORACLE = r"""
WITH d AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS ws FROM documents),
b AS (SELECT item_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS ws FROM benchmark),
b2 AS (SELECT item_id, ws, least(10, len(ws)) AS l FROM b WHERE len(ws) > 0),
w AS (SELECT DISTINCT item_id, l, array_to_string(ws[i:i + l - 1], ' ') AS win FROM (SELECT item_id, ws, l, unnest(range(1, len(ws) - l + 2)) AS i FROM b2)),
dw AS (SELECT doc_id, l, i, array_to_string(ws[i:i + l - 1], ' ') AS win FROM (SELECT doc_id, ws, l, unnest(range(1, len(ws) - l + 2)) AS i FROM d, (SELECT DISTINCT l FROM w))),
h AS (SELECT DISTINCT doc_id, item_id, w.l, i FROM dw JOIN w ON dw.win = w.win AND dw.l = w.l),
c AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + l)) AS p FROM h) GROUP BY 1),
k AS (SELECT doc_id, count(*) AS n_items, string_agg(CAST(item_id AS VARCHAR), ',' ORDER BY CAST(item_id AS VARCHAR)) AS s FROM (SELECT DISTINCT doc_id, item_id FROM h) GROUP BY 1)
SELECT d.doc_id, len(ws) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c ON d.doc_id = c.doc_id LEFT JOIN k ON d.doc_id = k.doc_id
"""
