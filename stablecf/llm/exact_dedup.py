"""Exact deduplication by an extendible-hash index, DataFrame functions only.

The index is a set of stored tables in the shared folder.  An entry is a 64-bit
key, a salt of the document and a count, so a group of copies, however large, is a
few entries.  A bucket is the entries of one prefix of the key.  The directory
starts with as many leading bits as the number of keys asks for; buckets with
more than ``bucket_keys`` different keys are split by one more bit, which doubles
the directory, and only their entries are written again.  The directory has at
most ``2**max_depth`` rows whatever the input, so it is broadcast; a bucket
of full depth chains more keys.  A bucket's owner task finds the keys of its range
that are met more than once; their texts are chained: grouped by their bytes,
salted by document, and a chain link is a text.

Defined results: null text is the empty text; blanks runs ``[\\x20\\x09-\\x0D]+``
count as one space; rows with a null id take part with the largest id; rows that
repeat a kept id are the kept document and are all marked kept; an empty table
gives an empty result; only the id and text columns are read.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm.common import id_back, ids_and_texts, staged

BLANKS = r"[\x20\x09-\x0D]+"


def prefix_of(key: str, depth: str) -> Column:
    """The leading ``depth`` bits (a column) of a key."""
    return F.expr(f"if({depth} = 0, 0L, shiftrightunsigned({key}, 64 - {depth}))")


def build_index(spark: SparkSession, keyed: DataFrame, bucket_keys: int, max_depth: int) -> tuple[DataFrame, int]:
    """(entries, global depth): entries are (depth, prefix, key, salt, n), each stored in the table of its bucket's last split."""
    entries = keyed.groupBy("key", "salt").agg(F.count(F.lit(1)).alias("n"))
    keys = keyed.select("key").distinct().count()
    depth = min(max_depth, math.ceil(math.log2(max(1.0, keys / bucket_keys))))
    held = entries.withColumn("depth", F.lit(depth)).withColumn("prefix", prefix_of("key", "depth"))
    settled = None
    while True:
        held = staged(spark, held.select("depth", "prefix", "key", "salt", "n").repartition("depth", "prefix"), "exact-buckets")
        load = held.groupBy("depth", "prefix", "key").agg(F.count(F.lit(1)).alias("salts")).groupBy("depth", "prefix").agg(F.count(F.lit(1)).alias("keys"))
        full = staged(spark, load.where((F.col("keys") > bucket_keys) & (F.col("depth") < max_depth)).select("depth", "prefix"), "exact-overfull")
        if not full.take(1):
            return (held if settled is None else settled.unionByName(held)), depth
        at = ["depth", "prefix"]
        kept = held.join(F.broadcast(full), at, "left_anti")
        settled = kept if settled is None else settled.unionByName(kept)
        depth += 1
        held = held.join(F.broadcast(full), at, "left_semi").withColumn("depth", F.col("depth") + 1).withColumn("prefix", prefix_of("key", "depth"))


def directory(entries: DataFrame, depth: int) -> DataFrame:
    """(cell, bucket_depth, bucket_prefix): for each value of the leading ``depth`` bits that is in use the bucket that holds it."""
    buckets = entries.select("depth", "prefix").distinct()
    first = F.expr(f"shiftleft(prefix, {depth} - depth)")
    cells = F.sequence(first, first + F.expr(f"shiftleft(1L, {depth} - depth)") - 1)
    return buckets.select(F.explode(cells).alias("cell"), F.col("depth").alias("bucket_depth"), F.col("prefix").alias("bucket_prefix"))


def exact_dedup(
    spark: SparkSession,
    df: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    bucket_keys: int = 4096,
    max_depth: int = 14,
    salts: int = 64,
    key: Callable[[Column], Column] = F.xxhash64,
) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256), one row per input row.

    ``key`` may be any 64-bit function of the normalised text; colliding texts are told apart by their bytes.
    """
    salt = F.pmod(F.xxhash64("doc_id"), F.lit(salts)).cast("int").alias("salt")
    norm = ids_and_texts(df, id_col, text_col).select("doc_id", F.regexp_replace("text", BLANKS, " ").alias("norm"))
    keyed = staged(spark, norm.select("doc_id", key(F.col("norm")).alias("key"), F.sha2("norm", 256).alias("sha"), salt), "exact-keys")
    entries, depth = build_index(spark, keyed, bucket_keys, max_depth)
    owned = entries.repartition("depth", "prefix").groupBy("depth", "prefix", "key").agg(F.sum("n").alias("n"), F.collect_set("salt").alias("salts"))
    again = staged(spark, owned.where("n > 1").select("key", F.col("depth").alias("bucket_depth"), F.col("prefix").alias("bucket_prefix"), F.explode("salts").alias("salt")), "exact-repeated")
    cells = F.broadcast(directory(entries, depth))
    texts = norm.select("doc_id", key(F.col("norm")).alias("key"), "norm", salt).withColumn("cell", prefix_of("key", str(depth)))
    bucket = ["bucket_depth", "bucket_prefix"]
    texts = texts.join(cells, "cell").join(again.hint("shuffle_hash"), [*bucket, "key", "salt"])
    links = texts.groupBy(*bucket, "key", "salt", "norm").agg(F.min("doc_id").alias("keep"), F.count(F.lit(1)).alias("n"))
    chains = links.groupBy(*bucket, "key", "norm").agg(F.min("keep").alias("keep"), F.sum("n").alias("n"), F.collect_set("salt").alias("salts"))
    chains = chains.select("key", F.sha2("norm", 256).alias("sha"), F.explode("salts").alias("salt"), "keep", "n")
    out = keyed.join(chains, ["key", "salt", "sha"], "left")
    keep = F.coalesce("keep", "doc_id")
    return out.select(
        id_back(),
        F.when(keep != (1 << 63) - 1, keep).alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        (F.col("doc_id") == keep).alias("kept"),
        F.col("sha").alias("text_sha256"),
    )


ORACLE = r"""
WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents)
SELECT doc_id, min(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size,
       doc_id = min(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256
FROM n
"""
