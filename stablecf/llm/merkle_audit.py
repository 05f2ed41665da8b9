"""Merkle fixity audit of record archives, DataFrame functions only.

Records are ordered by id and laid out by offset; a record's leaf hashes its id,
length and bytes.  Leaves of one id range hash into a node, nodes of ``fanout``
neighbouring ranges into a parent, up to one root.  Two replicas are compared
root first; a branch is descended only where its hashes differ, so that the
records of intact ranges are never joined.

Defined results: null payloads hash as empty with length 0 and a null marker;
a repeated id hashes the tree of its payload hashes and their counts and is reported
once, with its number of copies in each replica; a missing record has status ``missing``
(``extra`` if only the replica has it); empty replicas differ in every range of
the other; null ids are records of range -1; only the named columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from stablecf.llm.common import staged


def leaves(df: DataFrame, id_col: str, payload_cols: list[str], span: int) -> DataFrame:
    """(rid, range_id, leaf, length, copies), one row per record id."""
    length = sum((F.coalesce(F.octet_length(c), F.lit(0)) for c in payload_cols), F.lit(0)).cast("long")
    parts: list[Column] = []
    for c in payload_cols:
        parts += [F.coalesce(F.octet_length(c).cast("string"), F.lit("null")), F.lit(":"), F.coalesce(F.col(c), F.lit(""))]
    rid = F.col(id_col).cast("long")
    each = df.select(rid.alias("rid"), length.alias("length"), F.sha2(F.concat(F.coalesce(rid.cast("string"), F.lit("null")), F.lit("|"), *parts), 256).alias("h"))
    # one row a record, unless an id repeats
    key = [F.col("rid").isNull().alias("no_id"), F.coalesce("rid", F.lit(0)).alias("k")]
    each = each.select(*key, "length", "h")
    whole = each.groupBy("no_id", "k").agg(F.count(F.lit(1)).alias("copies"), F.sum("length").alias("length"), F.min("h").alias("one"))
    # the payloads of a repeated id hash in a small tree by the digits of their hashes, so that no task holds all of them
    many = each.join(whole.where("copies > 1").select("no_id", "k"), ["no_id", "k"], "left_semi").groupBy("no_id", "k", "h").agg(F.count(F.lit(1)).alias("n"))
    nodes = many.select("no_id", "k", F.concat("h", F.lit("*"), F.col("n").cast("string")).alias("h"), F.col("h").alias("at"))
    for digits in (6, 4, 2, 0):
        nodes = nodes.groupBy("no_id", "k", F.substring("at", 1, digits).alias("at")).agg(F.sha2(F.array_join(F.array_sort(F.collect_list("h")), ","), 256).alias("h"))
    both = whole.join(nodes.select("no_id", "k", F.col("h").alias("several")), ["no_id", "k"], "left")
    rid = F.when(~F.col("no_id"), F.col("k"))
    return both.select(rid.alias("rid"), F.coalesce(F.floor(rid / span), F.lit(-1)).cast("long").alias("range_id"), F.coalesce("several", "one").alias("leaf"), "length", "copies")


def with_offsets(leaf: DataFrame, fanout: int = 4096) -> DataFrame:
    """Adds the record's byte offset: sums over ranges, over blocks of ranges and so on up to a few, and back down within each block."""
    levels = [leaf.groupBy(F.col("range_id").alias("node")).agg(F.sum("length").alias("len"))]
    lo, hi = leaf.agg(F.min("range_id"), F.max("range_id")).first()
    while lo is not None and hi - lo > fanout:
        lo, hi = lo // fanout, hi // fanout
        levels.append(levels[-1].groupBy(F.floor(F.col("node") / fanout).cast("long").alias("node")).agg(F.sum("len").alias("len")))
    start = None
    for at in reversed(levels):
        up = F.floor(F.col("node") / fanout).cast("long")
        if start is None:  # at most ``fanout`` + 1 nodes
            start = at.select("node", (F.sum("len").over(Window.orderBy("node")) - F.col("len")).alias("start"))
        else:
            inside = at.withColumn("up", up).withColumn("before", F.sum("len").over(Window.partitionBy("up").orderBy("node")) - F.col("len"))
            start = inside.join(start.select(F.col("node").alias("up"), "start"), "up").select("node", (F.col("start") + F.col("before")).alias("start"))
    inside = F.sum("length").over(Window.partitionBy("range_id").orderBy("rid")) - F.col("length")
    return leaf.join(start.withColumnRenamed("node", "range_id"), "range_id").select("rid", "range_id", "leaf", "length", "copies", (F.col("start") + inside).alias("offset"))


def parents(nodes: DataFrame, fanout: int) -> DataFrame:
    """The next level up of (node, hash)."""
    return nodes.groupBy(F.floor(F.col("node") / fanout).cast("long").alias("node")).agg(F.sha2(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("node", "hash"))), lambda x: F.concat(x["node"].cast("string"), F.lit(":"), x["hash"])), ","), 256).alias("hash"))


def height(a: DataFrame, b: DataFrame, fanout: int) -> int:
    """Levels above the ranges until one node is left, or the two tops of negative and other ids, which no level joins."""
    lo, hi = a.select("range_id").unionByName(b.select("range_id")).agg(F.min("range_id"), F.max("range_id")).first()
    n = 0
    while lo is not None and lo != hi and (lo, hi) != (-1, 0):
        lo, hi, n = lo // fanout, hi // fanout, n + 1
    return n


def tree(spark: SparkSession, leaf: DataFrame, fanout: int, levels: int) -> list[DataFrame]:
    """Levels of (node, hash) from the ranges to the top; each is stored, so that neither the next level nor the descent hashes again."""
    ranges = leaf.groupBy(F.col("range_id").alias("node")).agg(F.sha2(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rid", "leaf"))), lambda x: x["leaf"]), ","), 256).alias("hash"))
    out = [staged(spark, ranges, "merkle-ranges")]
    for _ in range(levels):
        out.append(staged(spark, parents(out[-1], fanout), "merkle-level"))
    return out


def audit(spark: SparkSession, left: DataFrame, right: DataFrame, id_col: str, payload_cols: list[str], span: int = 64, fanout: int = 64, levels: int | None = None) -> DataFrame:
    """(rid, range_id, offset, length, left_leaf, right_leaf, status, left_copies, right_copies): the records that differ, found by descent from the roots.

    ``offset`` and ``length`` are of the left replica; ``levels`` is the height above the ranges,
    by default the one at which a single node is left (two if there are negative or null ids).
    """
    a = staged(spark, with_offsets(leaves(left, id_col, payload_cols, span)), "merkle-left")
    b = staged(spark, leaves(right, id_col, payload_cols, span), "merkle-right")
    levels = height(a, b, fanout) if levels is None else levels
    ta, tb = tree(spark, a, fanout, levels), tree(spark, b, fanout, levels)
    suspects = None
    for la, lb in zip(reversed(ta), reversed(tb), strict=True):
        if suspects is not None:
            keep = suspects.select(F.col("node").alias("up"))
            la, lb = (x.join(keep, F.floor(F.col("node") / fanout) == F.col("up"), "left_semi") for x in (la, lb))
        both = la.withColumnRenamed("hash", "ha").join(lb.withColumnRenamed("hash", "hb"), "node", "full")
        suspects = both.where(~F.col("ha").eqNullSafe(F.col("hb"))).select("node")
    bad = suspects.select(F.col("node").alias("range_id"))
    x = a.join(bad, "range_id", "left_semi").select("rid", "range_id", "offset", "length", F.col("leaf").alias("left_leaf"), F.col("copies").alias("left_copies"))
    y = b.join(bad, "range_id", "left_semi").select(F.col("rid").alias("r2"), F.col("range_id").alias("g2"), F.col("leaf").alias("right_leaf"), F.col("copies").alias("right_copies"))
    both = x.join(y, F.col("rid").eqNullSafe(F.col("r2")), "full").where(~F.col("left_leaf").eqNullSafe(F.col("right_leaf")))
    status = F.when(F.col("right_leaf").isNull(), "missing").when(F.col("left_leaf").isNull(), "extra").otherwise("corrupt")
    return both.select(F.coalesce("rid", "r2").alias("rid"), F.coalesce("range_id", "g2").alias("range_id"), "offset", "length", "left_leaf", "right_leaf", status.alias("status"), *(F.coalesce(c, F.lit(0).cast("long")).alias(c) for c in ("left_copies", "right_copies")))


def damaged(df: DataFrame) -> DataFrame:
    """A second replica of ``pages`` with known damage: changed, lost and added records."""
    k = F.col("page_id")
    kept = df.where(F.coalesce(k % 211 != 3, F.lit(True))).select(k, "url", F.when(k % 101 == 7, F.concat(F.lit("#"), F.coalesce("html", F.lit("")))).otherwise(F.col("html")).alias("html"))
    extra = df.where(k % 307 == 11).select((-k).alias("page_id"), "url", "html")
    return kept.unionByName(extra)


ORACLE = r"""
WITH a AS (SELECT page_id, sum(coalesce(octet_length(encode(url)), 0) + coalesce(octet_length(encode(html)), 0)) AS length,
  min(sha256(coalesce(CAST(page_id AS VARCHAR), 'null') || '|' || coalesce(CAST(octet_length(encode(url)) AS VARCHAR), 'null') || ':' || coalesce(url, '') || coalesce(CAST(octet_length(encode(html)) AS VARCHAR), 'null') || ':' || coalesce(html, ''))) AS leaf FROM pages GROUP BY page_id),
o AS (SELECT page_id, length, leaf, sum(length) OVER (ORDER BY page_id) - length AS "offset" FROM a),
r AS (SELECT page_id, url, CASE WHEN page_id % 101 = 7 THEN '#' || coalesce(html, '') ELSE html END AS html FROM pages WHERE page_id % 211 <> 3
  UNION ALL SELECT -page_id, url, html FROM pages WHERE page_id % 307 = 11),
b AS (SELECT page_id, sha256(coalesce(CAST(page_id AS VARCHAR), 'null') || '|' || coalesce(CAST(octet_length(encode(url)) AS VARCHAR), 'null') || ':' || coalesce(url, '') || coalesce(CAST(octet_length(encode(html)) AS VARCHAR), 'null') || ':' || coalesce(html, '')) AS leaf FROM r)
SELECT coalesce(o.page_id, b.page_id) AS rid, CAST(floor(coalesce(o.page_id, b.page_id) / 64.0) AS BIGINT) AS range_id, CAST("offset" AS BIGINT) AS "offset", CAST(length AS BIGINT) AS length,
  o.leaf AS left_leaf, b.leaf AS right_leaf, CASE WHEN b.leaf IS NULL THEN 'missing' WHEN o.leaf IS NULL THEN 'extra' ELSE 'corrupt' END AS status
FROM o FULL JOIN b ON o.page_id = b.page_id WHERE o.leaf IS DISTINCT FROM b.leaf
"""
