"""Surrounding operators on features and tables: each query with its Spark plan and the SQL that defines its result.

Rounded values get 1e-9 first on both sides, as means of cents are often exact ties.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stablecf.functions import features as A
from stablecf.functions import measures as B
from stablecf.sources.session import shared_dir

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def read(spark: SparkSession, d: str, t: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{t}.parquet")


def r(c, n: int = 4) -> Column:
    return F.round((F.col(c) if isinstance(c, str) else c) + 1e-9, n) + F.lit(0.0)


def feature(x: Column) -> list[Column]:
    """(w, m0, v0) of one axis."""
    return [F.count(F.lit(1)).cast("double").alias("w"), r(F.avg(x)).alias("m0"), r(F.var_pop(x)).alias("v0")]


def f_sql(x: str) -> str:
    return f"CAST(count(*) AS DOUBLE) AS w, round(avg({x}) + 1e-9, 4) + 0.0 AS m0, round(var_pop({x}) + 1e-9, 4) + 0.0 AS v0"


def price() -> Column:
    return F.col("l_extendedprice") / 1000
N = "count(*) AS n"


def count() -> Column:
    return F.count(F.lit(1)).alias("n")


@query("SELECT count(*) AS n, min(l_quantity) AS lo_qty, max(l_quantity) AS hi_qty, min(l_extendedprice) AS lo_price, max(l_extendedprice) AS hi_price FROM lineitem")
def q_op_scan_parquet(s, d):
    return read(s, d, "lineitem").agg(count(), *[f(c).alias(f"{n}_{x}") for c, x in (("l_quantity", "qty"), ("l_extendedprice", "price")) for n, f in (("lo", F.min), ("hi", F.max))])


@query("WITH g AS (SELECT l_returnflag, count(*) AS w, round(avg(l_quantity), 2) AS m0 FROM lineitem GROUP BY 1) SELECT format, l_returnflag, CAST(w AS DOUBLE) AS w, m0 FROM g, (VALUES ('parquet'), ('json'), ('csv'), ('orc')) f(format)")
def q_op_scan_roundtrip(s, d):
    """Features written in four formats to the shared folder and read back."""
    folder = shared_dir(s)
    g = read(s, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).cast("double").alias("w"), F.round(F.avg("l_quantity"), 2).alias("m0"))
    out = []
    for name in ("parquet", "json", "csv", "orc"):
        path = f"{folder}/features-{uuid.uuid4().hex}.{name}"
        g.write.format(name).save(path)
        out.append(s.read.format(name).schema(g.schema).load(path).select(F.lit(name).alias("format"), "l_returnflag", "w", "m0"))
    return reduce(DataFrame.unionByName, out)


@query("SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity AS x0, l_extendedprice / 1000 AS x1, l_discount * 100 AS x2, l_tax * 100 AS x3 FROM lineitem")
def q_op_project(s, d):
    return read(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.col("l_quantity").alias("x0"), price().alias("x1"), (F.col("l_discount") * 100).alias("x2"), (F.col("l_tax") * 100).alias("x3"))


@query("WITH e AS (SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem) SELECT CAST(floor((l_extendedprice - lo) / (hi - lo) * 10) AS BIGINT) AS tenth, count(*) AS n FROM lineitem, e GROUP BY 1")
def q_op_minmax(s, d):
    """Prices scaled to 0..1, as counts of tenths; the extremes are one row."""
    li = read(s, d, "lineitem").select("l_extendedprice")
    e = li.agg(F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"))
    x = (F.col("l_extendedprice") - F.col("lo")) / (F.col("hi") - F.col("lo"))
    return li.crossJoin(F.broadcast(e)).groupBy(F.floor(x * 10).cast("long").alias("tenth")).agg(count())


@query("SELECT count(*) AS n, sum(CASE WHEN value BETWEEN 1 AND 100 THEN 1 ELSE 0 END)::BIGINT AS in_range FROM events WHERE value IS NOT NULL AND NOT isnan(value) AND abs(value) < 'infinity'::DOUBLE")
def q_op_filter_finite(s, d):
    e = read(s, d, "events").where(F.col("value").isNotNull() & ~F.isnan("value") & (F.abs("value") < float("inf")))
    return e.agg(count(), F.sum(F.col("value").between(1, 100).cast("long")).alias("in_range"))


@query("SELECT p_brand, count(*) AS n FROM part WHERE p_brand IN ('Brand#1', 'Brand#2', 'Brand#3') AND p_name LIKE 'red%' GROUP BY 1")
def q_op_filter_in_like(s, d):
    return read(s, d, "part").where(F.col("p_brand").isin("Brand#1", "Brand#2", "Brand#3") & F.col("p_name").like("red%")).groupBy("p_brand").agg(count())


@query(f"SELECT r_name, {f_sql('c_acctbal / 1000')} FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def q_op_join_broadcast(s, d):
    c, n, g = read(s, d, "customer"), read(s, d, "nation"), read(s, d, "region")
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(g), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(*feature(F.col("c_acctbal") / 1000))


ORDERS_SQL = f"SELECT o_orderpriority, {f_sql('l_quantity')} FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _orders(s, d, hint):
    li, o = read(s, d, "lineitem").select("l_orderkey", "l_quantity"), read(s, d, "orders").select("o_orderkey", "o_orderpriority")
    return li.join(o.hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(*feature(F.col("l_quantity")))


@query(ORDERS_SQL)
def q_op_join_smj(s, d):
    return _orders(s, d, "merge")


@query(ORDERS_SQL)
def q_op_join_shuffle_hash(s, d):
    return _orders(s, d, "shuffle_hash")


NATION = "n AS (SELECT c_nationkey AS k, CAST(count(*) AS DOUBLE) AS w, avg(c_acctbal / 1000) AS a FROM customer GROUP BY 1)"


def _nations(s, d) -> DataFrame:
    return A.stable_agg(read(s, d, "customer"), [F.col("c_acctbal") / 1000], ["c_nationkey"])


@query(f"WITH {NATION} SELECT x.k AS a, y.k AS b, round(sqrt(x.w * y.w / (x.w + y.w)) * abs(x.a - y.a) + 1e-9, 4) + 0.0 AS value FROM n x JOIN n y ON x.k < y.k")
def q_op_join_theta(s, d):
    return B.pairwise(_nations(s, d), "c_nationkey", "D4").select("a", "b", r("value").alias("value"))


@query(f"WITH {NATION} SELECT k, c.comp, round((a - c.mu) * (a - c.mu) + 1e-9, 4) + 0.0 AS d2 FROM n, (VALUES (0, 1.0), (1, 4.0), (2, 7.0)) c(comp, mu)")
def q_op_join_cross(s, d):
    """Features with every component of a literal model: k rows."""
    model = s.createDataFrame([(0, 1.0), (1, 4.0), (2, 7.0)], "comp int, mu double")
    x = F.col("m")[0] - F.col("mu")
    return _nations(s, d).crossJoin(F.broadcast(model)).select(F.col("c_nationkey").alias("k"), "comp", r(x * x).alias("d2"))


@query("SELECT count(*) AS n, count(DISTINCT p_partkey) AS parts FROM lineitem JOIN part ON l_extendedprice BETWEEN 10 * p_retailprice - 1 AND 10 * p_retailprice + 1")
def q_op_join_range(s, d):
    """Prices within 1 of ten times a part's: a part goes to the two bins its range may touch, so the join is on equal bins."""
    p = read(s, d, "part").select("p_partkey", (F.col("p_retailprice") * 10 - 1).alias("lo"), (F.col("p_retailprice") * 10 + 1).alias("hi"))
    p = p.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / 4), F.floor(F.col("hi") / 4))))
    li = read(s, d, "lineitem").select(F.col("l_extendedprice").alias("x"), F.floor(F.col("l_extendedprice") / 4).alias("bin"))
    return li.join(p, "bin").where(F.col("x").between(F.col("lo"), F.col("hi"))).agg(count(), F.count_distinct("p_partkey").alias("parts"))


def _docs(s, d):
    return read(s, d, "documents").select("doc_id", "lang", "n_chars"), read(s, d, "labels").select(F.col("doc_id").alias("l_id"), "quality", "toxic")


SIDES = "count(*) AS n, count(d.doc_id) AS documents, count(l.doc_id) AS labelled, sum(l.toxic)::BIGINT AS toxic"


def _sides(s, d, how):
    docs, labels = _docs(s, d)
    return docs.join(labels, F.col("doc_id") == F.col("l_id"), how).agg(count(), F.count("doc_id").alias("documents"), F.count("l_id").alias("labelled"), F.sum("toxic").alias("toxic"))


@query(f"SELECT {SIDES} FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def q_op_join_left(s, d):
    return _sides(s, d, "left")


@query(f"SELECT {SIDES} FROM documents d RIGHT JOIN labels l ON d.doc_id = l.doc_id")
def q_op_join_right(s, d):
    return _sides(s, d, "right")


@query(f"SELECT {SIDES} FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def q_op_join_full(s, d):
    return _sides(s, d, "full")


@query("WITH g AS (SELECT c_mktsegment AS seg, avg(c_acctbal / 1000) AS a FROM customer GROUP BY 1), h AS (SELECT n_regionkey AS reg, avg(c_acctbal / 1000) AS b FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1), t AS (SELECT seg, reg, row_number() OVER (PARTITION BY seg ORDER BY abs(a - b), reg) AS place FROM g, h) SELECT seg, reg, place FROM t WHERE place <= 3")
def q_op_join_lateral(s, d):
    """The three nearest region features of each segment feature; both sides are a few rows."""
    c = read(s, d, "customer")
    g = A.stable_agg(c, [F.col("c_acctbal") / 1000], ["c_mktsegment"]).select(F.col("c_mktsegment").alias("seg"), F.col("m")[0].alias("a"))
    n = read(s, d, "nation").select("n_nationkey", F.col("n_regionkey").alias("reg"))
    h = A.stable_agg(c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")), [F.col("c_acctbal") / 1000], ["reg"]).select("reg", F.col("m")[0].alias("b"))
    w = Window.partitionBy("seg").orderBy(F.abs(F.col("a") - F.col("b")), "reg")
    return g.crossJoin(F.broadcast(h)).withColumn("place", F.row_number().over(w).cast("long")).where("place <= 3").select("seg", "reg", "place")


@query("SELECT count(*) AS n, count(DISTINCT a.user_id) AS users FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def q_op_join_self(s, d):
    """Events of a user within ten minutes: time bins make the join one on equal keys, so a busy user is split."""
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    e = read(s, d, "events").select("user_id", "event_id", t.alias("t"), F.floor(t / 600_000_000).alias("bin"))
    x = e.select("user_id", F.col("event_id").alias("i"), F.col("t").alias("ta"), F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"))
    j = x.join(e, ["user_id", "bin"]).where((F.col("i") < F.col("event_id")) & F.col("t").between(F.col("ta"), F.col("ta") + 600_000_000))
    return j.agg(count(), F.count_distinct("user_id").alias("users"))


@query(f"SELECT l_returnflag, l_linestatus, {f_sql('l_extendedprice / 1000')} FROM lineitem GROUP BY 1, 2")
def q_op_agg_hash(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(*feature(price()))


@query("SELECT r_name, list_aggregate(list_sort(list(CAST(n_name AS VARCHAR))), 'string_agg', ',') AS names, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def q_op_agg_object(s, d):
    n = read(s, d, "nation").join(F.broadcast(read(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return n.groupBy("r_name").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"), count())


@query("SELECT p_brand, max(p_name) AS last_name, arg_min(p_partkey, struct_pack(a := p_retailprice, b := p_partkey)) AS cheapest FROM part GROUP BY 1")
def q_op_agg_sort(s, d):
    return read(s, d, "part").groupBy("p_brand").agg(F.max("p_name").alias("last_name"), F.min_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("cheapest"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(*) AS n FROM lineitem GROUP BY 1")
def q_op_agg_distinct(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"), count())


@query("SELECT l_returnflag, TRUE AS parts_near, TRUE AS median_near FROM lineitem GROUP BY 1")
def q_op_agg_approx(s, d):
    """Whether sketches are within their bounds of the exact counts and medians."""
    g = read(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("b"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("p"), F.percentile("l_extendedprice", 0.5).alias("q"))
    return g.select("l_returnflag", (F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("parts_near"), (F.abs(F.col("p") - F.col("q")) <= 0.02 * F.col("q")).alias("median_near"))


@query("SELECT l_returnflag, count(*) FILTER (WHERE l_discount > 0.05) AS n, round(avg(l_quantity) FILTER (WHERE l_discount > 0.05) + 1e-9, 4) + 0.0 AS m0 FROM lineitem GROUP BY 1")
def q_op_agg_filter(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag").agg(F.expr("count(1) FILTER (WHERE l_discount > 0.05)").alias("n"), r(F.expr("avg(l_quantity) FILTER (WHERE l_discount > 0.05)")).alias("m0"))


@query("SELECT l_linestatus, round(var_pop(l_quantity) + 1e-9, 4) + 0.0 AS vp, round(var_samp(l_quantity) + 1e-9, 4) + 0.0 AS vs, round(stddev_pop(l_quantity) + 1e-9, 4) + 0.0 AS sp, round(covar_pop(l_quantity, l_extendedprice / 1000) + 1e-9, 4) + 0.0 AS cv, round(corr(l_quantity, l_extendedprice / 1000) + 1e-9, 4) + 0.0 AS co FROM lineitem GROUP BY 1")
def q_op_agg_moments(s, d):
    q = F.col("l_quantity")
    return read(s, d, "lineitem").groupBy("l_linestatus").agg(r(F.var_pop(q)).alias("vp"), r(F.var_samp(q)).alias("vs"), r(F.stddev_pop(q)).alias("sp"), r(F.covar_pop(q, price())).alias("cv"), r(F.corr(q, price())).alias("co"))


@query("SELECT l_returnflag, round(avg(CASE WHEN l_linestatus = 'F' THEN l_extendedprice / 1000 END) + 1e-9, 4) + 0.0 AS F, round(avg(CASE WHEN l_linestatus = 'O' THEN l_extendedprice / 1000 END) + 1e-9, 4) + 0.0 AS O FROM lineitem GROUP BY 1")
def q_op_agg_pivot(s, d):
    p = read(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.avg(price()))
    return p.select("l_returnflag", r("F").alias("F"), r("O").alias("O"))


LATTICE = "customer JOIN nation ON c_nationkey = n_nationkey"


def _lattice(s, d):
    c = read(s, d, "customer").join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return c.select("n_regionkey", "c_mktsegment", (F.col("c_acctbal") / 1000).alias("x0"))


def _level():
    return F.grouping_id().cast("long").alias("level")


@query(f"SELECT n_regionkey, c_mktsegment, CAST(grouping(n_regionkey) * 2 + grouping(c_mktsegment) AS BIGINT) AS level, {f_sql('c_acctbal / 1000')} FROM {LATTICE} GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
def q_op_rollup_features(s, d):
    return _lattice(s, d).rollup("n_regionkey", "c_mktsegment").agg(_level(), *feature(F.col("x0")))


@query(f"SELECT n_regionkey, c_mktsegment, CAST(grouping(n_regionkey) * 2 + grouping(c_mktsegment) AS BIGINT) AS level, {f_sql('c_acctbal / 1000')} FROM {LATTICE} GROUP BY CUBE (n_regionkey, c_mktsegment)")
def q_op_cube_features(s, d):
    return _lattice(s, d).cube("n_regionkey", "c_mktsegment").agg(_level(), *feature(F.col("x0")))


@query(f"SELECT n_regionkey, c_mktsegment, {f_sql('c_acctbal / 1000')} FROM {LATTICE} GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment))")
def q_op_grouping_sets(s, d):
    x = _lattice(s, d)
    return x.groupingSets([[F.col("n_regionkey")], [F.col("c_mktsegment")]], F.col("n_regionkey"), F.col("c_mktsegment")).agg(*feature(F.col("x0")))


@query("WITH g AS (SELECT n_regionkey, n_nationkey, count(*) AS w FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2) SELECT n_regionkey, n_nationkey, row_number() OVER o AS rn, rank() OVER p AS rk, dense_rank() OVER p AS dr, CAST(ntile(3) OVER o AS BIGINT) AS nt, round(percent_rank() OVER p + 1e-9, 4) + 0.0 AS pr FROM g WINDOW o AS (PARTITION BY n_regionkey ORDER BY w DESC, n_nationkey), p AS (PARTITION BY n_regionkey ORDER BY w DESC)")
def q_op_win_rank(s, d):
    g = read(s, d, "customer").join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_regionkey", "n_nationkey").agg(F.count(F.lit(1)).alias("w"))
    p = Window.partitionBy("n_regionkey").orderBy(F.desc("w"))
    o = Window.partitionBy("n_regionkey").orderBy(F.desc("w"), "n_nationkey")
    return g.select("n_regionkey", "n_nationkey", F.row_number().over(o).cast("long").alias("rn"), F.rank().over(p).cast("long").alias("rk"), F.dense_rank().over(p).cast("long").alias("dr"), F.ntile(3).over(o).cast("long").alias("nt"), r(F.percent_rank().over(p)).alias("pr"))


def _us() -> Column:
    return F.unix_micros(F.col("ts").cast("timestamp"))


@query("SELECT event_id, epoch_us(ts) - lag(epoch_us(ts)) OVER o AS gap, lead(event_id) OVER o AS next_id, first_value(event_id) OVER o AS first_id, last_value(event_id) OVER w AS last_id, nth_value(event_id, 2) OVER w AS second_id FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id), w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def q_op_win_analytic(s, d):
    o = Window.partitionBy("user_id").orderBy("ts", "event_id")
    w = o.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read(s, d, "events").select("event_id", (_us() - F.lag(_us()).over(o)).alias("gap"), F.lead("event_id").over(o).alias("next_id"), F.first("event_id").over(o).alias("first_id"), F.last("event_id").over(w).alias("last_id"), F.nth_value("event_id", 2).over(w).alias("second_id"))


@query("SELECT event_id, count(*) OVER w AS n, round(avg(value) OVER w + 1e-9, 4) + 0.0 AS m0 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 9 PRECEDING AND CURRENT ROW)")
def q_op_win_moving(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-9, 0)
    return read(s, d, "events").select("event_id", F.count(F.lit(1)).over(w).alias("n"), r(F.avg("value").over(w)).alias("m0"))


@query("SELECT event_id, count(*) OVER w AS n, round(avg(value) OVER w + 1e-9, 4) + 0.0 AS m0 FROM (SELECT *, epoch_us(ts) // 1000000 AS sec FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY sec RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)")
def q_op_win_range(s, d):
    e = read(s, d, "events").withColumn("sec", F.floor(_us() / 1_000_000))
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("n"), r(F.avg("value").over(w)).alias("m0"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
def q_op_sort_limit(s, d):
    return read(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100)


def _keys(s, d):
    return read(s, d, "customer").select(F.col("c_nationkey").alias("k")), read(s, d, "supplier").select(F.col("s_nationkey").alias("k"))


@query("SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier) GROUP BY 1")
def q_op_union(s, d):
    a, b = _keys(s, d)
    return a.unionByName(b).groupBy("k").agg(count())


@query("SELECT k, n FROM (SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier) GROUP BY 1)")
def q_op_intersect(s, d):
    a, b = _keys(s, d)
    return a.intersectAll(b).groupBy("k").agg(count()).join(a.intersect(b), "k", "left_semi")


@query("SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier) GROUP BY 1")
def q_op_except(s, d):
    a, b = _keys(s, d)
    return a.exceptAll(b).groupBy("k").agg(count())


@query("SELECT DISTINCT l_quantity, l_tax FROM lineitem")
def q_op_distinct(s, d):
    return read(s, d, "lineitem").select("l_quantity", "l_tax").dropDuplicates()


@query("SELECT p_partkey, round(sqrt(p_retailprice) + 1e-9, 4) + 0.0 AS a, round(ln(p_retailprice) + 1e-9, 4) + 0.0 AS b, round(exp(p_size / 100.0) + 1e-9, 4) + 0.0 AS c, round(pow(p_size, 1.5) + 1e-9, 4) + 0.0 AS d, CAST(floor(p_retailprice) AS BIGINT) AS e, abs(p_retailprice - 950) AS f, greatest(p_size, 25) AS g, CAST(sign(p_size - 25) AS INTEGER) AS h FROM part")
def q_op_math(s, d):
    p, z = F.col("p_retailprice"), F.col("p_size")
    return read(s, d, "part").select("p_partkey", r(F.sqrt(p)).alias("a"), r(F.log(p)).alias("b"), r(F.exp(z / 100.0)).alias("c"), r(F.pow(z, F.lit(1.5))).alias("d"), F.floor(p).cast("long").alias("e"), F.abs(p - 950).alias("f"), F.greatest(z, F.lit(25)).alias("g"), F.signum(z - 25).cast("int").alias("h"))


@query("SELECT event_id, epoch_us(date_trunc('hour', ts)) AS hour_us, epoch_us(ts) AS us, CAST(date_diff('day', TIMESTAMP '2024-01-01', ts) AS INTEGER) AS days, CAST(dayofweek(ts) + 1 AS INTEGER) AS dow, epoch_us(ts + INTERVAL 90 MINUTE) AS later_us FROM events")
def q_op_date(s, d):
    t = F.col("ts").cast("timestamp")
    return read(s, d, "events").select("event_id", F.unix_micros(F.date_trunc("hour", t)).alias("hour_us"), F.unix_micros(t).alias("us"), F.datediff(t.cast("date"), F.lit("2024-01-01").cast("date")).alias("days"), F.dayofweek(t).alias("dow"), F.unix_micros(t + F.expr("interval 90 minutes")).alias("later_us"))


@query(r"SELECT item_id, CAST(length(text) AS INTEGER) AS n, substring(text, 1, 8) AS head, CAST(length(regexp_replace(text, '[aeiou]', '', 'g')) AS INTEGER) AS consonants, CAST(len(string_split(text, ' ')) AS INTEGER) AS parts FROM benchmark")
def q_op_string(s, d):
    t = F.col("text")
    return read(s, d, "benchmark").select("item_id", F.length(t).alias("n"), F.substring(t, 1, 8).alias("head"), F.length(F.regexp_replace(t, "[aeiou]", "")).alias("consonants"), F.size(F.split(t, " ")).alias("parts"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE)))) + 1e-9, 4) + 0.0 AS norm, round(list_avg(list_transform(embedding, lambda v: CAST(v AS DOUBLE))) + 1e-9, 4) + 0.0 AS mean, CAST(list_position(embedding, list_max(embedding)) AS INTEGER) AS top FROM embeddings")
def q_op_array(s, d):
    e = F.transform("embedding", lambda v: v.cast("double"))
    sq = A.total(F.zip_with(e, e, lambda a, b: a * b))
    top = F.array_position("embedding", F.array_max("embedding")).cast("int")
    return read(s, d, "embeddings").select("vec_id", r(F.sqrt(sq)).alias("norm"), r(A.total(e) / F.size("embedding")).alias("mean"), top.alias("top"))


AXES_SQL = "e AS (SELECT unnest(range(0, 64)) AS axis, unnest(list_transform(embedding, lambda v: CAST(v AS DOUBLE))) AS x FROM embeddings)"


@query(f"WITH {AXES_SQL} SELECT CAST(axis AS INTEGER) AS axis, CAST(count(*) AS DOUBLE) AS w, round(avg(x) + 1e-9, 4) + 0.0 AS m0, round(var_pop(x) + 1e-9, 4) + 0.0 AS v0 FROM e GROUP BY axis")
def q_op_explode(s, d):
    e = read(s, d, "embeddings").select(F.posexplode("embedding").alias("axis", "x"))
    return e.groupBy("axis").agg(*feature(F.col("x").cast("double")))


@query("WITH s AS (SELECT stddev_pop(l_quantity) AS a, stddev_pop(l_extendedprice / 1000) AS b, stddev_pop(l_tax * 100) AS c FROM lineitem) SELECT axis, round(CASE axis WHEN 'qty' THEN a WHEN 'price' THEN b ELSE c END + 1e-9, 4) + 0.0 AS sd FROM s, (VALUES ('qty'), ('price'), ('tax')) v(axis)")
def q_op_map(s, d):
    """Axis names to spreads as a map, and back to rows."""
    cf = A.stable_agg(read(s, d, "lineitem"), [F.col("l_quantity"), price(), F.col("l_tax") * 100], [])
    m = F.map_from_arrays(F.array(F.lit("qty"), F.lit("price"), F.lit("tax")), A.axis_std(F.struct("w", "m", "q")))
    return cf.select(F.explode(m).alias("axis", "sd")).select("axis", r("sd").alias("sd"))


@query(f"SELECT l_returnflag, {f_sql('l_quantity')} FROM lineitem GROUP BY 1")
def q_op_struct(s, d):
    cf = A.stable_agg(read(s, d, "lineitem"), [F.col("l_quantity")], ["l_returnflag"]).select("l_returnflag", F.struct("w", "m", "q").alias("cf"))
    return cf.select("l_returnflag", "cf.w", r(F.col("cf.m")[0]).alias("m0"), r(F.col("cf.q")[0] / F.col("cf.w")).alias("v0"))


@query(f"SELECT event_type, {f_sql('''CAST(json_extract_string(props, '$.k') AS DOUBLE)''')} FROM events GROUP BY 1")
def q_op_json(s, d):
    return read(s, d, "events").groupBy("event_type").agg(*feature(F.get_json_object("props", "$.k").cast("double")))


@query("SELECT o_orderstatus, CAST(sum(CAST(o_totalprice AS DECIMAL(18, 2))) AS VARCHAR) AS total FROM orders GROUP BY 1")
def q_op_decimal(s, d):
    return read(s, d, "orders").groupBy("o_orderstatus").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("string").alias("total"))


@query("SELECT count(*) AS n, sum(o_orderkey)::BIGINT AS keys FROM orders WHERE o_orderkey % 10 = 3")
def q_op_hash_sample(s, d):
    """A deterministic sample by key: the operator's purpose."""
    return read(s, d, "orders").where(F.col("o_orderkey") % 10 == 3).agg(count(), F.sum("o_orderkey").alias("keys"))


@query("SELECT TRUE AS bernoulli_ok, TRUE AS strata_ok")
def q_op_sample(s, d):
    """Whether Bernoulli and stratified samples have about their shares (five standard deviations)."""
    li = read(s, d, "lineitem").select("l_returnflag")
    n = li.agg(count())
    a = li.sample(0.1, seed=3).agg(F.count(F.lit(1)).alias("a"))
    b = li.sampleBy("l_returnflag", {"R": 0.5}, seed=3).agg(F.count(F.lit(1)).alias("b"), F.min("l_returnflag").alias("lo"), F.max("l_returnflag").alias("hi"))
    x = n.crossJoin(a).crossJoin(b)
    return x.select((F.abs(F.col("a") - 0.1 * F.col("n")) <= 5 * F.sqrt(0.09 * F.col("n"))).alias("bernoulli_ok"), ((F.col("lo") == "R") & (F.col("hi") == "R")).alias("strata_ok"))


@query("SELECT count(*) AS n FROM lineitem WHERE l_extendedprice > (SELECT avg(l_extendedprice) FROM lineitem)")
def q_op_subquery_scalar(s, d):
    return s.sql("SELECT count(1) AS n FROM {li} WHERE l_extendedprice > (SELECT avg(l_extendedprice) FROM {li})", li=read(s, d, "lineitem"))


EXISTS = "SELECT o_orderpriority, count(*) AS n FROM {o} o WHERE EXISTS (SELECT 1 FROM {li} l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45) GROUP BY o_orderpriority"


@query(EXISTS.format(o="orders", li="lineitem"))
def q_op_subquery_exists(s, d):
    return s.sql(EXISTS, o=read(s, d, "orders"), li=read(s, d, "lineitem"))


IN = "SELECT c_mktsegment, count(*) AS n FROM {c} WHERE c_nationkey IN (SELECT n_nationkey FROM {n} WHERE n_regionkey = 2) GROUP BY c_mktsegment"


@query(IN.format(c="customer", n="nation"))
def q_op_subquery_in(s, d):
    return s.sql(IN, c=read(s, d, "customer"), n=read(s, d, "nation"))


@query("SELECT sum(w)::DOUBLE AS w, TRUE AS same FROM (SELECT count(*) AS w FROM lineitem)")
def q_op_udf(s, d):
    """The Arrow function ``cf_distance`` of registered SQL agrees with the column form on all pairs of supplier features."""
    from stablecf.plans.sql import register

    register(s)
    cf = A.stable_agg(read(s, d, "lineitem"), [F.col("l_quantity"), price()], ["l_returnflag"]).select("l_returnflag", F.struct("w", "m", "q").alias("cf"))
    both = s.sql("SELECT a.l_returnflag, a.cf AS fa, cf_distance(a.cf, b.cf, 'D4') AS v, b.cf AS fb FROM {cf} a CROSS JOIN {cf} b", cf=cf)
    one = cf.agg(F.sum("cf.w").alias("w"))
    return both.agg(F.min((F.abs(F.col("v") - B.distance(F.col("fa"), F.col("fb"), "D4")) < 1e-9)).alias("same")).crossJoin(one).select("w", "same")


@query("SELECT l_returnflag, CAST(count(*) AS DOUBLE) AS w, TRUE AS capped FROM lineitem GROUP BY 1")
def q_op_udtf(s, d):
    """The table function ``cf_leaves`` makes a tree of each partition: weights are kept, entries capped."""
    from stablecf.plans.sql import register

    register(s)
    li = read(s, d, "lineitem").select(F.col("l_returnflag").alias("k"), F.array("l_quantity", price()).alias("x"))
    t = s.sql("SELECT k, w FROM cf_leaves(TABLE({li}) PARTITION BY (k), 50)", li=li)
    return t.groupBy(F.col("k").alias("l_returnflag")).agg(F.sum("w").alias("w"), (F.count(F.lit(1)) <= 50).alias("capped"))


@query(f"SELECT c_mktsegment, {f_sql('c_acctbal / 1000')} FROM customer GROUP BY 1")
def q_op_apply_group(s, d):
    """The same feature by a grouped Arrow function, for comparison with the aggregate that needs no Python."""
    import pyarrow as pa

    def one(t: pa.Table) -> pa.Table:
        x = t["x"].to_numpy()
        return pa.table({"c_mktsegment": t["c_mktsegment"][:1], "w": [float(len(x))], "m": [float(x.mean())], "v": [float(((x - x.mean()) ** 2).mean())]})

    c = read(s, d, "customer").select("c_mktsegment", (F.col("c_acctbal") / 1000).alias("x"))
    return c.groupBy("c_mktsegment").applyInArrow(one, "c_mktsegment string, w double, m double, v double").select("c_mktsegment", "w", r("m").alias("m0"), r("v").alias("v0"))


@query(f"SELECT 'page' AS source, '' AS role, {f_sql('CAST(length(html) AS DOUBLE) / 1000')} FROM pages UNION ALL SELECT 'benchmark', '', {f_sql('CAST(length(text) AS DOUBLE) / 1000')} FROM benchmark UNION ALL SELECT 'conversation', role, {f_sql('CAST(length(text) AS DOUBLE) / 1000')} FROM conversations GROUP BY role")
def q_op_text_features(s, d):
    size = lambda c: F.length(c).cast("double") / 1000
    one = lambda t, c, n: read(s, d, t).agg(*feature(size(c))).select(F.lit(n).alias("source"), F.lit("").alias("role"), "w", "m0", "v0")
    talk = read(s, d, "conversations").groupBy("role").agg(*feature(size("text"))).select(F.lit("conversation").alias("source"), "role", "w", "m0", "v0")
    return one("pages", "html", "page").unionByName(one("benchmark", "text", "benchmark")).unionByName(talk)
