"""Registered queries of the engine and their SQL.  SQL is written from definitions (two passes, pair sums), not from the engine's forms."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.functions import features as A
from stablecf.functions import measures as B
from stablecf.operators import mixture as M
from stablecf.operators import downstream as D
from stablecf.operators.summarize import collect, collect_stable, compact_cells, project, summarize, summarize_by
from stablecf.operators.tree import TreeConfig
from stablecf.plans import relational
from stablecf.plans import workloads as W
from stablecf.sources import generators as G
from stablecf.streaming.windows import session_features, window_features


def read(spark: SparkSession, sf_dir: str, t: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{t}.parquet")


def _r(c, n: int = 4):
    return (F.round(c, n) + F.lit(0.0))


def _li(spark, d):
    return read(spark, d, "lineitem").select("l_returnflag", "l_linestatus", "l_orderkey", F.col("l_quantity").alias("x0"), (F.col("l_extendedprice") / 1000).alias("x1"))


def _axes(df: DataFrame, var_of: str = "q", n: int = 2) -> list:
    return [_r(F.col("m")[i]).alias(f"m{i}") for i in range(n)] + [_r(F.col(var_of)[i] / F.col("w")).alias(f"v{i}") for i in range(n)]




def xy() -> list:
    return [F.col("x0"), F.col("x1")]


def q_stable_group(spark, d):
    cf = A.stable_agg(_li(spark, d), xy(), ["l_returnflag", "l_linestatus"])
    return cf.select("l_returnflag", "l_linestatus", "w", *_axes(cf))


def q_classic_group(spark, d):
    cf = A.classic_agg(_li(spark, d), xy(), ["l_returnflag", "l_linestatus"])
    return cf.select("l_returnflag", "l_linestatus", "n", _r(F.col("ls")[0] / F.col("n")).alias("m0"), _r(F.col("ls")[1] / F.col("n")).alias("m1"), _r(A.classic_var(F.struct("n", "ls", "ss"))).alias("var"))


def q_stable_merge(spark, d):
    c = read(spark, d, "customer").select("c_nationkey", (F.col("c_acctbal") / 1000).alias("x0"))
    cf = A.stable_agg(c, [F.col("x0")], ["c_nationkey"])
    n = read(spark, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_regionkey").alias("region"))
    out = A.stable_merge_agg(cf.join(n, "c_nationkey"), ["region"], 1)
    return out.select("region", "w", *_axes(out, n=1))


def q_stable_fold(spark, d):
    c = read(spark, d, "customer").select("c_nationkey", (F.col("c_acctbal") / 1000).alias("x0"))
    cf = A.stable_agg(c, [F.col("x0")], ["c_nationkey"])
    n = read(spark, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_regionkey").alias("region"))
    f = cf.join(n, "c_nationkey").groupBy("region").agg(F.collect_list(F.struct("w", "m", "q")).alias("fs"))  # at most 25 features a region
    f = f.select("region", A.stable_fold(F.col("fs"), 1).alias("f")).select("region", "f.*")
    return f.select("region", "w", *_axes(f, n=1))


def q_stable_weighted(spark, d):
    li = read(spark, d, "lineitem").select("l_linestatus", "l_quantity", (F.col("l_extendedprice") / 1000).alias("x0"), "l_discount")
    cf = A.stable_weighted_agg(li, [F.col("x0"), F.col("l_discount") * 100], F.col("l_quantity"), ["l_linestatus"])
    return cf.select("l_linestatus", "w", *_axes(cf))


def q_cov_feature(spark, d):
    cf = A.stable_cov_agg(_li(spark, d), xy(), ["l_returnflag"])
    return cf.select("l_returnflag", "w", *[_r(F.col("qc")[i] / F.col("w")).alias(f"c{i}") for i in range(3)])


def q_convert_roundtrip(spark, d):
    cf = A.stable_agg(_li(spark, d), xy(), ["l_returnflag"])
    return cf.select("l_returnflag", _r(A.classic_var(A.to_classic(F.struct("w", "m", "q")))).alias("var"))


def q_cancel_minutes(spark, d):
    """Time stamps of a minute: the stable variance (seconds squared) where the textbook form cancels."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    e = read(spark, d, "events").select(F.floor(us / 60000000).cast("long").alias("minute"), us.cast("double").alias("x0"))
    cf = A.stable_agg(e, [F.col("x0")], ["minute"]).where("w > 1")
    return cf.select("minute", "w", _r(F.col("q")[0] / F.col("w") / 1e12, 3).alias("var"))


def q_cancel_flags(spark, d):
    """Buckets whose textbook variance is negative or zero though the truth is positive."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    e = read(spark, d, "events").select(F.floor(us / 60000000).cast("long").alias("minute"), us.cast("double").alias("x0"))
    cf = A.classic_agg(e, [F.col("x0")], ["minute"]).where("n > 1").select(A.classic_var(F.struct("n", "ls", "ss")).alias("v"))
    return cf.agg(F.count(F.lit(1)).alias("buckets"), F.sum((F.col("v") < 0).cast("long")).alias("negative"), F.sum((F.col("v") == 0).cast("long")).alias("zero"))


def _nations(spark, d):
    c = read(spark, d, "customer").select("c_nationkey", (F.col("c_acctbal") / 1000).alias("x0"), F.pmod("c_custkey", F.lit(7)).cast("double").alias("x1"))
    return c


def _pairs(spark, d, kind, form):
    c = _nations(spark, d)
    cf = A.classic_agg(c, xy(), ["c_nationkey"]) if form == "classic" else A.stable_agg(c, xy(), ["c_nationkey"])
    cols = ["n", "ls", "ss"] if form == "classic" else ["w", "m", "q"]
    f = cf.select("c_nationkey", F.struct(*cols).alias("f"))
    a, b = f.select(F.col("c_nationkey").alias("a"), F.col("f").alias("fa")), f.select(F.col("c_nationkey").alias("b"), F.col("f").alias("fb"))
    # 25 nations: the pairs of a bounded set of features
    return a.join(F.broadcast(b), F.col("a") < F.col("b")).select("a", "b", _r(B.distance(F.col("fa"), F.col("fb"), kind, form)).alias("value"))


def q_stable_scalar(spark, d):
    """One deviation for all axes: the sum of the vector form."""
    cf = A.stable_agg(_li(spark, d), xy(), ["l_returnflag"])
    return cf.select("l_returnflag", "w", _r(A.total(F.col("q")) / F.col("w")).alias("var"))


def q_variance_form(spark, d):
    """Features that store q / w; the merge of two status groups goes through q again."""
    cf = A.stable_agg(_li(spark, d), xy(), ["l_returnflag", "l_linestatus"])
    kept = cf.select("l_returnflag", "w", "m", F.transform("q", lambda q: q / F.col("w")).alias("v"))
    back = kept.select("l_returnflag", "w", "m", F.transform("v", lambda v: v * F.col("w")).alias("q"))
    out = A.stable_merge_agg(back, ["l_returnflag"], 2)
    return out.select("l_returnflag", "w", *_axes(out))


def q_feature_memory(spark, d):
    """Values a feature of each form holds, by the number of axes: of the vectors of ``embeddings`` and of their first axes alone."""
    n = F.col("d")
    sizes = read(spark, d, "embeddings").select(F.size("embedding").alias("n")).where("n > 0").distinct()
    return sizes.select(F.explode(F.sequence(F.lit(1).cast("long"), F.col("n").cast("long"))).alias("d")).distinct().select("d", (n + 2).alias("scalar"), (2 * n + 1).alias("vector"), (1 + n + (n * (n + 1) / 2).cast("long")).alias("covariance"))


def q_op_zscore(spark, d):
    """Standardised prices, as counts and means of half-unit bins; the statistics are one row."""
    li = _li(spark, d).select("x1")
    st = li.agg(F.avg("x1").alias("a"), F.sqrt(F.var_pop("x1")).alias("s"))
    z = li.join(F.broadcast(st)).select(((F.col("x1") - F.col("a")) / F.col("s")).alias("z"))
    return z.groupBy(F.floor(F.col("z") * 2).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("n"), _r(F.avg("z")).alias("mean_z"))


def q_op_topk_features(spark, d):
    """The three heaviest price cells of each return flag."""
    from pyspark.sql import Window

    c = _li(spark, d).groupBy("l_returnflag", F.floor(F.col("x1") / 10).cast("long").alias("cell")).agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("l_returnflag").orderBy(F.desc("n"), "cell")
    return c.withColumn("place", F.row_number().over(w).cast("long")).where("place <= 3")


def q_op_join_semi(spark, d):
    o, li = read(spark, d, "orders"), read(spark, d, "lineitem").where("l_returnflag = 'R'")
    return o.join(li, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


def q_op_join_anti(spark, d):
    o, li = read(spark, d, "orders"), read(spark, d, "lineitem").where("l_returnflag = 'R'")
    return o.join(li, F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


def q_nearest_feature(spark, d):
    """Each nation's nearest other nation, ties by the smaller key."""
    p = B.pairwise(A.stable_agg(_nations(spark, d), xy(), ["c_nationkey"]), "c_nationkey", "D4")
    both = p.unionByName(p.select(F.col("b").alias("a"), F.col("a").alias("b"), "value")).withColumn("value", F.round("value", 9))
    return both.groupBy("a").agg(F.min_by("b", F.struct("value", "b")).alias("nearest"), _r(F.min("value")).alias("value"))


def q_absorb_flags(spark, d):
    p = _pairs(spark, d, "R", "stable")
    return p.select("a", "b", (F.col("value") <= 3.75).alias("ok"))


def q_hier_first_merge(spark, d):
    """The pair of nations that agglomeration merges first."""
    p = B.pairwise(A.stable_agg(_nations(spark, d), xy(), ["c_nationkey"]), "c_nationkey", "D4")
    best = p.agg(F.min(F.struct(F.round("value", 9).alias("value"), "a", "b")).alias("x"))
    return best.select("x.a", "x.b", _r(F.col("x.value")).alias("value"))


def q_cells(spark, d):
    cf = compact_cells(_li(spark, d), xy(), [5.0, 10.0])
    return cf.select("cell0", "cell1", "w", *_axes(cf))


def _summary(spark, d, cap=500, form="stable"):
    return summarize(project(_li(spark, d), xy()), TreeConfig(leaf_cap=cap, form=form))


def q_tree_conservation(spark, d):
    cf = _summary(spark, d).select(F.lit(1).alias("k"), "w", "m", "q")
    out = A.stable_merge_agg(cf, ["k"], 2)
    return out.select("w", *_axes(out))


def q_tree_limits(spark, d):
    cf = _summary(spark, d)
    return cf.agg((F.count(F.lit(1)) <= 500).alias("cap_ok"), (F.max(F.when(F.col("w") > 1, A.total(F.col("q")) / F.col("w") - F.col("threshold") * F.col("threshold"))) <= 1e-6).alias("radius_ok"))


def q_summary_leaves(spark, d):
    return _summary(spark, d)


MODEL = [(0.5, (10.0, 20.0), (50.0, 200.0)), (0.3, (30.0, 40.0), (60.0, 300.0)), (0.2, (45.0, 70.0), (30.0, 150.0))]


def _logs(spread: bool, expected: bool = False):
    from math import log, pi

    out = []
    for w, mu, var in MODEL:
        e = F.lit(log(w))
        for i in range(2):
            v = F.lit(var[i]) + (F.col("q")[i] / F.col("w") if spread else F.lit(0.0))
            dev = (F.col("m")[i] - mu[i]) * (F.col("m")[i] - mu[i]) + (F.col("q")[i] / F.col("w") if expected else F.lit(0.0))
            e = e - F.lit(0.5) * (F.log(F.lit(2 * pi) * v) + dev / v)
        out.append(e)
    return out


def _estep(spark, d, kernel):
    cf = A.stable_agg(_li(spark, d).withColumn("g", F.pmod("l_orderkey", F.lit(20)).cast("long")), xy(), ["g"])
    logs = _logs(kernel == "overlap", kernel == "expected")
    cf = cf.select("g", "w", "m", "q", *[x.alias(f"l{i}") for i, x in enumerate(logs)])
    top = F.greatest("l0", "l1", "l2")
    den = sum((F.exp(F.col(f"l{i}") - top) for i in range(3)), F.lit(0.0))
    return cf.select("g", "w", "m", "q", *[(F.exp(F.col(f"l{i}") - top) / den).alias(f"r{i}") for i in range(3)])


def q_estep(kernel):
    def q(spark, d):
        return _estep(spark, d, kernel).select("g", *[_r(F.col(f"r{i}"), 6).alias(f"r{i}") for i in range(3)])

    q.__name__ = f"q_estep_{kernel}"
    return q


def q_mstep_diagonal(spark, d):
    e = _estep(spark, d, "overlap").select("w", "m", "q", F.posexplode(F.array("r0", "r1", "r2")).alias("comp", "r"))
    f = e.select("comp", (F.col("w") * F.col("r")).alias("w"), "m", F.transform("q", lambda v: v * F.col("r")).alias("q"))
    out = A.stable_merge_agg(f, ["comp"], 2)
    return out.select("comp", _r(F.col("w"), 2).alias("mass"), *_axes(out))


def q_loglik(spark, d):
    p = project(_li(spark, d), xy())
    logs = _logs(False)
    top = F.greatest(*logs)
    ll = top + F.log(sum((F.exp(x - top) for x in logs), F.lit(0.0)))
    return p.agg(F.count(F.lit(1)).alias("n"), _r(F.avg(ll)).alias("mean_ll"))


def q_assign_hard(spark, d):
    import numpy as np

    model = M.Mixture(np.array([x[0] for x in MODEL]), np.array([x[1] for x in MODEL]), np.array([x[2] for x in MODEL]))
    return M.assign(project(_li(spark, d), xy()), model).groupBy("comp").agg(F.count(F.lit(1)).alias("n"), _r(F.avg(F.col("m")[0])).alias("mean_qty"))


def q_compression(spark, d):
    cf = compact_cells(_li(spark, d), xy(), [5.0, 10.0])
    return cf.agg(F.sum("w").cast("long").alias("n"), F.count(F.lit(1)).alias("cells"), _r(F.sum("w") / F.count(F.lit(1))).alias("ratio"))


def q_rollup_features(spark, d):
    c = read(spark, d, "customer").join(read(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select("n_regionkey", "c_mktsegment", (F.col("c_acctbal") / 1000).alias("x0"))
    cf = c.rollup("n_regionkey", "c_mktsegment").agg(F.grouping_id().cast("long").alias("level"), F.count(F.lit(1)).cast("double").alias("w"), F.avg("x0").alias("a"), F.var_pop("x0").alias("v"))
    return cf.select("n_regionkey", "c_mktsegment", "level", "w", _r(F.col("a")).alias("m0"), _r(F.col("v")).alias("v0"))


def _rt(c, n: int = 4):
    """Rounding of means of cents, which are often exact ties: 1e-9 is added here and in the SQL."""
    return F.round(c + 1e-9, n) + F.lit(0.0)


def _axis(cf: DataFrame) -> list:
    return [_rt(F.col("m")[0]).alias("m0"), _rt(F.col("q")[0] / F.col("w")).alias("v0")]


def q_win_running_feature(spark, d):
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    e = read(spark, d, "events")
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("n"), _rt(F.avg("value").over(w)).alias("m0"), _rt(F.var_pop("value").over(w), 3).alias("v0"))


def q_stream_window(spark, d):
    cf = window_features(read(spark, d, "events"), [F.col("value")], "ts", "6 hours", keys=("event_type",))
    return cf.select(F.unix_micros("win.start").alias("start_us"), "event_type", "w", *_axis(cf))


def q_stream_sliding(spark, d):
    cf = window_features(read(spark, d, "events"), [F.col("value")], "ts", "12 hours", "6 hours")
    return cf.select(F.unix_micros("win.start").alias("start_us"), "w", *_axis(cf))


def q_op_join_interval(spark, d):
    li, o = read(spark, d, "lineitem"), read(spark, d, "orders")
    j = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).where((F.col("l_shipdate") >= F.col("o_orderdate")) & (F.col("l_shipdate") <= F.col("o_orderdate") + F.expr("interval 90 days")))
    return j.agg(F.count(F.lit(1)).alias("n"), _r(F.avg("l_quantity")).alias("mean_qty"))


def q_op_join_asof(spark, d):
    from pyspark.sql import Window

    e = read(spark, d, "events").where("event_type in ('error', 'view')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    x = e.withColumn("view_ts", F.last(F.when(F.col("event_type") == "view", F.col("ts")), True).over(w)).where("event_type = 'error'")
    return x.select("event_id", F.unix_micros(F.col("view_ts").cast("timestamp")).alias("view_us"))


def _fit(form, shape):
    def q(spark, d):
        rows = project(_li(spark, d), xy())
        kind, how = form.split("_")
        if kind == "points":
            model = M.fit_rows(rows, 5, shape, how)
        else:
            cf = collect(summarize(rows, TreeConfig(leaf_cap=500, form=how)))
            model = M.fit_features_classic(*cf, 5) if how == "classic" else M.fit_features(*cf, 5, shape)
        return M.loglik(rows, model)

    q.__name__ = f"q_fit_{form}_{shape}"
    return q


def scale(spark, d) -> float:
    """Size multiplier of generated data: the published sizes at sf0.1 and above, less in proportion below."""
    return min(1.0, read(spark, d, "lineitem").count() / 600_000)


def q_w1_shift(spark, d):
    return W.shift_sweep(spark, int(150_000 * scale(spark, d)))


def q_w1_lineitem(spark, d):
    return W.shift_lineitem(spark, read(spark, d, "lineitem"))


def q_w1_single(spark, d):
    return W.shift_sweep(spark, int(150_000 * scale(spark, d)), shifts=(0.0, 1e2, 1e3, 3e3, 1e4), cap=1000, precision="f32")


def q_w2_quality(spark, d):
    return W.quality(spark, read(spark, d, "lineitem"), W.lineitem_axes())


def _sizes(spark, d, make, name):
    """Three sizes with the 100 components that the data have, the largest with fewer too."""
    top = scale(spark, d)
    each = [W.quality(spark, make(spark, m * top), [F.col("x_0"), F.col("x_1")], ks=ks, name=f"{name}-{m}") for m, ks in ((0.01, (100,)), (0.1, (100,)), (1.0, (10, 20, 100)))]
    return reduce(DataFrame.unionByName, each)


def q_w2_grid(spark, d):
    return _sizes(spark, d, G.grid, "grid")


def q_w2_random(spark, d):
    return _sizes(spark, d, G.halton_blobs, "random")


def q_w3_build(spark, d):
    a = W.build_times(spark, read(spark, d, "lineitem"), W.lineitem_axes(), name="build-lineitem")
    return a.unionByName(W.build_times(spark, G.halton_blobs(spark, scale(spark, d)), [F.col("x_0"), F.col("x_1")], name="build-random"))


def _days(c: str):
    return F.unix_micros(F.col(c).cast("timestamp")) / 86400e6


def q_w5_real(spark, d):
    sources = {
        "orders": (read(spark, d, "orders"), [_days("o_orderdate"), F.col("o_totalprice") / 1000]),
        "shipped": (read(spark, d, "lineitem"), [_days("l_shipdate") * 24, F.col("l_extendedprice") / 1000]),
        "places": (G.geo_like(spark, int(600_000 * scale(spark, d))), [F.col("x_0"), F.col("x_1")]),
    }
    return W.real_like_sweep(spark, sources)


def q_w6_hulls(spark, d):
    return W.hull_map(spark, G.geo_like(spark, int(600_000 * scale(spark, d))), [F.col("x_0"), F.col("x_1")]).select("comp", "n", "weight", "mean", F.size("hull").alias("corners"))


def q_w7_measures(spark, d):
    return W.measure_grid(spark, read(spark, d, "lineitem"), W.lineitem_axes())


def q_w8_order(spark, d):
    return W.order_sensitivity(spark, read(spark, d, "lineitem"), W.lineitem_axes())


def q_w9_kernels(spark, d):
    a = W.kernels(spark, read(spark, d, "lineitem"), W.lineitem_axes())
    return a.unionByName(W.kernels(spark, G.halton_blobs(spark, scale(spark, d)), [F.col("x_0"), F.col("x_1")]))


def q_w10_storage(spark, d):
    return W.storage_ablation(spark, read(spark, d, "lineitem"), W.lineitem_axes())


def q_w11_wide(spark, d):
    return W.wide_vectors(spark, read(spark, d, "embeddings"))


def q_shapes(spark, d):
    return W.shapes(spark, read(spark, d, "lineitem"), W.lineitem_axes())


def q_routes(spark, d):
    return W.aggregation_routes(spark, read(spark, d, "lineitem"), W.lineitem_axes())


def q_tree_stats(spark, d):
    return W.tree_stats(spark, read(spark, d, "lineitem"), W.lineitem_axes())


def q_misrouting(spark, d):
    return W.misrouting(spark, read(spark, d, "orders"), [F.col("o_totalprice") / 1000])


def q_summary_by_group(spark, d):
    """Trees per return flag: weights and entries of each."""
    cf = summarize_by(_li(spark, d), ["l_returnflag"], xy(), TreeConfig(leaf_cap=100), salts=4)
    return cf.groupBy("l_returnflag").agg(F.sum("w").alias("w"), (F.count(F.lit(1)) <= 100).alias("capped"))


def q_kmeans_cost(spark, d):
    c, cost = M.kmeans(*collect(_summary(spark, d)), 4)
    plain, unweighted = M.kmeans(*collect(_summary(spark, d)), 4, weighted=False)
    return spark.createDataFrame([("weighted", 4, float(cost)), ("centres only", 4, float(unweighted))], "method string, k int, cost double")


def _nation_features(spark, d):
    return collect(A.stable_agg(_nations(spark, d), xy(), ["c_nationkey"]))


def q_hier(spark, d):
    out = []
    for kind in ("D0", "D1", "D2", "D3", "D4"):
        label, merges = M.agglomerate(*_nation_features(spark, d), 5, kind, history=True)
        out += [(kind, i, int(x), float(merges[-1][2])) for i, x in enumerate(label)]
    return spark.createDataFrame(out, "linkage string, feature int, cluster int, last_merge double")


def q_medoids(spark, d):
    ids, cost = D.kmedoids_search(*collect(_summary(spark, d)), 4)
    return spark.createDataFrame([(int(i), float(cost)) for i in ids], "entry int, cost double")


def q_density_clusters(spark, d):
    w, m, q = collect(_summary(spark, d))
    label = D.density_clusters(w, m, q, 4.0, float(w.sum()) / 200)
    return spark.createDataFrame([(int(c), float(w[label == c].sum())) for c in sorted(set(label.tolist()))], "cluster int, w double")


def q_expand(spark, d):
    """Rows of nearest entries and their clusters: every row once."""
    rows = project(_li(spark, d), xy())
    w, m, q = collect(_summary(spark, d, 100))
    return D.expand(rows, w, m, q, M.agglomerate(w, m, q, 5)).agg(F.sum("w").alias("w"), (F.count_distinct("cluster") <= 5).alias("clusters_ok"))


def q_init_pp(spark, d):
    """Seeds on rows and on entries (weighted or not), and the cost they start from."""
    rows = project(_li(spark, d), xy()).persist()
    w, m, q = collect(_summary(spark, d))
    out = []
    for name, c in (("rows", M.kmeanspp_rows(rows, 5, 1)), ("entries", M.kmeanspp(w, m, 5, 1)), ("entries, unweighted", M.kmeanspp(w, m, 5, 1, False))):
        out += [(name, i, x.tolist(), float((w * M._nearest(m, c)[1]).sum() + q.sum())) for i, x in enumerate(c)]
    return spark.createDataFrame(out, "method string, i int, centre array<double>, cost double")


def q_classic_merge(spark, d):
    """Classic features of flag and status groups merged over the status."""
    cf = A.classic_agg(_li(spark, d), xy(), ["l_returnflag", "l_linestatus"])
    f = cf.groupBy("l_returnflag").agg(F.array_sort(F.collect_list(F.struct("n", "ls", "ss"))).alias("fs"))  # one feature a status
    zero = F.struct(F.lit(0.0).alias("n"), F.array(F.lit(0.0), F.lit(0.0)).alias("ls"), F.lit(0.0).alias("ss"))
    f = f.select("l_returnflag", F.aggregate("fs", zero, A.classic_merge).alias("f")).withColumn("mean", A.classic_mean(F.col("f")))
    return f.select("l_returnflag", "f.n", _r(F.col("mean")[0]).alias("m0"), _r(F.col("mean")[1]).alias("m1"), _r(A.classic_var(F.col("f"), "zero")).alias("var"))


def q_classic_point(spark, d):
    """A region's key as a point, the next key added, and the first taken away again."""
    x = read(spark, d, "region").select("r_regionkey", F.array(F.col("r_regionkey").cast("double")).alias("x"))
    one = A.classic_point(F.col("x"))
    both = A.classic_add(one, F.transform("x", lambda v: v + 1))
    back = A.classic_subtract(both, one)
    return x.select("r_regionkey", both["n"].alias("n"), both["ls"][0].alias("ls"), both["ss"].alias("ss"), back["ls"][0].alias("left"))


def q_stable_point(spark, d):
    x = read(spark, d, "region").select("r_regionkey", F.array(F.col("r_regionkey").cast("double")).alias("x"))
    two = A.stable_merge(A.stable_point(F.col("x")), A.stable_point(F.transform("x", lambda v: v + 4), 3.0))
    old = A.stable_decay(two, 0.5)
    return x.select("r_regionkey", two["w"].alias("w"), two["m"][0].alias("m0"), two["q"][0].alias("q0"), old["w"].alias("old_w"), old["q"][0].alias("old_q"))


def q_cov_merge(spark, d):
    """Covariance features of flag and status groups merged over the status."""
    cf = A.stable_cov_agg(_li(spark, d), xy(), ["l_returnflag", "l_linestatus"])
    out = A.stable_cov_merge_agg(cf, ["l_returnflag"], 2)
    return out.select("l_returnflag", "w", *[_r(F.col("qc")[i] / F.col("w")).alias(f"c{i}") for i in range(3)])


def q_cov_fold(spark, d):
    """The same pair by pair, as a struct merge."""
    cf = A.stable_cov_agg(_li(spark, d), xy(), ["l_returnflag", "l_linestatus"])
    zero = F.struct(F.lit(0.0).alias("w"), F.array(*[F.lit(0.0)] * 2).alias("m"), F.array(*[F.lit(0.0)] * 3).alias("qc"))
    f = cf.groupBy("l_returnflag").agg(F.array_sort(F.collect_list(F.struct("w", "m", "qc"))).alias("fs"))  # one feature a status
    f = f.select("l_returnflag", F.aggregate("fs", zero, lambda a, b: A.stable_cov_merge(a, b, 2)).alias("f")).select("l_returnflag", "f.*")
    return f.select("l_returnflag", "w", *[_r(F.col("qc")[i] / F.col("w")).alias(f"c{i}") for i in range(3)])


def q_to_stable(spark, d):
    """Classic features with a square sum per axis, as stable ones."""
    li = _li(spark, d)
    cf = li.groupBy("l_returnflag").agg(F.count(F.lit(1)).cast("double").alias("n"), F.array(F.sum("x0"), F.sum("x1")).alias("ls"), F.array(F.sum(F.col("x0") * F.col("x0")), F.sum(F.col("x1") * F.col("x1"))).alias("ss"))
    out = cf.select("l_returnflag", A.to_stable(F.struct("n", "ls", "ss")).alias("f")).select("l_returnflag", "f.*")
    return out.select("l_returnflag", "w", *_axes(out), "lossy")


def q_derived_stats(spark, d):
    """What the paper says features are good for: spreads, extent, density, distance of a point in spreads."""
    cf = A.stable_agg(_li(spark, d), xy(), ["l_returnflag"]).select("l_returnflag", F.struct("w", "m", "q").alias("f"))
    f, sd = F.col("f"), A.axis_std(F.col("f"))
    at = F.array(F.lit(20.0), F.lit(40.0))
    return cf.select("l_returnflag", _r(sd[0]).alias("sd0"), _r(A.arrival_std(f, 1)).alias("sd1"), _r(A.extent(f)).alias("extent"), _r(A.diag_mahalanobis(at, f)).alias("mahalanobis"), _r(A.density(f, 2)).alias("density"))


def q_kde(spark, d):
    """Density of quantities from the features of return flags, at five points."""
    cf = A.stable_agg(_li(spark, d), xy(), ["l_returnflag"])
    grid = spark.createDataFrame([(float(x),) for x in (0, 10, 25, 40, 50)], "g double")
    return A.kde_from_features(cf, grid, 0, 2.0).select("g", _r(F.col("density"), 6).alias("density"))


def q_max_radius(spark, d):
    li = _li(spark, d).select("l_returnflag", F.array("x0", "x1").alias("m"))
    cf = A.stable_agg(_li(spark, d), xy(), ["l_returnflag"])
    return A.max_radius(li, cf, "l_returnflag").select("l_returnflag", _r(F.col("r_max")).alias("r_max"))


def q_single_at_rest(spark, d):
    """Features kept in single precision: means within its rounding, weights exact."""
    cf = A.stable_agg(_li(spark, d), xy(), ["l_returnflag"]).select("l_returnflag", F.struct("w", "m", "q").alias("f"))
    one = cf.select("l_returnflag", "f", A.to_single(F.col("f")).alias("s"))
    return one.select("l_returnflag", F.col("s.w").alias("w"), (F.abs(F.col("s.m")[0].cast("double") / F.col("f.m")[0] - 1) < 1e-6).alias("near"))


def q_shift_exact(spark, d):
    """Variances of integer quantities must not move with the shift."""
    li = read(spark, d, "lineitem").select((F.col("l_orderkey") % 2).alias("side"), F.col("l_quantity").alias("x"))
    moved = li.crossJoin(F.broadcast(spark.createDataFrame([(0,), (1000000,), (100000000,)], "s long"))).select("side", "s", (F.col("x") + F.col("s")).alias("x0"))
    cf = A.stable_agg(moved, [F.col("x0")], ["side", "s"])
    return cf.select("side", "s", _r(F.col("q")[0] / F.col("w"), 3).alias("var"))


def q_cells_multi(spark, d):
    """Cells of the summary's own form: any features in, deviations around the cell's centre."""
    from stablecf.operators.summarize import features_to_cells

    cf = features_to_cells(project(_li(spark, d), xy()), [5.0, 10.0])
    return cf.select(F.floor(F.col("m")[0] / 5.0).cast("long").alias("cell0"), F.floor(F.col("m")[1] / 10.0).cast("long").alias("cell1"), "w", *_axes(cf))


def q_nearest_region(spark, d):
    """The nearest region feature of each segment feature."""
    c = read(spark, d, "customer").join(F.broadcast(read(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).withColumn("x0", F.col("c_acctbal") / 1000)
    seg, reg = A.stable_agg(c, [F.col("x0")], ["c_mktsegment"]), A.stable_agg(c, [F.col("x0")], ["n_regionkey"])
    return B.nearest(seg, "c_mktsegment", reg, "n_regionkey", "D0").select("c_mktsegment", F.col("other").alias("n_regionkey"), _r(F.col("value")).alias("value"))


def _mstep(shape):
    def q(spark, d):
        e = _estep(spark, d, "overlap").select("w", "m", "q", F.posexplode(F.array("r0", "r1", "r2")).alias("comp", "r"))
        f = e.select("comp", (F.col("w") * F.col("r")).alias("w"), "m", F.transform("q", lambda v: v * F.col("r")).alias("q"))
        out = A.stable_merge_agg(f, ["comp"], 2)
        return out.select("comp", _r(F.col("w"), 2).alias("mass"), _r(A.total(F.col("q")) / F.col("w") / 2).alias("var"))

    q.__name__ = f"q_mstep_{shape}"
    return q


def q_mstep_full(spark, d):
    """Full covariances of one M-step, from covariance features."""
    src = _li(spark, d).withColumn("g", F.pmod("l_orderkey", F.lit(20)).cast("long"))
    cov = A.stable_cov_agg(src, xy(), ["g"]).select("g", "qc")
    e = _estep(spark, d, "overlap").join(cov, "g").select("w", "m", "qc", F.posexplode(F.array("r0", "r1", "r2")).alias("comp", "r"))
    f = e.select("comp", (F.col("w") * F.col("r")).alias("w"), "m", F.transform("qc", lambda v: v * F.col("r")).alias("qc"))
    out = A.stable_cov_merge_agg(f, ["comp"], 2)
    return out.select("comp", *[_r(F.col("qc")[i] / F.col("w"), 3).alias(f"c{i}") for i in range(3)])


def q_loglik_features(spark, d):
    cf = A.stable_agg(_li(spark, d).withColumn("g", F.pmod("l_orderkey", F.lit(20)).cast("long")), xy(), ["g"])
    logs = _logs(True)
    top = F.greatest(*logs)
    ll = top + F.log(sum((F.exp(x - top) for x in logs), F.lit(0.0)))
    return cf.agg(_r(F.sum(F.col("w") * ll) / F.sum("w")).alias("mean_ll"))


def _model() -> M.Mixture:
    import numpy as np

    return M.Mixture(np.array([x[0] for x in MODEL]), np.array([x[1] for x in MODEL]), np.array([x[2] for x in MODEL]))


def q_loglik_fitted(spark, d):
    """The likelihood that the fits report, under the literal model."""
    return M.loglik(project(_li(spark, d), xy()), _model()).select(F.col("rows").alias("n"), _r(F.col("mean_ll")).alias("mean_ll"))


def q_assign_soft(spark, d):
    soft = M.assign(project(_li(spark, d), xy()), _model(), "soft").select("w", F.posexplode("resp").alias("comp", "r"))
    return soft.groupBy("comp").agg(_r(F.sum(F.col("w") * F.col("r")), 2).alias("soft_mass"))


def _em(kind):
    def q(spark, d):
        rows = project(_li(spark, d), xy())
        if kind == "features_3":
            cf = collect(A.stable_agg(_li(spark, d).withColumn("g", F.pmod("l_orderkey", F.lit(20)).cast("long")), xy(), ["g"]))
            model = _model()
            for _ in range(3):
                r, _ = M.e_step(model, *cf)
                model = M.m_step(*cf, r, "diagonal", 0.0)
        else:
            mass, mean, dev, _ = M.row_step(rows, _model(), kind.split("_")[1])
            model = M.finish(mass, mean, dev, "diagonal", 0.0)
        out = spark.createDataFrame(model.rows(), M.MODEL_SCHEMA)
        return out.select("comp", _r(F.col("weight")).alias("weight"), *[_r(F.col("mean")[i], 3).alias(f"m{i}") for i in range(2)], *[_r(F.col("var")[i], 3).alias(f"v{i}") for i in range(2)])

    q.__name__ = f"q_em_{kind}"
    return q


def q_op_cte_chain(spark, d):
    """Three EM steps on features as chained common tables, planned as one query."""
    return spark.sql(_em_features_sql(3).replace("FROM lineitem", "FROM {lineitem}"), lineitem=read(spark, d, "lineitem"))


def q_kmeans_step(spark, d):
    """One weighted step on the cells with four literal centres."""
    cf = compact_cells(_li(spark, d), xy(), [5.0, 10.0])
    d2 = [(F.col("m")[0] - a) * (F.col("m")[0] - a) + (F.col("m")[1] - b) * (F.col("m")[1] - b) for a, b in CENTRES]
    at = F.array_position(F.array(*d2), F.least(*d2)) - 1
    w = F.col("w")
    return cf.groupBy(at.cast("int").alias("centre")).agg(F.sum("w").alias("w"), *[_r(F.sum(w * F.col("m")[i]) / F.sum("w")).alias(f"m{i}") for i in range(2)])


CENTRES = [(10.0, 15.0), (15.0, 30.0), (35.0, 40.0), (40.0, 70.0)]


def q_stream_session(spark, d):
    cf = session_features(read(spark, d, "events"), [F.col("value")], "ts", "6 hours", keys=("user_id",))
    return cf.select("user_id", F.unix_micros("win.start").alias("start_us"), "w", *_axis(cf))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = project(read(spark, sf_dir, "lineitem"), W.lineitem_axes())
    model = M.fit_features(*collect(summarize(rows, TreeConfig(leaf_cap=500))), 5, "diagonal")
    return M.assign(rows, model).groupBy("comp").agg(F.count(F.lit(1)).alias("n"))


_S = [q_stable_group, q_classic_group, q_stable_merge, q_stable_fold, q_stable_weighted, q_cov_feature, q_convert_roundtrip, q_cancel_minutes, q_nearest_feature, q_absorb_flags, q_hier_first_merge, q_cells, q_tree_conservation, q_tree_limits, q_estep("overlap"), q_estep("centre"), q_estep("expected"), q_mstep_diagonal, q_loglik, q_assign_hard, q_compression, q_rollup_features, q_win_running_feature, q_stream_window, q_stream_sliding, q_op_join_interval, q_op_join_asof, q_stable_scalar, q_variance_form, q_feature_memory, q_op_zscore, q_op_topk_features, q_op_join_semi, q_op_join_anti]
_S += [q_classic_merge, q_classic_point, q_stable_point, q_cov_merge, q_cov_fold, q_to_stable, q_derived_stats, q_kde, q_max_radius, q_single_at_rest, q_shift_exact, q_cells_multi, q_nearest_region, _mstep("spherical"), q_mstep_full, q_loglik_features, q_loglik_fitted, q_assign_soft, _em("points_stable"), _em("points_textbook"), _em("features_3"), q_kmeans_step, q_op_cte_chain, q_stream_session, q_summary_by_group, q_expand]
_ROWS = [q_cancel_flags, q_summary_leaves, q_tree_stats, q_misrouting, q_kmeans_cost, q_hier, q_medoids, q_density_clusters, q_init_pp, q_shapes, q_routes]
_WORKLOADS = [q_w1_shift, q_w1_lineitem, q_w1_single, q_w2_quality, q_w2_grid, q_w2_random, q_w3_build, q_w5_real, q_w6_hulls, q_w7_measures, q_w8_order, q_w9_kernels, q_w10_storage, q_w11_wide]
_ROWS += [*[_fit(f, s) for f, s in (("features_stable", "diagonal"), ("features_stable", "spherical"), ("features_classic", "spherical"), ("points_textbook", "spherical"), ("points_stable", "diagonal"), ("points_stable", "spherical"))]]


def _pair_query(kind: str, form: str):
    def q(spark, d):
        return _pairs(spark, d, kind, form)

    q.__name__ = f"q_{'classic_' if form == 'classic' else ''}{kind.lower()}"
    return q


_PAIRS = [_pair_query(k, f) for f in ("stable", "classic") for k in B.KINDS]


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in [*_S, *_PAIRS]} | relational.QUERIES | {f.__name__: f for f in _ROWS}


def workloads() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    """The experiments: the longest queries."""
    return {f.__name__: f for f in _WORKLOADS}


LI = "li AS (SELECT l_returnflag, l_linestatus, l_orderkey, l_quantity AS x0, l_extendedprice / 1000 AS x1 FROM lineitem)"
CU = "cu AS (SELECT c_nationkey AS k, c_acctbal / 1000 AS x0, CAST(c_custkey % 7 AS DOUBLE) AS x1 FROM customer)"


def _two_pass(source: str, keys: str, axes: int = 2, weight: str = "1.0", with_: str = LI) -> str:
    on = " AND ".join(f"s.{k} = t.{k}" for k in keys.split(", ")) if keys else "true"
    pre = f"{keys}, " if keys else ""
    spre = ", ".join(f"s.{k}" for k in keys.split(", ")) + ", " if keys else ""
    group = f"GROUP BY {keys}" if keys else ""
    sgroup = "GROUP BY " + ", ".join(f"s.{k}" for k in keys.split(", ")) if keys else ""
    means = ", ".join(f"sum({weight} * x{i}) / sum({weight}) AS a{i}" for i in range(axes))
    outs = ", ".join(f"round(max(a{i}), 4) + 0.0 AS m{i}" for i in range(axes)) + ", " + ", ".join(f"round(sum({weight} * (x{i} - a{i}) * (x{i} - a{i})) / sum({weight}), 4) + 0.0 AS v{i}" for i in range(axes))
    return f"WITH {with_}, t AS (SELECT {pre}{means} FROM {source} {group}) SELECT {spre}CAST(sum({weight}) AS DOUBLE) AS w, {outs} FROM {source} s JOIN t ON {on} {sgroup}"


def _pair_sql(kind: str, digits: int = 4) -> str:
    d2 = "((p.x0 - r.x0) * (p.x0 - r.x0) + (p.x1 - r.x1) * (p.x1 - r.x1))"
    head = f"WITH {CU}, g AS (SELECT k, avg(x0) AS a0, avg(x1) AS a1, count(*) AS n FROM cu GROUP BY k), pr AS (SELECT g.k AS a, h.k AS b, g.a0, g.a1, h.a0 AS b0, h.a1 AS b1, g.n, h.n AS nb FROM g JOIN g h ON g.k < h.k)"
    if kind in ("D0", "E"):
        return f"{head} SELECT a, b, round(sqrt((a0 - b0) ** 2 + (a1 - b1) ** 2), {digits}) + 0.0 AS value FROM pr"
    if kind == "D1":
        return f"{head} SELECT a, b, round(abs(a0 - b0) + abs(a1 - b1), {digits}) + 0.0 AS value FROM pr"
    if kind == "D2":
        return f"{head} SELECT p.k AS a, r.k AS b, round(sqrt(avg({d2})), {digits}) + 0.0 AS value FROM cu p JOIN cu r ON p.k < r.k GROUP BY 1, 2"
    union = f"{head}, u AS (SELECT pr.a, pr.b, cu.k, cu.x0, cu.x1 FROM pr JOIN cu ON cu.k = pr.a OR cu.k = pr.b), c AS (SELECT a, b, avg(x0) AS c0, avg(x1) AS c1 FROM u GROUP BY a, b), s AS (SELECT u.a, u.b, count(*) AS n, sum((x0 - c0) ** 2 + (x1 - c1) ** 2) AS q FROM u JOIN c ON u.a = c.a AND u.b = c.b GROUP BY u.a, u.b)"
    if kind == "R":
        return f"{union} SELECT a, b, round(sqrt(q / n), {digits}) + 0.0 AS value FROM s"
    if kind == "D3":
        return f"{union} SELECT a, b, round(sqrt(2 * q / (n - 1)), {digits}) + 0.0 AS value FROM s"
    own = ", o AS (SELECT cu.k, sum((x0 - a0) ** 2 + (x1 - a1) ** 2) AS q FROM cu JOIN g ON cu.k = g.k GROUP BY cu.k)"
    return f"{union}{own} SELECT s.a, s.b, round(sqrt(greatest(s.q - o.q - o2.q, 0)), {digits}) + 0.0 AS value FROM s JOIN o ON s.a = o.k JOIN o o2 ON s.b = o2.k"


def _estep_sql(kernel: str) -> str:
    vals = ", ".join(f"({i}, {w}, {mu[0]}, {mu[1]}, {v[0]}, {v[1]})" for i, (w, mu, v) in enumerate(MODEL))
    add = "+ f.v{i}" if kernel == "overlap" else ""
    dev = "+ f.v{i}" if kernel == "expected" else ""
    dens = " ".join(f"- 0.5 * (ln(2 * pi() * (c.s{i} {add.format(i=i)})) + ((f.a{i} - c.u{i}) ** 2 {dev.format(i=i)}) / (c.s{i} {add.format(i=i)}))" for i in (0, 1))
    return f"{LI}, f AS (SELECT CAST(l_orderkey % 20 AS BIGINT) AS g, CAST(count(*) AS DOUBLE) AS w, avg(x0) AS a0, avg(x1) AS a1, var_pop(x0) AS v0, var_pop(x1) AS v1 FROM li GROUP BY 1), c(comp, p, u0, u1, s0, s1) AS (VALUES {vals}), l AS (SELECT g, w, a0, a1, v0, v1, comp, ln(p) {dens} AS l FROM f, c), e AS (SELECT *, exp(l - max(l) OVER (PARTITION BY g)) AS e FROM l), r AS (SELECT *, e / sum(e) OVER (PARTITION BY g) AS r FROM e)"


def _em_features_sql(n: int) -> str:
    """``n`` iterations of EM on the features of 20 groups, unrolled as chained common tables."""
    vals = ", ".join(f"({i}, {w}, {mu[0]}, {mu[1]}, {v[0]}, {v[1]})" for i, (w, mu, v) in enumerate(MODEL))
    out = f"WITH {LI}, f AS (SELECT CAST(l_orderkey % 20 AS BIGINT) AS g, CAST(count(*) AS DOUBLE) AS w, avg(x0) AS a0, avg(x1) AS a1, var_pop(x0) AS v0, var_pop(x1) AS v1 FROM li GROUP BY 1), c0(comp, p, u0, u1, s0, s1) AS (VALUES {vals})"
    dens = " ".join(f"- 0.5 * (ln(2 * pi() * (c.s{i} + f.v{i})) + power(f.a{i} - c.u{i}, 2) / (c.s{i} + f.v{i}))" for i in (0, 1))
    for i in range(n):
        out += f", l{i} AS (SELECT f.*, comp, ln(p) {dens} AS l FROM f, c{i} c), e{i} AS (SELECT *, exp(l - max(l) OVER (PARTITION BY g)) AS e FROM l{i}), r{i} AS (SELECT *, w * e / sum(e) OVER (PARTITION BY g) AS s FROM e{i})"
        out += f", m{i} AS (SELECT comp, sum(s) AS mass, sum(s * a0) / sum(s) AS u0, sum(s * a1) / sum(s) AS u1 FROM r{i} GROUP BY comp)"
        out += f", c{i + 1} AS (SELECT r.comp, max(mass) / (SELECT sum(mass) FROM m{i}) AS p, max(u0) AS u0, max(u1) AS u1, sum(s * (v0 + power(a0 - u0, 2))) / max(mass) AS s0, sum(s * (v1 + power(a1 - u1, 2))) / max(mass) AS s1 FROM r{i} r JOIN m{i} m ON r.comp = m.comp GROUP BY r.comp)"
    return f"{out} SELECT CAST(comp AS INTEGER) AS comp, round(p, 4) + 0.0 AS weight, round(u0, 3) + 0.0 AS m0, round(u1, 3) + 0.0 AS m1, round(s0, 3) + 0.0 AS v0, round(s1, 3) + 0.0 AS v1 FROM c{n}"


def oracle_sql() -> dict[str, str]:
    nation = "c1 AS (SELECT n_regionkey AS region, c_acctbal / 1000 AS x0 FROM customer JOIN nation ON c_nationkey = n_nationkey)"
    li_disc = "lw AS (SELECT l_linestatus, l_quantity AS wt, l_extendedprice / 1000 AS x0, l_discount * 100 AS x1 FROM lineitem)"
    us = "epoch_us(ts)"
    dens = [f"ln({w}) - 0.5 * (ln(2 * pi() * {v[0]}) + (x0 - {mu[0]}) ** 2 / {v[0]}) - 0.5 * (ln(2 * pi() * {v[1]}) + (x1 - {mu[1]}) ** 2 / {v[1]})" for w, mu, v in MODEL]
    lls = f"ll AS (SELECT x0, {', '.join(f'{x} AS l{i}' for i, x in enumerate(dens))} FROM li)"
    out = {
        "q_stable_group": _two_pass("li", "l_returnflag, l_linestatus"),
        "q_classic_group": f"WITH {LI} SELECT l_returnflag, l_linestatus, CAST(count(*) AS DOUBLE) AS n, round(avg(x0), 4) + 0.0 AS m0, round(avg(x1), 4) + 0.0 AS m1, round(var_pop(x0) + var_pop(x1), 4) + 0.0 AS var FROM li GROUP BY 1, 2",
        "q_stable_merge": _two_pass("c1", "region", 1, with_=nation),
        "q_stable_fold": _two_pass("c1", "region", 1, with_=nation),
        "q_stable_weighted": _two_pass("lw", "l_linestatus", 2, "wt", li_disc),
        "q_cov_feature": f"WITH {LI} SELECT l_returnflag, CAST(count(*) AS DOUBLE) AS w, round(var_pop(x0), 4) + 0.0 AS c0, round(covar_pop(x0, x1), 4) + 0.0 AS c1, round(var_pop(x1), 4) + 0.0 AS c2 FROM li GROUP BY 1",
        "q_convert_roundtrip": f"WITH {LI} SELECT l_returnflag, round(var_pop(x0) + var_pop(x1), 4) + 0.0 AS var FROM li GROUP BY 1",
        "q_cancel_minutes": f"WITH e AS (SELECT {us} // 60000000 AS minute, CAST({us} AS HUGEINT) AS x FROM events) SELECT minute, CAST(count(*) AS DOUBLE) AS w, round(CAST(count(*) * sum((x - minute * 60000000) * (x - minute * 60000000)) - sum(x - minute * 60000000) * sum(x - minute * 60000000) AS DOUBLE) / count(*) / count(*) / 1e12, 3) + 0.0 AS var FROM e GROUP BY minute HAVING count(*) > 1",
        "q_nearest_feature": f"WITH p AS ({_pair_sql('D4', 9)}), t AS (SELECT a, b, value FROM p UNION ALL SELECT b, a, value FROM p), o AS (SELECT *, row_number() OVER (PARTITION BY a ORDER BY value, b) AS i FROM t) SELECT a, b AS nearest, round(value, 4) + 0.0 AS value FROM o WHERE i = 1",
        "q_absorb_flags": f"WITH p AS ({_pair_sql('R')}) SELECT a, b, value <= 3.75 AS ok FROM p",
        "q_hier_first_merge": f"WITH p AS ({_pair_sql('D4', 9)}) SELECT a, b, round(value, 4) + 0.0 AS value FROM p ORDER BY p.value, a, b LIMIT 1",
        "q_cells": f"WITH {LI} SELECT CAST(floor(x0 / 5) AS BIGINT) AS cell0, CAST(floor(x1 / 10) AS BIGINT) AS cell1, CAST(count(*) AS DOUBLE) AS w, round(avg(x0), 4) + 0.0 AS m0, round(avg(x1), 4) + 0.0 AS m1, round(var_pop(x0), 4) + 0.0 AS v0, round(var_pop(x1), 4) + 0.0 AS v1 FROM li GROUP BY 1, 2",
        "q_tree_conservation": _two_pass("li", ""),
        "q_tree_limits": "SELECT TRUE AS cap_ok, TRUE AS radius_ok",
        "q_mstep_diagonal": f"WITH {_estep_sql('overlap')}, m AS (SELECT comp, sum(w * r) AS mass, sum(w * r * a0) / sum(w * r) AS u0, sum(w * r * a1) / sum(w * r) AS u1 FROM r GROUP BY comp) SELECT r.comp, round(max(mass), 2) + 0.0 AS mass, round(max(m.u0), 4) + 0.0 AS m0, round(max(m.u1), 4) + 0.0 AS m1, round(sum(w * r * (v0 + (a0 - m.u0) ** 2)) / max(mass), 4) + 0.0 AS v0, round(sum(w * r * (v1 + (a1 - m.u1) ** 2)) / max(mass), 4) + 0.0 AS v1 FROM r JOIN m ON r.comp = m.comp GROUP BY r.comp",
        "q_loglik": f"WITH {LI}, {lls} SELECT count(*) AS n, round(avg(ln(exp(l0) + exp(l1) + exp(l2))), 4) + 0.0 AS mean_ll FROM ll",
        "q_assign_hard": f"WITH {LI}, {lls} SELECT CAST(CASE WHEN l0 >= l1 AND l0 >= l2 THEN 0 WHEN l1 >= l2 THEN 1 ELSE 2 END AS INTEGER) AS comp, count(*) AS n, round(avg(x0), 4) + 0.0 AS mean_qty FROM ll GROUP BY 1",
        "q_compression": f"WITH {LI}, c AS (SELECT floor(x0 / 5), floor(x1 / 10), count(*) AS w FROM li GROUP BY 1, 2) SELECT CAST(sum(w) AS BIGINT) AS n, count(*) AS cells, round(sum(w) / count(*), 4) + 0.0 AS ratio FROM c",
        "q_rollup_features": "SELECT n_regionkey, c_mktsegment, CAST(grouping(n_regionkey) * 2 + grouping(c_mktsegment) AS BIGINT) AS level, CAST(count(*) AS DOUBLE) AS w, round(avg(c_acctbal / 1000), 4) + 0.0 AS m0, round(var_pop(c_acctbal / 1000), 4) + 0.0 AS v0 FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)",
        "q_win_running_feature": "SELECT event_id, count(*) OVER w AS n, round(avg(value) OVER w + 1e-9, 4) + 0.0 AS m0, round(var_pop(value) OVER w + 1e-9, 3) + 0.0 AS v0 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)",
        "q_stream_window": f"SELECT {us} // 21600000000 * 21600000000 AS start_us, event_type, CAST(count(*) AS DOUBLE) AS w, round(avg(value) + 1e-9, 4) + 0.0 AS m0, round(var_pop(value) + 1e-9, 4) + 0.0 AS v0 FROM events GROUP BY 1, 2",
        "q_stream_sliding": f"WITH e AS (SELECT {us} // 21600000000 * 21600000000 - o * 21600000000 AS start_us, value FROM events, (VALUES (0), (1)) t(o)) SELECT start_us, CAST(count(*) AS DOUBLE) AS w, round(avg(value) + 1e-9, 4) + 0.0 AS m0, round(var_pop(value) + 1e-9, 4) + 0.0 AS v0 FROM e GROUP BY 1",
        "q_op_join_interval": "SELECT count(*) AS n, round(avg(l_quantity), 4) + 0.0 AS mean_qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 90 DAY",
        "q_op_join_asof": "SELECT e.event_id, epoch_us(v.ts) AS view_us FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT user_id, ts FROM events WHERE event_type = 'view') v ON e.user_id = v.user_id AND e.ts >= v.ts",
    }
    out |= {
        "q_stable_scalar": f"WITH {LI} SELECT l_returnflag, CAST(count(*) AS DOUBLE) AS w, round(var_pop(x0) + var_pop(x1), 4) + 0.0 AS var FROM li GROUP BY 1",
        "q_variance_form": _two_pass("li", "l_returnflag"),
        "q_feature_memory": "SELECT d, d + 2 AS scalar, 2 * d + 1 AS vector, 1 + d + d * (d + 1) // 2 AS covariance FROM (SELECT DISTINCT unnest(range(1, len(embedding) + 1)) AS d FROM embeddings) t",
        "q_op_zscore": f"WITH {LI}, s AS (SELECT avg(x1) AS a, stddev_pop(x1) AS s FROM li), z AS (SELECT (x1 - a) / s AS z FROM li, s) SELECT CAST(floor(z * 2) AS BIGINT) AS bin, count(*) AS n, round(avg(z), 4) + 0.0 AS mean_z FROM z GROUP BY 1",
        "q_op_topk_features": f"WITH {LI}, c AS (SELECT l_returnflag, CAST(floor(x1 / 10) AS BIGINT) AS cell, count(*) AS n FROM li GROUP BY 1, 2) SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY l_returnflag ORDER BY n DESC, cell) AS place FROM c) WHERE place <= 3",
        "q_op_join_semi": "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R') GROUP BY 1",
        "q_op_join_anti": "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R') GROUP BY 1",
    }
    li_var = f"{LI}, t AS (SELECT l_returnflag AS k, avg(x0) AS a0, avg(x1) AS a1, var_pop(x0) AS v0, var_pop(x1) AS v1, count(*) AS n FROM li GROUP BY 1)"
    vals = ", ".join(f"({i}, {a}, {b})" for i, (a, b) in enumerate(CENTRES))
    cells = f"{LI}, c AS (SELECT count(*) AS w, avg(x0) AS a, avg(x1) AS b FROM li GROUP BY floor(x0 / 5), floor(x1 / 10))"
    resp = "z AS (SELECT x0, x1, greatest(l0, l1, l2) AS t, l0, l1, l2 FROM ll), s AS (SELECT x0, x1, exp(l0 - t) AS e0, exp(l1 - t) AS e1, exp(l2 - t) AS e2 FROM z), y AS (SELECT x0, x1, unnest([0, 1, 2]) AS comp, unnest([e0, e1, e2]) / (e0 + e1 + e2) AS r FROM s)"
    lls2 = lls.replace("SELECT x0,", "SELECT x0, x1,")
    em_rows = f"WITH {LI}, {lls2}, {resp}, u AS (SELECT comp, sum(r) AS mass, sum(r * x0) / sum(r) AS u0, sum(r * x1) / sum(r) AS u1 FROM y GROUP BY 1) SELECT CAST(y.comp AS INTEGER) AS comp, round(max(mass) / (SELECT count(*) FROM li), 4) + 0.0 AS weight, round(max(u0), 3) + 0.0 AS m0, round(max(u1), 3) + 0.0 AS m1, round(sum(r * (x0 - u0) ** 2) / max(mass), 3) + 0.0 AS v0, round(sum(r * (x1 - u1) ** 2) / max(mass), 3) + 0.0 AS v1 FROM y JOIN u ON y.comp = u.comp GROUP BY y.comp"
    out |= {
        "q_classic_merge": f"WITH {LI} SELECT l_returnflag, CAST(count(*) AS DOUBLE) AS n, round(avg(x0), 4) + 0.0 AS m0, round(avg(x1), 4) + 0.0 AS m1, round(var_pop(x0) + var_pop(x1), 4) + 0.0 AS var FROM li GROUP BY 1",
        "q_classic_point": "SELECT r_regionkey, 2.0::DOUBLE AS n, CAST(2 * r_regionkey + 1 AS DOUBLE) AS ls, CAST(r_regionkey ** 2 + (r_regionkey + 1) ** 2 AS DOUBLE) AS ss, CAST(r_regionkey + 1 AS DOUBLE) AS \"left\" FROM region",
        "q_stable_point": "SELECT r_regionkey, 4.0::DOUBLE AS w, CAST(r_regionkey + 3 AS DOUBLE) AS m0, CAST(9 + 3 * 1 AS DOUBLE) AS q0, 2.0::DOUBLE AS old_w, 6.0::DOUBLE AS old_q FROM region",
        "q_to_stable": _two_pass("li", "l_returnflag").replace(" FROM li s JOIN", ", TRUE AS lossy FROM li s JOIN"),
        "q_derived_stats": f"WITH {li_var} SELECT k AS l_returnflag, round(sqrt(v0), 4) + 0.0 AS sd0, round(sqrt(v1), 4) + 0.0 AS sd1, round(sqrt(v0 + v1), 4) + 0.0 AS extent, round(sqrt((20 - a0) ** 2 / v0 + (40 - a1) ** 2 / v1), 4) + 0.0 AS mahalanobis, round(n / sqrt(v0 * v1), 4) + 0.0 AS density FROM t",
        "q_kde": f"WITH {li_var} SELECT g, round(sum(n * exp(-((g - a0) ** 2) / (2 * (v0 + 4))) / sqrt(2 * pi() * (v0 + 4))) / sum(n), 6) + 0.0 AS density FROM t, (VALUES (0.0::DOUBLE), (10.0::DOUBLE), (25.0::DOUBLE), (40.0::DOUBLE), (50.0::DOUBLE)) p(g) GROUP BY g",
        "q_max_radius": f"WITH {li_var} SELECT l_returnflag, round(sqrt(max((x0 - a0) ** 2 + (x1 - a1) ** 2)), 4) + 0.0 AS r_max FROM li JOIN t ON l_returnflag = k GROUP BY 1",
        "q_single_at_rest": "SELECT l_returnflag, CAST(count(*) AS DOUBLE) AS w, TRUE AS near FROM lineitem GROUP BY 1",
        "q_shift_exact": "WITH v AS (SELECT l_orderkey % 2 AS side, var_pop(CAST(l_quantity AS BIGINT)) AS var FROM lineitem GROUP BY 1) SELECT side, s, round(var, 3) + 0.0 AS var FROM v, (VALUES (0::BIGINT), (1000000::BIGINT), (100000000::BIGINT)) t(s)",
        "q_nearest_region": "WITH c AS (SELECT c_mktsegment, n_regionkey, c_acctbal / 1000 AS x FROM customer JOIN nation ON c_nationkey = n_nationkey), a AS (SELECT c_mktsegment, avg(x) AS a FROM c GROUP BY 1), b AS (SELECT n_regionkey, avg(x) AS b FROM c GROUP BY 1), p AS (SELECT *, row_number() OVER (PARTITION BY c_mktsegment ORDER BY abs(a - b), n_regionkey) AS i FROM a, b) SELECT c_mktsegment, n_regionkey, round(abs(a - b), 4) + 0.0 AS value FROM p WHERE i = 1",
        "q_mstep_spherical": f"WITH {_estep_sql('overlap')}, m AS (SELECT comp, sum(w * r) AS mass, sum(w * r * a0) / sum(w * r) AS u0, sum(w * r * a1) / sum(w * r) AS u1 FROM r GROUP BY comp) SELECT r.comp, round(max(mass), 2) + 0.0 AS mass, round(sum(w * r * (v0 + (a0 - m.u0) ** 2 + v1 + (a1 - m.u1) ** 2)) / max(mass) / 2, 4) + 0.0 AS var FROM r JOIN m ON r.comp = m.comp GROUP BY r.comp",
        "q_mstep_full": f"WITH {_estep_sql('overlap')}, k AS (SELECT CAST(l_orderkey % 20 AS BIGINT) AS g, covar_pop(x0, x1) AS cv FROM li GROUP BY 1), m AS (SELECT comp, sum(w * r) AS mass, sum(w * r * a0) / sum(w * r) AS u0, sum(w * r * a1) / sum(w * r) AS u1 FROM r GROUP BY comp) SELECT r.comp, round(sum(w * r * (v0 + (a0 - m.u0) ** 2)) / max(mass), 3) + 0.0 AS c0, round(sum(w * r * (cv + (a0 - m.u0) * (a1 - m.u1))) / max(mass), 3) + 0.0 AS c1, round(sum(w * r * (v1 + (a1 - m.u1) ** 2)) / max(mass), 3) + 0.0 AS c2 FROM r JOIN m ON r.comp = m.comp JOIN k ON k.g = r.g GROUP BY r.comp",
        "q_loglik_features": f"WITH {_estep_sql('overlap')}, x AS (SELECT g, max(w) AS w, max(l) + ln(sum(e)) AS ll FROM e GROUP BY g) SELECT round(sum(w * ll) / sum(w), 4) + 0.0 AS mean_ll FROM x",
        "q_loglik_fitted": f"WITH {LI}, {lls} SELECT CAST(count(*) AS DOUBLE) AS n, round(avg(ln(exp(l0) + exp(l1) + exp(l2))), 4) + 0.0 AS mean_ll FROM ll",
        "q_assign_soft": f"WITH {LI}, {lls2}, {resp} SELECT CAST(comp AS INTEGER) AS comp, round(sum(r), 2) + 0.0 AS soft_mass FROM y GROUP BY 1",
        "q_em_points_stable": em_rows,
        "q_em_points_textbook": em_rows,
        "q_em_features_3": _em_features_sql(3),
        "q_kmeans_step": f"WITH {cells}, p AS (SELECT w, a, b, i, row_number() OVER (PARTITION BY w, a, b ORDER BY (a - ca) ** 2 + (b - cb) ** 2, i) AS k FROM c, (VALUES {vals}) v(i, ca, cb)) SELECT CAST(i AS INTEGER) AS centre, CAST(sum(w) AS DOUBLE) AS w, round(sum(w * a) / sum(w), 4) + 0.0 AS m0, round(sum(w * b) / sum(w), 4) + 0.0 AS m1 FROM p WHERE k = 1 GROUP BY 1",
        "q_stream_session": f"WITH e AS (SELECT user_id, {us} AS t, value, event_id, {us} - lag({us}) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap FROM events), s AS (SELECT *, sum(CASE WHEN gap IS NULL OR gap >= 21600000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY t, event_id ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, min(t) AS start_us, CAST(count(*) AS DOUBLE) AS w, round(avg(value) + 1e-9, 4) + 0.0 AS m0, round(var_pop(value) + 1e-9, 4) + 0.0 AS v0 FROM s GROUP BY user_id, k",
        "q_summary_by_group": "SELECT l_returnflag, CAST(count(*) AS DOUBLE) AS w, TRUE AS capped FROM lineitem GROUP BY 1",
        "q_expand": "SELECT CAST(count(*) AS DOUBLE) AS w, TRUE AS clusters_ok FROM lineitem",
    }
    out["q_cov_merge"] = out["q_cov_fold"] = out["q_cov_feature"]
    out["q_cells_multi"], out["q_op_cte_chain"] = out["q_cells"], out["q_em_features_3"]
    out |= relational.SQL
    for k in ("overlap", "centre", "expected"):
        out[f"q_estep_{k}"] = f"WITH {_estep_sql(k)} SELECT g, " + ", ".join(f"round(sum(CASE WHEN comp = {i} THEN r END), 6) + 0.0 AS r{i}" for i in range(3)) + " FROM r GROUP BY g"
    for k in B.KINDS:
        out[f"q_{k.lower()}"] = out[f"q_classic_{k.lower()}"] = _pair_sql(k)
    return out
