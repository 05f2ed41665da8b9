"""The experiments on generators and on the given tables; each returns tidy rows (workload, method, param, metric, value)."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.operators import mixture as M
from stablecf.operators.summarize import _lists, collect, collect_stable, merge_equal, project, summarize, tree_statistics
from stablecf.operators.tree import TreeConfig
from stablecf.sources import generators as G
from stablecf.sources.session import ship

SCHEMA = "workload string, method string, param double, metric string, value double"
METHODS = (("points-stable", "diagonal"), ("points-stable", "spherical"), ("features-stable", "diagonal"), ("features-stable", "spherical"), ("features-classic", "spherical"))


def lineitem_axes() -> list:
    return [F.col("l_quantity"), F.col("l_extendedprice") / 1000, F.col("l_discount") * 100, F.col("l_tax") * 100]


def _rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(a, b, float(c), d, float(e)) for a, b, c, d, e in rows], SCHEMA)


def timed(fn: Callable) -> tuple:
    t = time.time()
    out = fn()
    return out, time.time() - t


def repeat(fn: Callable[[int], float], n: int = 10, seed: int = 0) -> tuple[float, float]:
    """Mean and standard deviation of a measure over ``n`` seeds."""
    values = [fn(seed + i) for i in range(n)]
    return float(np.mean(values)), float(np.std(values))


def shuffled(rows: DataFrame, seed: int) -> DataFrame:
    """The same rows in an order that the seed decides."""
    return rows.repartition(rows.sparkSession.sparkContext.defaultParallelism, F.xxhash64("m", F.lit(seed))).sortWithinPartitions(F.xxhash64("m", F.lit(seed + 1)))


def _fit(rows: DataFrame, summary, method: str, shape: str, k: int, iters: int, seed: int = 0) -> M.Mixture:
    kind, form = method.split("-")
    if kind == "points":
        return M.fit_rows(rows, k, shape, form, seed=seed, max_iter=iters)
    if form == "classic":
        return M.fit_features_classic(*summary, k, seed=seed, max_iter=iters)
    return M.fit_features(*summary, k, shape, seed=seed, max_iter=iters)


def shift_sweep(spark: SparkSession, n: int = 150_000, shifts=(0.0, 1e3, 1e5, 1e6, 5e6, 1e7, 2e7, 5e7, 1e8), cap: int = 5000, iters: int = 100, precision: str = "f64", seeds: int = 1) -> DataFrame:
    """Mean log-likelihood of four spherical methods, the error of their mean variance and the least variance they met, by shift."""
    truth = (16 / 9 + 1 + 9 / 16) / 3
    return _sweep(spark, lambda s, seed: project(G.gaussian_pair(spark, n, s, seed=7 + seed), [F.col(f"x_{i}") for i in range(3)]), lambda s: truth, shifts, cap, iters, precision, seeds, "shift")


def shift_lineitem(spark: SparkSession, source: DataFrame, shifts=(0.0, 1e3, 1e5, 1e6, 5e6, 1e7, 2e7, 5e7, 1e8), cap: int = 2000, iters: int = 100) -> DataFrame:
    """The same on a table: quantity, discount and tax of lineitem, moved by -s or +s by the parity of the order."""
    axes = [F.col("l_quantity"), F.col("l_discount") * 100, F.col("l_tax") * 100]
    side = F.when(F.col("l_orderkey") % 2 == 0, -1.0).otherwise(1.0)
    v = source.groupBy(F.col("l_orderkey") % 2).agg(F.count(F.lit(1)).alias("n"), *[F.var_pop(a).alias(f"v{i}") for i, a in enumerate(axes)]).collect()
    truth = sum(r["n"] * (r["v0"] + r["v1"] + r["v2"]) / 3 for r in v) / max(1, sum(r["n"] for r in v))
    # few values are different: equal rows, whose shifts are equal too, are one weighted row of every pass
    alike = source.groupBy(*[a.alias(f"x{i}") for i, a in enumerate(axes)], side.alias("side")).agg(F.count(F.lit(1)).alias("n"))
    alike = alike.coalesce(spark.sparkContext.defaultParallelism).persist()
    # without a shift the two sides lie on each other, so their variance is not what a mixture finds
    return _sweep(spark, lambda s, seed: project(alike, [F.col(f"x{i}") + F.col("side") * s for i in range(3)], F.col("n")), lambda s: truth if s >= 1e3 else float("nan"), shifts, cap, iters, "f64", 1, "shift-lineitem")


def _sweep(spark, rows_at, truth, shifts, cap, iters, precision, seeds, name) -> DataFrame:
    def at(s: float) -> list[tuple]:
        seen: dict[tuple[str, str], list[float]] = {}
        for seed in range(seeds):
            rows = rows_at(s, seed).persist()
            for method in ("points-textbook", "points-stable", "features-classic", "features-stable"):
                kind, form = method.split("-")
                cfg = TreeConfig(leaf_cap=cap, form=form, precision=precision)
                summary = None if kind == "points" else collect(summarize(rows, cfg, compact=precision == "f64"))
                model = _fit(rows, summary, method, "spherical", 2, iters, seed)
                seen.setdefault((method, "mean_ll"), []).append(M.mean_loglik(rows, model))
                # weighted by component, as one that cancelled may hold a few rows only
                var = float((model.weight[:, None] * model.var).sum() / model.var.shape[1])
                seen.setdefault((method, "variance_error"), []).append(abs(var - truth(s)) / truth(s))
                seen.setdefault((method, "least_variance"), []).append(model.least_var)
            rows.unpersist()
        return [(name, m, s, x, float(np.mean(v))) for (m, x), v in seen.items()]

    # no times are taken here, so shifts may share the cluster
    with ThreadPoolExecutor(4) as pool:
        return _rows(spark, [r for rs in pool.map(at, shifts) for r in rs])


def quality(spark: SparkSession, source: DataFrame, axes: list, ks=(2, 5, 10, 20), cap: int = 5000, iters: int = 100, name: str = "quality", rows_k: int | None = None, precision: str = "f64", methods=METHODS) -> DataFrame:
    """Log-likelihood and total time of five methods, build time, entries and compression, by k.  EM on rows is run for every k; beyond
    ``rows_k``, if given, where published figures of it end, its fits are marked ``beyond_published``.

    Equal rows are one weighted row of all methods, where that halves the rows.  Fits on rows share their passes, fits on summaries are
    tasks side by side, and all likelihoods are of one pass; a fit's time is its own part of that.
    """
    out = []
    read = project(source, axes)
    rows = merge_equal(read)
    rows.persist()
    n = rows.agg(F.sum("w")).first()[0] or 0
    summaries = {}
    for form in ("stable", "classic"):
        cfg = TreeConfig(leaf_cap=cap, form=form, precision=precision)
        summaries[form], took = timed(lambda cfg=cfg: collect(summarize(rows, cfg, compact=precision == "f64", regions=precision != "f64")))
        out += [(name, f"features-{form}", 0, "build_s", took), (name, f"features-{form}", 0, "entries", len(summaries[form][0])), (name, f"features-{form}", 0, "compression", n / max(1, len(summaries[form][0])))]
    build = {m: v for _, m, _, x, v in out if x == "build_s"}
    wanted = [(method, shape, k) for k in ks for method, shape in methods]
    fits, spread = {}, M.Spread(M.packed(rows))
    for method in sorted({m for m, *_ in wanted if m.startswith("points")}):
        each = [r for r in wanted if r[0] == method]
        fits |= dict(zip(each, M.fit_rows_many(rows, [(k, shape) for _, shape, k in each], method.split("-")[1], max_iter=iters, spread=spread), strict=True))
    each = [r for r in wanted if r[0] not in ("points-stable", "points-textbook")]
    jobs = [("classic", M.fit_features_classic, {"k": k, "max_iter": iters}) if method == "features-classic" else ("stable", M.fit_features, {"k": k, "shape": shape, "max_iter": iters}) for method, shape, k in each]
    fits |= dict(zip(each, M.fit_features_many(spark, summaries, jobs), strict=True))
    likely = dict(zip(wanted, M.mean_logliks(spread, [fits[r][0] for r in wanted]), strict=True))
    for method, shape, k in wanted:
        model, took = fits[method, shape, k]
        took += build.get(method, 0.0)
        label = f"{method}-{shape}"
        out += [(name, label, k, "mean_ll", likely[method, shape, k]), (name, label, k, "total_s", took), (name, label, k, "iterations", len(model.history)), (name, label, k, "converged", float(model.converged))]
        if method.startswith("points") and rows_k is not None and k > rows_k:
            out.append((name, label, k, "beyond_published", 1.0))
        if not method.startswith("points") and ("points-stable", shape, k) in fits:
            out.append((name, label, k, "speed_ratio", fits["points-stable", shape, k][1] / took))
    spread.batches.unpersist()
    rows.unpersist()
    return _rows(spark, out)


def build_times(spark: SparkSession, source: DataFrame, axes: list, caps=(250, 500, 1000, 5000), name: str = "build") -> DataFrame:
    """Time to build a summary and its entries, by leaf cap, of both forms."""
    out = []
    rows = project(source, axes).persist()
    rows.count()
    for cap in caps:
        for form in ("stable", "classic"):
            n, took = timed(lambda: summarize(rows, TreeConfig(leaf_cap=cap, form=form)).count())
            out += [(name, form, cap, "build_s", took), (name, form, cap, "entries", n)]
    rows.unpersist()
    return _rows(spark, out)


def tree_stats(spark: SparkSession, source: DataFrame, axes: list, cap: int = 500) -> DataFrame:
    """Of one tree per task: rows, entries, height, rebuilds, threshold, distance evaluations."""
    return tree_statistics(project(source, axes), TreeConfig(leaf_cap=cap))


def real_like_sweep(spark: SparkSession, sources: dict[str, tuple[DataFrame, list]], ks=(2, 5, 10, 20, 50, 100), cap: int = 15_000, rows_k: int = 50, iters: int = 100) -> DataFrame:
    """Single-precision features, full-data EM in double, by k; the latter also beyond ``rows_k``, the largest k published of it."""
    out = None
    for name, (source, axes) in sources.items():
        one = quality(spark, source, axes, ks, cap, iters, name, rows_k, "f32")
        out = one if out is None else out.unionByName(one)
    return out


def measure_grid(spark: SparkSession, source: DataFrame, axes: list, k: int = 5, cap: int = 300, iters: int = 100) -> DataFrame:
    """Every distance with every absorption test: likelihood, entries and threshold."""
    out = []
    rows = project(source, axes).persist()
    for dist in ("D0", "D1", "D2", "D3", "D4"):
        for test in ("R", "D3", "E", "D0", "D1", "D2", "D4"):
            cf = summarize(rows, TreeConfig(leaf_cap=cap, distance=dist, absorption=test)).persist()
            model = M.fit_features(*collect(cf), k, "diagonal", max_iter=iters)
            last = cf.agg(F.count(F.lit(1)).alias("n"), F.max("threshold").alias("t")).first()
            out += [("measures", f"{dist}/{test}", k, "mean_ll", M.mean_loglik(rows, model)), ("measures", f"{dist}/{test}", k, "entries", last["n"]), ("measures", f"{dist}/{test}", k, "threshold", last["t"])]
            cf.unpersist()
    rows.unpersist()
    return _rows(spark, out)


def order_sensitivity(spark: SparkSession, source: DataFrame, axes: list, k: int = 5, cap: int = 500, repeats: int = 10, iters: int = 100) -> DataFrame:
    """Mean and deviation of likelihood and entries over seeds and row orders, trees fed row by row."""
    rows = project(source, axes).persist()
    found: dict[str, list[float]] = {"mean_ll": [], "entries": []}
    for seed in range(repeats):
        cf = collect(summarize(shuffled(rows, seed), TreeConfig(leaf_cap=cap), compact=False))
        found["entries"].append(len(cf[0]))
        found["mean_ll"].append(M.mean_loglik(rows, M.fit_features(*cf, k, "diagonal", seed=seed, max_iter=iters)))
    rows.unpersist()
    return _rows(spark, [("order", "features-stable-diagonal", k, f"{x}_{n}", f(v)) for x, v in found.items() for n, f in (("mean", np.mean), ("sd", np.std))])


def kernels(spark: SparkSession, source: DataFrame, axes: list, k: int = 10, cap: int = 500, iters: int = 100) -> DataFrame:
    """Overlap, centre-only and expected kernels on one summary."""
    rows = project(source, axes).persist()
    cf = collect(summarize(rows, TreeConfig(leaf_cap=cap)))
    out = [("kernels", kernel, k, "mean_ll", M.mean_loglik(rows, M.fit_features(*cf, k, "diagonal", kernel, max_iter=iters))) for kernel in ("overlap", "centre", "expected")]
    rows.unpersist()
    return _rows(spark, out)


def storage_ablation(spark: SparkSession, source: DataFrame, axes: list, k: int = 10, cap: int = 500, iters: int = 100) -> DataFrame:
    """Deviations per axis or in all, kept as sums, as variances or in single precision: build time and likelihood."""
    out = []
    rows = project(source, axes).persist()
    rows.count()
    d = len(axes)
    for name, cfg, turn in (
        ("vector", TreeConfig(leaf_cap=cap), lambda w, q: q),
        ("scalar", TreeConfig(leaf_cap=cap, q="scalar"), lambda w, q: q),
        ("variance", TreeConfig(leaf_cap=cap), lambda w, q: (q / w[:, None]) * w[:, None]),
        ("single", TreeConfig(leaf_cap=cap), lambda w, q: q.astype(np.float32).astype(float)),
    ):
        (w, m, q), took = timed(lambda cfg=cfg: collect(summarize(rows, cfg)))
        m = m.astype(np.float32).astype(float) if name == "single" else m
        model = M.fit_features(w, m, turn(w, q), k, "spherical" if name == "scalar" else "diagonal", max_iter=iters)
        values = 2 + d if name == "scalar" else 1 + 2 * d
        out += [("storage", name, k, "build_s", took), ("storage", name, k, "mean_ll", M.mean_loglik(rows, model)), ("storage", name, k, "values", values)]
    rows.unpersist()
    return _rows(spark, out)


def wide_vectors(spark: SparkSession, embeddings: DataFrame, k: int = 10, cap: int = 500, floor: float = 1e-6, iters: int = 100) -> DataFrame:
    """Vectors of many axes: diagonal fits with a variance floor, on features and on rows."""
    rows = embeddings.where("embedding is not null").select(F.lit(1.0).alias("w"), F.transform("embedding", lambda v: v.cast("double")).alias("m"), F.transform("embedding", lambda v: F.lit(0.0)).alias("q")).persist()
    cf, took = timed(lambda: collect(summarize(rows, TreeConfig(leaf_cap=cap), compact=False)))
    a, fit_s = timed(lambda: M.fit_features(*cf, k, "diagonal", max_iter=iters, floor=floor))
    b, rows_s = timed(lambda: M.fit_rows(rows, k, "diagonal", max_iter=iters, floor=floor))
    out = [("wide", "features-stable-diagonal", k, x, v) for x, v in (("entries", len(cf[0])), ("mean_ll", M.mean_loglik(rows, a)), ("total_s", took + fit_s))]
    out += [("wide", "points-stable-diagonal", k, x, v) for x, v in (("mean_ll", M.mean_loglik(rows, b)), ("total_s", rows_s))]
    rows.unpersist()
    return _rows(spark, out)


def _hull(points: np.ndarray) -> np.ndarray:
    """Convex hull of plane points, counter-clockwise from the leftmost: a lower and an upper chain."""
    p = np.unique(points, axis=0)
    if len(p) < 3:
        return p

    def chain(ps) -> list:
        out: list = []
        for x in ps:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (x[1] - out[-2][1]) - (out[-1][1] - out[-2][1]) * (x[0] - out[-2][0]) <= 0:
                out.pop()
            out.append(x)
        return out

    return np.array(chain(p)[:-1] + chain(p[::-1])[:-1])


def hulls(assigned: DataFrame, min_share: float = 0.0) -> DataFrame:
    """(comp, n, hull) of rows with ``m`` (two axes) and ``comp``: hulls of tasks first, then the hull of these; clusters below ``min_share`` of the rows are left out."""
    ship(assigned.sparkSession)
    kind = pa.list_(pa.list_(pa.float64()))
    total = assigned.count()

    def partial(batches):
        held: dict[int, tuple[int, np.ndarray]] = {}
        for b in batches:
            x, c = _lists(b.column(1)) if b.num_rows else np.zeros((0, 2)), b.column(0).to_numpy()
            for j in np.unique(c).tolist():
                n, h = held.get(j, (0, np.zeros((0, 2))))
                mine = x[c == j]
                held[j] = (n + len(mine), _hull(np.concatenate([h, mine])))
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([v[0] for v in held.values()], pa.int64()), pa.array([v[1].tolist() for v in held.values()], kind)], ["comp", "n", "hull"])

    def whole(t: pa.Table) -> pa.Table:
        h = _hull(np.concatenate([np.array(x).reshape(-1, 2) for x in t["hull"].to_pylist()]))
        return pa.table({"comp": t["comp"][:1], "n": pa.array([sum(t["n"].to_pylist())], pa.int64()), "hull": pa.array([h.tolist()], kind)})

    schema = "comp int, n long, hull array<array<double>>"
    return assigned.select("comp", "m").mapInArrow(partial, schema).groupBy("comp").applyInArrow(whole, schema).where(F.col("n") >= min_share * total)


def hull_map(spark: SparkSession, source: DataFrame, axes: list, k: int = 100, cap: int = 15_000, min_share: float = 0.0005, iters: int = 100) -> DataFrame:
    """Centres and hulls of a diagonal fit's hard clusters, without those of a few wrong rows."""
    rows = project(source, axes).persist()
    model = M.fit_features(*collect(summarize(rows, TreeConfig(leaf_cap=cap))), k, "diagonal", max_iter=iters)
    centres = spark.createDataFrame(model.rows(), M.MODEL_SCHEMA)
    return hulls(M.assign(rows, model), min_share).join(centres.select("comp", "weight", "mean"), "comp").select("comp", "n", "weight", "mean", "hull")


def misrouting(spark: SparkSession, source: DataFrame, axes: list, shifts=(0.0, 1e6, 1e7, 1e8), cap: int = 200) -> DataFrame:
    """Share of rows whose nearest entry differs when distances are worked out of classic features instead of stable ones.

    The entries are one stable summary of the shifted rows, written in both forms; the classic ones carry the digits that their squares keep.
    """
    from stablecf.functions.measures import squared_classic_np, squared_np

    out = []
    for s in shifts:
        rows = project(source, [a + s for a in axes])
        w, m, q = collect(summarize(rows, TreeConfig(leaf_cap=cap)))
        ls, ss = m * w[:, None], q.sum(axis=1) + (m * m).sum(axis=1) * w
        ship(spark)

        def differ(batches, w=w, m=m, q=q, ls=ls, ss=ss):
            for b in batches:
                x = _lists(b.column(1)) if b.num_rows else np.zeros((0, m.shape[1]))
                none = np.zeros(m.shape[1])
                bad = [int(np.argmin(squared_np(1.0, r, none, w, m, q, "D2")) != np.argmin(squared_classic_np(1.0, r, r @ r, w, ls, ss, "D2"))) for r in x]
                yield pa.RecordBatch.from_arrays([pa.array([len(x)], pa.int64()), pa.array([sum(bad)], pa.int64())], ["n", "bad"])

        r = rows.select("w", "m").mapInArrow(differ, "n long, bad long").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).first()
        out.append(("misrouting", "classic-D2", s, "share", (r["bad"] or 0) / max(1, r["n"] or 0)))
    return _rows(spark, out)


def aggregation_routes(spark: SparkSession, source: DataFrame, axes: list, k: int = 5, cap: int = 500, iters: int = 100) -> DataFrame:
    """One summary for all, fits by partition whose components are features again, and EM on features with a job an iteration."""
    rows = project(source, axes).persist()
    out = []
    cf = summarize(rows, TreeConfig(leaf_cap=cap)).persist()
    parts = collect(M.fit_by_partition(rows, 4 * k, TreeConfig(leaf_cap=cap)))
    for name, model in (
        ("summary", M.fit_features(*collect(cf), k, max_iter=iters)),
        ("by-partition", M.fit_features(*parts, k, max_iter=iters)),
        ("distributed", M.fit_rows(cf, k, "diagonal", "overlap", max_iter=iters)),
    ):
        out.append(("routes", name, k, "mean_ll", M.mean_loglik(rows, model)))
    rows.unpersist()
    return _rows(spark, out)


def shapes(spark: SparkSession, source: DataFrame, axes: list, k: int = 5, cap: int = 500, iters: int = 100) -> DataFrame:
    """Spherical, diagonal and full covariances, tied and with a prior, on one summary."""
    rows = project(source, axes).persist()
    cf = collect_stable(summarize(rows, TreeConfig(leaf_cap=cap)))
    runs = {s: {"shape": s} for s in ("spherical", "diagonal", "full")} | {"diagonal-tied": {"shape": "diagonal", "tied": True}, "diagonal-prior": {"shape": "diagonal", "prior": (10.0, 1.0)}, "full-prior": {"shape": "full", "prior": (10.0, 1.0)}}
    out = [("shapes", name, k, "mean_ll", M.mean_loglik(rows, M.fit_features(*cf, k, max_iter=iters, **o))) for name, o in runs.items()]
    rows.unpersist()
    return _rows(spark, out)
