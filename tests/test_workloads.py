import inspect

from stablecf import registry
from stablecf.operators import mixture
from stablecf.plans import workloads

KINDS = {k: inspect.signature(getattr(workloads, k)) for k in ("quality", "shift_sweep")}


def calls(monkeypatch, spark, name, target="quality", sf="sf0.1"):
    """The full arguments with which a registered query calls a workload, which is not run."""
    seen, kind = [], KINDS[target]

    def stub(*args, **more):
        got = kind.bind(*args, **more)
        got.apply_defaults()
        seen.append(got.arguments)
        return spark.createDataFrame([], workloads.SCHEMA)

    monkeypatch.setattr(workloads, target, stub)
    registry.workloads()[name](spark, f"/root/testdata/{sf}")
    return seen


def test_workloads_are_registered_whole(spark, monkeypatch):
    a = calls(monkeypatch, spark, "q_w1_shift", "shift_sweep")[0]
    assert a["n"] == 150_000 and len(a["shifts"]) == 9 and a["cap"] == 5000 and a["iters"] == 100
    a = calls(monkeypatch, spark, "q_w2_quality")[0]
    assert max(a["ks"]) == 20 and a["cap"] == 5000 and a["iters"] == 100
    each = calls(monkeypatch, spark, "q_w2_grid")
    assert each[-1]["source"].count() == 1_000_000 and all(a["iters"] == 100 and max(a["ks"]) == 100 for a in each)
    assert calls(monkeypatch, spark, "q_w1_shift", "shift_sweep", "sf0.01")[0]["n"] == 15_000  # generated data follow the scale of the tables
    for a in calls(monkeypatch, spark, "q_w5_real"):
        assert max(a["ks"]) == 100 and a["cap"] == 15_000 and a["iters"] == 100 and a["rows_k"] == 50


def test_rows_and_features_may_run_equally_long(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(mixture, "fit_rows", lambda *args, max_iter=100, **more: seen.append(max_iter))
    monkeypatch.setattr(mixture, "loglik", lambda rows, model: rows)
    registry.queries()["q_fit_points_stable_diagonal"](spark, "/root/testdata/sf0.001")
    assert seen == [inspect.signature(mixture.fit_features).parameters["max_iter"].default]


def test_random_set_single_precision_and_speed_ratio(spark, monkeypatch):
    from pyspark.sql import functions as F

    from stablecf.sources import generators

    axes, few = [F.col("x_0"), F.col("x_1")], generators.halton_blobs(spark, 0.001)
    r = {(x.method, x.metric): x.value for x in workloads.quality(spark, few, axes, ks=(2,), cap=50, iters=2, precision="f32").collect()}
    for shape in ("diagonal", "spherical"):
        assert r[f"features-stable-{shape}", "speed_ratio"] == r[f"points-stable-{shape}", "total_s"] / r[f"features-stable-{shape}", "total_s"]
    assert len(calls(monkeypatch, spark, "q_w2_random")) == 3
    assert calls(monkeypatch, spark, "q_w5_real")[0]["precision"] == "f32"


def test_code_is_shipped_once_by_several_threads(spark, monkeypatch):
    import time
    from concurrent.futures import ThreadPoolExecutor
    from types import SimpleNamespace

    from stablecf.sources import session

    sent = []
    fake = SimpleNamespace(sparkContext=SimpleNamespace(applicationId="an application of its own", addPyFile=lambda path: (time.sleep(0.2), sent.append(path))))
    with ThreadPoolExecutor(4) as pool:
        list(pool.map(lambda _: session.ship(fake), range(4)))
    session._shipped.pop("an application of its own")
    assert len(sent) == 1


def test_equal_rows_are_one_weighted_row(spark, monkeypatch):
    import numpy as np
    from pyspark.sql import functions as F

    from stablecf.operators.summarize import merge_equal, project

    x = spark.range(4000).select((F.col("id") % 37 + F.when(F.col("id") % 2 == 0, 0.0).otherwise(200.0)).alias("a"), (F.col("id") % 5).alias("b"))
    rows = project(x, [F.col("a"), F.col("b")])
    few = merge_equal(rows)
    assert few.count() == x.distinct().count() and few.agg(F.sum("w")).first()[0] == 4000
    for variance in ("stable", "textbook"):
        a, b = (mixture.fit_rows(r, 2, "diagonal", variance, max_iter=10) for r in (rows, few))
        i, j = np.argsort(a.mean[:, 0]), np.argsort(b.mean[:, 0])
        assert np.allclose(a.mean[i], b.mean[j]) and np.allclose(a.var[i], b.var[j]) and np.allclose(a.weight[i], b.weight[j])
        assert np.isclose(mixture.mean_loglik(rows, a), mixture.mean_loglik(few, b))
    every = project(spark.range(100), [F.col("id")])
    assert merge_equal(every) is every
    r = {(y.method, y.metric): y.value for y in workloads.quality(spark, x, [F.col("a"), F.col("b")], ks=(2,), cap=50, iters=2).collect()}
    assert r["features-stable", "compression"] * r["features-stable", "entries"] == 4000


def test_lineitem_sweep_passes_weighted_values(spark, monkeypatch):
    """Each pass sees the different values only, weighted by all rows."""
    seen = []

    def stub(spark_, rows_at, *more):
        seen.append(rows_at(1e3, 0))
        return spark_.createDataFrame([], workloads.SCHEMA)

    monkeypatch.setattr(workloads, "_sweep", stub)
    li = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet")
    workloads.shift_lineitem(spark, li.unionByName(li))
    from pyspark.sql import functions as F

    assert seen[0].agg(F.sum("w")).first()[0] == 2 * li.count()
    assert seen[0].count() == li.select("l_quantity", "l_discount", "l_tax", F.col("l_orderkey") % 2).distinct().count()


def test_regional_trees_hold_all_rows_in_single_precision(spark):
    import numpy as np
    from pyspark.sql import functions as F

    from stablecf.operators.summarize import collect, collect_stable, project, summarize
    from stablecf.operators.tree import TreeConfig

    x = project(spark.range(6000).select((F.col("id") % 83).alias("a"), (F.col("id") * 7 % 61).alias("b")), [F.col("a"), F.col("b")])
    want = collect(x)[1]
    for form in ("stable", "classic"):
        out = summarize(x, TreeConfig(leaf_cap=1024, form=form, precision="f32"), regions=True)
        w, m, _ = collect_stable(out, form)
        assert out.rdd.getNumPartitions() > 1 and len(w) <= 1024 and w.sum() == 6000  # each region's tree is a result; none waits for a merge
        assert np.allclose((w[:, None] * m).sum(axis=0) / 6000, want.mean(axis=0), rtol=1e-4)


def test_where_empty_components_start_is_asked_only_then():
    """A step's second density pass is for empty components alone."""
    import numpy as np

    def never():
        raise AssertionError("asked without an empty component")

    one = mixture.Mixture(np.ones(1), np.zeros((1, 2)), np.ones((1, 2)))
    assert mixture._iterate(lambda now: (0.0, one, never), one, 3, 0.0).history == [0.0, 0.0]
    x, q = np.array([[0.0, 1.0], [5.0, -2.0], [1e8, 3.0]]), np.array([[0.5, 0.0], [0.1, 0.2], [1.0, 1.0]])
    m = mixture.Mixture(np.array([0.25, 0.75]), np.array([[0.0, 0.0], [1e8, 1.0]]), np.array([[1.0, 2.0], [0.5, 3.0]]))
    for spread in (None, q):
        v = m.var[None] + (0.0 if spread is None else spread[:, None, :])
        want = np.log(m.weight) - 0.5 * (np.log(2 * np.pi * v) + (x[:, None, :] - m.mean[None]) ** 2 / v).sum(axis=2)
        assert np.allclose(m.log_joint(x, spread), want, rtol=1e-12)


def test_passes_leave_out_only_what_is_nothing(spark, monkeypatch):
    """Components are worked out near their rows alone, and each sum is that of all rows and components."""
    import numpy as np
    from pyspark.sql import functions as F

    from stablecf.operators.summarize import collect, project
    from stablecf.sources import generators

    rows = project(generators.grid(spark, 0.02), [F.col("x_0"), F.col("x_1")])
    x = collect(rows)[1]
    centres = np.array([(5.0 * i, 5.0 * j) for i in range(10) for j in range(10)])
    near = mixture.Mixture(np.full(100, 0.01), centres + 0.3, np.ones((100, 2)))
    # the last one is nothing everywhere, though its own sums come from all rows
    rare = mixture.Mixture(np.append(np.full(100, 0.01), 1e-60), np.append(centres, [[20.0, 21.0]], axis=0), np.append(np.ones((100, 2)), [[900.0, 400.0]], axis=0))
    seen, whole = [], mixture.Mixture.log_joint
    monkeypatch.setattr(mixture.Mixture, "log_joint", lambda self, x, spread=None: (seen.append(len(x) * len(self.weight)), whole(self, x, spread))[1])
    spread = mixture.Spread(mixture.packed(rows))
    local = spread.local()
    for model in (near, rare):
        logs = np.log(model.weight) - 0.5 * (np.log(2 * np.pi * model.var) + (x[:, None] - model.mean) ** 2 / model.var).sum(axis=2)
        top = logs.max(axis=1, keepdims=True)
        r = np.exp(logs - top)
        ll = float((top[:, 0] + np.log(r.sum(axis=1))).sum())
        r /= r.sum(axis=1, keepdims=True)
        mean = r.T @ x / r.sum(axis=0)[:, None]
        dev = np.stack([(r * (x[:, i : i + 1] - mean[:, i]) ** 2).sum(axis=0) for i in range(2)], axis=1)
        for kept in (local, spread, rows):
            reach = [mixture.REACH]
            got = mixture.row_step(kept, model, "stable", reach=reach)
            assert all(np.allclose(a, b, rtol=1e-9, atol=0) for a, b in zip(got, (r.sum(axis=0), mean, dev, ll), strict=True))
            assert (reach[0] > mixture.REACH) == (model is rare)
            if kept is local and model is near:
                assert 0 < sum(seen) < 0.5 * len(x) * len(model.weight)


def test_rows_in_compact_order_are_all_there_with_their_nearest_centre():
    import numpy as np

    rng = np.random.default_rng(1)
    for n in (1, 512, 513, 5000):
        x = np.floor(rng.uniform(0, 60, (n, 2)))  # whole numbers, so that there are equal rows and ties
        order = mixture._compact_order(x)
        assert np.array_equal(np.sort(order), np.arange(n))
        x, c = x[order], np.floor(rng.uniform(0, 60, (200, 2)))
        d = ((x[:, None] - c) ** 2).sum(axis=2)
        at, best = mixture._nearest(x, c)
        assert np.array_equal(at, d.argmin(axis=1)) and np.array_equal(best, d.min(axis=1))
    lo, hi = mixture._boxes(x)
    assert (hi - lo).prod(axis=1).sum() < 1.5 * 60 * 60  # blocks hardly overlap


def test_fits_on_the_driver_and_by_jobs_agree(spark, monkeypatch):
    import numpy as np
    from pyspark.sql import functions as F

    from stablecf.operators.summarize import project
    from stablecf.sources import generators

    rows = project(generators.grid(spark, 0.01), [F.col("x_0"), F.col("x_1")])
    a = mixture.fit_rows(rows, 30, max_iter=8)
    monkeypatch.setattr(mixture, "ON_DRIVER", 0)
    b = mixture.fit_rows(rows, 30, max_iter=8)
    assert np.allclose(a.history, b.history) and np.allclose(a.mean, b.mean) and np.allclose(a.var, b.var)


def test_fits_that_share_passes_are_those_of_each_alone(spark, monkeypatch):
    """Every pass makes a step of all fits, so that several read the rows as often as the longest does."""
    import numpy as np
    from pyspark.sql import functions as F

    from stablecf.operators.summarize import project
    from stablecf.sources import generators

    rows = project(generators.grid(spark, 0.02), [F.col("x_0"), F.col("x_1")])
    runs, passes, scan = [(3, "diagonal"), (3, "spherical"), (12, "diagonal")], [], mixture.Spread.scan
    monkeypatch.setattr(mixture, "ON_DRIVER", 0)
    monkeypatch.setattr(mixture.Spread, "scan", lambda self, run, schema: (passes.append(schema), scan(self, run, schema))[1])
    many = mixture.fit_rows_many(rows, runs, max_iter=6)
    together = len(passes)
    passes.clear()
    for (k, shape), (model, took) in zip(runs, many, strict=True):
        one = mixture.fit_rows(rows, k, shape, max_iter=6)
        assert np.allclose(one.history, model.history) and np.allclose(one.mean, model.mean) and np.allclose(one.var, model.var) and took > 0
    assert 2 * together < len(passes)
    spread = mixture.Spread(mixture.packed(rows))
    assert np.allclose(mixture.mean_logliks(spread, [m for m, _ in many]), [mixture.mean_loglik(rows, m) for m, _ in many], rtol=1e-12)


def test_narrow_components_far_away_keep_their_digits():
    import numpy as np

    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(1e8, 1.0, (600, 2)), rng.normal(-1e8, 1e-3, (600, 2)), rng.uniform(-40, 40, (900, 2))])
    m = mixture.Mixture(np.array([0.3, 0.3, 0.4]), np.array([[1e8, 1e8], [-1e8, -1e8], [0.0, 1.0]]), np.array([[1.0, 1.0], [1e-6, 1e-6], [500.0, 400.0]]))
    want = np.log(m.weight) - 0.5 * (np.log(2 * np.pi * m.var) + (x[:, None] - m.mean) ** 2 / m.var).sum(axis=2)
    assert np.allclose(m.log_joint(x), want, rtol=1e-12)
    x = x[mixture._compact_order(x)]
    mass, mean, dev, _, _ = mixture._block_sums(m, np.ones(len(x)), x, mixture.REACH)
    for c, own in enumerate((x[x[:, 0] > 1e7], x[x[:, 0] < -1e7], x[abs(x[:, 0]) < 1e7])):
        assert np.isclose(mass[c], len(own)) and np.allclose(mean[c], own.mean(axis=0), rtol=1e-14)
        assert np.allclose(dev[c], ((own - own.mean(axis=0)) ** 2).sum(axis=0), rtol=1e-6)


def test_fits_on_summaries_are_tasks_side_by_side(spark):
    import numpy as np

    rng = np.random.default_rng(5)
    w, m, q = rng.uniform(1, 9, 80), rng.normal(size=(80, 2)), rng.uniform(0, 1, (80, 2))
    runs = [("a", mixture.fit_features, {"k": k, "shape": shape, "max_iter": 9}) for k, shape in ((2, "diagonal"), (5, "spherical"), (3, "diagonal"))]
    for (_, fit, more), (model, took) in zip(runs, mixture.fit_features_many(spark, {"a": (w, m, q)}, runs), strict=True):
        assert np.allclose(fit(w, m, q, **more).mean, model.mean) and took > 0


def test_full_data_fits_are_run_for_every_k(spark):
    from pyspark.sql import functions as F

    from stablecf.sources import generators

    few = generators.geo_like(spark, 3000)
    got = {(x.method, x.param, x.metric): x.value for x in workloads.real_like_sweep(spark, {"places": (few, [F.col("x_0"), F.col("x_1")])}, ks=(2, 6), cap=40, rows_k=2, iters=2).collect()}
    for shape in ("diagonal", "spherical"):
        for k in (2.0, 6.0):
            assert got[f"points-stable-{shape}", k, "mean_ll"] < 0 and got[f"features-stable-{shape}", k, "speed_ratio"] > 0
        assert (f"points-stable-{shape}", 6.0, "beyond_published") in got and (f"points-stable-{shape}", 2.0, "beyond_published") not in got


def test_rows_of_one_file_are_dealt_to_all_tasks_whole(spark):
    import numpy as np
    from pyspark.sql import functions as F

    from stablecf.operators.summarize import collect, project

    one = project(spark.range(0, 30_000, 1, 1).select((F.col("id") * 7 % 1009).alias("a"), F.col("id").alias("b")), [F.col("a"), F.col("b")], 1 + F.col("b") % 3 * (F.col("b") >= 20_000).cast("int"))
    for rows in (one, one.limit(700), one.where("w = 1")):
        kept = mixture.Spread(mixture.packed(rows))
        parts = [sum(len(w) for w, *_ in mixture._numbers(p)) for p in kept.batches.glom().collect()]
        want, got = collect(rows), [np.concatenate(v) for v in zip(*mixture._numbers(kept.batches.collect()), strict=True)]
        order = np.lexsort((*got[1].T, got[0]))
        assert all(np.array_equal(a, b[order]) for a, b in zip(want, got, strict=True))
        if len(want[0]) > 20_000:
            assert len(parts) == spark.sparkContext.defaultParallelism and max(parts) < 1.5 * len(want[0]) / len(parts)
