import numpy as np
import pytest
from pyspark.sql import functions as F

from stablecf.functions import features as A
from stablecf.functions import measures as B
from stablecf.operators import mixture as M
from stablecf.operators.summarize import collect, collect_stable, features_to_cells, invalid_rows, project, summarize
from stablecf.operators.tree import FeatureTree, TreeConfig
from stablecf.sources import generators as G


def feature(x):
    return len(x), x.mean(axis=0), ((x - x.mean(axis=0)) ** 2).sum(axis=0)


def test_measures_by_pairs():
    rng = np.random.default_rng(0)
    x, y = rng.normal(size=(7, 3)), rng.normal(size=(5, 3)) + 1
    a, b = feature(x), feature(y)
    got = {k: B.squared_np(*a, np.array([b[0]]), b[1][None], b[2][None], k)[0] for k in ("D0", "D1", "D2", "D3", "D4", "R")}
    u = np.concatenate([x, y])
    cross = ((x[:, None] - y[None]) ** 2).sum(axis=2)
    every = ((u[:, None] - u[None]) ** 2).sum(axis=2)
    s = lambda z: ((z - z.mean(axis=0)) ** 2).sum()
    want = {"D0": ((a[1] - b[1]) ** 2).sum(), "D1": np.abs(a[1] - b[1]).sum() ** 2, "D2": cross.mean(), "D3": every.sum() / (12 * 11), "D4": s(u) - s(x) - s(y), "R": s(u) / 12}
    assert got == pytest.approx(want)
    c = [(len(z), z.sum(axis=0), (z * z).sum()) for z in (x, y)]
    for k in want:
        assert B.squared_classic_np(*c[0], np.array([c[1][0]]), c[1][1][None], np.array([c[1][2]]), k)[0] == pytest.approx(want[k])


def test_hand_example(spark):
    f = spark.range(1).select(F.expr("struct(2D as w, array(1D) as m, array(2D) as q)").alias("a"), F.expr("struct(1D as w, array(4D) as m, array(0D) as q)").alias("b"))
    r = f.select(A.stable_merge(F.col("a"), F.col("b")).alias("u"), *[B.distance(F.col("a"), F.col("b"), k).alias(k) for k in B.KINDS]).first()
    assert (r["u"]["w"], r["u"]["m"], r["u"]["q"]) == (3.0, [2.0], [8.0])
    assert [round(r[k] ** 2, 9) for k in B.KINDS] == [9, 9, 10, 8, 6, round(8 / 3, 9), 9]


@pytest.mark.parametrize("form", ["stable", "classic"])
def test_tree_conserves_and_keeps_the_cap(form):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(3000, 2)) * 3
    t = FeatureTree(TreeConfig(leaf_cap=100, branching=10, form=form), 2)
    t.insert_batch(np.ones(len(x)), x, np.zeros_like(x))
    w, m, q = t.leaves()
    assert len(w) == t.entries <= 100 and w.sum() == 3000
    mean = (w[:, None] * m).sum(axis=0) / 3000
    assert mean == pytest.approx(x.mean(axis=0), abs=1e-9)
    assert q.sum() + (w[:, None] * (m - mean) ** 2).sum() == pytest.approx(((x - x.mean(axis=0)) ** 2).sum())


def test_equal_points_are_one_entry():
    t = FeatureTree(TreeConfig(leaf_cap=10), 2)
    t.insert_batch(np.ones(500), np.full((500, 2), 3.0), np.zeros((500, 2)))
    assert t.entries == 1 and t.threshold == 0


def test_stable_survives_a_shift_and_classic_does_not(spark):
    x = G.gaussian_pair(spark, 2000, 1e8, seed=3).where("true_comp = 0")
    ax = [F.col(f"x_{i}") for i in range(3)]
    v = A.stable_agg(x, ax, []).select(A.stable_var(F.struct("w", "m", "q")).alias("v")).first()["v"]
    assert v == pytest.approx([16 / 9, 1, 9 / 16], rel=0.15)
    c = A.classic_agg(x, ax, []).select(A.classic_var(F.struct("n", "ls", "ss")).alias("v")).first()["v"]
    assert abs(c - sum(v)) > 1


def test_separated_mixture_is_found(spark):
    rows = project(G.gaussian_pair(spark, 4000, 10.0, seed=5), [F.col(f"x_{i}") for i in range(3)])
    m = M.fit_features(*collect(summarize(rows, TreeConfig(leaf_cap=200), parts=3)), 2, "diagonal")
    assert sorted(m.mean[:, 0]) == pytest.approx([-10, 10], abs=0.15)
    assert np.sqrt(m.var).mean(axis=0) == pytest.approx([4 / 3, 1, 3 / 4], rel=0.06)
    assert M.assign(rows, m).groupBy("comp").count().count() == 2


def test_single_rows_as_features_equal_row_em(spark):
    rows = project(G.gaussian_pair(spark, 300, 2.0, seed=6), [F.col(f"x_{i}") for i in range(3)])
    w, m, q = collect(rows)
    begin = M.start(w, m, q, 2, 0)
    a = M.fit_features(w, m, q, 2, model=begin, max_iter=5, tol=0)
    b = M.fit_rows(rows, 2, model=begin, max_iter=5, tol=0)
    assert a.history == pytest.approx(b.history, rel=1e-9)


def test_bad_rows_are_left_out(spark):
    df = spark.createDataFrame([(1.0, 1.0), (None, 1.0), (float("nan"), 1.0), (float("inf"), 1.0), (2.0, 0.0)], "x double, w double")
    assert project(df, [F.col("x")], F.col("w")).count() == 1


def test_invalid_rows_are_found_or_end_the_job(spark):
    df = spark.createDataFrame([(1.0, 1.0), (None, 1.0), (2.0, None), (3.0, float("inf"))], "x double, w double")
    assert invalid_rows(df, [F.col("x")], F.col("w")).count() == 3
    with pytest.raises(Exception, match="invalid coordinate"):
        project(df, [F.col("x")], F.col("w"), "fail").collect()
    assert project(df.where("x = 1"), [F.col("x")], F.col("w"), "fail").count() == 1


def test_squares_and_clamps(spark):
    far = spark.sql("SELECT struct(3D AS n, array(3e9D) AS ls, 3e18D AS ss) AS a, struct(1D AS n, array(1e9D) AS ls, 1e18D - 1024 AS ss) AS b")
    one = far.select(*[B.distance(F.col("a"), F.col("b"), "R", "classic", squared=x, clamp=c).alias(f"{x}{c}") for x in (True, False) for c in ("none", "zero")]).first()
    assert one["Truenone"] < 0 and np.isnan(one["Falsenone"]) and one["Truezero"] == one["Falsezero"] == 0
    v = far.select(*[A.classic_var(F.col("b"), c).alias(c) for c in ("none", "zero", "nan")]).first()
    assert v["none"] < 0 and v["zero"] == 0 and np.isnan(v["nan"])


def test_hard_start_and_json():
    x = np.concatenate([np.random.default_rng(1).normal(size=(60, 1)), np.full((20, 1), 30.0)])
    m = M.start(np.ones(80), x, np.zeros_like(x), 2, 0, assign="hard")
    assert sorted(m.weight) == pytest.approx([0.25, 0.75]) and M.Mixture.of_json(m.to_json()).mean == pytest.approx(m.mean)


def test_agglomerate():
    w = np.ones(4)
    m = np.array([[0.0], [0.1], [5.0], [5.1]])
    assert M.agglomerate(w, m, np.zeros((4, 1)), 2).tolist() in ([0, 0, 1, 1], [1, 1, 0, 0])


def one_by_one(x, threshold, cap_leaf=10**6):
    """Entries (w, mean, q) of rows inserted in order into one leaf: nearest by variance increase, absorbed if the radius of the union allows."""
    out = []
    for r in x:
        if out:
            g = [w / (w + 1) * float(((r - m) ** 2).sum()) for w, m, _ in out]
            i = int(np.argmin(g))
            w, m, q = out[i]
            if (q.sum() + g[i]) / (w + 1) <= threshold**2:
                d = r - m
                out[i] = (w + 1, m + d / (w + 1), q + w / (w + 1) * d * d)
                continue
        out.append((1, r, np.zeros(len(r))))
    return out


@pytest.mark.parametrize("threshold", [0.0, 0.3, 1.0])
def test_leaf_entries_by_brute_force(threshold):
    x = np.random.default_rng(2).normal(size=(300, 2))
    x[50:60] = x[40]
    t = FeatureTree(TreeConfig(leaf_cap=1000, leaf_size=1000, strict=True), 2)
    t.threshold = threshold
    t.insert_batch(np.ones(300), x, np.zeros_like(x))
    want = one_by_one(x, threshold)
    w, m, q = t.leaves()
    assert w.tolist() == [e[0] for e in want]
    assert m == pytest.approx(np.array([e[1] for e in want])) and q == pytest.approx(np.array([e[2] for e in want]), abs=1e-12)


@pytest.mark.parametrize("strict", [True, False])
def test_invariants_after_rebuilds(strict):
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(size=(4000, 3)), rng.normal(size=(2000, 3)) + 9, np.full((500, 3), 2.0)])
    t = FeatureTree(TreeConfig(leaf_cap=150, branching=8, leaf_size=8, strict=strict), 3)
    before = 0.0
    for part in np.array_split(x[rng.permutation(len(x))], 7):
        t.insert_batch(np.ones(len(part)), part, np.zeros_like(part))
        assert all(t.check_invariants().values()) and t.threshold >= before
        before = t.threshold
    w, m, q = t.leaves()
    assert w.sum() == len(x) and q.sum() + (w[:, None] * (m - x.mean(axis=0)) ** 2).sum() == pytest.approx(((x - x.mean(axis=0)) ** 2).sum())


def test_single_entry_leaves_still_find_a_threshold():
    t = FeatureTree(TreeConfig(leaf_cap=4, branching=2, leaf_size=1, strict=True), 1)
    x = np.arange(40.0)[:, None] ** 2
    t.insert_batch(np.ones(40), x, np.zeros_like(x))
    assert t.entries <= 4 and t.rebuilds < 40


def test_guard_and_scalar_deviation():
    heavy = (np.array([1e5]), np.zeros((1, 2)), np.zeros((1, 2)))
    far = (np.ones(1), np.full((1, 2), 100.0), np.zeros((1, 2)))
    for guard, n in ((None, 1), (10.0, 2)):
        t = FeatureTree(TreeConfig(absorb_guard=guard), 2)
        t.threshold = 1.0
        t.insert_batch(*heavy)
        t.insert_batch(*far)
        assert t.entries == n
    x = np.random.default_rng(5).normal(size=(800, 3))
    a, b = (FeatureTree(TreeConfig(leaf_cap=60, q=q, strict=True), 3) for q in ("vector", "scalar"))
    for t in (a, b):
        t.insert_batch(np.ones(800), x, np.zeros_like(x))
        w, m, q = t.leaves()
        assert t.entries <= 60 and q.sum() + (w[:, None] * (m - x.mean(axis=0)) ** 2).sum() == pytest.approx(((x - x.mean(axis=0)) ** 2).sum())


@pytest.mark.parametrize("options", [{"compact": True}, {"compact": False}, {"compact": False, "parts": 5, "fan_in": 2}, {"compact": True, "parts": 3}])
@pytest.mark.parametrize("form", ["stable", "classic"])
def test_summaries_conserve(spark, options, form):
    rows = project(G.gaussian_pair(spark, 6000, 4.0, seed=8).repartition(6), [F.col(f"x_{i}") for i in range(3)])
    w, m, q = collect_stable(summarize(rows, TreeConfig(leaf_cap=120, form=form), **options), form)
    x = np.array([r["m"] for r in rows.collect()])
    assert len(w) <= 120 and w.sum() == 6000
    assert q.sum() + (w[:, None] * (m - x.mean(axis=0)) ** 2).sum() == pytest.approx(((x - x.mean(axis=0)) ** 2).sum(), rel=1e-9)


def test_summary_of_no_rows_and_of_few(spark):
    rows = project(G.gaussian_pair(spark, 3, 1.0), [F.col("x_0")])
    assert summarize(rows.where("false"), TreeConfig(leaf_cap=5)).count() == 0
    w, m, q = collect(summarize(rows, TreeConfig(leaf_cap=5)))
    assert w.tolist() == [1, 1, 1] and not q.any()


def test_cells_keep_moments_far_from_the_origin(spark):
    rows = project(G.gaussian_pair(spark, 4000, 0.0, seed=9), [F.col(f"x_{i}") + 1e9 for i in range(3)])
    w, m, q = collect(features_to_cells(rows, [0.5, 0.5, 0.5]))
    x = np.array([r["m"] for r in rows.collect()]) - 1e9
    m = m - 1e9
    assert q.sum() + (w[:, None] * (m - x.mean(axis=0)) ** 2).sum() == pytest.approx(((x - x.mean(axis=0)) ** 2).sum(), rel=1e-6) and (q >= 0).all()


def test_full_covariance_and_options():
    rng = np.random.default_rng(6)
    a = rng.multivariate_normal([0, 0], [[2, 1.2], [1.2, 1]], 3000)
    b = rng.multivariate_normal([12, 0], [[1, -0.6], [-0.6, 1]], 3000)
    x = np.concatenate([a, b])
    w, q = np.ones(len(x)), np.zeros((len(x), 2, 2))
    m = M.fit_features(w, x, q, 2, "full", seed=1)
    got = m.var[np.argsort(m.mean[:, 0])]
    assert got[0] == pytest.approx(np.cov(a.T, bias=True), abs=0.1) and got[1] == pytest.approx(np.cov(b.T, bias=True), abs=0.1)
    diag = M.fit_features(w, x, np.zeros_like(x), 2, "diagonal", seed=1)
    assert m.history[-1] > diag.history[-1]
    tied = M.fit_features(w, x, np.zeros_like(x), 2, "diagonal", seed=1, tied=True)
    assert tied.var[0] == pytest.approx(tied.var[1])
    strong = M.fit_features(w, x, np.zeros_like(x), 2, "diagonal", seed=1, prior=(1e9, 7.0))
    assert strong.var == pytest.approx(7.0, rel=1e-3)
    spread = np.repeat(np.diag([0.5, 0.25])[None], len(x), axis=0)
    one = M.Mixture(np.array([1.0]), np.zeros((1, 2)), np.array([[[2.0, 0.5], [0.5, 1.0]]]))
    flat = M.e_step(one, w, x, spread[:, [0, 1], [0, 1]], "expected")[1]
    assert M.e_step(one, w, x, spread, "expected")[1] == pytest.approx(flat)


def test_components_of_rows_round_trip():
    for m in (M.Mixture(np.array([0.4, 0.6]), np.eye(2), np.ones((2, 2))), M.Mixture(np.array([1.0]), np.zeros((1, 3)), np.eye(3)[None])):
        back = M.Mixture.of_rows(m.rows())
        assert back.var.shape == m.var.shape and back.mean == pytest.approx(m.mean)


def test_classic_algebra_fails_far_out_and_stable_does_not():
    rng = np.random.default_rng(7)
    for s, fails in ((0.0, False), (1e8, True)):
        x = np.concatenate([rng.normal(size=(400, 2)) - s - 5, rng.normal(size=(400, 2)) + s + 5])
        n, ls, ss = np.ones(800), x.copy(), (x * x).sum(axis=1)
        begin = M.Mixture(np.array([0.5, 0.5]), np.array([[-s - 5] * 2, [s + 5] * 2]), np.ones((2, 2)))
        a = M.fit_features_classic(n, ls, ss, 2, model=begin, max_iter=5)
        b = M.fit_features(n, x, np.zeros_like(x), 2, "spherical", model=begin, max_iter=5)
        assert b.var == pytest.approx(1.0, abs=0.2) and (a.least_var < 0.5 or a.least_var > 2) == fails


def test_best_model_is_kept_and_empty_components_start_anew():
    x = np.concatenate([np.zeros((50, 1)), np.full((50, 1), 9.0)])
    far = M.Mixture(np.array([0.5, 0.5]), np.array([[4.0], [1e6]]), np.ones((2, 1)))
    m = M.fit_features(np.ones(100), x, np.full_like(x, 0.01), 2, model=far, max_iter=50)
    assert sorted(m.mean[:, 0]) == pytest.approx([0, 9], abs=0.1)
    best, seen = M._iterate(lambda now: (now.weight[0], M.Mixture(now.weight - 1, now.mean, now.var), None), M.Mixture(np.array([3.0]), np.zeros((1, 1)), np.ones((1, 1))), 9, 0.0), 3.0
    assert best.weight[0] == seen and best.converged and best.history == [3.0, 2.0]


def test_seeds_on_rows_spread(spark):
    rows = project(G.grid(spark, 0.01), [F.col("x_0"), F.col("x_1")])
    c = M.kmeanspp_rows(rows, 100, 3)
    x = np.array([r["m"] for r in rows.collect()])
    cost = M._nearest(x, c)[1].sum()
    again = M.kmeanspp(np.ones(len(x)), x, 100, 3)
    assert len(c) == 100 and cost < 1.5 * M._nearest(x, again)[1].sum()
    assert np.array_equal(c, M.kmeanspp_rows(rows.repartition(7), 100, 3))


def test_merge_many_and_routes(spark):
    rng = np.random.default_rng(8)
    x, g = rng.normal(size=(500, 2)) + 1e8, rng.integers(0, 5, 500)
    w, m, q = A.merge_many(np.ones(500), x, np.zeros_like(x), g)
    for j in range(5):
        assert m[j] == pytest.approx(x[g == j].mean(axis=0)) and q[j] == pytest.approx(((x[g == j] - x[g == j].mean(axis=0)) ** 2).sum(axis=0), rel=1e-6)
    rows = project(G.gaussian_pair(spark, 3000, 6.0, seed=4).repartition(3), [F.col(f"x_{i}") for i in range(3)])
    parts = collect(M.fit_by_partition(rows, 6, TreeConfig(leaf_cap=100)))
    assert parts[0].sum() == pytest.approx(3000) and sorted(M.fit_features(*parts, 2).mean[:, 0]) == pytest.approx([-6, 6], abs=0.2)
    cf = summarize(rows, TreeConfig(leaf_cap=100))
    begin = M.start(*collect(cf), 2, 0)
    a, b = M.fit_features(*collect(cf), 2, model=begin, max_iter=4), M.fit_rows(cf, 2, variance="overlap", model=begin, max_iter=4)
    assert a.history == pytest.approx(b.history, rel=1e-9)


def test_generators_do_not_depend_on_the_layout(spark):
    for make in (lambda: G.gaussian_pair(spark, 1000, 3.0, seed=2), lambda: G.halton_blobs(spark, 0.002, seed=2), lambda: G.geo_like(spark, 1000, 2)):
        one = lambda df: sorted(map(tuple, df.collect()))
        assert one(make()) == one(make().repartition(3))
    x = np.array([r[0] for r in G.gaussian_pair(spark, 40000, 0.0, seed=1).select("x_1").collect()])
    assert abs(x.mean()) < 0.02 and x.std() == pytest.approx(1, abs=0.02)


def test_hulls_and_agglomeration_by_brute_force(spark):
    from stablecf.plans.workloads import hulls

    rng = np.random.default_rng(9)
    x = rng.normal(size=(400, 2))
    df = spark.createDataFrame([(int(i % 2), [float(a), float(b)]) for i, (a, b) in enumerate(x)] + [(7, [0.0, 0.0])], "comp int, m array<double>").repartition(5)
    got = {r["comp"]: r for r in hulls(df, 0.01).collect()}
    assert set(got) == {0, 1}
    for j in (0, 1):
        pts, h = x[j::2], np.array(got[j]["hull"])
        nxt = np.roll(h, -1, axis=0)
        for p in pts:  # every point lies left of or on every edge
            assert ((nxt[:, 0] - h[:, 0]) * (p[1] - h[:, 1]) - (nxt[:, 1] - h[:, 1]) * (p[0] - h[:, 0]) >= -1e-9).all()
    w, m, q = np.ones(60), rng.normal(size=(60, 2)), np.zeros((60, 2))
    for kind in ("D0", "D2", "D4"):
        f, at = [(1.0, m[i], q[i], [i]) for i in range(60)], []
        while len(f) > 6:
            i, j = min(((i, j) for i in range(len(f)) for j in range(i + 1, len(f))), key=lambda p: B.squared_np(*f[p[0]][:3], np.array([f[p[1]][0]]), f[p[1]][1][None], f[p[1]][2][None], kind)[0])
            a, b = f[i], f[j]
            u = A.merge_many(np.array([a[0], b[0]]), np.stack([a[1], b[1]]), np.stack([a[2], b[2]]))
            f[i] = (u[0][0], u[1][0], u[2][0], a[3] + b[3])
            del f[j]
        label = M.agglomerate(w, m, q, 6, kind)
        assert {frozenset(x[3]) for x in f} == {frozenset(np.flatnonzero(label == c).tolist()) for c in range(6)}
