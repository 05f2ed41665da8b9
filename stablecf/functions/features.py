"""Cluster features as columns and aggregates.

Stable feature: struct (w, m, q) of weight, means and sums of squared deviations per axis.
Classic feature: struct (n, ls, ss) of count, linear sums and the scalar sum of squares; its
variance cancels, which is why it is here: as the baseline.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def total(arr) -> Column:
    return F.aggregate(arr, F.lit(0.0), lambda s, v: s + v)


def stable_point(x: Column, w=1.0) -> Column:
    return F.struct(F.lit(w).cast("double").alias("w") if not isinstance(w, Column) else w.alias("w"), x.alias("m"), F.transform(x, lambda v: F.lit(0.0)).alias("q"))


def stable_merge(a: Column, b: Column) -> Column:
    """Merged feature; the between-part w_a w_b / w * d^2 is never negative, and a side of weight 0 is the identity."""
    w = a["w"] + b["w"]
    f = F.when(w > 0, b["w"] / w).otherwise(0.0)
    d = F.zip_with(a["m"], b["m"], lambda x, y: y - x)
    m = F.zip_with(a["m"], d, lambda x, y: x + f * y)
    q = F.zip_with(F.zip_with(a["q"], b["q"], lambda x, y: x + y), d, lambda x, y: x + a["w"] * f * y * y)
    return F.struct(w.alias("w"), m.alias("m"), q.alias("q"))


def stable_fold(features: Column, dims: int) -> Column:
    """Fold of an array of features."""
    zeros = F.array(*[F.lit(0.0)] * dims)
    return F.aggregate(features, F.struct(F.lit(0.0).alias("w"), zeros.alias("m"), zeros.alias("q")), stable_merge)


def stable_agg(df: DataFrame, axes: list[Column], keys: list[str]) -> DataFrame:
    """Features of unit-weight rows per group: Spark's own moments, which update online and merge map-side."""
    cols = [F.count(F.lit(1)).cast("double").alias("w"), F.array(*[F.avg(a) for a in axes]).alias("m"), F.array(*[F.var_pop(a) * F.count(a) for a in axes]).alias("q")]
    return df.groupBy(*keys).agg(*cols)


def stable_weighted_agg(df: DataFrame, axes: list[Column], weight: Column, keys: list[str]) -> DataFrame:
    """Weighted rows per group in two passes around the mean, which keeps the digits that one weighted pass loses."""
    rows = df.select(*keys, weight.cast("double").alias("w"), *[a.cast("double").alias(f"x{i}") for i, a in enumerate(axes)])
    d = range(len(axes))
    mean = rows.groupBy(*keys).agg(*[(F.sum(F.col("w") * F.col(f"x{i}")) / F.sum("w")).alias(f"m{i}") for i in d])
    # only one row a group; Spark broadcasts it if it is small enough and shuffles otherwise
    both = rows.join(mean, keys) if keys else rows.crossJoin(mean)
    r = [F.col(f"x{i}") - F.col(f"m{i}") for i in d]
    agg = both.groupBy(*keys).agg(F.sum("w").alias("w"), *[F.first(f"m{i}").alias(f"m{i}") for i in d], *[(F.sum(F.col("w") * r[i] * r[i]) - F.sum(F.col("w") * r[i]) * F.sum(F.col("w") * r[i]) / F.sum("w")).alias(f"q{i}") for i in d])
    return agg.select(*keys, "w", F.array(*[F.col(f"m{i}") for i in d]).alias("m"), F.array(*[F.col(f"q{i}") for i in d]).alias("q"))


def stable_merge_agg(cf: DataFrame, keys: list[str], dims: int) -> DataFrame:
    """Features per group from features: pass one the means, pass two the deviations of the members' means plus their own q."""
    d = range(dims)
    flat = cf.select(*keys, "w", *[F.col("m")[i].alias(f"x{i}") for i in d], *[F.col("q")[i].alias(f"s{i}") for i in d])
    mean = flat.groupBy(*keys).agg(*[(F.sum(F.col("w") * F.col(f"x{i}")) / F.sum("w")).alias(f"m{i}") for i in d])
    both = flat.join(mean, keys) if keys else flat.crossJoin(mean)
    r = [F.col(f"x{i}") - F.col(f"m{i}") for i in d]
    agg = both.groupBy(*keys).agg(F.sum("w").alias("w"), *[F.first(f"m{i}").alias(f"m{i}") for i in d], *[(F.sum(f"s{i}") + F.sum(F.col("w") * r[i] * r[i])).alias(f"q{i}") for i in d])
    return agg.select(*keys, "w", F.array(*[F.col(f"m{i}") for i in d]).alias("m"), F.array(*[F.col(f"q{i}") for i in d]).alias("q"))


def stable_cov_agg(df: DataFrame, axes: list[Column], keys: list[str]) -> DataFrame:
    """Covariance features: qc packs the upper triangle of co-moments."""
    d = range(len(axes))
    return df.groupBy(*keys).agg(F.count(F.lit(1)).cast("double").alias("w"), F.array(*[F.avg(a) for a in axes]).alias("m"), F.array(*[F.covar_pop(axes[i], axes[j]) * F.count(F.lit(1)) for i in d for j in d if i <= j]).alias("qc"))


def cov_index(i: int, j: int, dims: int) -> int:
    """Place of (i, j), i <= j, in the packed upper triangle."""
    return i * dims - i * (i - 1) // 2 + j - i


def stable_cov_merge(a: Column, b: Column, dims: int) -> Column:
    """Merged covariance feature (w, m, qc)."""
    w = a["w"] + b["w"]
    f = F.when(w > 0, b["w"] / w).otherwise(0.0)
    d = [b["m"][i] - a["m"][i] for i in range(dims)]
    m = [a["m"][i] + f * d[i] for i in range(dims)]
    qc = [a["qc"][cov_index(i, j, dims)] + b["qc"][cov_index(i, j, dims)] + a["w"] * f * d[i] * d[j] for i in range(dims) for j in range(i, dims)]
    return F.struct(w.alias("w"), F.array(*m).alias("m"), F.array(*qc).alias("qc"))


def stable_cov_merge_agg(cf: DataFrame, keys: list[str], dims: int) -> DataFrame:
    """Covariance features per group from covariance features, in two passes around the group's mean."""
    d, pairs = range(dims), [(i, j) for i in range(dims) for j in range(i, dims)]
    flat = cf.select(*keys, "w", *[F.col("m")[i].alias(f"x{i}") for i in d], *[F.col("qc")[n].alias(f"s{n}") for n in range(len(pairs))])
    mean = flat.groupBy(*keys).agg(*[(F.sum(F.col("w") * F.col(f"x{i}")) / F.sum("w")).alias(f"m{i}") for i in d])
    both = flat.join(mean, keys) if keys else flat.crossJoin(mean)
    r = [F.col(f"x{i}") - F.col(f"m{i}") for i in d]
    agg = both.groupBy(*keys).agg(F.sum("w").alias("w"), *[F.first(f"m{i}").alias(f"m{i}") for i in d], *[(F.sum(f"s{n}") + F.sum(F.col("w") * r[i] * r[j])).alias(f"q{n}") for n, (i, j) in enumerate(pairs)])
    return agg.select(*keys, "w", F.array(*[F.col(f"m{i}") for i in d]).alias("m"), F.array(*[F.col(f"q{n}") for n in range(len(pairs))]).alias("qc"))


def classic_point(x: Column, vector_ss: bool = False) -> Column:
    sq = F.transform(x, lambda v: v * v)
    return F.struct(F.lit(1.0).alias("n"), x.alias("ls"), (sq if vector_ss else total(sq)).alias("ss"))


def classic_add(cf: Column, x: Column) -> Column:
    """A point added to a classic feature with scalar ss."""
    return classic_merge(cf, classic_point(x))


def classic_subtract(a: Column, b: Column) -> Column:
    """What is left of ``a`` without the rows of ``b``.  Only classic features offer this: it cancels by its nature."""
    return F.struct((a["n"] - b["n"]).alias("n"), F.zip_with(a["ls"], b["ls"], lambda x, y: x - y).alias("ls"), (a["ss"] - b["ss"]).alias("ss"))


def classic_mean(cf: Column) -> Column:
    return F.transform(cf["ls"], lambda v: v / cf["n"])


def classic_merge(a: Column, b: Column) -> Column:
    return F.struct((a["n"] + b["n"]).alias("n"), F.zip_with(a["ls"], b["ls"], lambda x, y: x + y).alias("ls"), (a["ss"] + b["ss"]).alias("ss"))


def classic_agg(df: DataFrame, axes: list[Column], keys: list[str]) -> DataFrame:
    return df.groupBy(*keys).agg(F.count(F.lit(1)).cast("double").alias("n"), F.array(*[F.sum(a) for a in axes]).alias("ls"), sum((F.sum(a * a) for a in axes), F.lit(0.0)).alias("ss"))


def classic_var(cf: Column, clamp: str = "none") -> Column:
    """Variance summed over axes: mean of squares less the squared means of each axis.  ``clamp`` of what is negative: none, zero, nan."""
    v = _classic_var(cf)
    if clamp == "zero":
        return F.greatest(v, F.lit(0.0))
    return F.when(v < 0, F.lit(float("nan"))).otherwise(v) if clamp == "nan" else v


def _classic_var(cf: Column) -> Column:
    return cf["ss"] / cf["n"] - total(F.transform(cf["ls"], lambda v: (v / cf["n"]) * (v / cf["n"])))


def stable_var(cf: Column) -> Column:
    return F.transform(cf["q"], lambda v: v / cf["w"])


def scalar_q(cf: Column) -> Column:
    return total(cf["q"])


def to_classic(cf: Column) -> Column:
    ls = F.transform(cf["m"], lambda v: v * cf["w"])
    return F.struct(cf["w"].alias("n"), ls.alias("ls"), (total(cf["q"]) + total(F.transform(cf["m"], lambda v: v * v * cf["w"]))).alias("ss"))


def stable_decay(cf: Column, f: float) -> Column:
    return F.struct((cf["w"] * f).alias("w"), cf["m"].alias("m"), F.transform(cf["q"], lambda v: v * f).alias("q"))


def axis_std(cf: Column) -> Column:
    return F.transform(cf["q"], lambda v: F.sqrt(v / cf["w"]))


def to_stable(cf: Column) -> Column:
    """A classic feature with vector ss as (w, m, q, lossy); digits that its squares lost do not come back, hence the mark."""
    m = classic_mean(cf)
    q = F.zip_with(cf["ss"], cf["ls"], lambda s, v: F.greatest(F.lit(0.0), s - v * v / cf["n"]))
    return F.struct(cf["n"].alias("w"), m.alias("m"), q.alias("q"), F.lit(True).alias("lossy"))


def variance_form(cf: Column) -> Column:
    """The feature stored as (w, m, v) with v = q / w."""
    return F.struct(cf["w"].alias("w"), cf["m"].alias("m"), stable_var(cf).alias("v"))


def of_variance_form(cf: Column) -> Column:
    return F.struct(cf["w"].alias("w"), cf["m"].alias("m"), F.transform(cf["v"], lambda v: v * cf["w"]).alias("q"))


def to_single(cf: Column) -> Column:
    """The feature at rest in single precision; the weight stays double, as a float count stops at 2**24."""
    return F.struct(cf["w"].alias("w"), cf["m"].cast("array<float>").alias("m"), cf["q"].cast("array<float>").alias("q"))


def arrival_std(cf: Column, axis: int) -> Column:
    """Spread of one axis, such as time."""
    return F.sqrt(cf["q"][axis] / cf["w"])


def diag_mahalanobis(x: Column, cf: Column, floor: float = 1e-12) -> Column:
    """Distance of a point to the centre in units of the axes' spreads; variances below ``floor`` count as it."""
    z = F.zip_with(F.zip_with(x, cf["m"], lambda a, b: (a - b) * (a - b)), cf["q"], lambda d, q: d / F.greatest(q / cf["w"], F.lit(floor)))
    return F.sqrt(total(z))


def extent(cf: Column) -> Column:
    """Radius: root of the mean squared distance to the centre."""
    return F.sqrt(total(cf["q"]) / cf["w"])


def density(cf: Column, dims: int) -> Column:
    """Weight by volume of the cube whose sides are the axes' spreads, null where one is 0."""
    sides = F.aggregate(axis_std(cf), F.lit(1.0), lambda a, s: a * s)
    return F.when(sides > 0, cf["w"] / sides)


def kde_from_features(cf: DataFrame, grid: DataFrame, axis: int, bandwidth: float) -> DataFrame:
    """Density of one axis at the points ``g`` of ``grid`` (a few rows): each feature is a Gaussian of its own spread plus the bandwidth."""
    from math import pi

    v = F.col("q")[axis] / F.col("w") + bandwidth * bandwidth
    d = F.col("g") - F.col("m")[axis]
    at = cf.crossJoin(F.broadcast(grid.select(F.col("g").cast("double"))))
    each = F.col("w") * F.exp(-d * d / (2 * v)) / F.sqrt(2 * pi * v)
    return at.groupBy("g").agg((F.sum(each) / F.sum("w")).alias("density"))


def max_radius(rows: DataFrame, cf: DataFrame, key: str) -> DataFrame:
    """(key, r_max): the farthest row of each group from the group's centre; not a function of the feature, so it takes a scan of the rows (key, m)."""
    own = rows.join(cf.select(key, F.col("m").alias("_c")), key)
    d = total(F.zip_with("m", "_c", lambda a, b: (a - b) * (a - b)))
    return own.groupBy(key).agg(F.sqrt(F.max(d)).alias("r_max"))


def merge_many(w, m, q, groups=None):
    """Features merged in one task by numpy: all of them, or by group number (0, 1, ...), around each group's own mean."""
    import numpy as np

    groups = np.zeros(len(w), np.int64) if groups is None else np.asarray(groups)
    n = int(groups.max()) + 1 if len(groups) else 0
    t = np.bincount(groups, weights=w, minlength=n)
    base = np.zeros((n, m.shape[1]))
    base[groups] = m  # some member of each group: means are sums of small differences from it
    shift = np.stack([np.bincount(groups, weights=w * (m[:, i] - base[groups, i]), minlength=n) for i in range(m.shape[1])], axis=1)
    mean = base + shift / np.maximum(t, 1e-300)[:, None]
    dev = q + w[:, None] * (m - mean[groups]) ** 2
    return t, mean, np.stack([np.bincount(groups, weights=dev[:, i], minlength=n) for i in range(m.shape[1])], axis=1)
