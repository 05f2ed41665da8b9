"""Distances between features and absorption tests: columns, and the same in numpy (one feature to many)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stablecf.functions.features import classic_merge, classic_var, total

KINDS = ("D0", "D1", "D2", "D3", "D4", "R", "E")


def absorbs(a: Column, b: Column, kind: str, threshold, form: str = "stable") -> Column:
    """Whether the test lets ``a`` take ``b`` in; any distance may be the test."""
    return distance(a, b, kind, form) <= threshold


def pairwise(cf: DataFrame, key: str, kind: str, form: str = "stable") -> DataFrame:
    """(a, b, value) of all pairs of a bounded set of features, a < b."""
    cols = ["n", "ls", "ss"] if form == "classic" else ["w", "m", "q"]
    f = cf.select(key, F.struct(*cols).alias("f"))
    x, y = f.select(F.col(key).alias("a"), F.col("f").alias("fa")), f.select(F.col(key).alias("b"), F.col("f").alias("fb"))
    return x.join(F.broadcast(y), F.col("a") < F.col("b")).select("a", "b", distance(F.col("fa"), F.col("fb"), kind, form).alias("value"))


def nearest(cf: DataFrame, key: str, others: DataFrame, other_key: str, kind: str) -> DataFrame:
    """(key, other, value): the nearest of ``others`` (a bounded set) for each feature, ties by the smaller key."""
    x = cf.select(key, F.struct("w", "m", "q").alias("fa"))
    y = others.select(F.col(other_key).alias("other"), F.struct("w", "m", "q").alias("fb"))
    d = x.crossJoin(F.broadcast(y)).select(key, "other", distance(F.col("fa"), F.col("fb"), kind).alias("value"))
    return d.groupBy(key).agg(F.min_by("other", F.struct("value", "other")).alias("other"), F.min("value").alias("value"))


def distance(a: Column, b: Column, kind: str, form: str = "stable", squared: bool = False, clamp: str = "none") -> Column:
    """The measure ``kind``, or its square, which needs no root and shows a classic radicand that went negative; ``clamp``: none or zero."""
    if not squared and clamp == "none":
        return _distance(a, b, kind, form)
    d2 = _radicand(a, b, kind, form)
    d2 = F.greatest(d2, F.lit(0.0)) if clamp == "zero" else d2
    return d2 if squared else F.sqrt(d2)


def _distance(a: Column, b: Column, kind: str, form: str) -> Column:
    """``kind``: centre Euclid (D0, and E as a test), centre Manhattan, inter-cluster, intra-cluster (diameter of the union), variance increase, radius of the union.

    A classic radicand may be negative; the root is then NaN, as the baseline has it.
    """
    d2 = _radicand(a, b, kind, form)
    return F.sqrt(d2)


def _radicand(a: Column, b: Column, kind: str, form: str) -> Column:
    if form == "classic":
        return _classic(a, b, kind)
    diff = F.zip_with(a["m"], b["m"], lambda x, y: x - y)
    if kind == "D1":
        one = total(F.transform(diff, F.abs))
        return one * one
    d2 = total(F.transform(diff, lambda v: v * v))
    w = a["w"] + b["w"]
    g = a["w"] * b["w"] / w * d2
    s = total(a["q"]) + total(b["q"]) + g
    return {"D0": d2, "E": d2, "D2": total(a["q"]) / a["w"] + total(b["q"]) / b["w"] + d2, "D3": F.when(w > 1, 2 * s / (w - 1)), "D4": g, "R": s / w}[kind]


def _classic(a: Column, b: Column, kind: str) -> Column:
    u = classic_merge(a, b)
    sq = lambda v: total(F.transform(v, lambda x: x * x))
    diff = F.zip_with(F.transform(a["ls"], lambda v: v / a["n"]), F.transform(b["ls"], lambda v: v / b["n"]), lambda x, y: x - y)
    if kind == "D1":
        one = total(F.transform(diff, F.abs))
        return one * one
    dot = total(F.zip_with(a["ls"], b["ls"], lambda x, y: x * y))
    return {
        "D0": sq(diff),
        "E": sq(diff),
        "D2": a["ss"] / a["n"] + b["ss"] / b["n"] - 2 * dot / (a["n"] * b["n"]),
        "D3": 2 / (u["n"] - 1) * (u["ss"] - sq(u["ls"]) / u["n"]),
        "D4": sq(a["ls"]) / a["n"] + sq(b["ls"]) / b["n"] - sq(u["ls"]) / u["n"],
        "R": classic_var(u),
    }[kind]


def squared_np(w, m, q, W, M, Q, kind: str) -> np.ndarray:
    """Squared stable measure of one feature to many; Q and q are per axis."""
    d = M - m
    if kind == "D1":
        return np.abs(d).sum(axis=1) ** 2
    d2 = (d * d).sum(axis=1)
    if kind in ("D0", "E"):
        return d2
    t = W + w
    g = w * W / t * d2
    if kind == "D4":
        return g
    if kind == "D2":
        return q.sum() / w + Q.sum(axis=1) / W + d2
    s = q.sum() + Q.sum(axis=1) + g
    return s / t if kind == "R" else 2 * s / np.maximum(t - 1, 1e-300)


def squared_classic_np(n, ls, ss, N, LS, SS, kind: str) -> np.ndarray:
    """The same on classic features (scalar ss), with their cancellation."""
    if kind in ("D0", "E", "D1"):
        d = LS / N[:, None] - ls / n
        return np.abs(d).sum(axis=1) ** 2 if kind == "D1" else (d * d).sum(axis=1)
    t, u, s2 = N + n, LS + ls, SS + ss
    if kind == "D2":
        return ss / n + SS / N - 2 * (LS @ ls) / (n * N)
    if kind == "D4":
        return (ls @ ls) / n + (LS * LS).sum(axis=1) / N - (u * u).sum(axis=1) / t
    if kind == "R":
        return s2 / t - ((u / t[:, None]) ** 2).sum(axis=1)
    return 2 / np.maximum(t - 1, 1e-300) * (s2 - (u * u).sum(axis=1) / t)
