"""SQL functions: feature constructors, merges, distances and tests as Arrow functions, and a table function that makes trees."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from stablecf.functions.measures import squared_np
from stablecf.operators.tree import FeatureTree, TreeConfig
from stablecf.sources.session import ship

CF = "w double, m array<double>, q array<double>"


def _arrays(f: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return f["w"].to_numpy(float), np.stack(f["m"].to_numpy()), np.stack(f["q"].to_numpy())


def _point(x: pd.Series) -> pd.DataFrame:
    return pd.DataFrame({"w": np.ones(len(x)), "m": x, "q": [np.zeros(len(v)) for v in x]})


def _merge(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
    if not len(a):
        return a
    (wa, ma, qa), (wb, mb, qb) = _arrays(a), _arrays(b)
    w = wa + wb
    d, f = mb - ma, (wb / np.where(w > 0, w, 1))[:, None]
    return pd.DataFrame({"w": w, "m": list(ma + f * d), "q": list(qa + qb + wa[:, None] * f * d * d)})


def _distance(a: pd.DataFrame, b: pd.DataFrame, kind: pd.Series) -> pd.Series:
    if not len(a):
        return pd.Series([], dtype=float)
    (wa, ma, qa), (wb, mb, qb) = _arrays(a), _arrays(b)
    return pd.Series([float(np.sqrt(squared_np(wa[i], ma[i], qa[i], wb[i : i + 1], mb[i : i + 1], qb[i : i + 1], k)[0])) for i, k in enumerate(kind)])


def _absorbs(a: pd.DataFrame, b: pd.DataFrame, kind: pd.Series, threshold: pd.Series) -> pd.Series:
    return _distance(a, b, kind) <= threshold


def _var(a: pd.DataFrame) -> pd.Series:
    if not len(a):
        return pd.Series([], dtype=object)
    w, _, q = _arrays(a)
    return pd.Series(list(q / w[:, None]))


class Leaves:
    """One tree per partition of (k, x): rows (k, w, m, q)."""

    def __init__(self) -> None:
        self.key, self.x, self.tree, self.cap = None, [], None, 5000

    def eval(self, row, cap: int):
        self.key, self.cap = row["k"], cap
        self.x.append(list(row["x"]))
        if len(self.x) >= 20_000:
            self._flush()

    def _flush(self) -> None:
        if self.x:
            x = np.array(self.x, float)
            self.tree = self.tree or FeatureTree(TreeConfig(leaf_cap=self.cap), x.shape[1])
            self.tree.insert_batch(np.ones(len(x)), x, np.zeros_like(x))
            self.x = []

    def terminate(self):
        self._flush()
        if self.tree is not None:
            for w, m, q in zip(*self.tree.leaves(), strict=True):
                yield self.key, float(w), m.tolist(), q.tolist()


def register(spark: SparkSession) -> None:
    """cf_point, cf_merge, cf_distance, cf_absorbs, cf_var, and the table function cf_leaves(TABLE (k, x) PARTITION BY k, cap)."""
    ship(spark)
    for name, f, kind in (("cf_point", _point, CF), ("cf_merge", _merge, CF), ("cf_distance", _distance, "double"), ("cf_absorbs", _absorbs, "boolean"), ("cf_var", _var, "array<double>")):
        spark.udf.register(name, F.pandas_udf(f, kind))
    spark.udtf.register("cf_leaves", F.udtf(Leaves, returnType="k string, w double, m array<double>, q array<double>"))
