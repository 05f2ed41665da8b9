"""Clusterings of a summary's leaf entries beside mixtures, and measures on features; all on the driver, bounded by the leaf cap."""

from __future__ import annotations

import numpy as np

from stablecf.operators.mixture import Mixture, e_step


def kmedoids_search(w, m, q, k: int, neighbours: int = 100, restarts: int = 2, seed: int = 0) -> tuple[np.ndarray, float]:
    """Randomised search over medoid sets: a random swap that lowers the cost is taken, a set that resists ``neighbours`` swaps is a local optimum.

    Cost: weighted distance of each entry's centre to its nearest medoid (``q`` takes no part).  Returns (indices of the medoids, cost).
    """
    rng, n = np.random.default_rng(seed), len(w)
    k = min(k, n)
    best, best_cost = np.arange(k), np.inf

    def cost(ids: np.ndarray) -> float:
        return float((w * np.sqrt(((m[:, None] - m[ids][None]) ** 2).sum(axis=2).min(axis=1))).sum())

    for _ in range(restarts):
        now = rng.choice(n, k, replace=False)
        value, failed = cost(now), 0
        while failed < neighbours and k < n:
            other = now.copy()
            new = int(rng.integers(n))
            if new in now:
                failed += 1
                continue
            other[rng.integers(k)] = new
            v = cost(other)
            now, value, failed = (other, v, 0) if v < value else (now, value, failed + 1)
        if value < best_cost:
            best, best_cost = np.sort(now), value
    return best, best_cost


def density_clusters(w, m, q, eps: float, min_weight: float) -> np.ndarray:
    """Cluster of each entry, -1 for noise: entries whose neighbourhood weighs ``min_weight`` are cores, cores within ``eps`` are connected, others join a core in reach."""
    n = len(w)
    near = np.zeros((n, n), bool)  # one bit a pair; distances a block of rows at a time
    for i in range(0, n, 256):
        near[i : i + 256] = sum((m[i : i + 256, None, a] - m[None, :, a]) ** 2 for a in range(m.shape[1])) <= eps * eps
    core = near @ w >= min_weight
    label, at = np.full(n, -1), 0
    for i in np.flatnonzero(core):
        if label[i] >= 0:
            continue
        label[i], stack = at, [i]
        while stack:
            for j in np.flatnonzero(near[stack.pop()] & (label < 0)):
                label[j] = at
                if core[j]:
                    stack.append(j)
        at += 1
    return label


def loglik_features(w, m, q, model: Mixture, kernel: str = "overlap") -> float:
    """Mean log-likelihood on features; reported beside that on rows, never instead of it."""
    return e_step(model, w, m, q, kernel)[1] / float(w.sum())


def feature_values(form: str, d: int, q: str = "vector") -> int:
    """Numbers that one feature stores; form: classic, stable or covariance."""
    if form == "covariance":
        return 1 + d + d * (d + 1) // 2
    return 2 + d if q == "scalar" else 1 + 2 * d


def expand(rows, w, m, q, label, kind: str = "D4"):
    """Rows (w, m, ...) with the nearest entry and that entry's cluster; the entries are bounded by their cap and go with the task."""
    import pyarrow as pa

    from stablecf.functions.measures import squared_np
    from stablecf.operators.summarize import _lists
    from stablecf.sources.session import ship

    ship(rows.sparkSession)
    label = np.asarray(label)

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            x, none = _lists(b.column(b.schema.get_field_index("m"))), np.zeros(m.shape[1])
            at = np.array([int(np.argmin(squared_np(1.0, r, none, w, m, q, kind))) for r in x])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(at, pa.int32()), pa.array(label[at].astype(np.int32))], [*b.schema.names, "entry", "cluster"])

    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields)
    return rows.mapInArrow(run, f"{fields}, entry int, cluster int")
