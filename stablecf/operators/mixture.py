"""Gaussian mixtures on features (driver, bounded by the leaf cap) and on rows (one job an iteration, the baselines)."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stablecf.operators.summarize import _lists
from stablecf.operators.tree import FeatureTree, TreeConfig
from stablecf.sources.session import ship


def _no_holes(logs: np.ndarray) -> np.ndarray:
    """Components by rows turned, without infinite values or such that are no number."""
    return logs.T if np.isfinite(logs.sum()) else np.nan_to_num(logs.T, nan=-1e300, neginf=-1e300, copy=False)


#: Squared distances, in variances, up to which sums of powers around a block's middle are as good as differences: 1e4 * 2^-53 is 1e-12.
NEAR = 1e4


class _Rows:
    """Rows turned to axes by rows, with [1, x, x^2] of their distances from their middle: what passes of all models work out densities and sums of."""

    def __init__(self, xs: np.ndarray, at: np.ndarray | None = None, y: np.ndarray | None = None):
        self.xs, self.at, self.y, self.asked = xs, at, y, None
        if y is None:
            d, n = xs.shape
            self.at = 0.5 * xs.min(axis=1) + 0.5 * xs.max(axis=1) if n else np.zeros(d)
            self.y = np.empty((1 + 2 * d, n))
            self.y[0] = 1.0
            np.subtract(xs, self.at[:, None], out=self.y[1 : 1 + d])
            np.multiply(self.y[1 : 1 + d], self.y[1 : 1 + d], out=self.y[1 + d :])

    def __len__(self) -> int:
        return self.xs.shape[1]

    def __getitem__(self, z: slice) -> _Rows:
        return _Rows(self.xs[:, z], self.at, self.y[:, z])

    def far(self, model: Mixture) -> np.ndarray:
        """Which components' distances, worked out of powers, would lose digits; also those whose parameters are no numbers."""
        if self.asked is None or self.asked[0] is not model:
            with np.errstate(all="ignore"):
                most = self.y[1 + len(self.at) :].max(axis=1, initial=0.0)
                self.asked = model, ~((((model.mean - self.at) ** 2 + most) / model.var).sum(axis=1) <= NEAR) | ~(model.var > 0).all(axis=1)
        return self.asked[1]


@dataclass
class Mixture:
    """k components; ``var``: k x d (spherical and diagonal) or k x d x d (full)."""

    weight: np.ndarray
    mean: np.ndarray
    var: np.ndarray
    history: list[float] = field(default_factory=list)
    converged: bool = False
    #: smallest variance an M-step gave before the floor; below 0 where a baseline cancelled
    least_var: float = float("inf")

    def log_joint(self, x: np.ndarray | _Rows, spread: np.ndarray | None = None) -> np.ndarray:
        """log pi_c + log N(x | mean_c, var_c + spread): rows by components, a component's values side by side in memory."""
        with np.errstate(divide="ignore", invalid="ignore", over="ignore"):
            if self.var.ndim == 2 and spread is None:
                return _no_holes(self._log_joint_rows(x if isinstance(x, _Rows) else _Rows(np.ascontiguousarray(x.T))))
            n, d = x.shape
            k = len(self.weight)
            out = np.empty((k, n))
            if self.var.ndim == 3:
                for c in range(k):
                    out[c] = np.log(self.weight[c]) + _full_logpdf(x - self.mean[c], self.var[c], spread)
                return _no_holes(out)
            xs, t = np.ascontiguousarray(x.T), np.empty((k, n))
            out[:] = np.log(self.weight)[:, None]
            own, v, product = np.ascontiguousarray(np.broadcast_to(spread, x.shape).T), np.empty((k, n)), np.empty((k, n))
            # one logarithm for up to four axes, where all their variances are positive
            group = 4 if n and (self.var.min(axis=0) + own.min(axis=1) > 0).all() and self.var.max() + own.max() < 1e60 else 1
            out -= 0.5 * d * np.log(2 * np.pi)
            for i in range(d):
                np.subtract(xs[i], self.mean[:, i : i + 1], out=t)
                t *= t
                np.add(own[i], self.var[:, i : i + 1], out=v)
                t /= v
                if i % group == 0:
                    product[:] = v
                else:
                    product *= v
                if i % group == group - 1 or i == d - 1:
                    t += np.log(product, out=product)
                t *= 0.5
                out -= t
        return _no_holes(out)

    def _log_joint_rows(self, x: _Rows) -> np.ndarray:
        """Components by rows: one matrix product, and differences where that would lose digits."""
        far = x.far(self)
        base = np.log(self.weight)[:, None] - 0.5 * np.log(2 * np.pi * self.var).sum(axis=1, keepdims=True)
        near, var = np.where(far[:, None], 0.0, self.mean - x.at), np.where(far[:, None], 1.0, self.var)
        out = np.concatenate([base - 0.5 * (near**2 / var).sum(axis=1, keepdims=True), near / var, -0.5 / var], axis=1) @ x.y
        for c in np.flatnonzero(far).tolist():
            out[c] = base[c]
            for v, mean, var in zip(x.xs, self.mean[c], self.var[c], strict=True):
                out[c] += (v - mean) ** 2 * (-0.5 / var)
        return out

    def rows(self) -> list[dict]:
        """The model as rows (comp, weight, mean, var), var packed row by row."""
        return [{"comp": i, "weight": float(w), "mean": m.tolist(), "var": v.ravel().tolist()} for i, (w, m, v) in enumerate(zip(self.weight, self.mean, self.var, strict=True))]

    def to_json(self) -> str:
        return json.dumps(self.rows())

    @staticmethod
    def of_json(text: str) -> Mixture:
        return Mixture.of_rows(json.loads(text))

    @staticmethod
    def of_rows(rows: list) -> Mixture:
        rows = sorted(rows, key=lambda r: r["comp"])
        mean = np.array([r["mean"] for r in rows])
        var = np.array([r["var"] for r in rows])
        d = mean.shape[1]
        return Mixture(np.array([r["weight"] for r in rows]), mean, var.reshape(-1, d, d) if var.shape[1] == d * d and d > 1 else var)


MODEL_SCHEMA = "comp int, weight double, mean array<double>, var array<double>"


def _full_logpdf(r: np.ndarray, cov: np.ndarray, spread: np.ndarray | None) -> np.ndarray:
    d = r.shape[1]
    if spread is None:
        low = np.linalg.cholesky(cov + 1e-12 * np.trace(cov) / d * np.eye(d))
        z = np.linalg.solve(low, r.T)
        return -0.5 * (d * np.log(2 * np.pi) + (z * z).sum(axis=0)) - np.log(np.diag(low)).sum()
    each = cov + (spread if spread.ndim == 3 else spread[:, :, None] * np.eye(d))
    z = np.linalg.solve(each, r[:, :, None])[:, :, 0]
    return -0.5 * (d * np.log(2 * np.pi) + np.linalg.slogdet(each)[1] + (r * z).sum(axis=1))


def kmeanspp(w: np.ndarray, m: np.ndarray, k: int, seed: int, weighted: bool = True) -> np.ndarray:
    """k centres, drawn with probability proportional to (weight times) squared distance."""
    w = w if weighted else np.ones(len(m))
    rng = np.random.default_rng(seed)
    c = [m[rng.choice(len(m), p=w / w.sum())]]
    d = ((m - c[0]) ** 2).sum(axis=1)
    for _ in range(1, min(k, len(m))):
        p = w * d
        c.append(m[rng.choice(len(m), p=p / p.sum()) if p.sum() > 0 else rng.integers(len(m))])
        d = np.minimum(d, ((m - c[-1]) ** 2).sum(axis=1))
    return np.array(c)


#: Rows of a block that a pass bounds by a box, coordinates of rows that are put in order at once, and blocks that move together.
BLOCK, TOGETHER, SLICE = 512, 1 << 18, 4


def _compact_order(x: np.ndarray) -> np.ndarray:
    """An order of rows in which each next ``BLOCK`` of them lie side by side: halves along the widest axis, down to a block."""
    order, todo = np.arange(len(x)), [(0, len(x))]
    while todo:
        a, b = todo.pop()
        if b - a > BLOCK:
            own = x[order[a:b]]
            cut = BLOCK * -(-(b - a) // (2 * BLOCK))
            order[a:b] = order[a:b][np.argpartition(own[:, int(np.argmax(own.max(axis=0) - own.min(axis=0)))], cut)]
            todo += [(a, a + cut), (a + cut, b)]
    return order


def _boxes(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least and largest coordinates of each ``BLOCK`` of rows."""
    at, xs = np.arange(0, len(x), BLOCK), np.ascontiguousarray(x.T)
    return np.minimum.reduceat(xs, at, axis=1).T, np.maximum.reduceat(xs, at, axis=1).T


def _reach(lo: np.ndarray, hi: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least and largest distance, on one axis, of boxes (rows) from points (columns)."""
    a, b = lo[:, None] - c, hi[:, None] - c
    return np.maximum(np.maximum(a, -b), 0.0), np.maximum(np.abs(a), np.abs(b))


def packed(features: DataFrame) -> DataFrame:
    """Rows as rows of many each, whose numbers are bytes, near ones side by side: what an iterative fit keeps and reads again without
    converting each number.  They are dealt evenly, however few files or row groups the rows come from."""
    ship(features.sparkSession)

    def run(batches):
        held = []

        def out():
            w, x, q = (np.concatenate(a) for a in zip(*held, strict=True))
            held.clear()
            near = _compact_order(x)
            # unit weights and no deviations of their own, as of plain rows, are kept as nothing
            unit, plain = not (w != 1).any(), not q.any()
            for i in range(0, len(w), SLICE * BLOCK):
                some = near[i : i + SLICE * BLOCK]
                parts = (w[:0] if unit else w[some], x[some], q[:0] if plain else q[some])
                yield pa.RecordBatch.from_arrays([pa.array([x.shape[1]], pa.int32()), *(pa.array([np.ascontiguousarray(a, np.float64).tobytes()], pa.binary()) for a in parts)], ["d", "w", "m", "q"])

        for b in batches:
            if b.num_rows:
                one = b.column(0).to_numpy(), _lists(b.column(1)), _lists(b.column(2))
                if held and held[0][1].shape[1] != one[1].shape[1]:
                    yield from out()
                held.append(one)
                if sum(h[1].size for h in held) >= TOGETHER:
                    yield from out()
        if held:
            yield from out()

    out = features.select("w", "m", "q").mapInArrow(run, "d int, w binary, m binary, q binary")
    return out.repartition(features.sparkSession.sparkContext.defaultParallelism)


def _numbers(batches):
    """(w, x, q) of plain or packed batches."""
    for b in batches:
        if not b.num_rows:
            continue
        if b.schema.names[0] == "d":
            for d, w, m, q in zip(*(c.to_pylist() for c in b.columns), strict=True):
                x = np.frombuffer(m).reshape(-1, d)
                yield np.frombuffer(w) if w else np.ones(len(x)), x, np.frombuffer(q).reshape(-1, d) if q else np.zeros(x.shape)
        else:
            yield b.column(0).to_numpy(), _lists(b.column(1)), _lists(b.column(2))


#: Packed rows of at most this many coordinates, and densities a pass, are fetched once and iterated on the driver, where a job an iteration costs more than its work.
ON_DRIVER, DENSITIES = 1 << 20, 1 << 22


class Local(list):
    """Packed batches on the driver, read like a packed table."""

    columns = ("d", "w", "m", "q")

    def scan(self, run, schema: str) -> pa.Table:
        # threads would wait for each other's turn with Python between short operations: they take up to twice as long
        return pa.Table.from_batches(list(run(self)))


class Spread:
    """Packed batches that the executors keep: a pass over them is one job, which needs no plan of a query."""

    columns = ("d", "w", "m", "q")

    def __init__(self, table: DataFrame):
        names, kinds = list(self.columns), (pa.int32(), pa.binary(), pa.binary(), pa.binary())

        def joined(rows):
            """Slices that came to one task as few batches, those that don't end with a block last."""
            slices: dict[int, list] = {}
            for r in rows:
                slices.setdefault(r["d"], []).append(r)
            for d, own in slices.items():
                own.sort(key=lambda r: len(r["m"]) // (8 * d) % BLOCK > 0)
                many = max(1, TOGETHER // (SLICE * BLOCK * d))
                for some in (own[i : i + many] for i in range(0, len(own), many)):
                    sizes = [len(r["m"]) // (8 * d) for r in some]
                    w = b"".join(r["w"] or np.ones(n).tobytes() for r, n in zip(some, sizes, strict=True)) if any(r["w"] for r in some) else b""
                    q = b"".join(r["q"] or bytes(8 * n * d) for r, n in zip(some, sizes, strict=True)) if any(r["q"] for r in some) else b""
                    values = d, w, b"".join(r["m"] for r in some), q
                    yield pa.RecordBatch.from_arrays([pa.array([v], kind) for v, kind in zip(values, kinds, strict=True)], names)

        self.batches = table.rdd.mapPartitions(joined).persist(StorageLevel.MEMORY_AND_DISK)

    def scan(self, run, schema: str) -> pa.Table:
        return pa.Table.from_batches(self.batches.mapPartitions(run).collect())

    def local(self, components: int = 1) -> Local | None:
        """The batches themselves, where they and what passes with so many components in all work out of them are few."""
        total, rows = self.batches.map(lambda b: np.array([(n := b["m"][0].as_buffer().size), n / 8 / b["d"][0].as_py()])).fold(np.zeros(2), np.add)
        return Local(self.batches.collect()) if 0 < total <= 8 * ON_DRIVER and rows * components <= DENSITIES else None


def _scan(kept, run, schema: str) -> pa.Table:
    """What ``run`` makes of the batches of a table or of kept ones."""
    return kept.mapInArrow(run, schema).toArrow() if isinstance(kept, DataFrame) else kept.scan(run, schema)


def kmeanspp_rows(features: DataFrame, k: int, seed: int, rounds: int = 5, oversample: float = 2.0, kept: DataFrame | Local | Spread | None = None) -> np.ndarray:
    """k-means++ seeding on rows by oversampled rounds: each pass draws about ``oversample * k`` rows with probability proportional to
    their squared distance from what was drawn, the draws are weighted by the rows nearest to them, and k are picked of these.  ``kept``: the rows packed."""
    return kmeanspp_rows_many(features, [k], seed, rounds, oversample, kept)[0][k]


def kmeanspp_rows_many(features: DataFrame, ks: list[int], seed: int, rounds: int = 5, oversample: float = 2.0, kept: DataFrame | Local | Spread | None = None) -> tuple[dict[int, np.ndarray], dict[int, float]]:
    """The same for several k, each drawn as if alone, in passes that all share; with the seconds that are each one's part."""

    def draw(centres: list[np.ndarray], costs: list[float], salt: int):
        def run(batches):
            kind = pa.list_(pa.float64())
            for w, x, _ in _numbers(batches):
                h = np.frombuffer(np.ascontiguousarray(x + 0.0).tobytes(), np.uint64).reshape(len(x), -1)
                key = np.full(len(x), salt * 0x9E3779B97F4A7C15 % (1 << 64), np.uint64)
                for c in h.T:  # drawn by a hash of the point, so that a repeated task draws the same
                    key = (key ^ c) * np.uint64(0xD6E8FEB86659FD93)
                    key ^= key >> np.uint64(32)
                chance = (key >> np.uint64(11)).astype(float) / float(1 << 53)
                for i, (k, own, cost) in enumerate(zip(ks, centres, costs, strict=True)):
                    t = time.perf_counter()
                    d = w * _nearest(x, own)[1]
                    got = np.unique(x[chance * cost < oversample * k * d], axis=0) if cost > 0 else x[:0]
                    none = [0.0] * len(got)
                    yield pa.RecordBatch.from_arrays([pa.array([i] * (1 + len(got)), pa.int32()), pa.array([float(d.sum()), *none]), pa.array([None, *got.tolist()], kind), pa.array([time.perf_counter() - t, *none])], ["i", "cost", "x", "took"])

        return run

    ship(features.sparkSession)
    kept = features.select("w", "m", "q") if kept is None else kept
    began, parts = time.time(), np.full(len(ks), 1e-9)
    first = features.select("m").orderBy(F.xxhash64("m", F.lit(seed)), "m").limit(1).toArrow()
    if not first.num_rows:
        return {k: np.zeros((0, 0)) for k in ks}, dict.fromkeys(ks, 0.0)
    centres, costs = [_lists(first["m"])] * len(ks), [0.0] * len(ks)
    for r in range(rounds + 1):
        t = _scan(kept, draw(centres, costs, seed * 64 + r + 1), "i int, cost double, x array<double>, took double")
        at = t["i"].to_numpy()
        costs = np.bincount(at, weights=t["cost"].to_numpy(), minlength=len(ks)).tolist()
        parts += np.bincount(at, weights=t["took"].to_numpy(), minlength=len(ks))
        drawn = t.filter(t["x"].is_valid())
        at = drawn["i"].to_numpy()
        got = _lists(drawn["x"]) if len(at) else np.zeros((0, centres[0].shape[1]))
        centres = [np.unique(np.concatenate([c, got[at == i]]), axis=0) for i, c in enumerate(centres)]

    def count(batches):
        total = [np.zeros(len(c)) for c in centres]
        for w, x, _ in _numbers(batches):
            for own, c in zip(total, centres, strict=True):
                own += np.bincount(_nearest(x, c)[0], weights=w, minlength=len(c))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(sum(map(len, total))), pa.int32()), pa.array(np.concatenate(total))], ["c", "n"])

    t = _scan(kept, count, "c int, n double")
    w = np.split(np.bincount(t["c"].to_numpy(), weights=t["n"].to_numpy(), minlength=sum(map(len, centres))), np.cumsum([len(c) for c in centres])[:-1])
    out = {k: kmeanspp(own, c, k, seed) for k, own, c in zip(ks, w, centres, strict=True)}
    return out, dict(zip(ks, (parts / parts.sum() * (time.time() - began)).tolist(), strict=True))


def _nearest(x: np.ndarray, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nearest centre, squared distance) of each row, a centre at a time, an axis at a time; of rows in a compact order a block at a
    time, with the centres alone that may be the nearest there."""
    n = len(x)
    at, best, d, t, less = np.zeros(n, np.int64), np.full(n, np.inf), np.empty(n), np.empty(n), np.empty(n, bool)
    xs = np.ascontiguousarray(x.T)
    if n > BLOCK and len(centres) > 16:
        lo, hi = _boxes(x)
        least, most = (sum(v * v for v in ends) for ends in zip(*(_reach(lo[:, j], hi[:, j], centres[:, j]) for j in range(x.shape[1])), strict=True))
        may = ~(least > (1 + 1e-9) * most.min(axis=1, keepdims=True))
        if may.mean() < 0.25 and np.isfinite(most).all():
            for b, some in enumerate(may):
                z, some = slice(b * BLOCK, (b + 1) * BLOCK), np.flatnonzero(some)
                d = np.zeros((len(some), len(at[z])))
                for j in range(x.shape[1]):
                    t = xs[j, z] - centres[some, j : j + 1]
                    t *= t
                    d += t
                i = d.argmin(axis=0)
                at[z], best[z] = some[i], d[i, np.arange(d.shape[1])]
            return at, best
    for i, c in enumerate(centres):
        for j in range(len(c)):
            out = t if j else d
            np.subtract(xs[j], c[j], out=out)
            np.multiply(out, out, out=out)
            if j:
                np.add(d, t, out=d)
        np.less(d, best, out=less)
        np.copyto(at, i, where=less)
        np.copyto(best, d, where=less)
    return at, best


def start(w, m, q, k: int, seed: int, weighted: bool = True, assign: str = "pooled") -> Mixture:
    """Start on features.  ``pooled``: equal shares and the whole variance over k; ``hard``: shares and variances of one hard assignment."""
    return start_from_centres(w, m, q, kmeanspp(w, m, k, seed, weighted), assign)


def start_from_centres(w, m, q, c: np.ndarray, assign: str = "pooled") -> Mixture:
    mean = (w[:, None] * m).sum(axis=0) / w.sum()
    var = np.maximum(((w[:, None] * (m - mean) ** 2).sum(axis=0) + q.sum(axis=0)) / w.sum(), 1e-12)
    if assign == "hard":
        r = np.zeros((len(w), len(c)))
        r[np.arange(len(w)), _nearest(m, c)[0]] = 1.0
        return m_step(w, m, q, r, "diagonal", 1e-3 * float(var.mean()) / len(c))
    return Mixture(np.full(len(c), 1 / len(c)), c, np.repeat(var[None] / len(c), len(c), axis=0))


def _softmax(logs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    top = logs.max(axis=1)
    e = (logs - top[:, None]) if logs.flags.c_contiguous else np.subtract(logs.T, top).T
    np.exp(e, out=e)
    s = e.sum(axis=1)
    e /= s[:, None]
    return e, top + np.log(s)


def _responsibilities(model: Mixture, x: np.ndarray, spread: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(rows by components, log density of rows), worked out in blocks of rows that stay in a core's cache."""
    n, k = len(x), len(model.weight)
    step = max(256, (1 << 15) // max(1, k))
    if n <= step or model.var.ndim == 3:
        return _softmax(model.log_joint(x, spread))
    r, ll = np.empty((k, n)), np.empty(n)
    for i in range(0, n, step):
        z = slice(i, i + step)
        e, ll[z] = _softmax(model.log_joint(x[z], None if spread is None else spread[z]))
        r[:, z] = e.T
    return r.T, ll


def _deviations(s: np.ndarray, x: np.ndarray, mean: np.ndarray) -> np.ndarray:
    """Squared deviations of rows from each component's mean, weighted by ``s`` (rows by components): components by axes."""
    xs, t = np.ascontiguousarray(x.T), np.empty(len(x))
    st, out = np.ascontiguousarray(s.T), np.empty(mean.shape)
    for c in range(len(mean)):
        for i in range(mean.shape[1]):
            np.subtract(xs[i], mean[c, i], out=t)
            t *= t
            out[c, i] = st[c] @ t
    return out


def _blocks(w: np.ndarray, x: np.ndarray) -> tuple:
    """Of some rows what a pass of any model needs: the rows prepared, their blocks' boxes and weights."""
    return _Rows(np.ascontiguousarray(x.T)), *_boxes(x), np.add.reduceat(w, np.arange(0, len(x), BLOCK))


def _block_sums(model: Mixture, w: np.ndarray, x: np.ndarray, reach: float, blocks: tuple | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, float, np.ndarray]:
    """One pass of stable EM over rows, a block at a time: (masses, means, summed deviations, log-likelihood, most that was left out).

    A component whose density all over a block's box is below e^-reach of the largest there is left out of the block.  Last come
    bounds of what that lacks, by component: of its mass, and of the squared deviations from its mean in ``model`` on each axis.
    """
    (n, d), k = x.shape, len(model.weight)
    rows, lo, hi, heavy = blocks or _blocks(w, x)
    with np.errstate(all="ignore"):
        peak = np.log(model.weight) - 0.5 * np.log(2 * np.pi * model.var).sum(axis=1)
        ends = [_reach(lo[:, i], hi[:, i], model.mean[:, i]) for i in range(d)]
        best, worst = (peak - sum(0.5 * e[j] ** 2 / model.var[:, i] for i, e in enumerate(ends)) for j in (0, 1))
        most = worst.max(axis=1, keepdims=True)
        use = ~(best < most - reach)
        less = np.where(use, 0.0, np.exp(best - most)) * heavy[:, None]
    lost = np.stack([less.sum(axis=0), *((less * e[1] ** 2).sum(axis=0) for e in ends)], axis=1)
    # neighbours with the same components are one block, as far as that stays in a core's cache
    first, same = [], (use[1:] == use[:-1]).all(axis=1).tolist()
    for b, many in enumerate(use.sum(axis=1).tolist()):
        if not first or not same[b - 1] or (b + 1 - first[-1]) * BLOCK * many > 1 << 15:
            first.append(b)
    parts = len(first), k
    mass, mean, dev, ll = np.zeros(parts), np.zeros((*parts, d)), np.zeros((*parts, d)), 0.0
    for p, (b, end) in enumerate(zip(first, [*first[1:], len(use)], strict=True)):
        z, some = slice(b * BLOCK, end * BLOCK), np.flatnonzero(use[b])
        here, own = Mixture(model.weight[some], model.mean[some], model.var[some]), rows[z]
        if own.far(here).any():  # around their own middle they may be near
            own = _Rows(np.ascontiguousarray(own.xs))
        e = here.log_joint(own).T
        top = e.max(axis=0)
        e -= top
        np.exp(e, out=e)
        one = e.sum(axis=0)
        ll += float(w[z] @ (top + np.log(one)))
        share = w[z] / one  # goes to the rows' powers instead of every component's densities
        sums = e @ (own.y * share).T
        mass[p, some] = total = sums[:, 0]
        m = sums[:, 1 : 1 + d] / np.maximum(total, 1e-300)[:, None]
        mean[p, some] = own.at + m
        dev[p, some] = np.maximum(sums[:, 1 + d :] - total[:, None] * m**2, 0.0)
        for c in np.flatnonzero(own.far(here)).tolist():  # narrow ones, whose deviations powers would cancel
            s = e[c] * share
            mean[p, some[c]] = centre = (own.xs @ s) / max(total[c], 1e-300)
            dev[p, some[c]] = ((own.xs - centre[:, None]) ** 2) @ s
    return *_merged(mass, mean, dev), ll, lost


def _merged(mass: np.ndarray, mean: np.ndarray, dev: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Masses, means and deviations of parts (the first axis) as those of all."""
    total = mass.sum(axis=0)
    at = (mass[:, :, None] * mean).sum(axis=0) / np.maximum(total, 1e-300)[:, None]
    return total, at, dev.sum(axis=0) + (mass[:, :, None] * (mean - at) ** 2).sum(axis=0)


def _spread_in(spread: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Expected squared distance that an entry's own spread adds, in units of a component's variance: trace(v^-1 spread)."""
    if v.ndim == 1:
        return ((np.diagonal(spread, axis1=1, axis2=2) if spread.ndim == 3 else spread) / v).sum(axis=1)
    inv = np.linalg.inv(v)
    return np.einsum("ij,lji->l", inv, spread) if spread.ndim == 3 else spread @ np.diag(inv)


def e_step(model: Mixture, w, m, q, kernel: str = "overlap") -> tuple[np.ndarray, float]:
    """Responsibilities and weighted log-likelihood; kernels: overlap, centre, expected.  ``q``: L x d, or L x d x d co-moments."""
    spread = q / w.reshape(-1, *[1] * (q.ndim - 1))
    if kernel == "expected":
        r, ll = _softmax(model.log_joint(m) - 0.5 * np.stack([_spread_in(spread, v) for v in model.var], axis=1))
    else:
        r, ll = _responsibilities(model, m, spread if kernel == "overlap" else None)
    return r, float((w * ll).sum())


def m_step(w, m, q, r, shape: str, floor: float, prior: tuple[float, float] | None = None, tied: bool = False) -> Mixture:
    """Weighted update around the new means, so nothing cancels.  ``prior``: (mass, variance) added to each component; ``tied``: one variance for all."""
    s, d = w[:, None] * r, m.shape[1]
    mass = np.maximum(s.sum(axis=0), 1e-300)
    mean = (s.T @ m) / mass[:, None]
    if shape == "full":
        var = np.stack([((s[:, c : c + 1] * (m - mean[c])).T @ (m - mean[c])) + (np.tensordot(r[:, c], q, 1) if q.ndim == 3 else np.diag(r[:, c] @ q)) for c in range(r.shape[1])])
    else:
        flat = np.diagonal(q, axis1=1, axis2=2) if q.ndim == 3 else q
        var = _deviations(s, m, mean) + r.T @ flat
    return finish(mass, mean, var, shape, floor, prior, tied, d)


def finish(mass, mean, var, shape: str, floor: float, prior=None, tied: bool = False, d: int | None = None) -> Mixture:
    """Components from masses, means and summed squared deviations."""
    d = d or mean.shape[1]
    if tied:
        var, n = np.repeat(var.sum(axis=0, keepdims=True), len(mass), axis=0), np.full(len(mass), mass.sum())
    else:
        n = mass
    if prior:
        var, n = var + prior[0] * prior[1] * (np.eye(d) if shape == "full" else 1.0), n + prior[0]
    var = var / n.reshape(-1, *[1] * (var.ndim - 1))
    if shape == "spherical":
        var = np.repeat(var.mean(axis=1, keepdims=True), d, axis=1)
    if shape == "full":
        return Mixture(mass / mass.sum(), mean, var + floor * np.eye(d), least_var=float(np.diagonal(var, axis1=1, axis2=2).min()))
    return Mixture(mass / mass.sum(), mean, np.maximum(var, floor), least_var=float(var.min()))


class _Climb:
    """The steps of one fit: the best model is kept.  Ends after ``max_iter`` steps, at no improvement beyond ``tol``, or where the likelihood is no number."""

    def __init__(self, model: Mixture, max_iter: int, tol: float):
        self.model, self.best, self.best_ll, self.least, self.history, self.converged = model, model, -np.inf, np.inf, [], False
        self.left, self.tol = max_iter, tol

    def take(self, ll: float, new: Mixture, spare) -> None:
        """``ll``: mean log-likelihood of the present model; ``spare`` tells where an empty component may start anew."""
        self.history.append(ll)
        self.left -= 1
        self.least = min(self.least, new.least_var)
        gain = ll - self.best_ll
        if ll > self.best_ll:
            self.best, self.best_ll = self.model, ll
        if not np.isfinite(ll) or gain <= self.tol * abs(self.best_ll if np.isfinite(self.best_ll) else 0.0):
            self.converged, self.left = bool(np.isfinite(ll)), 0
            return
        empty = np.flatnonzero(new.weight < 1e-12)
        if len(empty) and spare is not None:
            new.mean[empty], new.weight[empty] = spare(), 1e-6
            new.weight /= new.weight.sum()
        self.model = new

    def result(self) -> Mixture:
        return Mixture(self.best.weight, self.best.mean, self.best.var, self.history, self.converged, self.least)


def _iterate(step, model: Mixture, max_iter: int, tol: float) -> Mixture:
    """``step(model)`` gives what a climb takes: (mean log-likelihood, next model, where an empty component may start anew)."""
    climb = _Climb(model, max_iter, tol)
    while climb.left > 0:
        climb.take(*step(climb.model))
    return climb.result()


def fit_features(w, m, q, k: int, shape: str = "diagonal", kernel: str = "overlap", seed: int = 0, max_iter: int = 100, tol: float = 0.0, floor: float = 1e-12, model: Mixture | None = None, weighted: bool = True, init: str = "pooled", **options) -> Mixture:
    """EM on features; the best model seen is kept, as feature likelihoods need not rise.  ``options``: prior, tied."""
    flat = np.diagonal(q, axis1=1, axis2=2) if q.ndim == 3 else q
    model = model or start(w, m, flat, k, seed, weighted, init)
    if shape == "full" and model.var.ndim == 2:
        model = Mixture(model.weight, model.mean, np.stack([np.diag(v) for v in model.var]))

    def step(now: Mixture):
        r, ll = e_step(now, w, m, q, kernel)
        return ll / w.sum(), m_step(w, m, q, r, shape, floor, **options), lambda: m[int(np.argmin(now.log_joint(m).max(axis=1)))]

    return _iterate(step, model, max_iter, tol)


def fit_features_classic(n, ls, ss, k: int, seed: int = 0, max_iter: int = 100, tol: float = 0.0, floor: float = 1e-12, model: Mixture | None = None) -> Mixture:
    """The baseline: spherical EM in classic algebra.  Means and variances are worked out of (n, ls, ss) at each use and cancel there."""
    ss, d = ss.reshape(len(n), -1)[:, 0], ls.shape[1]
    centre = ls / n[:, None]

    def variance(weight, lin, sq):
        return (sq / weight - ((lin / weight[..., None]) ** 2).sum(axis=-1)) / d

    if model is None:
        c = kmeanspp(n, centre, k, seed)
        v = float(ss.sum() / n.sum() - ((ls.sum(axis=0) / n.sum()) ** 2).sum()) / d
        model = Mixture(np.full(len(c), 1 / len(c)), c, np.full(c.shape, max(v / len(c), floor)))

    def step(now: Mixture):
        spread = np.repeat(variance(n, ls, ss)[:, None], d, axis=1)
        r, ll = _responsibilities(now, centre, spread)
        s = np.maximum(r.T @ n, 1e-300)
        lin, sq = r.T @ ls, r.T @ ss
        var = variance(s, lin, sq)
        new = Mixture(s / s.sum(), lin / s[:, None], np.repeat(np.maximum(var, floor)[:, None], d, axis=1), least_var=float(var.min()))
        return float((n * ll).sum() / n.sum()), new, None

    return _iterate(step, model, max_iter, tol)


#: Powers of e by which a pass first leaves components out of blocks, and where nothing but zeros is left out; what a sum may lack of itself.
REACH, ALL, ROUNDING = 50.0, 800.0, 1e-15


def row_step(features: DataFrame | Local | Spread, model: Mixture, variance: str, full: bool = False, reach: list[float] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """One EM pass over rows or features: each task sends k partial rows.  (masses, means, summed deviations, log-likelihood).

    ``textbook``: E[x^2] - E[x]^2 of rows; ``stable``: merged deviations; ``overlap``: the same of features, which bring their own.
    Stable passes leave components out of blocks of rows where they are nothing, and are done again with a longer reach if a sum
    might then lack more than its rounding.  ``reach``: one element, the reach to begin with, set to the one that was enough.
    """
    reach = [REACH] if reach is None else reach
    return row_steps(features, [model], variance, full, [reach])[0][:4]


def row_steps(features: DataFrame | Local | Spread, models: list[Mixture], variance: str, full: bool, reaches: list[list[float]]) -> list[tuple]:
    """The same of several models, in passes that they share; each one's part of the tasks' seconds comes last."""
    out, todo, took = [()] * len(models), list(range(len(models))), np.zeros(len(models))
    while todo:
        again = []
        for i, (mass, mean, dev, ll, lost, s) in zip(todo, _row_pass(features, [models[i] for i in todo], variance, full, [reaches[i][0] for i in todo]), strict=True):
            took[i] += s
            # deviations from the new means are at most twice those from the old ones and the way between
            moved = 2 * (lost[:, 1:] + lost[:, :1] * (mean - models[i].mean) ** 2)
            if reaches[i][0] >= ALL or not lost.any() or ((lost[:, 0] <= ROUNDING * mass).all() and (moved <= ROUNDING * dev).all()):
                out[i] = mass, mean, dev, ll, float(took[i])
            else:
                reaches[i][0] *= 2
                again.append(i)
        todo = again
    return out


def _row_pass(features: DataFrame | Local | Spread, models: list[Mixture], variance: str, full: bool, reaches: list[float]) -> list[tuple]:
    """(masses, means, summed deviations, log-likelihood, most that was left out, seconds) of each model; a task sends one row of each."""
    d = models[0].mean.shape[1]
    if isinstance(features, DataFrame):
        ship(features.sparkSession)
    names = ("s", "a", "b", "lost")

    def run(batches):
        held = [[] for _ in models]
        for w, x, q in _numbers(batches):
            q = q if variance == "overlap" else None
            blocks = _blocks(w, x) if variance == "stable" and not full else None
            for own, model, reach in zip(held, models, reaches, strict=True):
                t = time.perf_counter()
                own.append((*_row_sums(model, w, x, q, variance, full, reach, blocks), time.perf_counter() - t))
                if len(own) == 64:
                    own[:] = [_parts_sum(own, variance, full)]
        if held[0]:
            each = [_parts_sum(own, variance, full) for own in held]
            sums = [pa.array([np.ascontiguousarray(e[j], np.float64).tobytes() for e in each], pa.binary()) for j in (0, 1, 2, 4)]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(each)), pa.int32()), *sums, pa.array([e[3] for e in each]), pa.array([e[5] for e in each])], ["i", *names, "ll", "took"])

    t = _scan(features if features.columns[0] == "d" else features.select("w", "m", "q"), run, "i int, s binary, a binary, b binary, lost binary, ll double, took double")
    rows: list[list[tuple]] = [[] for _ in models]
    for r in t.to_pylist():
        k = len(models[r["i"]].weight)
        s, a, b, lost = (np.frombuffer(r[v]).reshape(shape) for v, shape in zip(names, (k, (k, d), (k, d, d) if full and variance != "textbook" else (k, d), (k, 1 + d)), strict=True))
        rows[r["i"]].append((s, a, b, r["ll"], lost, r["took"]))
    out = []
    for own in rows:
        mass, a, b, ll, lost, took = _parts_sum(own, variance, full)
        mass = np.maximum(mass, 1e-300)
        if variance == "textbook":
            a = a / mass[:, None]
            b = (b / mass[:, None] - a**2) * mass[:, None]
        out.append((mass, a, b, ll, lost, took))
    return out


def _row_sums(model: Mixture, w: np.ndarray, x: np.ndarray, q: np.ndarray | None, variance: str, full: bool, reach: float, blocks: tuple | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, float, np.ndarray]:
    """(masses, means, summed deviations, log-likelihood, most that was left out) of some rows; textbook: sums of rows and of squares in place of the second and third."""
    d, k = model.mean.shape[1], len(model.weight)
    if variance == "stable" and not full and model.var.ndim == 2:
        return _block_sums(model, w, x, reach, blocks)
    r, own = _responsibilities(model, x, q / w[:, None] if q is not None else None)
    s, ll, lost = w[:, None] * r, float((w * own).sum()), np.zeros((k, 1 + d))
    mass, first = s.sum(axis=0), s.T @ x
    if variance == "textbook":
        return mass, first, s.T @ (x * x), ll, lost
    first = first / np.maximum(mass, 1e-300)[:, None]
    if full:
        return mass, first, np.stack([(s[:, c : c + 1] * (x - first[c])).T @ (x - first[c]) for c in range(k)]), ll, lost
    return mass, first, _deviations(s, x, first) + (r.T @ q if q is not None else 0.0), ll, lost


def _parts_sum(parts: list[tuple], variance: str, full: bool) -> tuple:
    """What ``_row_sums`` and a clock give of several parts, as of all their rows."""
    s, a, b, lost = (np.stack([p[j] for p in parts]) for j in (0, 1, 2, 4))
    ll, took = (float(sum(p[j] for p in parts)) for j in (3, 5))
    if variance == "textbook":
        mass, mean, dev = s.sum(axis=0), a.sum(axis=0), b.sum(axis=0)
    elif full:
        mass = s.sum(axis=0)
        mean = (s[:, :, None] * a).sum(axis=0) / np.maximum(mass, 1e-300)[:, None]
        r = a - mean
        dev = (b + s[:, :, None, None] * r[:, :, :, None] * r[:, :, None, :]).sum(axis=0)
    else:
        mass, mean, dev = _merged(s, a, b)
    return mass, mean, dev, ll, lost.sum(axis=0), took


def fit_rows(features: DataFrame, k: int, shape: str = "diagonal", variance: str = "stable", seed: int = 0, max_iter: int = 100, tol: float = 0.0, model: Mixture | None = None, floor: float = 1e-12, **options) -> Mixture:
    """Full-data EM, the baseline, one job an iteration (few rows: a pass on the driver); k-means++ on rows unless a model is given.

    With ``variance="overlap"`` the rows are features and this is the features' EM for summaries too long for the driver.
    """
    return fit_rows_many(features, [(k, shape)], variance, seed, max_iter, tol, [model], floor, **options)[0][0]


def fit_rows_many(features: DataFrame, runs: list[tuple[int, str]], variance: str = "stable", seed: int = 0, max_iter: int = 100, tol: float = 0.0, models: list[Mixture | None] | None = None, floor: float = 1e-12, spread: Spread | None = None, **options) -> list[tuple[Mixture, float]]:
    """``fit_rows`` of several (k, shape), each with the steps it has alone: every pass over the rows makes one step of all that still
    iterate.  The seconds that come with a model are its part, by its share of the tasks' time, of the passes it took part in.

    All shapes are diagonal or spherical, or all are full.  ``spread``: the rows packed, which the caller keeps.
    """
    full = runs[0][1] == "full"
    if any((shape == "full") != full for _, shape in runs):
        raise ValueError("full covariances have passes of their own")
    own = Spread(packed(features)) if spread is None else spread
    began = time.time()
    kept = own.local(sum(k for k, _ in runs)) or own
    models = list(models or [None] * len(runs))
    took = np.full(len(runs), (time.time() - began) / len(runs))
    asked = sorted({k for (k, _), model in zip(runs, models, strict=True) if model is None})
    if asked:
        centres, seconds = kmeanspp_rows_many(features, asked, seed, kept=kept)
        x = centres[asked[0]]
        one = Mixture(np.ones(1), x[:1], np.ones((1, x.shape[1])))
        mass, _, dev, _ = row_step(kept, one, "stable")
        for i, (k, _) in enumerate(runs):
            if models[i] is None:
                x, took[i] = centres[k], seconds[k]
                models[i] = Mixture(np.full(len(x), 1 / len(x)), x, np.repeat(np.maximum(dev[0] / mass[0] / len(x), 1e-12)[None], len(x), axis=0))
    if full:
        models = [Mixture(m.weight, m.mean, np.stack([np.diag(v) for v in m.var])) if m.var.ndim == 2 else m for m in models]
    climbs, reaches = [_Climb(m, max_iter, tol) for m in models], [[REACH] for _ in runs]
    while on := [i for i, c in enumerate(climbs) if c.left > 0]:
        began = time.time()
        steps = row_steps(kept, [climbs[i].model for i in on], variance, full, [reaches[i] for i in on])
        for i, (mass, mean, dev, ll, _) in zip(on, steps, strict=True):
            climbs[i].take(ll / mass.sum(), finish(mass, mean, dev, runs[i][1], floor, **options), None)
        total = sum(s[4] for s in steps)
        took[on] += [(time.time() - began) * (s[4] / total if total > 0 else 1 / len(on)) for s in steps]
    if spread is None:
        own.batches.unpersist()
    return [(c.result(), float(s)) for c, s in zip(climbs, took, strict=True)]


def fit_features_many(spark, summaries: dict, runs: list[tuple]) -> list[tuple[Mixture, float]]:
    """Fits on summaries, each a task of its own: (name of its summary, function, options), where the function takes the summary's arrays
    and the options.  With each model come its seconds."""
    ship(spark)
    held = spark.sparkContext.broadcast(summaries)

    def run(part):
        for i, name, fit, more in part:
            t = time.perf_counter()
            yield i, fit(*held.value[name], **more), time.perf_counter() - t

    # the longest first, so that none of them begins last
    order = sorted(range(len(runs)), key=lambda i: -runs[i][2]["k"])
    got = spark.sparkContext.parallelize([(i, *runs[i]) for i in order], max(1, len(runs))).mapPartitions(run).collect()
    held.unpersist()
    return [(model, took) for _, model, took in sorted(got, key=lambda r: r[0])]


def fit_by_partition(features: DataFrame, k: int, cfg: TreeConfig = TreeConfig(), shape: str = "diagonal", max_iter: int = 50) -> DataFrame:
    """Each task fits k components to its own rows (through a tree, so memory is bounded) and sends them as features (w, m, q)."""

    def run(batches):
        tree = None
        for b in batches:
            if b.num_rows:
                m = _lists(b.column(1))
                tree = tree or FeatureTree(cfg, m.shape[1])
                tree.insert_batch(b.column(0).to_numpy(), m, _lists(b.column(2)))
        if tree is None:
            return
        w, m, q = tree.leaves()
        fit = fit_features(w, m, q, min(k, len(w)), shape, max_iter=max_iter)
        r, _ = e_step(fit, w, m, q)
        mass = r.T @ w
        use = mass > 0
        kind = pa.list_(pa.float64())
        own = m_step(w, m, q, r, "diagonal", 0.0)
        yield pa.RecordBatch.from_arrays([pa.array(mass[use]), pa.array(list(own.mean[use]), kind), pa.array(list(own.var[use] * mass[use, None]), kind)], ["w", "m", "q"])

    ship(features.sparkSession)
    return features.select("w", "m", "q").mapInArrow(run, "w double, m array<double>, q array<double>")


def assign(df: DataFrame, model: Mixture, output: str = "hard") -> DataFrame:
    """Rows (w, m, ...) with the log density and, by ``output``, the most likely component (hard) or all responsibilities (soft) too."""

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            r, ll = _responsibilities(model, _lists(b.column(b.schema.get_field_index("m"))))
            more = {"hard": [pa.array(r.argmax(axis=1), pa.int32())], "soft": [pa.array(list(r), pa.list_(pa.float64()))], "logpdf": []}[output]
            yield pa.RecordBatch.from_arrays([*b.columns, *more, pa.array(ll)], [*b.schema.names, *names, "logpdf"])

    ship(df.sparkSession)
    names, kinds = {"hard": (["comp"], "comp int, "), "soft": (["resp"], "resp array<double>, "), "logpdf": ([], "")}[output]
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in df.schema.fields)
    return df.mapInArrow(run, f"{fields}, {kinds}logpdf double")


def loglik(df: DataFrame, model: Mixture) -> DataFrame:
    """(rows, mean_ll): the weight of all rows and their mean log density."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                w = b.column(0).to_numpy()
                ll = _responsibilities(model, _lists(b.column(1)))[1]
                yield pa.RecordBatch.from_arrays([pa.array([w.sum()]), pa.array([float(w @ ll)])], ["w", "ll"])

    ship(df.sparkSession)
    sums = df.select("w", "m").mapInArrow(run, "w double, ll double")
    return sums.agg(F.sum("w").alias("rows"), (F.sum("ll") / F.sum("w")).alias("mean_ll"))


def mean_loglik(df: DataFrame, model: Mixture) -> float:
    return float(loglik(df, model).first()["mean_ll"])


def mean_logliks(kept: Spread, models: list[Mixture]) -> list[float]:
    """``mean_loglik`` of several models in one pass over packed rows."""

    def run(batches):
        for w, x, _ in _numbers(batches):
            yield pa.RecordBatch.from_arrays([pa.array([w.sum()]), pa.array([[float(w @ _responsibilities(m, x)[1]) for m in models]], pa.list_(pa.float64()))], ["w", "ll"])

    t = kept.scan(run, "w double, ll array<double>")
    return (_lists(t["ll"]).sum(axis=0) / t["w"].to_numpy().sum()).tolist()


def kmeans(w, m, q, k: int, seed: int = 0, max_iter: int = 100, weighted: bool = True) -> tuple[np.ndarray, float]:
    """Weighted Lloyd on features: (centres, exact cost of the rows behind them)."""
    use = w if weighted else np.ones_like(w)
    c = kmeanspp(use, m, k, seed)
    for _ in range(max_iter):
        at = _nearest(m, c)[0]
        new = np.array([(use[at == j, None] * m[at == j]).sum(axis=0) / use[at == j].sum() if (at == j).any() else c[j] for j in range(len(c))])
        if np.allclose(new, c):
            break
        c = new
    at = _nearest(m, c)[0]
    return c, float((w * ((m - c[at]) ** 2).sum(axis=1)).sum() + q.sum())


def agglomerate(w, m, q, k: int, kind: str = "D4", history: bool = False):
    """Cluster of each feature after merging nearest features (any distance as linkage) down to k; with ``history`` the merges (a, b, distance) too."""
    from stablecf.functions.measures import squared_np

    w, m, q = w.copy(), m.copy(), q.copy()
    n = len(w)
    label, alive, d = np.arange(n), np.ones(n, bool), np.full((n, n), np.inf)
    for i in range(n):
        d[i] = squared_np(w[i], m[i], q[i], w, m, q, kind)
        d[i, i] = np.inf
    near = d.argmin(axis=1) if n else np.zeros(0, int)  # each feature's nearest; only those a merge touches are looked up again
    merges = []
    for _ in range(max(0, n - k)):
        rows = np.flatnonzero(alive)
        i = int(rows[np.argmin(d[rows, near[rows]])])
        j = int(near[i])
        i, j = min(i, j), max(i, j)
        merges.append((i, j, float(np.sqrt(max(0.0, d[i, j])))))
        t = w[i] + w[j]
        delta = m[j] - m[i]
        q[i] += q[j] + w[i] * w[j] / t * delta**2
        m[i] += w[j] / t * delta
        w[i] = t
        label[label == j] = i
        alive[j] = False
        d[j, :] = d[:, j] = np.inf
        row = np.where(alive, squared_np(w[i], m[i], q[i], w, m, q, kind), np.inf)
        row[i] = np.inf
        d[i], d[:, i] = row, row
        stale = alive & ((near == i) | (near == j))
        stale[i] = True
        for x in np.flatnonzero(stale).tolist():
            near[x] = int(d[x].argmin())
        closer = alive & (row < d[np.arange(n), near])
        near[closer] = i
    return (np.unique(label, return_inverse=True)[1], merges) if history else np.unique(label, return_inverse=True)[1]
