"""Height-balanced feature tree in numpy; lives inside one task, only its leaf entries leave it."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from stablecf.functions.measures import squared_classic_np, squared_np


@dataclass(frozen=True)
class TreeConfig:
    """``strict`` inserts row by row; otherwise a block of rows is routed at once and only rows that no entry absorbs go one by one.

    ``q``: "vector" keeps deviations per axis, "scalar" their sum (in the first axis).  ``growth`` is the quantile of the
    nearest absorption values that a rebuild takes as the next threshold.  ``absorb_guard`` caps the distance of the centres
    of what is absorbed, as an average radius lets a heavy entry swallow a far point.
    """

    distance: str = "D4"
    absorption: str = "R"
    leaf_cap: int = 5000
    branching: int = 50
    leaf_size: int = 50
    form: str = "stable"
    precision: str = "f64"
    q: str = "vector"
    strict: bool = False
    growth: float = 0.25
    absorb_guard: float | None = None


BLOCK = 4096


class _Node:
    def __init__(self, cap: int, d: int, leaf: bool, dt) -> None:
        self.leaf, self.n = leaf, 0
        self.w, self.a, self.b = np.zeros(cap + 1), np.zeros((cap + 1, d), dt), np.zeros((cap + 1, d), dt)
        self.kids: list[_Node] = []


class FeatureTree:
    """Entries hold (w, mean, q) or, in classic form, (n, ls, ss in the first axis); one code, two algebras."""

    def __init__(self, cfg: TreeConfig, d: int) -> None:
        self.cfg, self.d, self.threshold = cfg, d, 0.0
        self.dt = np.float32 if cfg.precision == "f32" else np.float64
        self.rebuilds = self.evaluations = 0
        self._clear()

    def _clear(self) -> None:
        self.root, self.entries = _Node(self.cfg.leaf_size, self.d, True, self.dt), 0

    def _sq(self, node: _Node, w, a, b, kind: str) -> np.ndarray:
        self.evaluations += node.n
        n = node.n
        if self.cfg.form == "classic":
            return squared_classic_np(w, a, b[0], node.w[:n], node.a[:n], node.b[:n, 0], kind)
        return squared_np(w, a, b, node.w[:n], node.a[:n], node.b[:n], kind)

    def _merge_into(self, node: _Node, i: int, w, a, b) -> None:
        if self.cfg.form == "classic":
            node.a[i] += a
            node.b[i] += b
        else:
            t = node.w[i] + w
            delta = a - node.a[i]
            f = w / t
            if self.cfg.q == "scalar":
                node.b[i, 0] += b[0] + node.w[i] * f * (delta @ delta)
            else:
                node.b[i] += b + node.w[i] * f * delta * delta
            node.a[i] += f * delta
        node.w[i] += w

    def insert(self, w: float, a: np.ndarray, b: np.ndarray) -> None:
        node, path = self.root, []
        while not node.leaf:
            i = int(np.argmin(self._sq(node, w, a, b, self.cfg.distance)))
            self._merge_into(node, i, w, a, b)
            path.append((node, i))
            node = node.kids[i]
        if node.n:
            i = int(np.argmin(self._sq(node, w, a, b, self.cfg.distance)))
            one = _Node(0, self.d, True, self.dt)
            one.n, one.w, one.a, one.b = 1, node.w[i : i + 1], node.a[i : i + 1], node.b[i : i + 1]
            if self._sq(one, w, a, b, self.cfg.absorption)[0] <= self.threshold**2 and self._near_enough(one, w, a):
                self._merge_into(node, i, w, a, b)
                return
        self._put(node, w, a, b, None)
        self.entries += 1
        while node.n > (self.cfg.leaf_size if node.leaf else self.cfg.branching):
            left, right = self._split(node)
            if path:
                up, i = path.pop()
                self._set(up, i, left)
                self._put(up, *self._sum(right), right)
                node = up
            else:
                self.root = _Node(self.cfg.branching, self.d, False, self.dt)
                for x in (left, right):
                    self._put(self.root, *self._sum(x), x)
                break
        if self.entries > self.cfg.leaf_cap:
            self.rebuild()

    def _near_enough(self, one: _Node, w, a) -> bool:
        if self.cfg.absorb_guard is None:
            return True
        d = one.a[0] / one.w[0] - a / w if self.cfg.form == "classic" else one.a[0] - a
        return float(d @ d) <= self.cfg.absorb_guard**2

    def insert_batch(self, w: np.ndarray, m: np.ndarray, q: np.ndarray) -> None:
        """Features (w, m, q); a classic tree takes them as classic ones, with the sums of squares that this brings."""
        m, q = np.asarray(m, self.dt), np.asarray(q, self.dt)
        if self.cfg.form == "classic":
            ss = (q.sum(axis=1) + (m * m).sum(axis=1) * w.astype(self.dt)).astype(self.dt)
            m, q = m * w[:, None].astype(self.dt), np.zeros_like(q)
            q[:, 0] = ss
        elif self.cfg.q == "scalar":
            total = q.sum(axis=1)
            q = np.zeros_like(q)
            q[:, 0] = total
        self.insert_raw(w, m, q)

    def insert_raw(self, w: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
        """Features in the tree's own algebra, in blocks."""
        w, a, b = np.asarray(w, float), np.asarray(a, self.dt), np.asarray(b, self.dt)
        if not self.cfg.strict and not self.entries and not self.threshold and len(w) > self.cfg.leaf_cap:
            self.threshold = first_threshold(a / w[:, None] if self.cfg.form == "classic" else a, self.cfg.leaf_cap)
        plain = self.cfg.strict or self.cfg.form == "classic" or self.cfg.q == "scalar" or self.cfg.absorb_guard is not None or self.cfg.absorption == "D1"
        for i in range(0, len(w), BLOCK):
            z = slice(i, i + BLOCK)
            left = np.arange(len(w[z])) if plain or not self.threshold else self._absorb_block(w[z], a[z], b[z])
            for j in left.tolist():
                self.insert(float(w[i + j]), a[i + j], b[i + j])

    def _many(self, w, a, b, node: _Node, kind: str) -> np.ndarray:
        """Squared stable measure of rows to the children of a node: rows x children."""
        self.evaluations += len(w) * node.n
        W, d = node.w[: node.n], a[:, None, :] - node.a[None, : node.n, :]
        if kind == "D1":
            return np.abs(d).sum(axis=2) ** 2
        d2 = (d * d).sum(axis=2)
        if kind in ("D0", "E"):
            return d2
        g = w[:, None] * W / (w[:, None] + W) * d2
        if kind == "D4":
            return g
        Q, t = node.b[: node.n].sum(axis=1), w[:, None] + W
        if kind == "D2":
            return (b.sum(axis=1) / w)[:, None] + Q / W + d2
        s = b.sum(axis=1)[:, None] + Q + g
        return s / t if kind == "R" else 2 * s / np.maximum(t - 1, 1e-300)

    def _absorb_block(self, w, a, b) -> np.ndarray:
        """Routes rows level by level and merges those that their entries absorb, all of an entry's at once; returns the others.

        A group is taken only if the entry that results passes the test too, so that no entry outgrows the threshold.
        """
        missed, limit = [], self.threshold**2
        stack = [(self.root, np.arange(len(w)), [])]
        while stack:
            node, rows, path = stack.pop()
            if not node.n:
                missed.append(rows)
                continue
            at = np.argmin(self._many(w[rows], a[rows], b[rows], node, self.cfg.distance), axis=1)
            if not node.leaf:
                order = np.argsort(at, kind="stable")
                kids, first = np.unique(at[order], return_index=True)
                for i, r in zip(kids.tolist(), np.split(rows[order], first[1:]), strict=True):
                    stack.append((node.kids[i], r, [*path, (node, i)]))
                continue
            own = self._one_to_one(w[rows], a[rows], b[rows], node, at)
            pass_, missed_here = rows[own <= limit], rows[own > limit]
            missed.append(missed_here)
            at = at[own <= limit]
            if not len(pass_):
                continue
            order = np.argsort(at, kind="stable")
            pass_, at = pass_[order], at[order]
            to, first = np.unique(at, return_index=True)
            uw, ua, ub = self._union(w[pass_], a[pass_], b[pass_], first)
            ok = self._one_to_one(uw, ua, ub, node, to) <= limit
            size = np.diff(np.append(first, len(pass_)))
            missed.append(pass_[~np.repeat(ok, size)])
            if not ok.any():
                continue
            for i, x, y, z in zip(to[ok].tolist(), uw[ok].tolist(), ua[ok], ub[ok], strict=True):
                self._merge_into(node, i, x, y, z)
            if path:
                tw, ta, tb = self._union(uw[ok], ua[ok], ub[ok], np.zeros(1, int))
                for up, i in path:
                    self._merge_into(up, i, float(tw[0]), ta[0], tb[0])
        return np.sort(np.concatenate(missed))

    def _one_to_one(self, w, a, b, node: _Node, at: np.ndarray) -> np.ndarray:
        """Squared absorption value of each row with its own entry."""
        kind, W, d = self.cfg.absorption, node.w[at], a - node.a[at]
        d2 = (d * d).sum(axis=1)
        if kind in ("D0", "E"):
            return d2
        g = w * W / (w + W) * d2
        if kind == "D4":
            return g
        Q = node.b[at].sum(axis=1)
        if kind == "D2":
            return b.sum(axis=1) / w + Q / W + d2
        s, t = b.sum(axis=1) + Q + g, w + W
        return s / t if kind == "R" else 2 * s / np.maximum(t - 1, 1e-300)

    def _union(self, w, a, b, first: np.ndarray):
        """Merged features of consecutive groups that start at ``first``, around each group's own mean."""
        size = np.diff(np.append(first, len(w)))
        t = np.add.reduceat(w, first)
        base = np.repeat(a[first].astype(float), size, axis=0)
        shift = np.add.reduceat(w[:, None] * (a - base), first, axis=0) / t[:, None]
        mean = a[first] + shift
        r = a - np.repeat(mean, size, axis=0)
        return t, mean.astype(self.dt), np.add.reduceat(b + w[:, None] * r * r, first, axis=0).astype(self.dt)

    def _put(self, node, w, a, b, kid) -> None:
        node.w[node.n], node.a[node.n], node.b[node.n] = w, a, b
        node.n += 1
        if kid is not None:
            node.kids.append(kid)

    def _sum(self, node):
        t = _Node(0, self.d, True, self.dt)
        t.w[0], t.a[0], t.b[0] = node.w[0], node.a[0], node.b[0]
        for i in range(1, node.n):
            self._merge_into(t, 0, node.w[i], node.a[i], node.b[i])
        return t.w[0], t.a[0], t.b[0]

    def _set(self, up, i, kid) -> None:
        up.w[i], up.a[i], up.b[i] = self._sum(kid)
        up.kids[i] = kid

    def _split(self, node):
        d = np.stack([self._sq(node, node.w[i], node.a[i], node.b[i], self.cfg.distance) for i in range(node.n)])
        s, t = np.unravel_index(int(np.argmax(np.nan_to_num(d))), d.shape)
        if s == t:
            t = (s + 1) % node.n
        to_left = d[s] <= d[t]
        to_left[s], to_left[t] = True, False
        out = []
        for side in (to_left, ~to_left):
            x = _Node(self.cfg.leaf_size if node.leaf else self.cfg.branching, self.d, node.leaf, self.dt)
            for i in np.flatnonzero(side):
                self._put(x, node.w[i], node.a[i], node.b[i], node.kids[i] if node.kids else None)
            out.append(x)
        return out

    def _leaf_nodes(self):
        stack = [self.root]
        while stack:
            x = stack.pop()
            if x.leaf:
                yield x
            else:
                stack.extend(x.kids)

    def _nearest(self) -> np.ndarray:
        """Absorption value of each entry with its nearest in its leaf; across leaves where every leaf holds one."""
        near = []
        for x in self._leaf_nodes():
            for i in range(x.n if x.n > 1 else 0):
                v = self._sq(x, x.w[i], x.a[i], x.b[i], self.cfg.absorption)
                v[i] = np.inf
                near.append(np.sqrt(max(0.0, float(np.nanmin(v)))))
        if near or self.entries < 2:
            return np.array(near)
        every = _Node(self.entries, self.d, True, self.dt)
        w, a, b = self._raw()
        every.n, every.w[: len(w)], every.a[: len(w)], every.b[: len(w)] = len(w), w, a, b
        for i in range(0, len(w), max(1, len(w) // 512)):
            v = self._sq(every, w[i], a[i], b[i], self.cfg.absorption)
            v[i] = np.inf
            near.append(np.sqrt(max(0.0, float(np.nanmin(v)))))
        return np.array(near)

    def rebuild(self, threshold: float | None = None) -> None:
        """A larger threshold, from the nearest absorption values of entries unless given, and the entries inserted anew."""
        if threshold is None:
            near = self._nearest()
            grow = float(np.quantile(near, self.cfg.growth)) if len(near) else 0.0
            threshold = max(1.1 * self.threshold, grow, 1e-12)
        self.threshold = threshold
        w, a, b = self._raw()
        self.rebuilds += 1
        self._clear()
        for x in zip(w.tolist(), a, b, strict=True):
            self.insert(*x)

    def _raw(self):
        parts = [(x.w[: x.n], x.a[: x.n], x.b[: x.n]) for x in self._leaf_nodes() if x.n]
        if not parts:
            return np.zeros(0), np.zeros((0, self.d), self.dt), np.zeros((0, self.d), self.dt)
        return tuple(np.concatenate(p) for p in zip(*parts, strict=True))

    def raw_leaves(self):
        """Leaf entries in the tree's own algebra: (w, means, q), or (n, linear sums, sum of squares in the first axis)."""
        w, a, b = self._raw()
        return w, a.astype(float), b.astype(float)

    def leaves(self):
        """(w, means, q) of the leaf entries; of a classic or scalar tree q is the total deviation, spread over the axes."""
        w, a, b = self.raw_leaves()
        if self.cfg.form == "classic":
            return classic_as_stable(w, a, b)
        if self.cfg.q == "scalar":
            b = np.repeat(b[:, :1] / self.d, self.d, axis=1)
        return w, a, b

    def check_invariants(self) -> dict[str, bool]:
        """Whether all leaves are equally deep, nodes within their capacities, inner features the sums of their children and entries within the threshold."""
        depth, caps, sums = set(), True, True
        stack = [(self.root, 1)]
        while stack:
            x, h = stack.pop()
            caps &= x.n <= (self.cfg.leaf_size if x.leaf else self.cfg.branching)
            if x.leaf:
                depth.add(h)
                continue
            for i, kid in enumerate(x.kids):
                w, a, b = self._sum(kid)
                sums &= bool(np.isclose(w, x.w[i]) and np.allclose(a, x.a[i], rtol=1e-6, atol=1e-6) and np.allclose(b, x.b[i], rtol=1e-4, atol=1e-6))
                stack.append((kid, h + 1))
        w, _, q = self.leaves()
        within = True
        if self.cfg.form == "stable" and self.cfg.absorption == "R":
            within = bool((q.sum(axis=1) / w <= self.threshold**2 * (1 + 1e-9) + 1e-12).all())
        return {"one_depth": len(depth) == 1, "capacities": caps, "sums": sums, "within_threshold": within, "cap": self.entries <= self.cfg.leaf_cap}

    def stats(self) -> dict:
        h, x = 1, self.root
        while not x.leaf:
            h, x = h + 1, x.kids[0]
        return {"entries": self.entries, "height": h, "rebuilds": self.rebuilds, "threshold": self.threshold, "evaluations": self.evaluations}


def first_threshold(x: np.ndarray, cap: int) -> float:
    """Radius at which points fill about 0.8 ``cap`` entries: that of the square cells, halved from the widest extent down, that leave so many occupied."""
    x = np.asarray(x, float) - np.asarray(x, float).min(axis=0)
    lo, hi = 0.0, float(x.max())
    if hi <= 0:
        return 0.0
    for _ in range(24):
        g = (lo + hi) / 2
        code = np.zeros(len(x), np.uint64)
        for c in np.floor(x / g).astype(np.int64).astype(np.uint64).T:
            code = (code ^ c) * np.uint64(0x9E3779B97F4A7C15)
            code ^= code >> np.uint64(29)
        n = len(np.unique(code))
        lo, hi = (g, hi) if n > 0.8 * cap else (lo, g)
        if 0.7 * cap <= n <= 0.8 * cap:
            break
    return hi * float(np.sqrt(x.shape[1] / 12))


def classic_as_stable(n: np.ndarray, ls: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Classic features as (w, mean, q): what cancelled stays lost; the scalar deviation is spread evenly over the axes."""
    d = ls.shape[1]
    q = b[:, 0] - (ls * ls).sum(axis=1) / n
    return n, ls / n[:, None], np.repeat((q / d)[:, None], d, axis=1)
