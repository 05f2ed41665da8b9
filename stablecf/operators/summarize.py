"""Distributed summaries: cells in the JVM, a tree per task, then merge rounds that shuffle features only.

A summary is a table (w, m, q, threshold).  Of stable trees these are weight, means and squared deviations; of
classic trees they are the classic feature as it is: n, linear sums and, as the only element of q, the sum of squares.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.functions.features import stable_agg
from stablecf.operators.tree import FeatureTree, TreeConfig, classic_as_stable
from stablecf.sources.session import ship

SCHEMA = "w double, m array<double>, q array<double>, threshold double"
#: Cells a summary works on, as a multiple of its leaf cap, and the grids tried: numbers of cells on an axis.
CELLS_A_LEAF = 8
GRIDS = tuple(sorted({max(1, round(2 ** (i / 2))) for i in range(33)}))


def materialize(df: DataFrame) -> DataFrame:
    """Cuts the lineage in the shared folder, where the session names one; a cache otherwise."""
    sc = df.sparkSession.sparkContext
    folder = df.sparkSession.conf.get("spark.checkpoint.dir", None)
    if folder and not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(folder)
    return df.checkpoint() if sc._jsc.sc().getCheckpointDir().isDefined() else df.persist()


def _lists(col) -> np.ndarray:
    col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
    return col.flatten().to_numpy(zero_copy_only=False).reshape(len(col), -1)


def _checked(df: DataFrame, axes: list[Column], weight: Column | None) -> tuple[DataFrame, Column]:
    cols = [a.cast("double").alias(f"_x{i}") for i, a in enumerate(axes)]
    out = df.select("*", (weight.cast("double") if weight is not None else F.lit(1.0)).alias("_w"), *cols)
    ok = F.coalesce((F.col("_w") > 0) & (F.col("_w") < float("inf")), F.lit(False))
    for i in range(len(axes)):
        x = F.col(f"_x{i}")
        ok = ok & x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    return out, ok


def project(df: DataFrame, axes: list[Column], weight: Column | None = None, on_invalid: str = "drop") -> DataFrame:
    """(w, m, q) of rows.  A row with a null, NaN or infinite coordinate, or a weight that is not positive and finite, is left out
    (``drop``) or ends the job when it is read (``fail``); ``invalid_rows`` gives them."""
    rows, ok = _checked(df, axes, weight)
    if on_invalid == "fail":
        ok = F.when(ok, True).otherwise(F.raise_error(F.lit("a row has an invalid coordinate or weight")).cast("boolean"))
    d = len(axes)
    return rows.where(ok).select(F.col("_w").alias("w"), F.array(*[F.col(f"_x{i}") for i in range(d)]).alias("m"), F.array(*[F.lit(0.0)] * d).alias("q"))


def merge_equal(rows: DataFrame) -> DataFrame:
    """Equal rows of ``project`` as one row with their weights' sum: nothing is rounded or left out.  Where that saves less than
    about half of the rows, they come back as they are, without a shuffle: an estimate of the different rows decides this only."""
    d = _dims(rows)
    n = rows.agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct(F.xxhash64("m"), 0.05).alias("u")).first()
    if not d or 2 * n["u"] > n["n"]:
        return rows
    x = [f"x{i}" for i in range(d)]  # numbers are faster keys than arrays
    merged = rows.select("w", *[F.col("m")[i].alias(c) for i, c in enumerate(x)]).groupBy(*x).agg(F.sum("w").alias("w"))
    merged = merged.select("w", F.array(*x).alias("m"), F.array(*[F.lit(0.0)] * d).alias("q"))
    merged = merged.coalesce(rows.sparkSession.sparkContext.defaultParallelism).persist()  # a cached shuffle keeps all its small partitions
    merged.count()
    return merged


def invalid_rows(df: DataFrame, axes: list[Column], weight: Column | None = None) -> DataFrame:
    """The rows, as they are, that ``project`` leaves out."""
    rows, ok = _checked(df, axes, weight)
    return rows.where(~ok).select(*df.columns)


def _dims(df: DataFrame) -> int:
    row = df.select(F.size("m").alias("d")).first()
    return row["d"] if row else 0


def _table(w: np.ndarray, a: np.ndarray, b: np.ndarray, threshold: float) -> pa.RecordBatch:
    kind = pa.list_(pa.float64())
    return pa.RecordBatch.from_arrays([pa.array(w), pa.array(list(a), kind), pa.array(list(b), kind), pa.array(np.full(len(w), threshold))], ["w", "m", "q", "threshold"])


def _trees(cfg: TreeConfig, classic_in: bool = False, stats: bool = False):
    def run(batches):
        tree, held, rows = None, [], 0

        def flush() -> None:
            if held:
                w, a, b = (np.concatenate(x) for x in zip(*held, strict=True))
                held.clear()
                (tree.insert_raw if classic_in else tree.insert_batch)(w, a, b)

        for x in batches:
            if not x.num_rows:
                continue
            a, b = _lists(x.column(1)), _lists(x.column(2))
            if classic_in:
                b = np.concatenate([b[:, :1], np.zeros((len(b), a.shape[1] - 1))], axis=1)
            tree = tree or FeatureTree(cfg, a.shape[1])
            if x.num_columns > 3:  # entries of other trees: the union's threshold is at least each of theirs
                tree.threshold = max(tree.threshold, float(x.column(3).to_numpy().max()))
            held.append((x.column(0).to_numpy(), a, b))
            rows += x.num_rows
            if sum(len(h[0]) for h in held) >= max(8 * cfg.leaf_cap, 20_000):  # long enough to judge a first threshold
                flush()
        if tree is not None:
            flush()
            if stats:
                yield pa.RecordBatch.from_pylist([{"rows_in": rows, **tree.stats()}])
            else:
                w, a, b = tree.raw_leaves()
                yield _table(w, a, b[:, :1] if cfg.form == "classic" else tree.leaves()[2], tree.threshold)

    return run


def summarize_local(features: DataFrame, cfg: TreeConfig, classic_in: bool = False) -> DataFrame:
    """One tree per task over the rows of its partition."""
    ship(features.sparkSession)
    return features.select("w", "m", "q", *(["threshold"] if "threshold" in features.columns else [])).mapInArrow(_trees(cfg, classic_in), SCHEMA)


def tree_statistics(features: DataFrame, cfg: TreeConfig) -> DataFrame:
    """Per task: rows in, entries, height, rebuilds, threshold and distance evaluations of its tree."""
    ship(features.sparkSession)
    return features.select("w", "m", "q").mapInArrow(_trees(cfg, stats=True), "rows_in long, entries long, height long, rebuilds long, threshold double, evaluations long")


def z_order(cf: DataFrame, classic: bool, bits: int = 8) -> Column:
    """Interleaved bits of the quantised centres (up to seven axes), so that ranges of it are compact regions."""
    d = min(_dims(cf), 7)
    at = [F.col("m")[i] / F.col("w") if classic else F.col("m")[i] for i in range(d)]
    ends = cf.agg(*[f(x).alias(f"{n}{i}") for i, x in enumerate(at) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    cell = [F.floor((x - ends[f"lo{i}"]) * float(((1 << bits) - 1) / max(ends[f"hi{i}"] - ends[f"lo{i}"], 1e-300))).cast("long") if ends and ends[f"lo{i}"] is not None else F.lit(0).cast("long") for i, x in enumerate(at)]
    key = F.lit(0).cast("long")
    for b in range(bits - 1, -1, -1):
        for c in cell:
            key = key * 2 + F.pmod(F.shiftright(c, b), F.lit(2))
    return key


def grid_width(features: DataFrame, cells: int, sample: int = 50_000) -> list[float] | None:
    """Cell widths that leave about ``cells`` occupied cells among a bounded sample of rows, in steps of ``GRIDS``.

    The widths alone depend on the sample; every row goes into its cell.  None: there are no rows, or so few that cells gain nothing.
    """
    n = features.count()
    if n <= cells:
        return None
    some = features if n <= sample else features.sample(min(1.0, 1.1 * sample / n), seed=1)
    x = _lists(some.select("m").limit(sample).toArrow()["m"])
    span = np.maximum(x.max(axis=0) - x.min(axis=0), 1e-300)
    best = 1
    for g in GRIDS:
        code = np.zeros(len(x), np.uint64)
        for c in np.floor(x * (g / span)).astype(np.int64).astype(np.uint64).T:
            code = (code ^ c) * np.uint64(0x9E3779B97F4A7C15)
            code ^= code >> np.uint64(29)
        if len(np.unique(code)) > min(cells, 0.7 * len(x)):
            break
        best = g
    return (span / best).tolist()


def features_to_cells(features: DataFrame, width: list[float], form: str = "stable") -> DataFrame:
    """Features (w, m, q) merged by grid cell, in the JVM with map-side sums.

    Stable: deviations are summed around the cell's own centre, known without a pass, so nothing larger than a cell cancels.
    Classic: plain sums, with their cancellation; q then holds the sum of squares.
    """
    d = range(len(width))
    cell = [F.floor(F.col("m")[i] / width[i]) for i in d]
    rows = features.select("w", "m", "q", *[c.alias(f"c{i}") for i, c in enumerate(cell)])
    keys, w = [f"c{i}" for i in d], F.col("w")
    total = F.sum("w").alias("w")
    if form == "classic":
        sums = [F.sum(w * F.col("m")[i]).alias(f"s{i}") for i in d]
        square = F.sum(reduce(Column.__add__, [F.col("q")[i] + w * F.col("m")[i] * F.col("m")[i] for i in d])).alias("ss")
        return rows.groupBy(*keys).agg(total, *sums, square).select("w", F.array(*[F.col(f"s{i}") for i in d]).alias("m"), F.array("ss").alias("q"))
    r = [F.col("m")[i] - (F.col(f"c{i}") + 0.5) * width[i] for i in d]
    sums = [F.sum(w * r[i]).alias(f"s{i}") for i in d] + [F.sum(F.col("q")[i] + w * r[i] * r[i]).alias(f"q{i}") for i in d]
    out = rows.groupBy(*keys).agg(total, *sums)
    m = [(F.col(f"c{i}") + 0.5) * width[i] + F.col(f"s{i}") / w for i in d]
    return out.select("w", F.array(*m).alias("m"), F.array(*[F.greatest(F.lit(0.0), F.col(f"q{i}") - F.col(f"s{i}") * F.col(f"s{i}") / w) for i in d]).alias("q"))


def _centred(cells: DataFrame, classic: bool) -> DataFrame:
    """Classic cells as (w, mean, q) around which wider cells are summed again: q holds what their squares exceed those of the mean."""
    if not classic:
        return cells
    m = F.transform("m", lambda v: v / F.col("w"))
    q = F.col("q")[0] - F.aggregate(m, F.lit(0.0), lambda s, v: s + v * v) * F.col("w")
    return cells.select("w", m.alias("m"), F.transform(m, lambda v: q / F.size("m")).alias("q"))


def summarize(features: DataFrame, cfg: TreeConfig = TreeConfig(), fan_in: int = 16, parts: int | None = None, compact: bool = True, regions: bool = False) -> DataFrame:
    """At most ``cfg.leaf_cap`` features of all rows.

    ``compact``: rows are first merged to about ``CELLS_A_LEAF`` cells a leaf in the JVM, and trees are built on the cells;
    which share the leaves by ranges of the Z-order of their centres (``parts=1``: one tree).  Without it every task of the scan
    builds a tree of its rows, and trees of one round feed those of the next, dealt by such ranges, until one is left, which
    sees at most ``fan_in * leaf_cap`` features.  ``regions``: the rows themselves are dealt by ranges of the Z-order to trees that
    share the leaves, so the trees' precision is that of all sums, as without ``compact``, and no merge is due.
    """
    classic = cfg.form == "classic"
    if regions:
        parts = parts or max(1, min(32, cfg.leaf_cap // 256))
        if parts > 1 and _dims(features):
            return summarize_local(features.repartitionByRange(parts, z_order(features, False)), replace(cfg, leaf_cap=cfg.leaf_cap // parts))
        compact = False
    width = grid_width(features, CELLS_A_LEAF * cfg.leaf_cap) if compact else None
    if width is not None:
        raw, most = classic, CELLS_A_LEAF * cfg.leaf_cap
        out = materialize(features_to_cells(features, width, cfg.form))
        while (n := out.count()) > 2 * most:  # the table has more cells than its sample: cells are features, and merge to wider ones
            wider = max(1.2, (n / most) ** (1 / len(width)))
            width = [v * wider for v in width]
            out = materialize(features_to_cells(_centred(out, classic), width, cfg.form))
        # ranges of the Z-order are disjoint regions of about equally many cells: each gets its share of the leaves, and no merge is due
        parts = parts or max(1, min(16, cfg.leaf_cap // 512, n // 2048))
        if parts == 1:
            return summarize_local(out.coalesce(1), cfg, raw)
        return summarize_local(out.repartitionByRange(parts, z_order(out, classic)), replace(cfg, leaf_cap=max(1, cfg.leaf_cap // parts)), raw)
    parts = parts or max(1, min(features.sparkSession.sparkContext.defaultParallelism, 1 << 16))
    out = summarize_local(features.coalesce(parts), cfg)
    while parts > 1:
        parts = -(-parts // fan_in)
        out = materialize(out)
        out = summarize_local(out.repartitionByRange(parts, z_order(out, classic)) if parts > 1 else out.coalesce(1), cfg, classic)
    return out


def summarize_by(df: DataFrame, keys: list[str], axes: list[Column], cfg: TreeConfig = TreeConfig(), salts: int = 1) -> DataFrame:
    """A summary per group: ``keys``, w, m, q, threshold.  ``salts`` deals a heavy group to that many trees, whose entries a second tree merges."""
    d = len(axes)
    ship(df.sparkSession)
    rows = df.select(*keys, *[a.cast("double").alias(f"x{i}") for i, a in enumerate(axes)])
    ok = reduce(Column.__and__, [F.col(f"x{i}").isNotNull() & ~F.isnan(f"x{i}") & (F.abs(F.col(f"x{i}")) < float("inf")) for i in range(d)])
    rows = rows.where(ok).select(*keys, F.lit(1.0).alias("w"), F.array(*[F.col(f"x{i}") for i in range(d)]).alias("m"), F.array(*[F.lit(0.0)] * d).alias("q"), F.lit(0.0).alias("threshold"))
    fields = [f for f in rows.schema.fields if f.name in keys]
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in fields) + ", " + SCHEMA

    def merge(t: pa.Table) -> pa.Table:
        tree = FeatureTree(cfg, d)
        tree.threshold = float(t["threshold"].to_numpy().max())
        tree.insert_batch(t["w"].to_numpy(), _lists(t["m"]), _lists(t["q"]))
        out = _table(*tree.leaves(), tree.threshold)
        head = [pa.array([t[k][0].as_py()] * out.num_rows, t.schema.field(k).type) for k in keys]
        return pa.Table.from_arrays([*head, *out.columns], [*keys, *out.schema.names])

    if salts > 1:
        salted = rows.withColumn("_salt", F.pmod(F.xxhash64("m"), F.lit(salts)))
        rows = salted.groupBy(*keys, "_salt").applyInArrow(lambda t: merge(t.drop_columns(["_salt"])), schema)
    return rows.groupBy(*keys).applyInArrow(merge, schema)


def compact_cells(df: DataFrame, axes: list[Column], width: list[float]) -> DataFrame:
    """Grid cells as features, built in the JVM with map-side aggregation; legal input of a tree."""
    keys = [F.floor(a / w).cast("long").alias(f"cell{i}") for i, (a, w) in enumerate(zip(axes, width, strict=True))]
    cols = df.select(*keys, *[a.cast("double").alias(f"x{i}") for i, a in enumerate(axes)])
    return stable_agg(cols, [F.col(f"x{i}") for i in range(len(axes))], [f"cell{i}" for i in range(len(axes))])


def collect(cf: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A summary (bounded by its cap) as numpy arrays, in its own algebra; entries are sorted, so runs agree."""
    t = cf.select("w", "m", "q").toArrow()
    w, m, q = t["w"].to_numpy(), _lists(t["m"]), _lists(t["q"])
    order = np.lexsort((*m.T, w))
    return w[order], m[order], q[order]


def collect_stable(cf: DataFrame, form: str = "stable") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same as (w, means, q), whatever the form."""
    w, m, q = collect(cf)
    return classic_as_stable(w, m, q) if form == "classic" else (w, m, q)


def restore(spark: SparkSession, path: str) -> DataFrame:
    """A stored summary: features of several tables or days merge like any others."""
    return spark.read.schema(SCHEMA).parquet(path)
