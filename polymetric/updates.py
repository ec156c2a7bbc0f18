"""Updates of an index: inserts, deletes, compaction of leaves, drift of the normaliser. Each gives a new version; tables are never changed in place."""

from __future__ import annotations

import time
from collections.abc import Callable, Mapping
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.index import MultiMetricIndex, leaf_boxes, map_to_pivots
from polymetric.normalize import fit_normaliser
from polymetric.store import new_folder, written

#: Leaves of a group whose boxes a new row meets together, and what stands for a missing distance (distances aren't negative).
GROUP, MISSING = 64, -1.0


def place(index: MultiMetricIndex, rows: DataFrame) -> DataFrame:
    """New rows as objects of the index: mapped to its pivots, and sent to the leaf whose box is nearest (ties to the least
    leaf). Narrow: the boxes go to every task as arrays, and a row meets only those of groups that could hold a nearer one."""
    names = index.schema.names
    mapped = map_to_pivots(rows, index.schema, index.pivots)
    at = F.array(*(F.coalesce(F.col(f"v_{n}_0"), F.lit(MISSING)) for n in names))
    return mapped.withColumn("leaf_id", _nearest(index)(at)).select(*index.objects.columns)


def _nearest(index: MultiMetricIndex) -> Callable[[F.Column], F.Column]:
    """The leaf of the least gap, as an Arrow function over the distances to the first pivots. A missing distance, of a row or a box, has no
    gap. Groups are neighbours in the packing of the inner boxes; a group's gap is no larger than those of its boxes, rounding included."""
    names = index.schema.names
    by = {b["leaf_id"]: b for b in index.boxes}
    packed = [by[i] for i in index.inner.ids.tolist()]
    groups = [sorted(packed[i : i + GROUP], key=lambda b: b["leaf_id"]) for i in range(0, len(packed), GROUP)]
    sigma = [index.sigma[n] for n in names]
    ends = lambda k, none: [np.array([[none if b[f"{k}_{n}"] is None else b[f"{k}_{n}"] for n in names] for b in g], float) for g in groups]
    lo, hi, ids = ends("lo", -np.inf), ends("hi", np.inf), [np.array([b["leaf_id"] for b in g], np.int64) for g in groups]
    least, most = (np.array([f(x, axis=0) for x in xs]).reshape(len(groups), len(names)) for f, xs in ((np.min, lo), (np.max, hi)))

    def gaps(v: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        total = np.zeros((len(v), len(lo)))
        for j, s in enumerate(sigma):
            x = v[:, j, None]
            total += np.where(x == MISSING, 0.0, np.maximum(np.maximum(lo[:, j] - x, x - hi[:, j]), 0.0) / s)
        return np.where(np.isnan(total), np.inf, total)

    @F.pandas_udf("int")
    def nearest(vectors: pd.Series) -> pd.Series:
        v = np.array(vectors.tolist(), float).reshape(len(vectors), len(names))
        best, leaf = np.full(len(v), np.inf), np.full(len(v), np.iinfo(np.int64).max)
        far = gaps(v, least, most)

        def meet(g: int, at: np.ndarray) -> None:
            d = gaps(v[at], lo[g], hi[g])
            k = d.argmin(axis=1)  # the first of the least, so the least leaf
            d, i = d[np.arange(len(at)), k], ids[g][k]
            nearer = (d < best[at]) | (d == best[at]) & (i < leaf[at])
            best[at[nearer]], leaf[at[nearer]] = d[nearer], i[nearer]

        if len(v) and len(groups):
            own = far.argmin(axis=1)
            for g in np.unique(own):
                meet(g, np.flatnonzero(own == g))
            for g in range(len(groups)):
                if len(at := np.flatnonzero((far[:, g] <= best) & (own != g))):
                    meet(g, at)
        return pd.Series(leaf, dtype="int32") if len(groups) else pd.Series([None] * len(v), dtype="Int32")

    return nearest


def _version(index: MultiMetricIndex, objects: DataFrame, leaves: DataFrame, sigma: Mapping[str, float] | None = None) -> MultiMetricIndex:
    out = MultiMetricIndex(objects, leaves, index.schema, sigma or index.sigma, index.pivots)
    out.weights = dict(index.weights)
    return out


def widened(index: MultiMetricIndex, more: DataFrame) -> DataFrame:
    """The leaf boxes after ``more`` objects: only the new rows are read. The old boxes are on the driver, one row a leaf."""
    names = index.schema.names
    leaves = index.leaves.sparkSession.createDataFrame([tuple(b[c] for c in index.leaves.columns) for b in index.boxes], index.leaves.schema)
    both = leaves.unionByName(leaf_boxes(more, index.schema).select(*index.leaves.columns))
    return both.groupBy("leaf_id").agg(*(f(f"{k}_{n}").alias(f"{k}_{n}") for n in names for k, f in (("lo", F.min), ("hi", F.max))), F.sum("n_objects").alias("n_objects"))


def with_delta(index: MultiMetricIndex, delta: DataFrame) -> MultiMetricIndex:
    """The index with objects that are already placed."""
    return _version(index, index.objects.unionByName(delta.select(*index.objects.columns)), widened(index, delta))


def insert(index: MultiMetricIndex, rows: DataFrame) -> MultiMetricIndex:
    return with_delta(index, place(index, rows))


def delete(index: MultiMetricIndex, gone: DataFrame) -> MultiMetricIndex:
    """An anti join on ids; boxes and counts stay as they are, as bounds. Without exact counts a kNN seed may hold fewer
    than k objects; it then falls back to no bound."""
    return _version(index, index.objects.join(gone.select(index.schema.oid), index.schema.oid, "left_anti").select(*index.objects.columns), index.leaves)


def updated(index: MultiMetricIndex, gone: DataFrame, new: DataFrame) -> MultiMetricIndex:
    return insert(delete(index, gone), new)


def compact(index: MultiMetricIndex, most: int) -> MultiMetricIndex:
    """Tight boxes and exact counts, and leaves of over ``most`` objects split at the quantiles of their widest space."""
    names, exact = index.schema.names, leaf_boxes(index.objects, index.schema)
    big = [r.asDict() for r in exact.where(F.col("n_objects") > most).collect()]  # one row a leaf
    leaf, free = "leaf_id", max((b["leaf_id"] for b in index.boxes), default=0) + 1
    cuts = []
    for b in sorted(big, key=lambda b: b["leaf_id"]):
        wide = max(names, key=lambda n: ((b[f"hi_{n}"] - b[f"lo_{n}"]) / index.sigma[n], n))
        parts = -(-b["n_objects"] // most)
        at = index.objects.where(F.col("leaf_id") == b["leaf_id"]).agg(F.percentile_approx(f"v_{wide}_0", [i / parts for i in range(1, parts)])).first()[0]
        steps = " ".join(f"WHEN v_{wide}_0 <= {x!r}D THEN {free + i}" for i, x in enumerate(at))
        cuts.append(f"WHEN leaf_id = {b['leaf_id']} THEN CASE {steps} ELSE {b['leaf_id']} END")
        free += len(at)
    if cuts:
        leaf = f"CAST(CASE {' '.join(cuts)} ELSE leaf_id END AS INT)"
    objects = index.objects.withColumn("leaf_id", F.expr(leaf)).select(*index.objects.columns)
    return _version(index, objects, leaf_boxes(objects, index.schema))


def drift(index: MultiMetricIndex, df: DataFrame) -> dict[str, float]:
    """How far each normaliser moved: new sigma / old sigma."""
    now = fit_normaliser(df, index.schema)
    return {n: now[n] / index.sigma[n] for n in index.schema.names}


def refit(index: MultiMetricIndex, sigma: Mapping[str, float]) -> MultiMetricIndex:
    """Another normaliser on the same tables: stored distances are raw, so nothing is rebuilt."""
    return _version(index, index.objects, index.leaves, dict(sigma))


def update_cost(index: MultiMetricIndex, gone: DataFrame, new: DataFrame, q: Mapping[str, Any], w: Mapping[str, float], r: float) -> dict[str, float]:
    """Milliseconds an update, and the change of a range query's time after all of them. An update writes the ids that go and the new
    objects, mapped and sent to their leaves, beside the index, and widens the boxes."""
    def seconds(df: DataFrame) -> float:
        began = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        return time.perf_counter() - began

    folder = new_folder(index.objects.sparkSession)
    seconds(index.range(q, w, r))
    before, n = min(seconds(index.range(q, w, r)) for _ in range(3)), max(1, new.count())
    began = time.perf_counter()
    ids = written(gone.select(index.schema.oid), f"{folder}/gone")
    delta = written(place(index, new), f"{folder}/delta")
    after = with_delta(delete(index, ids), delta)
    cost = 1000 * (time.perf_counter() - began) / n
    seconds(after.range(q, w, r))
    return {"update_ms": cost, "query_delta_ms": 1000 * (min(seconds(after.range(q, w, r)) for _ in range(3)) - before)}
