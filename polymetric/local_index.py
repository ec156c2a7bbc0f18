"""Local indexes as tables keyed by (leaf_id, part): rectangles, vantage-point trees, gram postings, trees of covering balls.

Each is built in parallel over the leaves (a leaf of very many rows in several parts), written once, and has a range and a kNN
search that give candidate keys (leaf_id, oid); the combined distance is verified by the caller.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Mapping, Sequence
from functools import reduce
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from polymetric.distances import TWINS
from polymetric.index import PART_ROWS, MultiMetricIndex, knn_scan, range_scan
from polymetric.spaces import SLACK, MetricSpace, MultiMetricSchema, literal
from polymetric.store import new_folder, written

KEY = ["leaf_id", "part"]


def decompose(objects: DataFrame, space: MetricSpace, oid: str = "oid") -> DataFrame:
    """(leaf_id, part, oid, value) of one space: column pruning does the split. A leaf of over PART_ROWS rows has several parts,
    so that no task holds more; the counts are one row a leaf."""
    rows = objects.select("leaf_id", F.col(oid).alias("oid"), F.col(space.name).alias("value"))
    sizes = objects.groupBy("leaf_id").agg(F.ceil(F.count("*") / PART_ROWS).cast("int").alias("parts"))
    return rows.join(F.broadcast(sizes), "leaf_id").select("leaf_id", F.expr("pmod(xxhash64(oid), parts)").cast("int").alias("part"), "oid", "value")


def hidden_dimensions(df: DataFrame, schema: MultiMetricSchema | Sequence[MetricSpace], per_leaf: bool = False, n: int = 16, oid: str = "oid") -> DataFrame:
    """([leaf_id,] space, hd): mean^2 / (2 * variance) of distances to n anchors, in one pass for all spaces; 0 for a constant space."""
    spaces = list(getattr(schema, "spaces", schema))
    few = df.orderBy(F.expr(f"({oid} * 7919 + 104729) % 1000003"), oid).limit(n).select(*(F.col(s.name).alias(f"q_{s.name}") for s in spaces))
    d = df.join(F.broadcast(few)).select(*(["leaf_id"] if per_leaf else []), *(F.expr(s.sql(s.name, f"q_{s.name}")).alias(f"d_{s.name}") for s in spaces))
    grouped = d.groupBy("leaf_id") if per_leaf else d.groupBy()
    one = lambda c: F.coalesce(F.avg(c) ** 2 / F.nullif(2 * F.var_pop(c), F.lit(0.0)), F.lit(0.0))
    cells = ", ".join(f"'{s.name}', {s.name}" for s in spaces)
    row = grouped.agg(*(one(f"d_{s.name}").alias(s.name) for s in spaces))
    return row.selectExpr(*(["leaf_id"] if per_leaf else []), f"stack({len(spaces)}, {cells}) AS (space, hd)")


def hidden_dimension(df: DataFrame, space: MetricSpace, per_leaf: bool = False, n: int = 16, oid: str = "oid") -> DataFrame:
    return hidden_dimensions(df, [space], per_leaf, n, oid).drop("space")


def choose_index(space: MetricSpace, hd: float, threshold: float = 5.0) -> str:
    """Text goes to postings, spaces of high hidden dimension to vantage points, others to rectangles if they have coordinates."""
    if space.kind == "edit":
        return "inverted"
    return "mvp" if hd > threshold or space.kind not in _COORDINATES else "rtree"


_COORDINATES = ("l1", "l1v", "l2v", "linf")


class _Local:
    """What the indexes share: kNN as a range with a bound that k objects are sure to be within."""

    space: MetricSpace
    rows: DataFrame
    nodes: DataFrame  # (leaf_id, part, node, n, ...): the lowest nodes

    def kept(self, q: Any, t: float, leaves: Sequence[int] | None = None) -> DataFrame:
        """The lowest nodes that may hold an object within t."""
        raise NotImplementedError

    def far(self, q: Any) -> str:
        """An upper bound of the distance from q to any object of a node."""
        raise NotImplementedError

    def range(self, q: Any, t: float, leaves: Sequence[int] | None = None) -> DataFrame:
        raise NotImplementedError

    def knn(self, q: Any, k: int, leaves: Sequence[int] | None = None) -> DataFrame:
        """(leaf_id, oid, d) of the k nearest, ties to the least id: nodes in the order of their farthest point bound the k-th distance
        (at most k of them, as each holds an object), then a range search with the bound."""
        nodes = _within(self.nodes, leaves).select(F.expr(self.far(q)).alias("far"), "n")
        bound, total = float("inf"), 0
        for r in nodes.orderBy("far").limit(k).collect():
            total += r["n"]
            if total >= k:
                bound = r["far"]
                break
        return self.range(q, bound, leaves).orderBy("d", "oid").limit(k)


def _within(df: DataFrame, leaves: Sequence[int] | None) -> DataFrame:
    return df if leaves is None else df.where(F.col("leaf_id").isin([int(x) for x in leaves]))


class RTree(_Local):
    """Rectangles over all coordinates: each leaf is sorted and tiled by one coordinate after another into nodes of about ``cap`` objects;
    the tiles of each coordinate are the inner nodes above those of the next. Boxes are exact."""

    def __init__(self, objects: DataFrame, space: MetricSpace, cap: int = 64, dims: int = 4):
        if space.kind not in _COORDINATES:
            raise ValueError(f"{space.kind} has no coordinates")
        self.space, folder = space, new_folder(objects.sparkSession)
        rows = decompose(objects, space)
        self.scalar = space.kind == "l1"
        self.width = 1 if self.scalar else space.width or rows.select(F.max(F.size("value"))).first()[0] or 1
        sliced = min(dims, self.width)  # tiles of more coordinates would hold less than one object each
        rows = rows.withColumn("tiles", F.greatest(F.lit(1), F.ceil(F.pow(F.count("*").over(Window.partitionBy(*KEY)) / cap, F.lit(1 / sliced)))).cast("int"))
        path: list[str] = []
        for i in range(sliced):
            group = Window.partitionBy(*KEY, *path)
            rank = F.row_number().over(group.orderBy(F.expr(self._at("value", i)), "oid")) - 1
            rows = rows.withColumn(f"t{i}", F.floor(rank * F.col("tiles") / F.count("*").over(group)).cast("int"))
            path.append(f"t{i}")
        self.path = path
        self.rows = written(rows.drop("tiles"), f"{folder}/rows")
        boxes = [f(F.expr(self._at("value", i))).alias(f"{k}{i}") for i in range(self.width) for k, f in (("lo", F.min), ("hi", F.max))]
        self.nodes = written(self.rows.groupBy(*KEY, *path).agg(*boxes, F.count("*").alias("n")), f"{folder}/nodes")
        self.inner = [  # one level for each coordinate that was tiled, from the root's children down
            self.nodes.groupBy(*KEY, *path[: i + 1]).agg(*(f(f"{k}{j}").alias(f"{k}{j}") for j in range(self.width) for k, f in (("lo", F.min), ("hi", F.max)))) for i in range(sliced - 1)
        ]

    def _at(self, value: str, i: int) -> str:
        return value if self.scalar else f"{value}[{i}]"

    def _far(self, q: Any, side: str) -> str:
        q = [q] if self.scalar else q
        each = [f"greatest(0D, lo{i} - {x!r}D, {x!r}D - hi{i})" if side == "near" else f"greatest(abs({x!r}D - lo{i}), abs(hi{i} - {x!r}D))" for i, x in enumerate(map(float, q))]
        if self.space.kind == "l2v":
            return f"sqrt({' + '.join(f'pow({e}, 2)' for e in each)})"
        return each[0] if len(each) == 1 else f"greatest({', '.join(each)})" if self.space.kind == "linf" else " + ".join(each)

    def far(self, q: Any) -> str:
        return self._far(q, "far")

    def kept(self, q: Any, t: float, leaves: Sequence[int] | None = None) -> DataFrame:
        test = f"{self._far(q, 'near')} <= {t + SLACK!r}D" if t != float("inf") else "true"
        now = None
        for i, level in enumerate([*self.inner, self.nodes]):
            near = _within(level, leaves).where(test).select(*KEY, *self.path[: i + 1])
            now = near if now is None else near.join(now, [*KEY, *self.path[:i]], "left_semi")
        return now

    def range(self, q: Any, t: float, leaves: Sequence[int] | None = None) -> DataFrame:
        near = _within(self.rows, leaves).join(self.kept(q, t, leaves), [*KEY, *self.path], "left_semi").withColumn("d", F.expr(self.space.sql("value", literal(q))))
        return (near if t == float("inf") else near.where(F.col("d") <= t + SLACK)).select("leaf_id", "oid", "d")


def _distances(space: MetricSpace) -> Callable[[Any, Any], np.ndarray]:
    """Distances of many values to one, in numpy where the values are numbers."""
    fast = {"l1": lambda x, p: np.abs(x - p), "l1v": lambda x, p: np.abs(x - p).sum(axis=1), "l2v": lambda x, p: np.sqrt(((x - p) ** 2).sum(axis=1)), "linf": lambda x, p: np.abs(x - p).max(axis=1), "hamming": lambda x, p: (x != p).sum(axis=1).astype(float)}
    twin = TWINS[space.kind]
    return fast.get(space.kind) or (lambda x, p: np.array([twin(v, p) for v in x], float))


#: (members, their distances to the vantage points above, the constraints above: (vantage point, least, most distance))
_Cell = tuple[np.ndarray, np.ndarray, list[tuple[int, float, float]]]


def _vantage_cells(x: Any, far: Callable, order: int, cap: int, path_len: int) -> Iterable[_Cell]:
    """Multi-vantage-point tree: two vantage points a node, the second far from the first, and order * order shells by quantiles."""
    work: list[_Cell] = [(np.arange(len(x)), np.empty((len(x), 0)), [])]
    while work:
        at, path, above = work.pop()
        if len(at) <= cap:
            yield at, path, above
            continue
        d1 = far(x[at], x[at[0]])
        second = int(np.argmax(d1))
        d2 = far(x[at], x[at[second]])
        if not d1.max() > 0:  # all alike: nothing to split
            yield at, path, above
            continue
        path = np.column_stack([path, d1, d2])[:, :path_len]
        for one in np.array_split(np.argsort(d1, kind="stable"), order):
            for two in np.array_split(one[np.argsort(d2[one], kind="stable")], order):
                if len(two):
                    work.append((at[two], path[two], [*above, (int(at[0]), float(d1[two].min()), float(d1[two].max())), (int(at[second]), float(d2[two].min()), float(d2[two].max()))]))


def _ball_cells(x: Any, far: Callable, fan: int, cap: int, path_len: int) -> Iterable[_Cell]:
    """Tree of covering balls: each node's routers are far from each other, its members go to the nearest, and radii are exact."""
    work: list[_Cell] = [(np.arange(len(x)), np.empty((len(x), 0)), [])]
    while work:
        at, path, above = work.pop()
        if len(at) <= cap:
            yield at, path, above
            continue
        chosen, d = [0], [far(x[at], x[at[0]])]
        while len(chosen) < fan and (near := np.min(d, axis=0)).max() > 0:
            chosen.append(int(np.argmax(near)))
            d.append(far(x[at], x[at[chosen[-1]]]))
        if len(chosen) == 1:
            yield at, path, above
            continue
        best = np.argmin(d, axis=0)
        for k, c in enumerate(chosen):
            own = np.flatnonzero(best == k)
            work.append((at[own], np.column_stack([path[own], d[k][own]])[:, :path_len], [*above, (int(at[c]), 0.0, float(d[k][own].max()))]))


class MetricTree(_Local):
    """Trees over distances alone, built in numpy for each part of a leaf by recursion. A lowest node carries the constraints of all nodes
    above it, so a search tests a path from the root down and stops at the first that fails; its objects carry their distances
    to the vantage points on the path."""

    _KIND = {"mvp": _vantage_cells, "mtree": _ball_cells}

    def __init__(self, objects: DataFrame, space: MetricSpace, kind: str = "mvp", fan: int = 0, cap: int = 80, path_len: int = 4):
        self.space, cells, fan = space, self._KIND[kind], fan or {"mvp": 3, "mtree": 8}[kind]
        rows, folder = decompose(objects, space), new_folder(objects.sparkSession)
        value = rows.schema["value"].dataType.simpleString()
        far = _distances(space)

        def build(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
            group = group.sort_values("oid", kind="stable").reset_index(drop=True)
            x = np.array(group["value"].tolist(), dtype=object if value == "string" else None)
            out: dict[str, list] = {c: [] for c in ("node", "at", "n", "path", "above")}
            for node, (at, path, above) in enumerate(cells(x, far, fan, cap, path_len)):
                points = [{"vp": group["value"].iloc[v], "lo": lo, "hi": hi} for v, lo, hi in above]
                out["node"] += [node] * len(at)
                out["at"] += at.tolist()
                out["n"] += [len(at)] + [None] * (len(at) - 1)
                out["path"] += path.tolist()
                out["above"] += [points] + [None] * (len(at) - 1)
            taken = group.iloc[out["at"]]
            return pd.DataFrame({"leaf_id": key[0], "part": key[1], "node": out["node"], "oid": taken["oid"].to_numpy(), "value": taken["value"].to_numpy(), "n": pd.array(out["n"], "Int64"), "path": out["path"], "above": out["above"]})

        shape = f"leaf_id int, part int, node int, oid long, value {value}, n long, path array<double>, above array<struct<vp:{value},lo:double,hi:double>>"
        made = written(rows.withColumn("leaf_id", F.col("leaf_id").cast("int")).groupBy(*KEY).applyInPandas(build, shape), f"{folder}/tree")
        self.rows, self.nodes = made.drop("n", "above"), made.where("n IS NOT NULL").select(*KEY, "node", "n", "above")

    def far(self, q: Any) -> str:
        d = self.space.sql("x.vp", literal(q))
        return f"coalesce(array_min(transform(above, x -> {d} + x.hi)), CAST('Infinity' AS DOUBLE))"

    def kept(self, q: Any, t: float, leaves: Sequence[int] | None = None) -> DataFrame:
        nodes = _within(self.nodes, leaves)
        if t == float("inf"):
            return nodes
        d = self.space.sql("x.vp", literal(q))
        return nodes.where(F.expr(f"forall(above, x -> {d} BETWEEN x.lo - {t + SLACK!r}D AND x.hi + {t + SLACK!r}D)"))

    def range(self, q: Any, t: float, leaves: Sequence[int] | None = None) -> DataFrame:
        d = self.space.sql("x.vp", literal(q))
        kept = self.kept(q, t, leaves).select(*KEY, "node", F.expr(f"transform(above, x -> {d})").alias("own"))
        near = _within(self.rows, leaves).join(kept, [*KEY, "node"])
        if t != float("inf"):  # the objects' stored distances, before any real one
            near = near.where(F.expr(f"forall(zip_with(path, slice(own, 1, size(path)), (x, y) -> abs(x - y)), x -> x <= {t + SLACK!r}D)"))
        near = near.withColumn("d", F.expr(self.space.sql("value", literal(q))))
        return (near if t == float("inf") else near.where(F.col("d") <= t + SLACK)).select("leaf_id", "oid", "d")


def MvpTree(objects: DataFrame, space: MetricSpace, order: int = 3, cap: int = 80, path_len: int = 4) -> MetricTree:  # noqa: N802
    return MetricTree(objects, space, "mvp", order, cap, path_len)


def MTree(objects: DataFrame, space: MetricSpace, fan: int = 8, cap: int = 80, path_len: int = 4) -> MetricTree:  # noqa: N802
    return MetricTree(objects, space, "mtree", fan, cap, path_len)


class InvertedIndex(_Local):
    """Grams of texts with their counts, and lengths: an edit within t keeps max(length) - g + 1 - g * t grams."""

    def __init__(self, objects: DataFrame, space: MetricSpace, g: int = 2):
        self.space, self.g, folder = space, g, new_folder(objects.sparkSession)
        self.rows = written(decompose(objects, space).withColumn("len", F.length("value")), f"{folder}/rows")
        grams = F.expr(f"transform(sequence(1, greatest(1, length(value) - {g} + 1)), i -> substring(value, i, {g}))")
        self.postings = written(self.rows.select("leaf_id", "oid", F.explode(grams).alias("gram")).groupBy("gram", "leaf_id", "oid").agg(F.count("*").alias("cnt")), f"{folder}/postings")

    def range(self, q: str, t: float, leaves: Sequence[int] | None = None) -> DataFrame:
        """The query's grams are a literal list; texts too short for the count bound come in by length."""
        g = self.g
        if t == float("inf"):
            return _within(self.rows, leaves).select("leaf_id", "oid", F.expr(self.space.sql("value", literal(q))).alias("d"))
        mine: dict[str, int] = {}
        for i in range(max(1, len(q) - g + 1)):
            mine[q[i : i + g]] = mine.get(q[i : i + g], 0) + 1
        have = F.create_map(*(F.lit(x) for kv in mine.items() for x in kv))
        shared = _within(self.postings, leaves).where(F.col("gram").isin(*mine)).groupBy("leaf_id", "oid").agg(F.sum(F.least("cnt", have[F.col("gram")])).alias("common"))
        k = int(t + SLACK)
        sized = _within(self.rows, leaves).where(F.abs(F.col("len") - len(q)) <= k).join(shared, ["leaf_id", "oid"], "left")
        need = F.greatest("len", F.lit(len(q))) - g + 1 - g * k
        near = sized.where(F.coalesce("common", F.lit(0)) >= need).withColumn("d", F.expr(f"levenshtein(value, {literal(q)}, {k})"))
        return near.where("d >= 0").select("leaf_id", "oid", F.col("d").cast("double").alias("d"))

    def knn(self, q: str, k: int, leaves: Sequence[int] | None = None) -> DataFrame:
        """The radius doubles until k texts are found, then they are ranked; a radius beyond all lengths finds every text."""
        t, most = 1, max(len(q), _within(self.rows, leaves).agg(F.max("len")).first()[0] or 0)
        while t < most and self.range(q, t, leaves).limit(k).count() < k:
            t *= 2
        return self.range(q, t, leaves).orderBy("d", "oid").limit(k)


_KINDS: dict[str, Callable[..., Any]] = {"rtree": RTree, "mvp": MvpTree, "mtree": MTree, "inverted": InvertedIndex}


def register_index(kind: str, builder: Callable[..., Any]) -> None:
    """builder(objects, space) gives an object with range(q, t, leaves) and knn(q, k, leaves) -> DataFrame(leaf_id, oid, d)."""
    _KINDS[kind] = builder


class Forest:
    """Local indexes for each space, chosen by the hidden dimension of each leaf's own data (scope "leaf") or of all ("global"). kinds
    replaces the choice: {"low": "mtree"} or {"high": "mtree"} for the ablations."""

    def __init__(self, index: MultiMetricIndex, kinds: Mapping[str, str] | None = None, scope: str = "leaf", threshold: float = 5.0):
        self.index, kinds = index, kinds or {}
        ids = [b["leaf_id"] for b in index.boxes]
        numbers = [s for s in index.schema.spaces if s.kind != "edit"]
        made = index.__dict__.setdefault("_local", {})  # parts are shared by the forests of an index
        if ("hd", scope) not in made:
            rows = hidden_dimensions(index.objects, numbers, scope == "leaf").collect() if numbers else []  # one row a leaf and space
            made["hd", scope] = {(r["leaf_id"] if scope == "leaf" else None, r["space"]): r["hd"] for r in rows}
        self.chosen: dict[str, dict[str, list[int]]] = {}
        for s in index.schema.spaces:
            for leaf in ids:
                kind = choose_index(s, made["hd", scope].get((leaf if scope == "leaf" else None, s.name), 0.0), threshold)
                kind = {"rtree": kinds.get("low", kind), "mvp": kinds.get("high", kind)}.get(kind, kind)
                self.chosen.setdefault(s.name, {}).setdefault(kind, []).append(leaf)
        self.parts: dict[str, list[tuple[list[int], Any]]] = {}
        for s in index.schema.spaces:
            for kind, leaves in self.chosen[s.name].items():
                key = (s.name, kind, tuple(leaves))
                if key not in made:
                    own = index.objects if len(leaves) == len(ids) else index.objects.where(F.col("leaf_id").isin(leaves))
                    made[key] = _KINDS[kind](own, s)
                self.parts.setdefault(s.name, []).append((leaves, made[key]))

    def _each(self, name: str, leaves: Sequence[int]) -> Iterable[tuple[list[int], Any]]:
        for own, part in self.parts[name]:
            if both := sorted(set(own) & set(leaves)):
                yield both, part

    def candidates(self, q: Mapping[str, Any], w: Mapping[str, float], r: float) -> DataFrame:
        """(leaf_id, oid) in kept leaves and near in one active space at least, each at r / (sum of weights)."""
        t, index = r / sum(w.values()), self.index
        leaves = index.keep_leaves(index.query_pivots(q), w, r)
        found = [part.range(q[s.name], t * index.sigma[s.name], own).select("leaf_id", "oid") for s in index.schema.active(w) for own, part in self._each(s.name, leaves)]
        return reduce(DataFrame.unionByName, found).distinct() if found else index.objects.select("leaf_id", F.col(index.schema.oid).alias("oid")).limit(0)

    def range(self, q: Mapping[str, Any], w: Mapping[str, float], r: float) -> DataFrame:
        """Candidates meet their objects leaf by leaf, then the combined distance is verified."""
        index, leaves = self.index, self.index.keep_leaves(self.index.query_pivots(q), w, r)
        keys = self.candidates(q, w, r).withColumnRenamed("oid", index.schema.oid)
        return range_scan(_within(index.objects, leaves).join(keys, ["leaf_id", index.schema.oid], "left_semi"), index.schema, q, w, r, index.sigma)

    def bound(self, q: Mapping[str, Any], w: Mapping[str, float], k: int) -> float:
        """The k-th combined distance among each space's k nearest in the leaf whose centre is nearest."""
        index = self.index
        leaves = index.seed_leaves(index.query_pivots(q), w, k)
        found = [part.knn(q[s.name], k, own).select("leaf_id", "oid") for s in index.schema.active(w) for own, part in self._each(s.name, leaves)]
        keys = reduce(DataFrame.unionByName, found).distinct().withColumnRenamed("oid", index.schema.oid)
        rows = knn_scan(_within(index.objects, leaves).join(keys, ["leaf_id", index.schema.oid], "left_semi"), index.schema, q, w, k, index.sigma).select("dist").collect()
        return rows[-1]["dist"] if len(rows) == k else float("inf")

    def knn(self, q: Mapping[str, Any], w: Mapping[str, float], k: int) -> DataFrame:
        bound = self.bound(q, w, k)
        inside = self.index.objects if bound == float("inf") else self.range(q, w, bound + SLACK)
        return knn_scan(inside, self.index.schema, q, w, k, self.index.sigma)
