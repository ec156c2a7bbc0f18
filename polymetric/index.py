"""The two-layer index as tables: objects in leaves of a tree over pivot distances, with stored vantage distances, and the leaves' boxes."""

from __future__ import annotations

import json
from collections.abc import Mapping, Sequence
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from polymetric import bounds, cells, rstar
from polymetric.normalize import fit_normaliser
from polymetric.spaces import SLACK, MetricSpace, MultiMetricSchema, literal, mm_distance, query_row

#: Rows of the sample from which the tree is built on the driver: at least so many, and SAMPLE_PER_LEAF for each leaf.
SAMPLE, SAMPLE_PER_LEAF = 20_000, 16
#: Objects a leaf should have, and the depths between which the number of leaves follows them: 32 to 16,384 leaves.
LEAF_ROWS, LEAST_DEPTH, MOST_DEPTH = 4_000, 5, 14
#: Objects of a file, and of a leaf that one task of a local index holds.
FILE_ROWS, PART_ROWS = 1_000_000, 200_000
#: Up to this depth a row's leaf is found by nested CASE, deeper by a walk over two literal arrays.
CASE_DEPTH = 7
#: Rows inserted into an R*-tree.
RSTAR_ROWS = 2_000
#: Entries of an inner box.
FAN = 8
#: Queries of a block (up to as many are broadcast), rows of a strip, and partitions for the cells of a grid.
FEW_QUERIES, STRIP_ROWS, MOST_CELLS = 1_000, 20_000, 100_000


def select_pivots(df: DataFrame, schema: MultiMetricSchema, per_space: int = 1, method: str = "farthest", given: Sequence[int] | None = None) -> dict[str, list[dict[str, Any]]]:
    """Pivots of each space as (oid, value). farthest: from the least id, the farthest object, then the one farthest
    from all so far (ties to the least id), one aggregation over all spaces a step; random: by an arithmetic shuffle; given: by id."""
    oid = schema.oid
    if given is not None or method == "random":
        rows = [query_row(df, schema, i) | {"oid": i} for i in given] if given is not None else [r.asDict() | {"oid": r[oid]} for r in df.orderBy(F.expr(f"({oid} * 6007 + 1) % 1000033"), oid).limit(per_space).collect()]
        return {s.name: [{"oid": r["oid"], "value": r[s.name]} for r in (rows[k % len(rows) :] + rows)[:per_space]] for k, s in enumerate(schema.spaces)}
    start = df.orderBy(oid).limit(1).first()
    out: dict[str, list[dict[str, Any]]] = {s.name: [] for s in schema.spaces}
    for _ in range(per_space):
        best = []
        for s in schema.spaces:
            seen = [p["value"] for p in out[s.name]] or [start[s.name]]
            d = [s.sql(s.name, literal(v)) for v in seen]
            near = d[0] if len(d) == 1 else f"least({', '.join(d)})"
            best.append(F.expr(f"max_by(struct({oid} AS oid, {s.name} AS value), struct(round({near}, 9) AS d, -{oid} AS o))").alias(s.name))
        row = df.agg(*best).first()
        for s in schema.spaces:
            out[s.name].append(row[s.name].asDict())
    return out


def map_to_pivots(df: DataFrame, schema: MultiMetricSchema, pivots: Mapping[str, list[dict[str, Any]]]) -> DataFrame:
    """Adds raw distances v_<space>_<j> to the pivots: narrow, one select, weights play no part."""
    return df.select("*", *(F.expr(s.sql(s.name, literal(p["value"]))).alias(f"v_{s.name}_{j}") for s in schema.spaces for j, p in enumerate(pivots[s.name])))


def kd_leaf(schema: MultiMetricSchema, splits: Sequence[tuple[int, int, float]]) -> str:
    """The leaf of a row as nested CASE: pure SQL, no join."""
    by = {k: (axis, cut) for k, axis, cut in splits}

    def node(k: int) -> str:
        if k not in by:
            return str(k)
        axis, cut = by[k]
        return f"CASE WHEN v_{schema.names[axis]}_0 <= {cut!r}D THEN {node(2 * k + 1)} ELSE {node(2 * k + 2)} END"

    if max((k for k, *_ in splits), default=0) < 2 ** (CASE_DEPTH + 1):
        return node(0)
    most = max(by) + 1
    axes = ", ".join(str(by[k][0] + 1 if k in by else 0) for k in range(most))
    cuts = ", ".join(f"{by[k][1]!r}D" if k in by else "0D" for k in range(most))
    values = ", ".join(f"v_{n}_0" for n in schema.names)
    down = f"IF(k >= {most} OR element_at(array({axes}), k + 1) = 0, k, 2 * k + IF(element_at(array({values}), element_at(array({axes}), k + 1)) <= element_at(array({cuts}), k + 1), 1, 2))"
    return f"aggregate(sequence(0, {most.bit_length()}), 0, (k, x) -> {down})"


def leaf_boxes(objects: DataFrame, schema: MultiMetricSchema) -> DataFrame:
    """(leaf_id, lo_<space>, hi_<space>, n_objects): exact boxes of the routed rows."""
    return objects.groupBy("leaf_id").agg(*(f(f"v_{n}_0").alias(f"{k}_{n}") for n in schema.names for k, f in (("lo", F.min), ("hi", F.max))), F.count("*").alias("n_objects"))


class InnerBoxes:
    """The leaves' boxes and, above them, boxes of FAN neighbours each, up to one root: a walk skips whole subtrees. All on the driver,
    as arrays; the neighbours are next to each other in a packing by the axis of the widest spread."""

    def __init__(self, boxes: Sequence[Mapping[str, Any]], names: Sequence[str]):
        self.ids = np.array([b["leaf_id"] for b in boxes], np.int64)
        lo, hi = (np.array([[b[f"{k}_{n}"] for n in names] for b in boxes], float).reshape(len(boxes), len(names)) for k in ("lo", "hi"))
        spread = np.where((s := (lo + hi).std(axis=0)) > 0, s, 1.0) if len(boxes) else 1.0
        order = np.array([], np.int64) if not len(boxes) else np.concatenate(_tiles((lo + hi) / spread, np.arange(len(boxes))))
        self.ids, lo, hi = self.ids[order], lo[order], hi[order]
        self.levels = [(lo, hi)]
        while len(lo) > 1:
            starts = np.arange(0, len(lo), FAN)
            lo, hi = np.minimum.reduceat(lo, starts), np.maximum.reduceat(hi, starts)
            self.levels.append((lo, hi))

    def walk(self, keep: Any) -> tuple[list[int], int]:
        """Leaves that ``keep(lo, hi)`` holds on to, as do all boxes above them, and the number of boxes tested."""
        alive, tested = np.arange(len(self.levels[-1][0])), 0
        for depth in range(len(self.levels) - 1, -1, -1):
            lo, hi = self.levels[depth]
            tested += len(alive)
            alive = alive[keep(lo[alive], hi[alive])]
            if depth:
                below = (alive[:, None] * FAN + np.arange(FAN)).ravel()
                alive = below[below < len(self.levels[depth - 1][0])]
        return sorted(self.ids[alive].tolist()), tested


def _tiles(x: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
    if len(at) <= FAN:
        return [at]
    at = at[np.argsort(x[at, int(np.argmax(x[at].std(axis=0)))], kind="stable")]
    cut = max(FAN, FAN ** round(np.log(len(at) / 2) / np.log(FAN)))
    cut = len(at) // 2 if cut >= len(at) else cut
    cut = max(FAN, cut // FAN * FAN)
    return _tiles(x, at[:cut]) + _tiles(x, at[cut:]) if cut < len(at) else [at]


class MultiMetricIndex:
    """objects: the rows with vantage distances and leaf_id; leaves: their boxes, a small table."""

    def __init__(self, objects: DataFrame, leaves: DataFrame, schema: MultiMetricSchema, sigma: Mapping[str, float], pivots: Mapping[str, list[dict[str, Any]]]):
        self.objects, self.leaves, self.schema, self.sigma, self.pivots = objects, leaves, schema, dict(sigma), pivots
        self.boxes = [r.asDict() for r in leaves.collect()]  # one row a leaf
        self.inner = InnerBoxes(self.boxes, schema.names)
        self.weights: dict[str, dict[str, float]] = {}

    @staticmethod
    def build(df: DataFrame, schema: MultiMetricSchema, depth: int | None = None, vantages: int = 2, tree: str = "kd", sigma: Mapping[str, float] | None = None, pivots: Mapping | None = None) -> MultiMetricIndex:
        """Normaliser and pivots (one pass each), a tree from a bounded sample, then every row is routed to a leaf. Without a depth the
        number of leaves follows that of the rows."""
        sigma = dict(sigma or fit_normaliser(df, schema))
        pivots = pivots or select_pivots(df, schema, vantages)
        mapped = map_to_pivots(df, schema, pivots)
        oid = schema.oid
        if depth is None:
            depth = min(MOST_DEPTH, max(LEAST_DEPTH, (df.count() // LEAF_ROWS).bit_length()))
        most = max(SAMPLE, SAMPLE_PER_LEAF << depth)
        few = mapped.select(oid, *(f"v_{n}_0" for n in schema.names)).orderBy(F.expr(f"({oid} * 31 + 7) % 1000003"), oid).limit(most).toPandas()
        x = few[[f"v_{n}_0" for n in schema.names]].to_numpy(float) / np.array([sigma[n] for n in schema.names])
        if tree == "kd":
            splits = [(k, axis, cut * sigma[schema.names[axis]]) for k, axis, cut in rstar.kd_splits(x, depth)]
            objects = mapped.withColumn("leaf_id", F.expr(f"CAST({kd_leaf(schema, splits)} AS INT)"))
        else:
            objects = mapped.withColumn("leaf_id", _nearest_box(mapped, schema, sigma, x, max(2, len(x) >> depth), tree))
        return MultiMetricIndex(objects, leaf_boxes(objects, schema), schema, sigma, pivots)

    def save(self, path: str) -> MultiMetricIndex:
        """Objects by leaf directory (a leaf list prunes the scan), leaves beside them, and a manifest with all settings; gives the index
        as :meth:`load` reads it. A leaf of many rows is written by several tasks."""
        spark, schema = self.objects.sparkSession, self.schema
        sizes = {b["leaf_id"]: b["n_objects"] for b in self.boxes}
        files = max((-(-n // FILE_ROWS) for n in sizes.values()), default=1)
        part = F.expr(f"pmod(xxhash64({schema.oid}), {files})")
        dealt = self.objects.repartition(min(len(sizes) * files, MOST_CELLS) or 1, "leaf_id", part)
        dealt.sortWithinPartitions("leaf_id", f"v_{schema.names[0]}_0").write.mode("overwrite").partitionBy("leaf_id").parquet(f"{path}/objects")
        self.leaves.coalesce(1).write.mode("overwrite").parquet(f"{path}/leaves")
        kept = {
            "oid": schema.oid, "spaces": [[s.name, s.kind, s.width] for s in schema.spaces], "sigma": self.sigma, "pivots": self.pivots, "weights": self.weights,
            "objects": self.objects.schema.jsonValue(), "leaves": self.leaves.schema.jsonValue(),
        }
        spark.createDataFrame([(json.dumps(kept),)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")
        return MultiMetricIndex.load(spark, path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> MultiMetricIndex:
        """A saved index, from its path alone: nothing is computed, and queries read only the leaves that they keep."""
        kept = json.loads(spark.read.text(f"{path}/manifest").first()[0])
        schema = MultiMetricSchema(tuple(MetricSpace(n, k, w) for n, k, w in kept["spaces"]), kept["oid"])
        read = lambda name: spark.read.schema(StructType.fromJson(kept[name])).parquet(f"{path}/{name}")
        out = MultiMetricIndex(read("objects"), read("leaves"), schema, kept["sigma"], kept["pivots"])
        out.weights = kept["weights"]
        return out

    def bind(self, q: Mapping[str, Any] | int) -> Mapping[str, Any]:
        return query_row(self.objects, self.schema, q) if isinstance(q, int) else q

    def query_pivots(self, q: Mapping[str, Any]) -> dict[str, list[float]]:
        return {s.name: [s.between(q[s.name], p["value"]) for p in self.pivots[s.name]] for s in self.schema.spaces}

    def keep_leaves(self, a: Mapping[str, list[float]], w: Mapping[str, float], r: float, rule: str = "weighted_sum") -> list[int]:
        return self.walk(a, w, r, rule)[0]

    def walk(self, a: Mapping[str, list[float]], w: Mapping[str, float], r: float, rule: str = "weighted_sum") -> tuple[list[int], int]:
        """(leaves kept, boxes tested) from the root down. A rule that drops an inner box would drop each leaf in it, as a box's gap is
        no larger than those of the boxes inside. pigeonhole: some space alone is within r / (sum of weights)."""
        if rule == "uniform_all" and sum(w.values()) < 1:
            rule = "weighted_sum"
        active = [i for i, n in enumerate(self.schema.names) if w[n] > 0]
        names = [self.schema.names[i] for i in active]
        at, by, weight = (np.array(x, float) for x in ([a[n][0] for n in names], [self.sigma[n] for n in names], [w[n] for n in names]))

        def keep(lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
            gaps = np.clip(np.maximum(lo[:, active] - at, at - hi[:, active]), 0, None) / by
            if rule == "weighted_sum":
                return gaps @ weight <= r + SLACK
            if rule == "scaled_any":
                return (gaps * weight <= r + SLACK).all(axis=1)
            if rule == "uniform_all":
                return (gaps <= r + SLACK).any(axis=1)
            if rule == "pigeonhole":
                return (gaps <= r / weight.sum() + SLACK).any(axis=1)
            return np.ones(len(gaps), bool)

        return self.inner.walk(keep) if self.boxes else ([], 0)

    def candidates(self, q: Mapping[str, Any], w: Mapping[str, float], r: float, prune: str = "weighted_sum", local: str = "sum+staged") -> DataFrame:
        """Objects of the kept leaves that pass the local tests: one scan, no shuffle; leaves prune directories, ranges skip row groups."""
        a = self.query_pivots(q)
        df = self.objects.where(F.col("leaf_id").isin(self.keep_leaves(a, w, r, prune)))
        if "sum" in local:
            df = df.where(bounds.implied_ranges(a, w, self.sigma, r)).where(bounds.pivot_sum(a, w, self.sigma, r))
        if "staged" in local:
            df = df.where(bounds.staged(self.schema, q, w, self.sigma, bounds.pivot_lows(a, w), f"{r!r}D"))
        if "pigeonhole" in local:
            df = df.where(bounds.pigeonhole(self.schema, q, w, self.sigma, r))
        return df

    def range(self, q: Mapping[str, Any] | int, w: Any = None, r: float = 1.0, prune: str = "weighted_sum", local: str = "sum+staged") -> DataFrame:
        """Exact: (oid, dist, the objects' columns) within r."""
        q, w = self.bind(q), self.schema.weights(w)
        return range_scan(self.candidates(q, w, r, prune, local), self.schema, q, w, r, self.sigma)

    def seed_leaves(self, a: Mapping[str, list[float]], w: Mapping[str, float], k: int, n: int = 1, centre: str = "midpoint") -> list[int]:
        """Leaves by the nearness of their centre, until k objects and n leaves are reached."""
        medoids = self.medoids() if centre == "medoid" else {}

        def far(b: dict) -> float:
            if centre == "medoid":
                return sum(w[m] * abs(medoids[b["leaf_id"]][m] - v[0]) / self.sigma[m] for m, v in a.items())
            if centre == "mindist":
                return sum(w[m] * max(0.0, b[f"lo_{m}"] - v[0], v[0] - b[f"hi_{m}"]) / self.sigma[m] for m, v in a.items())
            return sum(w[m] * abs((b[f"lo_{m}"] + b[f"hi_{m}"]) / 2 - v[0]) / self.sigma[m] for m, v in a.items())
        out, total = [], 0
        for b in sorted(self.boxes, key=lambda b: (far(b), b["leaf_id"])):
            if total >= k and len(out) >= n:
                break
            out.append(b["leaf_id"])
            total += b["n_objects"]
        return out

    def medoids(self) -> dict[int, dict[str, float]]:
        """Pivot distances of each leaf's object that is nearest to its box's middle; found once, one row a leaf."""
        if not hasattr(self, "_medoids"):
            names = self.schema.names
            off = " + ".join(f"abs(v_{n}_0 - (lo_{n} + hi_{n}) / 2) / {self.sigma[n]!r}D" for n in names)
            joined = self.objects.join(F.broadcast(self.leaves), "leaf_id") if len(self.boxes) <= 100_000 else self.objects.join(self.leaves, "leaf_id")
            best = joined.groupBy("leaf_id").agg(F.min_by(F.struct(*(F.col(f"v_{n}_0").alias(n) for n in names)), F.struct(F.expr(off), self.schema.oid)).alias("m"))
            self._medoids = {r["leaf_id"]: r["m"].asDict() for r in best.collect()}
        return self._medoids

    def seed_bound(self, q: Mapping[str, Any], w: Mapping[str, float], k: int, seeds: int = 1, centre: str = "midpoint", seed: str = "exact") -> float:
        """The k-th distance within the seed leaves; any k objects bound the true one. per_space: only each space's k nearest are verified."""
        df = self.objects.where(F.col("leaf_id").isin(self.seed_leaves(self.query_pivots(q), w, k, seeds, centre)))
        if seed == "per_space":
            parts = [df.orderBy(F.expr(s.sql(s.name, literal(q[s.name]))), self.schema.oid).limit(k) for s in self.schema.active(w)]
            df = parts[0]
            for p in parts[1:]:
                df = df.unionByName(p)
            df = df.dropDuplicates([self.schema.oid])
        rows = knn_scan(df, self.schema, q, w, k, self.sigma).select("dist").collect()
        return max(r["dist"] for r in rows) if len(rows) >= k else float("inf")

    def knn(self, q: Mapping[str, Any] | int, w: Any = None, k: int = 10, seeds: int = 1, centre: str = "midpoint", seed: str = "exact", prune: str = "weighted_sum") -> DataFrame:
        """Exact: a bound from the seed leaves, then a range query with it, then the k best by (distance, id)."""
        q, w = self.bind(q), self.schema.weights(w)
        bound = self.seed_bound(q, w, k, seeds, centre, seed)
        df = self.objects if bound == float("inf") else self.candidates(q, w, bound + SLACK, prune)
        return knn_scan(df, self.schema, q, w, k, self.sigma)


def _nearest_box(mapped: DataFrame, schema: MultiMetricSchema, sigma: Mapping[str, float], x: np.ndarray, most: int, tree: str) -> F.Column:
    """Routes rows to the least enlarged box of a packed or an R*-tree, by an Arrow function over the vantage columns. Insertion into an
    R*-tree is slow, so its tree is made from RSTAR_ROWS of the sample, with as many leaves."""
    if tree == "str":
        groups = rstar.str_pack(x, most)
    else:
        few = x[: max(RSTAR_ROWS, 4)]
        t = rstar.RStarTree(x.shape[1], max(4, most * len(few) // max(1, len(x))))
        for v in few:
            t.insert(v)
        groups = [np.array(n.kids) for n in t.leaves()]
    lo, hi = np.array([g.min(axis=0) for g in groups]), np.array([g.max(axis=0) for g in groups])

    @F.pandas_udf("int")
    def route(vectors: pd.Series) -> pd.Series:
        v = np.array(vectors.tolist()).reshape(len(vectors), len(lo[0]))
        best, leaf = np.full(len(v), np.inf), np.zeros(len(v), np.int32)
        for k in range(len(lo)):  # a box at a time against the whole batch
            grown = np.clip(np.maximum(lo[k] - v, v - hi[k]), 0, None).sum(axis=1)
            nearer = grown < best - 1e-12
            best, leaf = np.where(nearer, grown, best), np.where(nearer, np.int32(k), leaf)
        return pd.Series(leaf, dtype="int32")

    return route(F.array(*(F.col(f"v_{n}_0") / sigma[n] for n in schema.names)))


def range_scan(df: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], r: float, sigma: Mapping[str, float]) -> DataFrame:
    """Brute force, and the verification of the indexed path."""
    return df.withColumn("dist", F.expr(mm_distance(schema, q, w, sigma))).where(F.col("dist") <= F.lit(r))


def knn_scan(df: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], k: int, sigma: Mapping[str, float]) -> DataFrame:
    return df.withColumn("dist", F.expr(mm_distance(schema, q, w, sigma))).orderBy("dist", schema.oid).limit(k)


def met(df: DataFrame, queries: DataFrame, schema: MultiMetricSchema) -> DataFrame:
    """(qid, q_<space>) of a stated query set beside all rows (oid, <space>). Few queries are broadcast; more meet the rows in a grid of
    (block of queries, strip of rows) cells, so no cell and no broadcast grows with the data."""
    qs = queries.select(F.col(schema.oid).alias("qid"), *(F.col(n).alias(f"q_{n}") for n in schema.names))
    n_queries = queries.count()
    rows, oid = df.select(schema.oid, *schema.names), schema.oid
    n_rows, parts = rows.count(), int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if n_queries <= FEW_QUERIES:
        spread = rows.repartition(parts, oid) if n_rows <= STRIP_ROWS * parts else rows  # a small input has few splits, but many pairs
        return spread.join(F.broadcast(qs))
    blocks, strips = -(-n_queries // FEW_QUERIES), max(1, -(-n_rows // STRIP_ROWS))
    grid = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    dealt = rows.withColumn("strip", F.expr(f"pmod(xxhash64({oid}), {strips})").cast("int")).withColumn("block", grid(blocks))
    asked = qs.withColumn("block", F.expr(f"pmod(xxhash64(qid), {blocks})").cast("int")).withColumn("strip", grid(strips))
    parts = max(parts, min(blocks * strips, MOST_CELLS))
    return dealt.repartition(parts, "block", "strip").join(asked.repartition(parts, "block", "strip").hint("shuffle_hash"), ["block", "strip"]).drop("block", "strip")


def paired(df: DataFrame, queries: DataFrame, schema: MultiMetricSchema, w: Mapping[str, float], sigma: Mapping[str, float]) -> DataFrame:
    """(qid, oid, dist) of a stated query set against all rows, dealt by ``met``."""
    return met(df, queries, schema).withColumn("dist", F.expr(mm_distance(schema, None, w, sigma)))


def range_batch(df: DataFrame, queries: DataFrame, schema: MultiMetricSchema, w: Mapping[str, float], r: float, sigma: Mapping[str, float]) -> DataFrame:
    """(qid, oid, dist) within r, of all pairs; costly distances are computed only where the cheap ones leave room for them. More than a few
    queries meet the rows by whole arrays, where all spaces have them."""
    from polymetric.batch import near_enough

    if cells.able(schema, w) and queries.count() > FEW_QUERIES:
        asked = queries.select(F.col(schema.oid).alias("qid"), *(F.col(s.name).alias(f"q_{s.name}") for s in schema.active(w)), F.lit(float(r)).alias("radius"))
        return cells.scan(df, asked, schema, w, sigma)
    near = met(df, queries, schema).withColumn("radius", F.lit(float(r)))
    return near_enough(near, bounds.staged(schema, None, w, sigma, {}, "radius"), mm_distance(schema, None, w, sigma)).drop("radius")


def knn_batch(df: DataFrame, queries: DataFrame, schema: MultiMetricSchema, w: Mapping[str, float], k: int, sigma: Mapping[str, float]) -> DataFrame:
    """(qid, rank, oid, dist): each cell of the grid gives its k nearest, and the rank filter the k nearest of all; other metrics
    than those of ``cells`` meet all pairs, and the filter becomes a per-task top-k before the shuffle on qid."""
    best = Window.partitionBy("qid").orderBy(F.col("dist").asc_nulls_last(), schema.oid)
    near = cells.grid(df, queries, schema, w, sigma, k=k) if cells.able(schema, w) else paired(df, queries, schema, w, sigma)
    return near.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
