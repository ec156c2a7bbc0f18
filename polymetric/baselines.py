"""What the index is compared with. The two metric baselines are reconstructions of behaviour: bound-then-range and per-space."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from concurrent.futures import ThreadPoolExecutor
from functools import reduce
from typing import Any

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from polymetric import batch, bounds
from polymetric.index import FEW_QUERIES, MultiMetricIndex, knn_scan, map_to_pivots, met, range_scan, select_pivots
from polymetric.spaces import SLACK, MultiMetricSchema, literal, mm_distance
from polymetric.store import new_folder, written


def space_top(df: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], name: str, c: int) -> DataFrame:
    """The c nearest in one space alone, ties by id."""
    s = next(s for s in schema.spaces if s.name == name)
    return df.orderBy(F.expr(f"round({s.sql(name, literal(q[name]))}, 9)"), schema.oid).limit(c)


def bound_then_range(df: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], k: int, sigma: Mapping[str, float], spaces: Sequence[str] | None = None) -> DataFrame:
    """kNN in some single spaces bounds the k-th combined distance; a range query with the bound holds the answer. Without an index."""
    names = spaces or [s.name for s in schema.active(w)][:1]
    limit = min(max((r["dist"] for r in (rows if len(rows) == k else [])), default=float("inf")) for n in names for rows in [knn_scan(space_top(df, schema, q, n, k), schema, q, w, k, sigma).select("dist").collect()])
    inside = df if limit == float("inf") else df.where(bounds.single_space(schema, q, w, sigma, limit + SLACK)).where(bounds.early_stop(schema, q, w, sigma, limit + SLACK))
    return knn_scan(inside, schema, q, w, k, sigma)


class BoundThenRange:
    """The same with an index: distances of all objects to pivots of each space, computed and stored once, on Spark spread by hash. It has
    no partitions to skip; a range search tests each space's stored distances alone, kNN starts with a bound from single spaces."""

    def __init__(self, df: DataFrame, schema: MultiMetricSchema, sigma: Mapping[str, float], vantages: int = 2, partitions: int | None = None):
        self.schema, self.sigma, spark = schema, dict(sigma), df.sparkSession
        self.folder = new_folder(spark)
        self.pivots = select_pivots(df, schema, vantages)
        spread = map_to_pivots(df, schema, self.pivots).repartition(partitions or int(spark.conf.get("spark.sql.shuffle.partitions")), schema.oid)
        self.objects = written(spread, self.folder)

    def near(self, q: Mapping[str, Any], w: Mapping[str, float], r: float) -> DataFrame:
        a = {s.name: [s.between(q[s.name], p["value"]) for p in self.pivots[s.name]] for s in self.schema.spaces}
        return self.objects.where(bounds.implied_ranges(a, w, self.sigma, r)).where(bounds.early_stop(self.schema, q, w, self.sigma, r))

    def range(self, q: Mapping[str, Any], w: Mapping[str, float], r: float) -> DataFrame:
        return range_scan(self.near(q, w, r), self.schema, q, w, r, self.sigma)

    def knn(self, q: Mapping[str, Any], w: Mapping[str, float], k: int, spaces: Sequence[str] | None = None) -> DataFrame:
        limit = float("inf")
        for n in spaces or [s.name for s in self.schema.active(w)][:1]:
            rows = knn_scan(space_top(self.objects, self.schema, q, n, k), self.schema, q, w, k, self.sigma).select("dist").collect()
            limit = min(limit, rows[-1]["dist"]) if len(rows) == k else limit
        return knn_scan(self.objects if limit == float("inf") else self.near(q, w, limit + SLACK), self.schema, q, w, k, self.sigma)

    def _asked(self, queries: DataFrame, radius: Any) -> DataFrame:
        far = [F.expr(s.sql(s.name, literal(p["value"]))).alias(f"a_{s.name}_{j}") for s in self.schema.spaces for j, p in enumerate(self.pivots[s.name])]
        return queries.select(F.col(self.schema.oid).alias("qid"), *(F.col(n).alias(f"q_{n}") for n in self.schema.names), *far, radius.alias("radius"))

    def range_queries(self, queries: DataFrame, w: Mapping[str, float], r: float | str) -> DataFrame:
        """(qid, oid, dist) of a query set; up to FEW_QUERIES of them are broadcast, more go block by block."""
        asked = self._asked(queries, F.col(r) if isinstance(r, str) else F.lit(float(r)))
        tests = [f"abs(v_{s.name}_{j} - a_{s.name}_{j}) <= {self.sigma[s.name] / w[s.name]!r}D * (radius + {SLACK!r}D)" for s in self.schema.active(w) for j in range(len(self.pivots[s.name]))]
        lows = bounds.pivot_lows({s.name: [f"a_{s.name}_{j}" for j in range(len(self.pivots[s.name]))] for s in self.schema.active(w)}, w)
        staged = bounds.staged(self.schema, None, w, self.sigma, lows, "radius")
        n = queries.count()
        parts = []
        for k in range(-(-n // FEW_QUERIES)):
            block = asked if n <= FEW_QUERIES else asked.where(F.expr(f"pmod(xxhash64(qid), {-(-n // FEW_QUERIES)}) = {k}"))
            near = self.objects.join(F.broadcast(block), F.expr(" AND ".join(tests)))
            parts.append(batch.near_enough(near, staged, mm_distance(self.schema, None, w, self.sigma)).select("qid", self.schema.oid, "dist"))
        return reduce(DataFrame.unionByName, parts) if parts else self.objects.select(F.col(self.schema.oid).alias("qid"), self.schema.oid, F.lit(0.0).alias("dist")).limit(0)

    def knn_queries(self, queries: DataFrame, w: Mapping[str, float], k: int) -> DataFrame:
        first = self.schema.active(w)[0]
        order = Window.partitionBy("qid").orderBy("d", self.schema.oid)
        met_ = met(self.objects, queries, self.schema)
        near = met_.withColumn("d", F.expr(f"round({first.sql(first.name, f'q_{first.name}')}, 9)")).withColumn("dist", F.expr(mm_distance(self.schema, None, w, self.sigma)))
        top = near.select("qid", self.schema.oid, "d", "dist").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
        limit = top.groupBy("qid").agg(F.when(F.count("*") == k, F.max("dist")).otherwise(float("inf")).alias("bound"))
        bounded = queries.join(F.broadcast(limit), F.col(self.schema.oid) == F.col("qid")).drop("qid") if queries.count() <= FEW_QUERIES else queries.join(limit, F.col(self.schema.oid) == F.col("qid")).drop("qid")
        return best_of_each(self.range_queries(bounded, w, "bound"), self.schema, k)


def best_of_each(found: DataFrame, schema: MultiMetricSchema, k: int) -> DataFrame:
    """(qid, rank, oid, dist): the k best of each query."""
    order = Window.partitionBy("qid").orderBy("dist", schema.oid)
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


class PerSpaceIndex:
    """One single-space index for each modality, at both layers: m layouts of the data, saved, and joined by id."""

    def __init__(self, df: DataFrame, schema: MultiMetricSchema, sigma: Mapping[str, float], depth: int | None = None):
        self.df, self.schema, self.sigma = df, schema, sigma
        self.folder = new_folder(df.sparkSession)

        def made(n: str) -> MultiMetricIndex:
            return MultiMetricIndex.build(df.select(schema.oid, n), schema.subset(n), depth, 1, sigma=sigma).save(f"{self.folder}/{n}")

        with ThreadPoolExecutor(4) as pool:  # small jobs of the driver, side by side
            self.parts = dict(zip(schema.names, pool.map(made, schema.names), strict=True))

    def range(self, q: Mapping[str, Any], w: Mapping[str, float], r: float) -> DataFrame:
        """Pigeonhole in every active space's index, the union of ids, and verification after a join on ids."""
        t = bounds.thresholds(w, r)
        found = [self.parts[n].range({n: q[n]}, {n: 1.0}, t[n] + SLACK).select(self.schema.oid) for n in t]
        ids = reduce(DataFrame.unionByName, found).distinct()
        return range_scan(self.df.join(ids, self.schema.oid), self.schema, q, w, r, self.sigma)

    def knn(self, q: Mapping[str, Any], w: Mapping[str, float], k: int) -> DataFrame:
        first = next(iter(bounds.thresholds(w, 1.0)))
        near = self.parts[first].knn({first: q[first]}, {first: 1.0}, k).select(self.schema.oid)
        rows = knn_scan(self.df.join(near, self.schema.oid), self.schema, q, w, k, self.sigma).select("dist").collect()
        if len(rows) < k:
            return knn_scan(self.df, self.schema, q, w, k, self.sigma)
        return knn_scan(self.range(q, w, rows[-1]["dist"] + SLACK), self.schema, q, w, k, self.sigma)

    def _verified(self, found: DataFrame, queries: DataFrame, w: Mapping[str, float]) -> DataFrame:
        oid = self.schema.oid
        asked = queries.select(F.col(oid).alias("qid"), *(F.col(n).alias(f"q_{n}") for n in self.schema.names))
        whole = found.join(self.df.select(oid, *self.schema.names), oid).join(asked, "qid")
        return whole.select("qid", oid, F.expr(mm_distance(self.schema, None, w, self.sigma)).alias("dist"))

    def range_queries(self, queries: DataFrame, w: Mapping[str, float], r: float | str) -> DataFrame:
        """(qid, oid, dist) of a query set: every active space's index is searched, and pairs are made whole by joins on ids."""
        oid, total = self.schema.oid, sum(w.values())
        radius = F.col(r) if isinstance(r, str) else F.lit(float(r))
        found = []
        for s in self.schema.active(w):
            asked = queries.select(oid, s.name, (radius / total + SLACK).alias("pm_radius"))
            found.append(batch.range_queries(self.parts[s.name], asked, {s.name: 1.0}, "pm_radius").select("qid", oid))
        pairs = reduce(DataFrame.unionByName, found).distinct()
        limits = queries.select(F.col(oid).alias("qid"), radius.alias("radius"))
        return self._verified(pairs, queries, w).join(limits, "qid").where("dist <= radius").select("qid", oid, "dist")

    def knn_queries(self, queries: DataFrame, w: Mapping[str, float], k: int) -> DataFrame:
        first, oid = self.schema.active(w)[0].name, self.schema.oid
        near = batch.knn_queries(self.parts[first], queries.select(oid, first), {first: 1.0}, k).select("qid", oid)
        limit = self._verified(near, queries, w).groupBy("qid").agg(F.when(F.count("*") == k, F.max("dist")).otherwise(float("inf")).alias("bound"))
        return best_of_each(self.range_queries(queries.join(limit, F.col(oid) == F.col("qid")).drop("qid"), w, "bound"), self.schema, k)


def vector_merge(df: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], k: int, ratio: int, sigma: Mapping[str, float]) -> DataFrame:
    """Approximate: each field's ratio * k nearest, merged and ranked by the combined distance. It has no range search."""
    lists = [space_top(df, schema, q, s.name, ratio * k) for s in schema.active(w)]
    return knn_scan(reduce(DataFrame.unionByName, lists).dropDuplicates([schema.oid]), schema, q, w, k, sigma)


def isolated_intersection(df: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], k: int, c: int, sigma: Mapping[str, float]) -> DataFrame:
    """Approximate: objects among the c nearest of every active space."""
    lists = [space_top(df, schema, q, s.name, c).select(schema.oid) for s in schema.active(w)]
    return knn_scan(df.join(reduce(DataFrame.intersect, lists), schema.oid), schema, q, w, k, sigma)


def vector_concat(df: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], k: int, sigma: Mapping[str, float]) -> DataFrame:
    """Fusion: scaled coordinates side by side under L1, which equals the combined distance if every space is L1."""
    active = schema.active(w)
    if any(s.kind not in ("l1", "l1v") for s in active):
        raise ValueError("only spaces under L1 can be concatenated")
    scale = {s.name: w[s.name] / sigma[s.name] for s in active}
    fused = "concat(" + ", ".join(f"transform({s.name if s.kind == 'l1v' else f'array({s.name})'}, x -> x * {scale[s.name]!r}D)" for s in active) + ")"
    flat = [x * scale[s.name] for s in active for x in (q[s.name] if s.kind == "l1v" else [q[s.name]])]
    d = f"round(aggregate(zip_with(fused, {literal(flat)}, (x, y) -> abs(x - y)), 0D, (s, x) -> s + x), 9)"
    return df.withColumn("fused", F.expr(fused)).withColumn("dist", F.expr(d)).orderBy("dist", schema.oid).limit(k)


def knn_naive(df: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], k: int, sigma: Mapping[str, float]) -> DataFrame:
    """Each space's k nearest, ranked: a negative control, since a true neighbour may be near in no space alone."""
    return vector_merge(df, schema, q, w, k, 1, sigma)
