"""Counts of work, balance of load, updates."""

from __future__ import annotations

import time
from collections.abc import Callable, Mapping, Sequence
from typing import TYPE_CHECKING, Any

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric import bounds
from polymetric.index import MultiMetricIndex, range_scan
from polymetric.updates import updated

if TYPE_CHECKING:
    from polymetric.queries import Setup


def timed(make: Callable[[], DataFrame], repeat: int = 3) -> float:
    """Seconds of a query with all its rows computed: the mean after one warm run."""
    make().write.format("noop").mode("overwrite").save()
    began = time.perf_counter()
    for _ in range(repeat):
        make().write.format("noop").mode("overwrite").save()
    return (time.perf_counter() - began) / repeat


def explain_query(index: MultiMetricIndex, q: Mapping[str, Any], w: Mapping[str, float], r: float) -> DataFrame:
    """(stage, n): leaves kept, objects after each test, results, in one pass."""
    a, schema = index.query_pivots(q), index.schema
    kept = index.keep_leaves(a, w, r)
    inside = index.objects.withColumn("in_leaf", F.col("leaf_id").isin(kept)).withColumn("near", F.expr(bounds.pigeonhole(schema, q, w, index.sigma, r))).withColumn("low", F.expr(bounds.pivot_sum(a, w, index.sigma, r)))
    from polymetric.spaces import mm_distance

    counted = inside.withColumn("hit", F.expr(mm_distance(schema, q, w, index.sigma)) <= r).agg(F.count("*").alias("objects"), F.count_if(F.expr("in_leaf")).alias("in_kept_leaves"), F.count_if(F.expr("in_leaf AND near")).alias("after_pigeonhole"), F.count_if(F.expr("in_leaf AND low")).alias("after_pivot_sum"), F.count_if(F.expr("in_leaf AND near AND low")).alias("verified"), F.count_if(F.expr("hit")).alias("results"))
    return counted.selectExpr(f"stack(8, 'leaves', {len(index.boxes)}L, 'leaves_kept', {len(kept)}L, 'objects', objects, 'in_kept_leaves', in_kept_leaves, 'after_pigeonhole', after_pigeonhole, 'after_pivot_sum', after_pivot_sum, 'verified', verified, 'results', results) AS (stage, n)")


def balance(index: MultiMetricIndex, workers: Sequence[int]) -> DataFrame:
    """(workers, stddev of objects a worker) when leaves go, largest first, to the least-loaded worker."""
    rows = [(n, float(spread_over([b["n_objects"] for b in index.boxes], n).std())) for n in workers]
    return index.objects.sparkSession.createDataFrame(rows, "workers int, stddev double")


def spread_over(work: Sequence[float], workers: int) -> np.ndarray:
    """Load of each worker when pieces of work go, largest first, to the least-loaded one."""
    load = np.zeros(workers)
    for c in sorted(work, reverse=True):
        load[int(load.argmin())] += c
    return load


def leaf_work(index: MultiMetricIndex, queries: DataFrame, w: Mapping[str, float], r: float) -> list[float]:
    """Objects that a query set meets in each leaf: queries routed to it times its objects; one row a leaf."""
    from polymetric import batch

    asked = batch.as_queries(index, queries).withColumn("radius", F.lit(float(r)))
    sizes = {b["leaf_id"]: b["n_objects"] for b in index.boxes}
    return [float(x["n"] * sizes[x["leaf_id"]]) for x in batch.route(index, asked, w).groupBy("leaf_id").agg(F.count("*").alias("n")).collect()]


def after_update(s: Setup, mod: int, r: float) -> DataFrame:
    """Deletes the objects with id % mod = 7, inserts them again with a price 1000 higher, and asks for a range."""
    index = s.index()
    moved = s.df.where(F.col("oid") % mod == 7)
    now = updated(index, moved.select("oid"), moved.withColumn("price", F.col("price") + 1000))
    return range_scan(now.candidates(s.q, s.w, r), s.schema, s.q, s.w, r, s.sigma).select("oid", F.round("dist", 6).alias("mm_dist"))


def is_folder(spark, path: str) -> bool:  # noqa: ANN001
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()
