"""Weight learning from example queries and their true neighbours, by a contrastive loss over per-space distances."""

from __future__ import annotations

import time
from collections.abc import Mapping
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from polymetric.index import met
from polymetric.spaces import MultiMetricSchema
from polymetric.store import new_folder, written


def cache_distances(df: DataFrame, queries: DataFrame, schema: MultiMetricSchema, sigma: Mapping[str, float]) -> DataFrame:
    """(qid, oid, d_<space>): distances don't depend on weights, so each iteration only re-ranks. Query sets may grow with the rows (``met``)."""
    return met(df, queries, schema).select("qid", schema.oid, *(F.expr(f"{s.sql(s.name, f'q_{s.name}')} / {sigma[s.name]!r}D").alias(f"d_{s.name}") for s in schema.spaces))


def retrieve(cache: DataFrame, schema: MultiMetricSchema, w: Mapping[str, float], k: int) -> DataFrame:
    d = "round(" + " + ".join(f"{w[n]!r}D * d_{n}" for n in schema.names) + ", 9)"
    best = Window.partitionBy("qid").orderBy("dist", schema.oid)
    return cache.withColumn("dist", F.expr(d)).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def others(cache: DataFrame, schema: MultiMetricSchema, truth: DataFrame, n: int | None = None) -> DataFrame:
    """The rows of the cache that are no true neighbours: all, or the first n of each query by an arithmetic shuffle. Weights play no part."""
    rest = cache.join(truth.select("qid", schema.oid), ["qid", schema.oid], "left_anti")
    order = Window.partitionBy("qid").orderBy(F.expr(f"({schema.oid} * 7901 + qid * 31) % 1000003"), schema.oid)
    return rest if n is None else rest.withColumn("n", F.row_number().over(order)).where(F.col("n") <= n).drop("n")


def sample(cache: DataFrame, schema: MultiMetricSchema, found: DataFrame, truth: DataFrame, positives: str = "truth", negatives: str = "knn", drawn: DataFrame | None = None) -> DataFrame:
    """(qid, oid, is_pos, d_*). positives: truth, intersection (true and retrieved) or union; negatives: knn (retrieved,
    not true), random (as many others, by an arithmetic shuffle; drawn: those, if they are known) or rest (all others)."""
    key = ["qid", schema.oid]
    f, t = found.select(*key), truth.select(*key)
    pos = {"truth": t, "intersection": f.intersect(t), "union": f.union(t).distinct()}[positives]
    if negatives == "knn":
        neg = f.join(t, key, "left_anti")
    else:
        neg = drawn if drawn is not None else others(cache, schema, truth, 50 if negatives == "random" else None).select(*key)
    tagged = pos.withColumn("is_pos", F.lit(True)).unionByName(neg.withColumn("is_pos", F.lit(False)))
    return cache.join(F.broadcast(tagged) if negatives != "rest" else tagged, key)


def loss_grad(samples: DataFrame, schema: MultiMetricSchema, w: Mapping[str, float], tau: float = 1.0, sign: int = -1) -> DataFrame:
    """One row (loss, g_<space>): mean over queries with both classes of -ln(positive mass / all mass), mass being the sum of
    exp(sign * distance / tau), and its gradient."""
    mass = F.exp(F.expr(f"{sign / tau!r}D * ({' + '.join(f'{w[n]!r}D * d_{n}' for n in schema.names)})"))
    one = samples.withColumn("m", mass).withColumn("p", F.when(F.col("is_pos"), F.col("m")).otherwise(0.0))
    sums = one.groupBy("qid").agg(F.sum("m").alias("a"), F.sum("p").alias("p"), F.count_if("is_pos").alias("n_pos"), F.count_if(~F.col("is_pos")).alias("n_neg"), *(F.sum(F.col(f"d_{n}") * F.col(c)).alias(f"{c}_{n}") for n in schema.names for c in ("m", "p")))
    both = sums.where("n_pos > 0 AND n_neg > 0")
    return both.agg(F.avg(-F.log(F.col("p") / F.col("a"))).alias("loss"), *(F.avg((F.col(f"m_{n}") / F.col("a") - F.col(f"p_{n}") / F.col("p")) * (sign / tau)).alias(f"g_{n}") for n in schema.names))


def recall(found: DataFrame, truth: DataFrame, key: tuple[str, ...] = ("qid", "oid")) -> DataFrame:
    """(qid, recall): the share of each query's true neighbours that were found."""
    hit = truth.select(*key).join(found.select(*key, F.lit(1).alias("hit")), list(key), "left")
    return hit.groupBy("qid").agg((F.count("hit") / F.count("*")).alias("recall"))


def learn_weights(cache: DataFrame, truth: DataFrame, schema: MultiMetricSchema, k: int, iters: int = 20, lr: float = 0.05, tau: float = 1.0, positives: str = "truth", negatives: str = "knn", optimiser: str = "adam", target: float = 0.9, seed: int = 3, sign: int = -1) -> tuple[dict[str, float], list[tuple]]:
    """(best weights, history of (iter, loss, recall, seconds so far)). Each iteration is retrieval, sampling and one row to the driver.
    It scans the cache once: what is sampled comes from the rows retrieved, the true ones, and negatives drawn before."""
    rng = np.random.default_rng(seed)
    w, m, v = rng.uniform(0.1, 1, len(schema.names)), 0.0, 0.0
    best, history, began = (-1.0, w), [], time.perf_counter()
    spark, cells = cache.sparkSession, ["qid", schema.oid, *(f"d_{n}" for n in schema.names)]
    whole = truth if set(cells) <= set(truth.columns) else cache.join(truth.select(*cells[:2]), cells[:2])
    truth = written(whole.select(*cells), new_folder(spark))
    drawn = written(others(cache, schema, truth, 50).select(*cells), new_folder(spark)) if negatives == "random" else None
    folder = new_folder(spark)
    for i in range(1, iters + 1):
        now = dict(zip(schema.names, map(float, w), strict=True))
        found = written(retrieve(cache, schema, now, k).select(*cells), f"{folder}/{i}")  # the one scan of the cache; its rows carry their distances
        pool = cache if negatives == "rest" else reduce(DataFrame.unionByName, [x for x in (found, truth, drawn) if x is not None]).dropDuplicates(["qid", schema.oid])
        got = recall(found, truth).agg(F.avg("recall")).first()[0]
        row = loss_grad(sample(pool, schema, found, truth, positives, negatives, None if drawn is None else drawn.select("qid", schema.oid)), schema, now, tau, sign).first()
        history.append((i, row["loss"], got, time.perf_counter() - began))
        best = max(best, (got, w.copy()), key=lambda b: b[0])
        if got >= target or row["loss"] is None:
            break
        g = np.array([row[f"g_{n}"] for n in schema.names])
        if optimiser == "adam":
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            g = (m / (1 - 0.9**i)) / (np.sqrt(v / (1 - 0.999**i)) + 1e-9)
        w = np.clip(w - lr * g, 0, None)
        w = w / w.max() if w.max() > 0 else np.ones_like(w)
    return dict(zip(schema.names, map(float, best[1]), strict=True)), history


def modality_profile(sets: Mapping[str, DataFrame], schema: MultiMetricSchema) -> DataFrame:
    """(tag, space, mean distance to the query) of labelled sets with d_<space> columns."""
    parts = [df.select(F.lit(tag).alias("tag"), *(f"d_{n}" for n in schema.names)) for tag, df in sets.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    cells = ", ".join(f"'{n}', m_{n}" for n in schema.names)
    return out.groupBy("tag").agg(*(F.avg(f"d_{n}").alias(f"m_{n}") for n in schema.names)).selectExpr("tag", f"stack({len(schema.names)}, {cells}) AS (space, mean)")
