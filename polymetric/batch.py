"""Many searches at once over the index: query sets that may grow with the data, joins of two tables, self joins.

Queries are routed to the leaves they can't rule out, then meet the objects in an equi-join on (leaf, bucket). A leaf is
cut into buckets by its size, known from the leaf table, so neither a hot leaf nor few leaves limit the parallelism. The
stored vantage distances are tested inside the join, before any real distance. Only the leaf table is broadcast: its
size is checked, and beyond the limit it is joined without a hint.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from polymetric import bounds, cells
from polymetric.index import MultiMetricIndex
from polymetric.spaces import SLACK, literal, mm_distance
from polymetric.store import new_folder

#: Objects of a bucket, and leaves that may be broadcast.
BUCKET_ROWS = 50_000
BROADCAST_LEAVES = 100_000
#: Rows of queries routed to leaves, at most, that are broadcast; the objects then stay where they are. More meet them in a shuffle.
BROADCAST_ROUTED = 50_000


def pools(index: MultiMetricIndex, w: Mapping[str, float]) -> list[dict]:
    """Neighbouring leaves put together to cells of ``cells``: (pool, buckets, leaves, lo_<space>, hi_<space>), one small row each. A leaf
    that is larger than a cell makes a pool with several buckets."""
    most, out = cells.cell_rows(index.schema, w), []
    by = {b["leaf_id"]: b for b in index.boxes}
    for b in (by[i] for i in index.inner.ids.tolist()):
        if not out or out[-1]["n"] + b["n_objects"] > most:
            out.append({"pool": len(out), "n": 0, "leaves": []})
        p = out[-1]
        for s in index.schema.active(w):
            for k, f in (("lo", min), ("hi", max)):
                c = f"{k}_{s.name}"
                p[c] = f(p.get(c, b[c]), b[c])
        p["n"] += b["n_objects"]
        p["leaves"].append(b["leaf_id"])
    return [p | {"buckets": -(-p["n"] // most)} for p in out]


def _meet_cells(index: MultiMetricIndex, asked: DataFrame, w: Mapping[str, float], k: int) -> DataFrame:
    """(qid, oid, dist), the k nearest of each cell: queries (with radius) go to the pools of leaves that their gaps can't rule out and meet the objects by ``cells``."""
    schema, spark, made = index.schema, index.objects.sparkSession, pools(index, w)
    names = [s.name for s in schema.active(w)]
    if not made:
        return asked.select("qid", F.col("qid").alias(schema.oid), F.lit(0.0).alias("dist")).limit(0)
    n_queries, n_cells = asked.count(), sum(p["buckets"] for p in made)
    blocks = cells.blocks_of(n_queries, n_cells)
    kind = "leaf_id int, pool int, buckets int"
    leaves = spark.createDataFrame([(leaf, p["pool"], p["buckets"]) for p in made for leaf in p["leaves"]], kind)
    ends = [f"{k}_{n}" for n in names for k in ("lo", "hi")]
    boxes = spark.createDataFrame([(p["pool"], p["buckets"], *(float(p[c]) for c in ends)) for p in made], "pool int, n_buckets int, " + ", ".join(f"{c} double" for c in ends))
    if len(index.boxes) <= BROADCAST_LEAVES:
        leaves, boxes = F.broadcast(leaves), F.broadcast(boxes)
    every = lambda n: F.explode(F.sequence(F.lit(0), n - F.lit(1)))
    objects = index.objects.select(schema.oid, "leaf_id", *names).join(leaves, "leaf_id").withColumn("bucket", F.expr(f"CAST(pmod(xxhash64({schema.oid}), buckets) AS INT)"))
    objects = objects.withColumn("block", every(F.lit(blocks)))
    routed = asked.join(boxes, F.expr(f"{_gap(index, w)} <= radius + {SLACK!r}D")).withColumn("bucket", every(F.col("n_buckets")))
    routed = routed.withColumn("block", F.expr(f"CAST(pmod(xxhash64(qid), {blocks}) AS INT)"))
    return cells.search(objects, routed, ["pool", "bucket", "block"], schema, w, index.sigma, k, min(4 * blocks * n_cells, cells.MOST_CELLS))


def _scan_pools(index: MultiMetricIndex, asked: DataFrame, w: Mapping[str, float]) -> DataFrame:
    """(qid, oid, dist) within each query's radius: the objects are dealt to pools of leaves once, and a pool meets the queries that its gaps
    can't rule out. Neither objects nor what is found are shuffled again."""
    made, names = pools(index, w), [s.name for s in index.schema.active(w)]
    if not made:
        return asked.select("qid", F.col("qid").alias(index.schema.oid), F.lit(0.0).alias("dist")).limit(0)
    leaves = index.objects.sparkSession.createDataFrame([(leaf, p["pool"]) for p in made for leaf in p["leaves"]], "leaf_id int, pool int")
    leaves = F.broadcast(leaves) if len(index.boxes) <= BROADCAST_LEAVES else leaves
    objects = index.objects.select(index.schema.oid, "leaf_id", *names, *(f"v_{n}_0" for n in names)).join(leaves, "leaf_id").drop("leaf_id")
    buckets = F.expr(f"CASE pool {' '.join(f'WHEN {p['pool']} THEN {p['buckets']}' for p in made if p['buckets'] > 1)} ELSE 1 END") if any(p["buckets"] > 1 for p in made) else F.lit(1)
    objects = objects.withColumn("bucket", F.pmod(F.xxhash64(index.schema.oid), buckets).cast("int"))
    dealt = objects.repartition(min(4 * sum(p["buckets"] for p in made), cells.MOST_CELLS), "pool", "bucket").sortWithinPartitions("pool")
    return cells.scan(dealt, asked, index.schema, w, index.sigma, {n: (f"v_{n}_0", f"a_{n}_0") for n in names}, "pool", len(made))


def leaf_table(index: MultiMetricIndex) -> DataFrame:
    """The leaves with their number of buckets, broadcast if few."""
    leaves = index.leaves.withColumn("buckets", F.ceil(F.col("n_objects") / BUCKET_ROWS).cast("int"))
    return F.broadcast(leaves) if len(index.boxes) <= BROADCAST_LEAVES else leaves


def as_queries(index: MultiMetricIndex, queries: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    """(qid, q_<space>, a_<space>_<j>): the queries with their pivot distances; narrow."""
    schema = index.schema
    far = [F.expr(s.sql(s.name, literal(p["value"]))).alias(f"a_{s.name}_{j}") for s in schema.spaces for j, p in enumerate(index.pivots[s.name])]
    return queries.select(F.col(schema.oid).alias("qid"), *(F.col(n).alias(f"q_{n}") for n in schema.names), *far, *extra)


def _gap(index: MultiMetricIndex, w: Mapping[str, float]) -> str:
    return " + ".join(f"{w[s.name]!r}D * greatest(0D, lo_{s.name} - a_{s.name}_0, a_{s.name}_0 - hi_{s.name}) / {index.sigma[s.name]!r}D" for s in index.schema.active(w))


def _meet(index: MultiMetricIndex, routed: DataFrame, w: Mapping[str, float]) -> DataFrame:
    """Routed queries (with leaf_id, buckets and radius) and the objects that their vantage distances can't rule out, with dist."""
    schema, oid = index.schema, index.schema.oid
    stored = [f"v_{s.name}_{j}" for s in schema.active(w) for j in range(len(index.pivots[s.name]))]
    lows = bounds.pivot_lows({s.name: [f"a_{s.name}_{j}" for j in range(len(index.pivots[s.name]))] for s in schema.active(w)}, w)
    sums = " + ".join(f"{w[n]!r}D * {x} / {index.sigma[n]!r}D" for n, x in lows.items())
    low, staged = f"{sums} <= radius + {SLACK!r}D", bounds.staged(schema, None, w, index.sigma, lows, "radius")
    if routed.limit(BROADCAST_ROUTED + 1).count() <= BROADCAST_ROUTED:
        few = F.broadcast(routed.drop("buckets").withColumnRenamed("leaf_id", "q_leaf"))
        near = index.objects.select(oid, "leaf_id", *(s.name for s in schema.active(w)), *stored).join(few, F.expr(f"leaf_id = q_leaf AND {low}"))
        return near_enough(near, staged, mm_distance(schema, None, w, index.sigma))
    spread = routed.withColumn("bucket", F.explode(F.sequence(F.lit(0), F.col("buckets") - 1))).drop("buckets").withColumnRenamed("leaf_id", "q_leaf")
    sizes = leaf_table(index).select("leaf_id", "buckets")
    objects = index.objects.select(oid, "leaf_id", *(s.name for s in schema.active(w)), *stored).join(sizes, "leaf_id").withColumn("o_bucket", F.expr(f"pmod(xxhash64({oid}), buckets)").cast("int"))
    parts = int(objects.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if sum(b["n_objects"] for b in index.boxes) <= BUCKET_ROWS * parts:
        # little input but many pairs: a set number of partitions isn't merged for its small size; larger inputs are left to the skew join
        objects, spread = objects.repartition(parts, "leaf_id", "o_bucket"), spread.repartition(parts, "q_leaf", "bucket")
    near = objects.join(spread, F.expr(f"leaf_id = q_leaf AND o_bucket = bucket AND {low}"))
    return near_enough(near, staged, mm_distance(schema, None, w, index.sigma))


def near_enough(pairs: DataFrame, test: str, dist: str) -> DataFrame:
    """Pairs within their radius, with dist, which is only computed where the test holds. The optimizer would move a filter on a computed
    column into the join, before the test, and compute it twice, in a method too large to be compiled; a generator of one row keeps it in place."""
    return pairs.withColumn("dist", F.explode(F.array(F.expr(f"CASE WHEN {test} THEN {dist} END")))).where("dist <= radius")


def range_queries(index: MultiMetricIndex, queries: DataFrame, w: Mapping[str, float], r: float | str) -> DataFrame:
    """(qid, oid, dist): exact range search for each row of ``queries``; r is a number or the name of its radius column."""
    extra = (r,) if isinstance(r, str) else ()
    asked = as_queries(index, queries, extra).withColumn("radius", F.col(r) if extra else F.lit(float(r)))
    if cells.able(index.schema, w):
        return _scan_pools(index, asked, w)
    return _meet(index, route(index, asked, w), w).select("qid", index.schema.oid, "dist")


def route(index: MultiMetricIndex, asked: DataFrame, w: Mapping[str, float]) -> DataFrame:
    """One row for each query and leaf whose weighted gaps add up to the query's radius at most."""
    names = [s.name for s in index.schema.active(w)]
    boxes = leaf_table(index).select("leaf_id", "buckets", *(f"{k}_{n}" for n in names for k in ("lo", "hi")))
    return asked.join(boxes, F.expr(f"{_gap(index, w)} <= radius + {SLACK!r}D")).drop(*(f"{k}_{n}" for n in names for k in ("lo", "hi")))


def seed_bounds(index: MultiMetricIndex, asked: DataFrame, w: Mapping[str, float], k: int) -> DataFrame:
    """(qid, radius): the k-th distance within the leaf of the nearest centre that holds k objects; no such leaf: infinity."""
    names = [s.name for s in index.schema.active(w)]
    mid = " + ".join(f"{w[n]!r}D * abs((lo_{n} + hi_{n}) / 2 - a_{n}_0) / {index.sigma[n]!r}D" for n in names)
    full = leaf_table(index).where(F.col("n_objects") >= k)
    seeds = asked.select("qid", *(c for c in asked.columns if c.startswith("a_"))).join(full).groupBy("qid").agg(F.min_by(F.struct("leaf_id", "buckets"), F.struct(F.expr(mid), "leaf_id")).alias("s"))
    routed = asked.join(seeds.select("qid", "s.leaf_id", "s.buckets"), "qid").withColumn("radius", F.lit(float("inf")))
    order = Window.partitionBy("qid").orderBy("dist", index.schema.oid)
    if cells.able(index.schema, w):  # a leaf and the queries that it is nearest to
        met = cells.search(index.objects, routed, ["leaf_id"], index.schema, w, index.sigma, k, min(4 * len(index.boxes), cells.MOST_CELLS))
    else:
        met = _meet(index, routed, w).select("qid", index.schema.oid, "dist")
    found = met.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    kth = found.where(F.col("rank") == k).select("qid", F.col("dist").alias("bound"))
    return asked.select("qid").join(kth, "qid", "left").select("qid", F.coalesce("bound", F.lit(float("inf"))).alias("radius"))


def knn_queries(index: MultiMetricIndex, queries: DataFrame, w: Mapping[str, float], k: int) -> DataFrame:
    """(qid, rank, oid, dist): exact kNN for each row of ``queries``, also a join of two tables. A bound for each query from
    its seed leaf, then range search with the bounds, then the k best; the rank filter keeps k rows a task before the shuffle. Where the
    leaves make up one cell, there is no leaf to rule out and no bound is needed."""
    asked = as_queries(index, queries)
    if cells.able(index.schema, w):
        near = _meet_cells(index, asked.join(seed_bounds(index, asked, w, k), "qid") if len(pools(index, w)) > 1 else asked.withColumn("radius", F.lit(float("inf"))), w, k)
    else:
        bounded = asked.join(seed_bounds(index, asked, w, k), "qid")
        near = _meet(index, route(index, bounded, w), w).select("qid", index.schema.oid, "dist")
    order = Window.partitionBy("qid").orderBy(F.col("dist").asc_nulls_last(), index.schema.oid)
    return near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def classes(df: DataFrame, schema) -> tuple[DataFrame, DataFrame]:  # noqa: ANN001
    """Objects that agree in every space: (one row a class, under its least id, with n_copies) and the membership (oid, rep)."""
    whole = F.sha2(F.to_json(F.struct(*schema.names)), 256)
    keyed = df.select(schema.oid, *schema.names).withColumn("class_key", whole)
    heads = keyed.groupBy("class_key").agg(F.min(schema.oid).alias("rep"), F.count("*").alias("n_copies"))
    members = keyed.select(schema.oid, "class_key").join(heads, "class_key").select(schema.oid, "rep", "n_copies")
    reps = df.select(schema.oid, *schema.names).join(heads.select(F.col("rep").alias(schema.oid), "n_copies"), schema.oid)
    return reps, members


def similarity_join(df: DataFrame, schema, w: Mapping[str, float], r: float, sigma: Mapping[str, float], **options) -> tuple[DataFrame, DataFrame]:  # noqa: ANN001, ANN003
    """All pairs within r, whole but not expanded: (pairs a < b of class representatives with dist, membership with n_copies).
    Equal objects collapse first, so a group of copies costs one object."""
    reps, members = classes(df, schema)
    index = MultiMetricIndex.build(reps, schema, sigma=sigma, **options).save(new_folder(df.sparkSession))  # each block of queries reads it
    pairs = range_queries(index, reps, w, r).where(F.col("qid") < F.col(schema.oid))
    return pairs.select(F.col("qid").alias("a"), F.col(schema.oid).alias("b"), "dist"), members


def link_counts(pairs: DataFrame, members: DataFrame, oid: str = "oid") -> DataFrame:
    """(oid, rep, links): how many other objects lie within the join's radius; copies count."""
    size = members.where(F.col(oid) == F.col("rep")).select("rep", "n_copies")
    ends = pairs.select(F.col("a").alias("x"), F.col("b").alias("rep")).unionByName(pairs.select(F.col("b").alias("x"), F.col("a").alias("rep")))
    near = ends.join(size, "rep").groupBy("x").agg(F.sum("n_copies").alias("others"))
    return members.join(near.withColumnRenamed("x", "rep"), "rep", "left").select(oid, "rep", (F.coalesce("others", F.lit(0)) + F.col("n_copies") - 1).alias("links"))
