"""The experiments as queries on the given tables, batch searches and joins, updates and streams."""

from __future__ import annotations

import time
from collections.abc import Callable, Mapping
from functools import reduce
from typing import Any

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from polymetric import baselines, batch, cells, fixtures, local_index, measures, ranks, sources, store, streaming, tuning, updates, weights
from polymetric.index import MultiMetricIndex, knn_batch, knn_scan, paired, range_batch, range_scan, select_pivots
from polymetric.normalize import norm_table
from polymetric.queries import _BATCH, ASK, ONES, QID, QUERIES, Setup, _learning, duck_dist, duck_knn, duck_norm, duck_range, duck_scan, query, skew, slim
from polymetric.spaces import DIGITS, MultiMetricSchema
from polymetric.store import once, written

_RENTAL, _FOOD, _QUAD, _EVT = (fixtures.schema(n) for n in ("rental", "food", "quad", "evt"))

# ---- batches and joins: every row whose id is divisible by 20 asks, against all rows --------------------------------


def _duck_asked(name: str, w: Mapping[str, float], ask: str = ASK) -> str:
    return f"{duck_norm(name)}, p AS (SELECT g.oid AS qid, f.oid, {duck_dist(fixtures.schema(name), w, 'f', 'g')} AS dist FROM f, (SELECT * FROM f WHERE {ask}) g, norm)"


def _ranked(df: DataFrame) -> DataFrame:
    return df.select("qid", "rank", "oid", F.round("dist", 6).alias("mm_dist"))


_TOP10 = "SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY dist, oid) AS INT) AS rank, oid, round(dist, 6) AS mm_dist FROM p QUALIFY rank <= 10"
for _name, _r in (("rental", 0.15), ("food", 0.8)):
    _w = skew(fixtures.schema(_name))
    query(f"q3_range_batch_indexed_{_name}", f"{_duck_asked(_name, _w)} SELECT qid, oid, round(dist, 6) AS mm_dist FROM p WHERE dist <= {_r}")(lambda spark, d, n=_name, w=_w, r=_r: (lambda s: batch.range_queries(s.index(), s.df.where(ASK), s.w, r).select("qid", "oid", F.round("dist", 6).alias("mm_dist")))(Setup(spark, d, n, w)))
    query(f"k3_knn_batch_indexed_{_name}", f"{_duck_asked(_name, _w)} {_TOP10}")(lambda spark, d, n=_name, w=_w: (lambda s: _ranked(batch.knn_queries(s.index(), s.df.where(ASK), s.w, 10)))(Setup(spark, d, n, w)))
query("k6_knn_join", f"{_duck_asked('quad', ONES['quad'], 'true')} {_TOP10}")(lambda spark, d: (lambda s: _ranked(batch.knn_queries(s.index(), s.df, s.w, 10)))(Setup(spark, d, "quad")))


def _links(name: str, r: float) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = Setup(spark, sf_dir, name)
        return batch.link_counts(*batch.similarity_join(s.df, s.schema, s.w, r, s.sigma))

    return run


for _name, _r in (("quad", 1.0), ("food", 1.0)):
    _same = ", ".join(fixtures.schema(_name).names)
    query(f"k7_range_join_{_name}", f"{_duck_asked(_name, ONES[_name], 'true')}, m AS (SELECT oid, min(oid) OVER (PARTITION BY {_same}) AS rep FROM f) SELECT m.oid, m.rep, count(p.qid) - 1 AS links FROM m JOIN p ON p.qid = m.oid AND p.dist <= {_r} GROUP BY ALL")(_links(_name, _r))
query("k5_knn_naive_per_space", f"{duck_scan('rental', skew(_RENTAL))}, c AS (" + " UNION ".join(f"SELECT * FROM (SELECT d.oid FROM d, q ORDER BY round({s.sql('d.' + s.name, 'q.' + s.name, True)}, 9), d.oid LIMIT 10)" for s in _RENTAL.spaces) + ") SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE oid IN (SELECT oid FROM c) ORDER BY dist, oid LIMIT 10")(lambda spark, d: (lambda s: slim(baselines.knn_naive(s.df, s.schema, s.q, s.w, 10, s.sigma)))(Setup(spark, d, "rental", skew(_RENTAL))))
query("n3_median_norm_sampled")(lambda spark, d: norm_table(fixtures.load(spark, d, "rental"), _RENTAL, n=64, exact=False).select("space", "sigma"))

# ---- pivots ----------------------------------------------------------------------------------------------------------
query("g2_pivots_several")(lambda spark, d: spark.createDataFrame([(n, j, p["oid"]) for n, ps in select_pivots(fixtures.load(spark, d, "rental"), _RENTAL, 3).items() for j, p in enumerate(ps)], "space string, ord int, oid long"))
query("g3_pivots_random", "WITH f AS MATERIALIZED (" + fixtures.duck_sql("rental") + "), p AS (SELECT oid, row_number() OVER (ORDER BY (oid * 6007 + 1) % 1000033, oid) AS j FROM f QUALIFY j <= 1) " + " UNION ALL ".join(f"SELECT '{n}' AS space, oid FROM p" for n in _RENTAL.names))(lambda spark, d: spark.createDataFrame([(n, p[0]["oid"]) for n, p in select_pivots(fixtures.load(spark, d, "rental"), _RENTAL, 1, "random").items()], "space string, oid long"))
query("bl2d_bound_then_range_distributed", duck_knn("rental", skew(_RENTAL), 10))(lambda spark, d: (lambda s: slim(baselines.bound_then_range(s.df.repartition(8, "oid"), s.schema, s.q, s.w, 10, s.sigma, s.schema.names)))(Setup(spark, d, "rental", skew(_RENTAL))))

# ---- updates -----------------------------------------------------------------------------------------------------------
_MOVED = f"{duck_norm('rental')}, d AS (SELECT f.oid, {duck_dist(_RENTAL, skew(_RENTAL))} AS dist FROM f, q, norm)"
query("p2_delete", f"{_MOVED} SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE dist <= 0.4 AND oid % 10 <> 3")(lambda spark, d: (lambda s: slim(updates.delete(s.index(), s.df.where("oid % 10 = 3").select("oid")).range(s.q, s.w, 0.4)))(Setup(spark, d, "rental", skew(_RENTAL))))
query("p4_compact", f"{_MOVED} SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE oid % 10 <> 3 ORDER BY dist, oid LIMIT 20")(lambda spark, d: (lambda s: slim(updates.compact(updates.delete(s.index(depth=3), s.df.where("oid % 10 = 3").select("oid")), 1000).knn(s.q, s.w, 20)))(Setup(spark, d, "rental", skew(_RENTAL))))


@query("p1_insert", duck_range("rental", skew(_RENTAL), 0.4))
def _inserted(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Setup(spark, sf_dir, "rental", skew(_RENTAL))
    late = F.col("oid") % 4 == 1
    return slim(updates.insert(s.of(s.df.where(~late)), s.df.where(late)).range(s.q, s.w, 0.4))


@query("p5_drift")
def _drifted(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Setup(spark, sf_dir, "rental")
    moved = s.df.withColumn("price", F.col("price") * 2)
    return spark.createDataFrame(sorted(updates.drift(s.index(depth=2), moved).items()), "space string, ratio double")


# ---- streams over the events ---------------------------------------------------------------------------------------------
def _arriving(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of objects, with their user and time (UTC)."""
    path, raw = f"{sf_dir}/events.parquet", spark.read.parquet(f"{sf_dir}/events.parquet")
    stream = spark.readStream.schema(raw.schema).option("pathGlobFilter", "events.parquet*").parquet(path if measures.is_folder(spark, path) else sf_dir)
    text = fixtures.FIXTURES["evt"][0](fixtures.Dialect(False)).replace(" FROM events", ", CAST(ts AS TIMESTAMP) AS ts, user_id FROM events")
    return fixtures.run_sql(spark, sf_dir, text, events=stream)


def _days(c: str = "start") -> F.Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm").alias("start")


_EV = f"{duck_scan('evt', ONES['evt'])}, e AS (SELECT d.oid, d.dist, d.value, ts, user_id, event_type, max(ts) OVER () - INTERVAL 1 HOUR AS mark FROM d JOIN events ON event_id = oid)"
_BEST3 = "SELECT strftime(start, '%Y-%m-%d %H:%M') AS start, CAST(row_number() OVER (PARTITION BY start ORDER BY dist, oid) AS INT) AS rank, oid, round(dist, 6) AS mm_dist FROM c QUALIFY rank <= 3"


def _window(slide: str | None) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = Setup(spark, sf_dir, "evt")
        got = streaming.landed(streaming.window_topk(_arriving(spark, sf_dir), s.schema, s.q, s.w, 3, s.sigma, length="1 day", slide=slide))
        return streaming.best_of(got, 3).select(_days("w_start"), "rank", "oid", F.round("dist", 6).alias("mm_dist"))

    return run


query("s3_stream_topk_tumbling", f"{_EV}, c AS (SELECT *, date_trunc('day', ts) AS start FROM e WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= mark) {_BEST3}")(_window(None))
query("s4_stream_topk_sliding", f"{_EV}, c AS (SELECT * FROM (SELECT *, date_trunc('day', ts) + CAST(j AS INT) * INTERVAL 12 HOUR AS start FROM e, generate_series(-1, 1) g(j)) WHERE start <= ts AND ts < start + INTERVAL 1 DAY AND start + INTERVAL 1 DAY <= mark) {_BEST3}")(_window("12 hours"))


@query("s5_stream_session", f"{_EV}, b AS (SELECT *, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM e), g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n_session FROM b) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M') AS start, count(*) AS n, CAST(sum(CAST(round(dist * 1e9) AS BIGINT)) AS BIGINT) AS total FROM g GROUP BY user_id, n_session HAVING max(ts) + INTERVAL 6 HOUR <= max(mark)")
def _sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Setup(spark, sf_dir, "evt")
    got = streaming.landed(streaming.session_distance(_arriving(spark, sf_dir), s.schema, s.q, s.w, s.sigma, gap="6 hours"))
    return got.select("user_id", _days(), "n", "total")


@query("s6_stream_running_topk", duck_knn("evt", ONES["evt"], 20))
def _running(spark: SparkSession, sf_dir: str) -> DataFrame:
    from polymetric.spaces import mm_distance

    s = Setup(spark, sf_dir, "evt")
    scored = _arriving(spark, sf_dir).withColumn("dist", F.expr(mm_distance(s.schema, s.q, s.w, s.sigma)))
    got = streaming.upserted(streaming.running_topk(scored, 20), ["bucket"])
    return slim(streaming.best_of(got, 20))


@query("s8_stream_dedup", "SELECT DISTINCT event_id AS oid FROM events")
def _once(spark: SparkSession, sf_dir: str) -> DataFrame:
    twice = _arriving(spark, sf_dir).select("oid", "ts").withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return streaming.landed(streaming.deduplicated(twice)).select("oid")


@query("s9_stream_stream_join", "SELECT a.event_id AS l_oid, b.event_id AS r_oid FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR AND abs(a.value - b.value) <= 20")
def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    slim_stream = lambda: _arriving(spark, sf_dir).select("oid", "user_id", "ts", "value")
    return streaming.landed(streaming.near_pairs(slim_stream(), slim_stream(), "user_id", "ts", "2 HOURS", "1 hour", "abs(l_value - r_value) <= 20").select("l_oid", "r_oid"))


@query("s1_stream_ingest", duck_range("evt", ONES["evt"], 0.5))
def _ingested(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Half of the events are indexed, the others arrive as a stream; the query sees both."""
    s = Setup(spark, sf_dir, "evt")
    index = s.of(s.df.where("oid % 2 = 1"), depth=3)
    delta = streaming.ingest(_arriving(spark, sf_dir).where("oid % 2 = 0"), index, store.new_folder(spark))
    return slim(updates.with_delta(index, delta).range(s.q, s.w, 0.5))


# ---- experiments -----------------------------------------------------------------------------------------------------------
_ROW = "workload string, fixture string, system string, parameter string, value double, measure string, result double"


def _seconds(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


SETS = ("food", "air", "rental", "syn50")
SHARES = (1, 4, 16)


def hundred(s: Setup) -> DataFrame:
    """The hundred queries that each time is a mean of: stored objects, written once."""
    return once(s.spark, ("hundred", *s.key), lambda: written(s.df.where("oid % 97 = 7").orderBy("oid").limit(100), store.new_folder(s.spark)))


class System:
    """A method with its index built once: seconds and bytes of the build, and searches for a query set."""

    NAMES = ("index", "per_space", "bound_then_range", "scan")

    def __init__(self, s: Setup, name: str):
        self.s, self.name, began = s, name, time.perf_counter()
        if name == "index":
            self.folder = store.new_folder(s.spark)
            self.made = MultiMetricIndex.build(s.df, s.schema, sigma=s.sigma).save(self.folder)
        elif name != "scan":
            self.made = {"per_space": baselines.PerSpaceIndex, "bound_then_range": baselines.BoundThenRange}[name](s.df, s.schema, s.sigma)
            self.folder = self.made.folder
        self.seconds = time.perf_counter() - began
        self.bytes = 0 if name == "scan" else store.size_of(s.spark, self.folder)

    def range(self, queries: DataFrame, w: Mapping[str, float], r: float) -> DataFrame:
        if self.name == "scan":
            return range_batch(self.s.df, queries, self.s.schema, w, r, self.s.sigma)
        return batch.range_queries(self.made, queries, w, r) if self.name == "index" else self.made.range_queries(queries, w, r)

    def knn(self, queries: DataFrame, w: Mapping[str, float], k: int) -> DataFrame:
        if self.name == "scan":
            return knn_batch(self.s.df, queries, self.s.schema, w, k, self.s.sigma)
        return batch.knn_queries(self.made, queries, w, k) if self.name == "index" else self.made.knn_queries(queries, w, k)


def system(s: Setup, name: str) -> System:
    return once(s.spark, ("system", *s.key, name), lambda: System(s, name))


def radii(s: Setup, shares: tuple[int, ...] = SHARES) -> dict[int, float]:
    """The radius within which a query of the hundred finds so many percent of the objects, over all their pairs."""
    def make() -> list[float]:
        if cells.able(s.schema, s.w):
            run = ranks.beside(s.df, hundred(s), s.schema, {x.name: (s.w[x.name], s.sigma[x.name]) for x in s.schema.active(s.w)})
            return [round(x, DIGITS) for x in ranks.order_statistics(run, 1, lambda n: [max(0, -(-x * n // 100) - 1) for x in shares])[0][0]]
        pairs = paired(s.df, hundred(s), s.schema, s.w, s.sigma)
        return pairs.agg(F.percentile_approx("dist", F.array(*(F.lit(x / 100) for x in shares)), F.lit(10_000))).first()[0]

    return dict(zip(shares, once(s.spark, ("radii", *s.key, shares, tuple(s.w.values())), make), strict=True))


#: The per-space baseline makes whole pairs by joins on ids, so it gets ten of the hundred queries; its times are a query's as well. In
#: fifty and more spaces it is as many builds and searches, and is left out; on AIR it is only built.
SLOW = {"per_space": 10}


def _asked(s: Setup, kind: str) -> tuple[DataFrame, int]:
    n = SLOW.get(kind, 100)
    return (hundred(s) if n == 100 else once(s.spark, ("asked", n, *s.key), lambda: written(hundred(s).orderBy("oid").limit(n), store.new_folder(s.spark)))), n


def _kinds(name: str) -> tuple[str, ...]:
    return System.NAMES if name in ("food", "rental") else ("index", "bound_then_range", "scan")


def _timed(workload: str, fixture: str, parameter: str, value: float, made: Mapping[str, tuple[DataFrame, int]]) -> list[tuple]:
    """Rows of seconds a query, queries a second and the first system's lead over each other one; made: (result, number of queries) by system."""
    took = {name: _seconds(df) / n for name, (df, n) in made.items()}
    first = next(iter(took))
    rows = [(workload, fixture, name, parameter, float(value), m, x) for name, t in took.items() for m, x in (("seconds", t), ("throughput", 1 / t))]
    return rows + [(workload, fixture, name, parameter, float(value), f"lead of {first}", t / took[first]) for name, t in took.items() if name != first]


@query("wl1_build_cost")
def _build(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds and megabytes of each system's index on each data set, written to the shared folder."""
    rows = []
    for name in (*SETS, "syn96"):
        s = Setup(spark, sf_dir, name)
        for kind in ("index", "bound_then_range", *(("per_space",) if name in ("food", "air", "rental") else ())):
            made = system(s, kind)
            rows += [("wl1", name, kind, "", 0.0, "seconds", made.seconds), ("wl1", name, kind, "", 0.0, "megabytes", made.bytes / 1e6)]
    return spark.createDataFrame(rows, _ROW)


@query("wl3_range_by_radius")
def _by_radius(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range search of a hundred queries at radii that return 1 to 16 % of the objects: seconds a query, throughput and lead of each
    system on four data sets, the work of the index, and one query on the local indexes with each choice of them."""
    rows = []
    for name in SETS:
        s = Setup(spark, sf_dir, name, skew(fixtures.schema(name)))
        for share, r in radii(s).items():
            rows += _timed("wl3", name, "share", share, {k: ((q := _asked(s, k)) and system(s, k).range(q[0], s.w, r), q[1]) for k in _kinds(name)})
            work = {t["stage"]: t["n"] for t in measures.explain_query(s.index(), s.q, s.w, r).collect()}
            rows += [("wl3", name, "index", "share", float(share), m, work[m] / work["objects"]) for m in ("in_kept_leaves", "after_pigeonhole", "after_pivot_sum", "verified", "results")]
        if name in ("food", "rental"):
            for kind, kinds in _CHOICES.items():
                forest = local_index.Forest(s.index(), kinds)
                rows += [("wl3", name, kind, "share", float(x), "seconds", _seconds(forest.range(s.q, s.w, radii(s)[x]))) for x in (1, 4, 16)]
    return spark.createDataFrame(rows, _ROW)


_CHOICES: dict[str, dict[str, str]] = {"default": {}, "low_as_mtree": {"low": "mtree"}, "high_as_mtree": {"high": "mtree"}}


@query("wl4_knn_by_k")
def _by_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """kNN of a hundred queries: seconds a query, throughput and lead of each system on four data sets."""
    rows = []
    for name in SETS:
        s = Setup(spark, sf_dir, name, skew(fixtures.schema(name)))
        for k in (1, 10, 100):
            rows += _timed("wl4", name, "k", k, {x: ((q := _asked(s, x)) and system(s, x).knn(q[0], s.w, k), q[1]) for x in _kinds(name)})
    return spark.createDataFrame(rows, _ROW)


@query("wl7_throughput_by_cardinality")
def _by_cardinality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A hundred range queries on 20 to 100 % of the objects, each share with an index of its own."""
    rows = []
    for name in ("food", "rental"):
        s = Setup(spark, sf_dir, name, skew(fixtures.schema(name)))
        for j in range(1, 6):
            part = s.df.where(F.col("oid") % 5 < j)
            index = s.of(part).save(store.new_folder(spark))
            bound = baselines.BoundThenRange(part, s.schema, s.sigma)
            r = radii(s)[1]
            rows += _timed("wl7", name, "percent", 20 * j, {"index": (batch.range_queries(index, hundred(s), s.w, r), 100), "bound_then_range": (bound.range_queries(hundred(s), s.w, r), 100), "scan": (range_batch(part, hundred(s), s.schema, s.w, r, s.sigma), 100)})
    return spark.createDataFrame(rows, _ROW)


def _merge_lists(df: DataFrame, queries: DataFrame, schema: MultiMetricSchema, sigma: Mapping[str, float], most: int) -> DataFrame:
    """(qid, oid, need): the least rank of an object in any space's own list, up to ``most``; each list is a batch kNN in one space."""
    lists = [knn_batch(df, queries, schema, {m: float(m == n) for m in schema.names}, most, sigma).select("qid", "oid", "rank") for n in schema.names]
    return reduce(DataFrame.unionByName, lists).groupBy("qid", "oid").agg(F.min("rank").alias("need"))


_D = " + ".join(f"{x!r} * d_{n}" for n, x in skew(_RENTAL).items())
_VM = f"""{duck_norm('rental')}, c AS (SELECT g.oid AS qid, f.oid, {', '.join(f"{s.sql('f.' + s.name, 'g.' + s.name, True)} / s_{s.name} AS d_{s.name}" for s in _RENTAL.spaces)} FROM f, (SELECT * FROM f WHERE {ASK}) g, norm),
    t AS (SELECT qid, oid FROM c QUALIFY row_number() OVER (PARTITION BY qid ORDER BY round({_D}, 9), oid) <= 10),
    l AS ({' UNION ALL '.join(f"SELECT qid, oid, row_number() OVER (PARTITION BY qid ORDER BY round(d_{n}, 9), oid) AS rn FROM c" for n in _RENTAL.names)}), n AS (SELECT qid, oid, min(rn) AS need FROM l GROUP BY ALL)
    SELECT CAST(range AS INT) AS ratio, round(avg(CASE WHEN need <= 10 * range THEN 1.0 ELSE 0.0 END), 6) AS recall FROM t JOIN n USING (qid, oid), range(1, 6) GROUP BY range"""


@query("wl5_vector_merge_recall", _VM)
def _merge_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of merged per-field lists at ratios 1 to 5; an object is found at a ratio if some field ranks it within ratio * k."""
    s = Setup(spark, sf_dir, "rental")
    asked = s.df.where(ASK)
    truth = knn_batch(s.df, asked, s.schema, skew(s.schema), 10, s.sigma).select("qid", "oid")
    need = truth.join(_merge_lists(s.df, asked, s.schema, s.sigma, 50), ["qid", "oid"], "left")
    by = need.select(F.explode(F.sequence(F.lit(1), F.lit(5))).alias("ratio"), "need")
    return by.groupBy("ratio").agg(F.round(F.avg(F.when(F.col("need") <= 10 * F.col("ratio"), 1.0).otherwise(0.0)), 6).alias("recall"))


def by_tasks(spark: SparkSession, n: int, search: Callable[[], DataFrame], run: Callable[[DataFrame], Any] = lambda df: df) -> Any:
    """What ``run`` gives for a search whose objects and queries meet in n tasks. Searches in cells set their own number of partitions, so
    that of the shuffles alone doesn't bind them."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        spark.conf.set("spark.sql.shuffle.partitions", str(n))
        return run(search().coalesce(n))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


@query("wl6_workers")
def _workers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range search by a number of workers: seconds a query with so many tasks at once, and the spread of the objects met by each worker
    when leaves (for bound-then-range: equal parts by hash) are dealt to them."""
    rows = []
    for name in ("food", "rental", "air"):
        s = Setup(spark, sf_dir, name, skew(fixtures.schema(name)))
        r = radii(s)[1]
        index = system(s, "index")
        work = measures.leaf_work(index.made, hundred(s), s.w, r)
        every = 100.0 * sum(b["n_objects"] for b in index.made.boxes)
        for n in (2, 4, 6, 8, 10):
            load = measures.spread_over(work, n)
            rows += [("wl6", name, "index", "workers", float(n), m, float(x)) for m, x in (("stddev", load.std()), ("most", load.max()))]
            rows.append(("wl6", name, "bound_then_range", "workers", float(n), "most", every / n))
        for n in (1, 2, 4, 8):
            rows += [("wl6", name, "index", "tasks", float(n), "seconds", by_tasks(spark, n, lambda: index.range(hundred(s), s.w, r), _seconds) / 100)]  # noqa: B023
    return spark.createDataFrame(rows, _ROW)


@query("wl15_hundred_queries", f"{duck_norm('rental')}, p AS (SELECT g.oid AS qid, f.oid, {duck_dist(_RENTAL, skew(_RENTAL), 'f', 'g')} AS dist FROM f, (SELECT * FROM f WHERE oid % 97 = 7 ORDER BY oid LIMIT 100) g, norm) {_TOP10}")
def _hundred(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Setup(spark, sf_dir, "rental", skew(_RENTAL))
    return _ranked(batch.knn_queries(s.index(), hundred(s), s.w, 10))


@query("wl9_case_study")
def _case(spark: SparkSession, sf_dir: str) -> DataFrame:
    """64 nearest under learned, uniform and hidden weights: mean distance to the query in each space, and means of their values."""
    s, cache, _, _ = _learning(spark, sf_dir)
    truth = written(weights.retrieve(cache, s.schema, skew(s.schema), 64), store.new_folder(spark))
    learned, _ = weights.learn_weights(cache, truth, s.schema, 64, iters=6)
    out = weights.modality_profile({"hidden": truth, "learned": weights.retrieve(cache, s.schema, learned, 64), "uniform": weights.retrieve(cache, s.schema, dict.fromkeys(s.schema.names, 1.0), 64)}, s.schema)
    rows = [(r[0], r[1], "distance", r[2]) for r in out.select("tag", "space", F.round("mean", 6)).collect()]
    numbers = [x.name for x in s.schema.spaces if x.kind == "l1"]
    for tag, w in (("hidden", skew(s.schema)), ("learned", learned), ("uniform", dict.fromkeys(s.schema.names, 1.0))):
        near = knn_scan(s.df, s.schema, s.q, s.schema.weights(w), 64, s.sigma)
        rows += [(tag, n, "value", x) for n, x in near.agg(*(F.round(F.avg(n), 6).alias(n) for n in numbers)).first().asDict().items()]
    return spark.createDataFrame(rows, "tag string, space string, what string, mean double")


def _query_mix(s: Setup, kind: str = "index") -> tuple[list[tuning.Knob], Callable[[Mapping], dict[str, float]]]:
    """A system's knobs, and what a mix of twenty range queries and one kNN takes under a setting: seconds a query, queries a second and, for
    the index, the share of the objects in kept leaves. Each setting is built and run once; a second look gives the same."""
    asked, r = written(hundred(s).limit(20), store.new_folder(s.spark)), radii(s)[1]
    seen: dict[tuple, dict[str, float]] = {}
    knobs = {
        "index": [tuning.Knob("depth", (2, 4, 6)), tuning.Knob("vantages", (1, 2)), tuning.Knob("partitions", (2, 8))],
        "bound_then_range": [tuning.Knob("vantages", (1, 2)), tuning.Knob("partitions", (2, 8))],
        "per_space": [tuning.Knob("depth", (1, 3)), tuning.Knob("partitions", (2, 8))],
    }[kind]

    def build(k: Mapping) -> tuple[Any, Callable[[], DataFrame]]:
        if kind == "index":
            made = s.index(depth=k["depth"], vantages=k["vantages"])
            return made, lambda: batch.range_queries(made, asked, s.w, r)
        made = once(s.spark, ("tuned", kind, *s.key, *sorted(x for x in k.items() if x[0] != "partitions")), lambda: baselines.BoundThenRange(s.df, s.schema, s.sigma, k["vantages"]) if kind == "bound_then_range" else baselines.PerSpaceIndex(s.df, s.schema, s.sigma, k["depth"]))
        return made, lambda: made.range_queries(asked, s.w, r)

    def measure(k: Mapping) -> dict[str, float]:
        key = tuple(sorted(k.items()))
        if key not in seen:
            before = s.spark.conf.get("spark.sql.shuffle.partitions")
            made, run = build(k)
            try:
                s.spark.conf.set("spark.sql.shuffle.partitions", str(k["partitions"]))
                one = min(_seconds(made.knn(s.q, s.w, 10)) for _ in range(2))
                many = min(_seconds(run()) for _ in range(2))
            finally:
                s.spark.conf.set("spark.sql.shuffle.partitions", before)
            seen[key] = {"latency": one, "throughput": 20 / many}
            if kind == "index":
                kept = set(made.keep_leaves(made.query_pivots(s.q), s.w, r))
                seen[key]["kept"] = sum(b["n_objects"] for b in made.boxes if b["leaf_id"] in kept) / sum(b["n_objects"] for b in made.boxes)
        return seen[key]

    return knobs, measure


_LOG = "workload string, fixture string, system string, method string, reward string, step int, latency double, throughput double, best double, gain double"


@query("wl10_tuning_methods")
def _methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fifty steps of the agent, of grid and of random search on the index, and of the agent on the two baselines; gain is what the best
    setting so far saves of the first one's latency. The last row of the agent is the setting that its policy recommends."""
    s, rows = Setup(spark, sf_dir, "food", skew(_FOOD)), []
    for kind, methods in (("index", ("agent", "grid", "random")), ("bound_then_range", ("agent",)), ("per_space", ("agent",))):
        knobs, measure = _query_mix(s, kind)
        for method in methods:
            env = tuning.TuningEnv(knobs, measure)
            agent = tuning.DDPGAgent(len(env.state), len(knobs))
            log = tuning.tune(env, 50, method=method, agent=agent)
            rows += [("wl10", "food", kind, method, "exp", x["step"], x["cost"], x["throughput"], x["best"], 1 - x["best"] / env.start) for x in log]
            if method == "agent":
                got = measure(agent.recommend(env))
                rows.append(("wl10", "food", kind, "recommended", "exp", 51, got["latency"], got["throughput"], got["latency"], 1 - got["latency"] / env.start))
    return spark.createDataFrame(rows, _LOG)


@query("wl11_reward_shapes")
def _shapes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fifty steps of the agent under each reward shape, on two data sets."""
    rows = []
    for name in ("food", "rental"):
        s = Setup(spark, sf_dir, name, skew(fixtures.schema(name)))
        knobs, measure = _query_mix(s)
        for kind in ("base", "exp", "log", "penalty"):
            env = tuning.TuningEnv(knobs, measure)
            rows += [("wl11", name, "index", "agent", kind, x["step"], x["cost"], x["throughput"], x["best"], 1 - x["best"] / env.start) for x in tuning.tune(env, 50, kind)]
    return spark.createDataFrame(rows, _LOG)


@query("wl12_index_choice")
def _choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of the local probes with the default indexes and with covering balls in place of each kind."""
    s = Setup(spark, sf_dir, "food", skew(_FOOD))
    index, rows = s.index(), []
    for system, kinds in _CHOICES.items():
        forest = local_index.Forest(index, kinds)
        forest.candidates(s.q, s.w, 0.8).count()
        began = time.perf_counter()
        n = forest.candidates(s.q, s.w, 0.8).count()
        rows += [("wl12", "food", system, "", 0.0, "seconds", time.perf_counter() - began), ("wl12", "food", system, "", 0.0, "candidates", float(n))]
    return spark.createDataFrame(rows, _ROW)


_W16 = {"ones": ONES["rental"], "skew": skew(_RENTAL), "one_hot": {n: float(n == "loc") for n in _RENTAL.names}, "gaps": {n: float(i % 2 == 0) for i, n in enumerate(_RENTAL.names)}, "small": dict.fromkeys(_RENTAL.names, 0.05)}


@query("wl16_one_index_many_weights", f"{duck_norm('rental')} " + " UNION ALL ".join(f"SELECT * FROM (SELECT '{t}' AS weights, f.oid, round({duck_dist(_RENTAL, w)}, 6) AS mm_dist FROM f, q, norm ORDER BY {duck_dist(_RENTAL, w)}, f.oid LIMIT 10)" for t, w in _W16.items()))
def _many(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Setup(spark, sf_dir, "rental")
    index = s.index()
    return reduce(DataFrame.unionByName, (slim(index.knn(s.q, w, 10)).select(F.lit(t).alias("weights"), "oid", "mm_dist") for t, w in _W16.items()))


@query("wl13_one_modality_or_all", f"{duck_scan('quad', ONES['quad'])}, best AS (SELECT oid FROM d ORDER BY dist, oid LIMIT 10) " + " UNION ALL ".join(f"SELECT '{s.name}' AS space, round(avg(CASE WHEN oid IN (SELECT oid FROM best) THEN 1.0 ELSE 0.0 END), 6) AS recall FROM (SELECT d.oid FROM d, q ORDER BY round({s.sql('d.' + s.name, 'q.' + s.name, True)}, 9), d.oid LIMIT 10)" for s in _QUAD.spaces))
def _motive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many of the ten nearest in all modalities a search in one modality finds."""
    s = Setup(spark, sf_dir, "quad")
    best = knn_scan(s.df, s.schema, s.q, s.w, 10, s.sigma).select("oid", F.lit(1.0).alias("hit"))
    parts = [baselines.space_top(s.df, s.schema, s.q, n, 10).select("oid").join(best, "oid", "left").agg(F.round(F.avg(F.coalesce("hit", F.lit(0.0))), 6).alias("recall")).select(F.lit(n).alias("space"), "recall") for n in s.schema.names]
    return reduce(DataFrame.unionByName, parts)


query("wl2_update_cost")(lambda spark, d: (lambda s: spark.createDataFrame([(label, *updates.update_cost(s.index(), s.df.where(f"oid % {m} = 7").select("oid"), s.df.where(f"oid % {m} = 7"), s.q, s.w, 0.4).values()) for label, m in (("0.1", 1000), ("1", 100))], "percent string, update_ms double, query_delta_ms double"))(Setup(spark, d, "rental", skew(_RENTAL))))


@query("o5_index_as_source", f"{duck_scan('food', skew(_FOOD))} SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE dist <= 0.8")
def _source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The index is saved, and read again by its format's name; its leaves were chosen by the boxes."""
    s = Setup(spark, sf_dir, "food", skew(_FOOD))
    index, folder = s.index(depth=3), store.new_folder(spark)
    index.save(folder)
    sources.register(spark)
    kept = index.keep_leaves(index.query_pivots(s.q), s.w, 0.8)
    found = spark.read.format("polymetric").option("leaves", ",".join(map(str, kept))).load(folder)
    return slim(range_scan(found, s.schema, s.q, s.w, 0.8, s.sigma))


#: Experiments that build several indexes and time them come after everything else.
for _name in ("wl12_index_choice", "wl2_update_cost", "wl7_throughput_by_cardinality", "wl4_knn_by_k", "wl3_range_by_radius", "wl6_workers", "wl10_tuning_methods", "wl11_reward_shapes", "wl1_build_cost"):
    QUERIES[_name] = QUERIES.pop(_name)
