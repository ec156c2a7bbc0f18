"""The methods and workloads as queries over the given tables, each with its DuckDB SQL where SQL can express it.

Indexed paths share the brute-force SQL: same answer, another plan.
"""

from __future__ import annotations

from collections.abc import Callable, Mapping

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from polymetric import baselines, bounds, cells, fixtures, local_index, measures, operators, streaming, tuning, weights
from polymetric import sql as mm_sql
from polymetric.index import MultiMetricIndex, knn_batch, knn_scan, leaf_boxes, map_to_pivots, paired, range_batch, range_scan, select_pivots
from polymetric.normalize import fit_normaliser, norm_table
from polymetric.rewards import reward_sql
from polymetric.spaces import MultiMetricSchema, check_metric, query_row
from polymetric.store import new_folder, once, written

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
#: The stored object that serves as the query, and fixed settings of each fixture: radius and weights.
QID = 7
RADIUS = {"rental": 1.1, "food": 2.5, "air": 2.6, "quad": 1.3, "syn50": 22.0, "syn96": 40.0, "evt": 0.9, "tiny": 1.0}
SKEW = (0.9, 0.05, 0.6, 0.1, 0.3)


def skew(schema: MultiMetricSchema) -> dict[str, float]:
    return {n: SKEW[i % 5] for i, n in enumerate(schema.names)}


def query(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def top(fixture: str) -> int:
    return 2 if fixture == "tiny" else QID


# ---- DuckDB side -------------------------------------------------------------------------------------------------
def duck_norm(name: str, schema: MultiMetricSchema | None = None) -> str:
    """f: the fixture, norm: one row of sigmas s_<space>, q: the query row."""
    s = schema or fixtures.schema(name)
    sig = ", ".join(f"CASE WHEN quantile_cont(d_{x.name}, 0.5) > 0 THEN 2 * quantile_cont(d_{x.name}, 0.5) ELSE 1.0 END AS s_{x.name}" for x in s.spaces)
    each = ", ".join(f"{x.sql('f.' + x.name, 'a.' + x.name, True)} AS d_{x.name}" for x in s.spaces)
    return f"""WITH f AS MATERIALIZED ({fixtures.duck_sql(name)}), a AS (SELECT * FROM f ORDER BY (oid * 7919 + 104729) % 1000003, oid LIMIT 16),
    norm AS (SELECT {sig} FROM (SELECT {each} FROM f, a)), q AS (SELECT * FROM f WHERE oid = {top(name)})"""


def duck_dist(schema: MultiMetricSchema, w: Mapping[str, float], a: str = "f", b: str = "q") -> str:
    return "round(" + " + ".join(f"{w[s.name]!r} * {s.sql(f'{a}.{s.name}', f'{b}.{s.name}', True)} / s_{s.name}" for s in schema.active(w)) + ", 9)"


def duck_scan(name: str, w: Mapping[str, float]) -> str:
    return f"{duck_norm(name)}, d AS (SELECT f.*, {duck_dist(fixtures.schema(name), w)} AS dist FROM f, q, norm)"


def duck_range(name: str, w: Mapping[str, float], r: float) -> str:
    return f"{duck_scan(name, w)} SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE dist <= {r}"


def duck_knn(name: str, w: Mapping[str, float], k: int) -> str:
    return f"{duck_scan(name, w)} SELECT oid, round(dist, 6) AS mm_dist FROM d ORDER BY dist, oid LIMIT {k}"


# ---- helpers -------------------------------------------------------------------------------------------------------
class Setup:
    """A fixture with its schema, normaliser, weights and query. The normaliser and each index are made once in an application; an
    index is saved, and queries read it from where it was saved."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, w: Mapping[str, float] | None = None):
        self.spark, self.key = spark, (sf_dir, name)
        self.df, self.schema = fixtures.load(spark, sf_dir, name), fixtures.schema(name)
        self.sigma = once(spark, ("sigma", *self.key), lambda: fit_normaliser(self.df, self.schema))
        self.q = once(spark, ("q", *self.key), lambda: query_row(self.df, self.schema, top(name)))
        self.w, self.r = self.schema.weights(w), RADIUS[name]

    def index(self, **options) -> MultiMetricIndex:  # noqa: ANN003
        return once(self.spark, ("index", *self.key, *sorted(options.items())), lambda: MultiMetricIndex.build(self.df, self.schema, sigma=self.sigma, **options).save(new_folder(self.spark)))

    def of(self, df: DataFrame, **options) -> MultiMetricIndex:  # noqa: ANN003
        """An index of other rows under this normaliser."""
        return MultiMetricIndex.build(df, self.schema, sigma=self.sigma, **options)


def slim(df: DataFrame) -> DataFrame:
    return df.select("oid", F.round("dist", 6).alias("mm_dist"))


def share_radii(df: DataFrame, asked: DataFrame, schema: MultiMetricSchema, w: Mapping[str, float], sigma: Mapping[str, float], percents: tuple[int, ...]) -> DataFrame:
    """(qid, r<percent>): exact percentiles of each query's distances to all rows, in one Arrow task for a block of queries where the rows fit
    in it, else of all pairs in SQL."""
    if cells.able(schema, w) and cells.one_cell(df, schema, w):
        found = cells.shares(df, asked, schema, w, sigma, [x / 100 for x in percents])
        return found.select("qid", *(F.round(F.when(~F.isnan(f"r{j}"), F.col(f"r{j}")), 6).alias(f"r{x}") for j, x in enumerate(percents)))
    return paired(df, asked, schema, w, sigma).groupBy("qid").agg(*(F.round(F.percentile("dist", F.lit(x / 100)), 6).alias(f"r{x}") for x in percents))


ONES: dict[str, dict[str, float]] = {n: dict.fromkeys(fixtures.schema(n).names, 1.0) for n in fixtures.FIXTURES}

# ---- normaliser, distances ----------------------------------------------------------------------------------------
for _name in ("rental", "food", "air", "quad", "evt", "tiny"):
    def _norms(spark: SparkSession, sf_dir: str, name: str = _name) -> DataFrame:
        return norm_table(fixtures.load(spark, sf_dir, name), fixtures.schema(name)).select("space", F.round("sigma", 6).alias("sigma"))

    query(f"n1_median_norm_{_name}", f"{duck_norm(_name)} " + " UNION ALL ".join(f"SELECT '{s.name}' AS space, round(s_{s.name}, 6) AS sigma FROM norm" for s in fixtures.schema(_name).spaces))(_norms)

_s4 = fixtures.schema("rental")
query("n2_median_norm_allpairs", f"WITH f AS MATERIALIZED ({fixtures.duck_sql("quad")}) " + " UNION ALL ".join(f"(SELECT '{s.name}' AS space, round(COALESCE(NULLIF(2 * quantile_cont({s.sql('f.' + s.name, 'g.' + s.name, True)}, 0.5), 0), 1.0), 6) AS sigma FROM f, f g)" for s in fixtures.schema("quad").spaces))(
    lambda spark, d: norm_table(fixtures.load(spark, d, "quad"), fixtures.schema("quad"), pairs="all").select("space", F.round("sigma", 6).alias("sigma"))
)
for _policy, _agg in (("max", "max({0})"), ("mean", "avg({0})"), ("none", "1.0")):
    query(f"n4_norm_policy_{_policy}", f"{duck_norm('rental')} " + " UNION ALL ".join(f"(SELECT '{s.name}' AS space, round({_agg.format(s.sql('f.' + s.name, 'a.' + s.name, True))}, 6) AS sigma FROM f, a" + (" LIMIT 1)" if _policy == "none" else ")") for s in _s4.spaces))(
        lambda spark, d, p=_policy: norm_table(fixtures.load(spark, d, "rental"), _s4, policy=p).select("space", F.round("sigma", 6).alias("sigma"))
    )

_DISTANCES = {"d1_l1_scalar": ("rental", "price", "l1", None), "d2_l1_vector_narrow": ("rental", "size", "l1v", 2), "d2_l1_vector_wide": ("food", "picture", "l1v", 64), "d3_l2_vector": ("rental", "loc", "l2v", 2), "d4_edit": ("food", "labels", "edit", None), "d5_discrete": ("rental", "review", "discrete", None), "d7_angular": ("food", "picture", "angular", 64), "d8_linf": ("food", "picture", "linf", 64), "d8_hamming": ("rental", "size", "hamming", 2)}
for _key, (_fx, _col, _kind, _width) in _DISTANCES.items():
    _sp = MultiMetricSchema.of((_col, _kind, _width)).spaces[0]
    def _dist(spark: SparkSession, sf_dir: str, fx: str = _fx, sp=_sp) -> DataFrame:  # noqa: ANN001
        df = fixtures.load(spark, sf_dir, fx)
        q = F.broadcast(df.where(F.col("oid") == QID).select(F.col(sp.name).alias("q_")))
        return df.join(q).select("oid", F.expr(f"round({sp.sql(sp.name, 'q_')}, 6)").alias("d"))

    query(_key, f"WITH f AS MATERIALIZED ({fixtures.duck_sql(_fx)}) SELECT f.oid, round({_sp.sql('f.' + _col, 'q.' + _col, True)}, 6) AS d FROM f, f q WHERE q.oid = {QID}")(_dist)

_words = MultiMetricSchema.of(("words", "jaccard")).spaces[0]
query("d6_jaccard", f"WITH f AS (SELECT oid, string_split(labels, ' ') AS words FROM ({fixtures.duck_sql('food')})) SELECT f.oid, round({_words.sql('f.words', 'q.words', True)}, 6) AS d FROM f, f q WHERE q.oid = {QID}")(
    lambda spark, d: (lambda f: f.join(F.broadcast(f.where(f"oid = {QID}").select(F.col("words").alias("q_")))).select("oid", F.expr(f"round({_words.sql('words', 'q_')}, 6)").alias("d")))(fixtures.load(spark, d, "food").select("oid", F.split("labels", " ").alias("words")))
)
for _space in ("price", "loc", "review"):
    query(f"d10_metric_axioms_{_space}", "SELECT 'x' AS rule, 0::BIGINT AS a, 0::BIGINT AS b, 0::BIGINT AS c WHERE false")(lambda spark, d, n=_space: check_metric(fixtures.load(spark, d, "rental"), next(s for s in _s4.spaces if s.name == n)))

# ---- range and kNN -------------------------------------------------------------------------------------------------
for _name in ("rental", "food", "air", "quad", "evt", "tiny"):
    for _wname, _w in (("ones", ONES[_name]), ("skew", skew(fixtures.schema(_name)))):
        _r = RADIUS[_name] * (1 if _wname == "ones" else 0.4)
        query(f"q1_range_scan_{_name}_{_wname}", duck_range(_name, _w, _r))(lambda spark, d, n=_name, w=_w, r=_r: (lambda s: slim(range_scan(s.df, s.schema, s.q, s.w, r, s.sigma)))(Setup(spark, d, n, w)))
        query(f"k1_knn_scan_{_name}_{_wname}", duck_knn(_name, _w, 10))(lambda spark, d, n=_name, w=_w: (lambda s: slim(knn_scan(s.df, s.schema, s.q, s.w, 10, s.sigma)))(Setup(spark, d, n, w)))
query("k1_knn_scan_syn50", duck_knn("syn50", ONES["syn50"], 10))(lambda spark, d: (lambda s: slim(knn_scan(s.df, s.schema, s.q, s.w, 10, s.sigma)))(Setup(spark, d, "syn50")))

for _name in ("rental", "food"):
    _w = skew(fixtures.schema(_name))
    _r = RADIUS[_name] * 0.4
    for _rule in ("weighted_sum", "scaled_any", "uniform_all", "none"):
        query(f"q2_range_{_name}_{_rule}", duck_range(_name, _w, _r))(lambda spark, d, n=_name, w=_w, r=_r, p=_rule: (lambda s: slim(s.index().range(s.q, s.w, r, prune=p)))(Setup(spark, d, n, w)))
    query(f"q2_range_{_name}_pigeonhole", duck_range(_name, _w, _r))(lambda spark, d, n=_name, w=_w, r=_r: (lambda s: slim(s.index().range(s.q, s.w, r, local="pigeonhole")))(Setup(spark, d, n, w)))
    for _tree in ("str", "rstar"):
        query(f"g6_range_{_name}_{_tree}", duck_range(_name, _w, _r))(lambda spark, d, n=_name, w=_w, r=_r, t=_tree: (lambda s: slim(s.index(tree=t).range(s.q, s.w, r)))(Setup(spark, d, n, w)))
    for _k in (1, 10, 50):
        query(f"k2_knn_{_name}_{_k}", duck_knn(_name, _w, _k))(lambda spark, d, n=_name, w=_w, k=_k: (lambda s: slim(s.index().knn(s.q, s.w, k)))(Setup(spark, d, n, w)))
    query(f"k2_knn_{_name}_per_space_seed", duck_knn(_name, _w, 10))(lambda spark, d, n=_name, w=_w: (lambda s: slim(s.index().knn(s.q, s.w, 10, seed="per_space")))(Setup(spark, d, n, w)))
    query(f"k4_knn_{_name}_medoid", duck_knn(_name, _w, 10))(lambda spark, d, n=_name, w=_w: (lambda s: slim(s.index().knn(s.q, s.w, 10, centre="medoid")))(Setup(spark, d, n, w)))
    query(f"k4_knn_{_name}_mindist", duck_knn(_name, _w, 10))(lambda spark, d, n=_name, w=_w: (lambda s: slim(s.index().knn(s.q, s.w, 10, centre="mindist", seeds=3)))(Setup(spark, d, n, w)))
query("m3_knn_switched_off_spaces", duck_knn("food", {n: float(i % 2 == 0) for i, n in enumerate(fixtures.schema("food").names)}, 20))(lambda spark, d: (lambda s: slim(s.index().knn(s.q, s.w, 20)))(Setup(spark, d, "food", {n: float(i % 2 == 0) for i, n in enumerate(fixtures.schema("food").names)})))

_BATCH = "oid % 97 = 7 AND oid < 97 * 30"  # the 30 training queries of the experiment
#: Searches, distances and recalls are asked by every row whose id is divisible by 20.
ASK = "oid % 20 = 0"
_duck_asked = f"{duck_norm('rental')}, p AS (SELECT g.oid AS qid, f.oid, {duck_dist(_s4, skew(_s4), 'f', 'g')} AS dist FROM f, (SELECT * FROM f WHERE {ASK}) g, norm)"
query("q3_range_batch", f"{_duck_asked} SELECT qid, oid, round(dist, 6) AS mm_dist FROM p WHERE dist <= 0.15")(lambda spark, d: (lambda s: range_batch(s.df, s.df.where(ASK), s.schema, s.w, 0.15, s.sigma).select("qid", "oid", F.round("dist", 6).alias("mm_dist")))(Setup(spark, d, "rental", skew(_s4))))
query("k3_knn_batch", f"{_duck_asked} SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY dist, oid) AS INT) AS rank, oid, round(dist, 6) AS mm_dist FROM p QUALIFY rank <= 50")(lambda spark, d: (lambda s: knn_batch(s.df, s.df.where(ASK), s.schema, s.w, 50, s.sigma).select("qid", "rank", "oid", F.round("dist", 6).alias("mm_dist")))(Setup(spark, d, "rental", skew(_s4))))
query("q4_radius_for_share", f"{_duck_asked} SELECT qid, " + ", ".join(f"round(quantile_cont(dist, {x / 100}), 6) AS r{x}" for x in (1, 2, 4, 8, 16)) + " FROM p GROUP BY qid")(lambda spark, d: (lambda s: share_radii(s.df, s.df.where(ASK), s.schema, s.w, s.sigma, (1, 2, 4, 8, 16)))(Setup(spark, d, "rental", skew(_s4))))
query("m2_distance_pairs", f"{duck_norm('quad')} SELECT g.oid AS qid, f.oid, " + ", ".join(f"round({s.sql('f.' + s.name, 'g.' + s.name, True)} / s_{s.name}, 6) AS d_{s.name}" for s in fixtures.schema("quad").spaces) + f" FROM f, (SELECT * FROM f WHERE {ASK}) g, norm")(lambda spark, d: (lambda s: weights.cache_distances(s.df, s.df.where(ASK), s.schema, s.sigma).select("qid", "oid", *(F.round(f"d_{n}", 6).alias(f"d_{n}") for n in s.schema.names)))(Setup(spark, d, "quad")))

# ---- pivots and bounds -------------------------------------------------------------------------------------------
query("g1_pivot_farthest", f"WITH f AS MATERIALIZED ({fixtures.duck_sql('rental')}), o AS (SELECT * FROM f ORDER BY oid LIMIT 1) " + " UNION ALL ".join(f"SELECT * FROM (SELECT '{s.name}' AS space, f.oid FROM f, o ORDER BY round({s.sql('f.' + s.name, 'o.' + s.name, True)}, 9) DESC, f.oid LIMIT 1)" for s in _s4.spaces))(
    lambda spark, d: spark.createDataFrame([(n, p[0]["oid"]) for n, p in select_pivots(fixtures.load(spark, d, "rental"), _s4).items()], "space string, oid long")
)


def _given(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = fixtures.load(spark, sf_dir, "tiny")
    got = map_to_pivots(df, fixtures.schema("tiny"), select_pivots(df, fixtures.schema("tiny"), given=[2, 4, 7]))
    return got.select("oid", *(F.round(f"v_{n}_0", 6).alias(f"v_{n}") for n in fixtures.schema("tiny").names))


_t = fixtures.schema("tiny").spaces
query("g3_g4_pivot_map_given", f"WITH f AS MATERIALIZED ({fixtures.duck_sql('tiny')}) SELECT f.oid, " + ", ".join(f"round({s.sql('f.' + s.name, f'p{i}.' + s.name, True)}, 6) AS v_{s.name}" for i, s in enumerate(_t)) + " FROM f, f p0, f p1, f p2 WHERE p0.oid = 2 AND p1.oid = 4 AND p2.oid = 7")(_given)
query("g9_leaf_boxes_cover")(lambda spark, d: leaf_boxes(Setup(spark, d, "rental").index().objects, _s4).select("leaf_id", "n_objects"))
query("g12_load_balance")(lambda spark, d: measures.balance(Setup(spark, d, "rental").index(), (2, 4, 6, 8, 10)))
query("e11_e12_explain_query")(lambda spark, d: (lambda s: measures.explain_query(s.index(), s.q, s.w, 0.4))(Setup(spark, d, "rental", skew(_s4))))

_wl = {n: 0.05 for n in _s4.names}
for _key, _test in {
    "b4_pigeonhole": lambda s, r: bounds.pigeonhole(s.schema, s.q, s.w, s.sigma, r),
    "b7_single_space": lambda s, r: bounds.single_space(s.schema, s.q, s.w, s.sigma, r),
    "b8_pigeonhole_general": lambda s, r: bounds.pigeonhole(s.schema, s.q, s.w, s.sigma, r, {n: i + 1 for i, n in enumerate(s.schema.names)}),
    "b10_early_stop": lambda s, r: bounds.early_stop(s.schema, s.q, s.w, s.sigma, r),
}.items():
    query(_key, duck_range("rental", _wl, 0.06))(lambda spark, d, t=_test: (lambda s: slim(range_scan(s.df.where(t(s, 0.06)), s.schema, s.q, s.w, 0.06, s.sigma)))(Setup(spark, d, "rental", _wl)))
query("b1_uniform_rule_guarded", duck_range("rental", _wl, 0.06))(lambda spark, d: (lambda s: slim(s.index().range(s.q, s.w, 0.06, prune="uniform_all")))(Setup(spark, d, "rental", _wl)))
query("b6_pivot_sum", duck_range("rental", _wl, 0.06))(lambda spark, d: (lambda s: slim(s.index(vantages=4).range(s.q, s.w, 0.06, local="sum")))(Setup(spark, d, "rental", _wl)))

def bound_index(s: Setup) -> baselines.BoundThenRange:
    return once(s.spark, ("bound", *s.key), lambda: baselines.BoundThenRange(s.df, s.schema, s.sigma))


def per_space(s: Setup) -> baselines.PerSpaceIndex:
    return once(s.spark, ("per space", *s.key), lambda: baselines.PerSpaceIndex(s.df, s.schema, s.sigma))


# ---- baselines -----------------------------------------------------------------------------------------------------
for _name in ("rental", "food"):
    _w = skew(fixtures.schema(_name))
    _sch = fixtures.schema(_name)
    query(f"bl2_bound_then_range_{_name}", duck_knn(_name, _w, 10))(lambda spark, d, n=_name, w=_w: (lambda s: slim(bound_index(s).knn(s.q, s.w, 10)))(Setup(spark, d, n, w)))
    query(f"bl2_bound_then_range_unindexed_{_name}", duck_knn(_name, _w, 10))(lambda spark, d, n=_name, w=_w: (lambda s: slim(baselines.bound_then_range(s.df, s.schema, s.q, s.w, 10, s.sigma)))(Setup(spark, d, n, w)))
    query(f"bl2_range_{_name}", duck_range(_name, _w, RADIUS[_name] * 0.4))(lambda spark, d, n=_name, w=_w: (lambda s: slim(bound_index(s).range(s.q, s.w, s.r * 0.4)))(Setup(spark, d, n, w)))
    for _ratio in range(1, 6):
        _lists = " UNION ".join(f"SELECT * FROM (SELECT d.oid FROM d, q ORDER BY round({s.sql('d.' + s.name, 'q.' + s.name, True)}, 9), d.oid LIMIT {10 * _ratio})" for s in _sch.spaces)
        query(f"bl4_vector_merge_{_name}_{_ratio}", f"{duck_scan(_name, _w)}, c AS ({_lists}) SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE oid IN (SELECT oid FROM c) ORDER BY dist, oid LIMIT 10")(lambda spark, d, n=_name, w=_w, x=_ratio: (lambda s: slim(baselines.vector_merge(s.df, s.schema, s.q, s.w, 10, x, s.sigma)))(Setup(spark, d, n, w)))
    _both = " INTERSECT ".join(f"SELECT * FROM (SELECT d.oid FROM d, q ORDER BY round({s.sql('d.' + s.name, 'q.' + s.name, True)}, 9), d.oid LIMIT 400)" for s in _sch.spaces)
    query(f"bl6_isolated_intersection_{_name}", f"{duck_scan(_name, _w)}, c AS ({_both}) SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE oid IN (SELECT oid FROM c) ORDER BY dist, oid LIMIT 10")(lambda spark, d, n=_name, w=_w: (lambda s: slim(baselines.isolated_intersection(s.df, s.schema, s.q, s.w, 10, 400, s.sigma)))(Setup(spark, d, n, w)))
query("bl3_per_space_range", duck_range("rental", skew(_s4), 0.3))(lambda spark, d: (lambda s: slim(per_space(s).range(s.q, s.w, 0.3)))(Setup(spark, d, "rental", skew(_s4))))
query("bl3_per_space_knn", duck_knn("rental", skew(_s4), 10))(lambda spark, d: (lambda s: slim(per_space(s).knn(s.q, s.w, 10)))(Setup(spark, d, "rental", skew(_s4))))
query("bl5_vector_concat", duck_knn("air", ONES["air"], 10))(lambda spark, d: (lambda s: slim(baselines.vector_concat(s.df, s.schema, s.q, s.w, 10, s.sigma)))(Setup(spark, d, "air")))
for _i, _n in enumerate(fixtures.schema("quad").names):
    query(f"bl7_single_modality_{_n}", duck_knn("quad", {_n: 1.0} | {m: 0.0 for m in fixtures.schema("quad").names if m != _n}, 10))(lambda spark, d, n=_n: (lambda s: slim(knn_scan(s.df, s.schema, s.q, s.w, 10, s.sigma)))(Setup(spark, d, "quad", {n: 1.0})))

# ---- weights -------------------------------------------------------------------------------------------------------
_W0 = dict(zip(_s4.names, (0.5, 0.5, 0.5, 0.5, 0.5), strict=True))
_duck_cache = f"""{duck_norm('rental')}, c AS (SELECT g.oid AS qid, f.oid, {', '.join(f"{s.sql('f.' + s.name, 'g.' + s.name, True)} / s_{s.name} AS d_{s.name}" for s in _s4.spaces)} FROM f, (SELECT * FROM f WHERE {_BATCH}) g, norm),
    t AS (SELECT qid, oid FROM c QUALIFY row_number() OVER (PARTITION BY qid ORDER BY round({' + '.join(f'{x!r} * d_{n}' for n, x in skew(_s4).items())}, 9), oid) <= 50),
    r AS (SELECT qid, oid FROM c QUALIFY row_number() OVER (PARTITION BY qid ORDER BY round({' + '.join(f'{x!r} * d_{n}' for n, x in _W0.items())}, 9), oid) <= 50)"""


def _learning(spark: SparkSession, sf_dir: str, name: str = "rental") -> tuple[Setup, DataFrame, DataFrame, DataFrame]:
    """The distances of the example queries to all rows are computed once and read by each iteration."""
    s = Setup(spark, sf_dir, name)
    cache = once(spark, ("distances", *s.key), lambda: written(weights.cache_distances(s.df, s.df.where(_BATCH), s.schema, s.sigma), new_folder(spark)))
    w0 = dict.fromkeys(s.schema.names, 0.5)
    return s, cache, weights.retrieve(cache, s.schema, skew(s.schema), 50), weights.retrieve(cache, s.schema, w0, 50)


query("w1_truth", f"{_duck_cache} SELECT qid, oid FROM t")(lambda spark, d: _learning(spark, d)[2].select("qid", "oid"))
query("w2_retrieve", f"{_duck_cache} SELECT qid, oid FROM r")(lambda spark, d: _learning(spark, d)[3].select("qid", "oid"))
_POS = {"truth": "SELECT * FROM t", "intersection": "SELECT * FROM t INTERSECT SELECT * FROM r", "union": "SELECT * FROM t UNION SELECT * FROM r"}
for _mode, _sql in _POS.items():
    query(f"w3_w4_samples_{_mode}", f"{_duck_cache} SELECT qid, oid, true AS is_pos FROM ({_sql}) UNION ALL SELECT qid, oid, false FROM (SELECT * FROM r EXCEPT SELECT * FROM t)")(lambda spark, d, m=_mode: (lambda s, c, t, f: weights.sample(c, s.schema, f, t, m).select("qid", "oid", "is_pos"))(*_learning(spark, d)))
_mass = "exp(-(" + " + ".join(f"0.5 * d_{n}" for n in _s4.names) + "))"
query("w6_w7_loss_gradient", f"""{_duck_cache}, s AS (SELECT c.*, t.oid IS NOT NULL AS is_pos, {_mass} AS m FROM c LEFT JOIN t USING (qid, oid) WHERE t.oid IS NOT NULL OR (qid, oid) IN (SELECT qid, oid FROM r)),
    g AS (SELECT qid, sum(m) AS a, sum(CASE WHEN is_pos THEN m ELSE 0 END) AS p, {', '.join(f"sum(d_{n} * m) AS m_{n}, sum(CASE WHEN is_pos THEN d_{n} * m ELSE 0 END) AS p_{n}" for n in _s4.names)} FROM s GROUP BY qid HAVING count(*) FILTER (is_pos) > 0 AND count(*) FILTER (NOT is_pos) > 0)
    SELECT round(avg(-ln(p / a)), 6) AS loss, {', '.join(f"round(avg(-(m_{n} / a - p_{n} / p)), 6) AS g_{n}" for n in _s4.names)} FROM g""")(
    lambda spark, d: (lambda s, c, t, f: weights.loss_grad(weights.sample(c, s.schema, f, t), s.schema, _W0).select(F.round("loss", 6).alias("loss"), *(F.round(f"g_{n}", 6).alias(f"g_{n}") for n in s.schema.names)))(*_learning(spark, d))
)
query("w10_recall", f"{_duck_cache} SELECT qid, round(avg(CASE WHEN (qid, oid) IN (SELECT qid, oid FROM r) THEN 1.0 ELSE 0.0 END), 6) AS recall FROM t GROUP BY qid")(lambda spark, d: (lambda s, c, t, f: weights.recall(f, t).select("qid", F.round("recall", 6).alias("recall")))(*_learning(spark, d)))
query("w13_modality_profile", f"{_duck_cache} " + " UNION ALL ".join(f"SELECT '{tag}' AS tag, '{n}' AS space, round(avg(d_{n}), 6) AS mean FROM c JOIN {x} USING (qid, oid)" for tag, x in (("demonstration", "t"), ("uniform", "r")) for n in _s4.names))(lambda spark, d: (lambda s, c, t, f: weights.modality_profile({"demonstration": t, "uniform": f}, s.schema).select("tag", "space", F.round("mean", 6).alias("mean")))(*_learning(spark, d)))


@query("w8_w11_learning_curves")
def _curves(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loss, recall and seconds of each iteration up to 90 % recall, with both kinds of negatives, on two data sets."""
    rows = []
    for name in ("rental", "food"):
        s, cache, truth, _ = _learning(spark, sf_dir, name)
        truth = written(truth, new_folder(spark))
        for neg in ("knn", "random"):
            rows += [(name, neg, *h) for h in weights.learn_weights(cache, truth, s.schema, 50, iters=12, negatives=neg, target=0.9)[1]]
    return spark.createDataFrame(rows, "fixture string, negatives string, iter int, loss double, recall double, seconds double")


# ---- rewards -------------------------------------------------------------------------------------------------------
for _kind in ("base", "exp", "log", "penalty"):
    _grid = "(CAST(a.n_nationkey AS DOUBLE) - 12) / 10"
    _text = f"SELECT x0, x1, round({reward_sql('x0', 'x1', _kind)}, 6) + CAST(0 AS DOUBLE) AS reward FROM (SELECT {_grid} AS x0, {_grid.replace('a.', 'b.')} AS x1 FROM nation a CROSS JOIN nation b) g"
    query(f"r_reward_{_kind}", _text)(lambda spark, d, t=_text: fixtures.run_sql(spark, d, t))

# ---- measures and workloads ------------------------------------------------------------------------------------------
for _j in range(1, 6):
    query(f"wl7_cardinality_{20 * _j}", f"{duck_scan('rental', ONES['rental'])} SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE dist <= 1.1 AND oid % 5 < {_j}")(lambda spark, d, j=_j: (lambda s: slim(range_scan(s.df.where(F.col("oid") % 5 < j), s.schema, s.q, s.w, 1.1, s.sigma)))(Setup(spark, d, "rental")))
for _k in (1, 5, 10, 20, 50, 100):
    query(f"wl4_knn_k{_k}", duck_knn("rental", ONES["rental"], _k))(lambda spark, d, k=_k: (lambda s: slim(s.index().knn(s.q, s.w, k)))(Setup(spark, d, "rental")))
for _mod, _label in ((1000, "0.1"), (100, "1")):
    query(f"wl2_update_{_label}", f"{duck_norm('rental')}, u AS (SELECT * REPLACE (CASE WHEN oid % {_mod} = 7 THEN price + 1000 ELSE price END AS price) FROM f), d AS (SELECT u.oid, {duck_dist(_s4, skew(_s4), 'u')} AS dist FROM u, q, norm) SELECT oid, round(dist, 6) AS mm_dist FROM d WHERE dist <= 0.4")(lambda spark, d, m=_mod: measures.after_update(Setup(spark, d, "rental", skew(_s4)), m, 0.4))
query("wl14_tiny_range", duck_range("tiny", ONES["tiny"], 0.5))(lambda spark, d: (lambda s: slim(range_scan(s.df, s.schema, s.q, s.w, 0.5, s.sigma)))(Setup(spark, d, "tiny")))

# ---- local indexes, SQL surface, streams, tuning -------------------------------------------------------------------------
for _fx, _sp in (("rental", "price"), ("rental", "loc"), ("food", "picture"), ("food", "labels")):
    _s = next(x for x in fixtures.schema(_fx).spaces if x.name == _sp)
    query(f"li1_hidden_dimension_{_sp}", f"WITH f AS MATERIALIZED ({fixtures.duck_sql(_fx)}), a AS (SELECT * FROM f ORDER BY (oid * 7919 + 104729) % 1000003, oid LIMIT 16), d AS (SELECT {_s.sql('f.' + _sp, 'a.' + _sp, True)} AS d FROM f, a) SELECT round(avg(d) * avg(d) / (2 * var_pop(d)), 6) AS hd FROM d")(lambda spark, d, fx=_fx, s=_s: local_index.hidden_dimension(fixtures.load(spark, d, fx), s).select(F.round("hd", 6).alias("hd")))
for _key, _kinds in {"li14_forest": {}, "v1_low_as_mtree": {"low": "mtree"}, "v2_high_as_mtree": {"high": "mtree"}}.items():
    _w = skew(fixtures.schema("food"))
    query(f"{_key}_range", duck_range("food", _w, 0.8))(lambda spark, d, w=_w, k=_kinds: (lambda s: slim(local_index.Forest(s.index(), k).range(s.q, s.w, 0.8)))(Setup(spark, d, "food", w)))
    query(f"{_key}_knn", duck_knn("food", _w, 10))(lambda spark, d, w=_w, k=_kinds: (lambda s: slim(local_index.Forest(s.index(), k).knn(s.q, s.w, 10)))(Setup(spark, d, "food", w)))
query("li1b_forest_global_choice", duck_range("food", skew(fixtures.schema("food")), 0.8))(lambda spark, d: (lambda s: slim(local_index.Forest(s.index(), scope="global").range(s.q, s.w, 0.8)))(Setup(spark, d, "food", skew(fixtures.schema("food")))))
query("b5_pigeonhole_nodes", duck_range("rental", _wl, 0.06))(lambda spark, d: (lambda s: slim(local_index.Forest(s.index()).range(s.q, s.w, 0.06)))(Setup(spark, d, "rental", _wl)))


def _local(p: Setup, kind: str, space) -> local_index._Local:  # noqa: ANN001
    return once(p.spark, ("local", *p.key, kind, space.name), lambda: local_index._KINDS[kind](p.index().objects, space))


for _fx, _sp, _cls, _t in (("rental", "price", "rtree", 20000.0), ("rental", "loc", "rtree", 2.0), ("food", "picture", "rtree", 8.0), ("food", "picture", "mvp", 8.0), ("food", "picture", "mtree", 8.0), ("food", "labels", "inverted", 6.0), ("rental", "size", "mtree", 10.0), ("rental", "review", "mvp", 3.0)):
    _s = next(x for x in fixtures.schema(_fx).spaces if x.name == _sp)
    _d = _s.sql("f." + _sp, "q." + _sp, True)
    query(f"li_{_cls}_range_{_sp}", f"WITH f AS MATERIALIZED ({fixtures.duck_sql(_fx)}) SELECT f.oid FROM f, f q WHERE q.oid = {QID} AND {_d} <= {_t}")(lambda spark, d, fx=_fx, s=_s, c=_cls, t=_t: (lambda p: _local(p, c, s).range(p.q[s.name], t).select("oid"))(Setup(spark, d, fx)))
    query(f"li_{_cls}_knn_{_sp}", f"WITH f AS MATERIALIZED ({fixtures.duck_sql(_fx)}) SELECT f.oid, round({_d}, 6) AS d FROM f, f q WHERE q.oid = {QID} ORDER BY {_d}, f.oid LIMIT 25")(lambda spark, d, fx=_fx, s=_s, c=_cls: (lambda p: _local(p, c, s).knn(p.q[s.name], 25).select("oid", F.round("d", 6).alias("d")))(Setup(spark, d, fx)))

_w9 = ", ".join(str(x) for x in skew(fixtures.schema("food")).values())
for _key, _text, _sqltext in (
    ("x1_sql_range", f"SELECT brand, count(*) AS n FROM {{t}} WHERE oid IN MM_RANGE({QID}, array({_w9}), 1.0) GROUP BY brand", f"SELECT brand, count(*) AS n FROM d WHERE dist <= 1.0 GROUP BY brand"),
    ("x2_sql_knn", f"SELECT oid, brand FROM {{t}} WHERE oid IN MM_KNN({QID}, array({_w9}), 20) -- MM_KNN(", "SELECT oid, brand FROM d ORDER BY dist, oid LIMIT 20"),
    ("x4_sql_learned_weights", f"SELECT oid FROM {{t}} WHERE oid IN MM_KNN({QID}, MM_WEIGHTS('mine'), 20)", "SELECT oid FROM d ORDER BY dist, oid LIMIT 20"),
    ("x5_sql_knn_then_filter", f"SELECT oid FROM {{t}} WHERE type = 'SMALL' AND oid IN MM_KNN({QID}, array({_w9}), 50)", "SELECT oid FROM (SELECT * FROM d ORDER BY dist, oid LIMIT 50) WHERE type = 'SMALL'"),
    ("x5_sql_knn_where", f"SELECT oid FROM {{t}} WHERE oid IN MM_KNN({QID}, array({_w9}), 20, WHERE => 'type = ''SMALL''')", "SELECT oid FROM d WHERE type = 'SMALL' ORDER BY dist, oid LIMIT 20"),
):
    def _sqlq(spark: SparkSession, sf_dir: str, text: str = _text) -> DataFrame:
        s = Setup(spark, sf_dir, "food")
        index = s.index()
        index.weights["mine"] = skew(s.schema)
        return mm_sql.sql(text, index, t=s.df)

    query(_key, f"{duck_scan('food', skew(fixtures.schema('food')))} {_sqltext}")(_sqlq)


@query("x1_sql_range_object", duck_range("tiny", ONES["tiny"], 0.5))
def _object(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The query object is written in the statement; it equals the second object of the example."""
    s = Setup(spark, sf_dir, "tiny")
    found = mm_sql.sql("""SELECT oid FROM {t} WHERE oid IN MM_RANGE(OBJECT('{"picture": [1, 2, 1], "loc": [1.0, 1], "review": "quiet sunny flat"}'), array(1, 1, 1), 0.5)""", s.index(), t=s.df)
    return slim(range_scan(s.df, s.schema, s.q, s.w, 1e9, s.sigma).join(found, "oid"))


query("x5_sql_filter_then_knn", f"{duck_scan('food', skew(fixtures.schema('food')))} SELECT oid FROM d WHERE type = 'SMALL' ORDER BY dist, oid LIMIT 20")(lambda spark, d: (lambda s: knn_scan(s.df.where("type = 'SMALL'"), s.schema, s.q, s.w, 20, s.sigma).select("oid"))(Setup(spark, d, "food", skew(fixtures.schema("food")))))


@query("s2_stream_range", duck_range("evt", ONES["evt"], 0.5))
def _alerts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events arrive as a stream of files; the objects of the batch fixture are derived on the way."""
    s = Setup(spark, sf_dir, "evt")
    raw = spark.read.parquet(f"{sf_dir}/events.parquet")
    stream = spark.readStream.schema(raw.schema).option("pathGlobFilter", "events.parquet*").parquet(f"{sf_dir}/events.parquet" if measures.is_folder(spark, f"{sf_dir}/events.parquet") else sf_dir)
    objects = fixtures.run_sql(spark, sf_dir, fixtures.FIXTURES["evt"][0](fixtures.Dialect(False)), events=stream)
    return slim(streaming.drain(streaming.range_alerts(objects, s.df.where(F.col("oid") == QID), s.schema, s.w, 0.5, s.sigma), "mm_alerts"))


@query("t_f_tuning_log")
def _tuned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counted cost, so that runs repeat: leaves kept plus objects verified by a range query, over depth, vantages and prune rule."""
    s = Setup(spark, sf_dir, "rental", skew(_s4))
    made: dict[tuple, float] = {}

    def cost(k: Mapping) -> float:
        key = (k["depth"], k["prune"])
        if key not in made:
            index = s.index(depth=k["depth"])
            kept = index.keep_leaves(index.query_pivots(s.q), s.w, 0.3, k["prune"])
            made[key] = len(index.boxes) + sum(b["n_objects"] for b in index.boxes if b["leaf_id"] in set(kept))
        return made[key]

    env = tuning.TuningEnv([tuning.Knob("depth", (2, 4, 6)), tuning.Knob("prune", ("none", "scaled_any", "weighted_sum"))], cost)
    rows = [(r["step"], str(r["settings"]), float(r["cost"]), float(r["reward"]), float(r["best"])) for r in tuning.tune(env, 50)]
    return spark.createDataFrame(rows, "step int, settings string, cost double, reward double, best double")


QUERIES |= operators.QUERIES
ORACLES |= operators.ORACLES
