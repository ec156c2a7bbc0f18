"""Bounds never lose a result, trees hold their members, rewards and learning behave, queries agree with DuckDB."""

import random

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from polymetric import distances, fixtures, index, queries, rstar, sql, tuning
from polymetric.normalize import norm_table
from polymetric.rewards import reward
from polymetric.spaces import MultiMetricSchema, distance, query_row

SF = "/root/testdata/sf0.001"
CHECKED = ["q2_range_rental_weighted_sum", "q2_range_food_scaled_any", "k2_knn_rental_10", "bl3_per_space_knn", "bl4_vector_merge_food_2", "b6_pivot_sum", "li14_forest_knn", "x5_sql_knn_then_filter", "w6_w7_loss_gradient", "wl2_update_1", "o18_cube", "s2_stream_range", "x1_sql_range_object", "x5_sql_knn_where", "li_rtree_knn_loc", "li_mvp_knn_picture", "li_mtree_range_picture", "li_inverted_knn_labels", "bl2_range_food", "wl15_hundred_queries", "m2_distance_pairs"]


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_oracle(spark, name):
    got = entry.queries()[name](spark, SF).toPandas()
    c = duckdb.connect()
    for t in fixtures.TABLES:
        c.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    want = c.sql(entry.oracle_sql()[name]).df()
    rows = lambda x: sorted(map(str, x[sorted(x.columns)].astype(object).where(x.notna(), None).itertuples(index=False, name=None)))
    assert rows(got) == rows(want)


def test_leaf_rules_keep_every_result_and_the_unscaled_any_rule_does_not():
    rng = np.random.default_rng(0)
    x = rng.random((2000, 3))
    lost = 0
    for w in ((0.2, 0.5, 0.3), (0.05, 0.05, 0.05), (1.0, 0.0, 0.4), (0.02, 0.01, 0.03)):
        q, r, w = np.array([0.05, 0.95, 0.05]), 0.3 * sum(w), np.array(w)
        boxes = rstar.str_pack(x, 50)
        for g in boxes:
            gap = np.clip(np.maximum(g.min(0) - q, q - g.max(0)), 0, None)
            hits = (np.abs(g - q) @ w <= r).any()
            if hits:
                assert w @ gap <= r + 1e-9 and all(w * gap <= r + 1e-9)
                lost += bool((gap > r).all())  # the rule that keeps a box with some unweighted gap within r drops this one
    assert sum(len(g) for g in boxes) == 2000
    assert lost > 0


@pytest.mark.parametrize("most", [4, 16])
def test_rstar_tree_holds_all_and_walk_is_complete(most):
    rng = np.random.default_rng(1)
    x = rng.random((400, 3))
    t = rstar.RStarTree(3, most)
    for v in x:
        t.insert(v)
    leaves = t.leaves()
    assert sorted(map(tuple, np.concatenate([n.kids for n in leaves]))) == sorted(map(tuple, x))
    assert all(len(n.kids) <= most and (n.lo <= np.array(n.kids)).all() and (n.hi >= np.array(n.kids)).all() for n in leaves)
    w, q = np.array([0.5, 0.2, 1.0]), rng.random(3)
    found = {tuple(k) for n in t.walk(q, w, 0.2) for k in n.kids}
    assert {tuple(v) for v in x if (np.abs(v - q) * w).sum() <= 0.2} <= found


def test_index_answers_do_not_depend_on_the_plan(spark):
    s = queries.Setup(spark, SF, "rental", queries.skew(fixtures.schema("rental")))
    want = sorted(r["oid"] for r in queries.slim(queries.range_scan(s.df, s.schema, s.q, s.w, 0.4, s.sigma)).collect())
    for depth, local in ((2, "sum"), (6, "pigeonhole"), (4, "pigeonhole+sum")):
        assert sorted(r["oid"] for r in s.index(depth=depth).range(s.q, s.w, 0.4, local=local).collect()) == want
    k = [r["oid"] for r in s.index(depth=6).knn(s.q, s.w, 10).collect()]
    assert k == [r["oid"] for r in queries.knn_scan(s.df, s.schema, s.q, s.w, 10, s.sigma).collect()]
    assert s.index().knn(s.q, s.w, 10_000).count() == s.df.count()


def test_range_query_plan_has_no_shuffle_of_objects(spark, tmp_path):
    s = queries.Setup(spark, SF, "rental", queries.skew(fixtures.schema("rental")))
    index = s.index()
    index.save(str(tmp_path))
    found = index.load(spark, str(tmp_path)).range(s.q, s.w, 0.2)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "PartitionFilters: [leaf_id" in plan.replace("isnotnull(leaf_id#", "leaf_id#") or "leaf_id" in plan
    assert found.count() == queries.range_scan(s.df, s.schema, s.q, s.w, 0.2, s.sigma).count()


def test_twins_agree_with_sql(spark):
    df, schema = fixtures.load(spark, SF, "food"), fixtures.schema("food")
    a, b = query_row(df, schema, 7), query_row(df, schema, 8)
    ones = dict.fromkeys(schema.names, 1.0)
    got = queries.range_scan(df.where("oid = 8"), schema, a, ones, 1e18, ones).first()["dist"]
    assert abs(got - distance(schema, a, b, ones, ones)) < 1e-6
    assert distances.TWINS["edit"]("kitten", "sitting") == 3


def test_weights_are_checked():
    schema = MultiMetricSchema.of(("a", "l1"), ("b", "l1"))
    for bad in ({"a": 0, "b": 0}, {"a": -1}, {"a": float("nan")}, {"c": 1}, {"a": 2}):
        with pytest.raises(ValueError):
            schema.weights(bad)


def test_tiny_example(spark):
    s = queries.Setup(spark, SF, "tiny")
    assert sorted(r["oid"] for r in s.index(depth=1).range(s.q, s.w, 0.5).collect()) == [2, 3]
    assert [r["oid"] for r in s.index(depth=1).knn(s.q, s.w, 1).collect()] == [2]


def test_predicates_in_strings_and_comments_stay(spark):
    s = queries.Setup(spark, SF, "tiny")
    text, frames = sql.rewrite("SELECT 'MM_KNN(1)' /* MM_RANGE( */ FROM t WHERE oid IN MM_RANGE(2, array(1, 1, 1), 0.5)", s.index(depth=1))
    assert "'MM_KNN(1)' /* MM_RANGE( */" in text and len(frames) == 1


def test_reward_shapes():
    assert reward(0.2, -1.5) == 0 and reward(0.2, -1.5, clip=False) > 0
    assert reward(0.3, 0.1, "exp") > reward(0.1, 0.1, "exp") > 0 > reward(-0.1, 0.1, "exp")
    assert reward(0.2, -0.1, "penalty") < reward(0.2, -0.1)
    assert abs(reward(0.2, 0.1, "log")) < abs(reward(0.2, 0.1, "log_as_printed"))


@pytest.mark.parametrize("method", ["agent", "random", "grid"])
def test_tuning_gains_on_a_counted_cost(method):
    random.seed(0)
    knobs = [tuning.Knob("a", tuple(range(9))), tuning.Knob("b", tuple(range(5)))]
    env = tuning.TuningEnv(knobs, lambda k: 10.0 + (k["a"] - 7) ** 2 + (k["b"] - 1) ** 2)
    log = tuning.tune(env, 50, method=method)
    assert len(log) == 50 and log[-1]["best"] <= 0.85 * env.start


def test_edit_distance_reads_whole_texts(spark):
    rng = random.Random(5)
    for _ in range(200):
        a, b = ("".join(rng.choice("abc ") for _ in range(rng.randrange(90))) for _ in "ab")
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            left, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                left, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, left + (x != y))
        assert distances.TWINS["edit"](a, b) == row[-1]
    distances.register_edit(spark)
    space = MultiMetricSchema.of(("text", "edit", distances.LONG)).spaces[0]
    df = spark.read.parquet(f"{SF}/documents.parquet").where("length(text) > 1000").limit(8)
    got = df.selectExpr(f"{space.sql('text', repr('same opening of two reports'))} AS d", "text").collect()
    assert got and all(r["d"] == distances.TWINS["edit"](r["text"], "same opening of two reports") for r in got)


def test_a_saved_index_is_loaded_by_its_path(spark, tmp_path):
    s = queries.Setup(spark, SF, "food", queries.skew(fixtures.schema("food")))
    built = queries.MultiMetricIndex.build(s.df, s.schema, sigma=s.sigma, depth=3)
    built.weights["mine"] = s.w
    built.save(str(tmp_path))
    again = queries.MultiMetricIndex.load(spark, str(tmp_path))
    assert (again.sigma, again.schema, again.weights) == (built.sigma, built.schema, built.weights)
    rows = lambda i: [tuple(r) for r in i.knn(7, s.w, 20).select("oid", "dist").collect()]
    assert rows(again) == rows(built) and sorted(b["leaf_id"] for b in again.boxes) == sorted(b["leaf_id"] for b in built.boxes)


def test_inner_boxes_keep_what_the_leaves_keep():
    rng = np.random.default_rng(7)
    for n in (1, 5, 8, 9, 70, 900):
        lo = rng.random((n, 3))
        boxes = [{"leaf_id": i} | {f"{k}_{c}": float(v[j]) for k, v in (("lo", lo[i]), ("hi", lo[i] + 0.02)) for j, c in enumerate("abc")} for i in range(n)]
        inner = index.InnerBoxes(boxes, list("abc"))
        q = rng.random(3)
        keep = lambda a, b, q=q: np.clip(np.maximum(a - q, q - b), 0, None).sum(axis=1) <= 0.15
        kept, tested = inner.walk(keep)
        assert kept == [i for i in range(n) if keep(lo[i : i + 1], lo[i : i + 1] + 0.02)[0]]
        assert n < 900 or tested < n


def test_deep_trees_route_as_shallow_ones(spark):
    schema = MultiMetricSchema.of(("a", "l1"), ("b", "l1"))
    rows = spark.range(4000).selectExpr("id AS oid", "CAST(id * 7919 % 1009 AS DOUBLE) AS v_a_0", "CAST(id * 104729 % 997 AS DOUBLE) AS v_b_0")
    x = rows.toPandas()[["v_a_0", "v_b_0"]].to_numpy()
    splits = rstar.kd_splits(x, 9)
    by = {k: (a, c) for k, a, c in splits}

    def leaf(v):
        k = 0
        while k in by:
            k = 2 * k + (1 if v[by[k][0]] <= by[k][1] else 2)
        return k

    got = [r[0] for r in rows.selectExpr(f"CAST({index.kd_leaf(schema, splits)} AS INT) AS leaf").collect()]
    assert got == [leaf(v) for v in x]


def test_a_tuned_policy_recommends_and_gains():
    env = tuning.TuningEnv([tuning.Knob("a", tuple(range(9))), tuning.Knob("b", tuple(range(9)))], lambda k: {"latency": 1 + (k["a"] - 6) ** 2 + (k["b"] - 2) ** 2, "throughput": 1.0, "kept": 0.5})
    agent = tuning.DDPGAgent(len(env.state), 2)
    log = tuning.tune(env, 50, agent=agent)
    assert tuning.gain(log, env.start) > 0.15 and set(agent.recommend(env)) == {"a", "b"}


def test_median_of_all_pairs_has_no_limit_of_rows(spark, monkeypatch):
    schema, rows = MultiMetricSchema.of(("a", "l1"), ("b", "l1"), ("c", "l1")), [(i, float(i * i % 97), float(i // 90), 1.0) for i in range(101)]
    want = [2 * float(np.median(np.abs(np.subtract.outer(x, x)))) or 1.0 for x in np.array(rows).T[1:]]
    df = spark.createDataFrame(rows, "oid long, a double, b double, c double")
    for few, sketch in ((20_000, 1e-4), (3, 0.02)):
        monkeypatch.setattr("polymetric.normalize.FEW_VALUES", few)
        monkeypatch.setattr("polymetric.normalize.SKETCH", sketch)
        assert [(r["sigma"], r["n_pairs"]) for r in norm_table(df, schema, pairs="all").collect()] == [(x, 101**2) for x in want]
    wide = spark.range(5001).selectExpr("id AS oid", "CAST(id % 3 AS DOUBLE) AS a")
    assert norm_table(wide, MultiMetricSchema.of(("a", "l1")), pairs="all").first()["sigma"] == 2.0


@pytest.mark.parametrize(("name", "table", "column", "share"), [("q4_radius_for_share", "orders", "qid", 20), ("o8_join_equi_inner", "orders", "o_orderkey", 1)])
def test_results_grow_with_the_table(spark, name, table, column, share):
    keys = spark.read.parquet(f"{SF}/{table}.parquet").where(f"o_orderkey % {share} = 0")
    assert entry.queries()[name](spark, SF).select(column).distinct().count() == keys.count()
