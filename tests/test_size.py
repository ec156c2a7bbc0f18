"""What only larger tables show, brought down to small ones."""

import random
import statistics

import pytest
from polymetric import batch, cells, index, normalize, updates
from polymetric.spaces import MultiMetricSchema, distance


@pytest.mark.parametrize("n", [60_000, 60_001])
def test_medians_stay_exact_when_an_interval_is_narrowed_more_than_once(spark, monkeypatch, n):
    monkeypatch.setattr(normalize, "FEW_VALUES", 12)
    monkeypatch.setattr(normalize, "SKETCH", 1e-3)
    rnd = random.Random(3)
    rows = [(rnd.random(), rnd.random() ** 9, float(i % 7), 1.0 * (i > n // 2) * rnd.random()) for i in range(n)]
    found, counted = normalize.medians(spark.createDataFrame(rows, "d_even double, d_steep double, d_few double, d_tied double").repartition(4), ["even", "steep", "few", "tied"])
    want = {k: statistics.median(r[i] for r in rows) for i, k in enumerate(("even", "steep", "few", "tied"))}
    assert counted == n and found == pytest.approx(want, abs=1e-12)


def test_medians_pass_over_distances_that_are_null(spark):
    rows = [(None if i % 3 else float(i * i),) for i in range(999)]
    assert normalize.medians(spark.createDataFrame(rows, "d_a double"), ["a"]) == ({"a": 498.0**2}, 999)


def test_an_interval_that_lost_the_middle_is_widened_by_the_counts(spark, monkeypatch):
    monkeypatch.setattr(normalize, "FEW_VALUES", 12)
    monkeypatch.setattr(normalize, "POINTS", [0.9, 0.95, 1.0])  # of all shares, those that never hold the middle rows
    rows = [(float(i * i),) for i in range(5001)]
    assert normalize.medians(spark.createDataFrame(rows, "d_a double").repartition(4), ["a"])[0]["a"] == 2500.0**2


def test_the_range_scan_skips_costly_distances_that_the_cheap_ones_rule_out(spark, monkeypatch):
    schema = MultiMetricSchema.of(("a", "l1"), ("t", "edit"))
    w, sigma = {"a": 1.0, "t": 0.5}, {"a": 2.0, "t": 3.0}
    rows = [(i, float(i % 7), "red blue green".split()[i % 3] * (1 + i % 2)) for i in range(60)]
    df = spark.createDataFrame(rows, "oid long, a double, t string")
    got = index.range_batch(df, df.where("oid % 20 = 0"), schema, w, 0.6, sigma)
    far = lambda x, y: distance(schema, {"a": x[1], "t": x[2]}, {"a": y[1], "t": y[2]}, w, sigma)
    assert {(r["qid"], r["oid"]): r["dist"] for r in got.collect()} == {(x[0], y[0]): far(x, y) for x in rows[::20] for y in rows if far(x, y) <= 0.6}
    tests = []
    monkeypatch.setattr(index.bounds, "staged", lambda *a: tests.append(a) or "true")
    index.range_batch(df, df, schema, w, 0.6, sigma)
    assert tests  # the test that comes before the distance


def test_new_rows_find_the_nearest_of_many_leaves_without_a_join_of_rows_and_leaves(spark):
    schema = MultiMetricSchema.of(("a", "l1"), ("v", "l2v", 2))
    rnd = random.Random(5)
    rows = [(i, float(rnd.randrange(400)), [float(rnd.randrange(60)), float(rnd.randrange(60))]) for i in range(3000)]
    built = index.MultiMetricIndex.build(spark.createDataFrame(rows, "oid long, a double, v array<double>"), schema, depth=9, sigma={"a": 7.0, "v": 3.0})
    new = [(i, x * 1.5 - 50, y) for i, x, y in rows[::3]] + [(9001, None, [1.0, 2.0]), (9002, 3.0, None), (9003, None, None)]
    placed = updates.place(built, spark.createDataFrame(new, "oid long, a double, v array<double>"))
    plan = placed._jdf.queryExecution().executedPlan().toString()
    assert len(built.boxes) > 256 and "Join" not in plan and "Cartesian" not in plan and "Exchange" not in plan

    def far(r, b):
        gaps = (0.0 if r[f"v_{n}_0"] is None else max(0.0, b[f"lo_{n}"] - r[f"v_{n}_0"], r[f"v_{n}_0"] - b[f"hi_{n}"]) / built.sigma[n] for n in schema.names)
        return sum(gaps), b["leaf_id"]

    got = placed.collect()
    assert len(got) == len(new) and all(r["leaf_id"] == min(built.boxes, key=lambda b: far(r, b))["leaf_id"] for r in got)
    more = {r["leaf_id"]: r["n_objects"] for r in updates.widened(built, placed).collect()}
    assert sum(more.values()) == len(rows) + len(new)


def test_a_range_scan_of_many_queries_shuffles_nothing_and_finds_all(spark, monkeypatch):
    schema = MultiMetricSchema.of(("a", "l1"), ("v", "l2v", 2), ("t", "edit"))
    w, sigma = {"a": 1.0, "v": 0.3, "t": 0.5}, {"a": 2.0, "v": 1.5, "t": 3.0}
    rnd = random.Random(7)
    rows = [(i, float(rnd.randrange(40)), [float(rnd.randrange(9)), float(rnd.randrange(9))], "red blue green".split()[i % 3] * (1 + i % 2)) for i in range(900)]
    rows += [(900, None, [1.0, 1.0], "red"), (901, 1.0, None, "red"), (902, 1.0, [1.0, 1.0], None)]
    df = spark.createDataFrame(rows, "oid long, a double, v array<double>, t string").repartition(3)
    want = {(r["qid"], r["oid"], r["dist"]) for r in index.paired(df, df.where("oid % 3 = 0"), schema, w, sigma).where("dist <= 0.9").collect()}
    monkeypatch.setattr(index, "FEW_QUERIES", 10)
    monkeypatch.setattr(cells, "CELL_NUMBERS", 800)  # blocks of 100 queries, cells of 100 rows
    monkeypatch.setattr(cells, "OUT_ROWS", 50)
    got = index.range_batch(df, df.where("oid % 3 = 0"), schema, w, 0.9, sigma)
    assert {tuple(r) for r in got.select("qid", "oid", "dist").collect()} == want and len(want) > 900
    stored = spark.createDataFrame(rows, "oid long, a double, v array<double>, t string").coalesce(1)
    assert "Exchange" not in index.range_batch(stored, df.where("oid % 3 = 0"), schema, w, 0.9, sigma)._jdf.queryExecution().executedPlan().toString()
    assert index.range_batch(df, df.where("oid < 0"), schema, w, 0.9, sigma).count() == 0
    monkeypatch.setattr(index, "FEW_QUERIES", -1)
    assert index.range_batch(df, df.where("oid < 0"), schema, w, 0.9, sigma).count() == index.range_batch(df.where("oid < 0"), df, schema, w, 0.9, sigma).count() == 0


def test_indexed_range_searches_in_blocks_deal_the_objects_once(spark, monkeypatch):
    schema = MultiMetricSchema.of(("a", "l1"), ("t", "edit"))
    w, sigma = {"a": 1.0, "t": 0.5}, {"a": 2.0, "t": 3.0}
    rows = [(i, float(i * 7 % 90), "red blue green".split()[i % 3] * (1 + i % 2)) for i in range(600)]
    df = spark.createDataFrame(rows, "oid long, a double, t string")
    built = index.MultiMetricIndex.build(df, schema, depth=5, sigma=sigma)
    monkeypatch.setattr(cells, "CELL_NUMBERS", 800)  # blocks of 100 queries and pools of about 100 objects
    far = lambda x, y: distance(schema, {"a": x[1], "t": x[2]}, {"a": y[1], "t": y[2]}, w, sigma)
    got = batch.range_queries(built, df.where("oid % 2 = 0"), w, 0.6)
    assert {(r["qid"], r["oid"]): r["dist"] for r in got.collect()} == {(x[0], y[0]): far(x, y) for x in rows[::2] for y in rows if far(x, y) <= 0.6}
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert len(batch.pools(built, w)) > 3 and "Generate" not in plan  # no copies of objects for blocks, nor of queries for cells
