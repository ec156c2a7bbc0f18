"""The searches by whole arrays against brute force."""

import random

import numpy as np
import pyarrow as pa
import pytest
from polymetric import batch, cells, index, queries, workloads
from polymetric.distances import _levenshtein
from polymetric.spaces import MultiMetricSchema, distance

SCHEMA = MultiMetricSchema.of(("a", "l1"), ("s", "l1v", 2), ("p", "l2v", 2), ("t", "edit"), ("v", "l1v", 20))
W, SIGMA = {"a": 0.9, "s": 0.05, "p": 0.6, "t": 0.3, "v": 0.2}, {"a": 2.0, "s": 3.0, "p": 1.5, "t": 4.0, "v": 7.0}
KIND = "oid long, a double, s array<double>, p array<double>, t string, v array<double>"


def rows(n=240, seed=5):
    rnd = random.Random(seed)
    one = lambda: (rnd.random() * 5, [float(rnd.randrange(4)) for _ in range(2)], [rnd.random(), rnd.random()], "".join(rnd.choices("abé ", k=rnd.choice((0, 3, 9, 64, 70)))), [rnd.random() for _ in range(20)])
    made = [one() for _ in range(n * 3 // 4)]
    return [(i, *(made[i] if i < len(made) else made[i % 7])) for i in range(n)]  # the last quarter are copies


def brute(table, w=W):
    as_dict = lambda r: dict(zip(SCHEMA.names, r[1:], strict=True))
    return {(x[0], y[0]): distance(SCHEMA, as_dict(x), as_dict(y), w, SIGMA) for x in table if x[0] % 20 == 0 for y in table}


@pytest.mark.parametrize("w", [W, {"a": 0.0, "s": 0.0, "p": 0.0, "t": 1.0, "v": 0.0}, {"a": 0.0, "s": 1.0, "p": 0.0, "t": 0.0, "v": 0.0}])
def test_batch_knn_by_cells_gives_the_rows_of_brute_force_with_ties_by_id(spark, monkeypatch, w):
    monkeypatch.setattr(index, "met", None)  # all pairs aren't met
    monkeypatch.setattr(cells, "CELL_NUMBERS", 27 * 90)  # three strips
    monkeypatch.setattr(cells, "BLOCK_QUERIES", 5)
    monkeypatch.setattr(cells, "PACK", 8)
    table = rows()
    df, far = spark.createDataFrame(table, KIND), brute(table, w)
    for k in (3, 30, 500):
        got = sorted((r["qid"], r["rank"], r["oid"], r["dist"]) for r in index.knn_batch(df, df.where("oid % 20 = 0"), SCHEMA, w, k, SIGMA).collect())
        want = [(q, j + 1, o, d) for q in range(0, 240, 20) for j, (d, o) in enumerate(sorted((d, o) for (x, o), d in far.items() if x == q)[:k])]
        assert [x[:3] for x in got] == [x[:3] for x in want] and [x[3] for x in got] == pytest.approx([x[3] for x in want], abs=1e-9)


def test_range_by_cells_finds_every_pair(spark):
    table = rows()
    df, far = spark.createDataFrame(table, KIND), brute(table)
    got = cells.grid(df, df.where("oid % 20 = 0"), SCHEMA, W, SIGMA, r=1.1)
    assert {(r["qid"], r["oid"]) for r in got.collect()} == {p for p, d in far.items() if d <= 1.1}


def test_a_missing_distance_comes_last(spark):
    df = spark.createDataFrame([(0, 1.0), (1, None), (2, 5.0), (20, 2.0)], "oid long, a double")
    got = index.knn_batch(df, df.where("oid = 0"), MultiMetricSchema.of(("a", "l1")), {"a": 1.0}, 9, {"a": 1.0}).orderBy("rank").collect()
    assert [(r["oid"], r["dist"]) for r in got] == [(0, 0.0), (20, 1.0), (2, 4.0), (1, None)]


def test_edit_distances_by_words_are_those_of_the_table():
    rnd = random.Random(1)
    texts = ["".join(rnd.choices("abcñ", k=n)) for n in (*range(12), 63, 64, 65, 130)]
    made = cells.Texts(texts)
    assert all(made.far(b).tolist() == [_levenshtein(a, b) for a in texts] for b in texts)


def test_of_copies_only_the_least_ids_stay():
    t = pa.table({"oid": list(range(99, -1, -1)), "a": [float(i % 3) for i in range(100)]})
    assert sorted(cells.fewest(t, list(MultiMetricSchema.of(("a", "l1")).spaces), "oid", 2)["oid"].to_pylist()) == sorted(sorted(i for i in range(100) if (99 - i) % 3 == m)[j] for m in range(3) for j in range(2))


def test_routed_batches_meet_in_cells_of_leaves(spark, monkeypatch):
    monkeypatch.setattr(batch, "_meet", None)  # pairs don't meet in SQL
    monkeypatch.setattr(cells, "CELL_NUMBERS", 27 * 70)  # pools of 70 rows
    table = rows()
    df, far = spark.createDataFrame(table, KIND), brute(table)
    made = index.MultiMetricIndex.build(df, SCHEMA, depth=4, sigma=SIGMA)
    few = df.where("oid % 20 = 0")
    assert len(batch.pools(made, W)) > 1
    got = batch.range_queries(made, few, W, 1.1)
    assert sorted((r["qid"], r["oid"]) for r in got.collect()) == sorted(p for p, d in far.items() if d <= 1.1)
    for k in (4, 300):
        near = sorted((r["qid"], r["rank"], r["oid"]) for r in batch.knn_queries(made, few, W, k).collect())
        assert near == [(q, j + 1, o) for q in range(0, 240, 20) for j, (d, o) in enumerate(sorted((d, o) for (x, o), d in far.items() if x == q)[:k])]


def test_radii_for_shares_are_exact_percentiles_without_all_pairs_in_sql(spark, monkeypatch):
    monkeypatch.setattr(queries, "paired", None)
    table = rows()
    df, far = spark.createDataFrame(table, KIND), brute(table)
    got = {r["qid"]: (r["r1"], r["r16"], r["r100"]) for r in queries.share_radii(df, df.where("oid % 20 = 0"), SCHEMA, W, SIGMA, (1, 16, 100)).collect()}
    want = {q: tuple(np.quantile([d for (x, _), d in far.items() if x == q], [0.01, 0.16, 1.0])) for q in range(0, 240, 20)}
    assert got.keys() == want.keys() and all(got[q] == pytest.approx(want[q], abs=2e-6) for q in want)


def test_merged_lists_come_from_a_search_in_each_space(spark, monkeypatch):
    monkeypatch.setattr(index, "met", None)
    table = [r[:2] + (r[4],) for r in rows(80)]
    schema, sigma = MultiMetricSchema.of(("a", "l1"), ("t", "edit")), {"a": 2.0, "t": 4.0}
    df = spark.createDataFrame(table, "oid long, a double, t string")
    got = {(r["qid"], r["oid"]): r["need"] for r in workloads._merge_lists(df, df.where("oid % 20 = 0"), schema, sigma, 9).collect()}
    want = {}
    for q in table[::20]:
        for far in (lambda x: abs(x[1] - q[1]) / 2, lambda x: _levenshtein(x[2], q[2]) / 4):
            for j, x in enumerate(sorted(table, key=lambda x: (round(far(x), 9), x[0]))[:9]):
                want[q[0], x[0]] = min(j + 1, want.get((q[0], x[0]), 99))
    assert got == want
