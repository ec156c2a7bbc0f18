"""Order statistics by passes of arrays against sorted lists."""

import random

import numpy as np
import pytest
from polymetric import fixtures, normalize, queries, ranks, workloads
from polymetric.distances import _levenshtein
from polymetric.spaces import MultiMetricSchema, distance

SCHEMA = MultiMetricSchema.of(("a", "l1"), ("p", "l2v", 2), ("t", "edit"), ("v", "l1v", 20), ("c", "l1"))
KIND = "oid long, a double, p array<double>, t string, v array<double>, c double"


def rows(n=230):
    rnd = random.Random(4)
    return [(i, None if i % 9 == 4 else rnd.random() ** 5 * 1e4, [rnd.random(), rnd.random()], "".join(rnd.choices("abé ", k=rnd.choice((0, 3, 9)))), [rnd.random() for _ in range(20)], 2.5) for i in range(n)]


def far(table, others):
    raw = {"a": lambda x, y: abs(x - y), "p": lambda x, y: ((x[0] - y[0]) ** 2 + (x[1] - y[1]) ** 2) ** 0.5, "t": _levenshtein, "v": lambda x, y: sum(abs(i - j) for i, j in zip(x, y, strict=True)), "c": lambda x, y: abs(x - y)}
    return {n: [f(x[i], y[i]) for x in table for y in others if x[i] is not None and y[i] is not None] for i, (n, f) in enumerate(raw.items(), 1)}


@pytest.mark.parametrize("few", [0, 50, 200_000])  # by bits to the last, mixed, gathered at once
def test_medians_of_all_pairs_are_exact_without_pairs_in_sql(spark, monkeypatch, few):
    monkeypatch.setattr(normalize, "observed", None)
    monkeypatch.setattr(ranks, "FEW", few)
    monkeypatch.setattr(ranks, "BLOCK_ROWS", 25)
    monkeypatch.setattr(ranks, "CHUNK", 1000)
    table = rows()
    got = {r["space"]: (r["sigma"], r["n_pairs"]) for r in normalize.norm_table(spark.createDataFrame(table, KIND), SCHEMA, pairs="all").collect()}
    want = {n: (2 * float(np.median(d)) or 1.0, 230 * 230) for n, d in far(table, table).items()}
    assert got.keys() == want.keys() and all(got[n] == pytest.approx(want[n], abs=1e-12) for n in want)


def test_medians_to_anchors_are_exact_without_distances_in_sql(spark, monkeypatch):
    monkeypatch.setattr(normalize, "observed", None)
    monkeypatch.setattr(ranks, "FEW", 30)
    table = rows()
    df = spark.createDataFrame(table, KIND).repartition(5)
    ids = [r["oid"] for r in normalize.anchors(df, SCHEMA).collect()]
    got = {r["space"]: (r["sigma"], r["n_pairs"]) for r in normalize.norm_table(df, SCHEMA).collect()}
    assert got == {n: (pytest.approx(2 * float(np.median(d)) or 1.0, abs=1e-12), 230 * 16) for n, d in far(table, [table[i] for i in ids]).items()}


def test_a_space_without_values_has_no_median(spark):
    df = spark.createDataFrame([(i, None) for i in range(20)], "oid long, a double")
    for pairs in ("anchors", "all"):
        assert [tuple(r) for r in normalize.norm_table(df, MultiMetricSchema.of(("a", "l1")), pairs=pairs).collect()] == [("a", 1.0, 320 if pairs == "anchors" else 400)]

def test_radii_of_the_hundred_are_the_exact_ranks_of_all_their_pairs(spark, monkeypatch):
    monkeypatch.setattr(workloads, "paired", None)
    s = queries.Setup(spark, "/root/testdata/sf0.001", "rental", queries.skew(fixtures.schema("rental")))
    got = workloads.radii(s, (2, 17, 50, 100))
    asked, all_rows = ([r.asDict() for r in x.collect()] for x in (workloads.hundred(s), s.df))
    d = sorted(distance(s.schema, x, y, s.w, s.sigma) for x in asked for y in all_rows)
    assert got == {x: pytest.approx(d[max(0, -(-x * len(d) // 100) - 1)], abs=1e-9) for x in (2, 17, 50, 100)}


def test_a_range_search_by_so_many_tasks_meets_in_so_many(spark):
    s = queries.Setup(spark, "/root/testdata/sf0.001", "rental", queries.skew(fixtures.schema("rental")))
    made, every = workloads.system(s, "index"), workloads.hundred(s)
    found = workloads.by_tasks(spark, 3, lambda: made.range(every, s.w, 0.1))
    assert found.rdd.getNumPartitions() == 3 and found.count() == made.range(every, s.w, 0.1).count() > 0
    assert spark.conf.get("spark.sql.shuffle.partitions") == "4"
