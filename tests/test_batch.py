"""Batches, joins, updates and streams against brute force."""

import datetime as dt

import pandas as pd

from polymetric import batch, fixtures, queries, streaming, updates
from polymetric.spaces import MultiMetricSchema, distance

SF = "/root/testdata/sf0.001"
SCHEMA = MultiMetricSchema.of(("a", "l1"), ("t", "edit"))
ONES, SIGMA = {"a": 1.0, "t": 0.5}, {"a": 2.0, "t": 3.0}
ROWS = [(i, float(i % 7), "red blue green".split()[i % 3] * (1 + i % 2)) for i in range(60)]


def brute(r):
    d = lambda x, y: distance(SCHEMA, {"a": x[1], "t": x[2]}, {"a": y[1], "t": y[2]}, ONES, SIGMA)
    return {(x[0], y[0]) for x in ROWS for y in ROWS if d(x, y) <= r}


def test_similarity_join_counts_copies_and_keeps_every_link(spark):
    df = spark.createDataFrame(ROWS, "oid long, a double, t string")
    got = batch.link_counts(*batch.similarity_join(df, SCHEMA, ONES, 0.6, SIGMA, depth=2)).collect()
    want = brute(0.6)
    assert {r["oid"]: r["links"] for r in got} == {x[0]: sum(p[0] == x[0] for p in want) - 1 for x in ROWS}
    assert all(r["rep"] == min(x[0] for x in ROWS if x[1:] == ROWS[r["oid"]][1:]) for r in got)


def test_batches_agree_with_scans_when_k_passes_every_leaf(spark):
    df = spark.createDataFrame(ROWS, "oid long, a double, t string")
    index = queries.MultiMetricIndex.build(df, SCHEMA, depth=3, sigma=SIGMA)
    few = df.where("oid % 20 = 0")
    assert {(r["qid"], r["oid"]) for r in batch.range_queries(index, few, ONES, 0.6).collect()} == {p for p in brute(0.6) if p[0] % 20 == 0}
    assert batch.knn_queries(index, few, ONES, 1000).count() == 3 * len(ROWS)
    one = batch.knn_queries(index, few, ONES, 5).where("qid = 20").orderBy("rank").collect()
    want = queries.knn_scan(df, SCHEMA, {"a": ROWS[20][1], "t": ROWS[20][2]}, ONES, 5, SIGMA).collect()
    assert [r["oid"] for r in one] == [r["oid"] for r in want]


def test_compaction_splits_leaves_and_keeps_answers(spark):
    s = queries.Setup(spark, SF, "rental")
    index = updates.delete(s.index(depth=2), s.df.where("oid % 3 = 0").select("oid"))
    tight = updates.compact(index, 200)
    assert len(tight.boxes) > len(index.boxes) and sum(b["n_objects"] for b in tight.boxes) == s.df.where("oid % 3 <> 0").count()
    ids = lambda x: sorted(r["oid"] for r in x.range(s.q, s.w, 1.0).select("oid").collect())
    assert ids(tight) == ids(index)


def test_late_rows_are_dropped_and_windows_close_once(spark, tmp_path):
    schema = MultiMetricSchema.of(("v", "l1"),)
    at = lambda h: dt.datetime(2024, 1, 1) + dt.timedelta(hours=h)
    for n, rows in enumerate([[(1, 1.0, at(1)), (2, 5.0, at(2))], [(3, 9.0, at(60))], [(4, 0.0, at(3)), (5, 2.0, at(61))], [(6, 7.0, at(200))]]):
        pd.DataFrame(rows, columns=["oid", "v", "ts"]).astype({"ts": "datetime64[us]"}).to_parquet(tmp_path / f"{n}.parquet")
    stream = spark.readStream.schema("oid long, v double, ts timestamp").option("maxFilesPerTrigger", 1).parquet(str(tmp_path))
    found = streaming.landed(streaming.window_topk(stream, schema, {"v": 0.0}, {"v": 1.0}, 2, {"v": 1.0}))
    best = streaming.best_of(found, 2).orderBy("w_start", "rank").collect()
    assert [r["oid"] for r in best] == [1, 2, 5, 3]  # 4 came behind the watermark; the window of 6 is still open


def test_a_grid_of_blocks_and_strips_pairs_every_query_with_every_row_once(spark, monkeypatch):
    df = spark.createDataFrame(ROWS, "oid long, a double, t string")
    few = sorted((r["qid"], r["oid"], r["dist"]) for r in queries.paired(df, df, SCHEMA, ONES, SIGMA).collect())
    for name, n in (("FEW_QUERIES", 7), ("STRIP_ROWS", 11)):
        monkeypatch.setattr(f"polymetric.index.{name}", n)
    assert sorted((r["qid"], r["oid"], r["dist"]) for r in queries.paired(df, df, SCHEMA, ONES, SIGMA).collect()) == few
    assert queries.paired(df.where("oid < 0"), df, SCHEMA, ONES, SIGMA).count() == 0
