"""Weight learning: what an iteration reads, and that its rows are those of the plain way."""

import random

import pytest
from polymetric import weights
from polymetric.spaces import MultiMetricSchema
from pyspark.sql import functions as F

SCHEMA = MultiMetricSchema.of(("a", "l1"), ("b", "l1"))
HIDDEN = {"a": 1.0, "b": 0.2}


@pytest.mark.parametrize("negatives", ["knn", "random"])
def test_an_iteration_scans_the_distances_once_and_samples_the_same_rows(spark, tmp_path, negatives):
    rnd, n = random.Random(4), 3 * 150
    rows = [(q, o, rnd.random(), rnd.random()) for q in range(3) for o in range(150)]
    spark.createDataFrame(rows, "qid long, oid long, d_a double, d_b double").write.parquet(str(tmp_path / "cache"))
    plain, read = spark.read.parquet(str(tmp_path / "cache")), spark.sparkContext.accumulator(0)

    def counted(batches):
        for x in batches:
            read.add(len(x))
            yield x

    truth = weights.retrieve(plain, SCHEMA, HIDDEN, 20)
    truth.select("qid", "oid").write.parquet(str(tmp_path / "truth"))
    truth = spark.read.parquet(str(tmp_path / "truth"))
    _, history = weights.learn_weights(plain.mapInPandas(counted, plain.schema), truth, SCHEMA, 20, iters=4, negatives=negatives, target=1.1)
    assert len(history) == 4
    assert read.value == n * (4 + 1 + (negatives == "random"))  # once an iteration, once for the truth's distances, once for the drawn
    first = weights.np.random.default_rng(3).uniform(0.1, 1, 2)
    w = {"a": float(first[0]), "b": float(first[1])}
    found = weights.retrieve(plain, SCHEMA, w, 20)
    want = weights.loss_grad(weights.sample(plain, SCHEMA, found, truth, "truth", negatives), SCHEMA, w).first()
    assert history[0][1] == pytest.approx(want["loss"], abs=1e-12)
    assert history[0][2] == pytest.approx(weights.recall(found, truth).agg(F.avg("recall")).first()[0])
