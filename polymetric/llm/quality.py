"""Supervised subword embeddings: hashed vectors of words and their character n-grams, averaged over a document, with
a softmax output, trained by stochastic gradient descent in numpy.

For two classes the output depends on a document only through the mean, over its features, of each vector's product with the
difference of the two output rows; scoring keeps that one number a bucket, so a word's sum is computed once and reused.
"""

from __future__ import annotations

import math
import operator
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.llm.common import worker_store

#: Word sums kept by a worker; the store starts anew when it is full.
MOST_KEPT = 500_000


@dataclass(frozen=True)
class Settings:
    """Documented bounds: at most ``most_rows`` labelled rows of each class are fitted, chosen by the hash of their id."""

    bits: int = 17
    width: int = 12
    least_n: int = 3
    most_n: int = 5
    most_rows: int = 1200
    epochs: int = 12
    rate: float = 80.0
    batch: int = 16
    seed: int = 7
    threshold: float = 0.3


def features(word: str, s: Settings) -> list[int]:
    """Buckets of a word and of its marked character n-grams."""
    w = f"<{word}>"
    mask = (1 << s.bits) - 1
    out = [zlib.crc32(w.encode()) & mask]
    out += [zlib.crc32(w[i : i + n].encode("utf-8", "replace"), n) & mask for n in range(s.least_n, s.most_n + 1) for i in range(len(w) - n + 1)]
    return out


def counted(text: str, s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Distinct buckets of a text and their shares."""
    words: dict[str, int] = {}
    for w in text.split():
        words[w] = words.get(w, 0) + 1
    if not words:
        return np.empty(0, np.int32), np.empty(0, np.float32)
    total = np.zeros(1 << s.bits)
    for w, n in words.items():
        np.add.at(total, features(w, s), n)
    total[again_bucket(s)] += again(text.split())
    at = np.flatnonzero(total)
    return at.astype(np.int32), (total[at] / total.sum()).astype(np.float32)


def again(words: list[str]) -> int:
    """Word bigrams of a word with itself. All of them are one feature, hashed and learned like the others: as words or plain
    bigrams they have nothing in common, and a bag of words can't tell a repeated word from a frequent one."""
    return sum(map(operator.eq, words, words[1:]))


def again_bucket(s: Settings) -> int:
    return zlib.crc32(b"\x00again") & ((1 << s.bits) - 1)


@dataclass
class Model:
    """gain[b]: what bucket b adds to the logit of label 1, weighed by its share; bias: the logit of an empty text."""

    gain: np.ndarray
    bias: float
    settings: Settings
    name: str = ""
    losses: list[float] = field(default_factory=list)


def fit(rows: list[tuple[np.ndarray, np.ndarray, int]], s: Settings) -> Model:
    """SGD on the softmax loss. Classes weigh alike whatever their numbers. Without rows the score is 0.5."""
    rng = np.random.default_rng(s.seed)
    vectors = rng.uniform(-1 / s.width, 1 / s.width, (1 << s.bits, s.width)).astype(np.float32)
    out, bias = np.zeros((2, s.width), np.float32), np.zeros(2, np.float32)
    n = np.bincount([y for *_, y in rows], minlength=2) if rows else np.zeros(2)
    weight = [len(rows) / (2 * max(1, c)) for c in n]
    losses, step, steps = [], 0, max(1, s.epochs * len(rows))
    for _ in range(s.epochs if rows else 0):
        loss = 0.0
        for k in rng.permutation(len(rows)):
            at, share, y = rows[k]
            rate = s.rate * (1 - step / steps) / s.batch
            step += 1
            mean = share @ vectors[at] if len(at) else np.zeros(s.width, np.float32)
            z = out @ mean + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            loss -= weight[y] * math.log(max(p[y], 1e-12))
            g = p * weight[y]
            g[y] -= weight[y]
            back = g @ out
            out -= min(rate, 0.5) * np.outer(g, mean)
            bias -= 0.02 * min(rate, 0.5) * g
            if len(at):
                vectors[at] -= (rate * share)[:, None] * back
        losses.append(loss / len(rows))
    d = out[1] - out[0]
    gain = (vectors @ d).astype(np.float64)
    return Model(gain, float(bias[1] - bias[0]) + calibration(rows, gain, float(bias[1] - bias[0]), s), s, losses=losses)


def calibration(rows: list[tuple[np.ndarray, np.ndarray, int]], gain: np.ndarray, bias: float, s: Settings) -> float:
    """What the bias takes so that the threshold is the best cut of the fitted rows: the one with the least sum of both classes' shares
    on the wrong side; of equally good ones the middle of the widest gap. 0 without rows of both classes."""
    z = np.array([share @ gain[at] + bias for at, share, _ in rows])
    y = np.array([q for *_, q in rows])
    if not len(rows) or y.all() or not y.any():
        return 0.0
    order = np.argsort(z, kind="stable")
    z, y = z[order], y[order]
    wrong = np.cumsum(y) / y.sum() + (1 - np.cumsum(1 - y) / (1 - y).sum())  # with the cut behind each row
    gaps = np.append(np.diff(z), 0.0)
    best = min(range(len(z) - 1), key=lambda i: (round(float(wrong[i]), 9), -float(gaps[i])), default=0)
    cut = (z[best] + z[min(best + 1, len(z) - 1)]) / 2
    return float(math.log(s.threshold / (1 - s.threshold)) - cut)


class _Sums(dict):
    """word -> sum of gains + number of features i, computed on demand."""

    def __init__(self, model: Model):
        super().__init__()
        self.model, self.again = model, float(model.gain[again_bucket(model.settings)])

    def __missing__(self, word: str) -> complex:
        if len(self) >= MOST_KEPT:
            self.clear()
        at = features(word, self.model.settings)
        value = complex(self.model.gain[at].sum(), len(at))
        if len(word) <= 64:
            self[word] = value
        return value


def score(text: str, sums: _Sums) -> float:
    """Probability of label 1."""
    words, m = text.split(), sums.model
    n = again(words)
    total = sum(map(sums.__getitem__, words), complex(n * sums.again, n))
    z = m.bias + (total.real / total.imag if words else 0.0)
    return 1 / (1 + math.exp(-z)) if z > -700 else 0.0


def labelled_rows(docs: DataFrame, labels: DataFrame, s: Settings, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text, quality): the bounded sample a model may learn from, never rows whose crc32(id) is divisible by 5. Both tables
    may have any other columns; ids of any whole type meet as long."""
    usable = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).where("doc_id IS NOT NULL AND quality IN (0, 1)")
    usable = usable.where(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) != 0)
    parts = [usable.where(F.col("quality") == q).orderBy(F.xxhash64("doc_id"), "doc_id").limit(s.most_rows) for q in (0, 1)]
    chosen = F.broadcast(parts[0].unionByName(parts[1]))  # at most 2 * most_rows rows of two numbers
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).join(chosen, "doc_id").select("doc_id", "text", "quality")


def train(docs: DataFrame, labels: DataFrame, s: Settings | None = None, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """Features are counted on the executors; the driver gets those of at most 2 * most_rows documents, and fits.

    labels: (doc_id, quality). Null ids and other qualities than 0 and 1 are passed over, a null text counts as empty, rows that
    repeat count once, and empty tables give a model that scores 0.5."""
    s = s or Settings()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [counted(t.as_py() or "", s) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(2), pa.array([a.tobytes() for a, _ in got], pa.binary()), pa.array([b.tobytes() for _, b in got], pa.binary())],
                ["doc_id", "quality", "buckets", "shares"],
            )

    got = labelled_rows(docs, labels, s, id_col, text_col).mapInArrow(run, "doc_id long, quality int, buckets binary, shares binary").collect()
    seen = sorted({(r["doc_id"], r["quality"], bytes(r["buckets"]), bytes(r["shares"])) for r in got})
    model = fit([(np.frombuffer(b, np.int32), np.frombuffer(w, np.float32), q) for _, q, b, w in seen], s)
    model.name = f"{zlib.crc32(model.gain.tobytes())}-{model.bias}"
    return model


SCHEMA = "doc_id long, held_out boolean, score double, predicted int"


def score_documents(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: held_out (crc32 of the id divisible by 5), the score, and 1 if it reaches the threshold.

    Narrow: no shuffle; the model, a fixed 2^bits numbers, is broadcast. A null text counts as empty and scores the
    bias alone; a null id is not held out; ids may repeat; other columns are ignored; an empty table gives no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    threshold = model.settings.threshold

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        sums = worker_store(f"quality {m.name}", lambda: _Sums(m))
        for batch in batches:
            scores = [score(t.as_py() or "", sums) for t in batch.column(2)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(scores, pa.float64()), pa.array([int(x >= threshold) for x in scores], pa.int32())],
                ["doc_id", "held_out", "score", "predicted"],
            )

    held = F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(5)) == 0, F.lit(False))
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), held.alias("held_out"), text_col).mapInArrow(run, SCHEMA)


def keep_good(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The rows whose texts reach the threshold, with all their columns: narrow, whatever the ids."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        sums = worker_store(f"quality {m.name}", lambda: _Sums(m))
        for batch in batches:
            yield batch.filter(pa.array([score(t.as_py() or "", sums) >= m.settings.threshold for t in batch.column(at)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
