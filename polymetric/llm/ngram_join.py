"""N-gram Jaccard join by MinHash banding: pairs of documents whose sets of word n-grams have Jaccard similarity at or above a threshold."""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.llm.common import Scratch, bloom_probe, bloom_words, components, heavy_join, worker_store
from polymetric.llm.neardup import band_keys, banding, mix, rough_components, verified

#: Words kept by a worker; the store starts anew when it is full.
MOST_KEPT = 400_000
_FACTOR = np.uint64(0x9DDFEA08EB382D69)


class _Hashes(dict):
    def __missing__(self, word: str) -> int:
        if len(self) >= MOST_KEPT:
            self.clear()
        h = xxhash.xxh3_64_intdigest(word.encode("utf-8", "replace"))
        if len(word) <= 64:
            self[word] = h
        return h


def shingles(text: str, n: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's n-grams of lower-cased words; a text of fewer words is one n-gram, an empty one has none."""
    words = (text or "").lower().split()
    w = np.fromiter(map(worker_store("words", _Hashes).__getitem__, words), np.uint64, len(words))
    k = min(n, len(w))
    if not k:
        return w
    h = w[: len(w) - k + 1].copy()
    for i in range(1, k):
        h *= _FACTOR
        h += w[i : len(w) - k + 1 + i]
    return np.unique(mix(h))


def permutations(k: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20_24)
    return rng.integers(0, 2**63, k, np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 2**63, k, np.uint64)


def signature(grams: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least value of each permutation over a non-empty set."""
    out = np.full(len(a), np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(grams), 1024):
        part = grams[i : i + 1024, None] * a
        part += b
        np.minimum(out, part.min(axis=0), out=out)
    return out


def ngram_join(docs: DataFrame, n: int = 5, threshold: Fraction = Fraction(4, 5), recall: float = 0.999, id_col: str = "doc_id", text_col: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """(doc_id, class_id, n_links, kept), one row for each input row.

    class_id: the least id that links lead to; n_links: how many other rows have similarity at or above the threshold; kept: whether
    the row is its class's first. A null text counts as empty; two texts without words are equal, similarity 1.
    Rows with one id are one document, whose texts are then in one class. A row without an id stands alone (null
    class, no links, kept). Other columns are ignored; an empty table gives no rows.

    Rows with equal sets collapse first, so copies never meet as pairs. A pair under the threshold is never linked; one
    at the threshold is missed with probability 1 - recall at most, less above it.
    """
    spark = docs.sparkSession
    scratch = scratch or Scratch(spark)
    bands, rows = banding(float(threshold), recall, 0.05)
    a, b = permutations(bands * rows)

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hi, lo, keys = [], [], []
            for t in batch.column(1):
                grams = shingles(t.as_py(), n)
                d = xxhash.xxh3_128_intdigest(grams.tobytes())
                hi.append((d >> 64) - (1 << 63))
                lo.append((d & (1 << 64) - 1) - (1 << 63))
                keys.append(band_keys(signature(grams, a, b)[None], bands, rows)[0] if len(grams) else np.empty(0, np.int64))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(hi, pa.int64()), pa.array(lo, pa.int64()), pa.array(keys, pa.list_(pa.int64()))], ["doc_id", "hi", "lo", "bands"]
            )

    whole = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    signed = scratch.table(whole.mapInArrow(sign, "doc_id long, hi long, lo long, bands array<long>"), "signed")
    total = signed.count()
    known = signed.where("doc_id IS NOT NULL")
    sets = scratch.table(known.groupBy("hi", "lo").agg(F.min("doc_id").alias("node"), F.count("*").alias("copies")), "sets")
    firsts = known.join(sets.select("hi", "lo", F.col("node").alias("doc_id")), ["hi", "lo", "doc_id"], "left_semi").select(F.col("doc_id").alias("node"), "bands")
    rough, by_bucket = rough_components(firsts, scratch, "docs")
    wanted = rough.join(sets, "node").select("node", "root", "members", "copies", "hi", "lo")
    near = bloom_probe(whole.where("doc_id IS NOT NULL").withColumn("k", F.xxhash64("doc_id")), "k", bloom_words(rough.select(F.xxhash64("node").alias("k")), "k"), "maybe").where("maybe")
    items = near.select(F.col("doc_id").alias("node"), "text").join(wanted, "node")
    edges, links = verified(items, by_bucket, lambda texts: [shingles(t, n) for t in texts], threshold, scratch, "docs")
    roots = components(edges, scratch, "docs-final")
    classes = sets.join(roots, "node", "left").join(links, "node", "left").select("hi", "lo", "copies", F.coalesce("root", "node").alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    classes = scratch.table(classes, "classes")
    scratch.drop(*(f"docs-{n}" for n in ("roots", "sized", "large", "cells", "marked", "split", "verified")))
    out = heavy_join(known.select("doc_id", "hi", "lo"), classes, ["hi", "lo"], "copies", total)
    alone = signed.where("doc_id IS NULL").select("doc_id", F.lit(None).cast("long").alias("class_id"), F.lit(0).cast("long").alias("n_links"), F.lit(True).alias("kept"))
    return out.select("doc_id", "class_id", "n_links", (F.col("doc_id") == F.col("class_id")).alias("kept")).unionByName(alone)
