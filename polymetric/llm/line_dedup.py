"""Fuzzy line dedup: character-shingle MinHash signatures, high-recall banding, exact Jaccard verification, then a
distributed union-find that keeps one line of each component.

Signatures are one-permutation MinHash: one hash a shingle, the least value in each of bands * rows bins, and empty bins filled from others
by fixed random probes, so equal sets get equal signatures at one pass over the characters.
"""

from __future__ import annotations

import hashlib
import itertools
from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.llm.common import Scratch, bloom_probe, bloom_words, components, fresh, heavy_join, worker_store
from polymetric.llm.neardup import band_keys, banding, mix, rough_components, verified

#: Characters of a shingle.
K = 8
_STEP = 0x9DDFEA08EB382D69
#: Characters that are hashed at once.
_CHUNK = 1 << 18


def normal(line: str) -> str:
    """What makes lines equal: lower case, white space runs as one blank, none at the ends."""
    return " ".join(line.lower().split())


def line_id(line: str) -> tuple[int, int]:
    d = hashlib.blake2b(line.encode("utf-8", "replace"), digest_size=16).digest()
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


def _grams(lines: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hash, line number) of the shingles of non-empty lines; a line shorter than a shingle is one, with blanks behind."""
    padded = [x if len(x) >= K else x + "\0" * (K - len(x)) for x in lines]
    size = np.fromiter(map(len, padded), np.int64, len(padded))
    h = np.frombuffer("".join(padded).encode("utf-32-le", "replace"), "<u4").astype(np.uint64)
    h += np.uint64(1)
    for width in (1, 2, 4):
        h = h[:-width] * np.uint64(pow(_STEP, width, 1 << 64)) + h[width:]
    ends = np.cumsum(size)
    ok = np.ones(int(ends[-1]), bool)
    for back in range(1, K):
        ok[ends - back] = False
    return mix(h[ok[: len(h)]]), np.repeat(np.arange(len(lines)), size - K + 1)


def shingle_sets(lines: list[str]) -> list[np.ndarray]:
    """Sorted distinct shingles of each non-empty line."""
    if not lines:
        return []
    h, line = _grams(lines)
    ends = np.searchsorted(line, np.arange(len(lines) + 1)).tolist()
    out = []
    for a, b in itertools.pairwise(ends):
        own = h[a:b]
        own.sort()
        again = own[1:] == own[:-1]
        out.append(own[np.append(True, ~again)] if again.any() else own)
    return out


def _probes(bins: int) -> np.ndarray:
    return np.random.default_rng(77).integers(0, bins, (4 * bins, bins))


def signatures(lines: list[str], bins: int) -> np.ndarray:
    """(lines, bins) values of non-empty lines."""
    h, line = _grams(lines)
    at = (h >> np.uint64(32)) * np.uint64(bins) >> np.uint64(32)
    none = np.uint32(0xFFFFFFFF)
    sig = np.full(len(lines) * bins, none, np.uint32)
    np.minimum.at(sig, line * bins + at.astype(np.int64), (h & np.uint64(0xFFFFFFFF)).astype(np.uint32) >> np.uint32(1))
    sig = sig.reshape(len(lines), bins)
    out, least = sig.copy(), sig.min(axis=1)
    rows, cols = np.nonzero(sig == none)
    for probe in _probes(bins):
        if not len(rows):
            break
        got = sig[rows, probe[cols]]
        hit = got != none
        out[rows[hit], cols[hit]] = got[hit]
        rows, cols = rows[~hit], cols[~hit]
    out[rows, cols] = least[rows]
    return out


def duplicate_lines(docs: DataFrame, threshold: Fraction = Fraction(4, 5), recall: float = 0.995, id_col: str = "doc_id", text_col: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """(doc_id, n_lines, n_dropped, dropped): one row for each input row, with the numbers of the lines to drop, ascending from 0.

    Lines are equal if alike up to case and white space, and near if their sets of 8-character shingles have Jaccard
    ``threshold`` or more. Of each component of near lines one stays: the one in the least document id, there the first.
    Lines without visible characters are never dropped. A null text counts as empty: one blank line. Rows with one id are one document,
    and the same lines are dropped from each; a null id is dealt with as id -2^63 and comes back null. Other columns are ignored; an empty table gives no rows.
    """
    spark = docs.sparkSession
    scratch = scratch or Scratch(spark)
    bands, rows = banding(float(threshold), recall, 0.10)
    none = -(1 << 63)

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        worker_store("lines", dict)  # lets go of what an earlier stage kept in this worker
        seen: set[int] = set()

        def told(docs: list[tuple]) -> pa.RecordBatch:
            fresh = []  # a line needs its bands once a task
            for _, _, _, own in docs:
                for line, (h, _), _ in own:
                    if h not in seen:
                        seen.add(h)
                        fresh.append((h, line))
            keys = band_keys(signatures([x for _, x in fresh], bands * rows), bands, rows) if fresh else np.empty((0, bands), np.int64)
            flat = [x for *_, own in docs for x in own]
            waiting = {h for h, _ in fresh}
            has = np.array([h in waiting and not waiting.discard(h) for _, (h, _), _ in flat], bool)
            at = np.concatenate([[0], np.cumsum(has * bands)])
            lists = pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(keys.ravel()))
            parts = [pa.array([x[1][0] for x in flat], pa.int64()), pa.array([x[1][1] for x in flat], pa.int64()), pa.array([x[2] for x in flat], pa.int32()), lists]
            kind = [pa.field("h", pa.int64()), pa.field("h2", pa.int64()), pa.field("n", pa.int32()), pa.field("bands", pa.list_(pa.int64()))]
            ends = np.concatenate([[0], np.cumsum([len(own) for *_, own in docs])])
            lines = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.StructArray.from_arrays(parts, fields=kind))
            return pa.RecordBatch.from_arrays(
                [pa.array([d for d, *_ in docs], pa.int64()), pa.array([n for _, n, _, _ in docs], pa.int32()), pa.array([r for _, _, r, _ in docs], pa.list_(pa.int32())), lines],
                ["doc_id", "n_lines", "again", "lines"],
            )

        for batch in batches:
            pending, chars = [], 0
            for d, t in zip(batch.column(0), batch.column(1), strict=True):
                text = t.as_py() or ""
                lines, own, again, here = text.split("\n"), [], [], set()
                for i, x in enumerate(lines):
                    if not (x := normal(x)):
                        continue
                    name = line_id(x)
                    if name in here:
                        again.append(i)
                    else:
                        here.add(name)
                        own.append((x, name, i))
                pending.append((d.as_py() if d.is_valid else none, len(lines), again, own))
                chars += len(text)
                if chars >= _CHUNK:
                    yield told(pending)
                    pending, chars = [], 0
            if pending:
                yield told(pending)

    whole = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    base = scratch.table(whole.mapInArrow(split, "doc_id long, n_lines int, again array<int>, lines array<struct<h:long,h2:long,n:int,bands:array<long>>>"), "lines")
    each = base.select("doc_id", F.explode("lines").alias("l")).select("doc_id", "l.h", "l.h2", "l.n")
    stats = scratch.table(each.groupBy("h", "h2").agg(F.min("doc_id").alias("first"), F.min_by("n", "doc_id").alias("at"), F.count("*").alias("n_rows")), "stats")
    keyed = base.select(F.explode("lines").alias("l")).select(F.col("l.h").alias("node"), "l.bands").where("size(bands) > 0")
    rough, by_bucket = rough_components(keyed, scratch, "lines")

    # the candidates' texts: from one document each, which gives all of its candidates
    wanted = stats.select(F.col("h").alias("node"), "first").join(rough, "node").dropDuplicates(["node"])
    by_doc = wanted.groupBy(F.col("first").alias("doc_id")).agg(F.collect_list(F.struct("node", "root", "members")).alias("want"))
    by_doc = scratch.table(by_doc, "wanted")
    keyed_docs = whole.withColumn("doc_id", F.coalesce("doc_id", F.lit(none))).withColumn("k", F.xxhash64("doc_id"))
    near = bloom_probe(keyed_docs, "k", bloom_words(by_doc.select(F.xxhash64("doc_id").alias("k")), "k"), "maybe").where("maybe").select("doc_id", "text")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            want = batch.column(1)
            node, ends = pa.compute.struct_field(want.values, "node").to_numpy(), want.offsets.to_numpy()
            at, lines = [], []
            for k, t in enumerate(batch.column(0)):
                left = {int(node[i]): i for i in range(ends[k], ends[k + 1])}
                for x in (t.as_py() or "").split("\n"):
                    if not left:
                        break
                    if (x := normal(x)) and (i := left.pop(line_id(x)[0], None)) is not None:
                        at.append(i)
                        lines.append(x)
            taken = want.values.take(pa.array(at, pa.int64()))
            names = ["node", "root", "members"]
            yield pa.RecordBatch.from_arrays([*(pa.compute.struct_field(taken, n) for n in names), pa.array(np.ones(len(at), np.int64)), pa.array(lines, pa.string())], [*names, "copies", "text"])

    items = near.join(by_doc, "doc_id").select("text", "want").mapInArrow(cut, "node long, root long, members long, copies long, text string")
    edges, _ = verified(items, by_bucket, shingle_sets, threshold, scratch, "lines")
    roots = scratch.table(components(edges, scratch, "lines-final"), "final")

    # which occurrences go: all but the first of its class, for lines that recur or have near ones
    named = stats.join(roots.withColumnRenamed("node", "h"), "h", "left")
    keep = named.where("root IS NOT NULL").groupBy("root").agg(F.min(F.struct("first", "at", "h")).alias("keep"))
    recurring = named.where("root IS NULL AND n_rows > 1").select("h", "h2", "n_rows", "first", F.col("h").alias("keep_h"))
    nearby = heavy_join(named.where("root IS NOT NULL"), keep.join(roots.groupBy("root").agg(F.count("*").alias("w")), "root"), ["root"], "w", roots.count()).select("h", "h2", "n_rows", F.col("keep.first").alias("first"), F.col("keep.h").alias("keep_h"))
    judged = scratch.table(recurring.unionByName(nearby), "judged")
    gone = heavy_join(each, judged, ["h", "h2"], "n_rows", max(1, stats.agg(F.coalesce(F.sum("n_rows"), F.lit(0))).first()[0])).where("doc_id <> first OR h <> keep_h").groupBy("doc_id").agg(F.collect_set("n").alias("gone"))
    scratch.drop(*(f"lines-{n}" for n in ("roots", "sized", "large", "cells", "marked", "split", "verified")))
    empty = F.array().cast("array<int>")
    told = base.select("doc_id", "n_lines", "again").join(gone, "doc_id", "left")
    dropped = F.array_sort(F.array_union("again", F.coalesce("gone", empty)))
    return told.select(F.when(F.col("doc_id") != none, F.col("doc_id")).alias("doc_id"), "n_lines", F.size(dropped).alias("n_dropped"), dropped.alias("dropped"))


def without_lines(docs: DataFrame, dropped: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents less the lines that :func:`duplicate_lines` names; other columns stay. Documents without such lines aren't shuffled."""
    k, maybe, own, cuts = (fresh(docs, n) for n in ("dl_k", "dl_maybe", "dl_id", "dl_lines"))
    gone = dropped.where("n_dropped > 0 AND doc_id IS NOT NULL").select(F.col("doc_id").alias(own), F.col("dropped").alias(cuts)).dropDuplicates([own])
    probed = bloom_probe(docs.withColumn(k, F.xxhash64(F.col(id_col).cast("long"))), k, bloom_words(gone.select(F.xxhash64(own).alias("k")), "k"), maybe)
    same = probed.where(~F.col(maybe) | F.col(id_col).isNull()).select(*docs.columns)
    met = probed.where(F.col(maybe) & F.col(id_col).isNotNull()).join(gone, F.col(id_col) == F.col(own), "left")
    lines = F.filter(F.split(F.col(text_col), "\n", -1), lambda x, i: ~F.array_contains(cuts, i))
    cut = F.when(F.col(own).isNull(), F.col(text_col)).otherwise(F.array_join(lines, "\n"))
    return same.unionByName(met.withColumn(text_col, cut).select(*docs.columns))
