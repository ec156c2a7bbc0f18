"""Near duplicates by banded MinHash: parameters, bucket edges without pairs, exact verification in blocks.

A bucket's rows are sorted by (band hash, node) over range partitions, which also split a bucket of any size; each row
is linked to the first of its bucket in its partition, and partitions that share a bucket are linked through their first rows.
The links join candidates into rough components. The candidates of a rough component are cut into blocks of a bounded size, and
every pair of blocks is verified by exact Jaccard in one bounded unit of work, which gives back counts and a spanning
forest, not pairs. Where strays have joined many small groups into one component, its blocks are those of its buckets
instead, if they need fewer texts: a pair counts in the first bucket it shares, so both ways verify every pair that meets.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.llm.common import Scratch, bloom_probe, bloom_words, components, heavy_join

#: Expected members of a block; a unit holds two blocks.
BLOCK = 64
#: A component is verified by its buckets if they need so many times fewer texts; rows then carry their bucket lists, so less doesn't pay.
SPLIT_GAIN = 8
_COLUMNS = 8192


def banding(threshold: float, recall: float, stray: float) -> tuple[int, int]:
    """(bands, rows): the fewest hashes that find a pair at ``threshold`` with probability ``recall`` at least, while
    a pair of similarity 0.3 meets with probability ``stray`` at most."""
    found = []
    for rows in range(1, 17):
        bands = math.ceil(math.log(1 - recall) / math.log(1 - threshold**rows))
        if 1 - (1 - 0.3**rows) ** bands <= stray:
            found.append((bands * rows, bands, rows))
    return min(found)[1:]


def mix(h: np.ndarray) -> np.ndarray:
    """Spreads 64-bit numbers, in place."""
    h ^= h >> np.uint64(31)
    h *= np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    return h


def band_keys(signatures: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """(n, bands * rows) values to (n, bands) 64-bit bucket keys."""
    parts = signatures.astype(np.uint64).reshape(len(signatures), bands, rows)
    h = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0xA24BAED4963EE407), parts.shape[:2]).copy()
    for r in range(rows):
        h = mix(h * np.uint64(0x9FB21C651E98DF25) + parts[:, :, r])
    return h.view(np.int64)


def bucket_edges(keyed: DataFrame, scratch: Scratch, tag: str) -> DataFrame:
    """(node, bands array) to edges (u, v) that join the members of every bucket; a node without bands has none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(key: np.ndarray, u: np.ndarray, v: np.ndarray, edge: bool) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(key), pa.array(u), pa.array(v), pa.array(np.full(len(u), edge))], ["key", "u", "v", "edge"])

        first, last_key, leader = None, None, None
        for batch in batches:
            k, x = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            if not len(k):
                continue
            new = np.empty(len(k), bool)
            new[0] = last_key is None or k[0] != last_key
            np.not_equal(k[1:], k[:-1], out=new[1:])
            at = np.maximum.accumulate(np.where(new, np.arange(len(k)), -1))
            lead = np.where(at >= 0, x[np.maximum(at, 0)], leader if leader is not None else 0)
            if first is None:
                first = (k[0], x[0])
            last_key, leader = k[-1], lead[-1]
            keep = lead != x
            yield out(k[keep], x[keep], lead[keep], True)
        if first is not None:
            ends = np.array([first, (last_key, leader)], np.int64)
            yield out(ends[:, 0].copy(), ends[:, 1].copy(), ends[:, 1].copy(), False)

    rows = keyed.select(F.explode("bands").alias("key"), "node").repartitionByRange("key", "node").sortWithinPartitions("key", "node")
    found = scratch.table(rows.mapInArrow(run, "key long, u long, v long, edge boolean"), f"{tag}-links")
    ends = found.where(~F.col("edge")).select("key", "u").distinct()  # two rows a partition at most
    across = ends.join(ends.groupBy("key").agg(F.min("u").alias("v")), "key").where("u <> v").select("u", "v")
    return found.where("edge").select("u", "v").unionByName(across)


def rough_components(keyed: DataFrame, scratch: Scratch, tag: str) -> tuple[DataFrame, DataFrame | None]:
    """(node, root, members) of the candidates: nodes that share buckets, directly or through others; and (node, bands, buckets) of those
    whose component is verified by buckets, if there are any. buckets: (unit, n) of the node's buckets with others."""
    found = scratch.table(components(bucket_edges(keyed, scratch, tag), scratch, f"{tag}-rough"), f"{tag}-roots")
    scratch.drop(f"{tag}-links")
    sizes = found.groupBy("root").agg(F.count("*").alias("members"))
    total = found.count()
    sized = scratch.table(heavy_join(found, sizes, ["root"], "members", total), f"{tag}-sized")
    many = sized.where(F.col("members") > 2 * BLOCK)
    if many.isEmpty():
        return sized, None
    few = bloom_probe(keyed.withColumn("k", F.xxhash64("node")), "k", bloom_words(many.select(F.xxhash64("node").alias("k")), "k"), "maybe").where("maybe")
    large = scratch.table(few.select("node", "bands").join(many, "node"), f"{tag}-large")
    texts = lambda c: F.col(c) * F.ceil(F.col(c) / BLOCK)  # noqa: E731 - that units of so many rows need
    cells = scratch.table(large.select("root", "members", F.explode("bands").alias("unit")).groupBy("root", "members", "unit").agg(F.count("*").alias("n")).where("n > 1"), f"{tag}-cells")
    split = cells.groupBy("root", "members").agg(F.sum(texts("n")).alias("texts")).where(F.col("texts") * SPLIT_GAIN < texts("members")).select("root", "members")
    if split.isEmpty():
        scratch.drop(f"{tag}-large", f"{tag}-cells")
        return sized, None
    marked = scratch.table(heavy_join(large.select("node", "root", "bands"), split, ["root"], "members", total).select("node", "bands"), f"{tag}-marked")
    each = marked.select("node", F.explode("bands").alias("unit"))
    met = heavy_join(each, cells.select("unit", "n"), ["unit"], "n", each.count()).groupBy("node").agg(F.collect_list(F.struct("unit", "n")).alias("buckets"))  # as many as bands at most
    both = scratch.table(marked.join(met, "node"), f"{tag}-split")
    scratch.drop(f"{tag}-large", f"{tag}-cells", f"{tag}-marked")
    return sized, both


def verified(items: DataFrame, split: DataFrame | None, sets: Callable[[list[str]], list[np.ndarray]], threshold: Fraction, scratch: Scratch, tag: str) -> tuple[DataFrame, DataFrame]:
    """Exact verification of rough components.

    items: (node, root, members, copies, text), one row a node; split: (node, bands, buckets) of those verified by buckets. Returns (edges (u, v) that join the same nodes as all
    pairs with Jaccard at or above the threshold do, links (node, links): for each node the copies at such other nodes).
    """
    num, den = threshold.numerator, threshold.denominator

    def solve(rows: list[tuple], got: list[np.ndarray], bucket: int, cross: bool) -> list[tuple[int, int, int]]:
        """rows: (node, block, copies, text, bands) of two blocks (cross) or of one, by block; got: their sets; bucket: the unit's, if it is one's."""
        if cross and rows[0][1] == rows[-1][1]:
            return []  # the other block is empty, and a block's own pairs have a unit
        if len(rows) == 2 and rows[0][4] is None:
            both = np.concatenate(got)
            both.sort()
            n = len(got[0]) + len(got[1])
            if int(np.count_nonzero(both[1:] == both[:-1])) * (num + den) < num * n:
                return []
            (u, _, c, *_), (v, _, d, *_) = rows
            return [(u, u, d), (v, v, c), (u, v, 0)]
        size = np.array([len(g) for g in got])
        low, block = rows[0][1], np.array([r[1] for r in rows])
        a, b = (np.flatnonzero(block == low), np.flatnonzero(block != low)) if cross else (np.arange(len(rows)),) * 2
        shared = np.zeros((len(a), len(b)), np.int64)
        every = np.concatenate(got)
        order = np.argsort(every, kind="stable")
        every, owner = every[order], np.repeat(np.arange(len(rows)), size)[order]
        new = np.ones(len(every), bool)
        new[1:] = every[1:] != every[:-1]
        term = np.cumsum(new) - 1
        many = np.bincount(term) > 1  # a term of one row adds to no pair
        owner, term = owner[many[term]], (np.cumsum(many) - 1)[term[many[term]]]
        for start in range(0, int(term[-1]) + 1 if len(term) else 0, _COLUMNS):
            lo, hi = np.searchsorted(term, [start, start + _COLUMNS])
            m = np.zeros((len(rows), min(_COLUMNS, int(term[-1]) + 1 - start)), np.float32)
            m[owner[lo:hi], term[lo:hi] - start] = 1
            shared += (m[a] @ m[b].T).astype(np.int64)
        ok = shared * (num + den) >= num * (size[a][:, None] + size[b][None, :])
        if not cross:
            np.fill_diagonal(ok, False)
        if rows[0][4] is not None:  # only pairs whose first common bucket is this one
            keys = np.array([r[4] for r in rows])
            same = keys[a][:, None, :] == keys[b][None, :, :]
            ok &= np.take_along_axis(np.broadcast_to(keys[a][:, None, :], same.shape), same.argmax(axis=2)[:, :, None], 2)[:, :, 0] == bucket
        copies = np.array([r[2] for r in rows], np.int64)
        root = list(range(len(rows)))

        def find(i: int) -> int:
            while root[i] != i:
                root[i] = root[root[i]]
                i = root[i]
            return i

        degree = np.zeros(len(rows), np.int64)
        np.add.at(degree, a, ok @ copies[b])
        if cross:
            np.add.at(degree, b, ok.T @ copies[a])
        out = [(rows[i][0], rows[i][0], int(d)) for i, d in enumerate(degree) if d]
        for p, q in zip(*np.nonzero(ok), strict=True):
            i, j = find(a[p]), find(b[q])
            if i != j:
                root[max(i, j)] = min(i, j)
                out.append((rows[a[p]][0], rows[b[q]][0], 0))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def told(found: list[tuple[int, int, int]]) -> pa.RecordBatch:
            cols = list(zip(*found, strict=True)) or [()] * 3
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["u", "v", "links"])

        def solved(units: list[tuple[int, bool, dict[int, tuple]]]) -> pa.RecordBatch:
            ordered = [(key, cross, sorted(u.values(), key=lambda r: (r[1], r[0]))) for key, cross, u in units if len(u) > 1]
            got = iter(sets([r[3] for *_, rows in ordered for r in rows]))
            return told([x for key, cross, rows in ordered for x in solve(rows, [next(got) for _ in rows], key, cross)])

        key, units, chars = None, [], 0  # whole units wait until there is enough text to hash at once
        for batch in batches:
            for root, i, j, node, blk, copies, bands, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (root, i, j, bands is None) != key:
                    if chars > 250_000:
                        yield solved(units)
                        units, chars = [], 0
                    key = (root, i, j, bands is None)
                    units.append((root, i != j, {}))
                units[-1][2].setdefault(node, (node, blk, copies, text or "", bands))
                chars += len(text or "")
        yield solved(units)

    if split is None:
        items = items.withColumn("bands", F.lit(None).cast("array<long>")).withColumn("buckets", F.lit(None).cast("array<struct<unit:long,n:long>>"))
    else:
        items = items.join(split, "node", "left")
    alone = F.array(F.struct(F.col("root").alias("unit"), F.col("members").alias("n")))
    own = items.select("node", "copies", "bands", "text", F.explode(F.coalesce("buckets", alone)).alias("u")).select("node", "copies", "bands", "text", "u.unit", F.ceil(F.col("u.n") / BLOCK).cast("int").alias("nb"))
    own = own.withColumn("blk", F.pmod(F.xxhash64("node"), F.col("nb")).cast("int"))
    units = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("nb") - 1))).select("unit", F.least("blk", "other").alias("i"), F.greatest("blk", "other").alias("j"), "node", "blk", "copies", "bands", "text")
    kind = F.isnull("bands")
    dealt = units.repartition(F.col("unit"), F.col("i"), F.col("j"), kind).sortWithinPartitions("unit", "i", "j", kind)
    found = scratch.table(dealt.mapInArrow(run, "u long, v long, links long"), f"{tag}-verified")
    links = found.where("u = v").groupBy(F.col("u").alias("node")).agg(F.sum("links").alias("links"))
    return found.where("u <> v").select("u", "v"), links
