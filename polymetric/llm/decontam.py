"""Benchmark decontamination by the q-gram lemma.

A region within e edits of an item of length L shares at least L - q + 1 - q * e of its q-grams with it, all on diagonals
at most e from the region's own. So shared q-grams are counted in diagonal bands of width 4e + 2 that overlap by half,
and only a band that reaches the bound is verified, by banded alignment. Bands of items and documents that stay below it can't hold a match.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.llm.common import Scratch, worker_store
from polymetric.llm.neardup import mix

#: Characters of benchmark text that go to the executors at once; a larger benchmark takes several passes.
BLOCK_CHARS = 4_000_000
#: Document characters looked up at once.
_CHUNK = 1 << 20
_TABLE_BITS = 22
#: Hits of q-grams in items, and cells of a table of documents and items, that are held at once.
MOST_HITS = 1 << 21
_SLICE = 1 << 10
_STEP = 0x9DDFEA08EB382D69


def normal(text: str) -> str:
    """Lower case and every white-space character a blank, place by place."""
    low = text.lower()
    low = low if len(low) == len(text) else "".join(c.lower() if len(c.lower()) == 1 else c for c in text)
    return low.translate(_BLANKS)


_BLANKS = {c: " " for c in map(ord, "\t\n\r\x0b\x0c   \x85")}


def codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "replace"), "<u4")


def qgrams(c: np.ndarray, q: int) -> np.ndarray:
    """64-bit hashes of the q-grams at each place, in about log2(q) steps."""
    if len(c) < q:
        return np.empty(0, np.uint64)
    part, width, out, done = c.astype(np.uint64) + np.uint64(1), 1, None, 0
    n = len(c) - q + 1
    while True:
        if q & width:
            piece = part[done : done + n]
            out = piece.copy() if out is None else out * np.uint64(pow(_STEP, width, 1 << 64)) + piece
            done += width
        if done == q:
            return mix(out)
        part = part[: len(part) - width] * np.uint64(pow(_STEP, width, 1 << 64)) + part[width:]
        width *= 2


def banded(item: np.ndarray, region: np.ndarray, e: int) -> tuple[int, int, int] | None:
    """(edits, start, end) of the stretch of ``region`` nearest to ``item``, if within ``e`` edits; starts lie within the
    first len(region) - len(item) + e places, and each row of the table only holds that band. Ties: the first end, then the longest stretch."""
    width = max(1, len(region) - len(item) + 2 * e + 1)
    big = len(item) + len(region) + 1
    cost, start = np.zeros(width, np.int64), np.arange(width) - e
    cost[(start < 0) | (start > len(region))] = big
    place = np.arange(width)
    for i in range(len(item)):
        at = i + place - e  # the region's character that ends here
        inside = (at >= 0) & (at < len(region))
        same = inside & (region[np.clip(at, 0, len(region) - 1)] == item[i]) if len(region) else inside
        keep = np.where(inside, cost + ~same, big)
        gap = np.append(cost[1:] + 1, big)
        gap[(at < -1) | (at >= len(region))] = big
        take = gap < keep
        new, frm = np.where(take, gap, keep), np.where(take, np.append(start[1:], 0), start)
        run = np.minimum.accumulate((new - place) * (width + 1) + place)  # insertions run along the row
        source = run % (width + 1)
        cost, start = np.minimum(run // (width + 1) + place, big), frm[source]
        if cost.min() > e:  # costs never fall from row to row
            return None
    best = int(np.argmin(cost))
    if cost[best] > e:
        return None
    return int(cost[best]), int(start[best]), len(item) + best - e


def budget(length: int, share: float, q: int) -> tuple[int, int]:
    """(edits, q-gram length) of an item: the stated share of its length, and the longest q-grams up to ``q`` of which e edits
    can't spoil all, so the bound is positive for every item; one without edits is a single q-gram if it is short."""
    e = int(share * length)
    return e, max(1, min(q, length // (e + 1)))


@dataclass(frozen=True)
class Benchmark:
    """A block of items with q-grams of one length: q-grams numbered in order, with the item and place of each."""

    ids: list[int]
    texts: list[np.ndarray]
    edits: np.ndarray
    least: np.ndarray
    grams: np.ndarray
    entry: np.ndarray
    place: np.ndarray
    q: int

    @staticmethod
    def of(rows: list[tuple[int, str]], q: int, share: float) -> list[Benchmark]:
        """One for each length of q-grams that the items need; items without characters are nowhere."""
        by: dict[int, list[tuple[int, np.ndarray, int]]] = {}
        for i, t in rows:
            if len(c := codes(normal(t))):
                e, own = budget(len(c), share, q)
                by.setdefault(own, []).append((i, c, e))
        return [Benchmark._of(items, own) for own, items in sorted(by.items())]

    @staticmethod
    def _of(items: list[tuple[int, np.ndarray, int]], q: int) -> Benchmark:
        texts, edits = [c for _, c, _ in items], np.array([e for *_, e in items], np.int64)
        got = [qgrams(c, q) for c in texts]
        every = np.concatenate(got)
        item = np.repeat(np.arange(len(items)), [len(g) for g in got])
        order = np.argsort(every, kind="stable")
        grams, first = np.unique(every[order], return_index=True)
        number = np.repeat(np.arange(len(grams)), np.diff(np.append(first, len(every))))
        place = np.concatenate([np.arange(len(g), dtype=np.int32) for g in got])
        least = np.array([len(c) for c in texts], np.int64) - q + 1 - q * edits
        return Benchmark([i for i, *_ in items], texts, edits, least, grams, number * len(items) + item[order], place[order], q)

    def table(self) -> np.ndarray:
        t = np.zeros(1 << _TABLE_BITS, bool)
        t[(self.grams >> np.uint64(64 - _TABLE_BITS)).astype(np.int64)] = True
        return t

    def search(self, docs: list[np.ndarray], table: np.ndarray) -> list[tuple[int, int, int, int, int]]:
        """(document number, item number, edits, start, end) of the best match of each item in each document.

        Hits of a q-gram in many items are never laid out for all documents and items at once: a part of the work is
        halved, by documents and then by items, until its hits and its table of pairs are bounded.
        """
        out: list[tuple[int, int, int, int, int]] = []
        if not docs:
            return out
        whole = np.concatenate(docs)
        starts = np.concatenate([[0], np.cumsum([len(d) for d in docs])])
        h = qgrams(whole, self.q)
        at = np.flatnonzero(table[(h >> np.uint64(64 - _TABLE_BITS)).astype(np.int64)])
        number = np.searchsorted(self.grams, h[at])
        real = (number < len(self.grams)) & (self.grams[np.minimum(number, len(self.grams) - 1)] == h[at])
        at, number = at[real], number[real]
        doc = np.searchsorted(starts, at, "right") - 1
        fits = at + self.q <= starts[doc + 1]
        at, number, doc = at[fits] - starts[doc[fits]], number[fits], doc[fits]
        n = len(self.ids)
        work = [(0, len(docs), 0, n)]
        while work:
            d0, d1, i0, i1 = work.pop()
            here = slice(*np.searchsorted(doc, [d0, d1]))
            lo, hi = np.searchsorted(self.entry, number[here] * n + i0), np.searchsorted(self.entry, number[here] * n + i1)
            hits = int((hi - lo).sum())
            if not hits:
                continue
            if d1 - d0 > 1 and (hits > MOST_HITS or (d1 - d0) * (i1 - i0) > MOST_HITS):
                mid = (d0 + d1) // 2
                work += [(mid, d1, i0, i1), (d0, mid, i0, i1)]
            elif i1 - i0 > 1 and (hits > MOST_HITS or i1 - i0 > MOST_HITS):
                mid = (i0 + i1) // 2
                work += [(d0, d1, mid, i1), (d0, d1, i0, mid)]
            else:
                out += self._matches(docs, doc[here], at[here], lo, hi, (d0, i0, i1 - i0))
        return sorted(out)

    def _matches(self, docs: list[np.ndarray], doc: np.ndarray, at: np.ndarray, lo: np.ndarray, hi: np.ndarray, part: tuple[int, int, int]) -> list[tuple[int, int, int, int, int]]:
        """Matches of a part: (first document, first item, items), with the hits [lo, hi) among the entries of each place."""
        d0, i0, ni = part
        out: dict[tuple[int, int], tuple[int, int, int]] = {}

        def laid_out(s: slice) -> tuple[np.ndarray, np.ndarray]:
            m = hi[s] - lo[s]
            return np.repeat(lo[s] - np.concatenate([[0], np.cumsum(m)[:-1]]), m) + np.arange(m.sum()), m

        if int((hi - lo).sum()) > MOST_HITS:  # of one document and one item: what a band counts is kept, a slice of places at a time
            length, half, seen = len(self.texts[i0]), 2 * int(self.edits[i0]) + 1, np.empty(0, np.int64)
            for k in range(0, len(at), _SLICE):
                entry, m = laid_out(slice(k, k + _SLICE))
                p = self.place[entry].astype(np.int64)
                seen = np.union1d(seen, (np.repeat(at[k : k + _SLICE], m) - p) // half * length + p)
            p, diagonal = seen % length, seen // length * half
            d, i = np.full(len(p), d0), np.full(len(p), i0)
        else:
            entry, m = laid_out(slice(None))
            d, i, a = np.repeat(doc, m), self.entry[entry] % len(self.ids), np.repeat(at, m)
            pair = (d - d0) * ni + i - i0
            some = np.bincount(pair)[pair] >= self.least[i]  # too few in all: too few in any band
            d, i, p = d[some], i[some], self.place[entry[some]].astype(np.int64)
            diagonal = a[some] - p
        half = 2 * self.edits[i] + 1
        for shift in (0, 1):
            band = (diagonal + shift * half) // (2 * half)
            order = np.lexsort((p, band, i, d))
            dd, ii, bb, pp = d[order], i[order], band[order], p[order]
            once = np.ones(len(dd), bool)  # each place of the item counts once in a band
            once[1:] = (pp[1:] != pp[:-1]) | (bb[1:] != bb[:-1]) | (ii[1:] != ii[:-1]) | (dd[1:] != dd[:-1])
            dd, ii, bb = dd[once], ii[once], bb[once]
            new = np.concatenate([[True], (dd[1:] != dd[:-1]) | (ii[1:] != ii[:-1]) | (bb[1:] != bb[:-1])]) if len(dd) else np.empty(0, bool)
            first = np.flatnonzero(new)
            count = np.diff(np.append(first, len(dd)))
            for k in first[count >= self.least[ii[first]]]:
                e, width = int(self.edits[ii[k]]), 2 * int(2 * self.edits[ii[k]] + 1)
                low = int(bb[k]) * width - shift * width // 2
                text, want = docs[dd[k]], self.texts[ii[k]]
                key = (int(dd[k]), int(ii[k]))
                frm, to = max(0, low - e), min(len(text), low + width + len(want) + e)
                if frm < to and (got := self._align(want, text[frm:to], e)):
                    new_ = (got[0], got[1] + frm, got[2] + frm)
                    out[key] = min(out.get(key, new_), new_)
        return [(*k, *v) for k, v in out.items()]

    @staticmethod
    def _align(want: np.ndarray, region: np.ndarray, e: int) -> tuple[int, int, int] | None:
        found = region.tobytes().find(want.tobytes())
        if found >= 0 and found % 4 == 0:
            return 0, found // 4, found // 4 + len(want)
        return banded(want, region, e)


SCHEMA = "doc_id long, item_id long, edits int, start int, end int"


def contaminated(docs: DataFrame, benchmark: DataFrame, q: int = 8, share: float = 0.1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, item_id, edits, start, end): the best occurrence of each benchmark item in each document that holds it.

    An occurrence is a stretch within ``share`` of the item's length in edits, after lower-casing and making white space
    blanks; start and end count characters. q-grams have ``q`` characters, fewer for items so short that their edits could spoil all of
    them, so the stated share holds for items of any length. Empty items, null texts and null ids give no rows on the benchmark side; a null document text is empty; a null doc_id is carried. Rows that repeat give
    rows that repeat. Clean documents give none. The benchmark goes to the executors in blocks of bounded size, one at a time, each
    with a pass over the texts; a benchmark of over one block is written block by block.
    """
    spark = docs.sparkSession
    sized = benchmark.where("item_id IS NOT NULL AND text IS NOT NULL").select(F.col("item_id").cast("long").alias("item_id"), "text").distinct()
    chars = sized.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    blocks = 1 + chars // BLOCK_CHARS
    scratch = Scratch(spark) if blocks > 1 else None
    parts = []
    for k in range(blocks):
        rows = sized.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == k).orderBy("item_id", "text").collect()
        shared = spark.sparkContext.broadcast(Benchmark.of([(r[0], r[1]) for r in rows], q, share))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:  # noqa: ANN001
            worker_store("decontamination", dict)  # lets go of what an earlier stage kept in this worker
            tables = [(bench, bench.table()) for bench in shared.value]

            def told(ids: list, texts: list[np.ndarray]) -> pa.RecordBatch:
                got = sorted(((d, bench.ids[i], *rest) for bench, table in tables for d, i, *rest in bench.search(texts, table)))
                got = [(ids[d], *rest) for d, *rest in got]
                cols = list(zip(*got, strict=True)) or [()] * 5
                return pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if j < 2 else pa.int32()) for j, c in enumerate(cols)], ["doc_id", "item_id", "edits", "start", "end"])

            for batch in batches:
                ids, texts, chars = [], [], 0
                for i, t in zip(batch.column(0), batch.column(1), strict=True):
                    ids.append(i.as_py())
                    texts.append(codes(normal(t.as_py() or "")))
                    chars += len(texts[-1])
                    if chars >= _CHUNK:
                        yield told(ids, texts)
                        ids, texts, chars = [], [], 0
                yield told(ids, texts)

        found = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_col).mapInArrow(run, SCHEMA)
        if scratch:
            found = scratch.table(found, f"block{k}")
            shared.unpersist()
        parts.append(found)
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
