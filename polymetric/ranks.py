"""Exact order statistics of distances that are never stored: passes of whole arrays that count values by the bits of their pattern.

The patterns of non-negative doubles are in the order of their values. A pass counts the values with a known opening by the next bits, the
counts name the opening of the place that is looked for, and once few values share it, or only one value does, they decide. Each pass
computes the distances anew; a task gives at most so many counts as a digit has values, whatever the rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric import cells
from polymetric.spaces import MetricSpace, MultiMetricSchema

#: Bits of the first digit and of the others, values of all spaces that may be gathered, values that are counted at once, and rows of a block of
#: pairs and blocks at least.
FIRST, NEXT, FEW, CHUNK = 16, 12, 200_000, 100_000
BLOCK_ROWS, LEAST_BLOCKS = 5_000, 8
#: An opening: (bits, their number, whether its values are gathered).
Opening = tuple[int, int, bool]
Want = dict[int, list[Opening]]
_KIND = pa.schema([("space", pa.int32()), ("k", pa.int32()), ("digit", pa.int32()), ("value", pa.float64()), ("n", pa.int64())])
_SQL = "space int, k int, digit int, value double, n long"
#: In place of a digit: a gathered value, the least and the largest value of an opening, and the number of values, missing ones included.
_VALUE, _LEAST, _LARGEST, _ALL = -1, -2, -3, -4


def _width(used: int) -> int:
    return NEXT if used else FIRST


class Tally:
    """What a task has counted, by space and opening."""

    def __init__(self, want: Want, weight: int = 1):
        self.want, self.weight = want, weight
        self.waiting: dict[int, list[np.ndarray]] = {j: [] for j in want}
        self.held, self.all = dict.fromkeys(want, 0), dict.fromkeys(want, 0)
        self.counts = {(j, k): np.zeros(1 << _width(used), np.int64) for j, asked in want.items() for k, (_, used, gather) in enumerate(asked) if not gather}
        self.values = {(j, k): [] for j, asked in want.items() for k in range(len(asked)) if asked[k][2]}
        self.ends: dict[tuple[int, int], tuple[float, float]] = {}

    def add(self, j: int, values: np.ndarray) -> None:
        self.waiting[j].append(values)
        self.held[j] += len(values)
        if self.held[j] >= CHUNK:
            self.flush(j)

    def flush(self, j: int) -> None:
        if not self.waiting[j]:
            return
        self.all[j] += self.held[j] * self.weight
        values = np.concatenate(self.waiting[j])
        self.waiting[j], self.held[j] = [], 0
        values = values[~np.isnan(values)] + 0.0
        bits = values.view(np.uint64)
        for k, (opening, used, gather) in enumerate(self.want[j]):
            own = bits[bits >> np.uint64(64 - used) == np.uint64(opening)] if used else bits
            if not len(own):
                continue
            lo, hi = (float(x.view(np.float64)) for x in (own.min(), own.max()))
            a, b = self.ends.get((j, k), (lo, hi))
            self.ends[j, k] = min(a, lo), max(b, hi)
            if gather:
                self.values[j, k].append(own)
            else:
                width = _width(used)
                digits = own >> np.uint64(64 - used - width) & np.uint64((1 << width) - 1)
                self.counts[j, k] += np.bincount(digits.astype(np.int64), minlength=1 << width) * self.weight

    def rows(self) -> pa.RecordBatch:
        out: list[tuple] = []
        for j in self.want:
            self.flush(j)
            out.append((j, 0, _ALL, 0.0, self.all[j]))
        for (j, k), (lo, hi) in self.ends.items():
            out += [(j, k, _LEAST, lo, 1), (j, k, _LARGEST, hi, 1)]
        for (j, k), n in self.counts.items():
            at = np.flatnonzero(n)
            out += [(j, k, d, 0.0, c) for d, c in zip(at.tolist(), n[at].tolist(), strict=True)]
        for (j, k), parts in self.values.items():
            if parts:
                value, n = np.unique(np.concatenate(parts), return_counts=True)
                out += [(j, k, _VALUE, x, c * self.weight) for x, c in zip(value.view(np.float64).tolist(), n.tolist(), strict=True)]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), _KIND.types, strict=True)], schema=_KIND)


class Plain(cells.Cell):
    """Rows and queries as arrays in the order given, vectors by columns."""

    def pack(self, ids: np.ndarray) -> None:
        self.columns = {s.name: [np.ascontiguousarray(c) for c in self.x[s.name].T] for s in self.spaces if s.kind in ("l1v", "l2v")}

    def wide(self, s: MetricSpace) -> bool:
        return False


def _distances(rows: pa.Table, asked: pa.Table, spaces: list[MetricSpace], tally: Tally, scale: Mapping[str, tuple[float, float]] | None) -> None:
    """Counts all distances of rows to queries: of each space wanted, or, with (weight, sigma) by space, the combined ones."""
    used = [s for j, s in enumerate(spaces) if scale is not None or j in tally.want]
    w, sigma = ({n: x[i] for n, x in (scale or {}).items()} for i in (0, 1))
    ids = rows.append_column("_at", pa.array(np.arange(rows.num_rows)))
    cell, every = Plain(ids, asked, used, w, sigma, "_at"), slice(None)
    order = [(j, s) for j, s in enumerate(spaces) if s in used]
    for i in range(asked.num_rows):
        if scale is not None:
            tally.add(0, cell.distances(i, every))
        else:
            for j, s in order:
                tally.add(j, cell.raw(s, i, every))


def _summed(told: DataFrame) -> DataFrame:
    return told.groupBy("space", "k", "digit", "value").agg(F.sum("n").alias("n"))


def beside(df: DataFrame, queries: DataFrame, schema: MultiMetricSchema, scale: Mapping[str, tuple[float, float]] | None = None) -> Callable[[Want], DataFrame]:
    """A pass over the distances of all rows to a fixed number of queries, which go to every task."""
    spaces = [s for s in schema.spaces if scale is None or s.name in scale]
    few = queries.select(*(F.col(s.name).alias(f"q_{s.name}") for s in spaces)).toArrow()

    def run(want: Want) -> DataFrame:
        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            tally = Tally(want)
            for batch in batches:
                if batch.num_rows:
                    _distances(pa.Table.from_batches([batch]), few, spaces, tally, scale)
            yield tally.rows()

        names = [s.name for j, s in enumerate(spaces) if scale is not None or j in want]
        return _summed(df.select(*names).mapInArrow(count, _SQL))

    return run


def among(df: DataFrame, schema: MultiMetricSchema) -> Callable[[Want], DataFrame]:
    """A pass over the distances of all pairs of rows, both ways and each row with itself: blocks of rows meet, two different ones once,
    and what they give counts twice, since distances are the same both ways."""
    blocks, oid, spaces = max(LEAST_BLOCKS, -(-df.count() // BLOCK_ROWS)), schema.oid, list(schema.spaces)
    dealt = df.withColumn("rk_block", F.expr(f"CAST(pmod(xxhash64({oid}), {blocks}) AS INT)"))

    def run(want: Want) -> DataFrame:
        names = [s.name for j, s in enumerate(spaces) if j in want]

        def count(keys: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
            a, b = (k.as_py() for k in keys)
            tally = Tally(want, 1 if a == b else 2)
            if left.num_rows and right.num_rows:
                _distances(left, right, spaces, tally, None)
            return pa.Table.from_batches([tally.rows()])

        every = lambda lo, hi: F.explode(F.expr(f"sequence({lo}, {hi})"))
        left = dealt.select(F.col("rk_block").alias("rk_a"), *names).withColumn("rk_b", every("rk_a", str(blocks - 1)))
        right = dealt.select(F.col("rk_block").alias("rk_b"), *(F.col(n).alias(f"q_{n}") for n in names)).withColumn("rk_a", every("0", "rk_b"))
        parts = min(2 * blocks * (blocks + 1), cells.MOST_CELLS)
        left, right = (x.repartition(parts, "rk_a", "rk_b") for x in (left, right))
        return _summed(left.groupBy("rk_a", "rk_b").cogroup(right.groupBy("rk_a", "rk_b")).applyInArrow(count, _SQL))

    return run


def order_statistics(run: Callable[[Want], DataFrame], n_spaces: int, places: Callable[[int], list[int]]) -> tuple[list[list[float]], int]:
    """The values of each space at ``places`` (from 0, a function of the number of values that aren't missing), and the number of values
    with missing ones. A space without values has none."""
    want: Want = {j: [(0, 0, False)] for j in range(n_spaces)}
    goals: dict[int, list[dict]] = {}
    n_all = 0
    while want:
        got = run(want).toArrow().to_pandas()
        if not n_all:
            n_all = int(got.n[(got.digit == _ALL) & (got.space == 0)].sum())
        parts = dict(iter(got[got.digit != _ALL].groupby(["space", "k"])))
        after: Want = {}
        for j, asked in want.items():
            if j not in goals:
                first = parts.get((j, 0))
                total = int(first.n[first.digit >= 0].sum()) if first is not None else 0
                goals[j] = [{"at": (0, 0), "rank": p, "value": None} for p in places(total)] if total else []
            for g in goals[j]:
                if g["value"] is not None:
                    continue
                k = next(k for k, x in enumerate(asked) if x[:2] == g["at"])
                (opening, used, gather), part = asked[k], parts[j, k]
                lo, hi = part.value[part.digit == _LEAST].min(), part.value[part.digit == _LARGEST].max()
                counted = part[part.digit == _VALUE].sort_values("value") if gather else part[part.digit >= 0].sort_values("digit")
                upto = counted.n.cumsum().to_numpy()
                i = int(np.searchsorted(upto, g["rank"], "right"))
                if lo == hi:
                    g["value"] = float(lo)
                elif gather:
                    g["value"] = float(counted.value.iloc[i])
                else:
                    width = _width(used)
                    opening, used, n = opening << width | int(counted.digit.iloc[i]), used + width, int(counted.n.iloc[i])
                    g["at"], g["rank"] = (opening, used), g["rank"] - int(upto[i] - n)
                    if used == 64:
                        g["value"] = float(np.uint64(opening).view(np.float64))
                    elif (ask := (opening, used, n <= FEW // n_spaces)) not in after.setdefault(j, []):
                        after[j].append(ask)
        want = after
    return [[g["value"] for g in goals[j]] for j in range(n_spaces)], n_all
