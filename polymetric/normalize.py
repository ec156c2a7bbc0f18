"""Normalisers: sigma of a space is twice the median of observed distances."""

from __future__ import annotations

import math
import operator
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.spaces import MultiMetricSchema

#: Anchors are the first of an arithmetic shuffle of the ids, so any engine picks the same.
ANCHOR_ORDER = "({oid} * 7919 + 104729) % 1000003"

#: Error of the sketch that narrows the exact median, as a share of the rows, rows of all spaces that may be counted by value, and the
#: shares at which an interval may be cut once the place of the middle rows in it is counted.
SKETCH, FEW_VALUES = 1e-4, 200_000
POINTS = [i / 64 for i in range(65)]


def anchors(df: DataFrame, schema: MultiMetricSchema, n: int = 16) -> DataFrame:
    return df.orderBy(F.expr(ANCHOR_ORDER.format(oid=schema.oid)), schema.oid).limit(n)


def observed(df: DataFrame, schema: MultiMetricSchema, pairs: str = "anchors", n: int = 16) -> DataFrame:
    """Distances of each space, columns d_<space>: of all rows to ``n`` anchors (broadcast, a fixed number), of all
    pairs (in the grid of ``index.met``), or of ``n`` pairs of neighbours in two arithmetic shuffles (random)."""
    if pairs == "all":
        from polymetric.index import met

        both = met(df, df, schema)
    else:
        both = df.join(F.broadcast(anchors(df, schema, n).select(*(F.col(s.name).alias(f"q_{s.name}") for s in schema.spaces))))
    return both.select(*(F.expr(s.sql(s.name, f"q_{s.name}")).alias(f"d_{s.name}") for s in schema.spaces))


def medians(d: DataFrame, names: list[str]) -> tuple[dict[str, float], int]:
    """Exact medians of columns d_<name> and the number of rows, for all names at once. Each pass counts the rows before and inside a
    name's interval, and a sketch of those inside proposes a narrower one around the middle. Only counts decide: an interval that has lost a
    middle row is widened again on that side. Once few rows are left, or no fewer, they are counted by value. Neither a task nor the driver
    holds a column, and nothing is shuffled by value. A column without values has no median."""
    n, few = 0, FEW_VALUES // len(names)
    held = dict.fromkeys(names, (-math.inf, math.inf))  # intervals that hold both middle rows, as counted
    tried = dict(held)  # intervals that the next pass counts
    shares = dict.fromkeys(names, [0.5 - 3 * SKETCH, 0.5 + 3 * SKETCH])
    first, last = {}, {}  # the middle rows' places in the interval held
    wide = list(names)
    while wide:
        cells = [F.count("*").alias("n")]
        for k in wide:
            c, inside = F.col(f"d_{k}"), F.col(f"d_{k}").between(*tried[k])
            sketch = F.percentile_approx(F.when(inside, c), F.array(*map(F.lit, shares[k])), F.lit(int(1 / SKETCH)))
            cells.append(F.struct(F.count_if(c.between(-math.inf, math.inf)), F.count_if(c < tried[k][0]), F.count_if(inside), sketch).alias(k))
        row = d.agg(*cells).first()
        n, after = row["n"], []
        for k in wide:
            values, before, count, cuts = row[k]
            (lo, hi), at, to = tried[k], (values - 1) // 2 - before, values // 2 - before
            if not values:
                continue
            if at < 0 or to >= count:
                tried[k], shares[k] = (held[k][0] if at < 0 else lo, held[k][1] if to >= count else hi), POINTS
                after.append(k)
                continue
            held[k], first[k], last[k] = (lo, hi), at, to
            below = [x for s, x in zip(shares[k], cuts, strict=True) if s <= at / count - 2 * SKETCH]
            above = [x for s, x in zip(shares[k], cuts, strict=True) if s >= to / count + 2 * SKETCH]
            tried[k] = (max(below, default=lo), min(above, default=hi))
            narrowed, coarse = tried[k] != held[k], shares[k] is POINTS
            shares[k] = POINTS if narrowed else [max(0.0, at / count - 3 * SKETCH), min(1.0, to / count + 3 * SKETCH)]
            if count > few and lo < hi and (narrowed or coarse):
                after.append(k)
        wide = after
    if not first:
        return {}, n
    cells = {k: F.col(f"d_{k}").between(*held[k]) for k in first}
    values = F.array(*(F.when(x, F.struct(F.lit(k).alias("space"), F.col(f"d_{k}").alias("d"))) for k, x in cells.items()))
    cut = d.where(reduce(operator.or_, cells.values())).select(F.explode(values).alias("v")).where("v IS NOT NULL").select("v.*")
    counts: dict[str, list[tuple[float, int]]] = {k: [] for k in first}
    for r in cut.groupBy("space", "d").agg(F.count("*").alias("c")).collect():  # a few values of each space
        counts[r["space"]].append((r["d"], r["c"]))
    out = {}
    for k, found in counts.items():
        before, middle = 0, []
        for x, c in sorted(found):
            middle += [x for place in (first[k], last[k]) if before <= place < before + c]
            before += c
        out[k] = middle[0] + (middle[1] - middle[0]) * 0.5
    return out, n


def _exact_medians(df: DataFrame, schema: MultiMetricSchema, pairs: str, n: int) -> tuple[dict[str, float], int]:
    """Medians by arrays (``ranks``) where all spaces have them, else of columns in SQL."""
    from polymetric import cells, ranks

    if pairs == "random" or not cells.able(schema, dict.fromkeys(schema.names, 1.0)):
        return medians(observed(df, schema, pairs, n), schema.names)
    run = ranks.among(df, schema) if pairs == "all" else ranks.beside(df, anchors(df, schema, n), schema)
    middle, n_pairs = ranks.order_statistics(run, len(schema.names), lambda values: [(values - 1) // 2, values // 2])
    return {k: m[0] + (m[1] - m[0]) * 0.5 for k, m in zip(schema.names, middle, strict=True) if m}, n_pairs


def norm_table(df: DataFrame, schema: MultiMetricSchema, pairs: str = "anchors", n: int = 16, policy: str = "median2", exact: bool = True) -> DataFrame:
    """(space, sigma, n_pairs), one pass for all spaces. policy: median2, max, mean or none; a constant space gets 1.
    exact False takes a sketch for the median."""
    if policy == "median2" and exact:
        found, n_pairs = _exact_medians(df, schema, pairs, n)
        return df.sparkSession.createDataFrame([(k, 2 * found[k] if found.get(k, 0) > 0 else 1.0, n_pairs) for k in schema.names], "space string, sigma double, n_pairs long")
    d = observed(df, schema, pairs, n)
    stat = {"median2": lambda c: 2 * F.percentile_approx(c, F.lit(0.5)), "max": F.max, "mean": F.avg, "none": lambda c: F.max(F.lit(1.0))}[policy]
    row = d.agg(F.count("*").alias("n_pairs"), *(stat(F.col(f"d_{s.name}")).alias(s.name) for s in schema.spaces))
    cells = ", ".join(f"'{s.name}', {s.name}" for s in schema.spaces)
    return row.selectExpr(f"stack({len(schema.spaces)}, {cells}) AS (space, s)", "n_pairs").select("space", F.when(F.col("s") > 0, F.col("s")).otherwise(1.0).alias("sigma"), "n_pairs")


def fit_normaliser(df: DataFrame, schema: MultiMetricSchema, **options) -> dict[str, float]:  # noqa: ANN003
    return {r["space"]: r["sigma"] for r in norm_table(df, schema, **options).collect()}
