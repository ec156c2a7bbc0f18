"""Distances as SQL expressions: one text for Spark, one for DuckDB, and Python twins for single values on the driver."""

from __future__ import annotations

import math
from collections.abc import Callable

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

#: Vectors up to this width are written out term by term, which stays inside whole-stage codegen.
UNROLL = 16
#: As the width of an edit space: texts of whole documents, compared by ``pm_edit`` (64 cells of the table a step) instead of cell by cell.
LONG = 1 << 16


def _vector(a: str, b: str, term: str, total: str, width: int | None, duck: bool) -> str:
    if duck:
        return total.format(f"list_sum(list_transform(list_zip({a}, {b}), lambda p: {term.format('p[1]', 'p[2]')}))")
    if width and width <= UNROLL:
        return total.format(" + ".join(term.format(f"{a}[{i}]", f"{b}[{i}]") for i in range(width)))
    return total.format(f"aggregate(zip_with({a}, {b}, (x, y) -> {term.format('x', 'y')}), 0D, (s, x) -> s + x)")


def l1(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    return f"abs({a} - {b})"


def l1_vector(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    return _vector(a, b, "abs({} - {})", "({})", width, duck)


def l2_vector(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    return _vector(a, b, "pow({0} - {1}, 2)", "sqrt({})", width, duck)


def edit(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    return f"pm_edit({a}, {b})" if width == LONG and not duck else f"CAST(levenshtein({a}, {b}) AS DOUBLE)"


def edit_capped(a: str, b: str, cap: str) -> str:
    """-1 where the distance passes ``cap``, which may be a column (Spark only)."""
    return f"levenshtein({a}, {b}, CAST({cap} AS INT))"


def discrete(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    return f"CASE WHEN {a} IS NOT DISTINCT FROM {b} THEN 0.0 ELSE 1.0 END" if duck else f"CASE WHEN {a} <=> {b} THEN 0D ELSE 1D END"


def linf(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    return f"list_max(list_transform(list_zip({a}, {b}), lambda p: abs(p[1] - p[2])))" if duck else f"array_max(zip_with({a}, {b}, (x, y) -> abs(x - y)))"


def hamming(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    return _vector(a, b, "CASE WHEN {0} = {1} THEN 0.0 ELSE 1.0 END" if duck else "CASE WHEN {0} = {1} THEN 0D ELSE 1D END", "({})", width, duck)


def jaccard(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    """1 - shared / all of two sets of tokens; two empty sets are equal."""
    if duck:
        return f"1.0 - COALESCE(CAST(len(list_intersect({a}, {b})) AS DOUBLE) / NULLIF(len(list_distinct(list_concat({a}, {b}))), 0), 1.0)"
    return f"1D - COALESCE(CAST(size(array_intersect({a}, {b})) AS DOUBLE) / NULLIF(size(array_union({a}, {b})), 0), 1D)"


def angular(a: str, b: str, width: int | None = None, duck: bool = False) -> str:
    """The angle between two non-zero vectors, which is a metric on directions (a cosine itself is not)."""
    dot, aa, bb = (_vector(x, y, "({0} * {1})", "({})", width, duck) for x, y in ((a, b), (a, a), (b, b)))
    return f"acos(least(1.0, greatest(-1.0, {dot} / sqrt({aa} * {bb}))))"


def _levenshtein(a: str, b: str) -> float:
    """Exact, by columns of the table as two whole numbers: where it rises and where it falls by one from row to row."""
    if len(a) < len(b):
        a, b = b, a
    if not b or a == b:
        return 0.0 if a == b else float(len(a))
    full = (1 << len(a)) - 1
    letters = {ord(c): "0" for c in set(a)}
    at = {c: int(a[::-1].translate(letters | {ord(c): "1"}), 2) for c in set(a) & set(b)}
    up, down = full, 0
    for c in b:
        same = at.get(c, 0)
        stay = same | down
        cross = (((same & up) + up) ^ up) | same
        rise, fall = down | (full & ~(cross | up)), up & cross
        rise, fall = (rise << 1) | 1, fall << 1
        up, down = (fall | ~(stay | rise)) & full, rise & stay & full
    return float(len(b) + up.bit_count() - down.bit_count())


def register_edit(spark: SparkSession) -> None:
    """Makes ``pm_edit`` known to the session, for spaces of LONG texts."""

    @F.pandas_udf("double")
    def pm_edit(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else _levenshtein(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")

    spark.udf.register("pm_edit", pm_edit)


KINDS: dict[str, Callable[..., str]] = {"l1": l1, "l1v": l1_vector, "l2v": l2_vector, "edit": edit, "discrete": discrete, "linf": linf, "hamming": hamming, "jaccard": jaccard, "angular": angular}
TWINS: dict[str, Callable] = {
    "l1": lambda a, b: abs(a - b),
    "l1v": lambda a, b: sum(abs(x - y) for x, y in zip(a, b, strict=True)),
    "l2v": lambda a, b: math.sqrt(sum((x - y) ** 2 for x, y in zip(a, b, strict=True))),
    "edit": _levenshtein,
    "discrete": lambda a, b: float(a != b),
    "linf": lambda a, b: max(abs(x - y) for x, y in zip(a, b, strict=True)),
    "hamming": lambda a, b: float(sum(x != y for x, y in zip(a, b, strict=True))),
    "jaccard": lambda a, b: 1 - len({*a} & {*b}) / len({*a} | {*b}) if {*a} | {*b} else 0.0,
    "angular": lambda a, b: math.acos(max(-1, min(1, sum(x * y for x, y in zip(a, b, strict=True)) / math.sqrt(sum(x * x for x in a) * sum(y * y for y in b))))),
}


def register_metric(name: str, expression: Callable[..., str], twin: Callable) -> None:
    """Adds a metric of the user's: an expression builder with the signature of those above, which may call a
    registered (Arrow) function, and its twin. The four axioms are the caller's word; ``check_metric`` samples them."""
    KINDS[name], TWINS[name] = expression, twin
