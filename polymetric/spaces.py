"""Metric spaces over columns, schemas of several of them, queries and weights."""

from __future__ import annotations

import math
from collections.abc import Mapping, Sequence
from dataclasses import dataclass
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.distances import KINDS, TWINS

#: Digits of canonical distances: ranking and boundary tests use them, so sums in another order agree.
DIGITS = 9
SLACK = 1e-9


@dataclass(frozen=True)
class MetricSpace:
    """A column and its metric; width: of short vectors, else None."""

    name: str
    kind: str
    width: int | None = None

    def sql(self, a: str, b: str, duck: bool = False) -> str:
        return KINDS[self.kind](a, b, self.width, duck)

    def between(self, a: Any, b: Any) -> float:
        return TWINS[self.kind](a, b)


@dataclass(frozen=True)
class MultiMetricSchema:
    spaces: tuple[MetricSpace, ...]
    oid: str = "oid"

    @staticmethod
    def of(*spaces: tuple) -> MultiMetricSchema:
        return MultiMetricSchema(tuple(MetricSpace(*s) for s in spaces))

    @property
    def names(self) -> list[str]:
        return [s.name for s in self.spaces]

    def weights(self, w: Mapping[str, float] | Sequence[float] | None) -> dict[str, float]:
        """Weights in [0, 1] by name, one above 0 at least; None: all 1."""
        given = dict.fromkeys(self.names, 1.0) if w is None else dict(w) if isinstance(w, Mapping) else dict(zip(self.names, w, strict=True))
        out = {n: float(given.get(n, 0.0)) for n in self.names}
        if set(given) - set(out) or any(math.isnan(x) or not 0 <= x <= 1 for x in out.values()) or not any(out.values()):
            raise ValueError(f"weights must be in [0, 1], of known spaces, and not all 0: {given}")
        return out

    def active(self, w: Mapping[str, float]) -> list[MetricSpace]:
        return [s for s in self.spaces if w[s.name] > 0]

    def subset(self, *names: str) -> MultiMetricSchema:
        return MultiMetricSchema(tuple(s for s in self.spaces if s.name in names), self.oid)


def infer_schema(df: DataFrame, oid: str = "oid") -> MultiMetricSchema:
    """Text by edit distance, pairs of numbers by L2, other arrays and numbers by L1."""
    out = []
    for name, kind in df.dtypes:
        if name != oid:
            out.append((name, "edit") if kind == "string" else (name, "l1v") if kind.startswith("array") else (name, "l1"))
    return MultiMetricSchema(tuple(MetricSpace(*s) for s in out), oid)


def literal(value: Any) -> str:
    """A value of a space as Spark SQL."""
    if isinstance(value, str):
        return "'" + value.replace("\\", "\\\\").replace("'", "\\'") + "'"
    if isinstance(value, (list, tuple)):
        return "array(" + ", ".join(literal(x) for x in value) + ")"
    return f"CAST({float(value)!r} AS DOUBLE)"


def query_row(df: DataFrame, schema: MultiMetricSchema, oid: int) -> dict[str, Any]:
    """A stored object as a query."""
    row = df.where(F.col(schema.oid) == oid).select(*schema.names).first()
    if row is None:
        raise ValueError(f"no object {oid}")
    return row.asDict()


def canonical(terms: Sequence[str]) -> str:
    return f"round({' + '.join(terms)}, {DIGITS})"


def mm_distance(schema: MultiMetricSchema, q: Mapping[str, Any] | None, w: Mapping[str, float], sigma: Mapping[str, float], alias: str = "", order: Sequence[str] | None = None) -> str:
    """The combined distance as Spark SQL. q None: against columns q_<space>. Spaces of weight 0 aren't read."""
    terms = []
    for s in schema.active(w):
        other = f"q_{s.name}" if q is None else literal(q[s.name])
        terms.append(f"{w[s.name]!r}D * {s.sql(alias + s.name, other)} / {sigma[s.name]!r}D")
    return canonical(terms)


def distance(schema: MultiMetricSchema, a: Mapping[str, Any], b: Mapping[str, Any], w: Mapping[str, float], sigma: Mapping[str, float]) -> float:
    return round(sum(w[s.name] * s.between(a[s.name], b[s.name]) / sigma[s.name] for s in schema.active(w)), DIGITS)


def check_metric(df: DataFrame, space: MetricSpace, n: int = 20, oid: str = "oid") -> DataFrame:
    """Triples of n objects, taken by an arithmetic hash of their ids, that break an axiom; (rule, a, b, c). The n objects are broadcast."""
    few = df.orderBy(F.expr(f"pmod({oid} * 7919, 10007)"), oid).limit(n).select(F.col(oid).alias("i"), F.col(space.name).alias("x"))
    a, b, c = (few.select(F.col("i").alias(k), F.col("x").alias(f"x{k}")) for k in "abc")
    d = lambda p, q: F.expr(space.sql(f"x{p}", f"x{q}"))
    all3 = a.join(F.broadcast(b)).join(F.broadcast(c)).withColumn("ab", d("a", "b")).withColumn("ba", d("b", "a")).withColumn("bc", d("b", "c")).withColumn("ac", d("a", "c")).withColumn("aa", d("a", "a"))
    rule = F.when(F.col("ab") < 0, "sign").when(F.abs(F.col("ab") - F.col("ba")) > SLACK, "symmetry").when(F.abs("aa") > 1e-6, "identity").when(F.col("ac") > F.col("ab") + F.col("bc") + SLACK, "triangle")
    return all3.select(rule.alias("rule"), "a", "b", "c").where("rule IS NOT NULL")
