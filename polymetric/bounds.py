"""Tests that discard leaves or objects without losing a result, as SQL over boxes or stored pivot distances.

Distances to pivots are stored raw and divided by sigma here, so one index serves any weights and a refitted normaliser.
All comparisons leave SLACK for rounding.
"""

from __future__ import annotations

from collections.abc import Mapping

from polymetric.spaces import SLACK, MetricSpace, MultiMetricSchema, literal


def query_box(a: Mapping[str, float], w: Mapping[str, float], sigma: Mapping[str, float], r: float, scaled: bool = True) -> dict[str, tuple[float, float]]:
    """The interval of raw pivot distances that results can have in each active space: half-width r, or r / weight."""
    return {n: (x - half, x + half) for n, x in a.items() if w[n] > 0 for half in [sigma[n] * r / (w[n] if scaled else 1)]}


def gap(name: str, a: float, sigma: float) -> str:
    """How far a leaf's interval is from the query, in normalised units."""
    return f"greatest(0D, lo_{name} - {a!r}D, {a!r}D - hi_{name}) / {sigma!r}D"


def leaf_test(a: Mapping[str, float], w: Mapping[str, float], sigma: Mapping[str, float], r: float, rule: str = "weighted_sum") -> str:
    """Leaves to keep. weighted_sum: the weighted gaps add up to r at most. scaled_any: each weighted gap is at most r.
    uniform_all: some unweighted gap is at most r, sound only for weights that add up to 1 or more (else weighted_sum)."""
    active = [n for n in a if w[n] > 0]
    if rule == "uniform_all" and sum(w.values()) < 1:
        rule = "weighted_sum"
    gaps = {n: gap(n, a[n], sigma[n]) for n in active}
    if rule == "uniform_all":
        return "(" + " OR ".join(f"{gaps[n]} <= {r + SLACK!r}D" for n in active) + ")"
    if rule == "scaled_any":
        return "(" + " AND ".join(f"{w[n]!r}D * {gaps[n]} <= {r + SLACK!r}D" for n in active) + ")"
    if rule == "none":
        return "true"
    return "(" + " + ".join(f"{w[n]!r}D * {gaps[n]}" for n in active) + f" <= {r + SLACK!r}D)"


def thresholds(w: Mapping[str, float], r: float, shares: Mapping[str, float] | None = None) -> dict[str, float]:
    """Pigeonhole thresholds t with sum of w * t = r: alike (r / sum of w), or by shares of r."""
    active = [n for n, x in w.items() if x > 0]
    total = sum(w.values())
    part = sum((shares or {}).get(n, 0) for n in active)
    return {n: (r / total if not shares else r * shares.get(n, 0) / part / w[n]) for n in active}


def pigeonhole(schema: MultiMetricSchema, q: Mapping, w: Mapping[str, float], sigma: Mapping[str, float], r: float, shares: Mapping[str, float] | None = None) -> str:
    """Necessary, not sufficient: a result is within its threshold in some active space."""
    t = thresholds(w, r, shares)
    return "(" + " OR ".join(f"{s.sql(s.name, literal(q[s.name]))} / {sigma[s.name]!r}D <= {t[s.name] + SLACK!r}D" for s in schema.active(w)) + ")"


def single_space(schema: MultiMetricSchema, q: Mapping, w: Mapping[str, float], sigma: Mapping[str, float], r: float) -> str:
    """Necessary: no space alone passes r."""
    return "(" + " AND ".join(f"{w[s.name]!r}D * {s.sql(s.name, literal(q[s.name]))} / {sigma[s.name]!r}D <= {r + SLACK!r}D" for s in schema.active(w)) + ")"


def pivot_sum(a: Mapping[str, list[float]], w: Mapping[str, float], sigma: Mapping[str, float], r: float) -> str:
    """The weighted sum of each space's best lower bound from stored vantage distances v_<space>_<j> is at most r."""
    parts = []
    for n, values in a.items():
        if w[n] > 0:
            lows = [f"abs(v_{n}_{j} - {x!r}D)" for j, x in enumerate(values)]
            parts.append(f"{w[n]!r}D * {lows[0] if len(lows) == 1 else 'greatest(' + ', '.join(lows) + ')'} / {sigma[n]!r}D")
    return f"({' + '.join(parts)} <= {r + SLACK!r}D)"


def implied_ranges(a: Mapping[str, list[float]], w: Mapping[str, float], sigma: Mapping[str, float], r: float) -> str:
    """One-column ranges that follow from pivot_sum; a Parquet reader can skip row groups by them."""
    out = []
    for n, values in a.items():
        if w[n] > 0:
            half = sigma[n] * (r + SLACK) / w[n]
            out += [f"v_{n}_{j} BETWEEN {x - half!r}D AND {x + half!r}D" for j, x in enumerate(values)]
    return "(" + " AND ".join(out) + ")"


def early_stop(schema: MultiMetricSchema, q: Mapping, w: Mapping[str, float], sigma: Mapping[str, float], r: float) -> str:
    """Verification that evaluates cheap spaces first and gives up once the partial sum passes r."""
    cost = {"l1": 0, "discrete": 0, "l2v": 1, "l1v": 2, "edit": 3}
    spaces = sorted(schema.active(w), key=lambda s: (cost.get(s.kind, 2), s.width or 64))
    so_far, tests = "0D", []
    for s in spaces:
        so_far = f"{so_far} + {w[s.name]!r}D * {s.sql(s.name, literal(q[s.name]))} / {sigma[s.name]!r}D"
        tests.append(f"WHEN {so_far} > {r + SLACK!r}D THEN false")
    return f"(CASE {' '.join(tests)} ELSE true END)"


CHEAP = ("l1", "l2v", "discrete")


def cheap(s: MetricSpace) -> bool:
    """Whether a space's distance costs no more than its bounds: numbers and short vectors."""
    return s.kind in CHEAP or s.kind in ("l1v", "linf", "hamming") and (s.width or 99) <= 16


def staged(schema: MultiMetricSchema, q: Mapping | None, w: Mapping[str, float], sigma: Mapping[str, float], low: Mapping[str, str], r: str) -> str:
    """Necessary: the distances of cheap spaces, and lower bounds of the others' (raw, as SQL), add up to r at most. q None: against columns q_<space>."""
    parts = []
    for s in schema.active(w):
        d = s.sql(s.name, f"q_{s.name}" if q is None else literal(q[s.name])) if cheap(s) else low.get(s.name, "0D")
        parts.append(f"{w[s.name]!r}D * {d} / {sigma[s.name]!r}D")
    return f"({' + '.join(parts)} <= {r} + {SLACK!r}D)"


def pivot_lows(a: Mapping[str, list], w: Mapping[str, float]) -> dict[str, str]:
    """The best lower bound of each active space's raw distance from stored vantage distances; a: numbers, or columns' names."""
    out = {}
    for n, values in a.items():
        if w[n] > 0:
            each = [f"abs(v_{n}_{j} - {x if isinstance(x, str) else repr(x) + 'D'})" for j, x in enumerate(values)]
            out[n] = each[0] if len(each) == 1 else "greatest(" + ", ".join(each) + ")"
    return out


def edit_lower(a_len: str, q_len: str, common: str, g: int) -> str:
    """A lower bound of edit distance from lengths and shared g-grams: each edit spoils g grams at most."""
    return f"greatest(abs({a_len} - {q_len}), CAST(ceil((greatest({a_len}, {q_len}) - {g} + 1 - {common}) / {g}.0) AS INT))"
