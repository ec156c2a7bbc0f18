"""The SQL surface: ``column IN MM_RANGE(query, weights, radius)`` and ``column IN MM_KNN(query, weights, k [, WHERE => 'condition'])``.

The query is a stored object's id or ``OBJECT('{"space": value, ...}')``, any object as JSON. With WHERE the k nearest of the rows that
meet the condition are found; a condition outside only filters the k nearest of all.

The predicates are found outside strings and comments and become IN-subqueries over the index's answer, so the rest of the statement is
plain Spark SQL, and no outer filter moves below a kNN. Weights are an array or MM_WEIGHTS('profile').
"""

from __future__ import annotations

import json
import re
import uuid

from pyspark.sql import DataFrame

from polymetric.index import MultiMetricIndex, knn_scan

_TOKEN = re.compile(r"'(?:[^'\\]|\\.|'')*'|--[^\n]*|/\*.*?\*/|\bMM_(?P<kind>RANGE|KNN)\s*\(", re.I | re.S)


def _close(text: str, at: int) -> int:
    depth = 1
    while depth:
        if at >= len(text):
            raise ValueError("a search predicate is not closed")
        if text[at] == "'":
            at = text.index("'", at + 1)
        depth += {"(": 1, ")": -1}.get(text[at], 0)
        at += 1
    return at


def _weights(index: MultiMetricIndex, text: str) -> dict[str, float]:
    if m := re.fullmatch(r"MM_WEIGHTS\s*\(\s*'(\w+)'\s*\)", text.strip(), re.I):
        return index.weights[m[1]]
    return index.schema.weights([float(x) for x in re.fullmatch(r"array\s*\((.*)\)", text.strip(), re.I | re.S)[1].split(",")])


def _args(text: str) -> list[str]:
    """The arguments between the outer commas, outside strings and brackets."""
    out, depth, at, start = [], 0, 0, 0
    while at < len(text):
        if text[at] == "'":
            at = text.index("'", at + 1)
        elif text[at] in "([{":
            depth += 1
        elif text[at] in ")]}":
            depth -= 1
        elif text[at] == "," and not depth:
            out.append(text[start:at].strip())
            start = at + 1
        at += 1
    return [*out, text[start:].strip()]


def _query(text: str, index: MultiMetricIndex) -> int | dict:
    if m := re.fullmatch(r"OBJECT\s*\(\s*'(.*)'\s*\)", text, re.I | re.S):
        given = json.loads(m[1].replace("\\'", "'").replace("''", "'"))
        if missing := set(index.schema.names) - set(given):
            raise ValueError(f"the object has no {sorted(missing)}")
        return {n: float(v) if isinstance(v := given[n], int) else v for n in index.schema.names}
    return int(text)


def _search(index: MultiMetricIndex, kind: str, args: list[str]) -> DataFrame:
    if len(args) < 3:
        raise ValueError("a search takes a query, weights and a radius or k")
    q, w = _query(args[0], index), _weights(index, args[1])
    if len(args) == 3:
        return index.range(q, w, float(args[2])) if kind == "RANGE" else index.knn(q, w, int(args[2]))
    m = re.fullmatch(r"WHERE\s*=>\s*'(.*)'", args[3], re.I | re.S)
    if kind != "KNN" or not m:
        raise ValueError(f"not understood: {args[3]}")
    return knn_scan(index.objects.where(m[1].replace("''", "'")), index.schema, index.bind(q), w, int(args[2]), index.sigma)


def rewrite(text: str, index: MultiMetricIndex) -> tuple[str, dict[str, DataFrame]]:
    """The statement with {placeholders} for the searches, and the searches."""
    out, frames, at = [], {}, 0
    while m := _TOKEN.search(text, at):
        if not m["kind"]:
            out.append(text[at : m.end()])
            at = m.end()
            continue
        end = _close(text, m.end())
        found = _search(index, m["kind"].upper(), _args(text[m.end() : end - 1]))
        name = f"mm_{uuid.uuid4().hex[:8]}"
        frames[name] = found.select(index.schema.oid)
        out += [text[at : m.start()], f"(SELECT {index.schema.oid} FROM {{{name}}})"]
        at = end
    return "".join([*out, text[at:]]), frames


def sql(text: str, index: MultiMetricIndex, **tables: DataFrame) -> DataFrame:
    """Runs a statement; tables are named in braces."""
    rewritten, frames = rewrite(text, index)
    return index.objects.sparkSession.sql(rewritten, **frames, **tables)
