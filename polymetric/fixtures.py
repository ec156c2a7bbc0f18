"""The experiment data sets on the given tables: one derivation in two dialects, Spark SQL and DuckDB SQL."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

from polymetric.distances import LONG, register_edit
from polymetric.spaces import MultiMetricSchema
from polymetric.store import new_folder, once

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@dataclass(frozen=True)
class Dialect:
    duck: bool
    n_vectors: str = "(SELECT count(*) FROM embeddings)"

    def days(self, c: str) -> str:
        return f"CAST(date_diff('day', DATE '1970-01-01', CAST({c} AS DATE)) AS DOUBLE)" if self.duck else f"CAST(datediff(CAST({c} AS DATE), DATE'1970-01-01') AS DOUBLE)"

    def vector(self, c: str) -> str:
        return f"CAST({c} AS DOUBLE[])" if self.duck else f"CAST({c} AS ARRAY<DOUBLE>)"

    def slice(self, c: str, first: int, n: int) -> str:
        return f"({c})[{first}:{first + n - 1}]" if self.duck else f"slice({c}, {first}, {n})"

    def array(self, *items: str) -> str:
        return f"[{', '.join(items)}]" if self.duck else f"array({', '.join(items)})"

    def ascii(self, c: str) -> str:
        return f"trim(regexp_replace(lower({c}), '[^a-z]+', ' '{', ' + chr(39) + 'g' + chr(39) if self.duck else ''}))"

    def number(self, c: str) -> str:
        return f"CAST({c} AS DOUBLE)"

    def feature(self, c: str, i: int) -> str:
        return f"CAST(({c} * {7919 + 37 * i} + {104729 * i}) % 10007 AS DOUBLE) / 10007"


def _vec(d: Dialect, key: str) -> str:
    return f"(SELECT vec_id, {d.vector('embedding')} AS vec FROM embeddings) e ON e.vec_id = {key}"


def _with_vector(d: Dialect, key: str, source: str) -> str:
    """The rows with the number of their vector, counted before any join."""
    n = d.n_vectors
    return f"(SELECT t.*, {key} % n_vec AS vec_key FROM {source} t, (SELECT count(*) AS n_vec FROM embeddings) c)" if d.duck else f"(SELECT t.*, {key} % {n} AS vec_key FROM {source} t)"


def _rental(d: Dialect) -> str:
    return f"""SELECT o_orderkey AS oid, {d.number('o_totalprice')} AS price,
        {d.array("COALESCE(n_lines, 0D)" if not d.duck else "COALESCE(n_lines, 0.0)", "COALESCE(quantity, 0D)" if not d.duck else "COALESCE(quantity, 0.0)")} AS size,
        {d.array(d.number('c_acctbal') + ' / 1000', d.number('c_nationkey'))} AS loc, {d.days('o_orderdate')} AS listed,
        o_orderpriority || ' ' || c_mktsegment AS review, r_name AS grp
    FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
    LEFT JOIN (SELECT l_orderkey, CAST(count(*) AS DOUBLE) AS n_lines, CAST(sum(l_quantity) AS DOUBLE) AS quantity FROM lineitem GROUP BY l_orderkey) t ON t.l_orderkey = o_orderkey"""


_LINE = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"


def _numbered(d: Dialect) -> str:
    """All line items with their number from 0 in the order of all columns. In Spark each stretch of orders is numbered alone, and
    only the counts of the stretches, one row for 4096 orders, are added up in one place."""
    if d.duck:
        return f"(SELECT *, row_number() OVER (ORDER BY {_LINE}) - 1 AS oid FROM lineitem)"
    return f"""(SELECT {_LINE}, CAST(row_number() OVER (PARTITION BY stretch ORDER BY {_LINE}) + before - 1 AS BIGINT) AS oid
        FROM (SELECT *, l_orderkey div 4096 AS stretch FROM lineitem) i
        JOIN (SELECT stretch AS s, sum(n) OVER (ORDER BY stretch) - n AS before FROM (SELECT l_orderkey div 4096 AS stretch, count(*) AS n FROM lineitem GROUP BY 1) c) b ON i.stretch = b.s)"""


def _air(d: Dialect) -> str:
    n = d.number
    cols = [n("l_quantity"), n("l_extendedprice"), n("l_discount"), n("l_tax"), n("l_linenumber"), d.days("l_shipdate"), n("o_totalprice"), d.days("o_orderdate"), n("p_size"), n("p_retailprice"), n("c_acctbal"), n("s_acctbal"), f"{d.days('l_shipdate')} - {d.days('o_orderdate')}"]
    return f"""SELECT oid, {', '.join(f'{c} AS x{i}' for i, c in enumerate(cols, 1))}
    FROM {_numbered(d)} l JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"""


def _food(d: Dialect) -> str:
    zero = "0.0" if d.duck else "0D"
    mean = lambda c: f"round(avg({d.number(c)}), 9) AS a_{c}"
    return f"""SELECT p_partkey AS oid, {d.number('p_size')} AS n_add, {d.number('p_retailprice')} AS energy,
        COALESCE(a_l_quantity, {zero}) AS salt, COALESCE(a_l_discount, {zero}) AS fat, COALESCE(a_l_tax, {zero}) AS sugar, COALESCE(a_l_extendedprice, {zero}) AS protein,
        p_type AS category, p_name || ' ' || p_brand AS labels, vec AS picture, p_brand AS brand, p_type AS type
    FROM {_with_vector(d, 'p_partkey', 'part')} p JOIN {_vec(d, 'vec_key')}
    LEFT JOIN (SELECT l_partkey, {mean('l_quantity')}, {mean('l_discount')}, {mean('l_tax')}, {mean('l_extendedprice')} FROM lineitem GROUP BY l_partkey) t ON t.l_partkey = p_partkey"""


def _place(d: Dialect, key: str) -> str:
    return d.array(f"{d.feature(key, 0)} * 180", f"{d.feature(key, 1)} * 90")


def _with_part(d: Dialect) -> str:
    """Documents with the key of a part, whose name is a text that is short by nature."""
    return "(SELECT doc_id, doc_id % n_part + 1 AS part_key FROM documents, (SELECT count(*) AS n_part FROM part) c)"


def _syn50(d: Dialect) -> str:
    return f"""SELECT doc_id AS oid, {_place(d, 'doc_id')} AS loc, p_name AS words, vec AS picture,
        {', '.join(f"{d.feature('doc_id', i + 1)} AS f{i}" for i in range(1, 48))}
    FROM {_with_vector(d, 'doc_id', _with_part(d))} t JOIN part ON p_partkey = part_key JOIN {_vec(d, 'vec_key')}"""


def _syn96(d: Dialect) -> str:
    s = [f"{d.slice('vec', 4 * i + 1, 4)} AS s{i + 1}" for i in range(8)] + [f"{d.slice('vec', 33 + 8 * i, 8)} AS t{i + 1}" for i in range(4)]
    return f"""SELECT oid, {_place(d, 'oid')} AS loc, p_name AS words, vec AS picture, {', '.join(s)}, {', '.join(f"{d.feature('oid', i + 1)} AS f{i}" for i in range(1, 82))}
    FROM {_with_vector(d, 'oid', _numbered(d))} l JOIN part ON l_partkey = p_partkey JOIN {_vec(d, 'vec_key')}"""


def _quad(d: Dialect) -> str:
    """The report is the title of a page, a text that is short by nature."""
    title = d.ascii("regexp_extract(html, '<title>(.*?)</title>', 1)")
    return f"""SELECT t.doc_id AS oid, vec AS picture, report, {d.number('n_chars')} AS len, {d.number('quality')} AS score
    FROM {_with_vector(d, 'doc_id', "(SELECT i.doc_id, n_chars, quality, i.doc_id % n_page AS page_key FROM documents i JOIN labels l ON i.doc_id = l.doc_id, (SELECT count(*) AS n_page FROM pages) c)")} t
    JOIN (SELECT page_id, {title} AS report FROM pages) p ON page_id = page_key JOIN {_vec(d, 'vec_key')}"""


def _evt(d: Dialect) -> str:
    at = "CAST(floor(epoch(ts)) AS DOUBLE) / 86400" if d.duck else "CAST(unix_timestamp(CAST(ts AS TIMESTAMP)) AS DOUBLE) / 86400"
    k = "CAST(json_extract_string(props, '$.k') AS DOUBLE)" if d.duck else "CAST(get_json_object(props, '$.k') AS DOUBLE)"
    return f"SELECT event_id AS oid, {d.number('value')} AS value, {at} AS at, event_type AS kind, {k} AS k FROM events"


def _tiny(d: Dialect) -> str:
    rows = [(1, (9, 1, 1), (8, 8), "noisy flat"), (2, (1, 2, 1), (1, 1), "quiet sunny flat"), (3, (2, 2, 1), (1, 2), "quiet sunny flats"), (4, (8, 7, 9), (9, 1), "dark cellar"), (5, (5, 5, 5), (5, 5), "small room"), (6, (7, 1, 3), (2, 9), "old house"), (7, (0, 9, 9), (9, 9), "modern loft"), (8, (6, 6, 2), (4, 8), "quiet old house")]
    num = lambda x: f"CAST({x} AS DOUBLE)"
    return " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS oid, {d.array(*map(num, p))} AS picture, {d.array(*map(num, c))} AS loc, '{t}' AS review" for i, p, c, t in rows)


_S = MultiMetricSchema.of
FIXTURES = {
    "rental": (_rental, _S(("price", "l1"), ("size", "l1v", 2), ("loc", "l2v", 2), ("listed", "l1"), ("review", "edit"))),
    "air": (_air, _S(*((f"x{i}", "l1") for i in range(1, 14)))),
    "food": (_food, _S(*((c, "l1") for c in ("n_add", "energy", "salt", "fat", "sugar", "protein")), ("category", "edit"), ("labels", "edit"), ("picture", "l1v", 64))),
    "syn50": (_syn50, _S(("loc", "l2v", 2), ("words", "edit"), ("picture", "l1v", 64), *((f"f{i}", "l1") for i in range(1, 48)))),
    "syn96": (_syn96, _S(("loc", "l2v", 2), ("words", "edit"), ("picture", "l1v", 64), *((f"s{i}", "l1v", 4) for i in range(1, 9)), *((f"t{i}", "l1v", 8) for i in range(1, 5)), *((f"f{i}", "l1") for i in range(1, 82)))),
    "quad": (_quad, _S(("picture", "l1v", 64), ("report", "edit"), ("len", "l1"), ("score", "l1"))),
    "evt": (_evt, _S(("value", "l1"), ("at", "l1"), ("kind", "edit"), ("k", "l1"))),
    "tiny": (_tiny, _S(("picture", "l1v", 3), ("loc", "l2v", 2), ("review", "edit"))),
}


def schema(name: str) -> MultiMetricSchema:
    return FIXTURES[name][1]


def duck_sql(name: str) -> str:
    return FIXTURES[name][0](Dialect(True))


def run_sql(spark: SparkSession, sf_dir: str, text: str, **frames: DataFrame) -> DataFrame:
    """Spark SQL over the given tables and frames by name, without leaving views behind."""
    used = [t for t in TABLES if re.search(rf"(?<![\w.]){t}(?![\w(])", text) and t not in frames]
    named = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in used} | frames
    held = text.replace("{", "{{").replace("}", "}}")
    held = reduce(lambda s, t: re.sub(rf"(?<=FROM )\b{t}\b|(?<=JOIN )\b{t}\b|(?<=from )\b{t}\b|(?<=join )\b{t}\b", "{" + t + "}", s), named, held)
    held = reduce(lambda s, t: s.replace(f"{{{t}}}.", f"{t}."), named, held)
    named = {t: f.alias(t) for t, f in named.items() if "{" + t + "}" in held}
    return spark.sql(held, **named)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A data set: derived once in an application, written to the shared folder in as many files as shuffles have partitions, and read from there."""

    def make() -> tuple[str, StructType]:
        n = spark.read.parquet(f"{sf_dir}/embeddings.parquet").count() if name in ("food", "syn50", "syn96", "quad") else 0
        df = run_sql(spark, sf_dir, FIXTURES[name][0](Dialect(False, str(n))))
        path = f"{new_folder(spark)}/{name}"
        df.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "oid").write.parquet(path)
        return path, df.schema

    path, kind = once(spark, ("fixture", sf_dir, name), make)
    df = spark.read.schema(kind).parquet(path)
    if any(s.width == LONG for s in schema(name).spaces):
        register_edit(spark)
    return df
