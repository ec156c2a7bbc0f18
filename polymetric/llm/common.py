"""Shared pieces: tables in the shared folder, joins on skewed keys, a register-blocked Bloom filter, gapless
numbers, connected components. All of it is DataFrame code; nothing here brings rows to the driver."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable
from typing import TypeVar

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A key counts as heavy with more than 1/HEAVY of all rows, so there are fewer than HEAVY heavy keys at any size.
HEAVY = 2000
T = TypeVar("T")
_left: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share; a temporary one only for a local master without the setting."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    made = "file://" + tempfile.mkdtemp(prefix="polymetric")
    spark.conf.set("spark.checkpoint.dir", made)
    return made


def _delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


@atexit.register
def _clear() -> None:
    for spark, path in _left:
        try:
            _delete(spark, path)
        except Exception:  # noqa: BLE001 - the session may be over; the folder's owner clears it then
            return


_store: dict[str, object] = {}


def worker_store(name: str, make: Callable[[], T]) -> T:
    """What a Python worker keeps between batches under a name. A worker keeps one at a time, so stages that follow
    each other in one worker don't add up."""
    if name not in _store:
        _store.clear()
        give_back()
        _store[name] = make()
    return _store[name]  # type: ignore[return-value]


def give_back() -> None:
    """Returns freed memory of this Python process to the system; else the allocators keep it for as long as a worker lives."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only the GNU C library has it
        ctypes.CDLL(None).malloc_trim(0)


class Scratch:
    """Tables written once in the shared folder: they cut lineage, survive lost executors and are read by column.

    ``drop`` removes those no longer needed; what a returned DataFrame still reads stays until the process ends.
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_folder(spark)}/polymetric-{uuid.uuid4().hex}"
        _left.append((spark, self.root))

    def table(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}"
        df.write.mode("overwrite").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        for name in names:
            _delete(self.spark, f"{self.root}/{name}")


def heavy_join(left: DataFrame, right: DataFrame, on: list[str], weight: str, total: int) -> DataFrame:
    """Inner join of many rows with one row a key, where ``weight`` counts the left rows of a key.

    Keys above total/HEAVY rows, fewer than HEAVY of them by counting, are broadcast, so their left rows stay where
    they are; the other keys meet in a shuffle with bounded groups.
    """
    most = max(1, total // HEAVY)
    heavy = F.broadcast(right.where(F.col(weight) > most))
    light = right.where(F.col(weight) <= most)
    rest = left.join(F.broadcast(right.where(F.col(weight) > most).select(*on)), on, "left_anti")
    return left.join(heavy, on).unionByName(rest.join(light, on))


def bloom_words(keys: DataFrame, key: str, most_words: int = 1 << 20) -> DataFrame:
    """A register-blocked Bloom filter of 64-bit hashes: each key sets 4 bits of one 64-bit word.

    At most ``most_words`` rows of 16 bytes whatever the input, hence safe to broadcast. With more keys the filter
    fills up and lets more rows through; it never misses one.
    """
    return keys.select(word_of(F.col(key), most_words).alias("bf_word"), mask_of(F.col(key)).alias("m")).groupBy("bf_word").agg(F.bit_or("m").alias("bf_bits"))


def word_of(h: Column, most_words: int = 1 << 20) -> Column:
    return F.shiftrightunsigned(h, 30).bitwiseAND(F.lit(most_words - 1).cast("long"))


def mask_of(h: Column) -> Column:
    bit = lambda n: F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(h, n).bitwiseAND(F.lit(63).cast("long")).cast("int"))
    return bit(0).bitwiseOR(bit(6)).bitwiseOR(bit(12)).bitwiseOR(bit(18))


def fresh(df: DataFrame, name: str) -> str:
    """A column name that ``df`` doesn't have, whatever the case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def bloom_probe(df: DataFrame, key: str, words: DataFrame, flag: str, most_words: int = 1 << 20) -> DataFrame:
    """``df`` with a Boolean column: false only where the key is surely not in the filter."""
    w, b = fresh(df, "bf_word"), fresh(df, "bf_bits")
    hit = F.col(b).bitwiseAND(mask_of(F.col(key))) == mask_of(F.col(key))
    named = words.select(F.col("bf_word").alias(w), F.col("bf_bits").alias(b))
    return df.withColumn(w, word_of(F.col(key), most_words)).join(F.broadcast(named), w, "left").withColumn(flag, F.coalesce(hit, F.lit(False))).drop(w, b)


def numbered(df: DataFrame, keys: list[str], spread: Column, order: list[str], name: str, parts: int) -> DataFrame:
    """Gapless numbers from 0 within each key, without one task for a key: a key's rows are dealt to ``parts`` parts,
    each part is numbered alone, and the counts of the parts before it (keys x parts rows) are added."""
    from pyspark.sql import Window

    dealt = df.withColumn("nb_part", F.pmod(spread, F.lit(parts)).cast("int"))
    counts = dealt.groupBy(*keys, "nb_part").agg(F.count("*").alias("nb_n"))
    before = Window.partitionBy(*keys).orderBy("nb_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select(*keys, "nb_part", F.coalesce(F.sum("nb_n").over(before), F.lit(0)).alias("nb_start"))
    within = F.row_number().over(Window.partitionBy(*keys, "nb_part").orderBy(*order))
    if parts == 1:
        return dealt.withColumn(name, within - 1).drop("nb_part")
    return dealt.withColumn("nb_row", within).join(starts, [*keys, "nb_part"]).withColumn(name, F.col("nb_start") + F.col("nb_row") - 1).drop("nb_part", "nb_row", "nb_start")


def _stars(edges: DataFrame) -> bool:
    """Whether every a has one b, which is no a: then the b are the roots."""
    ends = edges.select(F.col("a").alias("x"), F.lit(1).alias("up"), F.lit(0).alias("under")).unionByName(edges.select(F.col("b").alias("x"), F.lit(0).alias("up"), F.lit(1).alias("under")))
    return ends.groupBy("x").agg(F.sum("up").alias("up"), F.max("under").alias("under")).where("up > 1 OR up = 1 AND under = 1").isEmpty()


def components(edges: DataFrame, scratch: Scratch, tag: str = "cc") -> DataFrame:
    """Distributed union-find: (u, v) long pairs to (node, root), root the least node of its component.

    Nodes are relinked in turn to the least neighbour among all and among the smaller ones until nothing moves; each
    round is a table, so lineage does not grow. Hubs go through :func:`heavy_join`. Nodes that are roots are included.
    """
    oriented = edges.where("u <> v").select(F.greatest("u", "v").alias("a"), F.least("u", "v").alias("b")).distinct()
    now, i = scratch.table(oriented, f"{tag}0"), 0
    while not _stars(now):
        n = now.count()
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).withColumn("m", F.least("u", "m"))
        large = heavy_join(both, least, ["u"], "n", 2 * n).where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        large = scratch.table(large, f"{tag}{i}l")
        under = large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n"))
        small = heavy_join(large, under, ["a"], "n", large.count()).where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(under.select("a", F.col("m").alias("b"))).distinct()
        after = scratch.table(small, f"{tag}{i + 1}")
        scratch.drop(f"{tag}{i}", f"{tag}{i}l")
        now, i = after, i + 1
    leaves = now.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return leaves.unionByName(leaves.select(F.col("root").alias("node"), "root").distinct())
