"""Exact duplicates by two-pass Bloom filtering, in DataFrame functions only.

Pass one is a counting filter of at least 64 positions a row, spread over the executors: its cells are added up by position, so
what moves is one number of 8 bytes, no id, digest or text (a merged bitmap of this size would be 64 bits a row
itself). Positions hit twice may be repeats. Pass two puts those in a broadcast filter of about 16 bits each that
every row probes: rows outside it are certainly unique and pass straight through, and only the rest shuffle on their full digest.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polymetric.llm.common import Scratch, bloom_probe, bloom_words, heavy_join

#: Words of 64 bits of one broadcast filter, and how many filters, each with a scan of the digests, are made at most: a scan more
#: costs less than a shuffle of all rows only up to a few. Beyond it the filters fill up and more rows shuffle; the rows are the same.
MOST_WORDS, MOST_FILTERS = 1 << 22, 4
KEYS_PER_WORD = 4
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only; a text of ASCII bytes takes Spark's fast path."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256), one row for each input row.

    A null text counts as empty. Of equal texts the row with the largest id stays; a null id is smaller than any other
    and stays only in a group without ids. Rows repeated with one id are the same document and share its fate; each
    counts in group_size. Other columns are ignored, so clashing names don't matter; an empty table gives no rows.
    """
    scratch = scratch or Scratch(docs.sparkSession)
    norm = ascii_lower(F.coalesce(F.col(text_col), F.lit("")))
    slim = docs.select(F.col(id_col).alias("doc_id"), F.sha2(norm, 256).alias("text_sha256")).withColumn("h", F.xxhash64("text_sha256"))
    slim = scratch.table(slim, "digests")
    n = slim.count()
    positions = 1 << max(16, (64 * n).bit_length())
    at = F.pmod(F.col("h"), F.lit(positions))
    keyed = slim.withColumn("k", F.xxhash64(at))
    twice = scratch.table(slim.groupBy(at.alias("position")).agg(F.count("*").alias("n")).where("n > 1").select(F.xxhash64("position").alias("k")), "repeats")
    repeats = twice.count()
    filters = min(MOST_FILTERS, 1 + repeats // (KEYS_PER_WORD * MOST_WORDS))
    words = min(MOST_WORDS, 1 << max(10, (repeats // (KEYS_PER_WORD * filters)).bit_length()))
    probed = []
    for i in range(filters):
        mine = F.pmod(F.shiftright("k", 52), F.lit(filters)) == i  # bits that neither the word nor the mask takes
        probed.append(bloom_probe(keyed.where(mine), "k", bloom_words(twice.where(mine), "k", words), "maybe", words))
    probed = reduce(DataFrame.unionByName, probed)
    alone = probed.where(~F.col("maybe")).select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "text_sha256")
    suspects = probed.where("maybe").select("doc_id", "text_sha256")
    groups = suspects.groupBy("text_sha256").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    met = heavy_join(suspects, groups, ["text_sha256"], "group_size", n)
    return alone.unionByName(met.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"))


ORACLE_SQL = """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id IS NOT DISTINCT FROM max(doc_id) OVER w AS kept, text_sha256
FROM (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256
      FROM documents)
WINDOW w AS (PARTITION BY text_sha256)
"""
