"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read again as the next one's input."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from polymetric.llm import bpe, decontam, line_dedup, ngram_join, quality
from polymetric.llm.common import Scratch, bloom_probe, bloom_words, fresh


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The documents whose doc_id isn't among ``ids``: those outside a filter of the ids pass without a shuffle."""
    k, maybe, own = (fresh(docs, n) for n in ("pl_k", "pl_maybe", "pl_id"))
    gone = ids.select(F.col("doc_id").alias(own)).where(F.col(own).isNotNull()).distinct()
    probed = bloom_probe(docs.withColumn(k, F.xxhash64("doc_id")), k, bloom_words(gone.select(F.xxhash64(own).alias("k")), "k"), maybe)
    out = probed.where(~F.col(maybe) | F.col("doc_id").isNull()).select(*docs.columns)
    return out.unionByName(probed.where(F.col(maybe) & F.col("doc_id").isNotNull()).join(gone, F.col("doc_id") == F.col(own), "left_anti").select(*docs.columns))


def drop_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    model = quality.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.keep_good(docs, model)


def drop_near_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of near lines one stays; n_chars follows the text. A document may be left empty, and stays."""
    scratch = Scratch(spark)
    cut = line_dedup.without_lines(docs, scratch.table(line_dedup.duplicate_lines(docs, scratch=scratch), "told"))
    return cut.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.char_length("text").cast(docs.schema["n_chars"].dataType)))


def drop_near_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near documents the one with the least id stays."""
    scratch = Scratch(spark)
    return _without(docs, scratch.table(ngram_join.ngram_join(docs, scratch=scratch).where("NOT kept").select("doc_id"), "gone"))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a passage of the benchmark go."""
    found = decontam.contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return _without(docs, Scratch(spark).table(found.select("doc_id").distinct(), "gone"))


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents' token ids."""
    return bpe.encode_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), with_ids=True)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", drop_low_quality),
    ("line_dedup", drop_near_lines),
    ("ngram_join", drop_near_documents),
    ("decontamination", drop_contaminated),
    ("bpe", tokenize),
]
#: Neither a trained classifier nor banding is expressible in SQL; tests/llm holds the stages against brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, scratch = spark.read.parquet(f"{sf_dir}/documents.parquet"), Scratch(spark)
    for i, (name, stage) in enumerate(STAGES):
        docs = scratch.table(stage(spark, docs, sf_dir), name)
        if i:
            scratch.drop(STAGES[i - 1][0])
    return docs
