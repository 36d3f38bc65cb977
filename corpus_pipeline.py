"""The corpus pipeline: five stages, each applied to all its predecessor kept.

1. quality: documents that the classifier rejects go;
2. lines: lines that match an earlier line go, and documents left without a word;
3. copies: of each group of near copies (five-word shingles, similarity 0.8) one document stays;
4. mixture: documents are sampled to the raked source, language and topic weights;
5. pieces: texts are encoded and decoded.

All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from duetsieve.llm import linedup, mixing, pieces, quality, setjoin
from duetsieve.llm.common import documents, saved

NEAR = setjoin.Similar(words=5, num=80, den=100, fold=True)


def drop_poor(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return linedup.deduped(docs)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return setjoin.one_of_each(docs, NEAR)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.sampled(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pieces.digest_texts(docs, pieces.piece_model()).select(F.col("doc_id"), "n_tokens", "ids_sha256", "decoded_sha256")


STAGES = [("quality", drop_poor), ("lines", drop_lines), ("copies", drop_copies), ("mixture", mix_sources), ("pieces", encode)]

#: The classifier has no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = saved(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
