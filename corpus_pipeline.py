"""A corpus from raw documents to token ids: five stages, each an operator of approxmatch.llm over all rows that its
predecessor kept.

Line dedup comes before near-dedup: an exact copy loses all its lines there and goes; a near copy loses the lines that
it shares, and near-dedup compares what is left of it.

Defined cases: a null or empty text isn't toxic, has no lines and no near copy, and isn't mixed, having no words; rows
that repeat a document keep the same lines, and near-dedup keeps them together (its groups are of different doc_ids);
ties are decided by doc_id, and where these agree by the text; a null doc_id is scored, deduplicated by lines, kept by
near-dedup and mixed; a document may stand several times in the result, once per copy that the mix takes; empty tables
give an empty result; documents may have further columns, whatever their names, up to the last stage."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from approxmatch.llm import byte_bpe, line_dedup, mixing, near_dup, toxicity
from approxmatch.llm.shared import documents, keep


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.filtered(docs, toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.deduplicated(docs, drop_emptied=True)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dup.deduplicated(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return byte_bpe.digests(docs, *byte_bpe.public_vocabulary())


STAGES = [("toxicity", drop_toxic), ("line_dedup", drop_repeated_lines), ("near_dedup", drop_near_duplicates), ("mixing", mix_sources), ("byte_bpe", encode)]

#: Trained models and hashed permutations aren't SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = keep(docs)
    return docs
