"""A corpus prepared for training: five stages, each written as Parquet and read again as the next one's input.

Stage by stage: the quality classifier rejects documents; lines that an earlier
document holds are dropped; of near duplicates one document stays; sources are
mixed to target weights; the texts are encoded as token ids.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from aclvec.llm import bpe, jaccard, linededup, mixing, quality
from aclvec.llm.common import crc_mod, stored, table

#: At most so often may a document be taken: rare sources count more, and no document is left out.
REPEATS = 2.0


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier, trained on labels of one fold in three of four, accepts."""
    labels = table(spark, sf_dir, "labels").filter(crc_mod("doc_id", 4) != 2)
    return quality.accepted(docs, quality.train(docs, labels))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that one with a smaller id holds."""
    return linededup.dedup_lines(docs).select(*docs.columns)


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near duplicates."""
    return jaccard.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as their source's weight asks for, each once at least."""
    return mixing.mixed(docs, repeats=REPEATS)


def encode_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text, with digests of the ids and of the text decoded from them."""
    return bpe.encode(docs, bpe.read_ranks(bpe.default_path()), digests=True).drop("offsets")


STAGES = [
    ("quality_classifier", keep_quality),
    ("line_dedup", drop_lines),
    ("jaccard_join", keep_one_of_each),
    ("mixing", mix_sources),
    ("bpe_codec", encode_ids),
]
#: The classifier is no SQL; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, beginning with the documents."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = stored(docs)
    return docs
