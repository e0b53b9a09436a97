"""A training-data pipeline over `documents`: each stage is one operator, works on all that the one before kept, and its
decisions take effect. Stages but the last return the columns of their input.

1. quality classifier: documents scored below the threshold go
2. line dedup: boilerplate lines leave all texts that hold them (n_chars follows); every document stays
3. SimHash near-dedup: one document of each group stays, the one with the smallest doc_id; fingerprints within 4 bits are
   linked, and texts of which 0.8 or more of the five-word shingles agree
4. mixing: documents stand as often as the mix takes them, at most twice
5. BPE: ids and decoded text of every document, as digests

Defined cases, by stage: null and empty texts are scored like any other and go only if the classifier rejects them, lose no
lines, are one group of near copies, weigh nothing in the mix (so it takes none of them) and have no ids; very long texts
are taken whole everywhere; of documents that tie the smaller doc_id stays, then the smaller hash of the text; rows that
agree in doc_id and text are one document from stage 3 on; an empty table stays empty, with its columns, through all
stages; further columns, whatever their names, come along up to the last stage, which has its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sparkverdict.llm import bpe, fair_queue, line_spread, near_text, pu_quality, simhash
from sparkverdict.llm.common import materialise, table
from sparkverdict.llm.queries import vocabulary


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pu_quality.accepted(docs, table(spark, sf_dir, "labels"))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_spread.remove_boilerplate(docs, length="n_chars" if "n_chars" in docs.columns else None)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """By fingerprints alone, with the values of op3_simhash_covering."""
    return simhash.one_of_each(docs)


def similar_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The stage: by fingerprints, and by the similarity of the texts where fingerprints are too far apart."""
    return simhash.one_of_each(docs, similar=near_text.LEAST)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return fair_queue.mixed_documents(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.digests(docs, vocabulary())


STAGES = [
    ("quality classifier", quality),
    ("line dedup", line_dedup),
    ("SimHash near-dedup", similar_dedup),
    ("mixing sources to target weights", mixing),
    ("BPE encoding and decoding", tokens),
]
#: SimHash, the classifier and BPE are beyond SQL; tests/llm compare the pipeline with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), "stage-" + name.split()[0].lower())
    return STAGES[-1][1](spark, docs, sf_dir)
