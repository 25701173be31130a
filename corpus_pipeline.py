"""The corpus pipeline: language ID, near-duplicates, secrets, packing; each stage written and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gossamer.llm import common, golay_simhash, lang_mixture, secret_cnn, sos_packing
from gossamer.llm.queries import PACK_END_ID, SEQUENCE, vocabulary


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents go whose text is in no learnt language: null, without a letter, or explained by none of them.

    ``lang_mixture.kept`` also takes a set of languages and a least share; all learnt languages stay here.
    """
    return lang_mixture.kept(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each group stays; of its texts in that group, one.

    Groups are of texts: a doc_id whose texts differ may stay once in each of their groups. Rows without an id
    belong to no group: they stay, equal texts once.
    """
    stay = golay_simhash.survivors(docs.where("doc_id is not null"))
    return stay.unionByName(docs.where("doc_id is null").dropDuplicates(["text"]))


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Findings in texts are replaced by marks."""
    return secret_cnn.without_secrets(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sos_packing.packed(docs, vocabulary(spark, "byte_bpe_50k.json"), PACK_END_ID, SEQUENCE)


STAGES = [("language_id", language_id), ("near_dedup", near_dedup), ("secret_scan", secret_scan), ("packing", packing)]

#: Learnt models and encoders are outside SQL; tests hold the rows against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = common.settled(docs, name)
    return docs
