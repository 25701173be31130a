"""The queries of the training-data operators: each applies one to its whole table and derives digest columns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import adaptive_scan, chat_template, common, golay_simhash, lang_mixture, matrix_bpe, matroska, secret_cnn, sos_packing, sstable, text_density

#: Folder of the public vocabulary files; their package gives it, a session may set another.
VOCABULARY_SETTING = "spark.gossamer.vocabularies"
END_ID, PACK_END_ID, SEQUENCE = 1, 0, 2048


def vocabulary(spark: SparkSession, name: str) -> str:
    folder = spark.conf.get(VOCABULARY_SETTING, None)
    if folder:
        return f"{folder}/{name}"
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_sstable_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zlib import crc32

    manifest = sstable.write_shards(common.table(spark, sf_dir, "documents"), vocabulary(spark, "word_bpe_49k.json"), sstable.shard_folder(spark), END_ID)
    return sstable.read_shards(manifest, int(spark.conf.get("spark.sql.shuffle.partitions")), "ids_crc32 long", crc32)


def op2_text_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_density.main_text(common.table(spark, sf_dir, "pages"))


def op3_secret_cnn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_cnn.digests(secret_cnn.scanned(common.table(spark, sf_dir, "documents")))


def op4_adaptive_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return adaptive_scan.search(common.table(spark, sf_dir, "embeddings"), F.pmod(F.col("vec_id"), F.lit(20)) == 0)


def op5_matroska(spark: SparkSession, sf_dir: str) -> DataFrame:
    return matroska.features(matroska.store(common.table(spark, sf_dir, "documents")))


def op6_sum_of_squares(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sos_packing.packed(common.table(spark, sf_dir, "documents"), vocabulary(spark, "byte_bpe_50k.json"), PACK_END_ID, SEQUENCE)


def op7_lang_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lang_mixture.identified(common.table(spark, sf_dir, "documents"))


def op8_matrix_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    coded = matrix_bpe.encode(common.table(spark, sf_dir, "documents"), vocabulary(spark, "byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
    return coded.select("doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op9_golay_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = golay_simhash.near_duplicates(common.table(spark, sf_dir, "documents"))
    return found.select("doc_id", golay_simhash.fingerprint_hex(F.col("fp")).alias("fingerprint"), "component_id")


def op10_chat_template(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = "\\### Assistant: </turn> ok"
    planted = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    rows = common.table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text").unionByName(planted)
    return chat_template.read_back(chat_template.format_conversations(rows))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = [op1_sstable_shards, op2_text_density, op3_secret_cnn, op4_adaptive_scan, op5_matroska, op6_sum_of_squares, op7_lang_mixture, op8_matrix_bpe, op9_golay_simhash, op10_chat_template]
    return {f.__name__: f for f in own}


#: The digests of op10 from the turns themselves: a turn is written as ``### role: text</turn>`` and a line's end.
_CHAT_SQL = r"""
WITH said AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL
  SELECT -7, n, r, '\### Assistant: </turn> ok' FROM (VALUES (0, 'user'), (1, 'assistant')) planted(n, r)
)
SELECT conv_id,
  count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(length('### : </turn>') + 1 + length(role) + len(regexp_extract_all(role, '\\|###|</turn>|:'))
    + length(text) + len(regexp_extract_all(text, '\\|###|</turn>'))) AS BIGINT) AS formatted_chars
FROM said GROUP BY conv_id
"""


def oracle_sql() -> dict[str, str]:
    """Encoders, learnt models and searches are outside SQL; the tests hold those queries against brute force."""
    return {"op10_chat_template": _CHAT_SQL}
