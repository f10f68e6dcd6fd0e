"""Registered queries of the training-data operators; each runs over its whole table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlattice.llm import chat, decontam, langid, lm, omh, quality, rules, sentencepiece, suffix, urls
from pairlattice.llm.common import table


def fold_of(parts: int) -> Column:
    """The fold of a row by its id; a null id has none, so its row is never held out."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % parts, F.lit(-1))


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencepiece.encode(table(spark, sf_dir, "documents"))


def op2_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return omh.classes(table(spark, sf_dir, "documents"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    pieces = sentencepiece.PieceTable.load()
    model = langid.fit(docs.where(fold_of(3) != 1), pieces)
    return langid.predict(docs, pieces, model).select("doc_id", (fold_of(3) == 1).alias("held_out"), "lang_pred", "score")


def op4_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", probe), (-1, 1, "assistant", probe)], "conv_id long, turn long, role string, text string")
    return chat.digests(chat.format_chats(rows.unionByName(extra)))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality.fit(docs.where(fold_of(4) != 2), table(spark, sf_dir, "labels").where(fold_of(4) != 2))
    return quality.score(docs, model).select("doc_id", (fold_of(4) == 2).alias("held_out"), "score", "predicted")


def op6_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.digests(table(spark, sf_dir, "documents"))


def op7_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").withColumn("learn", fold_of(7) != 2)
    return lm.judged(docs, "learn").select("doc_id", (fold_of(7) == 2).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules.quality_rules(table(spark, sf_dir, "documents")).drop("text")


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages"))


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


QUERIES = {
    "op1_sentencepiece": op1_sentencepiece,
    "op2_order_minhash": op2_order_minhash,
    "op3_language_id": op3_language_id,
    "op4_chat_format": op4_chat_format,
    "op5_quality": op5_quality,
    "op6_suffix_array": op6_suffix_array,
    "op7_lm_score": op7_lm_score,
    "op8_quality_rules": op8_quality_rules,
    "op9_url_filter": op9_url_filter,
    "op10_decontaminate": op10_decontaminate,
}
ORACLES: dict[str, str] = {"op4_chat_format": chat.oracle(), "op6_suffix_array": suffix.oracle(), "op8_quality_rules": rules.oracle()}
