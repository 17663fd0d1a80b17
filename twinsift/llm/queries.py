"""The registered queries of this subpackage, over whole tables."""

from pyspark.sql import functions as F

from twinsift.llm import bpe, chat, embedding_dedup, language_id, license_scan, mixing, ngram_join, quality_cnn, sharding, telephony
from twinsift.llm.common import id_remainder, table

TOKENIZER = "byte_bpe_50k.json"


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_language_id(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return language_id.predict_language(docs, language_id.fit_profiles(docs))


def op2_license_scan(spark, sf_dir):
    found = license_scan.scan_licenses(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")


def op3_sharding(spark, sf_dir):
    placed = sharding.balance(table(spark, sf_dir, "documents"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op4_quality(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    scored = quality_cnn.score_quality(docs, quality_cnn.fit_quality(docs, table(spark, sf_dir, "labels")))
    held, good = F.coalesce(id_remainder(4) == 2, F.lit(False)), F.col("score") >= quality_cnn.THRESHOLD
    return scored.select("doc_id", held.alias("held_out"), "score", good.cast("int").alias("predicted"))


def op5_bpe(spark, sf_dir):
    coded = bpe.encode_texts(table(spark, sf_dir, "documents"), tokenizer_path(), keep=False, keep_ids=False)
    return coded.select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")


def op6_chat_format(spark, sf_dir):
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", said), (-1, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    done = chat.format_conversations(rows.unionByName(extra), keep=False)
    return done.select("conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "rewrites")


def op7_ngram_join(spark, sf_dir):
    return ngram_join.jaccard_components(table(spark, sf_dir, "documents"))


def op8_embedding_dedup(spark, sf_dir):
    return embedding_dedup.near_duplicates(table(spark, sf_dir, "embeddings"))


def op9_telephony(spark, sf_dir):
    stored = telephony.store_texts(table(spark, sf_dir, "documents"))
    return telephony.measure_stored(stored).select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")


def op10_mixing(spark, sf_dir):
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


QUERIES = {f.__name__: f for f in (op1_language_id, op2_license_scan, op3_sharding, op4_quality, op5_bpe, op6_chat_format, op7_ngram_join, op8_embedding_dedup, op9_telephony, op10_mixing)}
ORACLES = {"op2_license_scan": license_scan.ORACLE, "op10_mixing": mixing.ORACLE}
