"""A training corpus from raw documents in five stages, each one operator of twinsift.llm.

Every stage works on all that the one before kept and returns the columns of
`documents`; the last returns token ids. run() writes each stage as Parquet to
the shared checkpoint folder and reads it again, so no stage is computed twice
and a lost executor costs one stage's tasks at most.
"""

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twinsift.llm import bpe, language_id, mixing, ngram_join, quality_cnn
from twinsift.llm.queries import tokenizer_path
from twinsift.plans.checkpoints import ensure_checkpoint_dir

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
QUALITY_AT_LEAST = 0.5
LANGUAGE_AT_LEAST = 5 / language_id.DIMENSIONS**0.5  # unrelated vectors have cosines of deviation 1 / sqrt(DIMENSIONS)
TELLING = 24  # characters
STAGE_SHINGLE, STAGE_JACCARD = 5, (80, 100)  # words, and the threshold as a fraction; op7 has its own
BROADCAST_IDS = 1_000_000  # at most so many rows of two numbers are broadcast; beyond that Spark joins by shuffling

ORACLE_SQL = None  # learned models, hash-based sampling and BPE are not SQL


def _near(ids: DataFrame) -> DataFrame:
    return F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are likelier low quality than not go."""
    model = quality_cnn.fit_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality_cnn.score_quality(docs, model, COLUMNS).filter(F.col("score") >= QUALITY_AT_LEAST).select(*COLUMNS)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, or unlike every language that was learned, go. The lang column stays as it was.

    Unlike means below LANGUAGE_AT_LEAST; texts shorter than TELLING tell too little for that and only go at score 0."""
    found = language_id.predict_language(docs, language_id.fit_profiles(docs), COLUMNS)
    like = (F.col("score") >= LANGUAGE_AT_LEAST) | ((F.length("text") < TELLING) & (F.col("score") > 0))
    return found.filter((F.col("lang_pred") != language_id.UNKNOWN) & like).select(*COLUMNS)


def _keyed(docs: DataFrame, *told_apart_by: str) -> DataFrame:
    """The columns of documents, and key and shared: the id, or for rows that have none or share it (shared is true then) a 64-bit hash of the named columns."""
    common = ngram_join.cut(docs.groupBy("doc_id").agg(F.count("*").alias("n")).filter("n > 1 or doc_id is null").select(F.col("doc_id").alias("id"), F.lit(True).alias("shared")))
    marked = docs.select(*COLUMNS).join(_near(common), F.col("doc_id").eqNullSafe(F.col("id")), "left")
    return marked.select(*COLUMNS, F.when(F.col("shared"), F.xxhash64(*told_apart_by)).otherwise(F.col("doc_id").cast("long")).alias("key"), "shared")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the smallest id stays; of repeated rows (equal id, or none, and equal text) one."""
    rows = _keyed(docs, "doc_id", "text")
    groups = ngram_join.jaccard_components(rows.select(F.col("key").alias("doc_id"), "text"), STAGE_SHINGLE, *STAGE_JACCARD)
    groups = ngram_join.cut(groups.filter("n_shingles > 0").select(F.col("doc_id").alias("key"), "component_id").distinct().join(rows.select("key", "doc_id").distinct(), "key"))
    first = groups.groupBy("component_id").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "key")).alias("first"))
    gone = ngram_join.cut(groups.join(first, "component_id").filter(F.col("key") != F.col("first.key")).select("key"))
    kept = rows.join(_near(gone), "key", "left_anti")
    return kept.filter("shared is null").unionByName(kept.filter("shared").dropDuplicates(["key"])).select(*COLUMNS)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it; of rows that are equal in all columns one comes as often as all of them are taken."""
    rows = _keyed(docs, *COLUMNS)
    taken = mixing.cut(mixing.mix(rows.select(F.col("key").alias("doc_id"), "source", "text")).groupBy(F.col("doc_id").alias("key")).agg(F.sum("copies").cast("int").alias("copies")).filter("copies > 0"))
    alone = rows.filter("shared is null").unionByName(rows.filter("shared").dropDuplicates(["key"]))
    many = alone.join(_near(taken), "key")
    return many.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).select(*COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document of the mix, checked by their digests."""
    coded = bpe.encode_texts(docs, tokenizer_path(), keep=False)
    return coded.select("doc_id", "n_tokens", "ids", "ids_sha256", "decoded_sha256")


STAGES = [("quality classifier", quality), ("language ID", language), ("n-gram Jaccard join", near_duplicates), ("mixing sources", mix), ("BPE encoding", encode)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage over the whole documents table."""
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    docs, was = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for k, (_, stage) in enumerate(STAGES):
        out = f"{folder}/{k}"
        stage(spark, docs, sf_dir).write.parquet(out)
        docs = spark.read.parquet(out)
        if was:
            old = path(was)
            old.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(old, True)
        was = out
    return docs
