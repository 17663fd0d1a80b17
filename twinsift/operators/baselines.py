"""Rival vectors: tables of other models, and stand-ins that need no pretrained weights (always named as stand-ins)."""

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.functions.text import char_shingles, words
from twinsift.operators.matching import pairs

# Cosine thresholds published for pretrained rivals, by task.
THRESHOLDS = {"mUSE": {"news": 0.96, "scholarly": 0.97}, "mE5-base": {"news": 0.88, "scholarly": 0.87}, "LaBSE": {"scholarly": 0.88}}
DIMENSIONS = {"LaBSE": 768, "mUSE": 512, "mE5-base": 768, "Gecko": 768}


def external_pairs(vectors: DataFrame, threshold: float, dim: int | None = None) -> DataFrame:
    """Pairs of any table (vec_id, embedding) at a model's own threshold; dim, if given, is checked on every row."""
    if dim is not None:
        vectors = vectors.withColumn("embedding", F.when(F.size("embedding") == dim, F.col("embedding")).otherwise(F.raise_error(F.lit(f"vectors of {dim} dimensions are asked for")).cast("array<float>")))
    return pairs(vectors, threshold)


def _arrays(df: DataFrame, column: str) -> DataFrame:
    from pyspark.ml.functions import vector_to_array

    v = vector_to_array(F.col(column))
    return df.select("doc_id", v.alias("v"))


def word2vec(docs: DataFrame, size: int = 32, max_fit: int = 20_000) -> DataFrame:
    """Stand-in: mean of word vectors learned on at most about max_fit documents. (doc_id, v)"""
    from pyspark.ml.feature import Word2Vec

    rows = docs.filter("text is not null").select("doc_id", words(F.col("text")).alias("w"))
    n = docs.count()
    some = rows.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < min(1.0, max_fit / max(1, n)) * (1 << 30))
    model = Word2Vec(vectorSize=size, minCount=3, maxIter=1, seed=5, numPartitions=4, inputCol="w", outputCol="f").fit(some)
    return _arrays(model.transform(rows), "f")


def tfidf(docs: DataFrame, kind: str = "word", n: int = 1, features: int = 1024) -> DataFrame:
    """Stand-in: hashed counts of word or character n-grams, weighed by rarity, unit length. (doc_id, v)"""
    from pyspark.ml.feature import IDF, HashingTF, Normalizer

    units = words(F.col("text")) if kind == "word" else char_shingles(F.col("text"), max(n, 3))
    rows = docs.filter("text is not null").select("doc_id", units.alias("w"))
    counted = HashingTF(numFeatures=features, inputCol="w", outputCol="tf").transform(rows)
    weighed = IDF(inputCol="tf", outputCol="idf").fit(counted).transform(counted)
    return _arrays(Normalizer(inputCol="idf", outputCol="f").transform(weighed), "f")
