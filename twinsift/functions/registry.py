"""The methods as SQL: temporary functions, Arrow UDFs, grouped aggregates, table functions and views."""

import unicodedata

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from twinsift.functions.shipping import by_value

by_value(__name__)

# Written in SQL, so the optimizer sees through them.
SQL_FUNCTIONS = {
    "ts_md5_int": "(s string) returns bigint return cast(conv(substring(md5(s), 1, 15), 16, 10) as bigint)",
    "ts_hamming": "(a bigint, b bigint) returns int return bit_count(a ^ b)",
    "ts_dot": "(a array<double>, b array<double>) returns double return aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)",
    "ts_cosine": "(a array<double>, b array<double>) returns double return try_divide(ts_dot(a, b), sqrt(ts_dot(a, a) * ts_dot(b, b)))",
    "ts_l2_normalize": "(a array<double>) returns array<double> return transform(a, x -> try_divide(x, sqrt(ts_dot(a, a))))",
    "ts_words": r"(s string) returns array<string> return filter(split(lower(s), '[^\\p{L}\\p{N}]+'), w -> w <> '')",
    "ts_triples": "(w array<string>) returns array<string> return zip_with(zip_with(slice(w, 1, greatest(size(w) - 2, 0)), slice(w, 2, greatest(size(w) - 2, 0)), (x, y) -> concat_ws(' ', x, y)), slice(w, 3, greatest(size(w) - 2, 0)), (x, y) -> concat_ws(' ', x, y))",
    "ts_shingles": "(s string) returns array<string> return array_distinct(ts_triples(ts_words(s)))",
}


@F.pandas_udf(T.StringType())
def nfkc(text: pd.Series) -> pd.Series:
    return text.map(lambda t: None if t is None else unicodedata.normalize("NFKC", t))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def mean_vector_agg(v: pd.Series) -> list:
    x = np.array(v.tolist(), np.float64)
    return x.mean(0).tolist()


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def gem_agg(v: pd.Series) -> list:
    x = np.maximum(np.array(v.tolist(), np.float64), 1e-6)
    return ((x**3).mean(0) ** (1 / 3)).tolist()


@F.udtf(returnType=T.StructType().add("chunk_no", T.IntegerType()).add("start", T.IntegerType()).add("chunk", T.StringType()))
class Chunks:
    """chunks(text, size, stride): slices of a text."""

    def eval(self, text: str, size: int, stride: int):
        if text is not None:
            for k, s in enumerate(range(0, max(1, len(text)), stride)):
                yield k, s, text[s : s + size]


@F.udtf(returnType=T.StructType().add("shingle", T.StringType()))
class ShingleRows:
    """shingle_rows(text, n): distinct word n-grams."""

    def eval(self, text: str, n: int):
        w = "".join(c if c.isalnum() else " " for c in (text or "").lower()).split()
        for g in dict.fromkeys(" ".join(w[i : i + n]) for i in range(len(w) - n + 1)):
            yield (g,)


@F.udtf(returnType=T.StructType().add("band", T.IntegerType()).add("key", T.StringType()))
class BandKeys:
    """band_keys(signature, bands, rows): one key a band."""

    def eval(self, signature: list, bands: int, rows: int):
        for b in range(bands):
            yield b, "-".join(map(str, signature[b * rows : (b + 1) * rows]))


@F.udtf(returnType=T.StructType().add("copy", T.IntegerType()).add("text", T.StringType()))
class Augmentations:
    """augmentations(text, n): n copies with a tenth of their characters left out, by a fixed generator."""

    def eval(self, text: str, n: int):
        for k in range(n):
            rng = np.random.default_rng(k)
            keep = rng.random(len(text or "")) >= 0.1
            yield k, "".join(c for c, x in zip(text or "", keep, strict=True) if x)


def encoder_functions(spark: SparkSession, preset: str = "tiny") -> None:
    """encode_doc(text) and encode_chunks(text) with the given preset's weights."""
    from twinsift.encoder import api
    from twinsift.encoder.net import encode

    weights, c = api.model(preset)
    sent = spark.sparkContext.broadcast(weights)

    @F.pandas_udf("array<array<float>>")
    def encode_chunks(text: pd.Series) -> pd.Series:
        parts = [[t[i : i + c.chunk] for i in range(0, max(1, len(t)), c.chunk)] if t is not None else None for t in text]
        return pd.Series([None if p is None else encode(sent.value, c, p).tolist() for p in parts])

    @F.pandas_udf("array<float>")
    def encode_doc(text: pd.Series) -> pd.Series:
        parts = [[t[i : i + c.chunk] for i in range(0, max(1, len(t)), c.chunk)] if t is not None else None for t in text]
        out = []
        for p in parts:
            v = None if p is None else encode(sent.value, c, p).mean(0)
            out.append(None if v is None or not np.linalg.norm(v) else (v / np.linalg.norm(v)).tolist())
        return pd.Series(out)

    spark.udf.register("ts_encode_chunks", encode_chunks)
    spark.udf.register("ts_encode_doc", encode_doc)


def register(spark: SparkSession, sf_dir: str | None = None, encoder: bool = False) -> None:
    """All functions, and over a directory the views nd_chunks, nd_shingles, nd_band_keys, nd_pairs and nd_clusters."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}{body}")
    for name, f in {"ts_nfkc": nfkc, "ts_mean_vector": mean_vector_agg, "ts_gem": gem_agg}.items():
        spark.udf.register(name, f)
    for name, f in {"ts_chunks": Chunks, "ts_shingle_rows": ShingleRows, "ts_band_keys": BandKeys, "ts_augmentations": Augmentations}.items():
        spark.udtf.register(name, f)
    if encoder:
        encoder_functions(spark)
    if sf_dir:
        for name, df in views(spark, sf_dir).items():
            df.createOrReplaceTempView(name)


def views(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    from twinsift.catalogue.lexical import a_chunks_512
    from twinsift.operators import clustering, sketches
    from twinsift.sources.tables import read_table

    docs = read_table(spark, sf_dir, "documents")
    hashed = sketches.shingle_hashes(docs)
    bands, rows = sketches.choose_bands(0.8, 64)
    pairs = sketches.minhash_pairs(docs, 0.8, 64)
    return {
        "nd_chunks": a_chunks_512(spark, sf_dir),
        "nd_shingles": hashed.select("id", F.explode("hashes").alias("shingle")),
        "nd_band_keys": sketches.band_keys(sketches.sign_hashes(hashed, 64), bands, rows),
        "nd_pairs": pairs,
        "nd_clusters": clustering.label_all(docs, pairs, "doc_id"),
    }
