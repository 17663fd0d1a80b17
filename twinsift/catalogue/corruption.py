"""Queries of group G: every corruption operator over all documents, as digests of the corrupted texts."""

from pyspark.sql import functions as F

from twinsift.augment import policy
from twinsift.augment.lexicons import SQL_ROWS, with_lexicons
from twinsift.augment.operators import OPERATORS, Duck, expression
from twinsift.sources.tables import read_table

QUERIES, ORACLES = {}, {}
RATE = 0.1


def _digest(df):
    return df.select("doc_id", F.md5(F.col("text").cast("binary")).alias("digest"), F.length("text").cast("long").alias("n"))


def _native(name):
    def run(spark, sf_dir):
        return _digest(policy.corrupt_one(with_lexicons(read_table(spark, sf_dir, "documents")), name, RATE))

    return run


def _counted(name, n):
    return lambda spark, sf_dir: _digest(policy.corrupt_counted(read_table(spark, sf_dir, "documents"), name, RATE, n=n))


def _unicode(name):
    return lambda spark, sf_dir: _digest(policy.corrupt_unicode(read_table(spark, sf_dir, "documents"), name, RATE))


for _name in OPERATORS:
    QUERIES[f"g_{_name}"] = _native(_name)
    ORACLES[f"g_{_name}"] = f"select doc_id, md5(text) as digest, length(text)::bigint as n from ({expression(_name, RATE, 'g', Duck(), SQL_ROWS)})"
for _name in policy.COUNTED:
    for _n in (3, 4, 5) if "ngram" in _name else (3,):
        _key = f"g_{_name}" + (f"_{_n}" if _n > 3 else "")
        QUERIES[_key] = _counted(_name, _n)
        ORACLES[_key] = policy.counted_sql(_name, RATE, n=_n)
for _name in policy.UNICODE:
    QUERIES[f"g_{_name}"] = _unicode(_name)


def _policy(which):
    def run(spark, sf_dir):
        rows = policy.apply(with_lexicons(read_table(spark, sf_dir, "documents")), which, "p")
        return rows.select("doc_id", F.md5(F.col("text").cast("binary")).alias("digest"), F.array_join("report", ",").alias("report"))

    return run


QUERIES["g_policy_train"] = _policy(policy.TRAIN)
QUERIES["g_policy_bench"] = _policy(policy.BENCH)
