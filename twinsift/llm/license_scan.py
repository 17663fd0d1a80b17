"""License scan by diagonal voting.

Every position of every text gives the hashes of the word 2-gram and 4-gram that
begin there. They are joined to the positions of the templates; a hit lies on
the diagonal (text position - template position). Hits are counted by diagonal,
diagonals of a template that lie close together (a few words added or left out)
are merged into one span, and the span is kept if enough of the template's
grams are in it. The words themselves are compared with the hash, so a hash
collision makes no hit. Short phrases are indexed by 2-grams and must match as
a whole, longer notices by 4-grams.

Only DataFrame functions. The templates are a fixed list and are broadcast; no
text is shuffled, only hits and one row per document.

Defined cases: null text is empty: no words, no labels, score 0. Rows with the
same id and text are scanned once and returned as often as they occur; a null
id is an id of its own. Empty table: empty result. Further columns are ignored.
"""

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

MAX_SHIFT = 3
MAX_GAP = 12
COVERED = 0.75

# Phrases and labels of the base scan, then notices from public license texts.
PHRASES = (("gnu general public license", "gpl"), ("apache license", "apache"), ("cc by", "cc-by"), ("mit license", "mit"))
NOTICES = (
    ("licensed under the apache license version 2 0", "apache-2.0"),
    ("licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at", "apache-2.0"),
    ("unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind", "apache-2.0"),
    ("this work is licensed under the gnu general public license version 3", "gpl-3.0"),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "gpl"),
    ("released under the mit license", "mit"),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction", "mit"),
    ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "bsd"),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "isc"),
    ("this source code form is subject to the terms of the mozilla public license v 2 0", "mpl-2.0"),
    ("this is free and unencumbered software released into the public domain", "unlicense"),
    ("licensed under cc by nc 4 0", "cc-by-nc-4.0"),
    ("this work is licensed under a creative commons attribution", "cc-by"),
)
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BREAK = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER), BREAK), "")


def template_rows(templates) -> list[tuple]:
    """(k, template, label, grams, position, words) of every gram of every template."""
    rows = []
    for n, (text, label, k) in enumerate(templates):
        words = text.split()
        rows += [(k, n, label, len(words) - k + 1, p, *(words[p : p + k] + [None] * (4 - k))) for p in range(len(words) - k + 1)]
    return rows


def template_table(spark: SparkSession, templates, k: int) -> DataFrame:
    schema = f"k int, t{k} int, label{k} string, grams{k} int, p{k} int, a{k} string, b{k} string, c{k} string, d{k} string"
    rows = spark.createDataFrame([r for r in template_rows(templates) if r[0] == k], schema).drop("k")
    return rows.withColumn(f"h{k}", F.xxhash64(*(f"{c}{k}" for c in "abcd"[:k])))


def scan_licenses(docs: DataFrame, phrases=PHRASES, notices=NOTICES, covered: float = COVERED) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans."""
    spark = docs.sparkSession
    templates = [(t, label, 2) for t, label in phrases] + [(t, label, 4) for t, label in notices]
    texts = docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.xxhash64(docs["text"]).alias("text_hash"), words_of(docs["text"]).alias("w"))
    n = F.size("w")
    none = F.lit(None).cast("string")
    head = F.array(F.struct(*(none.alias(c) for c in "abcd")))  # one element before the words, so that every document has a row
    rolling = F.arrays_zip(F.col("w").alias("a"), F.slice("w", 2, n).alias("b"), F.slice("w", 3, n).alias("c"), F.slice("w", 4, n).alias("d"))
    grams = texts.select("doc_id", "text_hash", n.cast("long").alias("n_words"), F.posexplode(F.concat(head, rolling)).alias("pos", "g"))
    grams = grams.select("doc_id", "text_hash", "n_words", (F.col("pos") - 1).cast("long").alias("pos"), "g.a", "g.b", "g.c", "g.d")
    for k in (2, 4):
        same = F.when(F.col("abcd"[k - 1]).isNotNull(), F.xxhash64(*"abcd"[:k])) == F.col(f"h{k}")
        for c in "abcd"[:k]:  # compared after the hash has met, not part of the join's key
            same = same & F.coalesce(F.col(c) == F.col(f"{c}{k}"), F.lit(False))
        grams = grams.join(F.broadcast(template_table(spark, templates, k)), same, "left")
    kept = grams.filter((F.col("pos") == -1) | F.col("t2").isNotNull() | F.col("t4").isNotNull())
    hit = lambda k: F.when((F.col("pos") == -1) | F.col(f"t{k}").isNotNull(), F.struct(*(F.col(f"{c}{k}").alias(c) for c in ("t", "label", "grams", "p"))))
    either = F.when(F.col("pos") == -1, F.array(hit(2))).otherwise(F.array(hit(2), hit(4)))
    hits = kept.select("doc_id", "text_hash", "n_words", "pos", F.explode(either).alias("h")).filter("h is not null")
    hits = hits.select("doc_id", "text_hash", "n_words", "pos", "h.t", "h.label", "h.grams", "h.p").repartition("doc_id", "text_hash")

    # A row that hit several templates at once stands more than once; on one diagonal a position counts once.
    votes = hits.withColumn("diagonal", F.when(F.col("t").isNotNull(), F.col("pos") - F.col("p")))
    votes = votes.groupBy("doc_id", "text_hash", "t", "diagonal").agg(F.max("n_words").alias("n_words"), F.count(F.when(F.col("pos") == -1, 1)).alias("copies"), F.max("label").alias("label"), F.max("grams").alias("grams"), F.min("pos").alias("low"), F.max("pos").alias("high"), F.size(F.collect_set("pos")).alias("votes"))
    line = Window.partitionBy("doc_id", "text_hash", "t").orderBy("low", "diagonal")
    apart = (F.abs(F.col("diagonal") - F.lag("diagonal").over(line)) > MAX_SHIFT) | (F.col("low") - F.lag("high").over(line) > MAX_GAP) | (F.col("low") <= F.lag("low").over(line)) | (F.col("t") < len(phrases))
    votes = votes.withColumn("island", F.sum(F.coalesce(apart, F.lit(True)).cast("int")).over(line))
    spans = votes.groupBy("doc_id", "text_hash", "t", "island").agg(F.max("n_words").alias("n_words"), F.max("copies").alias("copies"), F.max("label").alias("label"), F.max("grams").alias("grams"), F.min("low").alias("low"), F.max("high").alias("high"), F.sum("votes").alias("votes"))
    share = F.least(F.col("votes") / F.col("grams"), F.lit(1.0))
    base = (F.col("t") < len(phrases)) & (F.col("votes") == F.col("grams"))
    found = base | ((F.col("t") >= len(phrases)) & (share >= covered))
    spans = spans.withColumn("share", F.when((F.col("t") >= len(phrases)) | base, share))
    joined = lambda c: F.array_join(F.array_sort(F.collect_set(F.when(c, F.col("label")))), ",")
    span = F.struct("label", F.col("low").alias("first"), (F.col("high") + F.when(base, 2).otherwise(4)).alias("end"), "share")
    out = spans.groupBy("doc_id", "text_hash").agg(F.max("n_words").alias("n_words"), F.max("copies").alias("copies"), F.sum(F.when(base, 1).otherwise(0)).cast("long").alias("n_base"), F.min(F.when(base, F.col("low"))).alias("first_word"), F.max(F.when(base, F.col("low"))).alias("last_word"), joined(base).alias("base_labels"), joined(found).alias("labels"), F.coalesce(F.max("share"), F.lit(0.0)).alias("score"), F.array_sort(F.collect_list(F.when(found, span))).alias("spans"))
    return out.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).drop("copy", "copies", "text_hash")


def _values(rows) -> str:
    return ", ".join("(" + ", ".join("null" if v is None else repr(v) for v in r) + ")" for r in rows)


_N = len(PHRASES)
_ROWS = template_rows([(t, label, 2) for t, label in PHRASES] + [(t, label, 4) for t, label in NOTICES])
ORACLE = rf"""
with texts as (select row_number() over (order by doc_id, text) as r, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents),
t(k, t, label, grams, p, a, b, c, d) as (values {_values(_ROWS)}),
grams as (select r, pos, w[pos + 1] as a, w[pos + 2] as b, w[pos + 3] as c, w[pos + 4] as d from (select r, w, unnest(range(len(w))) as pos from texts)),
votes as (select r, t, label, grams, pos - p as diagonal, min(pos) as low, max(pos) as high, count(distinct pos) as votes
  from grams g join t on g.a = t.a and g.b = t.b and (t.k = 2 or (g.c = t.c and g.d = t.d)) group by all),
lines as (select *, case when lag(low) over o is null or t < {_N} or abs(diagonal - lag(diagonal) over o) > {MAX_SHIFT} or low - lag(high) over o > {MAX_GAP} or low <= lag(low) over o then 1 else 0 end as apart
  from votes window o as (partition by r, t order by low, diagonal)),
islands as (select *, sum(apart) over (partition by r, t order by low, diagonal rows unbounded preceding) as island from lines),
spans as (select r, t, max(label) as label, min(low) as low, least(sum(votes)::double / max(grams), 1.0) as share, t < {_N} and sum(votes) = max(grams) as base from islands group by r, t, island),
marked as (select *, base or (t >= {_N} and share >= {COVERED}) as found from spans)
select doc_id, len(w)::bigint as n_words, count(*) filter (base) as n_base, (min(low) filter (base))::bigint as first_word, (max(low) filter (base))::bigint as last_word,
  coalesce(array_to_string(list_sort(list_distinct(list(label) filter (base))), ','), '') as base_labels,
  coalesce(array_to_string(list_sort(list_distinct(list(label) filter (found))), ','), '') as labels,
  coalesce(max(share) filter (base or t >= {_N}), 0.0) as score
from texts left join marked using (r) group by r, doc_id, w
"""
