"""Bounded lexicons for each language, as one row of arrays: words, letters and donor sentences."""

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.catalogue.lexical import WORDS, alphabet, top_words
from twinsift.functions.text import md5_int

WORDS_KEPT, DONORS_KEPT = 100, 32


def lexicons(docs: DataFrame) -> DataFrame:
    """(lang, lang_words, letters, donors, all_words). Each list is cut before it is collected."""
    words = top_words(docs, WORDS_KEPT)
    own = words.groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("rn", "word"))).alias("w")).select("lang", F.col("w.word").alias("lang_words"))
    letters = alphabet(docs).groupBy("lang").agg(F.array_sort(F.collect_set("ch")).alias("letters"))
    first = docs.filter("text is not null").select("lang", F.element_at(F.split("text", "[.] "), 1).alias("s")).filter("length(s) between 16 and 300").distinct()
    from twinsift.operators.clustering import top_window

    kept = top_window(first.withColumn("o", md5_int(F.col("s"))), ["lang"], ["o", "s"], DONORS_KEPT)
    donors = kept.groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("o", "s"))).alias("d")).select("lang", F.col("d.s").alias("donors"))
    everyone = words.agg(F.array_sort(F.collect_set("word")).alias("all_words"))
    rows = own.join(letters, "lang", "full").join(donors, "lang", "full").crossJoin(F.broadcast(everyone))  # one row
    return rows


def with_lexicons(docs: DataFrame, of: DataFrame | None = None) -> DataFrame:
    """The rows of docs, or those given, with the lexicons of docs."""
    rows = (docs if of is None else of).select("doc_id", "lang", "text").join(F.broadcast(lexicons(docs)), "lang", "left")
    return rows.select("doc_id", "lang", "text", "donors", "all_words", "lang_words", "letters")


SQL_ROWS = f"""(with w as (select lang, word, n, row_number() over (partition by lang order by n desc, word) as rn from (select lang, word, count(*) as n from (select lang, unnest({WORDS}) as word from documents) group by all)),
k as (select * from w where rn <= {WORDS_KEPT}), own as (select lang, list(word order by rn) as lang_words from k group by 1), everyone as (select list(distinct word order by word) as all_words from k),
letters as (select lang, list(distinct ch order by ch) as letters from (select lang, unnest(string_split(lower(text), '')) as ch from documents) where regexp_matches(ch, '^\\p{{L}}$') group by 1),
f as (select distinct lang, string_split(text, '. ')[1] as s from documents where text is not null), o as (select lang, s, ('0x' || substr(md5(s), 1, 15))::bigint as o from f where length(s) between 16 and 300),
donors as (select lang, list(s order by o, s) as donors from (select *, row_number() over (partition by lang order by o, s) as rn from o) where rn <= {DONORS_KEPT} group by 1)
select doc_id, d.lang, text, donors, all_words, lang_words, letters from documents d left join own using (lang) left join letters using (lang) left join donors using (lang), everyone)"""
