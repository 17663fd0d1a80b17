"""Mixtures of corruptions for training and for the benchmark, and the operators that need counts of the corpus.

A policy goes from sentences over words to characters; on each level the row's hash picks one kind of edit and an operator of it, and a rate up to the level's limit.
"""

import random
import unicodedata
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twinsift.augment import places
from twinsift.augment.operators import OPERATORS, SCANNED, SCANNED_AS, Spark, expression
from twinsift.functions.shipping import by_value
from twinsift.plans.checkpoints import cut

by_value(__name__)

KINDS = ("insert", "delete", "substitute", "swap")


@dataclass(frozen=True)
class Policy:
    """Largest share of units that an edit touches, by level; word and char share one limit."""

    para: float = 0.0
    sent: float = 0.25
    word_char: float = 0.30

    def levels(self) -> list[tuple[str, float]]:
        out = [("para", self.para), ("sent", self.sent), ("word", self.word_char / 2), ("char", self.word_char / 2)]
        return [(n, r) for n, r in out if r > 0]


TRAIN = Policy(0.0, 0.25, 0.30)
BENCH = Policy(0.125, 0.125, 0.25)


def operators_of(level: str, kind: str) -> list[str]:
    return [n for n, (lev, k, _) in OPERATORS.items() if lev == level and k == kind]


def corrupt_one(rows: DataFrame, name: str, rate: float, seed: str = "g") -> DataFrame:
    """(doc_id, lang, text) after one operator; rows as with_lexicons makes them. What needs no lexicon is done in one pass over Arrow batches."""
    if name in ALONE:
        return corrupt_alone(rows, name, rate, seed)
    view = f"ts_aug_{zlib.crc32(repr((name, rate, seed)).encode())}"
    rows.createOrReplaceTempView(view)
    return rows.sparkSession.sql(expression(name, rate, seed, Spark(), view))


#: Operators that put a fixed text in place of a character, with what they put.
ALONE = {"noise_scan": dict(zip(SCANNED, SCANNED_AS, strict=True)) | {" ": "-\n"}}


def corrupt_alone(rows: DataFrame, name: str, rate: float, seed: str) -> DataFrame:
    """(doc_id, lang, text) after an operator that needs no lexicon; rows: (doc_id, lang, text)."""
    changes = ALONE[name]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield from places.replaced(batch, changes, name, rate, seed)

    return rows.filter("text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text").mapInArrow(run, "doc_id long, lang string, text string")


def corrupt_picked(rows: DataFrame, names: tuple[str, ...], rate: float, seeds: list[str]) -> DataFrame:
    """The rows, in one narrow pass, with the text after the operator whose number is in the column pick; without a number it stays as it is."""
    from twinsift.augment.operators import SEPARATOR, Place

    d = Spark()
    levels: dict[str, list[int]] = {}
    for i, name in enumerate(names):
        levels.setdefault(OPERATORS[name][0], []).append(i)
    units = " ".join(f"when pick in ({', '.join(map(str, of))}) then {d.units(level, 'text')}" for level, of in levels.items())
    texts = " ".join(f"when {i} then {d.join(OPERATORS[n][2](Place(d, n, rate, seed)), SEPARATOR[OPERATORS[n][0]])}" for i, (n, seed) in enumerate(zip(names, seeds, strict=True)))
    view = f"ts_picked_{zlib.crc32(repr((names, rate, seeds)).encode())}"
    rows.createOrReplaceTempView(view)
    done = rows.sparkSession.sql(f"select *, case pick {texts} end as new from (select *, case {units} end as u from {view}) q")
    return done.withColumn("text", F.coalesce("new", "text")).drop("new", "u", "pick")


def apply(rows: DataFrame, policy: Policy, seed: str, kinds: tuple[str, ...] = KINDS) -> DataFrame:
    """The rows with corrupted text, and report: what was done on each level. Rows are split by operator and put together again, so every branch is one narrow pass."""
    rows = rows.withColumn("original", F.col("text")).withColumn("report", F.array().cast("array<string>"))
    for level, limit in policy.levels():
        options = [(k, n) for k in kinds for n in operators_of(level, k)]
        u = F.pmod(F.xxhash64("doc_id", F.lit(f"{seed}-{level}")), F.lit(1 << 40))
        pick = F.pmod(u, F.lit(len(options)))
        rate = F.pmod(F.shiftright(u, 20), F.lit(4))
        rows = rows.withColumn("_pick", pick * 4 + rate).withColumn("_text", F.col("text"))
        view = f"ts_pol_{level}_{zlib.crc32(repr((seed, policy)).encode())}"
        rows.createOrReplaceTempView(view)
        cases = []
        for k, (kind, name) in enumerate(options):
            for step in range(4):
                part = limit * (step + 1) / 4
                cases.append(f"when _pick = {4 * k + step} then struct({_inline(name, part, seed, level)} as text, '{level}:{kind}:{name}:{part:.4f}' as what)")
        body = f"select *, case {' '.join(cases)} end as _out from (select *, {Spark().units(level, 'text')} as u from {view})"
        done = rows.sparkSession.sql(body)
        rows = done.withColumn("text", F.coalesce("_out.text", "text")).withColumn("report", F.concat("report", F.array(F.coalesce("_out.what", F.lit("none"))))).drop("_pick", "_text", "_out", "u")
    return rows


def _inline(name: str, rate: float, seed: str, level: str) -> str:
    from twinsift.augment.operators import SEPARATOR, Place

    d = Spark()
    return d.join(OPERATORS[name][2](Place(d, name, rate, seed)), SEPARATOR[level])


def _unicode_char(rnd: random.Random) -> str:
    while True:
        c = chr(rnd.randrange(0x20, 0x2FFFF))
        if unicodedata.category(c) not in ("Cn", "Cs", "Co", "Cc"):
            return c


COUNTED = ("word_sub_trigram", "char_sub_ngram", "char_insert_ngram")
UNICODE = ("char_sub_unicode", "char_insert_unicode")


def corrupt_unicode(docs: DataFrame, name: str, rate: float, seed: str = "g") -> DataFrame:
    """(doc_id, lang, text): characters replaced by any assigned code point, or such put behind them."""

    def one(key, text: str) -> str:
        rnd = random.Random(f"{key}-{name}-{seed}")
        out = []
        for c in text:
            new = _unicode_char(rnd) if rnd.random() < rate else None
            out.append(c if new is None else c + new if "insert" in name else new)
        return "".join(out)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            yield rows.assign(text=[one(k, t) if t is not None else None for k, t in zip(rows["doc_id"], rows["text"], strict=True)])

    return docs.select("doc_id", "lang", "text").mapInPandas(run, "doc_id long, lang string, text string")


def continuations(docs: DataFrame, name: str, n: int = 3) -> DataFrame:
    """(key, next, lo, hi, total): every continuation in the corpus, with its part [lo, hi) of all that follow its key. A table, never on the driver."""
    from twinsift.catalogue.lexical import char_ngrams, word_trigrams

    if name == "word_sub_trigram":
        rows = word_trigrams(docs).select(F.concat_ws(" ", "first", "second").alias("key"), F.col("third").alias("next"), "n")
    else:
        rows = char_ngrams(docs, n).select(F.col("before").alias("key"), "next", "n")
    upto = F.sum("n").over(Window.partitionBy("key").orderBy("next").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    rows = rows.withColumn("hi", upto).withColumn("lo", F.col("hi") - F.col("n"))
    total = rows.groupBy("key").agg(F.sum("n").alias("total"))
    return rows.join(total, "key").select("key", "next", "lo", "hi", "total")


def _place_number(name: str, seed: str, i: F.Column, salt: str = "") -> F.Column:
    text = F.concat(F.col("doc_id").cast("string"), F.lit("-"), i.cast("string"), F.lit(f"-{name}{salt}-{seed}"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("long")


#: Continuations that are sent to all tasks; a larger table is joined.
SENT = 1_000_000


def _in_place(docs: DataFrame, name: str, rate: float, seed: str, n: int, table: DataFrame) -> DataFrame:
    """corrupt_counted for characters in one pass over the texts, with the table in every task."""
    rows = table.orderBy("key", "next").select("key", "next", "hi").toArrow()
    sent = docs.sparkSession.sparkContext.broadcast([rows[c].to_pylist() for c in ("key", "next", "hi")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = places.Continuations(*sent.value)
        for batch in batches:
            yield from places.edited(batch, known, n - 1, name, rate, seed)

    lower = F.when(F.octet_length("text") != F.length("text"), F.lower("text")).alias("lower")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text", lower).mapInArrow(run, "doc_id long, lang string, text string")


def corrupt_counted(docs: DataFrame, name: str, rate: float, seed: str = "g", n: int = 3, table: DataFrame | None = None) -> DataFrame:
    """(doc_id, lang, text) where chosen places follow the corpus: a word by what follows the two before it, a character by what follows the n - 1 before it.

    A place draws a number below its key's total and joins the continuation whose part holds it, so frequent ones come often and none is left out; a key that
    the table lacks leaves its place as it was. table: as `continuations` gives it."""
    table = continuations(docs, name, n) if table is None else table
    word = name == "word_sub_trigram"
    if not word:
        table = cut(table)
        if table.count() <= SENT:
            return _in_place(docs, name, rate, seed, n, table)
    units = F.split("text", " ") if word else F.filter(F.split("text", ""), lambda c: c != "")
    back = 2 if word else n - 1
    rows = docs.filter("text is not null").select("doc_id", units.alias("u"))
    chosen = F.filter(F.sequence(F.lit(back), F.size("u") - 1), lambda i: _place_number(name, seed, i) % 10000 < round(rate * 10000))
    key = lambda i: F.lower(F.array_join(F.slice("u", i - back + 1, F.lit(back)), " " if word else ""))
    at = rows.filter(F.size("u") > back).select("doc_id", F.explode(F.transform(chosen, lambda i: F.struct(i.alias("i"), key(i).alias("key"), _place_number(name, seed, i, "d").alias("draw")))).alias("p")).select("doc_id", "p.*")
    drawn = F.pmod("draw", "total")
    edits = at.join(table, "key").filter((drawn >= F.col("lo")) & (drawn < F.col("hi"))).groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("i", "next"))).alias("edits"))
    insert, glue = "insert" in name, " " if word else ""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            out = []
            for text, changes in zip(part["text"], part["edits"], strict=True):
                if text is not None and changes is not None:
                    own = text.split(" ") if word else list(text)
                    for e in changes:
                        own[e["i"]] = own[e["i"]] + e["next"] if insert else e["next"]
                    text = glue.join(own)
                out.append(text)
            yield pd.DataFrame({"doc_id": part["doc_id"], "lang": part["lang"], "text": out})

    both = docs.select("doc_id", "lang", "text").join(edits, "doc_id", "left")
    return both.select("doc_id", "lang", "text", "edits").mapInPandas(run, "doc_id long, lang string, text string")


def counted_sql(name: str, rate: float, seed: str = "g", n: int = 3) -> str:
    """The same in SQL, over documents."""
    from twinsift.catalogue.lexical import WORDS

    word = name == "word_sub_trigram"
    back, glue = (2, " ") if word else (n - 1, "")
    grams = f"select w[i] || ' ' || w[i+1] as key, w[i+2] as next, count(*) as n from (select w, unnest(range(1, len(w) - 1)) as i from (select {WORDS} as w from documents)) group by all having count(*) >= 2" if word else f"select substring(g, 1, {n - 1}) as key, substring(g, {n}, 1) as next, count(*) as n from (select substring(t, i, {n}) as g from (select lower(text) as t, unnest(range(1, length(lower(text)) - {n - 2})) as i from documents)) group by all having count(*) >= 2"
    number = lambda salt="": f"('0x' || substr(md5(doc_id::varchar || '-' || (i - 1)::varchar || '-{name}{salt}-{seed}'), 1, 13))::bigint"
    units = "string_split(text, ' ')" if word else "list_filter(string_split(text, ''), lambda c: c <> '')"
    new = "x || coalesce(next, '')" if "insert" in name else "coalesce(next, x)"
    return f"""with g as ({grams}), c as (select key, next, sum(n) over o - n as lo, sum(n) over o as hi, sum(n) over (partition by key) as total from g window o as (partition by key order by next)),
u as (select doc_id, {units} as u from documents where text is not null), e as (select doc_id, unnest(u) as x, unnest(range(1, len(u) + 1)) as i, u from u),
p as (select doc_id, i, lower(array_to_string(u[i-{back}:i-1], '{glue}')) as key, {number('d')} as draw from e where i > {back} and {number()} % 10000 < {round(rate * 10000)}),
d as (select doc_id, i, next from p join c using (key) where draw % total >= lo and draw % total < hi),
t as (select doc_id, string_agg({new}, '{glue}' order by i) as text from e left join d using (doc_id, i) group by doc_id)
select doc_id, md5(coalesce(t.text, s.text)) as digest, length(coalesce(t.text, s.text))::bigint as n from documents s left join t using (doc_id)"""
