"""Queries of groups A, T and B: chunks, bits, lexicons, samples, shingles, sketches and exact matches, each with its SQL."""

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from twinsift.augment import places
from twinsift.functions import text as tx
from twinsift.functions.shipping import by_value
from twinsift.operators import exact, sketches
from twinsift.sources.tables import read_table

by_value(__name__)

QUERIES, ORACLES = {}, {}

WORDS = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda w: w <> '')"
SHINGLES = f"(select doc_id as id, list_distinct(list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i+2], ' '))) as g from (select doc_id, {WORDS} as w from documents) where len(w) >= 3)"


def md5_sql(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 15))::bigint"


HASHES = f"(select id, list_distinct(list_transform(g, lambda s: {md5_sql('s')})) as h from {SHINGLES})"


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return keep


def documents(spark, sf_dir):
    return read_table(spark, sf_dir, "documents")


@query("select doc_id, (s / 512)::bigint as chunk_no, s::bigint as start, substring(text, s + 1, 512) as chunk from (select doc_id, text, unnest(range(0, greatest(length(text), 1), 512)) as s from documents where text is not null)")
def a_chunks_512(spark, sf_dir):
    rows = documents(spark, sf_dir).filter("text is not null").select("doc_id", F.posexplode(tx.chunk_array(F.col("text"), 512)).alias("chunk_no", "c"))
    return rows.select("doc_id", F.col("chunk_no").cast("long").alias("chunk_no"), F.col("c.start").cast("long").alias("start"), "c.chunk")


@query(" union all ".join(f"select {s}::bigint as size, sum(greatest(1, ceil(length(text) / {s}.0)))::bigint as chunks from documents" for s in (128, 256, 512, 1024, 2048)))
def a_chunks_sizes(spark, sf_dir):
    sizes = (128, 256, 512, 1024, 2048)
    counts = documents(spark, sf_dir).agg(*(F.sum(F.size(tx.chunk_array(F.col("text"), s))).alias(f"n{s}") for s in sizes))
    return counts.select(F.explode(F.array(*(F.struct(F.lit(s).cast("long").alias("size"), F.col(f"n{s}").alias("chunks")) for s in sizes))).alias("x")).select("x.*")


@query("select doc_id, s::bigint as start, length(substring(text, s + 1, 512))::bigint as n from (select doc_id, text, unnest(range(0, greatest(length(text), 1), 256)) as s from documents where text is not null)")
def a_chunk_stride(spark, sf_dir):
    rows = documents(spark, sf_dir).filter("text is not null").select("doc_id", F.explode(tx.chunk_array(F.col("text"), 512, 256)).alias("c"))
    return rows.select("doc_id", F.col("c.start").cast("long").alias("start"), F.length("c.chunk").cast("long").alias("n"))


@query("select b::bigint as bit, sum(n * ((cp >> b) & 1))::bigint as ones from (select unicode(c) as cp, count(*) as n from (select unnest(string_split(text, '')) as c from documents) where c <> '' group by 1), range(0, 24) t(b) group by 1")
def a_bit_counts(spark, sf_dir):
    chars = documents(spark, sf_dir).select(F.explode(tx.code_points(F.col("text"))).alias("cp")).groupBy("cp").agg(F.count("*").alias("n"))
    sums = chars.agg(*(F.sum(F.col("n") * F.getbit(F.col("cp"), F.lit(b)).cast("long")).alias(f"b{b}") for b in range(tx.CODE_BITS)))
    return sums.select(F.explode(F.array(*(F.struct(F.lit(b).cast("long").alias("bit"), F.col(f"b{b}").alias("ones")) for b in range(tx.CODE_BITS)))).alias("x")).select("x.*")


# training side ------------------------------------------------------------------------------------

@query("select doc_id, lang from documents where n_chars >= 16")
def t_usable(spark, sf_dir):
    return documents(spark, sf_dir).filter("n_chars >= 16").select("doc_id", "lang")


def language_weights(docs, exponent: float = 0.3):
    """lang, n and its share of the sample: n ** exponent over the sum. One row a language, so the window over all of them is small."""
    n = docs.groupBy("lang").agg(F.count("*").alias("n")).withColumn("w", F.pow("n", F.lit(exponent)))
    return n.select("lang", "n", (F.col("w") / F.sum("w").over(Window.partitionBy())).alias("share"))


def language_balanced(docs, n: int, seed: str = "lang", exponent: float = 0.3):
    """About n documents by language shares, at most all of a language; the id alone decides."""
    rate = F.least(F.lit(1.0), F.col("share") * n / F.col("n"))
    u = F.pmod(tx.md5_int(F.concat_ws("-", F.col("doc_id"), F.lit(seed))), F.lit(1_000_000)) / F.lit(1e6)
    return docs.join(F.broadcast(language_weights(docs, exponent).withColumn("rate", rate)), "lang").filter(u < F.col("rate"))


@query("select lang, n, round(n ** 0.3 / sum(n ** 0.3) over (), 9) as share from (select lang, count(*) as n from documents where n_chars >= 16 group by 1)")
def t_lang_weights(spark, sf_dir):
    return language_weights(t_usable(spark, sf_dir)).select("lang", "n", F.round("share", 9).alias("share"))


@query(f"with l as (select lang, count(*) as n from documents where n_chars >= 16 group by 1), w as (select lang, n, n ** 0.3 / sum(n ** 0.3) over () as share from l) select doc_id, d.lang from documents d join w on d.lang = w.lang where n_chars >= 16 and ({md5_sql(chr(100) + '.doc_id || ' + chr(39) + '-lang' + chr(39))} % 1000000) / 1e6 < least(1.0, share * 500 / n)")
def t_lang_sample(spark, sf_dir):
    return language_balanced(t_usable(spark, sf_dir), 500).select("doc_id", "lang")


def sentences(text):
    return F.filter(F.transform(F.split(text, r"[.!?]\s+|\n+"), lambda s: F.trim(s)), lambda s: s != "")


def sentence_chunks(docs, lo: int = 1, hi: int = 8, size: int = 512, min_chars: int = 16):
    """(doc_id, chunk_no, chunk): sentences one after another; the id and the chunk's number fix how many (lo to hi) it takes.

    A document's cuts follow from its own sentences, so the rows of a text stay together and nothing is shuffled."""
    s = F.col("s")
    take = lambda no: F.pmod(F.xxhash64("doc_id", no), F.lit(hi - lo + 1)).cast("int") + lo
    start = F.struct(F.lit(0).alias("left"), F.lit("").alias("now"), F.array().cast("array<string>").alias("done"))

    def step(acc, x):
        fresh = acc["left"] == 0
        now = F.when(fresh, x).otherwise(F.concat(acc["now"], F.lit(". "), x))
        left = F.when(fresh, take(F.size(acc["done"]))).otherwise(acc["left"]) - 1
        full = (left <= 0) | (F.length(now) >= size)
        return F.struct(F.when(full, 0).otherwise(left).alias("left"), now.alias("now"), F.when(full, F.concat(acc["done"], F.array(now))).otherwise(acc["done"]).alias("done"))

    rest = lambda acc: F.when(acc["left"] > 0, F.concat(acc["done"], F.array(acc["now"]))).otherwise(acc["done"])
    rows = docs.withColumn("s", sentences(F.col("text"))).select("doc_id", F.posexplode(F.aggregate(s, start, step, rest)).alias("chunk_no", "chunk"))
    return rows.filter(F.length("chunk") >= min_chars)


@query()
def t_sentence_chunks(spark, sf_dir):
    return sentence_chunks(documents(spark, sf_dir).filter("n_chars >= 16"))


@query("with s as (select doc_id // 16 as step from documents where n_chars >= 16), t as (select greatest(max(step), 1) as t from s) select step::bigint as step, count(*) as examples, round(0.0 + 0.001 * (1 + cos(pi() * step / t)) / 2, 12) as lr from s, t group by step, t")
def t_cosine_lr(spark, sf_dir):
    """(step, examples, lr) of an epoch over the usable documents: a step takes those of sixteen ids, and the rate falls from .001 to 0 at the last."""
    steps = documents(spark, sf_dir).filter("n_chars >= 16").groupBy(F.floor(F.col("doc_id") / 16).alias("step")).agg(F.count("*").alias("examples"))
    last = steps.agg(F.greatest(F.max("step"), F.lit(1)).alias("t"))  # one row
    return steps.crossJoin(F.broadcast(last)).select("step", "examples", F.round(F.lit(0.0) + F.lit(0.001) * (1 + F.cos(F.lit(3.141592653589793) * F.col("step") / F.col("t"))) / 2, 12).alias("lr"))


def top_words(docs, n: int = 200):
    """(lang, word, n, rn): the most frequent words of each language; partial counts before the exchange."""
    counts = docs.select("lang", F.explode(tx.words(F.col("text"))).alias("word")).groupBy("lang", "word").agg(F.count("*").alias("n"))
    return counts.withColumn("rn", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))).filter(F.col("rn") <= n)


def alphabet(docs):
    """(lang, ch, n): letters of each language. Characters are counted in groups of texts before anything is shuffled."""
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str | None, np.ndarray] = {}
        for batch in batches:
            by: dict[str | None, list[str]] = {}
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if text:
                    by.setdefault(lang, []).append(text)
            for lang, texts in by.items():
                points, n = np.unique(np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32), return_counts=True)
                held.setdefault(lang, np.zeros(0x110000, np.int64))[points] += n
            if len(held) > 16:
                yield from (told(lang, n) for lang, n in held.items())
                held = {}
        yield from (told(lang, n) for lang, n in held.items())

    def told(lang: str | None, n: np.ndarray) -> pa.RecordBatch:
        at = np.flatnonzero(n)
        at = at[(at < 0xD800) | (at > 0xDFFF)]
        return pa.record_batch([pa.array([lang] * len(at), pa.string()), pa.array([chr(i) for i in at.tolist()], pa.string()), pa.array(n[at])], ["lang", "ch", "n"])

    counted = docs.select(F.col("lang").cast("string").alias("lang"), F.lower("text").alias("text")).mapInArrow(count, "lang string, ch string, n long")
    return counted.groupBy("lang", "ch").agg(F.sum("n").alias("n")).filter(r"ch rlike '^\\p{L}$'")


def word_trigrams(docs, least: int = 2):
    """(first, second, third, n): what follows two words, and how often."""
    w = tx.words(F.col("text"))
    rows = docs.withColumn("w", w).filter("size(w) >= 3").select(F.explode(F.transform(F.sequence(F.lit(0), F.size("w") - 3), lambda i: F.struct(F.col("w")[i].alias("first"), F.col("w")[i + 1].alias("second"), F.col("w")[i + 2].alias("third")))).alias("t"))
    return rows.groupBy("t.first", "t.second", "t.third").agg(F.count("*").alias("n")).filter(F.col("n") >= least)


def char_ngrams(docs, n: int, least: int = 2):
    """(before, next, n): what follows n - 1 characters. Grams are counted in groups of texts before anything is shuffled."""
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for some in places.groups(t for batch in batches for t in batch.column(0).to_pylist()):
            grams, n_each = places.ngrams(some, n)
            yield pa.record_batch([pa.array(grams, pa.string()), pa.array(n_each, pa.int64())], ["g", "n"])

    rows = docs.select(F.lower("text").alias("t")).mapInArrow(count, "g string, n long").groupBy("g").agg(F.sum("n").alias("n")).filter(F.col("n") >= least)
    return rows.select(F.substring("g", 1, n - 1).alias("before"), F.substring("g", n, 1).alias("next"), "n")


@query(f"with c as (select lang, word, count(*) as n from (select lang, unnest({WORDS}) as word from documents) group by all) select * from (select lang, word, n, row_number() over (partition by lang order by n desc, word) as rn from c) where rn <= 200")
def t_lex_words(spark, sf_dir):
    return top_words(documents(spark, sf_dir))


@query(r"select lang, ch, count(*) as n from (select lang, unnest(string_split(lower(text), '')) as ch from documents) where regexp_matches(ch, '^\p{L}$') group by all")
def t_lex_alphabet(spark, sf_dir):
    return alphabet(documents(spark, sf_dir))


@query(f"select w[i] as first, w[i+1] as second, w[i+2] as third, count(*) as n from (select w, unnest(range(1, len(w) - 1)) as i from (select {WORDS} as w from documents)) group by all having count(*) >= 2")
def t_lex_trigrams(spark, sf_dir):
    return word_trigrams(documents(spark, sf_dir))


@query("select substring(g, 1, 2) as before, substring(g, 3, 1) as next, count(*) as n from (select substring(t, i, 3) as g from (select lower(text) as t, unnest(range(1, length(lower(text)) - 1)) as i from documents)) group by all having count(*) >= 2")
def t_lex_chargrams(spark, sf_dir):
    return char_ngrams(documents(spark, sf_dir), 3)


# baselines ----------------------------------------------------------------------------------------

@query(f"select id as doc_id, len(g)::bigint as n, md5(array_to_string(list_sort(g), '|')) as digest from {SHINGLES}")
def b_shingle_words(spark, sf_dir):
    g = documents(spark, sf_dir).select("doc_id", tx.word_shingles(F.col("text"), 3).alias("g")).filter("size(g) > 0")
    return g.select("doc_id", F.size("g").cast("long").alias("n"), F.md5(F.array_join(F.array_sort("g"), "|").cast("binary")).alias("digest"))


@query("select doc_id, count(*) as n, count(distinct g) as distinct_n from (select doc_id, substring(lower(text), i, 5) as g from (select doc_id, text, unnest(range(1, length(lower(text)) - 3)) as i from documents)) group by 1")
def b_shingle_chars(spark, sf_dir):
    g = documents(spark, sf_dir).select("doc_id", tx.char_shingles(F.col("text"), 5).alias("g")).filter("size(g) > 0")
    return g.select("doc_id", F.size("g").cast("long").alias("n"), F.size(F.array_distinct("g")).cast("long").alias("distinct_n"))


_PAIRS = f"(select a, b, s::double / (na + nb - s) as score from (select x.id as a, y.id as b, any_value(x.n) as na, any_value(y.n) as nb, count(*) as s from (select id, len(h) as n, unnest(h) as v from {HASHES}) x join (select id, len(h) as n, unnest(h) as v from {HASHES}) y on x.v = y.v and x.id < y.id group by all))"


@query(f"select a, b, round(score, 6) as score from {_PAIRS} where score >= 0.5")
def b_jaccard(spark, sf_dir):
    return sketches.jaccard_join(sketches.shingle_sets(documents(spark, sf_dir)), 0.5).select("a", "b", F.round("score", 6).alias("score"))


def _slots(k: int) -> str:
    return ", ".join(f"({i}, {a}, {b})" for i, (a, b) in enumerate(sketches.coefficients(k)))


def _minhash_sql(k: int) -> str:
    return f"select id, i::bigint as slot, list_min(list_transform(h, lambda v: ((v % {tx.PRIME31}) * a + b) % {tx.PRIME31}))::bigint as value from {HASHES}, (values {_slots(k)}) c(i, a, b)"


def _signature_rows(spark, sf_dir, k):
    signed = sketches.sign(documents(spark, sf_dir), k).filter("signature is not null")
    return signed.select("id", F.posexplode("signature").alias("slot", "value")).select("id", F.col("slot").cast("long").alias("slot"), "value")


@query(_minhash_sql(10))
def b_minhash_10(spark, sf_dir):
    return _signature_rows(spark, sf_dir, 10)


@query(_minhash_sql(256))
def b_minhash_256(spark, sf_dir):
    return _signature_rows(spark, sf_dir, 256)


@query(f"with p as (select a, b from {_PAIRS} where score >= 0.5), s as ({_minhash_sql(10)}) select a, b, round(avg((x.value = y.value)::int), 6) as similarity from p join s x on x.id = a join s y on y.id = b and x.slot = y.slot group by a, b")
def b_minhash_sim(spark, sf_dir):
    docs = documents(spark, sf_dir)
    signed = sketches.sign(docs, 10)
    near = sketches.jaccard_join(sketches.shingle_sets(docs), 0.5)
    both = near.join(signed.select(F.col("id").alias("a"), F.col("signature").alias("sa")), "a").join(signed.select(F.col("id").alias("b"), F.col("signature").alias("sb")), "b")
    return both.select("a", "b", F.round(sketches.agreement(F.col("sa"), F.col("sb")), 6).alias("similarity"))


_B, _R = sketches.choose_bands(0.8, 32)


@query(f"""with h as (select id, list_sort(h) as h from {HASHES}), reps as (select min(id) as id, h from h group by h),
sig as (select id, list(value order by slot) as v from (select id, i as slot, list_min(list_transform(h, lambda v: ((v % {tx.PRIME31}) * a + b) % {tx.PRIME31})) as value from reps, (values {_slots(32)}) c(i, a, b)) group by id),
k as (select id, n, v[n * {_R} + 1:(n + 1) * {_R}] as key from sig, range(0, {_B}) t(n)),
c as (select distinct x.id as a, y.id as b from k x join k y on x.n = y.n and x.key = y.key and x.id < y.id),
s as (select a, b, len(list_intersect(x.h, y.h)) as s, len(x.h) + len(y.h) as n from c join reps x on x.id = a join reps y on y.id = b)
select a, b, round(s::double / (n - s), 6) as score from s where s::double / (n - s) >= 0.8 union all select r.id as a, h.id as b, 1.0 as score from h join reps r on h.h = r.h and h.id <> r.id""")
def b_minhash_lsh(spark, sf_dir):
    return sketches.minhash_pairs(documents(spark, sf_dir), 0.8, 32).select("a", "b", F.round("score", 6).alias("score"))


_HALF = "list_sum(list_transform(range(0, 32), lambda b: case when list_sum(list_transform(h{p}, lambda x: ((x >> b) & 1) * 2 - 1)) > 0 then 1::bigint << b else 0 end))::bigint"
_FINGER = f"(select id, ({_HALF.format(p=0)})::hugeint * 4294967296 + ({_HALF.format(p=1)}) as u from (select doc_id as id, list_transform(g, lambda s: ('0x' || substr(md5(s), 1, 8))::bigint) as h0, list_transform(g, lambda s: ('0x' || substr(md5(s), 9, 8))::bigint) as h1 from (select doc_id, list_transform(range(1, length(text) - 3), lambda i: substring(lower(text), i, 5)) as g from documents where length(text) >= 5)))"
FINGERPRINTS = f"(select id, (case when u >= 9223372036854775808 then u - 18446744073709551616 else u end)::bigint as fingerprint from {_FINGER})"


def fingerprints(spark, sf_dir):
    return sketches.simhash_votes(documents(spark, sf_dir), 5).filter("fingerprint is not null")


@query(f"select * from {FINGERPRINTS}")
def b_simhash(spark, sf_dir):
    return fingerprints(spark, sf_dir)


_SIM_PAIRS = f"with f as {FINGERPRINTS} select x.id as a, y.id as b, bit_count(xor(x.fingerprint, y.fingerprint))::int as distance from f x join f y on x.id < y.id where bit_count(xor(x.fingerprint, y.fingerprint)) <= 6"


@query(_SIM_PAIRS)
def b_simhash_pairs(spark, sf_dir):
    from twinsift.plans.checkpoints import cut

    return sketches.simhash_pairs(cut(fingerprints(spark, sf_dir)), 6)


@query(_SIM_PAIRS)
def b_simhash_blocks(spark, sf_dir):
    from twinsift.plans.checkpoints import cut

    return sketches.simhash_block_pairs(cut(fingerprints(spark, sf_dir)), 6)


@query("select doc_id as id, min(doc_id) over (partition by text) as group_id, count(*) over (partition by text) as group_size from documents qualify group_size > 1")
def b_exact_full(spark, sf_dir):
    return exact.groups(documents(spark, sf_dir), F.col("text"))


@query(r"with f as (select doc_id, trim(regexp_replace(lower(text), '\s+', ' ', 'g')) as k from documents) select doc_id as id, min(doc_id) over (partition by k) as group_id, count(*) over (partition by k) as group_size from f qualify group_size > 1")
def b_exact_folded(spark, sf_dir):
    return exact.groups(documents(spark, sf_dir), exact.folded(F.col("text")))


@query(r"with f as (select doc_id, trim(regexp_replace(lower(string_split(text, chr(10))[1]), '\s+', ' ', 'g')) as k from documents) select doc_id as id, min(doc_id) over (partition by k) as group_id, count(*) over (partition by k) as group_size from f qualify group_size > 1")
def b_exact_title(spark, sf_dir):
    return exact.groups(documents(spark, sf_dir), exact.title(F.col("text")))


@query(f"""with w as (select id, s::bigint as s, array_to_string(w[s+1:s+50], ' ') as g from (select doc_id as id, w, unnest(range(0, len(w) - 49)) as s from (select doc_id, {WORDS} as w from documents))),
hit as (select id, s from w where g in (select g from w group by g having count(distinct id) > 1)), r as (select id, s, s - row_number() over (partition by id order by s) as island from hit)
select id, min(s) as first, max(s) - min(s) + 50 as words from r group by id, island""")
def b_exact_substring(spark, sf_dir):
    found = exact.shared_spans(exact.token_windows(documents(spark, sf_dir), 50), 50)
    return found.select("id", F.col("first").cast("long").alias("first"), F.col("words").cast("long").alias("words"))
