"""Queries of group H: the operators around the methods, on the given tables."""

from pyspark.sql import Window
from pyspark.sql import functions as F

from twinsift.functions.text import md5_int, words
from twinsift.operators import joins
from twinsift.sources.tables import html_text, html_title, read_table

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return keep


def t(spark, sf_dir, name):
    return read_table(spark, sf_dir, name)


@query("select 'documents' as name, count(*) as n from documents " + " ".join(f"union all select '{x}', count(*) from {x}" for x in ("labels", "benchmark", "pages", "conversations", "embeddings", "events", "part", "lineitem", "orders", "customer", "supplier", "nation", "region")))
def h_scan_parquet(spark, sf_dir):
    rows = None
    for name in ("documents", "labels", "benchmark", "pages", "conversations", "embeddings", "events", "part", "lineitem", "orders", "customer", "supplier", "nation", "region"):
        one = t(spark, sf_dir, name).agg(F.count("*").alias("n")).select(F.lit(name).alias("name"), "n")
        rows = one if rows is None else rows.union(one)
    return rows


@query(r"select page_id, md5(trim(regexp_replace(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]+>', ' ', 'g'), '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&#39;', chr(39)), '&amp;', '&'), '\s+', ' ', 'g'))) as digest, trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)) as title from pages".replace('\\"', '"'))
def h_html_text(spark, sf_dir):
    return t(spark, sf_dir, "pages").select("page_id", F.md5(html_text(F.col("html")).cast("binary")).alias("digest"), html_title(F.col("html")).alias("title"))


@query("select event_id, (props->>'$.k')::bigint as k from events where props is not null")
def h_json_props(spark, sf_dir):
    return t(spark, sf_dir, "events").filter("props is not null").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("select doc_id, lang, n_chars from documents where n_chars >= 1000 and lang in ('de', 'fr') and contains(text, 'en') and regexp_matches(text, '[.]') and source is not distinct from source")
def h_project_filter(spark, sf_dir):
    d = t(spark, sf_dir, "documents")
    return d.filter((F.col("n_chars") >= 1000) & F.col("lang").isin("de", "fr") & F.col("text").contains("en") & F.col("text").rlike("[.]") & F.col("source").eqNullSafe(F.col("source"))).select("doc_id", "lang", "n_chars")


@query("select n_name, count(*) as customers, round(sum(c_acctbal), 2) as balance from customer join nation on c_nationkey = n_nationkey group by 1")
def h_join_broadcast(spark, sf_dir):
    """A table of 25 rows is the broadcast side."""
    c = t(spark, sf_dir, "customer").join(F.broadcast(t(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return c.groupBy("n_name").agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


_OL = "select o_orderpriority, count(*) as n, sum(l_quantity)::bigint as quantity from lineitem join orders on l_orderkey = o_orderkey group by 1"


def _orders_lines(spark, sf_dir, hint):
    rows = t(spark, sf_dir, "lineitem").join(t(spark, sf_dir, "orders").hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("quantity"))


@query(_OL)
def h_join_shuffle_hash(spark, sf_dir):
    return _orders_lines(spark, sf_dir, "shuffle_hash")


@query(_OL)
def h_join_sort_merge(spark, sf_dir):
    return _orders_lines(spark, sf_dir, "merge")


@query("select x.n_name as a, y.n_name as b from nation x join nation y on x.n_nationkey < y.n_nationkey and bit_count(xor(x.n_nationkey, y.n_nationkey)) <= 1")
def h_join_nested_loop(spark, sf_dir):
    """A theta join of two fixed tables of 25 rows."""
    n = t(spark, sf_dir, "nation")
    x, y = n.select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("a")), n.select(F.col("n_nationkey").alias("l"), F.col("n_name").alias("b"))
    return x.join(F.broadcast(y), (F.col("k") < F.col("l")) & (F.bit_count(F.col("k").bitwiseXOR(F.col("l"))) <= 1)).select("a", "b")


@query("select p_partkey, count(*) as near from part join (select item_id, length(text) * 5.0 as price from benchmark) on price between p_retailprice - 10 and p_retailprice + 10 group by 1")
def h_join_range(spark, sf_dir):
    p, b = t(spark, sf_dir, "part"), t(spark, sf_dir, "benchmark").select("item_id", (F.length("text") * 5.0).alias("price"))
    rows = joins.range_join(p, b, F.col("p_retailprice") - 10, F.col("p_retailprice") + 10, F.col("price"), 20.0)
    return rows.groupBy("p_partkey").agg(F.count("*").alias("near"))


@query("with p as (select user_id, ts, max(event_id) as event_id from events where event_type = 'click' group by all) select e.event_id, p.event_id as click from (select * from events where event_type = 'purchase') e asof left join p on e.user_id = p.user_id and e.ts >= p.ts")
def h_join_asof(spark, sf_dir):
    """The last click of the user at or before each purchase."""
    e = t(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    clicks = e.filter("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("event_id"))
    return joins.asof_join(e.filter("event_type = 'purchase'"), clicks, "user_id", "ts", "event_id", "click").select("event_id", "click")


@query("select l.event_id as click, r.event_id as purchase from events l join events r on l.user_id = r.user_id and l.event_type = 'click' and r.event_type = 'purchase' and r.ts between l.ts and l.ts + interval 1 hour")
def h_join_interval(spark, sf_dir):
    """Purchases within an hour of a click of the same user: hour bins make it an equi-join."""
    e = t(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    hour = F.floor(F.unix_timestamp("ts") / 3600)
    c = e.filter("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t0"), F.explode(F.array(hour, hour + 1)).alias("h"))
    p = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("t1"), hour.alias("h"))
    return c.join(p, ["user_id", "h"]).filter("t1 >= t0 and t1 <= t0 + interval 1 hour").select("click", "purchase")


@query("select doc_id from documents where doc_id in (select doc_id from labels where toxic = 1)")
def h_join_semi(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id").join(t(spark, sf_dir, "labels").filter("toxic = 1"), "doc_id", "left_semi")


@query("select doc_id from documents where doc_id not in (select doc_id from labels)")
def h_join_anti(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id").join(t(spark, sf_dir, "labels"), "doc_id", "left_anti")


@query("with a as (select doc_id from labels where quality = 0), b as (select doc_id from labels where toxic = 1) select coalesce(a.doc_id, b.doc_id) as doc_id, (a.doc_id is not null)::int as low, (b.doc_id is not null)::int as toxic from a full join b on a.doc_id = b.doc_id")
def h_join_outer(spark, sf_dir):
    lab = t(spark, sf_dir, "labels")
    a, b = lab.filter("quality = 0").select("doc_id", F.lit(1).alias("low")), lab.filter("toxic = 1").select("doc_id", F.lit(1).alias("toxic"))
    return a.join(b, "doc_id", "full_outer").select("doc_id", F.coalesce("low", F.lit(0)).alias("low"), F.coalesce("toxic", F.lit(0)).alias("toxic"))


@query("select n_name, c_custkey, c_acctbal from (select n_name, c_custkey, c_acctbal, row_number() over (partition by n_nationkey order by c_acctbal desc, c_custkey) as rn from nation join customer on n_nationkey = c_nationkey) where rn <= 3")
def h_join_lateral(spark, sf_dir):
    """The three richest customers of each nation, as a lateral sub-query."""
    t(spark, sf_dir, "customer").createOrReplaceTempView("ts_customer")
    t(spark, sf_dir, "nation").createOrReplaceTempView("ts_nation")
    return spark.sql("select n_name, x.c_custkey, x.c_acctbal from ts_nation, lateral (select c_custkey, c_acctbal, row_number() over (order by c_acctbal desc, c_custkey) as rn from ts_customer where c_nationkey = n_nationkey) x where rn <= 3")


@query("select l_returnflag, l_linestatus, count(*) as n, sum(l_quantity)::bigint as quantity, min(l_discount) as lo, max(l_discount) as hi, round(avg(l_extendedprice), 4) as mean from lineitem group by all")
def h_agg_partial_final(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("quantity"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi"), F.round(F.avg("l_extendedprice"), 4).alias("mean"))


@query("select source, count(distinct lang) as langs, count(distinct text) as texts from documents group by 1")
def h_agg_distinct(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupBy("source").agg(F.count_distinct("lang").alias("langs"), F.count_distinct(F.sha2(F.col("text").cast("binary"), 256)).alias("texts"))


@query()
def h_agg_approx(spark, sf_dir):
    return t(spark, sf_dir, "documents").agg(F.approx_count_distinct("text", 0.02).alias("texts"), F.percentile_approx("n_chars", F.array(F.lit(0.5), F.lit(0.95)), F.lit(1000)).alias("lengths"))


@query("select conv_id, string_agg(role, '>' order by turn) as roles from conversations group by 1")
def h_agg_sort(spark, sf_dir):
    rows = t(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role"))).alias("x"))
    return rows.select("conv_id", F.array_join("x.role", ">").alias("roles"))


@query("select lang, max(n_chars) as n_chars, min(doc_id) filter (n_chars = m) as doc_id from (select *, max(n_chars) over (partition by lang) as m from documents) group by 1")
def h_agg_argmax(spark, sf_dir):
    rows = t(spark, sf_dir, "documents").groupBy("lang").agg(F.max_by(F.struct("n_chars", "doc_id"), F.struct(F.col("n_chars"), (-F.col("doc_id")))).alias("x"))
    return rows.select("lang", "x.n_chars", "x.doc_id")


@query("select lang, source, count(*) as n from documents group by grouping sets ((lang), (source), ())")
def h_group_sets(spark, sf_dir):
    t(spark, sf_dir, "documents").createOrReplaceTempView("ts_documents")
    return spark.sql("select lang, source, count(*) as n from ts_documents group by grouping sets ((lang), (source), ())")


@query("select quality, toxic, count(*) as n from labels group by cube (quality, toxic)")
def h_group_cube(spark, sf_dir):
    return t(spark, sf_dir, "labels").cube("quality", "toxic").agg(F.count("*").alias("n"))


@query("select lang, source, sum(n_chars)::bigint as n_chars from documents group by rollup (lang, source)")
def h_group_rollup(spark, sf_dir):
    return t(spark, sf_dir, "documents").rollup("lang", "source").agg(F.sum("n_chars").alias("n_chars"))


@query("select source, count(*) filter (lang = 'de') as de, count(*) filter (lang = 'en') as en, count(*) filter (lang = 'es') as es, count(*) filter (lang = 'fr') as fr from documents group by 1")
def h_pivot(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).fillna(0)


@query("select c_custkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt, round(percent_rank() over w, 6) as pr from customer window w as (partition by c_nationkey order by c_mktsegment, c_custkey)")
def h_win_rank(spark, sf_dir):
    w = Window.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")
    return t(spark, sf_dir, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("select event_id, lag(event_id) over w as before, lead(event_id) over w as after, first_value(event_id) over w as opening, nth_value(event_id, 2) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as second from events window w as (partition by user_id order by ts, event_id)")
def h_win_offset(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("opening"), F.nth_value("event_id", 2).over(whole).alias("second"))


@query("select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row), 6) as running from events")
def h_win_rows(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(spark, sf_dir, "events").select("event_id", F.round(F.sum("value").over(w), 6).alias("running"))


@query("select event_id, count(*) over (partition by user_id order by floor(epoch(ts))::bigint range between 3600 preceding and current row) as burst from events")
def h_win_range(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-3600, 0)
    return t(spark, sf_dir, "events").select("event_id", F.count("*").over(w).alias("burst"))


@query("select doc_id, n_chars from documents order by n_chars desc, doc_id limit 10")
def h_topk(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(10)


@query("select lang, source, n from (select lang, source, count(*) as n from documents group by all) order by lang nulls last, n desc, source")
def h_sort(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupBy("lang", "source").agg(F.count("*").alias("n")).orderBy(F.col("lang").asc_nulls_last(), F.desc("n"), "source")


def _two_sets(spark, sf_dir):
    lab = t(spark, sf_dir, "labels")
    return lab.filter("quality = 1").select("doc_id"), lab.filter("toxic = 1").select("doc_id")


@query("select doc_id from labels where quality = 1 union all select doc_id from labels where toxic = 1")
def h_union(spark, sf_dir):
    a, b = _two_sets(spark, sf_dir)
    return a.unionByName(b)


@query("select doc_id from labels where quality = 1 intersect select doc_id from labels where toxic = 1")
def h_intersect(spark, sf_dir):
    a, b = _two_sets(spark, sf_dir)
    return a.intersect(b)


@query("select doc_id from labels where quality = 1 except all select doc_id from labels where toxic = 1")
def h_except(spark, sf_dir):
    a, b = _two_sets(spark, sf_dir)
    return a.exceptAll(b)


@query("select p_partkey, lower(p_name) as low, trim(p_type) as kind, replace(p_name, ' ', '_') as joined, substring(p_name, 2, 4) as part, length(p_name) as n, reverse(p_name) as back, concat_ws('-', p_brand, p_type) as both, levenshtein(p_brand, p_type) as apart, instr(p_name, 'a') as at, lpad(p_brand, 12, '*') as padded from part")
def h_string(spark, sf_dir):
    c = F.col
    return t(spark, sf_dir, "part").select("p_partkey", F.lower("p_name").alias("low"), F.trim("p_type").alias("kind"), F.replace("p_name", F.lit(" "), F.lit("_")).alias("joined"), F.substring("p_name", 2, 4).alias("part"), F.length("p_name").alias("n"), F.reverse("p_name").alias("back"), F.concat_ws("-", "p_brand", "p_type").alias("both"), F.levenshtein("p_brand", "p_type").alias("apart"), F.instr(c("p_name"), "a").alias("at"), F.lpad("p_brand", 12, "*").alias("padded"))


@query("select doc_id, md5(text) as m, sha256(text) as s from documents where text is not null")
def h_hash(spark, sf_dir):
    b = F.col("text").cast("binary")
    return t(spark, sf_dir, "documents").filter("text is not null").select("doc_id", F.md5(b).alias("m"), F.sha2(b, 256).alias("s"))


@query(r"select doc_id, len(w)::bigint as n, len(list_distinct(w))::bigint as d, len(list_filter(w, lambda x: length(x) > 5))::bigint as long_n, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::bigint as chars, list_contains(w, 'the') as the from (select doc_id, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') as w from documents)")
def h_array(spark, sf_dir):
    w = t(spark, sf_dir, "documents").select("doc_id", words(F.col("text")).alias("w"))
    return w.select("doc_id", F.size("w").cast("long").alias("n"), F.size(F.array_distinct("w")).cast("long").alias("d"), F.size(F.filter("w", lambda x: F.length(x) > 5)).cast("long").alias("long_n"), F.aggregate("w", F.lit(0).cast("long"), lambda s, x: s + F.length(x)).alias("chars"), F.array_contains("w", "the").alias("the"))


@query("select lang, source, count(*) as n from documents group by all")
def h_map(spark, sf_dir):
    by = t(spark, sf_dir, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"))
    maps = by.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    return maps.select("lang", F.explode(F.transform_values("m", lambda k, v: v)).alias("source", "n"))


@query("select p_partkey, p_size % 7 as m, (p_size >> 1) as half, bit_count(p_size)::int as bits, round(sqrt(p_retailprice), 6) as root, round(ln(p_retailprice), 6) as lg, greatest(p_size, 10) as hi, least(p_size, 10) as lo from part")
def h_math_bits(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", F.pmod("p_size", F.lit(7)).alias("m"), F.shiftright("p_size", 1).alias("half"), F.bit_count("p_size").alias("bits"), F.round(F.sqrt("p_retailprice"), 6).alias("root"), F.round(F.log("p_retailprice"), 6).alias("lg"), F.greatest("p_size", F.lit(10)).alias("hi"), F.least("p_size", F.lit(10)).alias("lo"))


@query("select date_trunc('month', o_orderdate)::timestamp as month, count(*) as n, min(epoch(o_orderdate))::bigint as first_s from orders where o_orderdate >= timestamp '1995-01-01' - interval 30 day group by 1")
def h_date(spark, sf_dir):
    o = t(spark, sf_dir, "orders").filter(F.col("o_orderdate") >= F.expr("timestamp '1995-01-01' - interval 30 day"))
    return o.groupBy(F.date_trunc("month", "o_orderdate").alias("month")).agg(F.count("*").alias("n"), F.min(F.unix_timestamp("o_orderdate")).alias("first_s"))


@query("select doc_id, lang from documents where ('0x' || substr(md5(doc_id || '-sample'), 1, 15))::bigint % 1000 < 250")
def h_sample(spark, sf_dir):
    """A stable sample: the id alone decides."""
    return t(spark, sf_dir, "documents").filter(md5_int(F.concat_ws("-", "doc_id", F.lit("sample"))) % 1000 < 250).select("doc_id", "lang")


@query("select l_partkey, l_suppkey, count(*) as copies from lineitem group by all having count(*) > 1")
def h_row_dups(spark, sf_dir):
    from twinsift.operators.exact import row_groups

    return row_groups(t(spark, sf_dir, "lineitem"), ["l_partkey", "l_suppkey"])


@query("select r_name, n_name, count(distinct o_orderkey) as orders, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by all")
def h_star_report(spark, sf_dir):
    rows = t(spark, sf_dir, "lineitem").select("l_orderkey", "l_extendedprice", "l_discount").join(t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    rows = rows.join(t(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(F.broadcast(t(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.groupBy("r_name", "n_name").agg(F.count_distinct("o_orderkey").alias("orders"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))
