"""Tables with fixed schemas, raw pages as text, and sinks."""

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "benchmark": "item_id long, text string",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
}


def one_file(spark: SparkSession, path: str) -> bool:
    """Whether a path is a single file, which one task may have to read alone."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isFile()


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the given directory; its columns are checked by name."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    want = [c.split()[0] for c in SCHEMAS[name].split(", ")]
    missing = [c for c in want if c not in df.columns]
    if missing:
        raise ValueError(f"{name} lacks {missing}")
    df = df.select(*want)
    # small test tables are one file with one row group; a corpus is many files and is left as it is
    spread = name == "documents" and one_file(spark, f"{sf_dir}/{name}.parquet")
    return df.repartition(spark.sparkContext.defaultParallelism) if spread else df


def read_corpus(spark: SparkSession, path: str, form: str) -> tuple[DataFrame, DataFrame | None]:
    """A corpus in text, json, csv, orc or parquet form, and (json, csv) the rows that could not be parsed."""
    schema = SCHEMAS["documents"]
    if form == "text":
        lines = spark.read.text(path)
        return lines.select(F.xxhash64("value").alias("doc_id"), F.col("value").alias("text")), None
    if form == "json":
        how = {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "bad"}
        rows = spark.read.text(path).select(F.from_json("value", schema + ", bad string", how).alias("r")).select("r.*")
        return rows.filter("bad is null").drop("bad"), rows.filter("bad is not null").select("bad")
    if form == "csv":
        reader = spark.read.schema(schema + ", bad string").option("columnNameOfCorruptRecord", "bad").option("mode", "PERMISSIVE").option("header", True).option("multiLine", True).option("escape", '"')
        rows = reader.csv(path)
        return rows.filter("bad is null").drop("bad"), rows.filter("bad is not null")
    return spark.read.schema(schema).format(form).load(path), None


def write_store(df: DataFrame, path: str, by: str | None = None, form: str = "parquet") -> None:
    """A directory of files, by a column's values if one is named."""
    writer = df.write.mode("overwrite").format(form)
    (writer.partitionBy(by) if by else writer).save(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table whose rows are dealt by the key, so that joins on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


# HTML entities that extraction resolves, the ampersand last.
ENTITIES = (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&"))


def html_text(html: Column) -> Column:
    """Visible text of a page: scripts, styles and tags go, common entities are resolved, white space is folded."""
    text = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    text = F.regexp_replace(text, r"(?s)<[^>]+>", " ")
    for name, char in ENTITIES:
        text = F.replace(text, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(text, r"[\s]+", " "))


def html_title(html: Column) -> Column:
    return F.trim(F.regexp_extract(html, r"(?is)<title[^>]*>(.*?)</title>", 1))
