"""Queries of groups W and E: the experiments with lexical methods, and the same with the encoder (rows only)."""


from pyspark.sql import functions as F

from twinsift.encoder import api, net
from twinsift.experiments import workloads as w
from twinsift.sources.tables import read_table

ORACLES: dict[str, str] = {}
QUERIES = {f"w_{n}": getattr(w, f"w_{n}") for n in ("adversarial", "by_kind", "by_amount", "by_length", "news", "ratio", "thresholds", "scholarly", "corpus", "speed", "campaigns", "errors", "stream", "ablate_shape", "ablate_train")}
QUERIES["c_index_cost"] = w.c_index_cost


def _e(name, methods):
    return lambda spark, sf_dir: getattr(w, name)(spark, sf_dir, methods=methods)


QUERIES |= {
    "e_retrieve": _e("w_adversarial", ("doc", "chunk", "untrained")),
    "e_by_kind": _e("w_by_kind", ("doc", "chunk")),
    "e_by_amount": _e("w_by_amount", ("doc", "chunk")),
    "e_by_length": _e("w_by_length", ("doc", "chunk")),
    "e_news": _e("w_news", ("doc", "chunk")),
    "e_ratio": _e("w_ratio", ("doc", "chunk")),
    "e_thresholds": _e("w_thresholds", ("doc", "chunk")),
    "e_scholarly": _e("w_scholarly", ("doc", "chunk")),
    "e_dedup": _e("w_corpus", ("doc", "chunk")),
    "e_campaigns": _e("w_campaigns", ("doc",)),
    "e_throughput": _e("w_speed", ("doc",)),
}


def _slices(name, column):
    """A breakdown alone: the recall rows of a workload's lexical methods, by its slice."""
    def run(spark, sf_dir):
        return getattr(w, name)(spark, sf_dir).filter("metric = 'recall@1'").select("method", F.col("slice").alias(column), F.col("value").alias("recall"))

    return run


QUERIES |= {"c_recall_kind": _slices("w_by_kind", "kind"), "c_recall_amount": _slices("w_by_amount", "amount"), "c_recall_length": _slices("w_by_length", "bound")}


def e_encode_doc(spark, sf_dir):
    weights, c = api.model("tiny")
    return api.encode_texts(read_table(spark, sf_dir, "documents"), weights, c).select(F.col("id").alias("doc_id"), "doc_vector", F.size("chunk_vectors").alias("chunks"))


def e_encode_chunk(spark, sf_dir):
    weights, c = api.model("tiny")
    return api.encode_chunks(api.chunks_of(read_table(spark, sf_dir, "documents"), c), weights, c)


SKETCHES = (("minhash 256", 2048), ("minhash 10", 80), ("simhash 64", 8))


def c_footprint(spark, sf_dir):
    """(method, parameters, bytes, vectors, total_bytes) over the documents: parameters, bytes of a vector, and how many vectors the texts have; of encoders one a chunk."""
    texts = read_table(spark, sf_dir, "documents").filter("text is not null")
    chunks = lambda size: F.coalesce(F.sum(F.greatest(F.lit(1), F.ceil(F.length("text") / size))), F.lit(0)).cast("long")
    rows = [(name, net.n_params(c), 4 * c.dim, chunks(c.chunk)) for name, c in net.PRESETS.items()] + [(name, 0, size, F.count("*")) for name, size in SKETCHES]
    counts = texts.agg(*(n.alias(f"n{i}") for i, (*_, n) in enumerate(rows)))
    each = [F.struct(F.lit(name).alias("method"), F.lit(p).cast("long").alias("parameters"), F.lit(size).cast("long").alias("bytes"), F.col(f"n{i}").alias("vectors")) for i, (name, p, size, _) in enumerate(rows)]
    return counts.select(F.explode(F.array(*each)).alias("x")).select("x.*").withColumn("total_bytes", F.col("bytes") * F.col("vectors"))


QUERIES |= {f.__name__: f for f in (e_encode_doc, e_encode_chunk, c_footprint)}
ORACLES["c_footprint"] = "with n as (select count(*)::bigint as texts, coalesce(sum(greatest(1, ceil(length(text) / 512.0))), 0)::bigint as c512, coalesce(sum(greatest(1, ceil(length(text) / 128.0))), 0)::bigint as c128 from documents where text is not null), m as (select 'paper' as method, 535810 as parameters, 1024 as bytes, c512 as vectors from n union all select 'small', {small}, 256, c512 from n union all select 'tiny', {tiny}, {width}, c128 from n union all select 'minhash 256', 0, 2048, texts from n union all select 'minhash 10', 0, 80, texts from n union all select 'simhash 64', 0, 8, texts from n) select method, parameters::bigint as parameters, bytes::bigint as bytes, vectors, bytes * vectors as total_bytes from m".format(small=net.n_params(net.PRESETS["small"]), tiny=net.n_params(net.PRESETS["tiny"]), width=4 * net.PRESETS["tiny"].dim)
