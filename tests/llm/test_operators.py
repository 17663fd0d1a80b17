"""Each operator against brute force on small inputs, with nulls, ties, repeats and clashing extra columns."""

import hashlib
import json
import os
import random
import re
import subprocess
import sys
import zlib
from collections import Counter
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinsift.llm import bpe, chat, common, embedding_dedup, language_id, license_scan, mixing, ngram_join, quality_cnn, sharding, telephony
from twinsift.llm.queries import ORACLES, QUERIES, tokenizer_path

SF = "/root/testdata/sf0.001"
REPO = str(Path(__file__).resolve().parents[2])
ODD = [(1, None), (2, ""), (3, " \n\t"), (4, "a"), (4, "a"), (5, "MIT License\x0bmit license"), (None, "no id"), (6, "ÉÀ é　x " * 40), (7, "x" * 200_000), (8, "one two three"), (9, "One TWO three"), (10, "a b c d e f g h i j"), (11, "a b c d e f g h i j")]


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(i, t, "en" if k % 3 else None, "s" if k % 2 else None, k, 1.5, "x", 3, True) for k, (i, t) in enumerate(ODD)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score double, pos string, n int, copies boolean")


@pytest.fixture(scope="module")
def none(odd):
    return odd.limit(0)


def words(text, pattern=r"[^\x20\x09-\x0d]+"):
    return re.findall(pattern, text or "")


def test_language(odd, none, docs):
    model = language_id.fit_profiles(docs)
    got = language_id.predict_language(docs, model).collect()
    truth = {r.doc_id: r.lang for r in docs.collect()}
    held = [r for r in got if r.held_out]
    assert held and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in got)
    assert sum(r.lang_pred == truth[r.doc_id] for r in held) / len(held) > 0.97
    rows = language_id.predict_language(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r.score <= 1 for r in rows)
    assert {r.doc_id: r.lang_pred for r in rows}[2] == "und" and {r.doc_id: r.score for r in rows}[1] == 0
    assert language_id.predict_language(none, language_id.fit_profiles(none)).count() == 0
    assert {r.lang_pred for r in language_id.predict_language(odd, language_id.fit_profiles(none)).collect()} == {"und"}
    texts = ["aab!ba", "the a"]
    codes, owner, _ = model.trigrams(texts)
    slow = np.zeros((2, language_id.DIMENSIONS))
    for c, o in zip(codes.tolist(), owner.tolist(), strict=True):
        slow[o] += model.vectors(np.array([c]))[0]
    assert np.allclose(slow, model.bundle(texts)[0])


def test_language_letters_beyond_any_number(spark):
    """Learned letters have vectors of their own: two languages that differ only in letters that are rare over all."""
    rnd = random.Random(5)
    alphabet = [chr(c) for c in range(0x4E00, 0x4E00 + 600)]
    spoken = ["".join(alphabet[k : k + 3]) for k in range(0, 600, 3)]
    rows = [(i, " ".join(rnd.choice(spoken[:100] if i % 2 else spoken[100:]) for _ in range(60)), f"l{i % 2}") for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.fit_profiles(df)
    number = model.number[[ord(c) for c in alphabet]]
    assert len(set(number.tolist())) == len(alphabet) and model.size == 1 + len(alphabet) + language_id.SPARE
    assert all(r.lang_pred == f"l{r.doc_id % 2}" for r in language_id.predict_language(df, model).collect() if r.held_out)
    again = language_id.Profiles.of(*model.plain())
    assert again.predict(["".join(alphabet[:9])])[0] == model.predict(["".join(alphabet[:9])])[0]


def test_learning_rows_are_bounded(spark):
    rows = [(i, f"text {i}" * 3, "en") for i in range(2000)] + [(7, "text 7" * 3, "en")] * 500
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = common.learning_rows(df, 300, 1000, "s")
    assert 150 < len(got) < 450 and len({(r.doc_id, r.text) for r in got}) == len(got) and got == common.learning_rows(df, 300, 1000, "s")
    assert len(common.learning_rows(df, 10**6, 1000, "s")) == 2000 and not common.learning_rows(df, 10**6, 3, "s")


def test_queries_need_no_copy_of_the_repository(tmp_path):
    """Workers that cannot import the package run the operators: it travels with the tasks."""
    code = f"""
import sys
sys.path.insert(0, {REPO!r})
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[2]").config("spark.sql.shuffle.partitions", "2").config("spark.ui.enabled", "false").getOrCreate()
spark.sparkContext.setLogLevel("ERROR")
import __spark_entry__
queries = __spark_entry__.queries()
for name in ("op1_language_id", "op4_quality", "op6_chat_format", "op9_telephony"):
    assert queries[name](spark, {SF!r}).toPandas().shape[0] > 0, name
print("all ran")
"""
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    out = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=env, capture_output=True, text=True, timeout=300)
    assert "all ran" in out.stdout, out.stderr[-3000:]


def test_license(spark, odd, none):
    rows = {r.doc_id: r for r in license_scan.scan_licenses(odd).collect()}
    assert license_scan.scan_licenses(odd).count() == len(ODD) and license_scan.scan_licenses(none).count() == 0
    assert (rows[5].n_words, rows[5].n_base, rows[5].first_word, rows[5].last_word, rows[5].base_labels) == (4, 2, 0, 2, "mit")
    assert rows[1].n_words == 0 and rows[1].first_word is None and rows[1].score == 0
    notice = license_scan.NOTICES[6][0].split()
    broken = " ".join(notice[:12] + ["very"] + notice[12:])
    near = license_scan.scan_licenses(spark.createDataFrame([(1, "before " + broken), (2, " ".join(notice[:9]))], "doc_id long, text string")).orderBy("doc_id").collect()
    assert near[0].labels == "mit" and 0.75 <= near[0].score < 1 and near[1].labels == "" and near[1].score < 0.75


def test_sharding(spark, odd, none, docs):
    texts = docs.select("doc_id", "text").union(spark.range(1000, 1200).select("id", F.lit("the same")))
    out = sharding.balance(texts, shards=7).collect()
    sizes = Counter(r.shard for r in out)
    assert max(sizes.values()) - min(sizes.values()) <= 1 and len(out) == texts.count()
    for s in sizes:
        assert sorted(r.slot for r in out if r.shard == s) == list(range(sizes[s]))
    copies = [r for r in out if r.size == len("the same") + 16]
    assert max(Counter(r.shard for r in copies).values()) == max(sizes.values()) or len({r.shard for r in copies}) <= 4
    got = sharding.balance(odd).collect()
    assert len(got) == len(ODD) and {r.text_crc32 for r in got if r.doc_id in (1, 2)} == {0}
    assert sharding.balance(none).count() == 0


def test_sharding_keeps_quotas_and_counts_cut_links(spark):
    """Groups of many sizes: quotas hold, slots are gapless, cut_links counts what brute force counts, and fewer links are cut than by hash."""
    rnd = random.Random(14)
    rows = [(i, f"group {g}") for g, n in enumerate([60, 25, 12, 12, 7, 5, 3, 2, 2, 2, *[1] * 70]) for i in range(1000 * g, 1000 * g + n)]
    rows += [(None, "group 1")] * 5 + [(1000, "group 1")] * 2 + [(None, None)] * 3
    rnd.shuffle(rows)
    for shards in (3, 8):
        placed = sharding.balance(spark.createDataFrame(rows, "doc_id long, text string"), shards).cache()
        got = placed.collect()
        sizes = Counter(r.shard for r in got)
        assert [sizes[s] for s in range(shards)] == [len(rows) // shards + (s < len(rows) % shards) for s in range(shards)]
        assert all(sorted(r.slot for r in got if r.shard == s) == list(range(sizes[s])) for s in range(shards))
        assert Counter((r.doc_id, r.text_crc32) for r in got) == Counter((i, zlib.crc32((t or "").encode())) for i, t in rows)

        def apart(of):
            by = {}
            for r, s in of:
                by.setdefault(r.group, Counter())[s] += 1
            many = [c for c in by.values() if sum(c.values()) > 1]
            return sum(sum(c.values()) for c in many), sum(sum(c.values()) - max(c.values()) for c in many)

        mine = apart((r, r.shard) for r in got)
        one = sharding.cut_links(placed).first()
        assert (one.linked, one.apart) == mine
        assert max(0, 60 - max(sizes.values())) <= mine[1] < 0.7 * apart((r, zlib.crc32(repr(r).encode()) % shards) for r in got)[1]


def test_sharding_gathers_a_large_group(spark):
    cells = spark.range(16).selectExpr("7L as group", "cast(id as int) as bucket", "cast(id as int) as shard", "50L as n").coalesce(1)  # 8 quotas
    done, report = sharding.propagate(cells, [100] * 16)
    hot = {r["shard"]: r["n"] for r in done.groupBy("shard").agg(F.sum("n").alias("n")).collect()}
    assert sum(hot.values()) == 800 and len(hot) <= 9 and len(report) > 6
    with pytest.warns(UserWarning, match="still ask"):
        sharding.propagate(cells, [100] * 16, 1)


def test_quality(spark, odd, none, docs):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    model = quality_cnn.fit_quality(docs, labels)
    truth = {r.doc_id: r.quality for r in labels.collect()}
    got = {r.doc_id: r.score for r in quality_cnn.score_quality(docs, model).collect()}
    fit = [(got[i], q) for i, q in truth.items() if i in got and zlib.crc32(str(i).encode()) % 4 == 2]  # held out
    assert len(fit) >= 5
    good, bad = [s for s, q in fit if q == 1], [s for s, q in fit if q == 0]
    assert np.mean([g > b for g in good for b in bad]) > 0.95
    rows = quality_cnn.score_quality(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r.score <= 1 for r in rows)
    assert quality_cnn.score_quality(none, quality_cnn.fit_quality(none, labels)).count() == 0
    assert {r.score for r in quality_cnn.score_quality(odd, quality_cnn.fit_quality(odd, labels.limit(0))).collect()} == {0.5}


def test_quality_pairs_equal_plain_filters():
    net = quality_cnn.ByteCnn().prepare()
    data = np.random.default_rng(1).integers(0, 256, 1000, np.uint8)
    sym = np.concatenate([data, np.full(quality_cnn.WIDTH - 1, quality_cnn.PAD)])
    act = net.params["bias"] + sum(net.params["table"][w][sym[w : w + 1000]] for w in range(quality_cnn.WIDTH))
    slow = np.stack([act[a : a + quality_cnn.CELL].max(0) for a in range(0, 1000, quality_cnn.CELL)])
    assert np.allclose(slow, net.cell_tops(data), atol=1e-4)
    for cells in range(1, 40):
        starts = quality_cnn.chunk_starts(cells)
        seen = {s + k for s in starts for k in range(quality_cnn.CELLS_IN_CHUNK)}
        assert set(range(cells)) <= seen and max(starts) < cells


def test_quality_gradient():
    rng = np.random.default_rng(3)
    net = quality_cnn.ByteCnn(seed=2)
    texts, y = [bytes(rng.integers(97, 110, n, np.uint8)) for n in (3, 700, 1500)], np.array([1, 0, 1], np.float32)

    def loss():
        out = 0.0
        for t, label in zip(texts, y, strict=True):
            p = net.prepare().score(np.frombuffer(t, np.uint8))
            out -= np.log(p if label else 1 - p)
        return out / len(y)

    grads = net._gradients(texts, y)
    for name in ("out", "bias", "b"):
        for k in range(0, len(net.params[name]), 7):
            kept, e = net.params[name][k], 1e-2
            net.params[name][k] = kept + e
            up = loss()
            net.params[name][k] = kept - e
            down = loss()
            net.params[name][k] = kept
            assert abs((up - down) / (2 * e) - grads[name][k]) < 2e-2 * max(1, abs(grads[name][k])) + 5e-3


def test_bpe(odd, none, docs):
    from tokenizers import Tokenizer

    real = Tokenizer.from_file(tokenizer_path())
    rnd = random.Random(4)
    units = ["a", "b", " ", "  ", "\n", "'s", "é", "漢", "😀", "<|endoftext|>", "1", "²", "!", "\x1c", "\u0085", "‍"]
    texts = ["".join(rnd.choice(units) for _ in range(rnd.randint(0, 40))) for _ in range(800)] + ["a" * 3000, "aaaaa", ""]
    mine = bpe.PairIndexBpe(open(tokenizer_path(), encoding="utf-8").read())
    ids, at = mine.encode(texts)
    back = mine.decode(ids, at)
    for k, (text, e) in enumerate(zip(texts, real.encode_batch(texts, add_special_tokens=False), strict=True)):
        assert ids[at[k] : at[k + 1]].tolist() == e.ids
        assert back[k].decode() == real.decode(e.ids, skip_special_tokens=False) == text
    rows = bpe.encode_texts(odd, tokenizer_path()).collect()
    assert len(rows) == len(ODD) and all(r.decoded == (dict(ODD)[r.doc_id] or "") for r in rows)
    assert bpe.encode_texts(none, tokenizer_path()).count() == 0
    for r in QUERIES["op5_bpe"](docs.sparkSession, SF).limit(20).collect():
        e = real.encode(docs.filter(F.col("doc_id") == r.doc_id).first().text, add_special_tokens=False)
        assert r.ids_sha256 == hashlib.sha256(np.array(e.ids, "<u4").tobytes()).hexdigest()


def test_bpe_refuses_what_it_does_not_do():
    spec = json.loads(open(tokenizer_path(), encoding="utf-8").read())
    bpe.check_spec(spec)
    for change in ({"normalizer": {"type": "NFC"}}, {"pre_tokenizer": {"type": "Whitespace"}}, {"added_tokens": [spec["added_tokens"][0] | {"lstrip": True}]}, {"model": spec["model"] | {"ignore_merges": True}}):
        with pytest.raises(ValueError):
            bpe.check_spec(spec | change)
    with pytest.raises(ValueError):
        bpe.PairIndexBpe(open(tokenizer_path("word_bpe_49k.json"), encoding="utf-8").read())


def test_chat_round_trip_and_spans():
    rnd = random.Random(2)
    bits = [*chat.CONTROLS, "\\", "a", " ", "\n", "é", "b", "="]
    for _ in range(400):
        turns = [(rnd.choice(["user", "assistant", "system", "", "to\\ol[/ROLE]"]), "".join(rnd.choice(bits) for _ in range(rnd.randint(0, 9)))) for _ in range(rnd.randint(0, 9))]
        text = chat.instruct_template(turns)
        assert chat.parse_instruct(text) == turns
        spans = chat.Spans(chat.instruct_template, window=4)
        whole = spans.out
        for role, said in turns:
            added, a, b = spans.add(role, said)
            whole += added
            assert chat.unescape(added[a:b]) == said
        assert whole == text and spans.rewrites == 0


def test_chat_finds_rewritten_history():
    spans = chat.Spans(lambda turns: f"[{len(turns)} turns]" + "".join(t for _, t in turns))
    for k in range(3):
        spans.add("user", f"u{k}")
    assert spans.rewrites > 0


def test_chat_query(spark):
    got = {r.conv_id: r for r in QUERIES["op6_chat_format"](spark, SF).collect()}
    rows = spark.read.parquet(f"{SF}/conversations.parquet").orderBy("conv_id", "turn").collect()
    for conv in {r.conv_id for r in rows}:
        turns = [(r.role, r.text or "") for r in rows if r.conv_id == conv]
        loss = "".join(t for role, t in turns if role == "assistant")
        assert got[conv].n_turns == len(turns) and got[conv].loss_chars == len(loss)
        assert got[conv].turns_sha256 == hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in turns).encode()).hexdigest()
        assert got[conv].loss_sha256 == hashlib.sha256(loss.encode()).hexdigest()
        assert got[conv].formatted_chars == len(chat.instruct_template(turns)) and got[conv].rewrites == 0
    assert got[-1].loss_chars == len("</s>[INST] ok [/INST]")
    odd = spark.createDataFrame([(None, None, None, None, 1), (None, 1, "user", "x", 1), (5, 2, "assistant", "y" * 50, 1), (5, 2, "assistant", "y" * 50, 1), *((6, k, "assistant", f"t{k}", 1) for k in range(100))], "conv_id long, turn long, role string, text string, n_turns int")
    out = {r.conv_id: r for r in chat.format_conversations(odd).collect()}
    assert out[None].n_turns == 2 and out[5].n_turns == 2 and out[5].loss_chars == 100
    assert out[6].n_turns == 100 and out[6].rewrites == 0 and out[6].formatted == chat.instruct_template([("assistant", f"t{k}") for k in range(100)])
    assert "".join(chat.unescape(out[6].formatted[a:b]) for a, b in out[6].loss_spans) == "".join(f"t{k}" for k in range(100))
    assert chat.format_conversations(odd.limit(0)).count() == 0


def test_chat_keeps_true_prefixes(spark):
    rows = [(c, k, "assistant" if k % 2 else "user", f"{c}t{k}.", 1) for c, n in ((1, 10), (2, 100), (3, 31)) for k in range(n)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, n_turns int")
    said = {c: [(r, t) for i, _, r, t, _ in rows if i == c] for c in (1, 2, 3)}

    def last_thirty(turns):
        return "".join(f"<{r}|{t}>" for r, t in turns[-30:])

    def numbered(turns):
        return "".join(f"<{r}|{k}:{t}>" for k, (r, t) in enumerate(turns))

    def summary(turns):
        return (f"(early {len(turns[:-30])})" if len(turns) > 30 else "") + "".join(f"<{r}|{t}>" for r, t in turns[-30:])

    def parse(text):
        return [tuple(x.split("|")) for x in re.findall(r"<(.*?)>", text)]

    for render, rewrites in ((last_thirty, True), (numbered, False), (summary, True)):
        out = {r.conv_id: r for r in chat.format_conversations(df, render, parse, str).collect()}
        short = {r.conv_id: r for r in chat.format_conversations(df, render, parse, str, keep=False).collect()}
        for c, turns in said.items():
            r = out[c]
            assert r.formatted == render(turns) and r.formatted_chars == len(r.formatted)
            assert (r.rewrites > 0) == (rewrites and len(turns) > 30), (render, c)
            shown = turns if render is numbered else turns[-30:]
            loss = [t for role, t in shown if role == "assistant"]
            assert [r.formatted[a:b] for a, b in r.loss_spans] == loss and r.loss_chars == len("".join(loss))
            assert r.n_turns == len(shown) and short[c].loss_sha256 == r.loss_sha256 == hashlib.sha256("".join(loss).encode()).hexdigest()
            assert (short[c].turns_sha256, short[c].rewrites, short[c].formatted_chars) == (r.turns_sha256, r.rewrites, r.formatted_chars)


def test_chat_reads_the_finished_text(spark):
    """What is told comes from the text alone: another text under the same id tells something else."""
    rows = [(1, k, "assistant" if k % 2 else "user", f"t{k}", 1) for k in range(60)]
    made = chat.render_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, n_turns int"))
    first = chat.read_back(made).first()
    assert (first.n_turns, first.loss_chars, first.rewrites) == (60, sum(len(f"t{k}") for k in range(1, 60, 2)), 0)
    other = made.withColumn("formatted", F.lit(chat.instruct_template([("user", "x"), ("assistant", "yy")]))).withColumn("loss_spans", F.array(F.array(F.lit(0).cast("long"), F.lit(3).cast("long"))))
    got = chat.read_back(other).first()
    assert (got.n_turns, got.loss_chars) == (2, 3) and got.loss_sha256 == hashlib.sha256(b"<s>").hexdigest()


def brute_components(rows, linked):
    root = {i: i for i, _ in rows}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, x in rows:
        for b, y in rows:
            if a < b and linked(x, y):
                p, q = top(a), top(b)
                root[max(p, q)] = min(p, q)
    return {i: top(i) for i, _ in rows}


def shingles(text):
    w = words((text or "").translate({c: c + 32 for c in range(65, 91)}))
    return frozenset(tuple(w[k : k + 4]) for k in range(len(w) - 3)) if len(w) > 3 else frozenset([tuple(w)] if w else [])


def test_ngram_join(spark, odd, none, docs):
    rnd = random.Random(8)
    base = [[f"w{rnd.randint(0, 400)}" for _ in range(n)] for n in (5, 6, 9, 12, 20, 40, 90, 200)]
    texts = []
    for b in base:  # copies with a growing number of changes, around the threshold
        for changes in (0, 0, 1, 1, 1, 2, 2, 3, 4, 6):
            own = list(b)
            for _ in range(changes):
                own[rnd.randrange(len(own))] = f"x{rnd.randint(0, 9)}"
            texts.append(" ".join(own))
    planted = spark.createDataFrame(list(enumerate(texts, 10_000)), "doc_id long, text string")
    both = docs.select("doc_id", "text").union(planted)
    rows = [(r.doc_id, shingles(r.text)) for r in both.collect()]
    truth = brute_components(rows, lambda x, y: bool(x) and bool(y) and 100 * len(x & y) >= 85 * len(x | y))
    got = {r.doc_id: r for r in ngram_join.jaccard_components(both).collect()}
    sizes = dict(rows)
    assert all(got[i].component_id == truth[i] and got[i].n_shingles == len(sizes[i]) for i in truth) and len(got) == len(rows)
    assert len(set(truth.values())) < len(truth)
    few = ngram_join.jaccard_components(odd).collect()
    by = {r.doc_id: r.component_id for r in few}
    assert len(few) == len(ODD) and by[9] == 8 and by[11] == 10 and by[2] == 2 and by[None] is None and by[1] == 1
    assert ngram_join.jaccard_components(none).count() == 0


@pytest.mark.parametrize("hot", [64, 3])
def test_ngram_join_without_ids_and_with_common_keys(spark, hot, monkeypatch):
    """Sets that only rows without an id have still link others, and salted keys lose nothing."""
    monkeypatch.setattr(ngram_join, "HOT", hot)
    rnd = random.Random(31)
    base = [f"w{k}" for k in range(120)]
    rows = []
    for i in range(300):  # a large group of near copies
        own = list(base)
        for _ in range(rnd.choice([0, 1, 1, 2, 3, 5, 9])):
            own[rnd.randrange(120)] = f"x{rnd.randint(0, 50)}"
        rows.append((None if i % 3 == 0 else i + 5, " ".join(own)))
    chain = [f"c{k}" for k in range(100)]
    steps = [" ".join(f"d{k}" if k in changed else w for k, w in enumerate(chain)) for changed in ((), (10, 11, 12), (10, 11, 12, 50, 51, 52))]  # the ends link through the middle only
    rows += [(1, steps[0]), (None, steps[1]), (2, steps[2]), (None, "only rows without an id have this one"), (None, "only rows without an id have this one")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    numbered = list(enumerate(t for _, t in rows))
    truth = brute_components([(k, shingles(t)) for k, t in numbered], lambda x, y: 100 * len(x & y) >= 85 * len(x | y))
    name = {}
    for k, (i, _) in enumerate(rows):
        if i is not None:
            name[truth[k]] = min(i, name.get(truth[k], i))
    want = Counter((i, name.get(truth[k])) for k, (i, _) in enumerate(rows))
    assert truth[300] == truth[302] and name[truth[300]] == 1 and truth[303] == truth[304] and truth[303] not in name
    assert Counter((r.doc_id, r.component_id) for r in ngram_join.jaccard_components(df).collect()) == want


def test_ngram_plan_is_lossless():
    for band in range(30):
        for sets in (0, 10**3, 10**10):
            one, two, room = ngram_join.plan_band(band, sets)
            high = int(ngram_join.EDGES[band + 1]) - 1
            h = ngram_join.most_apart(high, high * 100 // 85)
            assert one + 2 * two == h + room >= h + 1


def test_ngram_sketches_bound_the_difference():
    """Sketches of any two lengths differ, at the shorter one, in no more bits than the sets in elements; wide ones tell unrelated long sets apart."""
    rng = np.random.default_rng(6)
    for m, n, common in ((900, 1100, 800), (1025, 2049, 900), (4000, 5000, 3900), (3000, 3100, 0), (80_000, 70_000, 60_000)):
        values = rng.integers(0, 1 << 63, m + n - common).astype(np.uint64)
        sets = values[:m], values[m - common :]
        wide = [np.frombuffer(ngram_join.wide_parity(v) or ngram_join.parity(v), np.uint64)[None] for v in sets]
        words = min(w.shape[1] for w in wide)
        apart = int(np.bitwise_count(ngram_join.folded(wide[0], words) ^ ngram_join.folded(wide[1], words)).sum())
        assert apart <= m + n - 2 * common
        if not common:
            assert apart > ngram_join.most_apart(m, n, 80, 100)
        narrow = ngram_join.folded(wide[0], ngram_join.BITS // 64)
        assert narrow.tobytes() == ngram_join.parity(sets[0])


def test_ngram_join_of_long_texts(spark):
    """Texts whose sets have sketches of several lengths, around the threshold, and ones that share only a passage."""
    rnd = random.Random(61)
    passage = [f"p{k}" for k in range(900)]
    texts = []
    for n in (1010, 1022, 2040, 3000):
        base = [f"b{n}x{k}" for k in range(n)]
        texts.append(" ".join(passage + base))
        for changes in (0, 1, 20, 36, 39, 42, 46, 60, 75, 79, 84, 90, 125):
            own = list(base)
            for _ in range(changes):
                own[rnd.randrange(n)] = f"y{rnd.random()}"
            texts.append(" ".join(own + [f"z{k}" for k in range(changes // 3)]))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    rows = [(i, shingles(t)) for i, t in enumerate(texts)]
    truth = brute_components(rows, lambda x, y: 100 * len(x & y) >= 85 * len(x | y))
    assert {r.doc_id: r.component_id for r in ngram_join.jaccard_components(df).collect()} == truth
    assert 4 < len(set(truth.values())) < len(texts)


@pytest.mark.parametrize("plan", [(8, 0, 2), (0, 4, 2), (4, 3, 4)])
def test_ngram_keys_meet(plan):
    rng = np.random.default_rng(5)
    h = plan[0] + 2 * plan[1] - plan[2]
    for _ in range(300):
        size = int(rng.integers(h + 1, 30))
        a = np.unique(rng.integers(1, 1 << 60, size, np.uint64))
        cut = int(rng.integers(0, h + 1))
        b = np.unique(np.concatenate([a[cut:], rng.integers(1, 1 << 60, h - cut, np.uint64)]))
        if len(np.setxor1d(a, b)) <= h:
            assert np.intersect1d(ngram_join._segment_keys(a, 3, plan), ngram_join._segment_keys(b, 3, plan)).size


def test_embeddings(spark):
    rng = np.random.default_rng(6)
    base = rng.normal(size=(30, 16))
    rows = []
    for k in range(240):
        v = base[k % 30] + rng.normal(size=16) * rng.choice([0, 0.02, 0.05, 0.1])
        rows.append((k, [float(x) for x in v.astype(np.float32)], k % 3 if k % 11 else None))
    rows += [(300, None, 1), (301, [0.0] * 16, 1), (302, [float("nan")] * 16, 1), (303, [None] * 16, 1), (304, [1.0, 0.0], 1), (305, [2.0, -0.0], 1), (306, [], 1), (307, [1e-300] * 16, 1), (308, [1e300] * 16, 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumn("node", F.lit("x"))
    got = {r.vec_id: r for r in embedding_dedup.near_duplicates(df, block=17).collect()}
    assert len(got) == len(rows)

    def good(v):
        return v and all(x is not None and np.isfinite(x) for x in v) and any(v)

    def linked(x, y):
        if x[1] is None or x[1] != y[1] or not good(x[0]) or not good(y[0]) or len(x[0]) != len(y[0]):
            return False
        a, b = (np.array(v[0]) / np.abs(v[0]).max() for v in (x, y))
        return a @ b / np.linalg.norm(a) / np.linalg.norm(b) >= 0.98

    items = [(i, (v, lab)) for i, v, lab in rows]
    truth = brute_components(items, linked)
    assert all(got[i].component_id == truth[i] and got[i].kept == (truth[i] == i) for i in truth)
    for i, x in items:
        assert got[i].n_links == sum(j != i and linked(x, y) for j, y in items), i
    twice = embedding_dedup.near_duplicates(df.union(df), block=17)
    assert twice.count() == 2 * len(rows) and all(got[r.vec_id].n_links == r.n_links for r in twice.collect())
    assert embedding_dedup.near_duplicates(df.limit(0)).count() == 0


def test_quantisation_bound():
    rng = np.random.default_rng(9)
    x = rng.normal(size=(200, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    q, s, near, err = embedding_dedup.quantise(x)
    product = (q.astype(int) @ q.astype(int).T) * s[:, None] * s[None]
    assert (np.abs(x @ x.T - product) <= near[:, None] * err[None] + err[:, None] + 1e-12).all()


def test_telephony(spark, odd, none):
    more = spark.createDataFrame([(100 + k, "é" * k + "text") for k in range(0, 900, 7)], "doc_id long, text string")
    both = odd.select("doc_id", "text").union(more)
    texts = dict(both.collect())
    for form in (None, telephony.MU_LAW, telephony.A_LAW, telephony.IMA):
        stored = telephony.store_texts(both, form)
        kept = {(r.doc_id, r.n_bytes): r for r in stored.collect()}
        rows = telephony.measure_stored(stored).collect()
        assert len(rows) == both.count()
        forms = set()
        for r in rows:
            raw = (texts[r.doc_id] or "").encode()
            payload = raw + b"\0" * (-len(raw) % 64 if raw else 64)
            assert (r.n_bytes, r.payload_bytes) == (len(raw), len(payload)) and r.payload_sha256 == hashlib.sha256(payload).hexdigest()
            media, pcm = kept[r.doc_id, r.n_bytes].media, kept[r.doc_id, r.n_bytes].pcm
            tag, rate, align, data = telephony.read_wav(media)
            forms.add(tag)
            assert rate == 8000 and tag == (telephony.form_of(payload) if form is None else form)
            assert data == payload if tag != telephony.IMA else telephony.ima_payload(data, align) == payload
            samples = len(payload) if tag != telephony.IMA else 2 * len(payload) + -(-len(payload) // 252)
            assert len(pcm) == 4 * samples and f"samples={samples};" in r.feature
            assert r.tail_crc32 == zlib.crc32(payload[-64:]) and (r.media_bytes, r.media_sha256) == (len(media), hashlib.sha256(media).hexdigest())
        assert forms == ({telephony.MU_LAW, telephony.A_LAW, telephony.IMA} if form is None else {form})
    assert telephony.measure_stored(telephony.store_texts(none)).count() == 0


def test_telephony_codecs(spark):
    mu, a = telephony.EXPAND[telephony.MU_LAW], telephony.EXPAND[telephony.A_LAW]
    assert (mu[0], mu[128], mu[255], mu[127]) == (-32124, 32124, 0, 0) and (a[0x55], a[0xD5], a[0xAA], a[0x2A]) == (-8, 8, 32256, -32256)
    assert len(set(mu.tolist())) == 255 and len(set(a.tolist())) == 256

    def slow(block):
        value, at = int.from_bytes(block[:2], "little", signed=True), min(88, block[2])
        out = [value]
        for byte in block[4:]:
            for c in (byte & 15, byte >> 4):
                step = int(telephony.IMA_STEPS[at])
                change = (step >> 3) + (step if c & 4 else 0) + (step >> 1 if c & 2 else 0) + (step >> 2 if c & 1 else 0)
                value = max(-32768, min(32767, value - change if c & 8 else value + change))
                at = max(0, min(88, at + int(telephony.IMA_MOVES[c])))
                out.append(value)
        return out

    data = np.random.default_rng(2).integers(0, 256, 36 * 5 + 14, np.uint8).tobytes()
    want = sum((slow(data[k : k + 36]) for k in range(0, len(data), 36)), [])
    assert telephony.decode_ima(data, 36).tolist() == want
    assert telephony.decode_ima(b"", 36).tolist() == []
    media = [(1, telephony.wav(data, telephony.IMA, bits=4, align=36)), (2, telephony.wav(b"ab", telephony.A_LAW)), (3, None)]
    out = {r.media_id: r.pcm for r in telephony.decode_media(spark.createDataFrame(media, "media_id long, media binary")).collect()}
    assert len(out[1]) == 4 * len(want) and out[3] is None
    assert telephony.resample(np.array([0, 10], np.int16), 2).tolist() == [0, 5, 10, 10]
    assert telephony.resample(np.array([0, 10, 20], np.int16), 1, 2).tolist() == [0]


def test_mixing(spark, odd, none):
    rows = [(k, "w " * (k % 50 + 1), None if k % 10 == 9 else f"s{min(k % 10, 5)}") for k in range(5000)]
    out = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    total = sum(r.size for r in out)
    targets = {r.source: (r.source_size, r.target) for r in out}
    assert abs(sum(t for _, t in targets.values()) - total) < 1e-6 * total
    names = sorted(s for s in targets if s) + [None]
    weight = {s: k % 3 + 1 for k, s in enumerate(names)}
    level = max(t / weight[s] for s, (_, t) in targets.items())
    for s, (size, target) in targets.items():
        assert abs(target - min(3 * size, level * weight[s])) < 1e-6 * total
        assert abs(sum(r.taken for r in out if r.source == s) - target) <= 50
    assert all(r.taken <= 3 * r.size for r in out)
    again = {r.doc_id: r.taken for r in mixing.mix(spark.createDataFrame(rows[::-1], "doc_id long, text string, source string")).collect()}
    assert all(again[r.doc_id] == r.taken for r in out)
    few = mixing.mix(odd).collect()
    assert len(few) == len(ODD) and {r.size for r in few if r.doc_id in (1, 2, 3)} == {0}
    assert mixing.mix(none).count() == 0


def slow_mix(rows):
    """The rule row by row: (source, doc_id, size) in order of odds, taken while that brings the source's words nearer to its rest."""
    by = {}
    for i, size, source in rows:
        by.setdefault(source, []).append((i, size))
    names = sorted(s for s in by if s is not None) + [None] * (None in by)
    weight, total = {s: k % 3 + 1 for k, s in enumerate(names)}, {s: sum(x for _, x in by[s]) for s in names}
    target, left, open_ = {}, sum(total.values()), set(names)
    while open_:
        level = left / sum(weight[s] for s in open_)
        over = [s for s in open_ if level * weight[s] > 3 * total[s]]
        for s in over or list(open_):
            target[s] = 3 * total[s] if over else level * weight[s]
            open_.discard(s)
            left -= target[s] if over else 0
    out = Counter()
    for s in names:
        if not total[s]:
            out.update((s, i, 0) for i, _ in by[s])
            continue
        mean, whole = total[s] / sum(x > 0 for _, x in by[s]), int(target[s] // total[s])
        rest, upto = target[s] - whole * total[s], 0

        def odds(i, x, mean=mean):
            u = (int(hashlib.md5(f"{'' if i is None else i}:{mixing.SEED}".encode()).hexdigest()[:13], 16) + 0.5) / (1 << 52)
            return u / (1 - u) / (x / mean) ** 0.5

        for _, i, x in sorted(((odds(i, x), -1 if i is None else i, x) for i, x in by[s] if x)):
            upto += x
            out[s, None if i < 0 else i, (whole + (2 * upto - x <= 2 * rest)) * x] += 1
        out.update((s, i, 0) for i, x in by[s] if not x)
    return out


def test_mixing_row_by_row(spark):
    """Ties in plenty: rows without an id, repeated ids, one source without words, one with a third of all rows."""
    rnd = random.Random(9)
    rows = [(None, rnd.choice([0, 1, 5, 5, 5]), "s1") for _ in range(900)] + [(rnd.randint(0, 40), rnd.choice([3, 7]), "s2") for _ in range(300)]
    rows += [(k, rnd.randint(0, 60), rnd.choice(["a", "b", None, "z"])) for k in range(1500)] + [(k, 0, "blank") for k in range(5)]
    df = spark.createDataFrame([(i, "w " * n, s) for i, n, s in rows], "doc_id long, text string, source string")
    for run in (mixing.RUN, 7):
        mixing.RUN, was = run, mixing.RUN
        try:
            got = Counter((r.source, r.doc_id, r.taken) for r in mixing.mix(df).collect())
        finally:
            mixing.RUN = was
        assert got == slow_mix(rows)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_against_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{SF}/documents.parquet'")
    want = con.sql(ORACLES[name]).df()
    got = QUERIES[name](spark, SF).toPandas()[list(want.columns)]
    order = list(want.columns)
    a, b = (x.sort_values(order).astype(object).where(x.sort_values(order).notna(), None).values.tolist() for x in (got, want))
    assert len(a) == len(b)
    for x, y in zip(a, b, strict=True):
        assert all(p == q or abs(p - q) < 1e-9 for p, q in zip(x, y, strict=True)), (x, y)


def test_pipeline(spark):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    was = docs
    for name, stage in cp.STAGES[:-1]:
        out = stage(spark, was, SF)
        assert out.columns == list(cp.COLUMNS), name
        out = out.cache()
        assert 0 < out.count()
        if name == "n-gram Jaccard join":
            rows = [(r.doc_id, shingles(r.text)) for r in was.collect()]
            truth = brute_components(rows, lambda x, y: bool(x) and bool(y) and 100 * len(x & y) >= 85 * len(x | y))
            assert sorted(r.doc_id for r in out.collect()) == sorted(set(truth.values()))
        was = out
    want = Counter(r.doc_id for r in was.collect())
    assert Counter(r.doc_id for r in cp.run(spark, SF).collect()) == want


def wide_shingles(text, size=5):
    w = words((text or "").translate({c: c + 32 for c in range(65, 91)}))
    return frozenset(tuple(w[k : k + size]) for k in range(len(w) - size + 1)) if len(w) >= size else frozenset([tuple(w)] if w else [])


def test_pipeline_near_duplicates_five_words(spark):
    import corpus_pipeline as cp

    rnd = random.Random(12)
    rows = []
    for n, most in ((12, 2), (20, 2), (60, 3), (100, 4), (150, 5), (300, 8), (1000, 30)):
        base = [f"w{n}_{k}" for k in range(n)]
        for changes in range(most + 1):
            for _ in range(2):
                own = list(base) if rnd.random() < 0.5 else [*base[:-1], f"e{rnd.randint(0, 2)}"]
                for at in rnd.sample(range(n), changes):
                    own[at] = f"x{rnd.randint(0, 10**6)}"
                rows.append((len(rows), " ".join(own)))
    two = [f"v{k}" for k in range(100)]
    rows += [(5000, " ".join(two)), (5001, " ".join(w if k not in (30, 60) else "y" for k, w in enumerate(two)))]  # .811 of five words, .848 of four
    truth = brute_components([(i, wide_shingles(t)) for i, t in rows], lambda x, y: 100 * len(x & y) >= 80 * len(x | y))
    assert truth != brute_components([(i, shingles(t)) for i, t in rows], lambda x, y: 100 * len(x & y) >= 85 * len(x | y)) and truth[5001] == 5000
    assert len(set(truth.values())) > 20

    def stage(rows):
        df = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
        return cp.near_duplicates(spark, df, SF).collect()

    assert sorted(r.doc_id for r in stage(rows)) == sorted(set(truth.values()))
    text, other, third = (" ".join(f"{c}{k}" for k in range(50)) for c in "pqr")
    odd = [(None, text), (None, text), (None, other), (7, other), (9, third), (9, third), (9, "quite another text than the rest of nine has"), (None, text + " end"), (3, third + " end"), (11, text + " of an own"), (12, "alone here with not many words")]
    got = Counter((r.doc_id, r.text) for r in stage(odd))
    assert got == Counter([(11, text + " of an own"), (7, other), (3, third + " end"), (9, "quite another text than the rest of nine has"), (12, "alone here with not many words")])
    nulls = Counter((r.doc_id, r.text) for r in stage([(None, text)] * 3 + [(None, other)]))
    assert nulls == Counter([(None, text), (None, other)])


def test_pipeline_mix_counts_rows_without_an_id_of_their_own(spark):
    """Rows without an id and rows that share one are mixed like any other; equal rows stand for each other."""
    import corpus_pipeline as cp

    rows = [(None, f"n{k} " * (k % 7 + 1), "en", "a", 5) for k in range(60)] + [(3, f"t{k} " * (k % 5 + 1), "en", "b", 5) for k in range(40)]
    rows += [(100 + k, f"u{k} " * (k % 9 + 1), "en", "c" if k % 2 else "a", 5) for k in range(80)] + [(None, "same same same", "en", "b", 5)] * 6
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = Counter((r.doc_id, r.text, r.source) for r in cp.mix(spark, df, SF).collect())
    given = Counter((i, t, s) for i, t, _, s, _ in rows)
    assert set(got) <= set(given) and all(n <= 3 * given[x] for x, n in got.items())
    words_of = lambda kept, source: sum(n * len(t.split()) for (_, t, s), n in kept.items() if s == source)
    total = sum(words_of(given, s) for s in "abc")
    targets = {s: min(3 * words_of(given, s), total * w / 6) for s, w in zip("abc", (1, 2, 3), strict=True)}
    assert all(targets[s] < 3 * words_of(given, s) for s in "abc")
    assert all(abs(words_of(got, s) - targets[s]) <= 9 for s in "abc")
    again = Counter((r.doc_id, r.text, r.source) for r in cp.mix(spark, df.orderBy("text"), SF).collect())
    assert again == got


@pytest.mark.parametrize("numer,denom", [(80, 100), (85, 100), (95, 100)])
def test_ngram_bands_hold_every_threshold(numer, denom):
    for band in range(30):
        one, two, room = ngram_join.plan_band(band, 10**6, numer=numer, denom=denom)
        high = int(ngram_join.EDGES[band + 1]) - 1
        assert one + 2 * two == ngram_join.most_apart(high, high * denom // numer, numer, denom) + room
        assert high * denom // numer < ngram_join.EDGES[band + 2]


def test_pipeline_language_drops_foreign_and_noise(spark, docs):
    import corpus_pipeline as cp

    rnd = random.Random(3)
    alphabets = [[chr(c) for c in range(0x430, 0x450)], [chr(c) for c in range(0x4E00, 0x5E00)], [chr(c) for c in range(0x627, 0x64A)], [chr(c) for c in range(97, 123)]]
    planted = []
    for letters in alphabets:
        for n in (10, 40, 300):
            for _ in range(10):
                planted.append((1_000_000 + len(planted), " ".join("".join(rnd.choice(letters) for _ in range(rnd.randint(3, 9))) for _ in range(n)), None, "planted", 0))
    both = docs.select(*cp.COLUMNS).union(spark.createDataFrame(planted, docs.select(*cp.COLUMNS).schema))
    kept = Counter(r.doc_id for r in cp.language(spark, both, SF).collect())
    assert not [i for i in kept if i >= 1_000_000]
    lettered = Counter(r.doc_id for r in docs.collect() if any(c.isalpha() for c in r.text or ""))
    assert kept == lettered
