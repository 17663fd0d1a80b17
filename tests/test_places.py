"""Counted corruptions: n-grams and hashes of many places at once, and the pass over the texts against the join."""

import random
from collections import Counter

import pytest

from twinsift.augment import places, policy

TEXTS = ["abcabcabc", "", "a", "ab\x00cd ab\x00cd", "Ünï ünï \U0001d4b3x\U0001d4b3x ", "abcde" * 3000]


@pytest.mark.parametrize("n", [3, 5])
def test_ngrams(n):
    for texts in (TEXTS, [t for t in TEXTS if "\x00" not in t], ["".join(map(chr, range(1, 9000))), "xyzxyz"]):
        got = dict(zip(*places.ngrams([t for t in texts if t], n), strict=True))
        assert got == Counter(t[i : i + n] for t in texts for i in range(len(t) - n + 1))


def test_places_are_those_of_the_hash():
    texts = [(0, 120), (7, 0), (123456789, 1105), (10**18, 11)]
    for tail in ("char_insert_ngram-g", "a-tail-that-is-too-long-for-a-block-of-sixty-four-bytes"):
        assert places.chosen(texts, 4, tail, 1000) == [[i for i in range(4, n) if places.number(f"{k}-{i}-{tail}") % 10000 < 1000] for k, n in texts]


@pytest.mark.parametrize("name", ["char_insert_ngram", "char_sub_ngram"])
def test_pass_over_texts_equals_the_join(spark, monkeypatch, name):
    rnd = random.Random(2)
    rows = [(i, "en", "".join(rnd.choice("abcABC éÉσΣ ") for _ in range(rnd.randint(0, 300)))) for i in range(40)] + [(50, None, None), (51, "de", "")]
    docs = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    one = sorted(map(tuple, policy.corrupt_counted(docs, name, 0.3, n=4).collect()))
    assert sum(t != dict((i, x) for i, _, x in rows)[k] for k, _, t in one) > 20
    monkeypatch.setattr(policy, "SENT", 0)
    assert one == sorted(map(tuple, policy.corrupt_counted(docs, name, 0.3, n=4).collect()))
