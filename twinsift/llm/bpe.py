"""BPE encoding and decoding by a pair occurrence index.

The distinct words of a batch lie one after another in arrays of symbols and
links. Each mergeable pair owns the list of all places where it occurs; active
ranks are taken in ascending order, every place of the pair is merged at once
with numpy, and the lists of the pairs that arise left and right are updated.
A merge can only give rise to pairs of a higher rank, so one ascending sweep is
the same as the word-by-word rule.

Defined cases: null text is empty and has no tokens; repeated rows give
repeated results; further columns are ignored; the text of the special token is
encoded as that token. The word index is reset when it exceeds WORDS entries,
so memory follows the batch and not the corpus. A vocabulary file that asks for a normalizer, another split or tokens with
flags is refused.
"""

import gc
import hashlib
import heapq
import json

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from twinsift.functions.shipping import by_value
from twinsift.llm.common import slices, small_batches

by_value(__name__)

WORDS = 150_000
# Fixed value: how the public vocabulary's pre-tokenizer splits text.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_END, _DEAD = -1, -2


def printable_bytes() -> dict[str, int]:
    """The visible character that stands for each byte in vocabulary files."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in shown]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(rest)}


def check_spec(spec: dict) -> None:
    """Refuses a vocabulary file that asks for anything but what is done here, rather than encode it otherwise than its library."""
    model, before = spec["model"], spec.get("pre_tokenizer") or {}
    wrong = [k for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "fuse_unk", "byte_fallback", "ignore_merges") if model.get(k)]
    wrong += [k for k in ("normalizer", "post_processor") if spec.get(k)]
    if model.get("type") != "BPE":
        wrong.append("model type")
    if before.get("type") != "ByteLevel" or before.get("add_prefix_space") or not before.get("use_regex", True):
        wrong.append("pre_tokenizer")
    if (spec.get("decoder") or {}).get("type") != "ByteLevel":
        wrong.append("decoder")
    wrong += [f"{t['content']}: {k}" for t in spec.get("added_tokens", []) for k in ("single_word", "lstrip", "rstrip", "normalized") if t.get(k)]
    if wrong:
        raise ValueError(f"the vocabulary file asks for what this encoder does not do: {', '.join(wrong)}")


class _Numbered(dict):
    def __missing__(self, word):
        self[word] = n = len(self)
        return n


class PairIndexBpe:
    def __init__(self, spec: str):
        model = json.loads(spec)
        check_spec(model)
        as_byte = printable_bytes()
        vocab = model["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in model["added_tokens"]}
        blobs = {i: bytes(as_byte[c] for c in token) for token, i in vocab.items()} | {i: s.encode() for s, i in self.special.items()}
        size = max(blobs) + 1
        self.token_len = np.array([len(blobs.get(i, b"")) for i in range(size)], np.int64)
        self.token_at = np.concatenate([[0], np.cumsum(self.token_len)])
        self.token_blob = np.frombuffer(b"".join(blobs.get(i, b"") for i in range(size)), np.uint8)
        self.byte_id = np.zeros(256, np.int32)
        for c, b in as_byte.items():
            self.byte_id[b] = vocab[c]
        pairs = [(vocab[a], vocab[b], vocab[a + b]) for a, b in model["model"]["merges"]]
        self.left, self.right, self.new = (np.array(x, np.int64) for x in zip(*pairs, strict=True))
        keys = self.left << 32 | self.right
        order = np.argsort(keys)
        self.keys, self.ranks = keys[order], order
        self.split = regex.compile(PATTERN)
        self.apart = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.reset()

    def reset(self) -> None:
        self.words, self.flat = _Numbered(), np.zeros(0, np.int32)
        self.starts = self.lens = np.zeros(0, np.int64)
        for token, i in self.special.items():
            self.words[("special", token)]
            self._append(np.array([i], np.int32), np.array([1]))

    def _append(self, flat, lens):
        ends = len(self.flat) + np.cumsum(lens)
        self.starts, self.lens = np.concatenate([self.starts, ends - lens]), np.concatenate([self.lens, lens])
        self.flat = np.concatenate([self.flat, flat])

    def rank_of(self, a, b):
        """Rank of each pair, or -1."""
        key = a.astype(np.int64) << 32 | b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where((self.keys[at] == key) & (a >= 0) & (b >= 0), self.ranks[at], -1)

    def encode_words(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words one after another, and their number in each word."""
        lens = np.fromiter(map(len, words), np.int64, len(words))
        ends = np.cumsum(lens + 1)
        sym = np.full(int(ends[-1]) + 1 if len(words) else 1, _END, np.int32)  # 12 bytes a byte of text in the three arrays
        inside = np.ones(len(sym), bool)
        inside[-1] = False
        inside[ends - 1] = False
        sym[inside] = self.byte_id[np.frombuffer(b"".join(words), np.uint8)]
        nxt, prv = np.arange(1, len(sym) + 1, dtype=np.int32), np.arange(-1, len(sym) - 1, dtype=np.int32)
        places, heap = {}, []

        def note(at, rank):
            order = np.argsort(rank, kind="stable")
            at, rank = at[order], rank[order]
            cuts = np.flatnonzero(np.diff(rank)) + 1
            for r, part in zip(rank[np.concatenate([[0], cuts])].tolist(), np.split(at, cuts), strict=True):
                if r in places:
                    places[r].append(part)
                else:
                    places[r] = [part]
                    heapq.heappush(heap, r)

        at = np.flatnonzero(inside)
        table = self.rank_of(np.repeat(self.byte_id, 256).astype(np.int64), np.tile(self.byte_id, 256).astype(np.int64))
        number = np.zeros(int(self.byte_id.max()) + 1, np.int64)
        number[self.byte_id] = np.arange(256)
        at = at[sym[at + 1] >= 0]
        rank = table[number[sym[at]] * 256 + number[sym[at + 1]]]
        if (rank >= 0).any():
            note(at[rank >= 0], rank[rank >= 0])
        while heap:
            r = heapq.heappop(heap)
            parts = places.pop(r)
            a, b, new = self.left[r], self.right[r], self.new[r]
            p = parts[0] if len(parts) == 1 else np.unique(np.concatenate(parts))
            p = p[sym[p] == a]
            p = p[sym[nxt[p]] == b]
            if not len(p):
                continue
            if a == b:  # of places that overlap, every second one from the left
                p = np.unique(p)
                linked = np.concatenate([[False], nxt[p[:-1]] == p[1:]])
                first = np.maximum.accumulate(np.where(linked, 0, np.arange(len(p))))
                p = p[(np.arange(len(p)) - first) % 2 == 0]
            gone = nxt[p]
            after = nxt[gone]
            sym[p], sym[gone] = new, _DEAD
            nxt[p], prv[after] = after, p
            before = prv[p]
            before = np.where(before < 0, len(sym) - 1, before)
            put = np.concatenate([before, p])
            rank = self.rank_of(sym[put], sym[nxt[np.minimum(put, len(sym) - 2)]])
            rank[: len(p)] = np.where(before == len(sym) - 1, -1, rank[: len(p)])
            ok = rank >= 0
            if ok.any():
                note(put[ok], rank[ok])
        alive = sym >= 0
        upto = np.concatenate([[0], np.cumsum(alive)])
        return sym[alive].astype(np.int32), upto[ends] - upto[ends - lens - 1] if len(words) else np.zeros(0, np.int64)

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts one after another, and the offsets of the texts."""
        if len(self.words) > WORDS:
            self.reset()
        known, number, found = len(self.words), self.words.__getitem__, []
        for text in texts:
            if self.apart is not None and any(s in text for s in self.special):
                own = []
                for k, part in enumerate(self.apart.split(text)):
                    own += [number(("special", part))] if k % 2 else map(number, self.split.findall(part))
            else:
                own = list(map(number, self.split.findall(text)))
            found.append(np.array(own, np.int64))
        if len(self.words) > known:
            added = list(self.words)[known:]
            self._append(*self.encode_words([w.encode() for w in added]))
        words = np.concatenate(found) if found else np.zeros(0, np.int64)
        lens = self.lens[words]
        ids = self.flat[spread(self.starts[words], lens)]
        upto = np.concatenate([[0], np.cumsum(lens)])
        return ids, upto[np.concatenate([[0], np.cumsum([len(x) for x in found])]).astype(np.int64)]

    def decode(self, ids: np.ndarray, offsets: np.ndarray) -> list[bytes]:
        """UTF-8 of the texts; bytes that are no UTF-8 become the replacement character."""
        lens = self.token_len[ids]
        data = self.token_blob[spread(self.token_at[ids], lens)].tobytes()
        ends = np.concatenate([[0], np.cumsum(lens)])[offsets].tolist()
        return [data[a:b].decode("utf-8", "replace").encode() for a, b in zip(ends, ends[1:], strict=False)]


def spread(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """All positions of the runs that begin at starts, one after another."""
    total = int(lens.sum())
    upto = np.cumsum(lens)
    return np.arange(total) + np.repeat(starts - (upto - lens), lens)


_OUT = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32())), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded", pa.string()), ("decoded_sha256", pa.string())])


def encode_texts(docs: DataFrame, tokenizer_path: str, keep: bool = True, keep_ids: bool = True) -> DataFrame:
    """Token ids of each text and the text decoded from them, with digests of both; keep=False leaves the decoded text out, keep_ids=False the ids.

    The vocabulary file (a few MB, fixed) is read once on the driver and travels with the tasks."""
    spark = docs.sparkSession
    small_batches(spark)
    with open(tokenizer_path, encoding="utf-8") as f:
        spec = spark.sparkContext.broadcast(f.read())
    schema = "doc_id long, ids array<int>, n_tokens long, ids_sha256 string, decoded string, decoded_sha256 string"

    def run(batches):
        bpe = PairIndexBpe(spec.value)
        gc.collect()
        for piece in slices(batches, 4 << 20):
            texts = [t or "" for t in piece.column(1).to_pylist()]
            ids, offsets = bpe.encode(texts)
            n = np.diff(offsets)
            id_sums, texts_back = [], []
            for k in range(0, len(texts), 512):
                o = offsets[k : k + 513]
                part = ids[o[0] : o[-1]]
                texts_back += bpe.decode(part, o - o[0])
                id_sums += [hashlib.sha256(part[a:b].astype("<u4").tobytes()).hexdigest() for a, b in zip((o - o[0]).tolist(), (o[1:] - o[0]).tolist(), strict=False)]
                if not keep:
                    texts_back[k:] = [hashlib.sha256(x).hexdigest() for x in texts_back[k:]]
            sums = [hashlib.sha256(x).hexdigest() for x in texts_back] if keep else texts_back
            lists = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(ids, pa.int32())) if keep_ids else pa.nulls(len(texts), pa.list_(pa.int32()))
            back = pa.array([x.decode() for x in texts_back] if keep else [None] * len(texts), pa.string())
            yield pa.RecordBatch.from_arrays([piece.column(0), lists, pa.array(n, pa.int64()), pa.array(id_sums, pa.string()), back, pa.array(sums, pa.string())], schema=_OUT)

    return docs.select(docs["doc_id"].cast("long"), docs["text"]).mapInArrow(run, schema)
