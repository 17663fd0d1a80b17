"""Counting character n-grams and hashing places of texts, many at a time."""

import hashlib
import math
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from twinsift.functions.shipping import by_value

by_value(__name__)

#: Characters, or places, that are worked on at a time.
AT_ONCE = 1 << 20
# Fixed values of MD5: shifts of the four rounds, sines, start.
SHIFTS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
BLOCK = 55


def groups(texts: Iterator[str | None]) -> Iterator[list[str]]:
    """Texts in groups of about AT_ONCE characters."""
    some, size = [], 0
    for t in texts:
        if t:
            some.append(t)
            size += len(t)
        if size >= AT_ONCE:
            yield some
            some, size = [], 0
    if some:
        yield some


def ngrams(texts: list[str], n: int) -> tuple[list[str], list[int]]:
    """The n-grams of these texts and how often each comes."""
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    held = np.zeros(0x110000, bool)
    held[points] = True
    letters = np.flatnonzero(held).astype(np.uint32)
    bits = max(1, int(len(letters) - 1).bit_length())
    if bits * n > 62 or held[0]:  # many letters, or one that an array of texts would drop at the end
        found = Counter(t[i : i + n] for t in texts for i in range(len(t) - n + 1))
        return list(found), list(found.values())
    number = np.zeros(0x110000, np.int64)
    number[letters] = np.arange(len(letters))
    ids, m = number[points], max(0, len(points) - n + 1)
    whole = np.ones(len(points), bool)
    end = np.cumsum([len(t) for t in texts])
    for k in range(1, n):
        whole[np.maximum(end - k, 0)] = False  # else it would reach into the next text
    packed = np.zeros(m, np.int64)
    for k in range(n):
        packed = packed << bits | ids[k : k + m]
    grams, count = np.unique(packed[whole[:m]], return_counts=True)
    parts = np.stack([letters[grams >> bits * (n - 1 - k) & (1 << bits) - 1] for k in range(n)], axis=1) if len(grams) else np.zeros((0, n), np.uint32)
    return np.ascontiguousarray(parts).view(f"<U{n}").ravel().tolist(), count.tolist()


def md5_words(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the MD5 of each padded block of 64 bytes."""
    x = np.ascontiguousarray(rows.view("<u4").T)
    a, b, c, d = (np.full(x.shape[1], s, np.uint32) for s in START)
    for i in range(64):
        if i < 16:
            f, g = d ^ (b & (c ^ d)), i
        elif i < 32:
            f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif i < 48:
            f, g = b ^ c ^ d, (3 * i + 5) % 16
        else:
            f, g = c ^ (b | ~d), 7 * i % 16
        f = f + a + x[g] + np.uint32(SINES[i])
        s = SHIFTS[i // 16][i % 4]
        a, d, c, b = d, c, b, b + (f << np.uint32(s) | f >> np.uint32(32 - s))
    return a + np.uint32(START[0]), b + np.uint32(START[1])


def number(text: str) -> int:
    """The first 13 hexadecimal digits of the MD5, as Place.hash has it."""
    return int(hashlib.md5(text.encode()).hexdigest()[:13], 16)


DECIMALS: dict[int, np.ndarray] = {}


def decimals(digits: int) -> np.ndarray:
    """The digits of all numbers of so many, in order; kept, since every text asks for them."""
    if digits not in DECIMALS:
        i = np.arange(10 ** (digits - 1) if digits > 1 else 0, 10**digits)
        DECIMALS[digits] = np.stack([48 + i // 10 ** (digits - 1 - k) % 10 for k in range(digits)], axis=1).astype(np.uint8)
    return DECIMALS[digits]


def numbers(key: int, first: int, size: int, tail: str) -> np.ndarray:
    """Padded blocks of the texts 'key-i-tail' for i from first to size - 1; they must fit a block."""
    out = np.zeros((max(0, size - first), 64), np.uint8)
    head, tail = f"{key}-".encode(), f"-{tail}".encode()
    lo = first
    while lo < size:
        digits = len(str(lo))
        hi = min(size, 10**digits)
        block, at = out[lo - first : hi - first], len(head)
        block[:, :at] = np.frombuffer(head, np.uint8)
        if digits <= 5:
            base = 10 ** (digits - 1) if digits > 1 else 0
            block[:, at : at + digits] = decimals(digits)[lo - base : hi - base]
        else:
            for k in range(digits):
                block[:, at + k] = 48 + np.arange(lo, hi) // 10 ** (digits - 1 - k) % 10
        at += digits
        block[:, at : at + len(tail)] = np.frombuffer(tail, np.uint8)
        at += len(tail)
        block[:, at] = 128
        block[:, 56:58] = (at * 8 & 255, at * 8 >> 8)
        lo = hi
    return out


def below(rows: np.ndarray, limit: int) -> np.ndarray:
    """Which of the padded blocks have a number that is below the limit modulo 10000."""
    hit = np.zeros(len(rows), bool)
    for at in range(0, len(rows), 1 << 15):  # as much as the processor's cache holds
        a, b = md5_words(rows[at : at + (1 << 15)])
        value = a.byteswap().astype(np.int64) << 20 | b.byteswap().astype(np.int64) >> 12
        hit[at : at + (1 << 15)] = value % 10000 < limit
    return hit


def chosen(texts: list[tuple[int, int]], first: int, tail: str, limit: int) -> list[list[int]]:
    """Of each text (key, size) the places from `first` on whose number modulo 10000 is below the limit."""
    if any(len(f"{k}-{n}-{tail}") > BLOCK for k, n in texts):
        return [[i for i in range(first, n) if number(f"{k}-{i}-{tail}") % 10000 < limit] for k, n in texts]
    rows = np.concatenate([numbers(k, first, n, tail) for k, n in texts] or [np.zeros((0, 64), np.uint8)])
    hit = below(rows, limit)
    out, at = [], 0
    for _, n in texts:
        m = max(0, n - first)
        out.append((np.flatnonzero(hit[at : at + m]) + first).tolist())
        at += m
    return out


class Continuations:
    """What follows each key, in order, with the upper ends of the parts."""

    def __init__(self, key: list[str], follows: list[str], hi: list[int]):
        self.follows, self.hi, self.at = follows, np.array(hi, np.int64), {}
        for i, k in enumerate(key):  # rows of a key stand together
            first, _ = self.at.get(k, (i, i))
            self.at[k] = (first, i + 1)

    def draw(self, key: str, value: int) -> str | None:
        if key not in self.at:
            return None
        lo, end = self.at[key]
        return self.follows[bisect_right(self.hi, value % int(self.hi[end - 1]), lo, end)]


def lowered(text: str, lower: str | None, a: int, b: int) -> str:
    """text[a:b] in lower case: of a text that is not ASCII as the plan has it, unless that has another length or a letter that depends on its place."""
    part = text[a:b]
    if part.isascii() or lower is None or len(lower) != len(text) or "Σ" in part:
        return part.lower()
    return lower[a:b]


def edited(batch: pa.RecordBatch, table: Continuations, back: int, name: str, rate: float, seed: str) -> Iterator[pa.RecordBatch]:
    """(doc_id, lang, text) of rows (doc_id, lang, text, lower): chosen characters are replaced by a drawn one, or followed by it."""
    keys, langs, texts, lowers = (batch.column(c).to_pylist() for c in ("doc_id", "lang", "text", "lower"))
    start, size = 0, 0
    for end in range(1, len(keys) + 1):
        size += len(texts[end - 1] or "")
        if size < AT_ONCE >> 2 and end < len(keys):
            continue
        places = chosen([(k, len(t or "")) for k, t in zip(keys[start:end], texts[start:end], strict=True)], back, f"{name}-{seed}", round(rate * 10000))
        out = []
        for k, text, lower, some in zip(keys[start:end], texts[start:end], lowers[start:end], places, strict=True):
            if some:
                own = list(text)
                for i in some:
                    new = table.draw(lowered(text, lower, i - back, i), number(f"{k}-{i}-{name}d-{seed}"))
                    if new is not None:
                        own[i] = own[i] + new if "insert" in name else new
                text = "".join(own)
            out.append(text)
        yield pa.record_batch([pa.array(keys[start:end], pa.int64()), pa.array(langs[start:end], pa.string()), pa.array(out, pa.string())], ["doc_id", "lang", "text"])
        start, size = end, 0


def replaced(batch: pa.RecordBatch, changes: dict[str, str], name: str, rate: float, seed: str) -> Iterator[pa.RecordBatch]:
    """(doc_id, lang, text) of rows (doc_id, lang, text): chosen characters that `changes` names are replaced. Only their places are hashed, since no other place can change."""
    keys, langs, texts = (batch.column(c).to_pylist() for c in ("doc_id", "lang", "text"))
    named, tail, limit = np.zeros(0x110000, bool), f"{name}-{seed}", round(rate * 10000)
    named[[ord(c) for c in changes]] = True
    start, size = 0, 0
    for end in range(1, len(keys) + 1):
        size += len(texts[end - 1])
        if size < AT_ONCE >> 2 and end < len(keys):
            continue
        at = [np.flatnonzero(named[np.frombuffer(t.encode("utf-32-le", "surrogatepass"), np.uint32)]) for t in texts[start:end]]
        rows = [numbers(k, 0, len(t), tail)[i] if len(f"{k}-{len(t)}-{tail}") <= BLOCK else None for k, t, i in zip(keys[start:end], texts[start:end], at, strict=True)]
        hit = below(np.concatenate([np.zeros((0, 64), np.uint8), *(r for r in rows if r is not None)]), limit)
        out, done = [], 0
        for k, text, i, r in zip(keys[start:end], texts[start:end], at, rows, strict=True):
            some = i[hit[done : done + len(i)]].tolist() if r is not None else [j for j in i.tolist() if number(f"{k}-{j}-{tail}") % 10000 < limit]
            done += len(i) if r is not None else 0
            if some:
                own = list(text)
                for j in some:
                    own[j] = changes[own[j]]
                text = "".join(own)
            out.append(text)
        yield pa.record_batch([pa.array(keys[start:end], pa.int64()), pa.array(langs[start:end], pa.string()), pa.array(out, pa.string())], ["doc_id", "lang", "text"])
        start, size = end, 0
