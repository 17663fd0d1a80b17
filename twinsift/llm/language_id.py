"""Language identification with hyperdimensional profiles.

Each letter owns a random vector of +1 and -1. A trigram's vector binds those of
its letters, permuted by their place (product of rotations); a text's vector
bundles its trigrams (sum); a language's prototype bundles its texts. The
prediction is the prototype of largest cosine, the score that cosine, 0 at least.

Letters are lower-cased; every run of other characters is one gap, which is a
symbol of its own. Every letter that learning saw has a vector of its own, however many there are; letters that it never saw share
SPARE vectors by code point.

Learned on a bounded sample (about FIT_ROWS rows, none over FIT_BYTES); every text is scored whole: its
trigrams are counted with numpy and the counts multiplied by the trigram vectors, in
blocks of bounded size. The model travels to the tasks as plain arrays.

Defined cases: null text, or text without a letter: `und` with score 0; so is
every text if no row can teach. Rows with a null id predict like others, teach nothing and count as not held out.
Ties go to the language that sorts first. Repeated rows repeat; an empty table
gives an empty one; further columns are ignored.
"""

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.llm.common import id_remainder, kept_columns, learning_rows, slices, small_batches, text_first

by_value(__name__)

DIMENSIONS, SPARE = 1024, 12
FIT_ROWS, FIT_BYTES = 4000, 65_536
MAX_CELLS = 1 << 20
TABLE = 1 << 22  # cells
BLOCK = 4096  # trigrams whose vectors are in memory at a time
UNKNOWN = "und"


def letter_flags() -> np.ndarray:
    """For each code point whether it is a letter."""
    return np.fromiter((chr(c).isalpha() if not 0xD800 <= c < 0xE000 else False for c in range(0x110000)), bool, 0x110000)


class Profiles:
    """Letter vectors, and a prototype of unit length for each language."""

    def __init__(self, letters: list[str], languages: list[str], seed: int = 11):
        self.languages = languages
        self.size = 1 + len(letters) + SPARE
        number = np.zeros(0x110000, np.int32)
        flags = letter_flags()
        number[flags] = 1 + len(letters) + np.flatnonzero(flags) % SPARE
        for i, c in enumerate(letters):
            number[ord(c)] = 1 + i
        self.number = number
        base = np.random.default_rng(seed).integers(0, 2, (self.size, DIMENSIONS), np.int8) * 2 - 1
        self.rolled = [np.roll(base, r, axis=1) for r in (2, 1, 0)]
        self.prototypes = np.zeros((len(languages), DIMENSIONS), np.float32)
        self.letters, self.seed = letters, seed

    def plain(self) -> tuple:
        """All that a task needs to have the model again: strings, a number and an array."""
        return "".join(self.letters), self.languages, self.seed, self.prototypes

    @classmethod
    def of(cls, letters: str, languages: list[str], seed: int, prototypes: np.ndarray) -> "Profiles":
        model = cls(list(letters), languages, seed)
        model.prototypes = prototypes
        return model

    def vectors(self, codes: np.ndarray) -> np.ndarray:
        """Trigram vectors: the letters' vectors, permuted by place and multiplied."""
        a, b, c = codes // (self.size * self.size), codes // self.size % self.size, codes % self.size
        return (self.rolled[0][a] * self.rolled[1][b] * self.rolled[2][c]).astype(np.float32)

    def trigrams(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Trigram codes of all texts, the text of each, and whether a text has a letter."""
        low = [t.lower() for t in texts]
        points = np.frombuffer("\n".join([*low, ""]).encode("utf-32-le", "surrogatepass"), np.uint32)
        ids = self.number[points].astype(np.int64)
        owner = np.repeat(np.arange(len(low), dtype=np.int32), [len(t) + 1 for t in low])
        has = np.zeros(len(low), bool)
        has[owner[ids > 0]] = True
        kept = (ids > 0) | np.concatenate([[True], ids[:-1] > 0])
        ids, owner = ids[kept], owner[kept]
        if len(ids) < 3:
            return np.zeros(0, np.int64), np.zeros(0, np.int32), has
        inside = owner[2:] == owner[:-2]
        return ((ids[:-2] * self.size + ids[1:-1]) * self.size + ids[2:])[inside], owner[2:][inside], has

    def numbered(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The distinct codes, and the place of each code among them; by a table where all possible codes fit in one."""
        if self.size**3 > TABLE:
            return np.unique(codes, return_inverse=True)
        there = np.zeros(self.size**3, bool)
        there[codes] = True
        distinct = np.flatnonzero(there)
        column = np.zeros(self.size**3, np.int32)
        column[distinct] = np.arange(len(distinct))
        return distinct, column[codes]

    def bundle(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The vector of each text, and whether it has a letter."""
        codes, owner, has = self.trigrams(texts)
        out = np.zeros((len(texts), DIMENSIONS), np.float32)
        distinct, col = self.numbered(codes)
        for a in range(0, len(distinct), BLOCK):  # blocks of trigrams, and of texts, bound the memory
            vectors = self.vectors(distinct[a : a + BLOCK])
            width = len(vectors)
            mine = (col >= a) & (col < a + width) if len(distinct) > BLOCK else slice(None)
            c, o = col[mine] - a, owner[mine]
            rows = max(1, MAX_CELLS // width)
            for r in range(0, len(texts), rows):
                lo, hi = np.searchsorted(o, [r, r + rows])
                n = min(rows, len(texts) - r)
                counts = np.bincount((o[lo:hi].astype(np.int64) - r) * width + c[lo:hi], minlength=n * width).reshape(n, width)
                out[r : r + n] += counts.astype(np.float32) @ vectors
        return out, has

    def learn(self, texts: list[str], languages: list[str]) -> None:
        place = {name: i for i, name in enumerate(self.languages)}
        for a in range(0, len(texts), 256):
            vectors, _ = self.bundle(texts[a : a + 256])
            np.add.at(self.prototypes, [place[x] for x in languages[a : a + 256]], vectors)
        self.prototypes /= np.maximum(np.linalg.norm(self.prototypes, axis=1, keepdims=True), 1e-9)

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray]:
        vectors, has = self.bundle(texts)
        if not self.languages:
            return [UNKNOWN] * len(texts), np.zeros(len(texts))
        cosine = (vectors @ self.prototypes.T) / np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)
        best = cosine.argmax(1)
        score = np.clip(cosine[np.arange(len(texts)), best].astype(float), 0, 1)
        return [self.languages[b] if h else UNKNOWN for b, h in zip(best.tolist(), has, strict=True)], np.where(has, score, 0.0)


def fit_profiles(docs: DataFrame) -> Profiles:
    """Learn `lang` from the rows whose crc32(doc_id) mod 3 is not 1."""
    rows = docs.select("doc_id", "text", "lang").filter((id_remainder(3) != 1) & F.col("text").isNotNull() & F.col("lang").isNotNull())
    got = learning_rows(rows, FIT_ROWS, FIT_BYTES, "language")
    texts, langs = [r["text"] for r in got], [r["lang"] for r in got]
    letters = sorted({c for t in texts for c in set(t.lower()) if c.isalpha()})
    model = Profiles(letters, sorted(set(langs)))
    model.learn(texts, langs)
    return model


def predict_language(docs: DataFrame, model: Profiles, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns in keep, and held_out, lang_pred and score of every whole text."""
    small_batches(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model.plain())

    def run(batches):
        model = Profiles.of(*sent.value)
        for piece in slices(batches, 2 << 20):
            names, scores = model.predict([t or "" for t in piece.column(1).to_pylist()])
            found = [piece.column(0), pa.array(names, pa.string()), pa.array(scores, pa.float64())]
            yield pa.RecordBatch.from_arrays([*kept_columns(piece, keep), *found], names=[*keep, "held_out", "lang_pred", "score"])

    held = F.coalesce(id_remainder(3) == 1, F.lit(False))
    schema = docs.select(*keep).schema.add("held_out", "boolean").add("lang_pred", "string").add("score", "double")
    return text_first(docs, held, keep).mapInArrow(run, schema)
