"""Text as words, shingles, chunks and code-point bits, as column expressions that Spark and DuckDB compute alike."""

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD_BREAK = r"[^\p{L}\p{N}]+"
PRIME31 = (1 << 31) - 1
CODE_BITS = 24


def md5_int(text: Column) -> Column:
    """60-bit number of a text, the same in every engine that has md5."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def words(text: Column) -> Column:
    """Lower-case runs of letters and digits."""
    return F.filter(F.split(F.lower(text), WORD_BREAK), lambda w: w != "")


def _runs(units: Column, n: int, glue: str) -> Column:
    """Every n neighbours of an array joined. Slices are zipped, so no array is computed again inside a lambda."""
    shifted = [F.slice(units, k + 1, F.greatest(F.size(units) - n + 1, F.lit(0))).alias(f"u{k}") for k in range(n)]
    return F.transform(F.arrays_zip(*shifted), lambda z: F.concat_ws(glue, *(z[f"u{k}"] for k in range(n))))


def word_shingles(text: Column, n: int) -> Column:
    """Distinct word n-grams; a text of fewer words has none."""
    return F.array_distinct(_runs(words(text), n, " "))


def char_shingles(text: Column, n: int) -> Column:
    """All character n-grams of the lower-case text, repeats kept."""
    return _runs(F.filter(F.split(F.lower(text), ""), lambda c: c != ""), n, "")


def chunk_array(text: Column, size: int, stride: int | None = None) -> Column:
    """Slices of size code points; an empty text has one empty slice, null has null."""
    starts = F.sequence(F.lit(0), F.greatest(F.length(text) - 1, F.lit(0)), F.lit(stride or size))
    return F.when(text.isNotNull(), F.transform(starts, lambda s: F.struct(s.alias("start"), F.substring(text, s + 1, F.lit(size)).alias("chunk"))))


def code_points(text: Column) -> Column:
    return F.transform(F.filter(F.split(text, ""), lambda c: c != ""), lambda c: F.ascii(c))


def bit_rows(text: Column) -> Column:
    """For each character its 24 bits, lowest first."""
    return F.transform(code_points(text), lambda c: F.transform(F.sequence(F.lit(0), F.lit(CODE_BITS - 1)), lambda b: F.getbit(c, b)))


def hamming(a: Column, b: Column) -> Column:
    return F.bit_count(a.bitwiseXOR(b))


def jaccard(a: Column, b: Column) -> Column:
    """Of two arrays of distinct elements; two empty ones have 0."""
    same = F.size(F.array_intersect(a, b))
    return F.coalesce(F.try_divide(same, F.size(a) + F.size(b) - same), F.lit(0.0))
