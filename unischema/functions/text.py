"""String functions of the methods as column expressions: q-grams, edit distance, bucket hash, path sums."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def edit_distance(a: Column | str, b: Column | str) -> Column:
    """Edit distance in characters."""
    return F.levenshtein(a, b)


def edit_within(a: Column | str, b: Column | str, eps: int) -> Column:
    """Edit distance if at most ``eps``, else null; the computation stops at the threshold."""
    d = F.levenshtein(a, b, eps)
    return F.when(d >= 0, d)


def qgrams(word: Column, q: int) -> Column:
    """The bag of ``length - q + 1`` grams, as an array in order; empty for shorter words."""
    n = F.length(word)
    grams = F.transform(F.sequence(F.lit(1), n - (q - 1)), lambda i: F.substring(word, i, F.lit(q)))
    return F.when(n >= q, grams).otherwise(F.array().cast("array<string>"))


def numbered_grams(word: Column, q: int) -> Column:
    """Grams with their occurrence numbers, so that bag intersection becomes set intersection."""
    grams = qgrams(word, q)

    def numbered(all_grams: Column) -> Column:
        return F.transform(
            all_grams,
            lambda g, i: F.struct(g.alias("gram"), F.size(F.filter(F.slice(all_grams, 1, i + 1), lambda h: h == g)).alias("occ"), (i + 1).alias("pos")),
        )

    return F.get(F.transform(F.array(grams), numbered), F.lit(0))


def gram_key(gram: Column) -> Column:
    """A 64-bit key of a gram; the gram is kept beside it where collisions matter."""
    return F.xxhash64(gram)


def count_bound(la: Column, lb: Column, q: int, eps: int) -> Column:
    """Least number of shared grams for an edit distance within ``eps``, by the longer word."""
    return F.greatest(la, lb) - q + 1 - q * eps


def count_bound_self(length: Column, q: int, eps: int) -> Column:
    """The bound from one word's length alone (not sound for the longer partner's sake)."""
    return length - q + 1 - q * eps


def deletions(word: Column, eps: int) -> Column:
    """All strings that up to ``eps`` deletions make of a word, the word included."""
    found = F.array(word)
    for _ in range(eps):

        def shorter(s: Column) -> Column:
            n = F.length(s)
            cuts = F.transform(F.sequence(F.lit(1), n), lambda i: F.concat(F.substring(s, F.lit(1), i - 1), F.substring(s, i + 1, n)))
            return F.when(n >= 1, cuts).otherwise(F.array().cast("array<string>"))

        found = F.array_distinct(F.concat(found, F.flatten(F.transform(found, shorter))))
    return found


def bucket_offset(word: Column, seed: int, length: int) -> Column:
    """Polynomial hash of the characters in signed 32-bit arithmetic, reduced to a bucket's length.

    Each step wraps in 64-bit: the value is kept in [0, 2^32) and read as signed at the end.
    """
    wrap = 1 << 32
    codes = F.transform(F.filter(F.split(word, ""), lambda c: c != ""), lambda c: F.ascii(c).cast("long"))
    raw = F.aggregate(codes, F.lit(0).cast("long"), lambda k, c: F.pmod(k * seed + c, F.lit(wrap)))
    signed = F.when(raw >= wrap // 2, raw - wrap).otherwise(raw)
    return F.pmod(signed, F.lit(length)).cast("long")


def bucket_address(word: Column, seed: int = 13, length: int = 10_000, base: int | Column = 1_000_000) -> Column:
    return (F.lit(base) if isinstance(base, int) else base) + bucket_offset(word, seed, length)


def path_energy(lengths: Column) -> Column:
    """Sum of squared path lengths."""
    return F.aggregate(F.transform(lengths, lambda x: x * x), F.lit(0).cast("long"), lambda a, x: a + x)


def cosine(x: Column, y: Column) -> Column:
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda u, v: u.cast("double") * v), F.lit(0.0), lambda s, z: s + z)
    return dot(x, y) / F.sqrt(dot(x, x) * dot(y, y))


def register_sql(spark: SparkSession) -> None:
    """``edit_within``, ``qgrams`` and ``count_bound`` for SQL users, as SQL functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION count_bound(la INT, lb INT, q INT, eps INT) RETURNS INT RETURN greatest(la, lb) - q + 1 - q * eps")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edit_within(a STRING, b STRING, eps INT) RETURNS BOOLEAN RETURN levenshtein(a, b) <= eps")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION qgrams(w STRING, q INT) RETURNS ARRAY<STRING> "
        "RETURN CASE WHEN length(w) >= q THEN transform(sequence(1, length(w) - q + 1), i -> substring(w, i, q)) ELSE array() END"
    )
