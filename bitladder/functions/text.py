"""Words, letter trigrams, vocabularies and sliding windows of sparse counts.

Null or empty text gives an empty list of words, hence no windows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: trigram dimensions of the published model
DIMS = 49_292


def let(value: Column, body) -> Column:
    """``body(value)`` with the value computed once, however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words(text: Column, lower: bool = True) -> Column:
    """Runs of letters and digits."""
    t = F.coalesce(text, F.lit(""))
    t = F.lower(t) if lower else t
    return F.filter(F.split(F.regexp_replace(t, r"[^\p{L}\p{N}]+", " "), " "), lambda w: F.length(w) > 0)


def letter_trigrams(word: Column, mark: str = "#") -> Column:
    """Shingles of three letters of a word between boundary marks."""
    w = F.concat(F.lit(mark), word, F.lit(mark))
    return F.transform(F.sequence(F.lit(1), F.greatest(F.length(w) - 2, F.lit(1))), lambda i: F.substring(w, i, F.lit(3)))


def hash_ids(trigram: Column, dims: int = DIMS) -> Column:
    """Id of a trigram without a vocabulary."""
    return F.pmod(F.xxhash64(trigram), F.lit(dims)).cast("int")


def build_vocab(docs: DataFrame, text: str = "text", min_df: int = 1, max_size: int = DIMS) -> DataFrame:
    """trigram, df, idx: dense ids by falling document frequency, ties by trigram.

    One shuffle of distinct (document, trigram); the ranking sorts only the kept
    vocabulary, which ``max_size`` bounds.
    """
    grams = F.array_distinct(F.flatten(F.transform(words(F.col(text)), lambda w: letter_trigrams(w))))
    counts = docs.select(F.explode(grams).alias("trigram")).groupBy("trigram").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
    top = counts.orderBy(F.desc("df"), "trigram").limit(max_size)
    return top.withColumn("idx", (F.row_number().over(Window.orderBy(F.desc("df"), "trigram")) - 1).cast("int"))


def counts_of(ids: Column) -> Column:
    """Sparse counts (idx, cnt) of a list of ids, by id."""
    return F.transform(F.array_sort(F.array_distinct(ids)), lambda d: F.struct(d.alias("idx"), F.size(F.filter(ids, lambda x: x == d)).cast("float").alias("cnt")))


def shifted(ids: Column, by: int) -> Column:
    return F.transform(ids, lambda x: x + F.lit(by))


def word_windows(text: Column, width: int = 3, dims: int = DIMS, mode: str = "bag") -> Column:
    """For each word the sparse trigram counts of the ``width`` words around it.

    Ends are padded with nothing.  ``positions`` keeps the place of each word in
    the window, so ids run up to ``width * dims``.
    """
    half = width // 2
    nothing = F.array().cast("array<int>")

    def windows(per_word: Column) -> Column:
        count = F.size(per_word)

        def window(i: Column) -> Column:
            parts = []
            for p in range(width):
                at = i + F.lit(p - half)
                ids = F.when((at >= 1) & (at <= count), F.element_at(per_word, F.greatest(F.least(at, count), F.lit(1)))).otherwise(nothing)
                parts.append(shifted(ids, p * dims) if mode == "positions" else ids)
            return let(F.flatten(F.array(*parts)), counts_of)

        return F.when(count > 0, F.transform(F.sequence(F.lit(1), F.greatest(count, F.lit(1))), window)).otherwise(F.array().cast("array<array<struct<idx:int,cnt:float>>>"))

    return let(F.transform(words(text), lambda w: F.transform(letter_trigrams(w), lambda t: hash_ids(t, dims))), windows)
