"""From raw documents to packed training sequences, in five stages.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes it
as Parquet and reads it again for the next one.  All stages but the last return
the columns of ``documents``.

* quality: line-first cleaning; rejected documents go, failing lines go from the rest
* lines: lines that a smaller document holds go; documents without words left go
* near: one document stays of each group of near duplicates
* mix: rows in the order of the mixture, nothing dropped
* pack: pieces in sequences of at most 2048 tokens, numbered in the order of the mixture

Every stage takes null values in any column, empty and very long texts, repeated
rows, empty tables and further columns (whatever their names, they are left out).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitladder.llm import lines, mixing, near, packing, quality
from bitladder.llm.common import written
from bitladder.llm.queries import vocabulary

#: fixed values: the columns of ``documents``
COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _documents(df: DataFrame, text: str) -> DataFrame:
    """The columns of ``documents`` with a changed text and its length."""
    out = {"text": F.col(text), "n_chars": F.char_length(text).cast("long")}
    return df.select(*[out.get(c, F.col(c)).alias(c) for c in COLUMNS])


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without failing lines, of the documents that pass; null texts and texts under 20 words go."""
    cleaned = quality.clean(docs.select(*COLUMNS), keep=("lang", "source"))
    return _documents(cleaned.where("kept"), "clean_text")


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A document that was only lines of smaller documents has nothing left and goes."""
    out = lines.dedup_lines(docs.select(*COLUMNS), keep=("lang", "source"))
    return _documents(out.where(F.col("kept_text").rlike("[^ \\t\\n\\r\\x0B\\f]") | (F.col("n_dropped") == 0)), "kept_text")


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of a group the smallest doc_id stays; rows that repeat it stay with it.

    Rows without doc_id come before others; of several with one text one stays.
    """
    gone = near.document_classes(docs).where("doc <> class").select(F.col("doc").alias("_gone"))
    rest = docs.select(*COLUMNS, near.doc_key().alias("_doc")).join(gone, F.col("_doc") == F.col("_gone"), "left_anti")
    unnamed = F.col("doc_id").isNull() & F.coalesce(F.col("text").rlike(near.WORDED), F.lit(False))
    one = rest.where(unnamed).groupBy("_doc").agg(F.min(F.struct(*COLUMNS)).alias("row")).select("row.*")
    return rest.where(~unnamed).select(*COLUMNS).unionByName(one)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows in the order of the mixture; rows that repeat (source, doc_id) follow the first of them."""
    return mixing.mixed_documents(docs.select(*COLUMNS))


#: remainders that wait for a window: the mixture holds within about so many documents
POOL_DOCS = 256


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces in sequences whose numbers rise with the mixture.

    A scan reads files by size, so the order of the mixture, which depends on the rows
    alone, is set up again; each partition of it is packed from a small pool.
    """
    ordered = mixing.mixed_documents(docs.select(*COLUMNS))
    return packing.digest(packing.pack(ordered, vocabulary(), pool_docs=POOL_DOCS))


STAGES = [
    ("quality", quality_rules),
    ("lines", line_dedup),
    ("near", near_dedup),
    ("mix", mix_sources),
    ("pack", pack_sequences),
]

#: tokens and similarity classes are beyond SQL; tests compare with brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
