"""Corpus pipeline over ``documents``: language, near copies, repeated passages, packing.

Each stage takes ``(spark, docs, sf_dir)`` and works on all that the stage before it
kept; the runner writes every result as Parquet and reads it back. All stages but the
last return the columns of ``documents``.
"""

from __future__ import annotations

import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kmfold.llm import langid, ngramjoin, packing, suffixdedup
from kmfold.staging import stage

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop the documents that language ID rejects: no letters (null and empty texts too), or no clear language.

    Rows of a repeated id are judged one by one; an empty table stays empty.
    """
    told = langid.predict(docs, langid.learn(docs), keep=COLUMNS)
    return told.filter(~F.col("rejected")).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the document of least id of each group linked at five words and 0.8; documents without words stay.

    Rows of a repeated id are separate documents: of those that are linked with one
    another one row stays, those that are linked with nothing all stay. A null id is
    larger than all others. An empty table stays empty.
    """
    return ngramjoin.first_of_each_group(docs, n=5, num=80, den=100).select(*COLUMNS)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Take out every 50-byte string that starts in a document of smaller id; all documents stay.

    A character of which a part was taken out goes as a whole; a null text stays null.
    """

    def finish(table, part, spans):
        kept = [suffixdedup.keep_bytes(t, a, z).decode("utf-8", "ignore") for t, (a, z) in zip(part.texts, spans)]
        rest = table.take(part.order)
        none = rest.column("text").is_null().to_pylist()
        kept = [None if z else k for k, z in zip(kept, none)]
        size = [n if z else len(k) for k, z, n in zip(kept, none, rest.column("n_chars").to_pylist())]
        return pa.table({"doc_id": rest.column("doc_id"), "text": pa.array(kept, pa.string()), "lang": rest.column("lang"), "source": rest.column("source"), "n_chars": pa.array(size, pa.int64())})

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang", "source", F.col("n_chars").cast("long").alias("n_chars"))
    return suffixdedup.with_spans(rows, finish, "doc_id long, text string, lang string, source string, n_chars long", COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack what is left into sequences of 2048 ids: one row a piece with its place.

    Null and empty texts have the end id alone; rows of a repeated id are separate
    pieces; an empty table gives no piece.
    """
    return packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("language", identify_language),
    ("near_copies", drop_near_copies),
    ("repeated_passages", drop_repeated_passages),
    ("packing", pack_sequences),
]

#: Compression sizes and the packing program are not expressible in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
