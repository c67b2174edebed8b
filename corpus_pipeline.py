"""From raw documents to token ids: toxicity, near duplicates, repeated passages, mixing, encoding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that, written as Parquet and read
again, is the next stage's docs.  All but the last return the columns of ``documents``.

In every stage null and empty texts have no words, rows of null doc_id are kept and never removed
for another row, an empty table stays empty, whole texts are read, and columns that ``documents``
does not have are carried along whatever their names, up to the last stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from lmrel.llm import bpe, jaccard, mixing, substrings, toxicity
from lmrel.llm.common import reliable, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model does not reject; its labels are those of ``labels``.

    Rows are judged one by one: repeated rows alike, null and empty texts as texts of no words.
    """
    return toxicity.without_toxic(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates, that of the smallest doc_id.

    Of rows equal in doc_id and text one stays; texts of no words are near duplicates of nothing.
    """
    return jaccard.one_of_each_class(docs)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages that a document of smaller doc_id has too.

    A text of which nothing is left goes; one that had no words stays as it is; repeated rows of a
    doc_id take nothing from each other.
    """
    return substrings.without_repeats(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Copies and parts of documents so that each source's words come near its target.

    A null source is a source; documents of no words stay once; copies keep their doc_id.
    """
    return mixing.mixed_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text, with doc_id, lang and source; null and empty texts have no ids."""
    return bpe.token_ids(docs, ("doc_id", "lang", "source"))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("substring_dedup", cut_repeats),
    ("mixing", mix_sources),
    ("byte_pair_encoding", encode),
]

#: The model of the first stage has no SQL; the tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, cut by checkpoints between them."""
    docs = table(spark, sf_dir, "documents")
    for at, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        docs = docs if at == len(STAGES) - 1 else reliable(docs)
    return docs
