"""A corpus pipeline of five stages; each takes (spark, docs, sf_dir) and works on all that the one before kept.

Every stage's result is written to the shared folder and read again as the next one's documents. All but
the last return the columns that they were given, whatever these are called.

All stages take null, empty and very long texts, null or repeated ids, repeated rows and empty tables; each stage's
docstring says what becomes of them. An empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relgraph.llm import linededup, mixing, packing, quality, simhash
from relgraph.llm.common import modest, staged, table
from relgraph.llm.queries import word_vocabulary

#: Share of the tokens that the mix may hold.
MIX_SHARE = 0.75


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the byte network accepts, learned from the labels outside the held-out fold.

    Rows are judged by their whole text alone, so equal texts stay or go together, whatever their ids. Null and empty texts
    are judged as padding and stay null or empty. A score of exactly one half stays. Without labels all rows stay.
    """
    modest(spark)
    network = quality.fit(docs, table(spark, sf_dir, "labels"))
    return quality.accepted(docs, network)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that three or more of them share; n_chars follows the text, where there is such a column.

    No row goes. Rows without doc_id keep all lines; rows of one doc_id are one document and lose the same lines. Null
    texts stay null, texts that lose all lines become empty. The largest doc_id keeps a shared line, so there are no ties.
    """
    modest(spark)
    found = linededup.clean(docs)
    return _counted(found) if "n_chars" in docs.columns else found


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of texts that five-word similarities of at least 0.8 link.

    Rows are judged by their text alone, so rows with null or repeated ids lose only duplicates. The row with the least
    doc_id stays, null after all others, and among equal ones that of least hash; rows that are the same in all columns are
    one. Texts without words, null or empty, are one group.
    """
    modest(spark)
    return simhash.distinct(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents by the target weights of the tree of domains, languages and sources, each in one epoch at most.

    The document at the end of a leaf's prefix is cut to the tokens that are left, and its n_chars follows. Null and empty
    texts are one token. Null sources and languages are names of their own. Ids decide only the order; null ids are
    ordered by their text.
    """
    found = mixing.chosen(docs, mixing.corpus_tree(), mixing.corpus_weights(), MIX_SHARE, epochs=1)
    size, take = found.columns[-2:]
    part = F.col(take) < F.col(size)
    found = found.withColumn("text", F.when(part, mixing.prefix("text", F.col(take))).otherwise(F.col("text")))
    if "n_chars" in docs.columns:
        found = found.withColumn("n_chars", F.when(part, F.length("text")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType))
    return found.select(*(f"`{c}`" for c in docs.columns))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 2048 tokens and their places in sequences.

    Every row is packed: null and empty texts as one piece of the end id, very long ones as several pieces; rows of one
    doc_id or without any are packed each. Ties between pieces of one length fall to doc_id, then to the piece.
    """
    modest(spark)
    return packing.pack_documents(docs, word_vocabulary())


def _counted(docs: DataFrame) -> DataFrame:
    return docs.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


STAGES = [
    ("quality classifier", quality_filter),
    ("line dedup", line_dedup),
    ("SimHash near-dedup", near_dedup),
    ("mixing to target weights", mix),
    ("best-fit packing", pack),
]

#: SQL has no form of the network or the tokenizer; the stages are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table."""
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = staged(stage(spark, docs, sf_dir), f"stage-{i}")
    return docs
