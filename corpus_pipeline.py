"""The corpus pipeline: operators of dpsynth.llm as stages over the documents table.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; run() chains
them.  All stages but the last return the columns of documents, unchanged but for text and n_chars
after line dedup; extra columns stay, whatever their names.  Empty tables stay empty.  What a stage
does with null and empty texts, null ids and repeated rows stands in its docstring.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpsynth.llm import bpe, fmindex, langid, linededup, nearcopies
from dpsynth.llm.common import columns_of, fresh, named, table

#: Documents below this score, and those without a letter, are rejected.
MIN_LANG_SCORE = 0.5


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage 1: documents whose language can be told.  Null texts and texts without a letter go;
    repeated rows fare alike, null ids like any other.  Without any labelled text all stay."""
    model = langid.train(docs)
    if not model.langs:
        return docs
    names = tuple(fresh(docs, "lang_pred", "score"))
    return langid.identify(docs, model, names).where(named(names[1]) >= MIN_LANG_SCORE).select(*columns_of(docs))


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage 2: lines that ten or more documents share go; n_chars follows the text.  Every row
    stays; a null text becomes an empty one; rows of one doc_id (null is one) count as one document."""
    kept = linededup.dedup_lines(docs)
    if "n_chars" in docs.columns:
        kept = kept.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return kept.select(*columns_of(docs))


def dedup_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage 3: one document of each component of near copies (five-word shingles, similarity 0.8)
    stays, that of the smallest doc_id (null first).  Null, empty and blank texts are alike, and
    repeated rows are copies."""
    return nearcopies.keep_one(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage 4: documents with a passage of the benchmark go.  Null and empty texts stay, and
    repeated rows of a clean text."""
    return fmindex.clean_documents(docs, table(spark, sf_dir, "benchmark"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage 5: every text that is left, with its token ids in one more column, token_ids (a column
    of this name is replaced).  Null and empty texts have no ids."""
    return bpe.encode_documents(docs)


STAGES = [
    ("language ID", identify_language),
    ("line dedup", dedup_lines),
    ("SimHash near-dedup", dedup_documents),
    ("benchmark decontamination", decontaminate),
    ("byte-level BPE", encode),
]

#: SQL has no XXH64 fingerprints, no naive Bayes and no byte-pair encoding; tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply the stages to the documents table, one after the other."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
    return docs
