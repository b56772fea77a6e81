"""Corpus cleaning in five stages, each one operator applied to all that the stage before kept.

1. toxicity: documents predicted toxic go; all others, null and empty texts included, stay.
2. line_dedup: of lines that repeat, exactly or nearly, the first occurrence stays; documents stay.
3. ngram_jaccard: of documents that five-word shingles link at a Jaccard similarity of 0.8, one stays; documents
   without words stay.
4. pii: personal data is masked in the text.
5. packing: what is left is cut and packed into training sequences.

All but the last return the columns of the documents; where a stage changes the text, n_chars follows.
"""

from __future__ import annotations

import public_tokenizers as vocabularies
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codedreg.llm import toxicity
from codedreg.llm.common import cut, read_table
from codedreg.llm.jaccard import jaccard_components
from codedreg.llm.linededup import dedup_lines
from codedreg.llm.packing import pack_documents
from codedreg.llm.pii import masked

SHINGLE_WORDS = 5
SIMILAR_PERCENT = 80


def _recount(docs: DataFrame) -> DataFrame:
    if "n_chars" not in docs.columns:
        return docs
    return docs.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows not predicted toxic; null and empty texts, null ids, repeated rows and extra columns stay as they are."""
    model = toxicity.fit(docs, read_table(spark, sf_dir, "labels"))
    return toxicity.score_documents(docs, model, docs.columns).where("predicted = 0").select(docs.columns)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows; of each component of lines the first occurrence stays.  Rows without id and null texts stay as they are."""
    return _recount(dedup_lines(docs))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each group stays, once even if its row repeats (of rows that differ, the one of the lowest hash);
    rows without doc_id stay, documents without words are groups of their own."""
    groups = cut(jaccard_components(docs, SHINGLE_WORDS, SIMILAR_PERCENT))
    kept = groups.where("doc_id = component_id").select("doc_id")
    named = docs.join(kept, "doc_id", "left_semi")
    if groups.count() < docs.count():
        hashed = named.withColumn("hash__", F.xxhash64(*docs.columns))
        least = hashed.groupBy("doc_id").agg(F.min("hash__").alias("hash__"))
        named = hashed.join(least, ["doc_id", "hash__"]).dropDuplicates(["doc_id"])
    return named.select(docs.columns).unionByName(docs.where("doc_id is null"))


def mask_pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, with spans of personal data replaced by their kind; null texts stay null."""
    return _recount(masked(docs))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all rows in sequences; a null text is an empty document, repeated rows are packed once each."""
    return pack_documents(docs, vocabularies.path("byte_bpe_50k.json"), vocabularies.PATTERN)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_lines),
    ("ngram_jaccard", drop_near_copies),
    ("pii", mask_pii),
    ("packing", pack),
]
#: SQL expresses neither the trained model nor the tokenizer.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
