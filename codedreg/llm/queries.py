"""Registered queries of the training-data operators: each applies one operator to its whole table."""

from __future__ import annotations

import public_tokenizers as vocabularies
from pyspark.sql import DataFrame, SparkSession

from codedreg.llm import language, toxicity
from codedreg.llm.bpe import encode_documents
from codedreg.llm.common import read_table
from codedreg.llm.fingerprints import fingerprint_documents
from codedreg.llm.jaccard import ORACLE as JACCARD_SQL
from codedreg.llm.jaccard import jaccard_components
from codedreg.llm.linededup import summary as line_summary
from codedreg.llm.packing import pack_documents
from codedreg.llm.pii import find_pii
from codedreg.llm.shards import materialise
from codedreg.llm.topk import ORACLE as TOP_K_SQL
from codedreg.llm.topk import integer_vectors, queries_of, top_k

RANKS = vocabularies.path("byte_bpe_50k.tiktoken")
TOKENIZER = vocabularies.path("byte_bpe_50k.json")
PATTERN = vocabularies.PATTERN


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "documents").select("doc_id", "text")


def op1_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = integer_vectors(read_table(spark, sf_dir, "embeddings"))
    return top_k(queries_of(vectors, 20), vectors)


def op2_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(_documents(spark, sf_dir))


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(_documents(spark, sf_dir), RANKS, PATTERN, digests=True)


def op4_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint_documents(_documents(spark, sf_dir))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_summary(_documents(spark, sf_dir))


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_pii(_documents(spark, sf_dir))


def op7_training_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    return materialise(_documents(spark, sf_dir), TOKENIZER, PATTERN)


def op8_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(_documents(spark, sf_dir), TOKENIZER, PATTERN)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir)
    return toxicity.score_documents(docs, toxicity.fit(docs, read_table(spark, sf_dir, "labels")))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return language.identify(docs, language.fit(docs))


QUERIES = {f.__name__: f for f in (op1_exact_top_k, op2_ngram_jaccard, op3_byte_bpe, op4_fingerprints, op5_line_dedup, op6_pii, op7_training_order, op8_harmonic_packing, op9_toxicity, op10_language)}
ORACLES: dict[str, str] = {"op1_exact_top_k": TOP_K_SQL, "op2_ngram_jaccard": JACCARD_SQL}
