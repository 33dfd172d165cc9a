"""Queries of this subpackage: name -> function, and the SQL of those SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from parsieve.llm import fingerprints, jpeg, langid, lines, minhash, mixing, packing, pii, secrets, tokens
from parsieve.llm.common import table


def vocabulary(name: str = "piece_bpe_32k.model") -> str:
    """Path of a public vocabulary file; the package that holds it is on every machine."""
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op1_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(spark, table(spark, sf_dir, "documents"))


def op2_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = langid.identify(docs, langid.train(docs))
    return found.select("doc_id", langid.held_out().alias("held_out"), "lang_pred", "score", "bits_per_byte")


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    prints = fingerprints.document_fingerprints(spark, table(spark, sf_dir, "documents"))
    return fingerprints.with_links(spark, prints)


def op4_jpeg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jpeg.text_as_jpeg(table(spark, sf_dir, "documents"))


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixture(table(spark, sf_dir, "documents"))


def op6_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lines.deduped(spark, table(spark, sf_dir, "documents"))


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pseudonymised(spark, table(spark, sf_dir, "documents"))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(table(spark, sf_dir, "documents"))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_spans(table(spark, sf_dir, "documents"))


def op10_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.token_counts(table(spark, sf_dir, "documents"), vocabulary())


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_minhash": op1_minhash,
    "op2_language": op2_language,
    "op3_simhash": op3_simhash,
    "op4_jpeg": op4_jpeg,
    "op5_mixing": op5_mixing,
    "op6_lines": op6_lines,
    "op7_pii": op7_pii,
    "op8_packing": op8_packing,
    "op9_secrets": op9_secrets,
    "op10_tokens": op10_tokens,
}

ORACLE_SQL: dict[str, str] = {}
