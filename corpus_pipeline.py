"""The corpus pipeline: stages over `documents`, each written and read again.

Language ID drops texts without a language, line dedup takes repeated lines out, near
dedup keeps one document of each group, mixing repeats rare sources, packing fills bins.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from parsieve.llm import langid, lines, minhash, mixing, packing
from parsieve.llm.common import Cuts, table

STAGES = [
    ("language_id", lambda spark, docs, sf_dir: langid.language_filter(spark, docs)),
    ("line_dedup", lambda spark, docs, sf_dir: lines.line_dedup(spark, docs)),
    ("near_dedup", lambda spark, docs, sf_dir: minhash.keep_one(spark, docs)),
    ("mixing", lambda spark, docs, sf_dir: mixing.mix_stage(spark, docs)),
    ("packing", lambda spark, docs, sf_dir: packing.pack_stage(spark, docs)),
]

# The first three stages are a trained model and two iterative searches, which SQL cannot
# express; the tests hold the pipeline against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written as Parquet and read again."""
    cuts = Cuts(spark)
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        kept = cuts.cut(stage(spark, docs, sf_dir), name)
        cuts.drop(docs)  # what the stage before wrote
        docs = kept
    return STAGES[-1][1](spark, docs, sf_dir)
