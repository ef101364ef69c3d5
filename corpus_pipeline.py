"""A corpus pipeline over documents: language, lines, near-duplicates, mix, pieces."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from transit_engine.llm import curriculum_mix, language_id, line_dedup, piece_lattice, simhash_vptree
from transit_engine.llm.common import materialise

#: (name, function of (spark, docs, sf_dir)); each works on all that the one before kept.
STAGES = [
    ("language_id", language_id.stage),
    ("line_dedup", line_dedup.stage),
    ("simhash_near_dedup", simhash_vptree.stage),
    ("curriculum_mix", curriculum_mix.stage),
    ("piece_encoding", piece_lattice.stage),
]

#: A trained network decides the first stage, which SQL can't express; tests compare each stage with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; every stage's result is written and read again by the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
