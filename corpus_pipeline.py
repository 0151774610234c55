"""A corpus in five stages: language, near duplicates, benchmark leaks, personal data, mixing.

Every stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the
last return the columns of `documents`, each is written as Parquet and read again for the next.

Defined cases: empty tables stay empty; documents without text go at the first stage, as they have no
language; repeated rows and rows with a null id are kept or dropped alike, but rows of one id are one
document for the near duplicates; further columns pass through all stages, whatever their names,
except that the last one replaces columns called like its own (size, source_size, target, taken).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from driftlattice.llm import decontaminate, jaccard, language, mixing, private_terms
from driftlattice.llm.shared import written


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The surviving documents with the words that the mix takes of each (repeats counted)."""
    own = ("doc_id", "size", "source_size", "target", "taken")
    return mixing.mix(docs, keep=[c for c in docs.columns if c.lower() not in own])


STAGES = [
    ("language", language.stage),
    ("near_duplicates", jaccard.stage),
    ("decontamination", decontaminate.stage),
    ("personal_data", private_terms.stage),
    ("mixing", mixed),
]

#: Language models, set joins and learned terms are beyond SQL; tests hold the pipeline against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = written(docs)
    return docs
