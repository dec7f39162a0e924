"""From raw documents to packed sequences: quality rules, near duplicates, benchmark passages, secrets, packing.

Each stage is a function of (spark, docs, sf_dir); its result is written as Parquet and read back as the docs of the next.
All stages but the last return the columns that they were given, whatever their names, and no others; verdicts hold for
rows, so rows without doc_id or with one that stands twice are judged like any other. A stage removes the scratch tables of the stage before it, whose
result has been written by then.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from clusterfuse.functions.deploy import ship
from clusterfuse.llm import decontaminate, near_dup, packing, quality_rules, secrets
from clusterfuse.llm.common import release, scope, store, table

SCRATCH = "pipeline"


def _stage(work):
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        release(ship(spark), SCRATCH)
        with scope(SCRATCH):
            return work(spark, docs, sf_dir)

    return run


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rule and the learned list keep."""
    return quality_rules.kept(docs, quality_rules.learn_from(docs, table(spark, sf_dir, "labels", "doc_id", "quality")))


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest doc_id of each group of near duplicates, once."""
    return near_dup.without_copies(docs)


def keep_clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark window."""
    return decontaminate.without_contaminated(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with every secret masked in the text and n_chars counted anew where a text changed."""
    return secrets.redacted(docs, secrets.train(secrets.labelled_findings(spark)))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of binary lengths with their sequences."""
    return packing.pack(docs, with_ids=False).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


STAGES = [
    ("quality_rules", _stage(keep_quality)),
    ("near_duplicates", _stage(keep_one_of_each)),
    ("decontamination", _stage(keep_clean)),
    ("secret_scan", _stage(redact_secrets)),
    ("packing", _stage(pack_sequences)),
]
#: Components, a learned list and tokenizers are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = store(docs, f"pipeline-{name}")
    return docs


def queries():
    return {"pipeline": run}


def oracle_sql():
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
