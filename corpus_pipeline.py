"""A corpus pipeline of the training-data operators: each stage's rows are written as Parquet and read by the next.

In order: toxic documents go, later copies of line runs go, one document of each near-duplicate class stays, documents
that hold a benchmark item go, and what is left is packed into sequences. All stages but the last keep the columns of
documents; the last gives one row per packed piece.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from meshcut.llm import common
from meshcut.llm.contamination import drop_leaks
from meshcut.llm.line_dedup import drop_later_lines
from meshcut.llm.near_stage import drop_near_copies
from meshcut.llm.packing import pack_kept
from meshcut.llm.toxicity import drop_toxic

STAGES = [
    ("toxicity", drop_toxic),
    ("line dedup", drop_later_lines),
    ("simhash near-dedup", drop_near_copies),
    ("benchmark decontamination", drop_leaks),
    ("packing", pack_kept),
]

#: Word fingerprints, a fitted classifier and a tokenizer have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = common.written(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return docs
