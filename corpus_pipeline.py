"""A cleaning pipeline over documents: language, repeated lines, near duplicates, benchmark passages, packing.

Every stage takes (spark, docs, sf_dir) and works on all rows that the stage before kept. All but the last return the columns of docs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecgraph.llm.common import materialize, table
from vecgraph.llm.decontaminate import flag_contaminated
from vecgraph.llm.language_id import LanguageFilters
from vecgraph.llm.line_dedup import dedup_lines
from vecgraph.llm.near_join import keep_one
from vecgraph.llm.packing import pack


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no learned language is found go: null texts and texts without a letter."""
    found = LanguageFilters.fit(docs).predict(docs.withColumnsRenamed({c: f"_in_{c}" for c in ("lang_pred", "score") if c in docs.columns}))
    kept = found.where(F.col("lang_pred") != "und").drop("lang_pred", "score")
    return kept.withColumnsRenamed({f"_in_{c}": c for c in docs.columns})


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that at least ten documents hold go from every text; documents stay, even without lines."""
    found = dedup_lines(docs)
    columns = {"text": F.col("kept_text"), "n_chars": F.char_length("kept_text").cast("long")}
    return found.select(*(columns[c].alias(c) if c in columns else F.col(f"`{c}`") for c in docs.columns))


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates stays."""
    return keep_one(docs)


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that contain a benchmark item go."""
    items = table(spark, sf_dir, "benchmark").select("text")
    return flag_contaminated(docs, items, out="_hit").where(~F.col("_hit")).drop("_hit")


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs)


STAGES = [("language_id", language_stage), ("line_dedup", line_stage), ("near_join", near_stage), ("decontaminate", benchmark_stage), ("packing", packing_stage)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
