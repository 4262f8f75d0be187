"""A corpus pipeline of five stages over ``documents``.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read
back as the next stage's input; all but the last keep the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubegrid.llm import decontaminate, language_id, line_dedup, mixing, near_dup
from cubegrid.llm.common import fresh, stored, table


def _columns(docs: DataFrame) -> list:
    return [F.col(f"`{c}`") for c in docs.columns]


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a recognisable language go: null or letterless text, or an undecided score."""
    lang, score = fresh(docs.columns, "lang_seen", "lang_score")
    model = language_id.fit(docs, ~language_id.is_held_out(F.col("doc_id")))
    seen = language_id.predict(docs, model, keep=tuple(docs.columns), names=(lang, score))
    if not model.langs:  # nothing to learn from: only what has no letter is rejected
        return docs.where(F.col("text").rlike(r"\p{L}"))
    return seen.where((F.col(lang) != "und") & (F.col(score) >= 0.5)).select(*_columns(docs))


def remove_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated line runs are cut out; a document left without any line goes."""
    lines, removed, runs = fresh(docs.columns, "lines_had", "lines_cut", "runs_cut")
    out = line_dedup.dedup_lines(docs, counts=(lines, removed, runs))
    out = out.where((F.col(removed) == 0) | (F.col(removed) < F.col(lines)))
    changed = F.when(F.col(removed) > 0, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))
    return out.withColumn("n_chars", changed).select(*_columns(docs))


def keep_one_of_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class stays."""
    return near_dup.drop_near_duplicates(docs)


def remove_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the contamination rule marks go."""
    own, body = fresh(docs.columns, "bad_id", "bad_text")
    marked = decontaminate.contamination(docs, table(spark, sf_dir, "benchmark"))
    bad = marked.where("contaminated").select(F.col("doc_id").alias(own), F.col("text_hash").alias(body)).distinct()
    same = F.col("doc_id").cast("long").eqNullSafe(F.col(own)) & F.xxhash64("text").eqNullSafe(F.col(body))
    return docs.join(bad, same, "left_anti")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document gets its place in the mix of sources."""
    return mixing.mix(docs)


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", remove_repeated_lines),
    ("near_duplicates", keep_one_of_near_duplicates),
    ("decontamination", remove_contaminated),
    ("mixing", mix_sources),
]

#: The models and iterative stages have no SQL form; the tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
