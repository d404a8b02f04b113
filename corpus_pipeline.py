"""Corpus pipeline: language ID, near duplicates, substring dedup, decontamination, packing.

Each stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame; all but the
last return the columns of ``docs``.  ``run`` writes each stage's result as Parquet
in the shared folder and reads it again as the next stage's input.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.llm import decontaminate, jaccard, langid, packing, substring
from tallquant.llm.common import Workspace

#: Words of the shortest passage that substring dedup removes.
PASSAGE_WORDS = 30
#: Words of a benchmark window, and of the shortest item that can condemn a document.
WINDOW_WORDS, LEAST_ITEM_WORDS = 10, 6
#: Chunks whose ids a worker keeps: earlier stages leave an executor more workers than cores, and each keeps its own.
CACHED_CHUNKS = 200_000


def _boxed(docs: DataFrame) -> tuple[DataFrame, str]:
    """``doc_id, text`` and the other columns as one struct, whose name no column has; so none can clash with a result, and texts travel once."""
    name = "tallquant_row"
    while name in {c.lower() for c in docs.columns}:
        name += "_"
    return docs.select("doc_id", "text", F.struct(*[F.col(f"`{c}`") for c in docs.columns if c != "text"]).alias(name)), name


def _unboxed(frame: DataFrame, name: str, docs: DataFrame, **new) -> DataFrame:
    """The columns of ``docs`` again, some of them new."""
    return frame.select(*[(new[c].cast(kind) if c in new else F.col("text") if c == "text" else F.col(name)[c]).alias(c) for c, kind in docs.dtypes])


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised; rejected ones (no letter, or far from every centroid) go."""
    model = langid.learn(spark, docs, F.lit(True))
    boxed, name = _boxed(docs)
    return _unboxed(langid.identify(spark, boxed, model, keep=[name, "text"]).where("not rejected"), name, docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one of smallest doc_id.

    Of rows of a group that share that identifier the one of smallest hash stays;
    unrelated texts stay whatever their identifiers are, and so do documents without words.
    """
    groups = jaccard.similar_groups(spark, docs, shingle=5, similarity=(80, 100))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "key"))
    members = groups.where("n_shingles > 0")
    heads = members.groupBy("component").agg(first.alias("h")).select("h.key")
    stay = heads.union(groups.where("n_shingles = 0").select("key").distinct())
    boxed, name = _boxed(docs)
    keyed = boxed.select(name, "text", F.xxhash64("doc_id", "text").alias("key"), F.col("text").rlike(r"[^\x20\x09-\x0D]").alias("words"))
    left = keyed.join(stay.hint("shuffle_hash"), "key", "left_semi")
    whole = left.where("words").dropDuplicates(["key"])
    empty = left.where(F.coalesce(~F.col("words"), F.lit(True)))
    return _unboxed(whole.union(empty), name, docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that an earlier document holds are cut out; documents emptied by that go."""
    boxed, name = _boxed(docs)
    kept = substring.dedup_substrings(spark, boxed, width=PASSAGE_WORDS, keep=[name]).where("n_removed < n_words or n_words = 0")
    return _unboxed(kept, name, docs, text=F.col("kept_text"), n_chars=F.length("kept_text"))


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    boxed, name = _boxed(docs)
    found = decontaminate.decontaminate(spark, boxed, benchmark, width=WINDOW_WORDS, least_words=LEAST_ITEM_WORDS, keep=[name, "text"])
    return _unboxed(found.where("not contaminated"), name, docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of at most 2048 tokens: one row for each piece."""
    return packing.pack(spark, docs, width=2048, cached=CACHED_CHUNKS)


STAGES = [
    ("language_id", language_id),
    ("near_duplicates", near_duplicates),
    ("substring_dedup", substring_dedup),
    ("decontamination", decontamination),
    ("packing", pack),
]

#: Learned and token-based stages have no SQL; tests compare them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of ``sf_dir``."""
    work = Workspace(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = work.save(stage(spark, docs, sf_dir), name)
    return docs
