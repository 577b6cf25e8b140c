"""A corpus pipeline: five stages, each by one of the corpus operators, each on all that its predecessor kept.

Every stage takes the rows of ``documents`` with whatever columns they have and returns those columns, the last apart,
which returns the packing. Null texts have no language and go in the first stage. Rows without an id are told apart by
their text. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.llm import langid, nearcopies, packing, quality, substrings
from weftgraph.llm.common import crc_mod, read, stored

#: A document goes if no language has at least this mean posterior.
LEAST_LANGUAGE_SCORE = 0.4


def _free(docs: DataFrame, name: str) -> str:
    """A column name that the rows do not have."""
    while name in docs.columns:
        name += "_"
    return name


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep texts in a language that the corpus is labelled with."""
    model = langid.train(docs.select("doc_id", F.col("text").cast("string").alias("text"), "lang").where(crc_mod("doc_id", 3) != 1))
    lang, score = _free(docs, "lang_pred"), _free(docs, "score")
    told = langid.predict(docs, model, keep=tuple(docs.columns), names=(lang, score))
    return told.where((F.col(lang) != langid.UNKNOWN) & (F.col(score) >= LEAST_LANGUAGE_SCORE)).select(*docs.columns)


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep texts that score at least the classifier's threshold."""
    labels = read(spark, sf_dir, "labels").where(crc_mod("doc_id", 5) != 0)
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    model = quality.train(own.where(crc_mod("doc_id", 5) != 0), labels)
    score = _free(docs, "score")
    return quality.predict(docs, model, keep=tuple(docs.columns), name=score).where(F.col(score) >= quality.THRESHOLD).select(*docs.columns)


def one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group linked by whole-text Jaccard similarity of 0.8 or more (five-word shingles) keep the document with the smallest id."""
    own = F.coalesce(F.col("doc_id").cast("long"), -F.abs(F.xxhash64(F.coalesce(F.col("text"), F.lit("")))))
    base = docs.select(F.struct(own.alias("id"), F.xxhash64(F.col("text").cast("string")).alias("at")).alias("_id"), F.col("text").cast("string").alias("text"), F.struct(*docs.columns).alias("_all"))
    groups = nearcopies.near_copies(base.select("_id", "text"), "_id")
    kept = groups.groupBy("_id", "component_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("_id") == F.col("component_id")).select("_id", "n")
    rest = base.select("_id", "_all").join(kept, "_id")
    repeated = rest.where("n > 1").dropDuplicates(["_id"])
    return rest.where("n = 1").unionByName(repeated).select("_all.*")


def no_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Take windows of 20 words that stand earlier out of the texts."""
    out = substrings.without_repeats(docs)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack what is left into bins."""
    return packing.best_fit(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "source"))


STAGES = [
    ("language", language),
    ("quality", good_quality),
    ("near_duplicates", one_of_near_copies),
    ("repeated_windows", no_repeats),
    ("packing", packed),
]

#: Learned models, fingerprints' components and packing have no SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
