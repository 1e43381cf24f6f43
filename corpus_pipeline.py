"""A corpus pipeline: language identification, line dedup, near-duplicate removal, decontamination, mixing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents. A
stage works on all rows that the one before it kept. Rows that share a doc_id are one document; a row with a null doc_id
is a document of its own. Null and empty texts go in the first stage. An empty table gives an empty table. Further columns
of docs are left out, whatever their names. Whole texts are read, however long, and never cut.
"""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.llm import decontaminate, language_id, line_dedup, mixing, near_dedup
from graphsummary.llm.common import documents, fold_of, small, store

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter (null and empty texts too) go; lang becomes the predicted language. Without a row to
    learn from, every document is undetermined and goes."""
    model = language_id.learn(docs.where(fold_of("doc_id") != 0).select("text", "lang"))
    judged = language_id.predict(docs.select(*COLUMNS), model)
    return judged.where(F.col("lang_pred") != language_id.NONE).withColumn("lang", F.col("lang_pred")).select(*COLUMNS)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in ten or more documents leave every text; n_chars follows the text."""
    index = line_dedup.LineIndex.of(docs)
    made = index.apply(docs.select(*COLUMNS))
    changed = F.when(F.col("n_dropped") > 0, F.length("text").cast("bigint")).otherwise(F.col("n_chars"))
    return made.withColumn("n_chars", changed).select(*COLUMNS)


def _numbered(docs: DataFrame) -> DataFrame:
    """docs with __id: the doc_id, or for a null one a number of its own beyond every doc_id."""
    nulls = docs.where("doc_id is null")
    if nulls.isEmpty():
        return docs.withColumn("__id", F.col("doc_id"))
    most = docs.agg(F.max("doc_id")).first()[0] or 0
    numbered = store(nulls.withColumn("__id", F.monotonically_increasing_id() + (max(int(most), 0) + 1)), "numbered")
    return docs.where("doc_id is not null").withColumn("__id", F.col("doc_id").cast("bigint")).unionByName(numbered)


def _without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    return docs.join(small(store(gone.distinct(), "gone")), "__id", "left_anti").select(*COLUMNS)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays, the one with the smallest doc_id, null last."""
    own = _numbered(docs.select(*COLUMNS))
    groups = near_dedup.near_duplicates(own, doc_id="__id")
    return _without(own, groups.where(~F.col("kept")).select(F.col("doc_id").alias("__id")))


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item, or the same question with other numbers or names, go."""
    own = _numbered(docs.select(*COLUMNS))
    found = decontaminate.matches(own, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), doc_id="__id")
    return _without(own, found.select(F.col("doc_id").alias("__id")))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the mix takes, with how often (copies) and how many words (taken)."""
    size = mixing.words_in("text")
    sized = store(docs.select("doc_id", "source", mixing.source_key("source").alias("key"), size.alias("size")), "sizes")
    targets = {s: t for s, (_, t) in mixing.source_targets(sized, "key", "size").items()}
    mixed = mixing.mix(docs.select(*COLUMNS).withColumn("size", size), targets, F.array(mixing.source_key("source")), "size", counted=sized)
    return mixed.where("copies > 0").select(*COLUMNS, "copies", F.col("taken").cast("bigint").alias("taken"))


STAGES = [
    ("language identification", language),
    ("line dedup", lines),
    ("near-duplicate removal", near),
    ("benchmark decontamination", clean),
    ("mixing to target weights", mixture),
]

#: Language identification, min-hash tables and mixing have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = store(docs, name.replace(" ", "-"))
    return docs
