"""A corpus pipeline of four stages: toxicity, n-gram Jaccard join, benchmark decontamination, mixing.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept and returns a DataFrame, which is
written as Parquet and read again as the next stage's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from brushcube.llm import decontaminate, jaccard_join, mixing, toxicity
from brushcube.llm.common import hand_over, table


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go; null and empty texts stay."""
    model = toxicity.train_on(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic"))
    return docs.withColumn("__toxicity", toxicity.scorer(model)(F.col("text"))).where("__toxicity < 0.5").drop("__toxicity")


def jaccard_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of similar documents one row stays: that with the smallest id (nulls last), of equal ids that whose text has the smallest hash,
    of equal rows any. Rows are told apart by id and text, so a repeated id with unlike texts loses neither. Null and wordless texts are in no group and stay."""
    tag = F.xxhash64("text")
    rows = jaccard_join.jaccard_components(docs.select("doc_id", "text"), tag).where("group is not null")
    rows = hand_over(rows.groupBy("group", "doc_id", "tag").agg(F.count("*").alias("__copies")), "groups")
    first = rows.groupBy("group").agg(F.min(F.struct(F.col("doc_id").isNull().alias("unknown"), "doc_id", "tag")).alias("f"))
    # handed over: a join whose side isn't summed in the same stage can be split where a group is large
    first = hand_over(first.select(F.col("group").alias("of"), F.col("f.doc_id").alias("first_id"), F.col("f.tag").alias("first_tag")), "first-rows")
    same = F.col("doc_id").eqNullSafe(F.col("first_id")) & (F.col("tag") == F.col("first_tag"))
    told = rows.join(first, F.col("group") == F.col("of")).select(F.col("doc_id").alias("__told_id"), F.col("tag").alias("__told_tag"), same.alias("__stays"), "__copies")
    found = F.col("doc_id").eqNullSafe(F.col("__told_id")) & (tag == F.col("__told_tag"))
    out = docs.join(told.where("not __stays"), found, "left_anti")
    twice = told.where("__stays and __copies > 1")
    if twice.isEmpty():
        return out
    once = out.join(twice, found, "left_semi").withColumn("__tag", tag).dropDuplicates(["doc_id", "__tag"]).drop("__tag")
    return out.join(twice, found, "left_anti").unionByName(once)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents contaminated by benchmark items go. Null and empty texts have no words and stay; of repeated ids each row is judged by its own text; without items, or documents, nothing goes."""
    found = decontaminate.decontaminate(docs.select("doc_id", "text", F.xxhash64("text").alias("tag")), table(spark, sf_dir, "benchmark"))
    dirty = found.where("contaminated").select(F.col("doc_id").alias("__dirty_id"), F.col("tag").alias("__dirty_tag")).distinct()
    return docs.join(dirty, F.col("doc_id").eqNullSafe(F.col("__dirty_id")) & (F.xxhash64("text") == F.col("__dirty_tag")), "left_anti")


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the mix takes, with their copies, words taken and their source's target. Null texts have size 0; a null source is a source; rows with one id and source are taken together; no documents make an empty mix."""
    return mixing.mix(docs).where("copies > 0")


BATCH = 1000  # rows of texts that go to a Python worker at once
STAGES = [("toxicity", toxicity_stage), ("jaccard_join", jaccard_stage), ("decontamination", decontamination_stage), ("mixing", mixing_stage)]
ORACLE_SQL = None  # the classifier has no SQL; tests hold run() against a plain version


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = hand_over(stage(spark, docs, sf_dir), f"stage-{name}", batch=BATCH)
    return STAGES[-1][1](spark, docs, sf_dir)
