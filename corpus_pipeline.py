"""The corpus pipeline: quality rules, near-duplicate join, benchmark decontamination, packing.

``STAGES`` lists (name, function); each function takes (spark, docs, sf_dir) and works on
all rows that its predecessor kept. All but the last return the columns of documents.
Rows come in with any extra columns and in any order; an empty table goes through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpusdedup.llm.decontaminate import drop_contaminated
from corpusdedup.llm.ngram_join import similar_components
from corpusdedup.llm.packing import pack, word_lengths
from corpusdedup.llm.quality import fit, keep_good
from corpusdedup.session import spread, stage

#: No SQL grows an isolation forest or packs bins.
ORACLE_SQL = None


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop what the base rules or the isolation forest reject."""
    return keep_good(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of similar documents keep the one with the smallest doc_id.

    Rows without id are kept: nothing says which of them others repeat. Rows that repeat
    an id and its text count as copies, and one stays; other texts of the id are
    documents of their own, and of similar ones with one id that of the smallest MD5 stays.
    """
    twice = stage(docs.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("__copies")).where("__copies > 1").select(F.col("doc_id").alias("__twice")), "pipeline-repeated")
    if not twice.isEmpty():
        return _near_duplicates_by_text(docs, twice)
    away = similar_components(docs.select("doc_id", "text")).where("doc_id != component_id").select(F.col("doc_id").alias("__away"))
    return docs.join(away, docs["doc_id"] == away["__away"], "left_anti")


def _near_duplicates_by_text(docs: DataFrame, twice: DataFrame) -> DataFrame:
    """The same where ids repeat: every further text of such an id gets an unused id for the join."""
    key = F.coalesce(F.md5("text"), F.lit(""))
    low, high = docs.agg(F.min("doc_id"), F.max("doc_id")).first()
    room = 2**48
    if high + room < 2**63:
        fresh = F.lit(high + 1) + F.monotonically_increasing_id()
    elif low - room >= -(2**63):
        fresh = F.lit(low - 1) - F.monotonically_increasing_id()
    else:
        raise ValueError("no unused ids beyond the given ones")
    texts = docs.join(twice, docs["doc_id"] == twice["__twice"], "left_semi").select(F.col("doc_id").alias("__id"), key.alias("__text")).distinct()
    seat = F.row_number().over(Window.partitionBy("__id").orderBy("__text"))
    further = stage(texts.withColumn("__seat", seat).where("__seat > 1").select("__id", "__text", fresh.alias("__new")), "pipeline-texts")
    keyed = docs.withColumn("__key", key)
    keyed = keyed.join(further, (keyed["doc_id"] == further["__id"]) & (keyed["__key"] == further["__text"]), "left")
    keyed = keyed.withColumn("__node", F.coalesce("__new", "doc_id")).select(*docs.columns, "__key", "__node")
    comps = similar_components(keyed.select(F.col("__node").alias("doc_id"), "text")).where("doc_id is not null").select(F.col("doc_id").alias("__same"), "component_id").distinct()
    nodes = keyed.select("__node", F.col("doc_id").alias("__id"), "__key").distinct()
    named = stage(nodes.join(comps, F.col("__node") == F.col("__same")).drop("__same"), "pipeline-nodes")
    first = named.groupBy("component_id").agg(F.min_by("__node", F.struct("__id", "__key")).alias("__first"))
    gone = named.join(first, "component_id").where("__node != __first").select(F.col("__node").alias("__gone"))
    kept = keyed.join(gone, F.col("__node") == F.col("__gone"), "left_anti").select(*docs.columns)
    again = F.col("doc_id") == F.col("__twice")
    return kept.join(twice, again, "left_anti").unionByName(kept.join(twice, again, "left_semi").dropDuplicates(["doc_id", "text"]))


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that hold a benchmark item within its edit budget."""
    return drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Place the remaining documents' tokens in bins: one row for each piece."""
    return pack(word_lengths(docs)).drop("row")


STAGES = [("quality_rules", quality_rules), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("packing", packing)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again."""
    docs = spread(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    for name, function in STAGES[:-1]:
        docs = stage(function(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
