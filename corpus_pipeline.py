"""The corpus pipeline: quality rules, line dedup, near-duplicate removal, decontamination, packing.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept.  All but the last return the columns
of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from streamcut.llm.best_fit_packing import pack
from streamcut.llm.decontaminate import remove_contaminated
from streamcut.llm.frames import Scratch, free, salted_join
from streamcut.llm.jaccard_join import jaccard_classes
from streamcut.llm.line_dedup import drop_boilerplate
from streamcut.llm.quality_rules import quality_filter


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no quality rule rejects.  Null and empty texts go (no words); rows that repeat are judged alike."""
    return quality_filter(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Boilerplate lines leave the texts; all rows and other columns stay.

    ``n_chars``, where present, follows a text that changed.  A null text stays null; a null source is a host of its own.
    """
    rest = [c for c in docs.columns if c != "text"]
    rows = drop_boilerplate(docs.select(F.struct(*rest).alias("row"), "source", "text"))
    n_chars = F.when(F.col("n_dropped") > 0, F.length("text")).otherwise(F.col("row.n_chars")).cast(docs.schema["n_chars"].dataType) if "n_chars" in rest else None
    own = {"text": F.col("text"), "n_chars": n_chars}
    return rows.select(*[(own[c] if c in own else F.col("row").getField(c)).alias(c) for c in docs.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the row with the smallest id stays (of equal or no ids, the first numbered).

    Rows are compared as rows: rows that share an id but not their text are different documents, and a row without an
    id can be a copy too.  Texts without words are copies of nothing and stay.
    """
    scratch = Scratch(spark, "copies")
    nth = free(docs, "nth")
    keyed = scratch.keep(docs.withColumn(nth, F.monotonically_increasing_id()), "rows")
    classes = jaccard_classes(keyed.select(F.col(nth).alias("doc_id"), "text")).select(F.col("doc_id").alias(nth), F.col("component_id").alias("group"))
    classes = scratch.keep(classes.join(keyed.select(nth, F.col("doc_id").alias("id")), nth), "classes")
    many = classes.groupBy("group").agg(F.count("*").alias("n"), F.min(F.struct(F.col("id").isNull().alias("none"), F.col("id").alias("id"), F.col(nth).alias("nth"))).alias("first")).where("n > 1")
    gone = salted_join(classes, many.select("group", F.col("first.nth").alias("stays")), "group").where(F.col(nth) != F.col("stays")).select(nth)
    return keyed.join(gone, nth, "left_anti").select(docs.columns)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that aren't contaminated by the benchmark.  Null texts stay; each row is judged by its own text."""
    return remove_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The packed pieces.  A null text is one piece of one token; rows that share an id are pieces of their own."""
    return pack(docs)


STAGES = [
    ("quality_rules", quality),
    ("line_dedup", lines),
    ("ngram_jaccard_join", near_duplicates),
    ("benchmark_decontamination", decontamination),
    ("best_fit_packing", packing),
]

#: Trained vocabularies, shingle links and the packing plan have no SQL form; tests compare with plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = scratch.keep(stage(spark, docs, sf_dir), name)
    return docs
