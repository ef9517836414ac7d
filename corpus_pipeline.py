"""Five stages over a document table, each on all that the stage before kept."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bicommunity.llm import mixing, packing, quality, resemblance, substring
from bicommunity.llm.store import new_path, read


def _shielded(docs: DataFrame, *used: str) -> tuple[DataFrame, list[Column]]:
    """``docs`` as the used columns and one struct of all others, which no operator can take for its own; and the
    expressions that give the columns of ``docs`` back."""
    others = [c for c in docs.columns if c not in used]
    row = F.struct(*[F.col(f"`{c}`") for c in others]) if others else F.lit(None).cast("int")
    back = [F.col(c) if c in used else F.col("row")[c].alias(c) for c in docs.columns]
    return docs.select(*used, row.alias("row")), back


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the classifier. Null, blank and very short texts fail the base
    rules; repeated rows are judged each; an empty table, or one without labels, is judged by the base rules alone.
    Columns of any name are handed on."""
    model = quality.train(docs.select("doc_id", "text"), read(spark, sf_dir, "labels"))
    own, back = _shielded(docs, "doc_id", "text")
    return quality.judge(own, model).filter("kept").select(*back)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document (the smallest doc_id) of each group of texts that share 0.8 of their
    five-word shingles or more. Texts without a word are one group; fully repeated rows are one document; rows
    without a doc_id stay; an empty table stays empty. Columns of any name are handed on."""
    return resemblance.keep_one(docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages that a smaller doc_id has; documents that lose all their words
    go. A text that loses nothing, a null or blank one too, stays as it is; rows that repeat a doc_id don't count against one
    another, and rows without a doc_id stay; an empty table stays empty. n_chars follows the text; other columns, of any name, are handed on."""
    own, back = _shielded(docs, "doc_id", "text")
    kept = substring.dedup_windows(own, rejoin=False).filter("n_removed = 0 or n_removed < n_words")
    to = dict(zip(docs.columns, back))
    to["doc_id"] = F.col("doc_id").cast(docs.schema["doc_id"].dataType)
    to["text"] = F.col("kept_text").alias("text")
    if "n_chars" in to:
        size = F.when(F.col("n_removed") > 0, F.length("kept_text")).otherwise(F.col("row")["n_chars"])
        to["n_chars"] = size.cast(docs.schema["n_chars"].dataType).alias("n_chars")
    return kept.select(*[to[c] for c in docs.columns])


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it. Null texts have size 0 and a null source is a source;
    repeated rows share their copies; an empty table stays empty. Columns of any name are handed on."""
    return mixing.mixed_rows(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Length buckets and token-budget batches; texts without words (null, blank) have a row of length 0 and no bucket,
    repeated rows are packed each, an empty table gives an empty result."""
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [
    ("quality", quality_rules),
    ("near_dedup", near_dedup),
    ("substring_dedup", substring_dedup),
    ("mixing", mix_sources),
    ("packing", packing_stage),
]

#: The classifier and the hash-based groups can't be said in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read back as the documents of the next. Nulls, blanks, repeated
    rows, empty tables and clashing columns as the stages say."""
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = new_path(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
