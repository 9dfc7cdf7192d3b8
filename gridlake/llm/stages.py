"""The stages of the corpus pipeline, each over a table of documents.

quality     importance resampling; documents that it rejects go
near        exact Jaccard join; the first document of each component stays
substrings  bytes of strings that repeat are removed from the texts
private     personal data is replaced by its kind
packed      what is left is packed into token sequences (the last stage's rows)

Defined results: a null text counts as empty and stays null where no stage changes it; a
null id has no label, stays a document of its own and is never merged with another by its
id; repeated rows are separate documents, of which ``near`` keeps the one with the least row
key (ids where they are unique, else the order of reading); ties of ``quality`` go to that key
too; an empty table gives an empty table with the same columns from every stage; columns
beside those of the documents are kept as they are, whatever their names, up to ``packed``;
``n_chars``, where there is one, is the text's length after ``substrings`` and ``private``;
texts of any length are worked on whole.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridlake.llm import bin_packing, jaccard_join, pii_supervision, quality_resampling, substring_dedup
from gridlake.llm.common import RID, Scratch, numbered
from gridlake.llm.queries import tokenizer


def _counted(docs: DataFrame, columns: list[str]) -> DataFrame:
    """The columns of the documents, ``n_chars`` as the text is now."""
    if "n_chars" in columns:
        docs = docs.withColumn("n_chars", F.length("text").cast("long"))
    return docs.select(*columns)


def _chosen(docs: DataFrame, kept: DataFrame, columns: list[str]) -> DataFrame:
    return docs.join(kept.select(F.col("rid").alias(RID)), RID, "left_semi").select(*columns)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    with Scratch(spark, "quality") as s:
        rows = numbered(s, docs)
        scored = quality_resampling.resample(s, rows, spark.read.parquet(f"{sf_dir}/labels.parquet"))
        return _chosen(rows, scored.where("selected"), docs.columns)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    with Scratch(spark, "near") as s:
        rows = numbered(s, docs)
        return _chosen(rows, jaccard_join.join_components(s, rows).where("rid = first_rid"), docs.columns)


def substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    with Scratch(spark, "substrings") as s:
        rows = numbered(s, docs)
        cut = substring_dedup.dedup(s, rows, texts=True).where("n_removed > 0").select(F.col("rid").alias(RID), F.col("kept").alias("__gridlake_kept"))
        return _counted(rows.join(cut, RID, "left").withColumn("text", F.coalesce("__gridlake_kept", "text")), docs.columns)


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    with Scratch(spark, "private") as s:
        # the candidates are found once, for the fit and for the redaction
        found = s.keep(pii_supervision.with_candidates(docs), "candidates")
        return _counted(pii_supervision.redacted(found, pii_supervision.fit_table(found)), docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bin_packing.pack_documents(docs, tokenizer())


STAGES = [("quality classifier", quality), ("n-gram Jaccard join", near), ("suffix-array dedup", substrings), ("PII", private), ("best-fit packing", packed)]
