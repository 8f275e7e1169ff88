"""A corpus pipeline: language, exact copies, near copies, source weights, sequences.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() applies all of them to the
table of documents, writing each result as Parquet and reading it again.

Stages decide on rows, not on ids: where a doc_id is null or repeated, rows are numbered in the
order of doc_id (null first) and text, and that number stands in for the id.  Null and empty texts
are defined in each stage; an empty table gives no rows; columns other than those of documents are
left behind.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from itemlens.llm import exact_dedup, language_id, mixing, packing, similarity_join
from itemlens.llm.common import checkpointed, ranked, table

#: A text whose best language has less than this share of the posterior is rejected, as is one without letters.
LEAST_LANGUAGE_SCORE = 0.5
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def with_rows(docs: DataFrame) -> DataFrame:
    """The columns of documents and `row`, a number of each row: its doc_id where all are given and unique, else its rank by doc_id and text."""
    docs = docs.select(COLUMNS)
    seldom = docs.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 or doc_id is null")
    if seldom.isEmpty():
        return docs.withColumn("row", F.col("doc_id").cast("long"))
    return ranked(docs, "doc_id", "text", "source", "lang", name="row")


def _by_row(docs: DataFrame) -> DataFrame:
    return docs.withColumn("doc_id", F.col("row"))


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts in some language the model knows; null, empty and letterless texts go.  Equal rows are treated alike."""
    verdict = language_id.identified(docs.select(COLUMNS), carry=COLUMNS[1:])
    return verdict.where(F.col("lang_pred") != language_id.UNKNOWN).where(F.col("score") >= LEAST_LANGUAGE_SCORE).select(COLUMNS)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the row with the largest doc_id: one row of each, also where ids are repeated or null.  Null counts as the empty text."""
    rows = with_rows(docs)
    kept = exact_dedup.exact_duplicates(_by_row(rows)).where("kept").select(F.col("doc_id").alias("row"))
    return rows.join(kept, "row", "left_semi").select(COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, the row with the smallest doc_id (null first).  Texts without words are copies of nothing and stay."""
    rows = with_rows(docs)
    kept = similarity_join.similarity_classes(_by_row(rows)).where("doc_id = component_id").select(F.col("doc_id").alias("row"))
    return rows.join(kept, "row", "left_semi").select(COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as its source's weight and its length make of it: not at all, once or twice.  Texts without words go; null sources are one source."""
    rows = with_rows(docs)
    copies = mixing.mixed(_by_row(rows)).where("copies > 0").select(F.col("doc_id").alias("row"), "copies")
    repeated = rows.join(copies, "row").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies"))))
    return repeated.select(COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all rows with their places in sequences; a repeated row is packed as often as it comes, an empty text as its end alone."""
    return packing.packed(docs)


STAGES = [
    ("language_id", identify_language),
    ("exact_dedup", drop_exact_copies),
    ("ngram_join", drop_near_copies),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Language scores, components and packing are beyond SQL; tests/llm compares each stage with plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = checkpointed(stage(spark, docs, sf_dir))
    return docs
