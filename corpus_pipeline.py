"""From raw documents to packed sequences: the stages, in order, and one call that runs them.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as
Parquet and read again as the next one's docs.  All stages but the last return the
columns of documents; texts that a stage changes get their new n_chars.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from signpart.llm import jaccard_join, language_id, line_dedup, mixing, packing, store

#: A language is told if its share of the hits is so many times the equal share of all learned languages.
LEAST_ADVANTAGE = 1.2


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a letter, and those whose n-grams are spread over the languages as chance would spread them.

    A text that has a letter but no known n-gram, as a very short one, stays: nothing
    speaks against it.  With one learned language, or none, only letters count.
    Null texts go; repeated rows share one fate; columns of any name are kept.
    """
    learned = docs.where(~language_id.held_out() & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("key"), "text", "lang")
    filters = language_id.fit(learned)
    if filters is None:
        return docs.where(F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)))
    # Beside the document, whose own columns may be called lang_pred or score.
    found = language_id.predict(docs.select("text", F.struct(*docs.columns).alias("doc")), filters)
    share = F.col("score") * len(filters.languages)
    told = (F.col("score") == 0) | (share >= LEAST_ADVANTAGE) | F.lit(len(filters.languages) < 2)
    return found.where((F.col("lang_pred") != language_id.UNDECIDED) & told).select("doc.*")


def without_common_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops lines that stand in ten documents or more; n_chars follows the text.

    A null text becomes empty; each row is a document, also if doc_ids repeat or are null.
    """
    found = line_dedup.line_dedup(docs).withColumn("n_chars", F.length("text").cast("long"))
    return found.select(*docs.columns)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document, that of the least doc_id, of each group of near copies (five words, 0.8).

    Documents without words and those with a null doc_id stay; rows that share the least doc_id all stay.
    """
    groups = jaccard_join.jaccard_groups(docs, words=5, percent=80)
    extra = store.written(groups.where("doc_id <> component_id").select("doc_id").distinct())
    return docs.join(store.broadcast_if_small(extra), "doc_id", "left_anti").select(*docs.columns)


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats or drops documents until the sources have their target weights; a null source is a source."""
    return mixing.repeated(mixing.mix_sources(docs), docs.columns)


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the tokenised documents; one row for each piece; a null text is the end mark alone."""
    return packing.pack_documents(docs)


STAGES = [
    ("language ID", known_language),
    ("line dedup", without_common_lines),
    ("n-gram Jaccard join", one_of_each_group),
    ("mixing sources", mixed_sources),
    ("best-fit packing", packed_sequences),
]

#: Language filters and tokens are beyond SQL; the tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = store.table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = store.written(stage(spark, docs, sf_dir))
    return docs
