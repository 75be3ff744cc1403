"""A corpus pipeline of five stages, each applying one training-data operator to what the stage before it kept.

What holds for every stage: extra columns pass through whatever their names, in a struct that no operator looks into;
a null text is an empty one to the operator and stays null; repeated rows, ties, very long texts and empty tables have
the results that the stage's docstring names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from residua.llm import curriculum, jaccard, langid, pieces, secrets
from residua.llm.common import cut, table
from residua.llm.queries import vocabulary

#: SQL can express neither the language profiles nor the tokenizer.
ORACLE_SQL = None

#: A prediction below this score is no language that was learnt (clean texts of a few words score 0.4 and more).
LEAST_SCORE = 0.2


def packed(docs: DataFrame, *own: str) -> DataFrame:
    """The columns that an operator reads, and all others as one struct ``rest``."""
    others = [F.col(f"`{c}`") for c in docs.columns if c not in own]
    return docs.select(*own, F.struct(*others, F.lit(0).alias("__none")).alias("rest"))


def unpacked(rows: DataFrame, docs: DataFrame, *own: str) -> DataFrame:
    """The columns of ``docs`` again, in their order."""
    return rows.select(*[F.col(c) if c in own else F.col("rest").getField(c).alias(c) for c in docs.columns])


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts of no known language go; the others carry the predicted one.

    Profiles come from the rows with text and lang. A text that is null, empty or without a letter goes, and so do all
    texts if no row has a lang. Ties go to the first language by code point; repeated rows are judged alike; long texts
    are read whole; an empty table gives an empty one.
    """
    profiles = langid.learn(docs.select("text", "lang"))
    found = langid.predict(packed(docs, "text"), profiles, keep=("text", "rest"))
    kept = found.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SCORE))
    return kept.select(*[F.col("text") if c == "text" else F.col("lang_pred").alias(c) if c == "lang" else F.col("rest").getField(c).alias(c) for c in docs.columns])


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of similar texts (five-word shingles, similarity 0.8), the rows of the smallest id stay, each text of an id once.

    Null, empty and wordless texts resemble nothing and stay. Rows with a null id are no vertices and stay, equal ones once.
    Of rows that repeat an id and text one stays, whichever. An empty table gives an empty one.
    """
    found = jaccard.near_sets(docs.select("doc_id", "text"), words=5, percent=80)
    gone = found.where("doc_id <> component_id").select(F.col("doc_id").alias("__gone")).distinct()
    rows = packed(docs, "doc_id", "text")
    kept = rows.join(gone, rows["doc_id"] == gone["__gone"], "left_anti")
    once = kept.withColumn("__digest", F.sha2("text", 256)).dropDuplicates(["doc_id", "__digest"])
    return unpacked(once, docs, "doc_id", "text")


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every secret found is replaced in its text; n_chars follows. No row goes; null texts and their n_chars stay as they are."""
    masked = unpacked(secrets.redacted(secrets.scan(packed(docs, "doc_id", "text"))), docs, "doc_id", "text")
    if "n_chars" not in docs.columns:
        return masked
    return masked.withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars")))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the mix takes, as often as it takes them whole or in part, range-sorted by training position.

    Documents without words, null texts among them, take no place in a mix of words and go. Null sources are one source.
    Repeated rows count each. An empty table gives an empty one.
    """
    mixed = curriculum.mix(packed(docs, "doc_id", "source", "text"), keep=("doc_id", "text", "rest"))
    times = F.when(F.col("size") > 0, F.ceil(F.col("taken") / F.greatest(F.col("size"), F.lit(1)))).otherwise(0).cast("int")
    rows = mixed.where("taken > 0").withColumn("__pass", F.explode(F.sequence(F.lit(1), times)))
    at = F.when(F.col("__pass") == 1, F.col("position")).otherwise(F.col("last_position"))
    return unpacked(rows.withColumn("__at", at).orderBy("__at", "doc_id", "__pass"), docs, "doc_id", "source", "text")


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of each document the mix holds; a null text is an empty one, repeated rows stay, an empty table gives an empty one."""
    return pieces.encode_column(docs, vocabulary(), keep=["doc_id", "source"])


STAGES = [("language_id", identify_language), ("ngram_jaccard", drop_near_copies), ("secret_scan", mask_secrets), ("curriculum_mix", mix_sources), ("sentencepiece", encode)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = cut(docs)
    return docs
