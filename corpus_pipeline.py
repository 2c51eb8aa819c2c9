"""The corpus pipeline: documents in, a deduplicated and mixed corpus out.

Five stages, each over all that the one before it kept: texts in no language go; boilerplate lines spread over ten sites or more are cut; of
near-duplicates (five-word shingles, similarity 0.8 or more, or fingerprints within two bits) one document stays; documents
with a benchmark window go; sources are mixed to their target weights. All stages but the last return the columns of
documents. Language identification and similarity are beyond SQL, so there is no ORACLE_SQL; the tests hold run()
against a plain Python version.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trilist.llm import decontaminate, language, lines, mixing, similar
from trilist.llm.common import materialise, read_table

ORACLE_SQL = None


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Reject texts that are null or have no letter; the model learns from the rows themselves, as in op5.

    Where no row has a language to learn from, all texts with a letter stay.
    """
    model = language.train(docs.filter(F.col("doc_id").isNotNull() & ~language.held_out()).select("text", "lang"))
    if not model.families:
        return docs.filter(F.col("text").rlike(r"\p{L}"))
    return language.predict(docs, model).filter("lang_pred <> 'und'").select("doc.*")


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Shorten texts by their boilerplate lines, short ones too, and set n_chars anew; every document stays."""
    done = lines.dedup_lines(docs, min_chars=1)
    new = {"text": F.col("text"), "n_chars": F.when(F.col("n_gone") > 0, F.length("text")).otherwise(F.col("doc.n_chars")).cast(docs.schema["n_chars"].dataType)}
    return done.select(*(new.get(c, F.col(f"doc.`{c}`")).alias(c) for c in docs.columns))


def dedup_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates, the document with the smallest doc_id stays."""
    return similar.near_duplicates(docs).filter("stays").select("doc.*")


def decontaminate_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Remove documents that hold a ten-word window of a benchmark item."""
    found = decontaminate.contamination(docs, read_table(spark, sf_dir, "benchmark"))
    return found.filter("n_hit = 0").select("doc.*")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Mix sources to their targets: the rows taken, with mix_size, mix_taken and mix_copies."""
    return mixing.mix_documents(docs)


STAGES = [
    ("language identification", identify_language),
    ("line dedup", dedup_lines),
    ("SimHash near-dedup", dedup_near),
    ("benchmark decontamination", decontaminate_benchmark),
    ("source mix", mix_sources),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result but the last is written to the shared folder and read again."""
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
