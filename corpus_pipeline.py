"""Corpus pipeline: stages that each apply one operator to all rows the stage before kept.

Language identification drops what has no language, near-duplicate detection keeps one
document of each class, decontamination drops documents that hold a benchmark window, personal
data is replaced in place, and packing places every token of what is left.
"""

from pyspark.sql import functions as F

from relanom.llm import decontaminate, language_id, near_dups, packing, pii, scratch

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def identify_language(spark, docs, sf_dir):
    """Documents with a language; those without a letter are rejected."""
    found = language_id.identify(docs, keep=[c for c in COLUMNS if c != "doc_id"])
    return found.filter("lang_pred <> 'und'").select(*COLUMNS)


def drop_near_duplicates(spark, docs, sf_dir):
    """One document of each class."""
    return near_dups.deduplicated(docs).select(*COLUMNS)


def drop_contaminated(spark, docs, sf_dir):
    """Documents without a window of a benchmark item."""
    return decontaminate.decontaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(*COLUMNS)


def replace_personal_data(spark, docs, sf_dir):
    """All documents, personal data replaced, their lengths counted anew."""
    made = pii.replace(docs, pii.session_key(spark), keep=["lang", "source"])
    return made.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def pack_sequences(spark, docs, sf_dir):
    """One row per piece of a document with its place in a sequence."""
    return packing.pack(docs)


STAGES = [
    ("language_id", identify_language),
    ("near_dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("pii", replace_personal_data),
    ("packing", pack_sequences),
]
#: Language models, signatures and tokenisers are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    """All stages over ``documents``, each result written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = scratch.table(docs, name)
    return docs
