"""Corpus pipeline: language ID, SimHash near-dedup, benchmark decontamination, secret scan, best-fit packing.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before has kept; its result is written as
Parquet and read again as the next one's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubgraph.llm import decontam, langid, packing, secrets, simhash
from hubgraph.llm.common import stage, table
from hubgraph.llm.queries import ranks_path

REDACTED = "[REDACTED]"


def identify_language(spark, docs, sf_dir):
    """Documents with a language go on, with lang set to the predicted one; those without a letter, null and empty texts
    too, go. Repeated rows stay, ties go to the first name, an empty table gives an empty result."""
    samples = langid.sample_languages(docs)
    found = langid.predict_languages(docs, samples)
    return found.where(F.col("lang_pred") != langid.UNKNOWN).withColumn("lang", F.col("lang_pred")).select(*docs.columns)


def drop_near_duplicates(spark, docs, sf_dir):
    """Of each group of near-duplicates (five-word shingles, similarity 0.8 or more) the row with the smallest doc_id stays (a null one last); rows equal in doc_id and text count as one."""
    rows = simhash.near_duplicate_rows(docs)
    kept = rows.groupBy("label").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key")).alias("low")).select(F.col("low.key").alias("key_of_row"))
    one = Window.partitionBy("key_of_row").orderBy("text", "lang", "source", "n_chars")  # one exchange of the texts serves the join and the window
    held = docs.withColumn("key_of_row", simhash.row_key()).join(kept, "key_of_row", "left_semi")
    return held.withColumn("copy_of_row", F.row_number().over(one)).where("copy_of_row = 1").select(*docs.columns)


def drop_contaminated(spark, docs, sf_dir):
    """Documents that hold a benchmark passage go, each row judged by itself. Null and empty texts stay."""
    return decontam.uncontaminated(docs, table(spark, sf_dir, "benchmark"))


def redact_secrets(spark, docs, sf_dir):
    """Every document stays; each secret in it is replaced by a mark, and n_chars follows. Null texts become empty."""
    return secrets.redact_documents(docs, stage(secrets.scan_unseen(docs)), REDACTED)


def pack_sequences(spark, docs, sf_dir):
    """The pieces of all documents with their sequence and offset; a null or empty text is its closing id alone."""
    return packing.pack(docs, ranks_path())


STAGES = [
    ("language_id", identify_language),
    ("near_dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("secrets", redact_secrets),
    ("packing", pack_sequences),
]

ORACLE_SQL = None  # language ID, hashing and packing have no SQL form; tests hold the operators behind the stages against plain programs


def run(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    for name, stage_function in STAGES[:-1]:
        docs = stage(stage_function(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
