"""The corpus pipeline: toxicity, line dedup, SimHash near-dedup, source mixing, packing.

Each stage reads all that its predecessor kept, and writes rows with the columns
of ``documents`` (the last one: placements).  ``run`` writes every stage's result
as a table before the next one reads it, so a lost executor repeats one stage's
tasks only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from particle_engine.llm import line_dedup, mixing, packing, simhash, toxicity
from particle_engine.llm.common import bounded_broadcast, stage_table, table

#: Near-duplicate stages on word shingles take five words.
NEAR_WORDS = 5
#: Jaccard similarity of near copies.
NEAR_SIMILARITY = 0.8
ORACLE_SQL = None  # learned, iterated and hashed stages have no SQL form; each is tested by itself


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents the toxicity operator rejects (score 0.5 or more) go.

    Null and empty texts score the calibration's value for no distance; repeated rows share their fate; a null doc_id is scored like any.
    """
    return toxicity.reject_toxic(docs, table(spark, sf_dir, "labels"))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal and nearly equal lines one stays; ``n_chars`` follows the text.

    No row goes: a text whose lines all go is empty, null stays null, and rows that repeat a doc_id and text share their fate.
    """
    out = line_dedup.dedup_lines(docs)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the smallest doc_id stays, once.

    Rows that repeat a doc_id are copies of one document: one of them stays (the smallest text, nulls first). Rows without a
    doc_id cannot be named and stay. Empty texts are one group, as texts without tokens have one fingerprint.
    """
    groups = simhash.near_duplicates(docs, words=NEAR_WORDS, similarity=NEAR_SIMILARITY).where("not is_kept").select(F.col("doc_id").alias("__gone")).distinct()
    groups = stage_table(groups, "near-copies")
    kept = docs.join(bounded_broadcast(groups, 16), docs["doc_id"].cast("long") == F.col("__gone"), "left_anti").select(*docs.columns)
    return _one_row_each(kept)


def _one_row_each(docs: DataFrame) -> DataFrame:
    """One row of each doc_id; rows without one stay. Only repeated ids are shuffled with their rows."""
    repeated = docs.where("doc_id is not null").groupBy(F.col("doc_id").alias("__id")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("__id")
    repeated = stage_table(repeated, "repeated-ids")
    if repeated.isEmpty():
        return docs
    met = docs.join(bounded_broadcast(repeated, 16), F.col("doc_id") == F.col("__id"), "left")
    row = F.struct("text", F.struct(*[c for c in docs.columns if c != "text"]).alias("rest"))
    one = met.where("__id is not null").groupBy("doc_id").agg(F.min(row).alias("row"))
    cells = [F.col("row.text") if c == "text" else F.col(f"row.rest.`{c}`") for c in docs.columns]
    return met.where("__id is null").select(*docs.columns).unionByName(one.select(*[cell.alias(c) for cell, c in zip(cells, docs.columns)]))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents drawn to the target weights; each at most once, so epochs end at one.

    Rows are told apart by doc_id: rows that repeat one are drawn together. Null languages and sources are the leaf named '',
    null and empty texts have no tokens and are taken with whole epochs or in a prefix that reaches them.
    """
    drawn = mixing.mix(docs, max_epochs=1).select(F.col("doc_id").alias("__drawn")).distinct()
    drawn = stage_table(drawn, "drawn")
    return docs.join(bounded_broadcast(drawn, 16), docs["doc_id"].cast("long").eqNullSafe(F.col("__drawn")), "left_semi").select(*docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Placements of all pieces in sequences of the permitted lengths.

    Texts without tokens (null, empty, white space) are one piece without a bin; repeated rows are packed each.
    """
    return packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_repeated_lines),
    ("simhash_near_dedup", drop_near_copies),
    ("source_mixing", mix_sources),
    ("best_fit_packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stage_table(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
