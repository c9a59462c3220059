"""Exact deduplication through a log-structured merge index of digests, in DataFrame functions only.

* memtable and flush: each input partition hashes its texts and leaves as one
  run of (digest, doc_id) rows sorted by digest, with a Parquet bloom filter on
  the digest, so later point probes skip runs;
* compaction: runs merge to one row per digest with the identifier that stays
  and the group's size (combined in each task before the shuffle, so a group
  of copies costs a row per task);
* byte verification: of digests with several rows the texts themselves are
  compared.  Equal smallest and largest text prove all texts of a digest equal,
  and both are combined in each task first.  A digest with unequal texts stops
  the run instead of merging different texts.

Defined results: null text counts as empty; repeated rows (same doc_id too) are
copies of each other, and every row with the kept doc_id is kept; null doc_ids
never name a group unless it has no other id.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from particle_engine.llm.common import ascii_lower, bounded_broadcast, stage_table


def _normal() -> Column:
    return ascii_lower(F.coalesce(F.col("text").cast("string"), F.lit("")))


def flush_runs(docs: DataFrame) -> DataFrame:
    """Level 0: sorted runs of (doc_id, digest), one file per memtable, with filters."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.unhex(F.sha2(_normal(), 256)).alias("digest"))
    return stage_table(rows, "runs", sort=["digest", "doc_id"], **{"parquet.bloom.filter.enabled#digest": "true", "parquet.bloom.filter.expected.ndv#digest": "100000"})


def compact(runs: DataFrame, keep: str = "min") -> DataFrame:
    """Level 1: (digest, keep_id, group_size); ``keep`` is min (the index's own rule) or max."""
    pick = {"min": F.min, "max": F.max}[keep]
    return runs.groupBy("digest").agg(pick("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))


def probe(level: DataFrame, docs: DataFrame) -> DataFrame:
    """Rows of ``docs`` whose text an index level already holds: (doc_id, keep_id)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.unhex(F.sha2(_normal(), 256)).alias("digest"))
    return rows.join(level, "digest").select("doc_id", "keep_id")


def exact_groups(docs: DataFrame, keep: str = "min") -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) for every row of ``docs``."""
    runs = flush_runs(docs)
    hits = stage_table(compact(runs, keep).where("group_size > 1"), "hits")
    n_hits = hits.count()
    # only texts of hits are compared; their rows come from the runs (a counted broadcast, or a join)
    members = stage_table(runs.join(bounded_broadcast(hits.select("digest"), 80, n_hits), "digest", "left_semi"), "members")
    wanted = bounded_broadcast(members.select(F.col("doc_id").alias("member_id"), "digest").distinct(), 100, members.count())
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    several = source.join(wanted, F.col("doc_id").eqNullSafe(F.col("member_id"))).select("digest", _normal().alias("body"))
    several = several.where(F.unhex(F.sha2("body", 256)) == F.col("digest"))
    checked = several.groupBy("digest").agg(F.min("body").alias("low"), F.max("body").alias("high")).select("digest", (F.col("low") == F.col("high")).alias("same"))
    proven = hits.join(checked, "digest").select(
        "digest", "group_size", F.when(F.col("same"), F.col("keep_id")).otherwise(F.raise_error(F.lit("unequal texts under one digest")).cast("long")).alias("keep_id")
    )
    proven = stage_table(proven, "proven")
    return runs.join(proven, "digest", "left").select(
        "doc_id",
        F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
        F.when(F.col("group_size").isNull(), F.lit(True)).otherwise(F.col("doc_id").eqNullSafe(F.col("keep_id"))).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )
