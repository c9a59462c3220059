"""Helpers shared by the training-data operators.

``stage_table`` cuts lineage by writing Parquet into the folder that the
cluster shares between driver and executors (``spark.checkpoint.dir``).  Files
written there survive lost executors, unlike ``localCheckpoint``.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side is broadcast only if its measured size stays under this bound.
BROADCAST_BYTES = 32 << 20

#: Bytes of an Arrow batch to Python: long texts make a batch of many rows large on both sides.
BATCH_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors see; a private one is set only in local mode, where none is set (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        found = spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="particle_engine_")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def stage_table(df: DataFrame, label: str, sort: list[str] | None = None, **options: str) -> DataFrame:
    """Write ``df`` into the shared folder and return it re-read (no lineage, exact row counts)."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    out = df.sortWithinPartitions(*sort) if sort else df
    out.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bounded_broadcast(df: DataFrame, bytes_per_row: int, rows: int | None = None) -> DataFrame:
    """Mark a side for broadcast only if its counted size is under ``BROADCAST_BYTES``; else leave the join to Spark."""
    rows = df.count() if rows is None else rows
    return F.broadcast(df) if rows * bytes_per_row <= BROADCAST_BYTES else df


def small_batches(df: DataFrame) -> DataFrame:
    """Bound the session's Arrow batches by ``BATCH_BYTES``, whatever the texts' lengths; returns ``df``."""
    conf, key = df.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    if conf.get(key, None) is not None:  # releases without the setting bound rows only
        conf.set(key, str(BATCH_BYTES))
    return df


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z and nothing else; pure-ASCII texts take the cheap built-in."""
    plain = F.octet_length(text) == F.char_length(text)
    return F.when(plain, F.lower(text)).otherwise(F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))


def connected_components(edges: DataFrame, left: str, right: str) -> DataFrame:
    """Distributed union-find over long node ids: (node, root), one root per component.

    Every round each node hooks to the neighbour with the smallest hash (its
    own included), edges are rewritten to the hooked nodes and self-loops go.
    Hash order makes chains contract by a constant factor, so rounds grow with
    the logarithm of the longest chain.  Hooks are aggregated before the
    shuffle, so a hub costs one row per task.  Each round is a written table:
    a lost executor repeats one round at most.
    """
    a, b = F.col(left), F.col(right)
    pairs = edges.where(a != b).select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b")).distinct()
    pairs = stage_table(pairs, "links")
    hooks: list[DataFrame] = []
    while pairs.count():
        rank = F.struct(F.xxhash64("b").alias("h"), F.col("b").alias("id"))
        near = pairs.union(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).groupBy("a").agg(F.min(rank).alias("n"))
        own = F.struct(F.xxhash64("a").alias("h"), F.col("a").alias("id"))
        hook = stage_table(near.select(F.col("a").alias("node"), F.least(F.col("n"), own)["id"].alias("root")), "hooks")
        hooks.append(hook)
        up_a = hook.select(F.col("node").alias("a"), F.col("root").alias("ra"))
        up_b = hook.select(F.col("node").alias("b"), F.col("root").alias("rb"))
        moved = pairs.join(up_a, "a").join(up_b, "b").where("ra <> rb")
        pairs = stage_table(moved.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(), "links")
    if not hooks:
        return pairs.select(F.col("a").alias("node"), F.col("b").alias("root"))
    roots = hooks[0]
    for hook in hooks[1:]:
        step = hook.select(F.col("node").alias("root"), F.col("root").alias("next"))
        roots = roots.join(step, "root", "left").select("node", F.coalesce("next", "root").alias("root"))
    return stage_table(roots, "roots") if len(hooks) > 1 else roots
