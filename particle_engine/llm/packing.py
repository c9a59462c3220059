"""Best-fit packing of documents into training sequences of several permitted lengths.

Items go longest first into the open bin with the least room that still fits.
Where none fits, all permitted lengths compete for the new bin: a length costs a fixed
charge per sequence and, for each token, more the longer the sequence is (attention grows with the
square), and it is expected to hold the item and as much of its room as the waiting items that
fit there can fill; the length of least cost per expected token opens.  When all items are placed,
every bin shrinks to the smallest permitted length that holds its contents.

Texts longer than the largest length are cut into pieces of that length and a
rest.  Documents are dealt by hash into shards of about ``SHARD_DOCS``; a shard
is packed on its own, so memory is bounded and shards run anywhere and can be
repeated.

Defined results: null or empty texts (no tokens) are one piece without a bin;
repeated rows are packed each; nothing is dropped.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right, insort
from collections import defaultdict
from collections.abc import Callable
from itertools import accumulate

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from particle_engine.llm.common import stage_table
from particle_engine.llm.mixing import WORD

LENGTHS = (512, 1024, 2048, 4096)
OPEN_COST = 64
#: A sequence of this length costs twice its tokens.
DOUBLE_AT = 16384
SHARD_DOCS = 1000
SCHEMA = "doc_id long, piece int, start_token long, n_tokens long, bin_id string, bin_size int, bin_offset int"


def word_tokens(text: Column) -> Column:
    """Default length: words. Pass another column expression (a tokenizer's UDF) to ``pack`` for its own count."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def bin_cost(length: int, open_cost: int = OPEN_COST) -> float:
    return open_cost + length * (1 + length / DOUBLE_AT)


def choose_length(need: int, waiting: Callable[[int], int], lengths: tuple[int, ...] = LENGTHS, open_cost: int = OPEN_COST) -> int:
    """The permitted length with the least cost per token it is expected to hold; ties open the larger.

    ``waiting(room)`` is the number of tokens in waiting items of at most ``room`` tokens.
    """
    return min((c for c in lengths if c >= need), key=lambda c: (bin_cost(c, open_cost) / (need + min(c - need, waiting(c - need))), -c))


def best_fit(sizes: list[int], lengths: tuple[int, ...] = LENGTHS, open_cost: int = OPEN_COST) -> tuple[list[tuple[int, int]], list[int]]:
    """Place items given longest first: (bin, offset) per item, and each bin's final length."""
    room: list[tuple[int, int]] = []  # (free, bin), sorted
    length: list[int] = []
    places: list[tuple[int, int]] = []
    rising = sizes[::-1]
    upto = [0, *accumulate(rising)]  # tokens of the k shortest items
    for i, size in enumerate(sizes):
        at = bisect_left(room, (size, -1))
        if at < len(room):
            free, b = room.pop(at)
        else:
            left = len(sizes) - i - 1  # the items still waiting are the shortest
            waiting = lambda r: upto[min(left, bisect_right(rising, r))]  # noqa: B023, E731
            b, free = len(length), choose_length(size, waiting, lengths, open_cost)
            length.append(free)
        places.append((b, length[b] - free))
        if free > size:
            insort(room, (free - size, b))
    filled: dict[int, int] = defaultdict(int)
    for size, (b, _) in zip(sizes, places):
        filled[b] += size
    return places, [min(c for c in lengths if c >= filled[b]) for b in range(len(length))]


def pack(docs: DataFrame, tokens: Column | None = None, lengths: tuple[int, ...] = LENGTHS, open_cost: int = OPEN_COST) -> DataFrame:
    """One row per piece: doc_id, piece, start_token, n_tokens, bin_id, bin_size, bin_offset."""
    lengths = tuple(sorted(lengths))
    largest = lengths[-1]
    n = word_tokens(F.col("text").cast("string")) if tokens is None else tokens.cast("long")
    rows = stage_table(docs.select(F.col("doc_id").cast("long").alias("doc_id"), n.alias("n")), "lengths")
    shards = max(1, -(-rows.count() // SHARD_DOCS))
    pieces = rows.select("doc_id", "n", F.posexplode(F.sequence(F.lit(0).cast("long"), F.greatest(F.col("n") - 1, F.lit(0)), F.lit(largest).cast("long"))).alias("piece", "start_token"))
    pieces = pieces.select("doc_id", "piece", "start_token", F.least(F.col("n") - F.col("start_token"), F.lit(largest)).alias("n_tokens"), F.pmod(F.xxhash64("doc_id", "piece", "n"), F.lit(shards)).alias("shard"))

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["n_tokens", "doc_id", "piece"], ascending=[False, True, True], kind="stable", ignore_index=True)
        full = pdf[pdf["n_tokens"] > 0]
        places, final = best_fit(full["n_tokens"].tolist(), lengths, open_cost)
        rest = [None] * (len(pdf) - len(full))
        pdf["bin_id"] = [f"{key[0]:x}-{b:x}" for b, _ in places] + rest
        pdf["bin_size"] = pd.array([final[b] for b, _ in places] + rest, dtype="Int32")
        pdf["bin_offset"] = pd.array([o for _, o in places] + rest, dtype="Int32")
        pdf["doc_id"] = pdf["doc_id"].astype("Int64")
        return pdf[["doc_id", "piece", "start_token", "n_tokens", "bin_id", "bin_size", "bin_offset"]]

    return pieces.groupBy("shard").applyInPandas(run, SCHEMA)
