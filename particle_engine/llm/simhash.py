"""SimHash near-duplicate detection with a Gray-order hierarchical index.

Fingerprints within ``RADIUS`` bits share one of four 16-bit blocks and, of
the 48 bits left, one of four 12-bit blocks (pigeonhole twice), so every pair
meets under one of 16 keys of 28 bits.  Under a key the fingerprints are
sorted by Gray rank and indexed by a tree: a node holds the bits on which all
members agree (mask and pattern), and its children only add bits to that mask.
A pair of nodes carries the differences found so far; going down adds those of
the newly shared bits alone, and a pair over the radius is dropped with all its
members.  A key emits a spanning forest of its links, never all pairs.

A radius of 3 bits holds only the lightest edits.  With ``similarity`` texts
whose shingle sets have that Jaccard similarity are linked too: 16 bands of four
MinHash values propose pairs (at 0.8 a pair is missed with probability 0.0002),
and exact shingle sets decide.  In a band each text meets its predecessor and
the first; where that leaves several components, all pairs across them meet,
and those that parity sketches (as in ``line_dedup``) leave possible are verified.

Defined results: null text counts as empty; no words give fingerprint zero,
linked like any other; repeated rows share a fingerprint and a component; a
null doc_id takes part as a row of its own fingerprint group but never names a
component unless the group has no other id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from particle_engine.llm.common import bounded_broadcast, connected_components, small_batches, stage_table

RADIUS = 3
LEAF = 16
SEED = 42
BANDS, ROWS = 16, 4
#: Longs of a text's parity sketch.
SKETCH = 16
#: Texts of a band that one row of comparisons meets in a task.
BLOCK = 1024


def shingles_of(text: str | None, words: int) -> list[bytes]:
    """Runs of ``words`` tokens, lower case; a shorter text is one shingle, one without tokens has none."""
    tokens = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if len(tokens) <= words:
        return [b" ".join(tokens)] if tokens else []
    flat = b" ".join(tokens)
    ends = np.cumsum([len(t) + 1 for t in tokens])
    starts = np.concatenate(([0], ends[:-1]))[: len(tokens) - words + 1].tolist()
    return [flat[i:j] for i, j in zip(starts, (ends[words - 1 :] - 1).tolist())]


def fingerprint(text: str | None, words: int = 3) -> int:
    """64-bit SimHash: bit i is set if set in over half of the shingle hashes (repeats count)."""
    shingles = shingles_of(text, words)
    if not shingles:
        return 0
    digest = xxhash.xxh64_intdigest
    total = np.zeros(64, np.int64)
    for at in range(0, len(shingles), 1 << 14):  # bounded memory on very long texts
        hashes = np.array([digest(s, SEED) for s in shingles[at : at + (1 << 14)]], np.uint64)
        total += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    bits = (2 * total > len(shingles)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view(np.int64)[0])


def fingerprints(docs: DataFrame, words: int = 3) -> DataFrame:
    """(doc_id, fp): one row per document, fp a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = pa.array([fingerprint(t.as_py(), words) for t in batch.column(1)], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), prints], ["doc_id", "fp"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return small_batches(rows).mapInArrow(run, "doc_id long, fp long")


class GrayIndex:
    """Tree over fingerprints in Gray order; ``links`` walks it against itself."""

    def __init__(self, codes: np.ndarray, radius: int = RADIUS):
        self.codes, self.radius = codes, radius
        self.parent = np.arange(len(codes))
        self.nodes: list[tuple[int, int, int, int, int, int]] = []
        self._build(0, len(codes))

    def _build(self, lo: int, hi: int) -> int:
        part = self.codes[lo:hi]
        every, some = int(np.bitwise_and.reduce(part)), int(np.bitwise_or.reduce(part))
        mask = ~(every ^ some) & 0xFFFFFFFFFFFFFFFF
        at = len(self.nodes)
        self.nodes.append((lo, hi, mask, every & mask, -1, -1))
        if hi - lo > LEAF:
            # split where the highest undecided bit changes most evenly: the middle in Gray order
            mid = (lo + hi) // 2
            left, right = self._build(lo, mid), self._build(mid, hi)
            self.nodes[at] = (lo, hi, mask, every & mask, left, right)
        return at

    def find(self, i: int) -> int:
        parent = self.parent
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    def links(self) -> list[tuple[int, int]]:
        """A spanning forest of all pairs within the radius, as positions."""
        out, stack = [], [(0, 0, self.nodes[0][2], 0)]
        while stack:
            x, y, shared, differing = stack.pop()
            lo, hi, _, _, left, right = self.nodes[x]
            lo2, hi2, _, _, left2, right2 = self.nodes[y]
            if left < 0 and left2 < 0:
                open_bits = np.uint64(~shared & 0xFFFFFFFFFFFFFFFF)
                far = differing + np.bitwise_count((self.codes[lo:hi, None] ^ self.codes[None, lo2:hi2]) & open_bits)
                for i, j in np.argwhere(far <= self.radius).tolist():
                    if (x != y or i < j) and (p := self.find(lo + i)) != (q := self.find(lo2 + j)):
                        self.parent[max(p, q)] = min(p, q)
                        out.append((lo + i, lo2 + j))
                continue
            if x == y:
                below = [(left, left), (left, right), (right, right)]
            elif left2 < 0 or (left >= 0 and hi - lo >= hi2 - lo2):
                below = [(left, y), (right, y)]
            else:
                below = [(x, left2), (x, right2)]
            for u, v in below:
                _, _, mask, pattern, _, _ = self.nodes[u]
                _, _, mask2, pattern2, _, _ = self.nodes[v]
                both = mask & mask2  # holds all of ``shared``
                more = differing + ((pattern ^ pattern2) & (both ^ shared)).bit_count()
                if more <= self.radius:
                    stack.append((u, v, both, more))
        return out


def _under_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows arrive sorted by key and Gray rank; a key may span batches."""
    rest_key, rest_code = np.empty(0, np.int64), np.empty(0, np.int64)
    for batch in batches:
        key = np.concatenate((rest_key, batch.column(0).to_numpy()))
        code = np.concatenate((rest_code, batch.column(1).to_numpy()))
        whole = np.searchsorted(key, key[-1]) if len(key) else 0
        rest_key, rest_code = key[whole:], code[whole:]
        yield _link_runs(key[:whole], code[:whole])
    yield _link_runs(rest_key, rest_code)


def _link_runs(key: np.ndarray, codes: np.ndarray) -> pa.RecordBatch:
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.empty(0, np.int64)
    sizes = np.diff(np.r_[starts, len(key)])
    pair = starts[sizes == 2]
    near = np.bitwise_count((codes[pair] ^ codes[pair + 1]).view(np.uint64)) <= RADIUS
    a, b = [codes[pair[near]]], [codes[pair[near] + 1]]
    for at, n in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist()):
        if found := GrayIndex(codes[at : at + n].view(np.uint64)).links():
            i, j = np.array(found).T
            a.append(codes[at + i])
            b.append(codes[at + j])
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate(a), pa.int64()), pa.array(np.concatenate(b), pa.int64())], ["a", "b"])


def near_links(codes: DataFrame) -> DataFrame:
    """Links (a, b) that connect what is within the radius, from distinct fingerprints (column fp)."""
    rank = F.col("fp")
    for shift in (1, 2, 4, 8, 16, 32):  # inverse Gray code: the position of fp in Gray order
        rank = rank.bitwiseXOR(F.shiftrightunsigned(rank, shift))
    keys = []
    for block in range(4):
        head = F.shiftrightunsigned("fp", 16 * block).bitwiseAND(F.lit(0xFFFF))
        low = F.col("fp").bitwiseAND(F.lit((1 << 16 * block) - 1)) if block else F.lit(0).cast("long")
        others = low.bitwiseOR(F.shiftleft(F.shiftrightunsigned("fp", 16 * (block + 1)), 16 * block)) if block < 3 else low
        for sub in range(4):
            part = F.shiftrightunsigned(others, 12 * sub).bitwiseAND(F.lit(0xFFF))
            keys.append(F.shiftleft(head, 12).bitwiseOR(part).bitwiseOR(F.lit((4 * block + sub) << 28)))
    keyed = codes.select("fp", rank.alias("gray"), F.explode(F.array(*keys)).alias("key"))
    return keyed.repartition("key").sortWithinPartitions("key", "gray").select("key", "fp").mapInArrow(_under_keys, "a long, b long")


def min_bands(text: str | None, words: int) -> list[int]:
    """One key for each band of ``ROWS`` MinHash values; none without tokens."""
    shingles = list(set(shingles_of(text, words)))
    if not shingles:
        return []
    draw = np.random.default_rng(SEED).integers(0, 1 << 63, (2, BANDS * ROWS), np.uint64)
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 1 << 12):  # bounded memory on very long texts
        hashes = np.array([xxhash.xxh64_intdigest(s, SEED) for s in shingles[at : at + (1 << 12)]], np.uint64)
        mixed = (hashes[:, None] ^ draw[0]) * (draw[1] | np.uint64(1))
        mixed = (mixed ^ (mixed >> np.uint64(32))) * np.uint64(0x9E3779B97F4A7C15)
        least = np.minimum(least, mixed.min(0))
    return [xxhash.xxh64_intdigest(least[i * ROWS : (i + 1) * ROWS].tobytes(), i) - (1 << 63) for i in range(BANDS)]


def _alike(pairs: DataFrame, texts: DataFrame, words: int, similarity: float) -> DataFrame:
    """Pairs (a, b) whose shingle sets have Jaccard similarity ``similarity`` or more."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3)):
                p, q = set(shingles_of(x.as_py(), words)), set(shingles_of(y.as_py(), words))
                shared = len(p & q)
                keep.append(shared >= similarity * (len(p) + len(q) - shared))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left, right = texts.select(F.col("key").alias("a"), F.col("text").alias("ta")), texts.select(F.col("key").alias("b"), F.col("text").alias("tb"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", "ta", "tb")
    return stage_table(both.mapInArrow(run, "a long, b long"), "alike")


def parity(text: str | None, words: int) -> tuple[int, np.ndarray]:
    """Number of distinct shingles, and ``SKETCH`` longs of bits that are each the parity of the shingles that hash there."""
    shingles = list(set(shingles_of(text, words)))
    odd = np.zeros(64 * SKETCH, np.int64)
    for at in range(0, len(shingles), 1 << 14):  # bounded memory on very long texts
        hashes = np.array([xxhash.xxh64_intdigest(s, SEED) for s in shingles[at : at + (1 << 14)]], np.uint64)
        odd += np.bincount((hashes % np.uint64(64 * SKETCH)).astype(np.int64), minlength=64 * SKETCH)
    return len(shingles), np.packbits((odd & 1).astype(np.uint8), bitorder="little").view(np.int64)


def sketched(texts: DataFrame, words: int) -> DataFrame:
    """(key, n, w0, w1, ...): number of shingles and parity sketch of each text."""
    names = [f"w{i}" for i in range(SKETCH)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [parity(t.as_py(), words) for t in batch.column(1)]
            bits = np.array([b for _, b in found], np.int64).reshape(-1, SKETCH)
            cells = [batch.column(0), pa.array([n for n, _ in found], pa.int64()), *[pa.array(bits[:, i]) for i in range(SKETCH)]]
            yield pa.RecordBatch.from_arrays(cells, ["key", "n", *names])

    return small_batches(texts.select("key", "text")).mapInArrow(run, "key long, n long, " + ", ".join(f"{c} long" for c in names))


def _across(apart: DataFrame, similarity: float) -> DataFrame:
    """(key, o): texts of a band in different components that their sketches allow to be similar; of a band's largest component one side at most.

    A shingle that one set alone has flips one bit, so more differing bits than the similarity leaves room for rule a pair out for certain.
    """
    blocks = F.expr(f"(size + {BLOCK - 1}) div {BLOCK}")
    mine = ["key", "comp", "n", *[f"w{i}" for i in range(SKETCH)]]
    x = apart.where("comp <> top").select("band", *mine, F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1)).alias("block"))
    other = [F.col(c).alias("o" if c == "key" else f"o_{c}") for c in mine]
    y = apart.select("band", *other, (F.col("comp") != F.col("top")).alias("out"), F.pmod(F.xxhash64("key", "band"), blocks).alias("block"))
    once = (F.col("comp") != F.col("o_comp")) & (~F.col("out") | (F.col("key") < F.col("o")))
    sizes = F.least("n", "o_n") >= similarity * F.greatest("n", "o_n") - 1e-6
    differing = sum((F.bit_count(F.col(f"w{i}").bitwiseXOR(F.col(f"o_w{i}"))) for i in range(SKETCH)), F.lit(0))
    near = differing * (1 + similarity) <= (1 - similarity) * (F.col("n") + F.col("o_n")) + 1e-6
    return x.join(y, ["band", "block"]).where(once & sizes & near).select("key", "o")


def similar_links(docs: DataFrame, words: int, similarity: float) -> DataFrame:
    """Links (a, b) between the xxhash64 of different texts, which connect what is similar and shares a band."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bands = pa.array([min_bands(t.as_py(), words) for t in batch.column(1)], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), bands], ["key", "bands"])

    keyed = docs.select(F.col("text").cast("string").alias("text")).where("text is not null").select(F.xxhash64("text").alias("key"), "text")
    banded = small_batches(keyed).mapInArrow(run, "key long, bands array<long>").select("key", F.explode("bands").alias("band")).distinct()
    order = Window.partitionBy("band").orderBy("key")
    met = banded.withColumns({"before": F.lag("key").over(order), "head": F.first("key").over(order), "after": F.lead("key").over(order)})
    met = stage_table(met.where("before is not null or after is not null").drop("after"), "similar-bands")
    ids = stage_table(met.select("key").distinct(), "similar-ids")
    texts = stage_table(keyed.join(bounded_broadcast(ids, 16), "key", "left_semi").groupBy("key").agg(F.first("text").alias("text")), "similar-texts")
    ordered = lambda d: stage_table(d.select(F.least("key", "o").alias("a"), F.greatest("key", "o").alias("b")).where("a <> b").distinct(), "similar-pairs")
    links = _alike(ordered(met.select("key", F.explode(F.array_compact(F.array("before", "head"))).alias("o"))), texts, words, similarity)
    roots = connected_components(links, "a", "b").withColumnRenamed("node", "key")
    named = met.select("band", "key").join(roots, "key", "left").select("band", "key", F.coalesce("root", "key").alias("comp"))
    sizes = named.groupBy("band", "comp").agg(F.count(F.lit(1)).alias("m")).groupBy("band").agg(F.max(F.struct("m", "comp"))["comp"].alias("top"), F.count(F.lit(1)).alias("comps"), F.sum("m").alias("size")).where("comps > 1")
    apart = stage_table(named.join(sizes, "band").select("band", "key", "comp", "top", "size"), "similar-apart")
    some = stage_table(apart.select("key").distinct(), "similar-ids")
    sketches = stage_table(sketched(texts.join(bounded_broadcast(some, 16), "key", "left_semi"), words), "similar-sketches")
    return links.union(_alike(ordered(_across(apart.join(sketches, "key"), similarity)), texts, words, similarity))


def near_duplicates(docs: DataFrame, words: int = 3, similarity: float | None = None) -> DataFrame:
    """(doc_id, fingerprint, component_id, is_kept): one row per input row; component_id is the smallest doc_id reachable.

    Links are fingerprints within ``RADIUS`` and, if given, texts of Jaccard ``similarity`` or more.
    """
    prints = stage_table(fingerprints(docs, words), "simhash")
    codes = stage_table(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "codes")
    links = near_links(codes.select("fp"))
    if similarity is not None:
        found = stage_table(similar_links(docs, words, similarity), "similar-links")
        ids = stage_table(found.select(F.explode(F.array("a", "b")).alias("key")).distinct(), "similar-ids")
        texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("key", F.xxhash64("text"))
        texts = texts.join(bounded_broadcast(ids, 16), "key", "left_semi").dropDuplicates(["key"])
        by_key = stage_table(fingerprints(texts.select(F.col("key").alias("doc_id"), "text"), words), "similar-prints")
        links = links.union(found.join(by_key.select(F.col("doc_id").alias("a"), F.col("fp").alias("fa")), "a").join(by_key.select(F.col("doc_id").alias("b"), F.col("fp").alias("fb")), "b").select("fa", "fb"))
    roots = connected_components(links, "a", "b")
    linked = codes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    firsts = linked.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = stage_table(linked.join(firsts, "root").select("fp", "component_id"), "components")
    return prints.join(named, "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", (F.col("doc_id") == F.col("component_id")).alias("is_kept")
    )
