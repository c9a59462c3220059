"""Fuzzy line deduplication by MinHash.

* Equal lines meet by a 64-bit hash of the line, and a second hash of each must
  agree; the first in (doc_id, line) order is theirs.  Where one hash has lines
  that differ in the second, all of them stay as they are.
* Shingles are the runs of ``SHINGLE`` characters at every position, as a set;
  signature, parity sketch and Jaccard similarity all use this one definition.
* Signature: the first ``BOTTOM`` shingles of a line, in one order for all lines: those that begin
  with a space come first, then by hash.  So most lines need not hash the shingles at all other positions.
* Banding: a band is a pair of signature values; with 5 values there are 10
  bands, and lines of similarity 0.8 share one with probability 0.99.
  Values that one line alone has are left out before bands are built.
* Parity sketch: ``BITS`` bits, each the parity of the shingles that hash there.  Two
  sketches differ in at most as many bits as the sets differ in shingles, so more
  differing bits than similarity 0.8 allows rule a pair out for certain.  Only lines that share a band have one.
* Verification: exact Jaccard similarity of the two shingle sets.  In bands of up to
  ``SMALL`` lines every pair that its sketches allow is verified.  In larger ones all lines are first
  compared with the band's medoid; then every line that this leaves outside the band's largest
  component is compared with all lines of other components, in blocks of ``BLOCK``, in the smallest band
  that both share.  No pair is capped away.
* Distributed union-find joins verified links; a component keeps its first line.

Defined results: null text stays null; blank lines stay where they are and are
never compared; lines of fewer than two shingles match exact copies only; repeated rows of
one document (same doc_id and text) share their fate line by line; a text whose
lines all go is empty.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations, pairwise
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from particle_engine.llm.common import bounded_broadcast, connected_components, stage_table

SHINGLE = 12
SIMILARITY = 0.8
BOTTOM, WIDTH = 5, 2
BITS = 512
#: In bands of up to so many lines every pair is compared at once.
SMALL = 64
#: Lines by which a band's medoid is chosen.
REFERENCES = 32
#: Lines of a large band that one row of comparisons meets in a task.
BLOCK = 4096
#: Bytes of a shingle, and of one character, in UTF-32.
WIDE, UNIT = 4 * SHINGLE, 4


def shingles(line: Column) -> Column:
    """Hashes of the character shingles of a line, one for every position; none for a line shorter than one shingle.

    In UTF-32 a shingle is a slice at a known place, whatever comes before it.
    """

    def cut(units: Column) -> Column:
        starts = F.sequence(F.lit(1), F.greatest(F.length(units) - F.lit(WIDE - 1), F.lit(1)), F.lit(UNIT))
        every = F.transform(starts, lambda at: F.xxhash64(F.substring(units, at, F.lit(WIDE))))
        return F.when(F.length(units) >= WIDE, every).otherwise(F.slice(F.array(F.lit(0).cast("long")), 1, 0))

    # a lambda's variable is the encoded line itself; a column would be encoded anew at every position
    return F.get(F.transform(F.array(F.encode(line, "UTF-32")), cut), F.lit(0))


def with_shingles(df: DataFrame, line: str, out: str) -> DataFrame:
    """Adds the distinct hashes of a line's character shingles; a line shorter than one shingle has none."""
    return df.withColumn(out, F.array_distinct(shingles(F.col(line))))


def _begun(first: str) -> Column:
    """Sorted hashes of the shingles of ``line`` whose first character is in the class ``first``, repeats included."""
    cut = F.regexp_extract_all(F.col("line"), F.lit(rf"(?s)(?=({first}.{{{SHINGLE - 1}}}))"), F.lit(1))
    return F.sort_array(F.transform(cut, lambda s: F.xxhash64(s)))


def _lead(ranked: str) -> Column:
    """The first ``BOTTOM`` different values of a sorted array; most arrays begin with so many and need no set."""
    at = [F.get(ranked, F.lit(i)) for i in range(BOTTOM)]
    differ = reduce(and_, [x < y for x, y in pairwise(at)], F.size(ranked) >= BOTTOM)
    return F.when(differ, F.slice(ranked, 1, BOTTOM)).otherwise(F.slice(F.array_distinct(ranked), 1, BOTTOM))


def signed_lines(lines: DataFrame) -> DataFrame:
    """(line_id, sig): the first ``BOTTOM`` of each line's shingles, those that begin with a space before all others, then by hash.

    Columns of their own keep sorting and cutting out of lambdas, which are interpreted.
    """
    few = lines.select("line_id", "line", _begun(" ").alias("few")).select("line_id", "line", _lead("few").alias("few"))
    whole = F.slice(F.concat("few", F.array_distinct(_begun("[^ ]"))), 1, BOTTOM)
    return few.select("line_id", F.when(F.size("few") >= BOTTOM, F.col("few")).otherwise(whole).alias("sig"))


def sketched(texts: DataFrame) -> DataFrame:
    """(line_id, n, bits): number of shingles and parity sketch, as longs, of each line."""
    # explode would put a filter on the array below it, which cuts and hashes every line once more
    each = with_shingles(texts, "line", "x").select("line_id", F.explode_outer("x").alias("h")).where("h is not null")
    word, bit = F.col("h").bitwiseAND(F.lit(BITS // 64 - 1)), F.shiftrightunsigned("h", 32).bitwiseAND(F.lit(63)).cast("int")
    one = F.call_function("shiftleft", F.lit(1).cast("long"), bit)
    words = [F.coalesce(F.bit_xor(F.when(word == i, one)), F.lit(0).cast("long")).alias(f"w{i}") for i in range(BITS // 64)]
    found = each.groupBy("line_id").agg(F.count(F.lit(1)).cast("int").alias("n"), *words)
    return found.select("line_id", "n", F.array(*[f"w{i}" for i in range(BITS // 64)]).alias("bits"))


def differing(x: str, y: str) -> Column:
    """Bits in which the sketches of sides ``x`` and ``y`` differ."""
    return sum((F.bit_count(F.get(f"{x}.bits", F.lit(i)).bitwiseXOR(F.get(f"{y}.bits", F.lit(i)))) for i in range(BITS // 64)), F.lit(0))


def may_be_similar(x: str, y: str) -> Column:
    """Whether the sketches of sides ``x`` and ``y`` leave similarity 0.8 possible; never false where it holds."""
    size = lambda side: F.col(f"{side}.n")
    near = differing(x, y) * (1 + SIMILARITY) <= (1 - SIMILARITY) * (size(x) + size(y)) + 1e-6
    return (F.least(size(x), size(y)) >= SIMILARITY * F.greatest(size(x), size(y))) & near


def _lines(docs: DataFrame) -> DataFrame:
    text = F.col("text").cast("string")
    row = F.xxhash64(F.col("doc_id").cast("long"), text)
    # a document is hashed and cut below the generator, so once and not for each of its lines
    cut = docs.where(text.isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), row.alias("row_key"), F.split(text, "\n", -1).alias("parts"))
    lines = cut.select("doc_id", "row_key", F.posexplode_outer("parts").alias("line_no", "line"))
    return lines.where(F.trim("line") != "").withColumn("line_id", F.xxhash64("line"))


def _bands(signed: DataFrame) -> DataFrame:
    """(band, line_id, size): the bands that hold two lines or more.

    Values and bands are dealt out once each, for counting and for what goes on; the tests on ``last`` and
    ``high`` keep both uses of an exchange alike, or Spark would deal out twice.
    """
    values = signed.select("line_id", F.posexplode("sig").alias("place", "v")).repartition("v")
    several = values.groupBy("v").agg(F.min("line_id").alias("low"), F.max("line_id").alias("high"), F.max("place").alias("last"))
    shared = several.where("low < high and last >= 0").select("v")
    at = [F.max(F.when(F.col("place") == i, F.col("v"))).alias(f"v{i}") for i in range(BOTTOM)]
    mine = values.join(shared.hint("shuffle_hash"), "v").groupBy("line_id").agg(*at)
    pairs = [F.when(F.col(f"v{i}").isNotNull() & F.col(f"v{j}").isNotNull(), F.xxhash64(f"v{i}", f"v{j}")) for i, j in combinations(range(BOTTOM), WIDTH)]
    bands = mine.select(F.explode(F.array(*pairs)).alias("band"), "line_id").where("band is not null").repartition("band")
    sizes = bands.groupBy("band").agg(F.count(F.lit(1)).alias("size"), F.min("line_id").alias("low"), F.max("line_id").alias("high")).where("low < high")
    return bands.join(sizes.select("band", "size").hint("shuffle_hash"), "band")


def _spread(df: DataFrame, rows: int, per_task: int, *keys: str) -> DataFrame:
    """``df`` dealt over tasks by work, not by bytes: few bytes of pairs stand for much comparing."""
    return df.repartition(max(1, -(-rows // per_task)), *keys)


def _ordered(met: DataFrame) -> DataFrame:
    """Distinct (a, b, shingles), a < b, of sides x and y; ``shingles`` is the number both have together."""
    both = met.select(F.least("x.line_id", "y.line_id").alias("a"), F.greatest("x.line_id", "y.line_id").alias("b"), (F.col("x.n") + F.col("y.n")).alias("shingles"))
    return both.where("a < b").distinct()


def verified_links(texts: DataFrame, pairs: DataFrame) -> DataFrame:
    """Pairs (a, b) whose shingle sets have Jaccard similarity ``SIMILARITY`` or more."""
    pairs = stage_table(pairs, "pairs")
    pairs = _spread(pairs, pairs.count(), 20_000, "a")
    left, right = texts.select(F.col("line_id").alias("a"), F.col("line").alias("la")), texts.select(F.col("line_id").alias("b"), F.col("line").alias("lb"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", "shingles", F.size(F.array_intersect(shingles(F.col("la")), shingles(F.col("lb")))).alias("shared"))
    # the test is a generator of one row or none: a filter would sink below the projection and cut both lines again
    alike = F.when(F.col("shared") >= SIMILARITY * (F.col("shingles") - F.col("shared")), F.array(F.lit(1)))
    return stage_table(both.select("a", "b", F.explode(alike).alias("one")).select("a", "b"), "verified")


def _side(name: str) -> Column:
    return F.struct("line_id", "n", "bits", "comp").alias(name)


def _apart(large: DataFrame, links: DataFrame) -> DataFrame:
    """Members of the large bands that hold several components, with their component and the band's largest one."""
    roots = connected_components(links, "a", "b")
    named = large.join(roots.select(F.col("node").alias("line_id"), "root"), "line_id", "left").withColumn("comp", F.coalesce("root", "line_id")).drop("root")
    named = stage_table(named, "large-bands")
    sizes = named.groupBy("band", "comp").agg(F.count(F.lit(1)).alias("m")).groupBy("band").agg(F.max(F.struct("m", "comp"))["comp"].alias("top"), F.count(F.lit(1)).alias("comps")).where("comps > 1")
    return stage_table(named.join(sizes, "band").drop("comps"), "apart")


def _stars(large: DataFrame) -> DataFrame:
    """Sides x and y: each line of a band with the band's medoid, judged by the bits in which it differs from some lines."""
    some = large.where(F.pmod(F.xxhash64("line_id", "band"), F.lit(1 << 20)) * F.col("size") <= F.lit(REFERENCES << 20))
    judged = large.select("band", _side("x")).join(some.select("band", _side("y")), "band").groupBy("band", "x.line_id").agg(F.sum(differing("x", "y")).alias("d"), F.first("x").alias("x"))
    medoids = judged.groupBy("band").agg(F.min_by("x", F.struct("d", "line_id")).alias("y"))
    return large.select("band", _side("x")).join(medoids, "band").where(may_be_similar("x", "y")).select("x", "y")


def _rest(apart: DataFrame) -> DataFrame:
    """Pairs (a, b) of lines of a large band in different components; of a band's largest component one side at most.

    Lines that share several bands meet in the smallest of them only, so no pair is made twice.
    """
    blocks = F.expr(f"(size + {BLOCK - 1}) div {BLOCK}")
    of = apart.groupBy("line_id").agg(F.sort_array(F.collect_set("band")).alias("bands"))
    apart = stage_table(apart.join(of, "line_id"), "apart-bands")
    side = lambda name: F.struct("line_id", "n", "bits", "comp", "bands").alias(name)
    x = apart.where("comp <> top").select("band", side("x"), F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1)).alias("block"))
    y = apart.select("band", side("y"), (F.col("comp") != F.col("top")).alias("out"), F.pmod(F.xxhash64("line_id", "band"), blocks).alias("block"))
    once = (F.col("x.comp") != F.col("y.comp")) & (~F.col("out") | (F.col("x.line_id") < F.col("y.line_id")))
    first = F.get(F.array_intersect("x.bands", "y.bands"), F.lit(0)) == F.col("band")
    met = x.join(y.withColumnsRenamed({"band": "band_y", "block": "block_y"}), (F.col("band") == F.col("band_y")) & (F.col("block") == F.col("block_y")) & once & may_be_similar("x", "y") & first)
    return _ordered(met)


def line_links(lines: DataFrame) -> DataFrame:
    """Verified links (a, b) that connect all similar lines which share a band; ``lines`` (line_id, line) are different lines."""
    banded = stage_table(_bands(stage_table(signed_lines(lines), "signatures")), "banded")
    ids = stage_table(banded.select("line_id").distinct(), "line-ids")
    texts = lines.select("line_id", "line").join(bounded_broadcast(ids, 16), "line_id", "left_semi").dropDuplicates(["line_id"])
    texts = stage_table(texts, "line-texts")
    members = stage_table(banded.join(sketched(texts), "line_id"), "members").withColumn("comp", F.col("line_id"))
    small, large = members.where(F.col("size") <= SMALL), members.where(F.col("size") > SMALL)
    near = small.select("band", _side("x")).join(small.select("band", _side("y")), "band").where("x.line_id < y.line_id").where(may_be_similar("x", "y"))
    pairs = _ordered(near.select("x", "y").union(_stars(large)))
    links = verified_links(texts, pairs)
    if large.isEmpty():
        return links
    return links.union(verified_links(texts, _rest(_apart(large.drop("comp"), links))))


def dropped_lines(docs: DataFrame) -> DataFrame:
    """(row_key, drops): line numbers to drop from each document that loses any."""
    lines = _lines(docs)
    spots = stage_table(lines.select("line_id", F.hash("line").alias("second"), "doc_id", "row_key", "line_no"), "spots")
    firsts = spots.groupBy("line_id").agg(F.min(F.struct("doc_id", "row_key", "line_no")).alias("first"), F.count(F.lit(1)).alias("n"), (F.min("second") != F.max("second")).alias("torn"))
    equal = stage_table(firsts.where("n > 1").select("line_id", "first", "torn"), "equal-lines")
    # only the first of equal lines goes on; a counted broadcast or a join tells which
    marked = lines.join(bounded_broadcast(equal, 48), "line_id", "left")
    once = marked.where("first is null or (not torn and row_key = first.row_key and line_no = first.line_no)").drop("first", "torn")
    roots = connected_components(line_links(once), "a", "b").select(F.col("node").alias("line_id"), "root")
    linked = spots.join(bounded_broadcast(roots, 24), "line_id").groupBy("line_id", "root").agg(F.min(F.struct("doc_id", "row_key", "line_no")).alias("first"))
    alone = equal.where("not torn").join(roots, "line_id", "left_anti").select("line_id", F.col("line_id").alias("root"), "first")
    several = stage_table(linked.unionByName(alone), "several")
    kept = several.groupBy("root").agg(F.min("first").alias("kept"))
    kept = stage_table(several.join(kept, "root").select("line_id", F.col("kept.row_key").alias("kept_key"), F.col("kept.line_no").alias("kept_line")), "kept")
    gone = spots.join(bounded_broadcast(kept, 64), "line_id").where("row_key <> kept_key or line_no <> kept_line")
    return stage_table(gone.groupBy("row_key").agg(F.collect_set("line_no").alias("drops")), "drops")


def dedup_lines(docs: DataFrame) -> DataFrame:
    """All columns of ``docs``, ``text`` without duplicate lines, plus ``n_lines`` and ``n_dropped``."""
    drops = dropped_lines(docs).withColumnRenamed("row_key", "__row_key").withColumnRenamed("drops", "__drops")
    size = drops.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.size("__drops")), F.lit(0)).alias("m")).first()
    drops = bounded_broadcast(drops, 16, size["n"] * 2 + size["m"])
    text = F.col("text").cast("string")
    # the lines are cut below the join, so picking them above does not cut the text again for each
    cut = docs.withColumn("__parts", F.split(text, "\n", -1)).withColumn("__key", F.xxhash64(F.col("doc_id").cast("long"), text))
    rows = cut.join(drops, F.col("__key") == F.col("__row_key"), "left")
    stay = F.array_except(F.sequence(F.lit(0), F.size("__parts") - 1), F.col("__drops"))
    short = F.array_join(F.transform(stay, lambda i: F.get(F.col("__parts"), i)), "\n")
    rows = rows.withColumn("text", F.when(F.col("__drops").isNull(), text).otherwise(short))
    out = [F.col(c) for c in docs.columns if c not in ("n_lines", "n_dropped")]
    n_lines = F.when(F.col("__parts").isNull(), 0).otherwise(F.size("__parts"))
    return rows.select(*out, n_lines.alias("n_lines"), F.coalesce(F.size("__drops"), F.lit(0)).alias("n_dropped"))
