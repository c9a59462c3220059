"""Secret scanning: fixed patterns plus sliding-window entropy, in DataFrame functions only.

Candidate strings are runs of 20 token characters or more.  Each belongs to a character
class (hexadecimal, digits, letters, or general) with a threshold of its own.  A window
slides over the candidate; counts per character are kept packed in a few integers and
change only for the character that enters and the one that leaves, and the sum
of c*log2(c) follows them, so a step costs no recount.  Candidates on the allow
list (whole dates and times, versions, identifiers of eight-four-four-four-twelve digits)
and those that overlap a base span are suppressed.

Defined results: null text counts as empty and has no spans; positions are code
points, ends exclusive; repeated rows give repeated results; a null doc_id stays null.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The base patterns and the least lengths of what they must match.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ASSIGN_KEY = r"(?i)(password|passwd|secret|token|api_?key)"
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
ALLOWED = r"^([0-9]{4}-[0-9]{2}-[0-9]{2}([T_-][0-9]{2}-?[0-9]{2}(-?[0-9]{2}(-?[0-9]{1,9})?)?Z?)?|[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}|[vV]?[0-9]{1,8}([_-][0-9]{1,8})+)$"
WINDOW = 20
#: Thresholds in bits by class, the first class that fits decides.
CLASSES = [(r"^[0-9]+$", 3.1), (r"^[0-9a-fA-F]+$", 3.0), (r"^[^0-9]+$", 4.0), (r"", 3.6)]
#: Matches whose places are summed up in one inner step.
CHUNK = 256
#: Token characters are the codes FIRST to FIRST + 83; PACK counts of five bits fit an integer.
FIRST, PACK, FIELDS = 43, 12, 7

KINDS = ("assign", "access", "hex", "entropy")
SPAN = "array<struct<start:int,kind_no:int,stop:int,kind:string>>"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is evaluated once, however often ``body`` names it."""
    return F.get(F.transform(F.array(value), body), 0)


def located(text: Column, pattern: str, value_group: int = 0) -> Column:
    """array<struct<start, stop, value>> of all non-overlapping matches, from the gaps between them."""
    whole = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.split(text, pattern, -1)  # one more than there are matches
    value = whole if value_group == 0 else F.regexp_extract_all(text, F.lit(pattern), F.lit(value_group))
    sized = F.zip_with(whole, gaps, lambda m, g: F.struct(F.length(g).alias("gap"), F.length(m).alias("size")))
    steps = F.filter(F.zip_with(sized, value, lambda s, v: F.struct(s["gap"].alias("gap"), s["size"].alias("size"), v.alias("value"))), lambda s: s["size"].isNotNull())
    spans = "array<struct<start:int,stop:int,value:string>>"

    def add(state: Column, m: Column) -> Column:
        begin = state["at"] + m["gap"]
        stop = begin + m["size"]
        return F.struct(stop.alias("at"), F.concat(state["out"], F.array(F.struct(begin.alias("start"), stop.alias("stop"), m["value"].alias("value")))).alias("out"))

    def add_chunk(state: Column, chunk: Column) -> Column:
        done = F.aggregate(chunk, F.struct(state["at"].alias("at"), F.array().cast(spans).alias("out")), add)
        return let(done, lambda d: F.struct(d["at"].alias("at"), F.concat(state["out"], F.array(d["out"])).alias("out")))

    # places are summed in chunks, so a text of very many matches does not append to one long list each time
    chunks = let(steps, lambda st: F.transform(F.sequence(F.lit(0), F.floor(F.size(st) / CHUNK).cast("int")), lambda k: F.slice(st, k * CHUNK + 1, F.lit(CHUNK))))
    return F.aggregate(chunks, F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{spans}>").alias("out")), add_chunk, lambda s: F.flatten(s["out"]))


def _spans(text: Column, probe: str, pattern: str, kind: int, keep, value_group: int = 0) -> Column:
    found = F.transform(
        F.filter(located(text, pattern, value_group), lambda m: keep(m["value"])),
        lambda m: F.struct(m["start"].alias("start"), F.lit(kind).alias("kind_no"), m["stop"].alias("stop"), F.lit(KINDS[kind]).alias("kind")),
    )
    return F.when(text.rlike(probe), found).otherwise(F.array().cast(SPAN)).cast(SPAN)


def window_entropy(value: Column, width: int = WINDOW) -> Column:
    """Largest Shannon entropy (bits, 6 decimals) of any window of ``width`` token characters, by incremental counts."""
    codes = F.transform(F.split(value, ""), lambda c: F.ascii(c) - FIRST)
    term = lambda c: F.when(c > 1, c * F.log2(c)).otherwise(F.lit(0.0))
    zero = F.struct(*[F.lit(0).cast("long").alias(f"f{j}") for j in range(FIELDS)], F.lit(0.0).alias("total"), F.lit(1e9).alias("least"), F.lit(1).alias("seen"))
    place = lambda c, name: F.struct(F.floor(c / PACK).cast("int").alias("field"), (F.pmod(c, F.lit(PACK)) * 5).alias("shift"), c.alias("code")).alias(name)
    # each character with the one that leaves the window as it enters; -1 where none does yet
    steps = let(codes, lambda cs: F.zip_with(cs, F.concat(F.array_repeat(F.lit(-1), width), cs), lambda x, y: F.struct(place(x, "enters"), place(y, "leaves"))))
    steps = F.filter(steps, lambda x: x["enters"]["code"].isNotNull())

    def count(s: Column, c: Column) -> Column:
        packed = F.lit(0).cast("long")
        for j in range(FIELDS):
            packed = F.when(c["field"] == j, s[f"f{j}"]).otherwise(packed)
        return F.call_function("shiftright", packed, c["shift"]).bitwiseAND(F.lit(31))

    def slide(s: Column, x: Column) -> Column:
        enters, leaves = x["enters"], x["leaves"]
        one = lambda c: F.call_function("shiftleft", F.lit(1).cast("long"), c["shift"])
        fields = [(s[f"f{j}"] + F.when(enters["field"] == j, one(enters)).otherwise(F.lit(0)) - F.when((leaves["code"] >= 0) & (leaves["field"] == j), one(leaves)).otherwise(F.lit(0))).alias(f"f{j}") for j in range(FIELDS)]
        both = F.struct(F.when(leaves["code"] >= 0, count(s, leaves)).otherwise(F.lit(0)).alias("gone"), (count(s, enters) - F.when(leaves["code"] == enters["code"], F.lit(1)).otherwise(F.lit(0))).alias("here"))
        total = let(both, lambda n: s["total"] - term(n["gone"]) + term(n["gone"] - 1) - term(n["here"]) + term(n["here"] + 1))
        return let(total, lambda t: F.struct(*fields, t.alias("total"), F.when(s["seen"] >= width, F.least(s["least"], t)).otherwise(s["least"]).alias("least"), (s["seen"] + 1).alias("seen")))

    return F.aggregate(steps, zero, slide, lambda s: F.round(F.log2(F.lit(width)) - s["least"] / width, 6))


def threshold(value: Column) -> Column:
    """Bits a candidate needs, by its character class."""
    out = F.lit(CLASSES[-1][1])
    for pattern, bits in reversed(CLASSES[:-1]):
        out = F.when(value.rlike(pattern), F.lit(bits)).otherwise(out)
    return out


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["stop"])), ",")


def scan_secrets(docs: DataFrame) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, n_entropy, base_sha256, spans): one row per document."""
    t = F.col("body")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("body"))
    suspicious = lambda v: ~v.rlike(ALLOWED)
    entropic = lambda v: window_entropy(v) >= threshold(v)
    rows = rows.select(
        "doc_id",
        _spans(t, ASSIGN_KEY, ASSIGN, 0, lambda v: F.length(v) >= 12, 2).alias("assign"),
        _spans(t, "AKIA[A-Z0-9]{14}", ACCESS, 1, lambda v: F.length(v) >= 18).alias("access"),
        # a run of 16 hexadecimal characters or more is a whole match of the base pattern
        _spans(t, "[0-9a-f]{16}", "[0-9a-f]{16,}", 2, lambda v: F.length(v) >= 16).alias("hex"),
        _spans(t, CANDIDATE, CANDIDATE, 3, lambda v: F.when(suspicious(v), entropic(v)).otherwise(F.lit(False))).alias("strings"),
    )
    rows = rows.withColumn("base", F.array_sort(F.concat("assign", "access", "hex")))
    fresh = F.filter("strings", lambda e: ~F.exists("base", lambda b: (b["start"] < e["stop"]) & (e["start"] < b["stop"])))
    rows = rows.withColumn("fresh", fresh)
    size = lambda c: F.size(c).cast("long").alias(f"n_{c}")
    return rows.select(
        "doc_id", size("assign"), size("access"), size("hex"), F.size("fresh").cast("long").alias("n_entropy"),
        F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.array_sort(F.concat("base", "fresh"))).alias("spans"),
    )


def _sql_located(pattern: str, group: int) -> str:
    """DuckDB: list of {s, e, v} from gaps and matches."""
    p = pattern.replace("'", "''")
    return f"""list_transform(range(1, len(regexp_extract_all(t, '{p}')) + 1), lambda i: {{
      's': CAST(list_sum(list_transform(string_split_regex(t, '{p}')[1:i], lambda g: length(g))) + coalesce(list_sum(list_transform(regexp_extract_all(t, '{p}')[1:i-1], lambda g: length(g))), 0) AS INTEGER),
      'e': CAST(list_sum(list_transform(string_split_regex(t, '{p}')[1:i], lambda g: length(g))) + list_sum(list_transform(regexp_extract_all(t, '{p}')[1:i], lambda g: length(g))) AS INTEGER),
      'v': regexp_extract_all(t, '{p}', {group})[i]}})"""


def oracle() -> str:
    """The same result in DuckDB SQL; entropy is recounted for each window."""
    chars = "string_split(m.v, '')"
    h = f"""list_max(list_transform(range(1, length(m.v) - {WINDOW} + 2), lambda i: round(log2({WINDOW}) - list_sum(list_transform(list_distinct({chars}[i:i+{WINDOW - 1}]),
      lambda c: len(list_filter({chars}[i:i+{WINDOW - 1}], lambda x: x = c)) * log2(len(list_filter({chars}[i:i+{WINDOW - 1}], lambda x: x = c))))) / {WINDOW}, 6)))"""
    spans = lambda name, no, cond: f"list_transform(list_filter({name}, lambda m: {cond}), lambda m: {{'start': m.s, 'kind_no': {no}, 'stop': m.e, 'kind': '{KINDS[no]}'}})"
    bits = " ".join(f"WHEN regexp_matches(m.v, '{p}') THEN {b}" for p, b in CLASSES[:-1])
    entropic = f"NOT regexp_matches(m.v, '{ALLOWED}') AND {h} >= CASE {bits} ELSE {CLASSES[-1][1]} END"
    joined = lambda x: f"array_to_string(list_transform({x}, lambda s: s.kind || ':' || s.start || ':' || s.stop), ',')"
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
    m AS (SELECT doc_id, {_sql_located(ASSIGN, 2)} AS a, {_sql_located(ACCESS, 0)} AS k, {_sql_located('[0-9a-f]{16,}', 0)} AS x, {_sql_located(CANDIDATE, 0)} AS c FROM d),
    s AS (SELECT doc_id, {spans('a', 0, 'length(m.v) >= 12')} AS a, {spans('k', 1, 'length(m.v) >= 18')} AS k, {spans('x', 2, 'true')} AS x, {spans('c', 3, entropic)} AS c FROM m),
    b AS (SELECT *, list_sort(list_concat(list_concat(a, k), x)) AS base FROM s),
    f AS (SELECT *, list_filter(c, lambda e: len(list_filter(base, lambda y: y.start < e.stop AND e.start < y.stop)) = 0) AS fresh FROM b)
    SELECT doc_id, CAST(len(a) AS BIGINT) AS n_assign, CAST(len(k) AS BIGINT) AS n_access, CAST(len(x) AS BIGINT) AS n_hex, CAST(len(fresh) AS BIGINT) AS n_entropy,
      sha256({joined('base')}) AS base_sha256, {joined('list_sort(list_concat(base, fresh))')} AS spans FROM f"""
