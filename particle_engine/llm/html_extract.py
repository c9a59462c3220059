"""Main-text extraction with a host suffix array.

A page is cut once into blocks with a role: chrome (navigation, headers, footers,
sidebars, notices, adverts, forms, comments), main (inside an article or main
element) or open (neither).  Chrome goes; on pages with an article open blocks are
page furniture and go too.  What is left is the page's token stream.

The streams of a host's pages are then searched for long substrings that distinct
pages repeat.  Pages are dealt by hash into groups of about ``GROUP`` pages of one
host (a host of any size is spread over as many tasks).  A group's streams are concatenated
and all their suffixes sorted (prefix doubling on word ranks, so a suffix ends with its
block); common-prefix lengths of neighbours give the maximal runs of suffixes that
share ``MIN_RUN`` words, and each run is counted by its distinct pages.  The counts of a
run's first words meet over the host's groups.  Blocks of fewer words count whole.

Words that such substrings cover go: of open blocks where ``SHARE`` of the host's pages
repeat them, and of main blocks, whose words are the article's own, only where
``MAIN_SHARE`` of the pages and ``MAIN_PAGES`` or more do.  Runs that are unique stay.

Defined results: null html gives empty text; character references are decoded
after tags are gone; unclosed and cut-off markup is read as far as it goes (a tag whose quote
never ends stops at its next '>'); repeated rows of one page_id and url are one page to the array
and give repeated results; a null url is the host without a name.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from urllib.parse import urlsplit

import numpy as np
import pyarrow as pa
import xxhash
import zstandard as zs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from particle_engine.llm.common import bounded_broadcast, small_batches, stage_table

MIN_RUN = 20
SHARE, MAIN_SHARE, MAIN_PAGES = 0.2, 0.5, 8
GROUP = 256
TOKEN = re.compile(
    r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)"
    r"|<(?P<raw>script|style|template|noscript|svg|math|iframe|object|select|textarea|title)\b[^>]*>.*?(?:</(?P=raw)\s*>|$)"
    r"|<(?P<end>/?)(?P<tag>[a-zA-Z][a-zA-Z0-9:-]*)(?P<marks>(?:[^>\"']|\"[^\"<]*\"|'[^'<]*')*)(?:>|$)"
    r"|<(?P<end2>/?)(?P<tag2>[a-zA-Z][a-zA-Z0-9:-]*)(?P<marks2>[^>]*)(?:>|$)|<[!?/][^>]*(?:>|$)",
    re.S | re.I,
)
SPACE = re.compile(r"\s+")
# Element names by the part they play.
INLINE = set("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
CHROME_TAGS = set("nav footer aside form button head menu dialog fieldset".split())
MAIN_TAGS = {"article", "main"}
# Words of class, id and role names that mark page furniture, and words that only say where or what shape it is.
CHROME_WORDS = set("ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments consent cookie cookies disqus footer gdpr masthead menu modal nav navbar navigation newsletter notice notices pager pagination popup promo promoted recommended related replies reply respond share sharing sidebar signup social sponsor sponsored subscribe teaser toolbar widget widgets".split())
PLACE_WORDS = set("area articles bar block body bottom box btn button buttons col column container content cta foot footer form global group head header icon icons inner item items left link links list main message outer overlay page panel posts primary right row secondary section site slot stories text thread title tools top unit user wrap wrapper".split())
CHROME_ROLES = set("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
MARK = re.compile(r"""\b(?:class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""", re.I)
WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


def _names_chrome(token: str) -> bool:
    """A name marks furniture if it has a word for it and otherwise only words of place: 'comment-list' does, 'related-work' not."""
    words = [w.lower() for w in WORDS.findall(token)]
    return any(w in CHROME_WORDS for w in words) and all(w in CHROME_WORDS or w in PLACE_WORDS for w in words)


def _is_chrome(tag: str, attributes: str, in_main: bool) -> bool:
    if tag in CHROME_TAGS or (tag == "header" and not in_main):
        return True
    if not attributes or tag in ("body", "html") or tag in MAIN_TAGS:
        return False
    tokens = [t for m in MARK.findall(attributes) for t in m.strip("\"'").split()]
    return any(_names_chrome(t) or t.lower() in CHROME_ROLES or (t.lower() in ("header", "site-header", "page-header") and not in_main) for t in tokens)


def blocks(page: str | None) -> list[tuple[str, str]]:
    """(role, text) of each non-empty block in page order; role is chrome, main or open."""
    page = page or ""
    out: list[tuple[str, str]] = []
    stack: list[tuple[str, bool, bool]] = []  # tag, chrome, main
    buffer: list[str] = []
    role = "open"
    mute: list = []  # an inline element of furniture: its tag, how often it is open, the depth around it

    def close() -> None:
        if buffer:
            text = SPACE.sub(" ", entities.unescape("".join(buffer))).strip()
            buffer.clear()
            if text:
                out.append((role, text))

    at = 0
    for m in TOKEN.finditer(page):
        if m.start() > at and not mute:
            buffer.append(page[at : m.start()])
        at = m.end()
        tag = m["tag"] or m["tag2"]
        if tag is None:
            if m["raw"]:
                close()
            continue
        tag, end, marks = tag.lower(), m["end"] or m["end2"], m["marks"] or m["marks2"] or ""
        if tag in INLINE:
            if mute and tag == mute[0]:
                mute[1] += -1 if end else 1
                if not mute[1]:
                    mute = []
            elif not mute and not end and marks and tag not in VOID and not marks.endswith("/") and _is_chrome(tag, marks, bool(stack and stack[-1][2])):
                mute = [tag, 1, len(stack)]
            continue
        close()
        if tag in VOID or marks.endswith("/"):
            continue
        if end:
            depth = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag), -1)
            if depth >= 0:
                del stack[depth:]
            if mute and len(stack) < mute[2]:
                mute = []
        else:
            if stack and stack[-1][0] == "p":  # any other block ends a paragraph
                stack.pop()
            chrome, main = stack[-1][1:] if stack else (False, False)
            if tag in MAIN_TAGS and not (chrome and main):
                chrome, main = False, True
            stack.append((tag, chrome or _is_chrome(tag, marks, main), main or tag in MAIN_TAGS))
        chrome, main = stack[-1][1:] if stack else (False, False)
        role = "chrome" if chrome else "main" if main else "open"
    if not mute:
        buffer.append(page[at:])
    close()
    return out


def stream(page: str | None) -> tuple[bool, list[str]]:
    """(whether the page has an article, its candidate blocks): main blocks if it has, else open ones."""
    parts = blocks(page)
    has_main = any(role == "main" for role, _ in parts)
    wanted = "main" if has_main else "open"
    return has_main, [text for role, text in parts if role == wanted]


def host_of(url: str | None) -> str:
    try:
        return (urlsplit(url or "").hostname or "").lower()
    except ValueError:
        return ""


def _hash(text: str) -> int:
    return xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass")) - (1 << 63)


def suffix_array(tokens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, lcp): suffixes of an integer text in order, and the common-prefix length of each with the one before."""
    n = len(tokens)
    rank = np.unique(tokens, return_inverse=True)[1].astype(np.int64)
    levels, step, top = [rank], 1, int(rank.max(initial=0))
    while step < n and top < n - 1:  # ranks of prefixes of twice the length, until all differ
        after = np.zeros(n, np.int64)
        after[: n - step] = rank[step:] + 1
        rank = np.unique(rank * (n + 2) + after, return_inverse=True)[1].astype(np.int64)
        levels.append(rank)
        step, top = 2 * step, int(rank.max())
    order = np.argsort(rank, kind="stable")
    a, b = order[1:].copy(), order[:-1].copy()
    lcp = np.zeros(n, np.int64)
    for level in range(len(levels) - 1, -1, -1):  # equal ranks of a level are equal prefixes of its length
        inside = (a < n) & (b < n)
        same = np.zeros(n - 1 if n else 0, bool)
        same[inside] = levels[level][a[inside]] == levels[level][b[inside]]
        same &= np.maximum(a, b) + (1 << level) <= n
        for side in (a, b):
            side[same] += 1 << level
    if n:
        lcp[1:] = a - order[1:]
    return order, lcp


def repeated_runs(pages: list[list[str]]) -> list[tuple[int, int]]:
    """(key, pages) of what two or more of the pages repeat: runs of ``MIN_RUN`` words, and shorter blocks whole."""
    ids: dict[str, int] = {}
    tokens: list[int] = []
    page_of: list[int] = []
    words_at: list[str] = []
    short: Counter = Counter()
    ends = 0
    for p, texts in enumerate(pages):
        whole = set()
        for text in texts:
            words = text.lower().split(" ")
            if len(words) < MIN_RUN:
                whole.add(_hash("\x00" + " ".join(words)))
                continue
            ends += 1
            tokens += [ids.setdefault(w, len(ids) + 1) for w in words]
            tokens.append(-ends)  # no two blocks end alike, so no common prefix leaves its block
            words_at += words
            words_at.append("")
            page_of += [p] * (len(words) + 1)
        short.update(whole)
    out = [(k, n) for k, n in short.items() if n > 1]
    if not tokens:
        return out
    order, lcp = suffix_array(np.array(tokens, np.int64))
    run_no = np.cumsum(lcp < MIN_RUN)  # neighbours that share MIN_RUN words are one run
    owner = np.array(page_of, np.int64)[order]
    pairs = np.unique(np.stack((run_no, owner)), axis=1)  # distinct pages of each run
    runs, n_pages = np.unique(pairs[0], return_counts=True)
    first = np.searchsorted(run_no, runs[n_pages > 1])
    for at, n in zip(order[first].tolist(), n_pages[n_pages > 1].tolist()):
        out.append((_hash(" ".join(words_at[at : at + MIN_RUN])), n))
    return out


def uncovered(text: str, repeated: set[int]) -> str:
    """The words of a block that no repeated substring covers."""
    words = text.split(" ")
    lower = text.lower().split(" ")
    if len(words) < MIN_RUN:
        return "" if _hash("\x00" + " ".join(lower)) in repeated else text
    covered = np.zeros(len(words), bool)
    for j in range(len(words) - MIN_RUN + 1):
        if _hash(" ".join(lower[j : j + MIN_RUN])) in repeated:
            covered[j : j + MIN_RUN] = True
    return text if not covered.any() else " ".join(w for w, gone in zip(words, covered.tolist()) if not gone)


def _packed(texts: list[str]) -> bytes:
    return zs.ZstdCompressor(level=1).compress("\x00".join(texts).encode("utf-8", "surrogatepass"))


def _unpacked(data: bytes) -> list[str]:
    whole = zs.ZstdDecompressor().decompress(data).decode("utf-8", "surrogatepass")
    return whole.split("\x00") if whole else []


def _parsed(pages: DataFrame) -> DataFrame:
    """(page_id, url, host_key, page_key, has_main, stream): each page parsed once; streams travel compressed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hosts, keys, mains, streams = [], [], [], []
            for page_id, url, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                has_main, texts = stream(html.as_py())
                hosts.append(_hash(host_of(url)))
                keys.append(_hash(f"{page_id}\x00{url}"))
                mains.append(has_main)
                streams.append(_packed([t.replace("\x00", "�") for t in texts]))
            columns = [pa.array(hosts, pa.int64()), pa.array(keys, pa.int64()), pa.array(mains, pa.bool_()), pa.array(streams, pa.binary())]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns], ["page_id", "url", "host_key", "page_key", "has_main", "stream"])

    source = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return small_batches(source).mapInArrow(run, "page_id long, url string, host_key long, page_key long, has_main boolean, stream binary")


def _group_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Repeated runs of each group; rows (host_key, shard, page_key, stream) arrive sorted, and a group may span batches."""
    held: dict[int, list[str]] = {}
    group: tuple[int, int] | None = None

    def flush() -> pa.RecordBatch:
        found = repeated_runs(list(held.values()))
        return pa.RecordBatch.from_arrays([pa.array([group[0]] * len(found), pa.int64()), pa.array([k for k, _ in found], pa.int64()), pa.array([n for _, n in found], pa.int64())], ["host_key", "key", "n"])

    for batch in batches:
        for host, shard, page, data in zip(*(batch.column(i).to_pylist() for i in range(3)), batch.column(3)):
            if (host, shard) != group:
                if group is not None:
                    yield flush()
                held, group = {}, (host, shard)
            held.setdefault(page, _unpacked(data.as_py()))  # repeated rows of a page are one page
    if group is not None:
        yield flush()


def host_runs(parsed: DataFrame) -> DataFrame:
    """(host_key, open_keys, main_keys): what is boilerplate on each host that has any."""
    totals = stage_table(parsed.groupBy("host_key").agg(F.count_distinct("page_key").alias("total")), "hosts")
    several = bounded_broadcast(totals.where("total > 1"), 32, totals.count())
    dealt = parsed.join(several, "host_key").withColumn("shard", F.pmod(F.xxhash64("page_key"), F.expr(f"(total + {GROUP - 1}) div {GROUP}")))
    dealt = dealt.select("host_key", "shard", "page_key", "stream").repartition("host_key", "shard").sortWithinPartitions("host_key", "shard", "page_key")
    counted = small_batches(dealt).mapInArrow(_group_runs, "host_key long, key long, n long").groupBy("host_key", "key").agg(F.sum("n").alias("n"))
    often = counted.join(several, "host_key").where(F.col("n") >= SHARE * F.col("total"))
    main = (F.col("n") >= MAIN_SHARE * F.col("total")) & (F.col("n") >= MAIN_PAGES)
    return stage_table(often.groupBy("host_key").agg(F.collect_list("key").alias("open_keys"), F.collect_list(F.when(main, F.col("key"))).alias("main_keys")), "host-runs")


def extract(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars): one row per page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = []
            for has_main, data, open_keys, main_keys in zip(batch.column(2).to_pylist(), batch.column(3), batch.column(4), batch.column(5)):
                gone = set((main_keys if has_main else open_keys).as_py() or ())
                kept = _unpacked(data.as_py())
                text.append(" ".join(filter(None, (uncovered(t, gone) for t in kept) if gone else kept)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(text, pa.string())], ["page_id", "url", "text"])

    parsed = stage_table(_parsed(pages), "parsed-pages")
    runs = host_runs(parsed)
    # a host has as many keys as a page has words, at most five times over
    keys = runs.agg(F.coalesce(F.sum(F.size("open_keys") + F.size("main_keys") + 4), F.lit(0)).alias("n")).first()["n"]
    rows = parsed.join(bounded_broadcast(runs, 8, keys), "host_key", "left").select("page_id", "url", "has_main", "stream", "open_keys", "main_keys")
    out = small_batches(rows).mapInArrow(run, "page_id long, url string, text string")
    return out.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
