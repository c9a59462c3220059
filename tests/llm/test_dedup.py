import hashlib
import itertools
import random
import re

import numpy as np
import xxhash

from particle_engine.llm import exact_dedup, line_dedup, simhash
from particle_engine.llm.common import connected_components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, digest string, fp string, line string"


def docs(spark, pairs):
    return spark.createDataFrame([(i, t, "en", "src1", len(t or ""), "d", "f", "l") for i, t in pairs], SCHEMA)


def words(seed, n, vocabulary=400):
    rng = random.Random(seed)
    return [f"w{rng.randrange(vocabulary)}" for _ in range(n)]


def brute_print(text, n=3):
    tokens = re.findall(rb"[^\x20\x09-\x0d]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    grams = [b" ".join(tokens[i : i + n]) for i in range(len(tokens) - n + 1)] or ([b" ".join(tokens)] if tokens else [])
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def closure(n, links):
    root = list(range(n))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in links:
        root[max(find(a), find(b))] = min(find(a), find(b))
    return [find(i) for i in range(n)]


def test_simhash_matches_brute_force(spark):
    texts = [" ".join(words(i, 200)) for i in range(30)]
    for i in range(10):
        changed = texts[i].split()
        changed[50] = "changed"
        texts.append(" ".join(changed))
    texts += [texts[0], "", None, "A b", "a B", "one two three", " \t\n"]
    prints = [brute_print(t) for t in texts]
    roots = closure(len(texts), [(i, j) for i in range(len(texts)) for j in range(i) if (prints[i] ^ prints[j]).bit_count() <= 3])
    got = simhash.near_duplicates(docs(spark, enumerate(texts))).collect()
    assert {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in got} == {i: (f"{p:016x}", c) for i, (p, c) in enumerate(zip(prints, roots))}


def test_similar_texts_are_linked(spark):
    rng = random.Random(9)
    texts = [" ".join(words(500 + i, 300, 5000)) for i in range(60)]
    for i in range(60):
        changed = texts[i].split()
        for at in rng.sample(range(300), 3 if i < 40 else 12):  # about 0.9 alike, and about 0.65
            changed[at] = "changed"
        texts.append(" ".join(changed))
    for i in range(150):  # a star: edits are less alike to each other than to their text
        changed = texts[0].split()
        for at in rng.sample(range(300), 6):
            changed[at] = f"edit{i}"
        texts.append(" ".join(changed))
    sets = [{tuple(t.split()[i : i + 5]) for i in range(296)} for t in texts]
    alike = [(i, j) for i in range(len(sets)) for j in range(i) if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])]
    prints = [brute_print(t, 5) for t in texts]
    assert sum((prints[i] ^ prints[j]).bit_count() > 3 for i, j in alike) > 50
    near = [(i, j) for i in range(len(texts)) for j in range(i) if (prints[i] ^ prints[j]).bit_count() <= 3]
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(docs(spark, [*enumerate(texts), (900, None), (901, "")]), 5, 0.8).collect()}
    assert [got[i] for i in range(len(texts))] == closure(len(texts), alike + near) and got[901] == 900


def test_near_copies_of_one_text_are_not_all_verified(spark, monkeypatch):
    """Texts three edits from one text: most pairs share a band, few are similar, sketches rule nearly all others out and none of the similar."""
    base, rng, texts = words(3, 120, 4000), random.Random(3), []
    for i in range(150):
        edited = list(base)
        for at in rng.sample(range(120), rng.choice((2, 3, 5))):
            edited[at] = f"x{i}.{at}"
        texts.append(" ".join(edited))
    met, alike = [], simhash._alike
    monkeypatch.setattr(simhash, "_alike", lambda pairs, *rest: met.append(pairs.count()) or alike(pairs, *rest))
    df = docs(spark, list(enumerate(texts)))
    key = {r["k"]: r["doc_id"] for r in df.selectExpr("doc_id", "xxhash64(text) as k").collect()}
    found = simhash.similar_links(df, 5, 0.8).collect()
    bands, sets = [set(simhash.min_bands(t, 5)) for t in texts], [set(simhash.shingles_of(t, 5)) for t in texts]
    shared = [(i, j) for i in range(150) for j in range(i) if bands[i] & bands[j]]
    true = [(i, j) for i, j in shared if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])]
    assert closure(150, [(key[a], key[b]) for a, b in found]) == closure(150, true)
    assert len(shared) > 5000 and met[1] < len(shared) / 10


def test_parity_of_texts_bounds_the_difference(spark):
    a, b = " ".join(words(1, 300)), " ".join(words(1, 290) + words(2, 20))
    x, y = (set(simhash.shingles_of(t, 5)) for t in (a, b))
    (n, p), (m, q) = simhash.parity(a, 5), simhash.parity(b, 5)
    assert (n, m) == (len(x), len(y)) and len(p) == simhash.SKETCH
    assert 0 < np.bitwise_count((p ^ q).view(np.uint64)).sum() <= len(x ^ y)
    assert simhash.parity(None, 5)[0] == 0


def test_gray_index_finds_all_links():
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, 200).astype(np.uint64)
    near = [base] + [base ^ (np.uint64(1) << rng.integers(0, 64, 200).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 200).astype(np.uint64)) for _ in range(3)]
    codes = np.unique(np.concatenate(near))
    rank = codes.copy()
    for s in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(s)
    codes = codes[np.argsort(rank)]
    far = np.bitwise_count(codes[:, None] ^ codes[None, :])
    want = closure(len(codes), [(i, j) for i, j in np.argwhere(far <= 3).tolist() if j < i])
    assert closure(len(codes), simhash.GrayIndex(codes).links()) == want


def test_accumulated_differences_at_every_radius():
    """Crowded codes, where whole nodes agree on most bits and are pruned by what their pairs above found."""
    rng = np.random.default_rng(8)
    for n in (1, 2, 17, 60, 150, 400):
        flips = rng.integers(0, 64, (n, 6)).tolist()
        codes = np.unique(np.array([0x0F0F1234ABCD5678 ^ sum(1 << b for b in set(f)) for f in flips], np.uint64))
        rank = codes.copy()
        for s in (1, 2, 4, 8, 16, 32):
            rank ^= rank >> np.uint64(s)
        codes = codes[np.argsort(rank)]
        far = np.bitwise_count(codes[:, None] ^ codes[None, :])
        for radius in (0, 3, 8):
            want = closure(len(codes), [(i, j) for i, j in np.argwhere(far <= radius).tolist() if j < i])
            assert closure(len(codes), simhash.GrayIndex(codes, radius).links()) == want


def test_every_near_pair_shares_a_key(spark):
    rng = np.random.default_rng(6)
    a = rng.integers(-(1 << 62), 1 << 62, 60)
    flips = [sum(1 << int(b) for b in rng.choice(63, 3, replace=False)) for _ in a]
    rows = [(int(x),) for x in a] + [(int(x) ^ f,) for x, f in zip(a, flips)]
    links = {frozenset((r["a"], r["b"])) for r in simhash.near_links(spark.createDataFrame(rows, "fp long").distinct()).collect()}
    assert {frozenset((int(x), int(x) ^ f)) for x, f in zip(a, flips)} <= links


def test_exact_groups(spark):
    rows = [(1, "Abc"), (2, "aBC"), (3, "abc "), (4, None), (5, ""), (6, "É"), (7, "é"), (8, "x" * 100_000), (9, "X" * 100_000), (9, "X" * 100_000), (None, "abc")]
    got = [tuple(r) for r in exact_dedup.exact_groups(docs(spark, rows), keep="max").select("doc_id", "keep_id", "group_size", "kept").collect()]
    assert sorted(got, key=str) == sorted(
        [(1, 2, 3, False), (2, 2, 3, True), (None, 2, 3, False), (3, 3, 1, True), (4, 5, 2, False), (5, 5, 2, True), (6, 6, 1, True), (7, 7, 1, True), (8, 9, 3, False), (9, 9, 3, True), (9, 9, 3, True)], key=str
    )
    one = exact_dedup.exact_groups(docs(spark, [(1, "Abc É")])).first()
    assert one["text_sha256"] == hashlib.sha256("abc É".encode()).hexdigest()
    assert exact_dedup.exact_groups(docs(spark, [])).collect() == []


def test_exact_index_keeps_smallest_and_probes(spark):
    first, second = docs(spark, [(5, "a"), (3, "a"), (4, "b")]), docs(spark, [(9, "A"), (10, "new")])
    level = exact_dedup.compact(exact_dedup.flush_runs(first))
    assert {(r["keep_id"], r["group_size"]) for r in level.collect()} == {(3, 2), (4, 1)}
    assert [tuple(r) for r in exact_dedup.probe(level, second).collect()] == [(9, 3)]


def jaccard(a, b):
    cut = lambda s: {s[i : i + 12] for i in range(len(s) - 11)}
    x, y = cut(a), cut(b)
    return len(x & y) / max(1, len(x | y))


def test_lines_without_spaces_and_inserted_letters(spark):
    rng = random.Random(11)
    letters = lambda n, of: "".join(rng.choice(of) for _ in range(n))
    lines = []
    for of in ("abcdefghijklmnopqrstuvwxyz", "xyz", "中文字符漢語書學生活工作時間地點人民", "абвгдежзиклмнпрст", "acgt0236"):
        for _ in range(6):
            line = letters(300, of)
            at = rng.randrange(300)
            lines += [line, "q" + line, line[:at] + line[at + 1 :], line[:150] + letters(150, of)]
    roots = closure(len(lines), [(i, j) for i in range(len(lines)) for j in range(i) if jaccard(lines[i], lines[j]) >= 0.8])
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(docs(spark, enumerate(lines))).collect()}
    assert {i for i, t in got.items() if t} == set(roots) and len(set(roots)) == 60


def test_lines_share_of_links_found(spark):
    """Recall of links at similarities around the threshold, against an exhaustive join."""
    rng = random.Random(12)
    vocabulary = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(2, 10))) for _ in range(3000)]
    lines = []
    for _ in range(150):
        line = [rng.choice(vocabulary) for _ in range(60)]
        near = list(line)
        for at in rng.sample(range(60), 2):
            near[at] = rng.choice(vocabulary)
        lines += [" ".join(line), " ".join(near)]
    alike = {(i, i + 1) for i in range(0, 300, 2) if jaccard(lines[i], lines[i + 1]) >= 0.8}
    got = {(r["a"], r["b"]) for r in line_dedup.line_links(spark.createDataFrame(list(enumerate(lines)), "line_id long, line string")).collect()}
    assert len(alike) > 100 and got <= alike and len(got) >= 0.97 * len(alike)


def test_fuzzy_lines_against_brute_force(spark):
    rng = random.Random(3)
    base = [" ".join(words(100 + i, 40)) for i in range(30)]
    lines = []
    for i, b in enumerate(base):
        lines.append(b)
        if i < 20:
            changed = b.split()
            changed[rng.randrange(40)] = "zz"
            lines.append(" ".join(changed))
    lines += ["short", "short", "tiny line", ""]
    pairs = [(i, lines[i]) for i in range(len(lines))]
    roots = closure(len(lines), [(i, j) for i in range(len(lines)) for j in range(i) if lines[i] == lines[j] or (lines[i] and lines[j] and jaccard(lines[i], lines[j]) >= 0.8)])
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(docs(spark, pairs)).collect()}
    assert got == {i: (t if roots[i] == i or not t else "") for i, t in pairs}


def test_star_of_edits_keeps_one_line(spark):  # 300 lines: bands over SMALL, medoid and prefix join
    rng = random.Random(1)
    vocabulary = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(3, 9))) for _ in range(2000)]
    template = [rng.choice(vocabulary) for _ in range(30)]
    lines = {" ".join(template)}
    while len(lines) < 300:
        edit = list(template)
        edit[rng.randrange(30)] = rng.choice(vocabulary)
        lines.add(" ".join(edit))
    lines = sorted(lines)
    roots = closure(len(lines), [(i, j) for i in range(len(lines)) for j in range(i) if jaccard(lines[i], lines[j]) >= 0.8])
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(docs(spark, enumerate(lines))).collect()}
    assert {i for i, t in got.items() if t} == set(roots)


def test_line_signatures_without_python_and_in_one_order(spark):
    """No step of line dedup leaves the engine; a line of few words fills its signature from its other shingles."""
    few, none, long = "abcdefghijklmn opqrstuvwxyz0123", "abcdefghijklmnopqrst", " ".join(words(5, 40))
    signed = line_dedup.signed_lines(spark.createDataFrame([(1, few), (2, none), (3, long), (4, "short")], "line_id long, line string"))
    plan = signed._jdf.queryExecution().executedPlan().toString()
    assert "MapIn" not in plan and "Python" not in plan
    xx = lambda x: (h := xxhash.xxh64_intdigest(x, 42)) - (h >> 63 << 64)
    grams = lambda x: {x[i : i + 12] for i in range(len(x) - 11)}
    want = lambda x: [h for _, h in sorted((g[0] != " ", xx(g)) for g in grams(x))[:5]]
    assert {r["line_id"]: r["sig"] for r in signed.collect()} == {1: want(few), 2: want(none), 3: want(long), 4: []}


def test_line_sketches_are_parities_of_shingles(spark):
    texts = ["a line with ten or more words, of wörds and 😀 smileys too " * 3, "exactly12chr", "short"]
    got = {r["line_id"]: r for r in line_dedup.sketched(spark.createDataFrame(list(enumerate(texts)), "line_id long, line string")).collect()}
    assert sorted(got) == [0, 1] and [got[i]["n"] for i in got] == [len({t[i : i + 12] for i in range(len(t) - 11)}) for t in texts[:2]]
    assert all(sum(bin(w & (1 << 64) - 1).count("1") for w in got[i]["bits"]) % 2 == got[i]["n"] % 2 for i in got)


def test_line_work_is_done_once(spark):
    """Documents are hashed below the generator of lines, lines are cut once for their sketch, values and bands are dealt out once."""
    plan = lambda df, kind="optimizedPlan": getattr(df._jdf.queryExecution(), kind)().toString()
    cut = plan(line_dedup._lines(docs(spark, [(1, "one line\nanother")]))).split("\n")
    where = lambda what: [i for i, x in enumerate(cut) if what in x and "xxhash64(doc_id" in x or what == "Generate" and what in x]
    assert len(where("Generate")) == 1 and where("row_key") and min(where("row_key")) > where("Generate")[0]
    lines = spark.createDataFrame([(i, " ".join(words(i // 2, 30)) + " x" * (i % 2)) for i in range(20)] * 2, "line_id long, line string")
    assert plan(line_dedup.sketched(lines)).count("encode(") == 1
    signed = line_dedup.signed_lines(lines).localCheckpoint()
    banded = line_dedup._bands(signed)
    got = [(r["band"], r["line_id"], r["size"]) for r in banded.collect()]
    assert plan(banded, "executedPlan").split("== Initial Plan ==")[0].count("ReusedExchange") == 2
    sigs = {r["line_id"]: r["sig"] for r in signed.collect()}
    members = {}
    for i, sig in sigs.items():
        for pair in itertools.combinations(sig, 2):
            members.setdefault(pair, set()).add(i)
    want = sorted((i, len(m)) for m in members.values() if len(m) > 1 for i in m)
    assert sorted((i, n) for _, i, n in got) == want and len({(b, i) for b, i, _ in got}) == len(want) > 40


def test_lines_of_several_shared_bands_meet_once(spark, monkeypatch):
    """The join across components makes each pair of lines once, however many bands both are in, and leaves none out."""
    rng = random.Random(4)
    held = {i: rng.sample(range(6), rng.randrange(1, 5)) for i in range(40)}
    comp = {i: 100 + i // 3 for i in held}
    top = {b: max(comp[i] for i in held if b in held[i]) for b in range(6)}
    rows = [(b, i, 100, 90, [0] * 8, comp[i], top[b]) for i in held for b in held[i]]
    apart = spark.createDataFrame(rows, "band long, line_id long, size long, n int, bits array<long>, comp long, top long")
    monkeypatch.setattr(line_dedup, "_ordered", lambda met: met)
    got = [tuple(sorted(r)) for r in line_dedup._rest(apart).select("x.line_id", "y.line_id").collect()]
    want = {(i, j) for i in held for j in held if i < j and comp[i] != comp[j] and set(held[i]) & set(held[j])}
    assert set(got) == want and len(got) == len(want)


def test_line_dedup_edges(spark):
    long = "\n".join(" ".join(words(i, 12)) for i in range(3000))
    rows = [(1, "keep me please now\n\nsecond line of it\nkeep me please now"), (2, "second line of it\n  \nown words stay here"), (3, None), (4, ""), (5, long), (6, "nospaces" * 500 + "\nx"), (6, "nospaces" * 500 + "\nx")]
    out = line_dedup.dedup_lines(docs(spark, rows))
    got = sorted(((r["doc_id"], r["text"], r["n_dropped"]) for r in out.collect()), key=lambda r: r[0])
    assert got[0] == (1, "keep me please now\n\nsecond line of it", 1)
    assert got[1] == (2, "  \nown words stay here", 1)
    assert got[2][1] is None and got[3][1] == "" and got[4][1] == long
    assert got[5] == got[6] == (6, "nospaces" * 500 + "\nx", 0)
    assert line_dedup.dedup_lines(docs(spark, [])).collect() == []
    assert out.columns[:8] == docs(spark, []).columns


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(60)] + [(1000, 1000 + i) for i in range(1, 40)] + [(7, 7)]
    got = connected_components(spark.createDataFrame(edges, "a long, b long"), "a", "b").collect()
    groups = {}
    for r in got:
        groups.setdefault(r["root"], set()).add(r["node"])
    assert sorted(map(len, groups.values())) == [40, 61]
    assert connected_components(spark.createDataFrame([], "a long, b long"), "a", "b").collect() == []
