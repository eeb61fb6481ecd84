"""Near duplicates, substrings, pages and media: against brute force, and on awkward rows."""

import hashlib
import itertools
import random
import struct

import numpy as np
import pytest
from test_text_ops import ROWS, SCHEMA

from fdrepair.llm import media, neardup, pages, substrings
from fdrepair.llm.common import WordHashes


def text_of(rnd, n, words=400):
    return [f"w{rnd.randrange(words)}" for _ in range(n)]


def corpus(seed=3):
    """Texts with exact and near copies, shared passages, short and empty ones."""
    rnd, rows = random.Random(seed), []
    passage = text_of(rnd, 60)
    for _ in range(12):
        base = text_of(rnd, rnd.choice([4, 18, 60, 200]))
        rows.append(base)
        for _ in range(rnd.randrange(4)):
            copy = list(base)
            for _ in range(rnd.randrange(3)):
                copy[rnd.randrange(len(copy))] = "changed"
            rows.append(copy)
        rows.append(text_of(rnd, 20) + passage[: rnd.randrange(15, 60)] + text_of(rnd, 5))
        twice = text_of(rnd, 30)
        rows.append(twice + twice)
    rnd.shuffle(rows)
    return [(k * 3 + 1, " ".join(r)) for k, r in enumerate(rows)]


@pytest.fixture(scope="module")
def rows(spark):
    return [*corpus(), (9000, None), (9001, ""), (9002, "one two"), (9003, "one two")]


def union(ids, links):
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    return {i: find(i) for i in ids}


def test_near_duplicates_as_brute_force(spark, rows):
    hashes = WordHashes()
    vectors = {i: neardup.weighted_shingles(hashes.array(neardup.words_of(t))) for i, t in rows}
    links = [(a, b) for a, b in itertools.combinations(vectors, 2) if len(vectors[a][0]) and neardup.similarity(vectors[a], vectors[b]) >= 0.8]
    want = union(list(vectors), links)
    got = {r.doc_id: r.class_id for r in neardup.classes(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == want
    kept = neardup.keep_one(spark.createDataFrame(rows, SCHEMA))
    assert sorted(r.doc_id for r in kept.collect()) == sorted(set(want.values()))


def test_large_buckets_lose_nothing(spark, monkeypatch):
    monkeypatch.setattr(neardup, "SMALL", 2)
    rnd = random.Random(5)
    base = text_of(rnd, 120, 5000)
    rows = []
    for k in range(60):
        copy = list(base)
        for _ in range(rnd.randrange(3)):
            copy[rnd.randrange(len(copy))] = f"x{rnd.randrange(999)}"
        rows.append((k, " ".join(copy)))
    hashes = WordHashes()
    v = {i: neardup.weighted_shingles(hashes.array(neardup.words_of(t))) for i, t in rows}
    want = union(list(v), [(a, b) for a, b in itertools.combinations(v, 2) if neardup.similarity(v[a], v[b]) >= 0.8])
    got = {r.doc_id: r.class_id for r in neardup.classes(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == want


def test_a_hub_in_the_middle_of_a_large_bucket(spark):
    """Copies that are similar to one text only, whose id is neither the least nor the greatest: one class."""
    rnd = random.Random(8)
    base = text_of(rnd, 300, 50_000)
    rows = [(50, " ".join(base))]
    for k in [*range(50), *range(51, 101)]:
        copy, at = list(base), rnd.randrange(270)
        copy[at : at + 24] = [f"x{k}y{j}" for j in range(24)]
        rows.append((k, " ".join(copy)))
    hashes = WordHashes()
    v = {i: neardup.weighted_shingles(hashes.array(neardup.words_of(t))) for i, t in rows}
    assert all(neardup.similarity(v[50], v[i]) >= 0.8 for i in v)
    assert sum(neardup.similarity(v[i], v[j]) < 0.8 for i, j in itertools.combinations(v, 2)) > 4000
    got = {r.class_id for r in neardup.classes(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == {0}


def test_large_buckets_of_different_texts(spark):
    """Rounds go on to the last pair: links between members that no early pivot is similar to are found."""
    rnd = random.Random(9)
    base = text_of(rnd, 300, 50_000)
    rows = []
    for k in range(40):
        copy, at = list(base), rnd.randrange(260)
        copy[at : at + 32] = [f"x{k // 2}y{j}" for j in range(32)] if k > 30 else [f"z{k}y{j}" for j in range(32)]
        rows.append((k, " ".join(copy)))
    hashes = WordHashes()
    v = {i: neardup.weighted_shingles(hashes.array(neardup.words_of(t))) for i, t in rows}
    want = union(list(v), [(a, b) for a, b in itertools.combinations(v, 2) if neardup.similarity(v[a], v[b]) >= 0.8])
    got = {r.doc_id: r.class_id for r in neardup.classes(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == want and 1 < len(set(want.values())) < 40


def test_darts_estimate_weighted_similarity():
    rnd = np.random.default_rng(1)
    for share in (0.3, 0.8):
        elements = rnd.integers(0, 1 << 62, 400, dtype=np.uint64)
        a = rnd.integers(1, 6, 400).astype(float)
        b = np.where(rnd.random(400) < share, a, rnd.integers(1, 6, 400))
        true = np.minimum(a, b).sum() / np.maximum(a, b).sum()
        same = np.mean(neardup.dart_signature(elements, a, 2000) == neardup.dart_signature(elements, b, 2000))
        assert abs(same - true) < 0.05
    one = np.array([7], np.uint64)
    assert len(neardup.dart_signature(one, np.array([1.0]))) == neardup.HASHES


def test_near_duplicates_awkward(spark):
    df = spark.createDataFrame(ROWS, SCHEMA).selectExpr("*", "1 as class_id", "2 as node", "3 as keys")
    got = [(r.doc_id, r.class_id) for r in neardup.classes(df).collect()]
    assert sorted(got, key=str) == sorted({(i, i) for i, _ in ROWS}, key=str)
    assert neardup.keep_one(df).count() == len({i for i, _ in ROWS}) and neardup.keep_one(df).columns == df.columns
    assert neardup.classes(spark.createDataFrame([], SCHEMA)).count() == 0


def removed_by_rule(rows):
    words = {i: (t or "").encode().split() for i, t in rows}
    seen, out = {}, {}
    for i in sorted(words):
        for p in range(len(words[i]) - 19):
            seen.setdefault(tuple(words[i][p : p + 20]), (i, p))
    for i, w in words.items():
        gone = [False] * len(w)
        for p in range(len(w) - 19):
            if seen[tuple(w[p : p + 20])] < (i, p):
                gone[p : p + 20] = [True] * 20
        kept = [x for x, g in zip(w, gone) if not g]
        out[i] = (len(w), sum(gone), hashlib.sha256(b" ".join(kept)).hexdigest())
    return out


@pytest.mark.parametrize("shard,split", [(5000, 100_000), (1, 100_000), (5000, 2)])
def test_substrings_as_brute_force(spark, rows, monkeypatch, shard, split):
    monkeypatch.setattr(substrings, "SHARD", shard)
    monkeypatch.setattr(substrings, "SPLIT", split)
    got = {r.doc_id: tuple(r)[1:] for r in substrings.digests(substrings.repeats(spark.createDataFrame(rows, SCHEMA))).collect()}
    assert got == removed_by_rule(rows)


def test_substrings_awkward(spark):
    df = spark.createDataFrame(ROWS, SCHEMA).selectExpr("*", "1 as ranges", "2 as name")
    got = substrings.digests(substrings.repeats(df)).collect()
    assert len(got) == len(ROWS)
    assert {r.n_removed for r in got if r.doc_id in (1, 2, 3, 4, None)} == {0}
    # three words over and over: only the first 3 windows are new, so only the words before the fourth window stay
    assert next(r for r in got if r.doc_id == 5).n_removed == 60_000 - 3
    assert substrings.without_repeats(df).count() == len(ROWS)
    assert substrings.repeats(spark.createDataFrame([], SCHEMA)).count() == 0


def test_automaton_statistics():
    rnd = random.Random(2)
    for _ in range(200):
        added = [[rnd.randrange(3) for _ in range(rnd.randrange(8))] for _ in range(3)]
        automaton = substrings.SuffixAutomaton()
        for a in added:
            automaton.add(a)
        text = [rnd.randrange(3) for _ in range(9)]
        runs = {tuple(a[i:j]) for a in added for i in range(len(a)) for j in range(i + 1, len(a) + 1)}
        want = [max((n for n in range(k + 2) if tuple(text[k + 1 - n : k + 1]) in runs), default=0) for k in range(len(text))]
        assert automaton.statistics(text) == want


@pytest.mark.parametrize("size", [10, 200_000])
def test_against_a_reference(spark, size):
    rnd = random.Random(4)
    passage = text_of(rnd, 50)
    docs = spark.createDataFrame([(1, " ".join(text_of(rnd, 10, 9) + passage[:30] + text_of(rnd, 10, 9))), (2, " ".join(passage[:19])), (3, None)], SCHEMA)
    reference = spark.createDataFrame([(" ".join(passage),), (None,)], "text string")
    got = {r.doc_id: [(x.start, x.stop) for x in r.ranges] for r in substrings.against(docs, reference, shard_words=size, at_once=2).collect()}
    covered = {k for a, b in got[1] for k in range(a, b)}
    assert covered == set(range(10, 40)) and got[2] == [] and got[3] == []


PAGE = """<!DOCTYPE html><html><head><title>No &amp; no</title><style>p{}</style></head><body><header><h1>Site</h1></header><nav><ul><li><a href="/">Home</a></ul></nav>
<div class="cookie-notice">We use cookies</div>%s<aside>More</aside><form><label>Name</label><input></form><section id="comments"><article class="comment"><p>Nice!</p></article></section><footer>&copy; 2020</footer></body></html>"""


def test_page_blocks():
    page = PAGE % "<article><h1>Title &lt;1&gt;</h1><!-- <p>hidden</p> --><p>One <b>two</b>\n three<br>four<p>Five &eacute;<div class='ad'>Buy</div><ul><li>six</li></ul><script>var a='<p>x</p>'</script></article>"
    kept = [t for r, t in pages.blocks(page) if r == pages.KEPT]
    assert kept == ["Title <1>", "One two three four", "Five é", "six"]
    assert pages.blocks(None) == [] and pages.blocks("") == [] and pages.blocks("<p>cut <b") == [(pages.OPEN, "cut")]


def test_lines_shared_with_a_neighbour_go(spark):
    frame = lambda k: f"<html><body><div>Welcome to our site</div><div>Story {k} is told here</div><p>Second part of story {k}</p><div>All rights reserved</div></body></html>"
    rows = [(k, f"https://a.example/news/{k}", frame(k)) for k in range(8)] + [(20, "https://b.example/x", frame(99)), (21, None, None), (22, "::bad", "")]
    rows.append((0, "https://a.example/news/0", frame(0)))  # a repeated row
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    got = {r.page_id: r.text for r in pages.main_text(df).collect()}
    assert got[5] == "Story 5 is told here\nSecond part of story 5"
    assert got[20].startswith("Welcome") and got[21] == "" and got[22] == ""
    assert pages.main_text(df).count() == len(rows)
    assert pages.main_text(spark.createDataFrame([], df.schema)).count() == 0


def longest(a, b):
    """Length of a longest common subsequence, cell by cell."""
    row = [0] * (len(b) + 1)
    for x in a:
        last = row[:]
        for k, y in enumerate(b):
            row[k + 1] = last[k] + 1 if x == y else max(row[k], last[k + 1])
    return row[-1]


@pytest.mark.parametrize("most", [1, 30, 10**9])
def test_common_lines_as_brute_force(most):
    rnd = random.Random(3)
    for _ in range(300):
        a, b = ([rnd.randrange(6) for _ in range(rnd.randrange(18))] for _ in range(2))
        got = pages.common(a, b, most)
        for side in (a, b):
            rest = iter(side)
            assert all(x in rest for x in got)
        assert len(got) == longest(a, b)


def test_long_pages_in_bounded_memory():
    a = list(range(30_000))
    assert len(pages.common(a[::2] + a, a + a[::3])) >= 30_000


def test_differencing_as_brute_force(spark):
    """Lines that a page has in common with a neighbour by path go unless they are in its article; then markup's dropped ones go."""
    rnd, rows = random.Random(12), []
    frames = {"a.example": ["Welcome", "Menu of the site", "Contact us"], "b.example": ["Top", "All rights reserved"]}
    for k in range(60):
        host = rnd.choice(list(frames))
        frame = [f"<div>{t}</div>" for t in frames[host] if rnd.random() < 0.8] + ["<nav>Nav shared</nav>", f"<aside>Aside {rnd.randrange(4)}</aside>"]
        own = [f"<p>Own {k} {j}</p>" for j in range(rnd.randrange(3))] + ["<article><p>Common story</p></article>"] * rnd.randrange(2)
        parts = frame + own
        rnd.shuffle(parts)
        rows.append((k, f"https://{host}/p/{rnd.randrange(1000):03d}", "".join(parts)))
    rows += [(100, None, None), (101, "https://c.example/", "<p>alone</p>" * 3000)]
    got = {r.page_id: r for r in pages.main_text(spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as blocks", "2 as text", "3 as shared").repartition(5)).collect()}
    cut = {i: pages.blocks(h) for i, _, h in rows}
    shared = {i: set() for i, _, _ in rows}
    in_order = sorted(((*pages.place(u), i) for i, u, _ in rows))
    for (h1, _, i), (h2, _, j) in zip(in_order, in_order[1:]):
        if h1 == h2:
            both = pages.common(*([pages.line_hash(t) for r, t in cut[x] if r != pages.KEPT] for x in (i, j)))
            shared[i] |= set(both)
            shared[j] |= set(both)
    for i, _, _ in rows:
        differ = [(r, t) for r, t in cut[i] if r == pages.KEPT or pages.line_hash(t) not in shared[i]]
        kept = [t for r, t in differ if r != pages.DROPPED]
        assert (got[i].text, got[i].n_shared, got[i].n_marked) == ("\n".join(kept), len(cut[i]) - len(differ), len(differ) - len(kept))
    assert sum(r.n_shared for r in got.values()) > 50 and sum(r.n_marked for r in got.values()) > 5


def test_media_round_trip(spark):
    df = spark.createDataFrame(ROWS, SCHEMA).selectExpr("*", "1 as media", "2 as clip")
    got = media.digests(df).collect()
    assert len(got) == len(ROWS)
    for r, (_, t) in zip(sorted(got, key=lambda r: (str(r.doc_id), r.n_bytes)), sorted(ROWS, key=lambda r: (str(r[0]), len((r[1] or "").encode())))):
        n, payload = media.payload_of(t)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (n, len(payload), hashlib.sha256(payload).hexdigest())
    assert {r.payload_bytes for r in got if r.doc_id == 1} == {192}
    assert media.clips(media.store(df)).count() >= len(ROWS)
    assert media.digests(spark.createDataFrame([], SCHEMA)).count() == 0


def test_media_all_bytes_and_no_index():
    data = bytes(range(256)) * 9
    data = data.ljust(-(-len(data) // 192) * 192)
    file = media.files_of([data])[0]
    cut = file.rfind(b"idx1")
    for f in (file, file[:cut]):
        second, frames = media.samples_of([f])[0]
        assert b"".join(x.tobytes() for x in frames) == data and second == pytest.approx(0.04)
    assert media.shots([]) == []


def test_shots_follow_the_material():
    dark, light = np.full((8, 8), 10, np.uint8), np.full((8, 8), 200, np.uint8)
    assert media.shots([dark] * 6 + [light] * 5) == [(0, 6), (6, 11)]


def test_baseline_frame():
    """Two grey blocks with DC values only, packed by hand: quantiser 8, so samples are 128 plus the DC value."""
    quant = struct.pack(">BBHB", 0xFF, 0xDB, 67, 0) + bytes([8] * 64)
    size = struct.pack(">BBHBHHB", 0xFF, 0xC0, 11, 8, 8, 16, 1) + bytes([1, 0x11, 0])
    dc = struct.pack(">BBHB", 0xFF, 0xC4, 19 + 12, 0) + bytes(media.DC_COUNTS) + bytes(media.DC_VALUES)
    ac = struct.pack(">BBHB", 0xFF, 0xC4, 19 + 1, 0x10) + bytes([1, *[0] * 15]) + bytes([0])
    codes = media.canonical_codes(media.DC_COUNTS, media.DC_VALUES)
    bits = ""
    for d in (20, -50):  # differences of DC values
        n = abs(d).bit_length()
        code, length = codes[n]
        bits += f"{code:0{length}b}" + f"{d if d > 0 else d + (1 << n) - 1:0{n}b}" + "0"
    bits = bits.ljust(-(-len(bits) // 8) * 8, "1")
    scan = bytes(int(bits[k : k + 8], 2) for k in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")
    frame = b"\xff\xd8" + quant + size + dc + ac + struct.pack(">BBHB", 0xFF, 0xDA, 8, 1) + bytes([1, 0, 0, 63, 0]) + scan + b"\xff\xd9"
    image = media.decode_frames([frame])[0]
    assert image.shape == (8, 16) and set(image[:, :8].ravel()) == {148} and set(image[:, 8:].ravel()) == {98}
    file = media.avi([frame], 16, 8)
    assert media.samples_of([file])[0][1][0].tolist() == image.tolist()


def test_pages_are_stored_compressed(spark):
    """What is stored and dealt of a page takes less than half of its blocks, and gives them back."""
    page = "<nav>menu</nav><div>open é</div><article>" + "".join(f"<p>This is sentence {k} of the story of the day.</p>" for k in range(60)) + "</article>"
    row = pages.parsed(spark.createDataFrame([(1, "https://a.example/1", page)], "page_id long, url string, html string")).first()
    told = sum(len(t) for _, t in pages.blocks(page))
    assert "blocks" not in row.asDict() and len(row.packed) < told / 2
    text = "\n".join(t for r, t in pages.blocks(page) if r != pages.DROPPED)
    assert pages.left_over(row.packed, row.outside, []) == (text, 0, 1)
    assert pages.left_over(row.packed, row.outside, [pages.line_hash("open é")]) == (text.split("\n", 1)[1], 1, 1)


def test_bound_by_the_lightest_member_joins_nothing(spark):
    """A bucket's members learn its lightest one without a join, and the same members stay as by a join."""
    words = [f"w{k}" for k in range(60)]
    texts = spark.createDataFrame([(k, " ".join(words[: 30 + k % 25] + [f"x{k}_{j}" for j in range(k % 7)])) for k in range(40)], "node long, text string")
    large = spark.createDataFrame([(b, k, k % 3 if k % 3 else k, 40) for b in range(3) for k in range(40) if (k + b) % 4], "key long, node long, root long, n int")
    out = neardup.bounded(large, texts, 0.8)
    assert "least" not in "".join(line for line in out._jdf.queryExecution().optimizedPlan().toString().split("\n") if "Join" in line)
    runs = {r.node: neardup.weighted_shingles(WordHashes().array(neardup.words_of(r.text))) for r in texts.collect()}
    rows = [tuple(r)[:3] for r in large.collect()]
    root = {k: r for _, k, r in rows}
    where = {}
    for k, r in root.items():
        for e in runs[k][0]:
            where.setdefault(e, set()).add(r)
    w = {k: runs[k][1].sum() for k in root}
    s = {k: sum(c for e, c in zip(*runs[k]) if len(where[e]) > 1) for k in root}
    left = [x for x in rows if s[x[1]] >= w[x[1]] * (0.8 - 1e-9)]
    for _ in range(2):
        of = {key: [x for x in left if x[0] == key] for key, _, _ in left}
        left = [x for x in left if len({y[2] for y in of[x[0]]}) > 1 and s[x[1]] >= (w[x[1]] + min(w[y[1]] for y in of[x[0]])) * (0.8 / 1.8 - 1e-9)]
    assert left and sorted((r.key, r.node, r.root) for r in out.collect()) == sorted(left)
