"""BPE, quality, toxicity, PII, decontamination and LM scoring: against references, and on awkward rows."""

import hashlib
import math
import re
from collections import Counter

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fdrepair.llm import bpe, decontaminate, lmscore, pii, quality, toxicity
from fdrepair.llm.queries import tokenizer

LONG = "lorem ipsum dolor " * 20_000
ROWS = [(1, None), (2, ""), (3, "  \n\t "), (4, "plain words here, and more of them."), (4, "plain words here, and more of them."), (5, LONG), (None, "no id at all"), (6, "a" * 50_000), (7, "mail me at Jane.Doe@mail.example.com or +1 (555) 010-9999, ip 10.0.0.1")]
SCHEMA = "doc_id long, text string"


@pytest.fixture(scope="module")
def docs(spark):
    """Awkward rows, with extra columns named as the operators' outputs."""
    df = spark.createDataFrame(ROWS, SCHEMA)
    for c in ("score", "ids", "decoded", "n_tokens", "leaks", "class_id", "spans", "ranges", "media"):
        df = df.selectExpr("*", f"'old' as {c}")
    return df


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def reference():
    import tiktoken

    path, pattern = tokenizer()
    return tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=bpe.vocabulary(path), special_tokens={})


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=80) | st.text(alphabet="ab ", max_size=200) | st.text(alphabet="aé1!\n", max_size=120))
def test_bpe_as_reference(reference, text):
    codec = bpe.codec(*tokenizer())
    ids = codec.encode(text)
    assert ids == reference.encode_ordinary(text)
    assert codec.decode(ids) == text.encode("utf-8", "replace")


def test_bpe_long_pre_token(reference):
    import random

    codec, rnd = bpe.codec(*tokenizer()), random.Random(1)
    for text in ("a" * 20_000, "".join(rnd.choice("abcdeé") for _ in range(20_000))):
        assert codec.encode(text) == reference.encode_ordinary(text)


def test_bpe_rank_lower_than_its_parts():
    ranks = {bytes([b]): b + 10 for b in range(256)} | {b"ab": 300, b"abc": 1, b"bc": 301, b"cd": 299}
    codec = bpe.ByteBPE(ranks, r".+")
    assert codec.ids(b"abcd") == [ranks[b"ab"], ranks[b"cd"]]
    assert codec.ids(b"abcx") == [1, ranks[b"x"]]


def test_bpe_frames(docs, empty):
    got = bpe.digests(docs, *tokenizer()).collect()
    assert len(got) == len(ROWS)
    assert {r.decoded_sha256 for r in got if r.doc_id == 1} == {hashlib.sha256(b"").hexdigest()}
    back = bpe.decode(bpe.encode(docs, *tokenizer()), *tokenizer())
    assert all(bytes(r.decoded).decode() == (r.text or "") for r in back.collect())
    assert bpe.digests(empty, *tokenizer()).count() == 0


def test_quality_tells_prose_from_noise(spark, docs, empty):
    good = [f"the quick brown fox number {k} walks to the river and drinks water" for k in range(60)]
    bad = [f"$$$ %%% {k} ### &&& click!! WIN!! {k * 7} *** ### $$$ %%%" for k in range(60)]
    texts = spark.createDataFrame([(k, t) for k, t in enumerate(good + bad)], SCHEMA)
    labels = spark.createDataFrame([(k, int(k < 60)) for k in range(120)], "doc_id long, quality int")
    model = quality.fit(texts, labels)
    got = {r.doc_id: r.score for r in quality.score(texts, model).collect()}
    assert min(got[k] for k in range(60)) > 0.5 > max(got[k] for k in range(60, 120))
    assert all(0 <= r.score <= 1 for r in quality.score(docs, model).collect())
    none = quality.fit(empty, labels)
    assert {r.score for r in quality.score(docs, none).collect()} == {0.5}
    assert quality.score(empty, model).count() == 0


def test_toxicity_reads_disguised_words(spark, docs, empty):
    texts = [f"you are an idiot and a moron {k}" if k % 2 else f"you are a kind and helpful friend {k}" for k in range(80)]
    model = toxicity.fit_model(texts, [k % 2 for k in range(80)])
    scorer = toxicity.Scorer(model)
    for t in ("what an 1d10t", "such a m0r0n", "you i d i o t there", "what an i.d.i.o.t", "an idiooooot", "what an id!ot"):
        assert scorer.probability(t) > 0.7, t
    for t in ("a kind friend", "", None, "items 100 and 3d models"):
        assert scorer.probability(t) < 0.3, t
    assert all(0 <= r.score <= 1 for r in toxicity.score(docs, model).collect())
    assert toxicity.score(empty, model).count() == 0


def spans_by_rule(text):
    """Base spans by the patterns as stated."""
    out = [(0, *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [(1, *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = re.sub(r"\D", "", m[0])
        if 16 <= len(d) <= 19 and sum(sum(divmod(int(c) * 2, 10)) if k % 2 else int(c) for k, c in enumerate(reversed(d))) % 10 == 0:
            out.append((2, *m.span()))
    out += [(3, *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 8 <= len(re.sub(r"\D", "", m[0])) <= 15]
    return out


@settings(max_examples=400, deadline=None)
@given(st.text(alphabet="a1.@+- (4x%", max_size=60) | st.text(alphabet="0123456789 -.", max_size=60))
def test_pii_base_as_stated(text):
    assert pii.base_spans(text) == spans_by_rule(text)


def test_pii_base_long_runs():
    for text, n in (("9" * 200_000, 0), ("1." * 100_000, 25_000), ("a" * 100_000 + "@" * 1000, 0), ("+1" + " " * 100_000, 0), ("4111 1111 1111 1111", 1)):
        assert len(pii.base_spans(text)) == n


def test_pii_discloses_terms(spark, docs, empty):
    rows = [(k, f"write to zorblax quixote at secret@example.com about item {k}") for k in range(6)] + [(k + 10, f"the weather is fine at place {k} about item") for k in range(60)]
    df = spark.createDataFrame(rows, SCHEMA)
    got = {r.doc_id: r for r in pii.spans(df).collect()}
    words = {rows[0][1][t.start : t.end] for t in got[0].terms}
    assert "zorblax" in words and "item" not in words
    clean = {r.doc_id: r.text for r in pii.sanitise(df).collect()}
    assert "[EMAIL]" in clean[0] and "zorblax" not in clean[0] and clean[10] == rows[6][1]
    out = pii.digests(pii.spans(docs)).collect()
    assert len(out) == len(ROWS)
    assert {r.base_sha256 for r in out if r.doc_id == 1} == {hashlib.sha256(b"").hexdigest()}
    seven = next(r for r in out if r.doc_id == 7)
    assert (seven.n_email, seven.n_ip, seven.n_phone) == (1, 1, 1)
    assert pii.sanitise(docs).count() == len(ROWS) and pii.sanitise(docs).columns == docs.columns
    assert pii.spans(empty).count() == 0 and pii.sanitise(empty).count() == 0


def test_pii_terms_as_brute_force(spark):
    """Every term of a document with an entity, by the definition over whole documents."""
    import random

    rnd, rows = random.Random(6), []
    people = [f"p{k}@example.com" for k in range(12)]
    for k in range(300):
        words = [f"word{min(int(rnd.expovariate(0.05)), 400)}" for _ in range(30)]
        if k % 4 == 0:
            words += rnd.sample(people, rnd.choice([1, 1, 2, 3]))
        if k % 7 == 0:
            words += [f"only{k}"]
        rnd.shuffle(words)
        rows.append((k, " ".join(words)))
    rows.append((900, rows[0][1]))  # a copy
    rows.append((901, "far and near secret@example.com " + " ".join(["word1"] * 50) + " unheard"))
    held = [(i, set(re.findall(r"\S+@example\.com", t)), set(re.findall(r"\w{3,}", re.sub(r"\S+@\S+", " ", t))), t) for i, t in rows]
    size, n_t, n_e, both = len(rows), Counter(), Counter(), Counter()
    for _, entities, _, t in held:
        n_t.update(set(re.findall(r"\w{3,}", t)))
        n_e.update(entities)
    for _, entities, terms, _ in held:
        both.update((e, t) for e in entities for t in terms)
    want = {}
    for i, entities, terms, _ in held:
        want[i] = {t for t in terms for e in entities if math.log2(both[e, t] * size / (n_t[t] * n_e[e])) >= 0.8 * math.log2(size / n_e[e]) - 1e-9}
    got = {r.doc_id: {dict(rows)[r.doc_id][x.start : x.end] for x in r.terms} for r in pii.spans(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == want
    assert "unheard" in want[901] and "word1" not in want[901] and any(want[i] for i in range(0, 300, 4))


def test_pii_generalises_to_classes():
    text = "Call Zorblax or 12345 or ab12 or zorblax now"
    places = [{"start": m.start(), "end": m.end()} for m in re.finditer(r"\b(?:[Zz]orblax|12345|ab12)\b", text)]
    assert pii.redact(text, [], places) == "Call [NAME] or [NUMBER] or [CODE] or [WORD] now"


def test_decontamination(spark, docs, empty):
    item = "A farmer named Alice has 12 apples and gives 5 kg to Bob, how many apples does Alice keep at the end of that day?"
    bench = spark.createDataFrame([(1, item), (2, None), (3, ""), (4, "too short")], "item_id long, text string")
    texts = [
        (1, "Intro words come first. " + item + " And more follows."),
        (2, "Once more: A farmer named Carol has 40 apples and gives 9 lb to Dave, how many apples does Carol keep at the end of that day? Yes."),
        (3, "A farmer named Carol has 40 apples and gives 9 lb to Dave, how many apples does Erin keep at the end of"),
        (4, "nothing of the kind is said in this text, which has many other words in it"),
        (5, None),
    ]
    found = {(r.doc_id, r.item_id): r for r in decontaminate.leaks(spark.createDataFrame(texts, SCHEMA), bench).collect()}
    assert (1, 1) in found and (2, 1) in found and {d for d, _ in found} <= {1, 2, 3}
    assert found[1, 1].verbatim > 0 and found[2, 1].verbatim < found[2, 1].runs
    assert (3, 1) not in found or found[3, 1].runs < found[2, 1].runs
    assert decontaminate.clean(docs, bench).count() == len(ROWS)
    assert decontaminate.clean(docs, bench).columns == docs.columns
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.leaks(docs, none).count() == 0 and decontaminate.clean(docs, none).count() == len(ROWS)
    assert decontaminate.leaks(empty, bench).count() == 0


def test_decontamination_of_short_and_number_rich_items(spark):
    bench = spark.createDataFrame([(1, "Add 12 kg, 5 g, 7 kg and 3 g."), (2, "What is 2 + 2?"), (3, "12 34 56 78 90 11 13 17 19")], "item_id long, text string")
    texts = [
        (1, "It says so. Add 12 kg, 5 g, 7 kg and 3 g. That is all."),
        (2, "It says so. Add 40 lb, 6 oz, 9 lb and 8 oz. That is all."),
        (3, "It says so. Add 40 lb, 6 oz, 9 mg and 8 oz. That is all."),
        (4, "Now then. What is 2 + 2? Four."),
        (5, "Now then. What is 3 + 4? Seven."),
        (6, "codes 12 34 56 78 90 11 13 17 19 end"),
        (7, "codes 21 43 65 87 99 12 14 18 20 end"),
    ]
    found = {(r.doc_id, r.item_id): r for r in decontaminate.leaks(spark.createDataFrame(texts, SCHEMA), bench).collect()}
    assert set(found) == {(1, 1), (2, 1), (4, 2), (6, 3)}
    assert found[1, 1].verbatim == found[1, 1].runs and found[2, 1].verbatim == 0


@settings(max_examples=300, deadline=None)
@given(st.lists(st.sampled_from(["Alice", "alice", "A", "12", "kg", "Kg", "%", "$", ".", "\n", "3.5", "don't", "McDonald", "x", "é"]), max_size=14).map(" ".join))
def test_template_by_arrays(text):
    kinds, _ = decontaminate.template(text)
    hashes = decontaminate.Codes().template(text).tolist()
    assert len(kinds) == len(hashes)
    assert len(set(zip(kinds, hashes))) == len(set(kinds)) == len(set(hashes))


def leaks_by_rule(doc, item):
    """(runs, verbatim) of an item in a document, window by window and diagonal by diagonal."""
    kinds, values = decontaminate.template(doc)
    their_kinds, their_values = decontaminate.template(item)
    width = min(8, len(their_kinds))
    n, good, same = len(their_kinds) - width + 1, 0, 0
    if not width:
        return 0, 0
    for shift in range(-len(their_kinds), len(kinds)):
        at = [q for q in range(n) if 0 <= q + shift <= len(kinds) - width and kinds[q + shift : q + shift + width] == their_kinds[q : q + width]]
        pairs = lambda qs: {(their_kinds[k], their_values[k], values[k + shift]) for q in qs for k in range(q, q + width) if their_kinds[k][0] == "\x00"}
        one_to_one = lambda p: len({x[:2] for x in p}) == len(p) == len({(x[0], x[2]) for x in p})
        bound = []
        for q in at:
            literals = sum(x[0] != "\x00" for x in their_kinds[q : q + width])
            verbatim = their_values[q : q + width] == values[q + shift : q + shift + width]
            if width >= 6 and literals >= min(5, width):
                if one_to_one(pairs([*bound, q])):
                    bound.append(q)
                    good, same = good + 1, same + verbatim
            elif verbatim:
                good, same = good + 1, same + 1
            elif len(at) == n and len(their_kinds) >= 6 and any(x[0] != "\x00" for x in their_kinds) and one_to_one(pairs(at)):
                good += 1
    return good, same


def test_decontamination_as_brute_force(spark):
    import random

    rnd = random.Random(11)
    some = ["12", "7", "kg", "lb", "Alice", "Bob", "the", "a", "has", "red", "box", "and", "of", "then", ".", "goes", "home"]
    items = [(k, " ".join(rnd.choice(some) for _ in range(rnd.choice([0, 3, 6, 9, 14, 25])))) for k in range(25)]
    docs = []
    for k in range(40):
        parts = [" ".join(rnd.choice(some) for _ in range(rnd.randrange(12)))]
        for _ in range(rnd.randrange(3)):
            words = rnd.choice(items)[1].split()
            swap = rnd.choice([{}, {"12": "40"}, {"Alice": "Carol", "kg": "oz"}, {"12": "7"}])
            words = [swap.get(w, w) for w in words]
            if words and rnd.random() < 0.3:
                words[rnd.randrange(len(words))] = rnd.choice(some)
            parts += [" ".join(words), rnd.choice(some)]
        docs.append((k, " ".join(parts)))
    bench = spark.createDataFrame(items, "item_id long, text string")
    df = spark.createDataFrame(docs, SCHEMA)
    want = {(d, i): v for d, t in docs for i, x in items if (v := leaks_by_rule(t, x))[0]}
    got = {(r.doc_id, r.item_id): (r.runs, r.verbatim) for r in decontaminate.leaks(df, bench).collect()}
    assert got == want and len(want) > 20
    assert {r.doc_id for r in decontaminate.clean(df, bench).collect()} == {d for d, _ in docs} - {d for d, _ in want}


def test_lm_scores_by_hand(spark, docs, empty):
    texts = [(1, "a b a b"), (2, "a c"), (3, "c c c d"), (4, None)]
    df = spark.createDataFrame(texts, SCHEMA)
    labels = spark.createDataFrame([(1, 1), (2, 1), (3, 0)], "doc_id long, quality int")
    got = {r.doc_id: r for r in lmscore.cross_entropy_difference(df, labels).collect()}

    def bits(text, corpus):
        vocab = {"a", "b", "c", "d"}
        words, after, ctx = Counter(), Counter(), Counter()
        for t in corpus:
            prev = "<s>"
            for w in t.split():
                words[w] += 1
                after[prev, w] += 1
                ctx[prev] += 1
                prev = w
        total, prev, out = sum(words.values()), "<s>", []
        for w in text.split():
            one = (words[w] + 1) / (total + len(vocab) + 1)
            out.append(-math.log2(0.7 * after[prev, w] / ctx[prev] + 0.3 * one if ctx[prev] else one))
            prev = w
        return sum(out) / len(out)

    for i, t in texts[:3]:
        target, background = bits(t, ["a b a b", "a c"]), bits(t, ["a b a b", "a c", "c c c d"])
        assert got[i].target_bits == pytest.approx(target, abs=1e-5)
        assert got[i].score == pytest.approx(background - target, abs=1e-5)
    assert got[4].n_words == 0 and got[4].score == 0
    assert got[1].score > got[3].score
    assert lmscore.cross_entropy_difference(docs, labels).count() == len(ROWS)
    assert lmscore.cross_entropy_difference(empty, labels).count() == 0


def test_toxicity_is_fitted_on_all_labelled_rows(spark):
    """The odds of a word count every labelled text, and a few texts get what the fit on lists gives."""
    from pyspark.sql import functions as F

    n = 12_000
    docs = spark.range(n).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 2 == 1, F.concat(F.lit("you vile grobnik number "), F.col("id"))).otherwise(F.concat(F.lit("a calm day with number "), F.col("id"))).alias("text"))
    labels = docs.select("doc_id", (F.col("doc_id") % 2).cast("int").alias("toxic"))
    model = toxicity.fit(docs, labels)
    rows = labels.where(toxicity.crc_mod(F.col("doc_id"), 3) != 1).groupBy("toxic").count().orderBy("toxic").collect()
    other, toxic = rows[0]["count"], rows[1]["count"]
    assert toxic + other > 7500 and toxicity.LEAST_TEXTS < toxic
    assert model.odds["=grobnik"] == pytest.approx(math.log((toxic + 0.1) / (toxic + 1)) - math.log(0.5 / (other + 1)))
    assert model.odds["=grobnik"] > math.log(2 * 3500)
    scorer = toxicity.Scorer(model)
    assert scorer.probability("such a grobnik") > 0.9 > 0.1 > scorer.probability("a calm day")
    again = toxicity.fit(docs.repartition(7), labels)
    assert again.odds == model.odds and again.letters.logs == model.letters.logs and again.weights == pytest.approx(model.weights, abs=1e-6)


def test_runs_of_several_widths_and_few_false_hits(spark):
    import numpy as np
    from fdrepair.llm.common import mix64, rolled, rolled_all

    for n in (0, 1, 5, 40):
        ids = mix64(np.arange(n, dtype=np.uint64))
        got = rolled_all(ids, [2, 3, 8])
        assert all(np.array_equal(got.get(w, np.empty(0, np.uint64)), rolled(ids, w)) for w in (2, 3, 8))
    words = lambda a, n: " ".join(f"w{a}x{k}" for k in range(n))
    bench = spark.createDataFrame([(k, words(k, 60)) for k in range(400)], "item_id long, text string")
    docs = spark.createDataFrame([(k, words(f"d{k}", 400)) for k in range(50)] + [(99, words(7, 60))], "doc_id long, text string")
    hits = decontaminate.with_hits(docs, decontaminate.item_windows(bench)).where("size(hits) > 0").select("doc_id").collect()
    assert 99 in {r.doc_id for r in hits} and len(hits) < 6  # by one place alone about 43 of 51 have a hit


def test_toxicity_labels_meet_texts_one_way(spark, monkeypatch):
    """Small tables go the way of large ones, so that what is measured on them grows in proportion."""
    plans, kept = [], toxicity.written
    monkeypatch.setattr(toxicity, "written", lambda df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or kept(df))
    docs = spark.createDataFrame([(k, f"plain words {k}") for k in range(30)], "doc_id long, text string")
    toxicity.fit(docs, spark.createDataFrame([(k, k % 2) for k in range(30)], "doc_id long, toxic int"))
    assert "SortMergeJoin" in plans[0] and "BroadcastHashJoin" not in plans[0]
