"""Personal data: patterns, and terms that reveal them by what the corpus says.

Spans of four kinds (email, ip, card, phone) are found by pattern. Each of them is a protected entity; its value is what
occurs again. Any other word of a document with an entity may give it away: for a term t and an entity e,
PMI(t; e) = log2(p(t, e) / (p(t) p(e))) is the information that t discloses about e, and IC(e) = -log2 p(e) is all there is to disclose,
with p as shares of whole documents over the whole corpus. A term with PMI >= ``DISCLOSED`` * IC for an entity of a document
is generalised at all its places in that document: to its class (name, number, code, word). Rare entities go by the same
threshold: an entity of one document is disclosed by the terms of that document that hardly any other one holds.

With N documents, n(t), n(e) and n(t, e) of them holding the term, the entity and both, the condition is
n(t, e) / n(t) >= (n(e) / N) ** (1 - DISCLOSED). As n(t, e) <= n(e), terms over N ** (1 - DISCLOSED) * n(e) ** DISCLOSED documents are out before pairs
are made; and an entity of one document needs no pairs, as n(t, e) is 1 for each of its document's terms. Terms are counted in
partial sums, so hot ones do not gather in one task. Only texts with entities are moved between tasks.

Defined results: null and empty texts have no spans; repeated rows have the same spans; a row's spans belong to its
text, even if another row has the same id; ``sanitise`` keeps extra columns. Offsets are in code points.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator

import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dropped, freed, written

KINDS = ("email", "ip", "card", "phone")
DISCLOSED = 0.8
HELD_TERMS = 300_000

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_domain = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++").match
_ip = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++").finditer
_card = re.compile(r"[0-9](?:[\x20-]?[0-9])+").finditer
_phone = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]").finditer
_not_digit = re.compile(r"[^0-9]+")
_terms = re.compile(r"\w{3,}")


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Every address around an @, each @ looked at once; runs of local characters end at the last match."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        match = _domain(text, at + 1) if start < at else None
        if match:
            yield start, match.end()
            done = match.end()
            at = text.find("@", done)
        else:
            done = at + 1
            at = text.find("@", done)


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        v = ord(d) - 48
        if k & 1:
            v = v * 2 - 9 * (v > 4)
        total += v
    return total % 10 == 0


def base_spans(text: str | None) -> list[tuple[int, int, int]]:
    """(kind, start, end) by kind, then start; kinds are places in ``KINDS``."""
    text = text or ""
    out = [(0, *s) for s in emails(text)] if "@" in text else []
    for m in _ip(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):
            out.append((1, *m.span()))
    for m in _card(text):
        if m.end() - m.start() >= 16 and 16 <= len(digits := _not_digit.sub("", m[0])) <= 19 and luhn(digits):
            out.append((2, *m.span()))
    if "+" in text:
        for m in _phone(text):
            if 8 <= len(_not_digit.sub("", m[0])) <= 15:
                out.append((3, *m.span()))
    return out


def entity(kind: int, value: str) -> int:
    """A signed 64-bit name of a protected value."""
    return xxhash.xxh64_intdigest(f"{kind}:{value.lower() if kind < 2 else _not_digit.sub('', value)}") - (1 << 63)


def term(word: str) -> int:
    return xxhash.xxh64_intdigest(word.lower()) - (1 << 63)


def free_terms(text: str, spans: list[tuple[int, int, int]]) -> Iterator[tuple[int, int, int]]:
    """(term, start, end) of the words that touch no span."""
    ends = sorted((a, b) for _, a, b in spans)
    k, reach = 0, 0  # spans that start before a word's end, and how far they go
    for m in _terms.finditer(text):
        x, y = m.span()
        while k < len(ends) and ends[k][0] < y:
            reach = max(reach, ends[k][1])
            k += 1
        if reach <= x:
            yield term(m[0]), x, y


_SPANS = "array<struct<kind:int,start:int,end:int>>"


def with_spans(docs: DataFrame, text: str = "text", out: str = "spans") -> DataFrame:
    """docs and their base spans."""

    @F.pandas_udf(_SPANS)
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            yield pd.Series([[dict(zip(("kind", "start", "end"), s)) for s in base_spans(t)] for t in part])

    return docs.withColumn(out, of(docs[text]))


def holdings(texts: DataFrame) -> DataFrame:
    """row, n, entities, terms: the different ones of each text with spans; texts: row, n, text, spans."""

    @F.pandas_udf("entities array<long>, terms array<long>")
    def of(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        for values, spans in parts:
            rows = []
            for t, found in zip(values, spans):
                s = [(x["kind"], x["start"], x["end"]) for x in found]
                rows.append((sorted({entity(k, t[a:b]) for k, a, b in s}), sorted({w for w, _, _ in free_terms(t, s)})))
            yield pd.DataFrame(rows, columns=["entities", "terms"])

    return texts.select("row", "n", of("text", "spans").alias("h")).select("row", "n", "h.*")


def term_documents(docs: DataFrame, text: str = "text") -> DataFrame:
    """t, n: in how many documents each term occurs; partial counts by task."""

    def count(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: Counter[str] = Counter()

        def told() -> pd.DataFrame:
            out = pd.DataFrame({"t": [term(w) for w in seen], "n": list(seen.values())}, dtype="int64")
            seen.clear()
            return out

        for part in parts:
            for t in part["text"]:
                if t:
                    seen.update(set(_terms.findall(t.lower())))
            if len(seen) > HELD_TERMS:
                yield told()
        yield told()

    return docs.select(docs[text].alias("text")).mapInPandas(count, "t long, n long").groupBy("t").agg(F.sum("n").alias("n"))


def disclosing(texts: DataFrame, docs: DataFrame, text: str = "text", share: float = DISCLOSED) -> DataFrame:
    """row, terms: the terms of each text that disclose one of its entities. texts: row, n (how many rows of docs it stands for), text, spans."""
    held = written(holdings(texts))
    total = docs.select(F.count(F.lit(1)).alias("total"))  # one row
    entities = held.select("row", "n", F.explode("entities").alias("e"))
    n_e = entities.groupBy("e").agg(F.sum("n").alias("n_e"))
    entities = entities.drop("n").join(n_e, "e").crossJoin(F.broadcast(total)).where("n_e < total")
    bound = F.pow("total", F.lit(1 - share)) * F.pow("n_e", F.lit(share)) * (1 + 1e-9)
    entities = written(entities.withColumn("most", F.floor(bound)))
    reach = entities.groupBy("row").agg(F.max("most").alias("most"))
    terms = held.select("row", "n", F.explode("terms").alias("t")).join(reach, "row").join(term_documents(docs, text).withColumnRenamed("n", "n_t"), "t")
    terms = written(terms.where("n_t <= most").select("row", "n", "t", "n_t"))
    enough = F.col("n_et") / F.col("n_t") >= F.pow(F.col("n_e") / F.col("total"), F.lit(1 - share)) * (1 - 1e-9)
    # an entity of one text: its terms occur with it just as often as it does
    alone = entities.join(entities.groupBy("e").agg(F.count(F.lit(1)).alias("k")).where("k = 1").select("e"), "e", "left_semi")
    alone = terms.join(alone.select("row", "n_e", "total", "most"), "row").where("n_t <= most").withColumn("n_et", F.col("n_e")).where(enough).select("row", "t")
    several = entities.join(entities.groupBy("e").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("e"), "e", "left_semi")
    pairs = several.join(terms, "row").where("n_t <= most")
    told = pairs.groupBy("e", "t").agg(F.sum("n").alias("n_et"), F.first("n_t").alias("n_t"), F.first("n_e").alias("n_e"), F.first("total").alias("total")).where(enough).select("e", "t")
    return alone.union(pairs.join(told, ["e", "t"], "left_semi").select("row", "t")).groupBy("row").agg(F.collect_set("t").alias("terms"))


def places(texts: DataFrame) -> DataFrame:
    """texts with the places of their terms; texts: text, spans, terms (null: none)."""

    @F.pandas_udf("array<struct<start:int,end:int>>")
    def of(parts: Iterator[tuple[pd.Series, ...]]) -> Iterator[pd.Series]:
        for values, spans, terms in parts:
            out = []
            for t, found, told in zip(values, spans, terms):
                told = set() if told is None else set(told)
                out.append([{"start": a, "end": b} for w, a, b in free_terms(t, [(x["kind"], x["start"], x["end"]) for x in found]) if w in told] if told else [])
            yield pd.Series(out)

    return texts.withColumn("terms", of("text", "spans", "terms"))


def found(docs: DataFrame, text: str = "text", whole: bool = True) -> tuple[DataFrame, DataFrame]:
    """(docs with spans, with a key of a text that has some; the texts that have some: row, n, text, spans, terms as places).

    Equal texts are one of the second, so that a large group of copies is looked at once. whole: texts without spans are kept in the first.
    """
    some = F.size("__spans") > 0
    every = with_spans(docs, text, "__spans").withColumn("__key", F.when(some, F.unhex(F.sha2(F.col(text).cast("binary"), 256))))
    every = written(every if whole else every.withColumn(text, F.when(some, F.col(text))))
    private = every.where(F.size("__spans") > 0)
    each = private.groupBy(F.col("__key").alias("key")).agg(F.count(F.lit(1)).alias("n"), F.first(text).alias("text"), F.first("__spans").alias("spans"))
    texts = written(each.withColumn("row", F.monotonically_increasing_id()))
    if not whole:  # the texts are in the second table now
        held = every
        every = written(every.drop(text))
        dropped(held)
    freed(docs.sparkSession)
    told = written(disclosing(texts, docs, text))
    freed(docs.sparkSession)
    return every, places(texts.join(told, "row", "left"))


def spans(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, spans (base), terms (spans of disclosing terms), one row for each row of docs."""
    slim = docs.select(docs[doc_id].alias("doc_id"), docs[text].alias("text"))
    every, texts = found(slim, whole=False)
    none = F.array().cast("array<struct<start:int,end:int>>")
    clean = every.where(F.size("__spans") == 0).select("doc_id", F.col("__spans").alias("spans"), none.alias("terms"))
    private = every.where(F.size("__spans") > 0).select("doc_id", F.col("__key").alias("key")).join(texts.select("key", "spans", "terms"), "key")
    return clean.unionByName(private.select("doc_id", "spans", "terms"))


def digests(found: DataFrame) -> DataFrame:
    """What the query returns of ``spans``."""
    base = F.transform("spans", lambda x: F.concat_ws(":", F.element_at(F.array(*map(F.lit, KINDS)), x.kind + 1), x.start.cast("string"), x.end.cast("string")))
    extra = F.transform("terms", lambda x: F.concat_ws(":", F.lit("term"), x.start.cast("string"), x.end.cast("string")))
    def counted(k: int):
        return F.size(F.filter("spans", lambda x: x.kind == k)).cast("long")

    counts = [counted(k).alias(f"n_{name}") for k, name in enumerate(KINDS)]
    return found.select("doc_id", *counts, F.sha2(F.array_join(base, ",").cast("binary"), 256).alias("base_sha256"), F.array_join(F.concat(base, extra), ",").alias("spans"))


def general(word: str) -> str:
    """The class that a word is generalised to."""
    if word.isdigit():
        return "[NUMBER]"
    if any(c.isdigit() or c == "_" for c in word):
        return "[CODE]"
    return "[NAME]" if word[0].isupper() else "[WORD]"


def redact(text: str | None, spans, terms) -> str | None:
    """The text with each span replaced by its kind and each disclosing term by its class; overlaps go to the earlier, longer one."""
    if text is None:
        return None
    parts = sorted([(s["start"], -s["end"], f"[{KINDS[s['kind']].upper()}]") for s in spans] + [(s["start"], -s["end"], general(text[s["start"] : s["end"]])) for s in terms])
    out, done = [], 0
    for start, end, name in parts:
        if start < done:
            done = max(done, -end)
            continue
        out += [text[done:start], name]
        done = -end
    return "".join([*out, text[done:]])


def sanitise(docs: DataFrame, text: str = "text") -> DataFrame:
    """The documents with personal data and what discloses it replaced in the text; other columns stay.

    Documents without spans pass as they were read; each different text with some is rewritten once.
    """
    every, texts = found(docs, text)

    @F.pandas_udf("string")
    def of(parts: Iterator[tuple[pd.Series, ...]]) -> Iterator[pd.Series]:
        for values, s, t in parts:
            yield pd.Series([redact(x, a, b) for x, a, b in zip(values, s, t)], dtype=object)

    clean = every.where(F.size("__spans") == 0).select(*docs.columns)
    fresh = texts.select(F.col("key").alias("__same"), of("text", "spans", "terms").alias("__text"))
    private = every.where(F.size("__spans") > 0).drop(text).join(fresh, F.col("__key") == F.col("__same"))
    return clean.unionByName(private.withColumnRenamed("__text", text).select(*docs.columns))


def digest_of(spans: list[tuple[int, int, int]]) -> str:
    """The digest of base spans, for tests."""
    return hashlib.sha256(",".join(f"{KINDS[k]}:{a}:{b}" for k, a, b in spans).encode()).hexdigest()
