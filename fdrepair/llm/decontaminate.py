"""Benchmark decontamination by template canonicalisation.

Texts are cut in tokens; numbers, names (capitalised words inside a sentence) and units after a
number become typed placeholders, everything else is put in lower case without punctuation. Runs of
``WINDOW`` template tokens of the documents are hash-joined with those of the benchmark; in the matched runs of a document and an item on the same
diagonal the values behind the placeholders must be consistent: one value of the item always stands for one value
of the document and the other way round. So a question whose numbers, names or units were swapped is found as well as a verbatim passage.

Documents are read once: a filter of twice ``SLOTS`` marks, of that size whatever the benchmark's, says by two places of a hash which windows may match, and only those go on to the join with the
benchmark's windows. A run's place in the item fixes its place in the document on a diagonal, so what is checked together
is bounded by the item's length. Spark decides by size how the join is made; nothing of the benchmark but the marks is on the driver.

An item shorter than the window is matched as one run of its whole length. Runs with few literals or of a short item say little by their template, so they
count only if their values are verbatim, or (items of ``SHORTEST`` tokens or more with a literal) if the whole item is there with consistent values.

Defined results: null or empty texts, and items that are null, empty or without an id, match nothing; repeated rows give one row in ``leaks`` and all go or stay in ``clean``;
equal items are reported each; extra columns are kept by ``clean``.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import rolled, rolled_all, written

WINDOW = 8
SHORTEST = 6
LITERALS = 5  # windows with fewer tokens that are no placeholders need the exact check
SLOT_BITS = 22
SLOTS = 1 << SLOT_BITS
HELD_TOKENS = 400_000
# Units that follow a number.
UNITS = frozenset("mm cm m km in ft yd mi mg g kg lb oz ml l s sec min h hr hours hour minutes seconds days day weeks week months years usd eur dollars cents euros percent mph kmh".split())
_token = re.compile(r"[^\W_]+(?:['’.,][^\W_]+)*|%|[$€£]|[.!?\n]").findall
NUMBER, NAME, UNIT = "\x00n", "\x00p", "\x00u"


def template(text: str | None) -> tuple[list[str], list[str]]:
    """Template tokens of a text and the value that each stands for."""
    kinds, values, fresh, after_number = [], [], True, False
    for t in _token(text or ""):
        if t in ".!?\n":
            fresh, after_number = True, False
            continue
        low = t.lower()
        if t[0].isdigit():
            kind = NUMBER
        elif after_number and (low in UNITS or t in "%"):
            kind = UNIT
        elif t in "$€£%":
            kind = UNIT
        elif t[0].isupper() and not fresh and t[1:].islower():
            kind = NAME
        else:
            kind = low
        kinds.append(kind)
        values.append(low)
        after_number, fresh = kind == NUMBER, False
    return kinds, values


END, DIGIT, CAPITAL, MEASURE, SIGN = 1, 2, 4, 8, 16
FLAGS = np.uint64(31)


class Codes(dict):
    """Of each token, what ``template`` looks at (low bits) and a hash of its lower-case form; remembered up to a bound."""

    def __missing__(self, t: str) -> int:
        low = t.lower()
        flags = END * (t in ".!?\n") | DIGIT * t[0].isdigit() | CAPITAL * (t[0].isupper() and t[1:].islower()) | MEASURE * (low in UNITS) | SIGN * (t in "$€£%")
        value = xxhash.xxh64_intdigest(low) & ~31 | flags
        if len(self) >= HELD_TOKENS:
            self.clear()
        self[t] = value
        return value

    def template(self, text: str | None) -> np.ndarray:
        """A hash of each template token, as ``template`` gives them, by arrays."""
        tokens = _token(text or "")
        codes = np.fromiter(map(self.__getitem__, tokens), np.uint64, len(tokens))
        flags = (codes & FLAGS).astype(np.uint8)
        before = np.concatenate(([END], flags[:-1])).astype(np.uint8) if len(flags) else flags
        number = flags & DIGIT > 0
        unit = ~number & ((flags & MEASURE > 0) & (before & DIGIT > 0) | (flags & SIGN > 0))
        name = ~number & ~unit & (flags & CAPITAL > 0) & (before & END == 0)
        kinds = np.where(number, np.uint64(1), np.where(unit, np.uint64(2), np.where(name, np.uint64(3), codes & ~FLAGS)))
        return kinds[flags & END == 0]


_WINDOWS = "item_id long, n int, q int, width int, strong boolean, h long, kinds array<string>, values array<string>"


def _key(run: np.ndarray, width: int) -> np.ndarray:
    """The join key of runs: their hash and width."""
    return (run ^ np.uint64(width)).view(np.int64)


def item_windows(benchmark: DataFrame, item_id: str = "item_id", text: str = "text", window: int = WINDOW) -> DataFrame:
    """Every window of every item, with its template and values; n is the item's number of windows."""

    def of(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codes = Codes()
        for part in parts:
            rows = []
            for i, t in zip(part["item_id"], part["text"]):
                kinds, values = template(t)
                width = min(window, len(kinds))
                if not width:
                    continue
                keys = _key(rolled(codes.template(t), width), width).tolist()
                for q, h in enumerate(keys):
                    strong = width >= min(window, SHORTEST) and sum(x[0] != "\x00" for x in kinds[q : q + width]) >= min(LITERALS, width)
                    rows.append((i, len(keys), q, width, strong, h, kinds[q : q + width], values[q : q + width]))
            yield pd.DataFrame(rows, columns=["item_id", "n", "q", "width", "strong", "h", "kinds", "values"])

    return benchmark.select(benchmark[item_id].alias("item_id"), benchmark[text].alias("text")).where("item_id is not null and text is not null").mapInPandas(of, _WINDOWS)


_HITS = "array<struct<p:int,width:int,h:long,kinds:array<string>,values:array<string>>>"


def with_hits(docs: DataFrame, windows: DataFrame, text: str = "text", out: str = "hits") -> DataFrame:
    """docs with their windows that may occur in the benchmark."""
    slot = F.expr(f"shiftrightunsigned(h, {64 - SLOT_BITS})")
    other = F.expr(f"{SLOTS} + (h & {SLOTS - 1})")
    marks = windows.select("width", F.explode(F.array(slot, other)).alias("slot")).distinct().toArrow()  # at most twice SLOTS for each width, whatever the benchmark's size
    widths = sorted(set(marks["width"].to_pylist()))
    slots = np.unique(marks["slot"].to_numpy())

    @F.pandas_udf(_HITS)
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        codes, marked = Codes(), np.zeros(2 * SLOTS, bool)
        marked[slots] = True
        for part in parts:
            out = []
            for t in part:
                ids, found = codes.template(t), []
                for width, runs in rolled_all(ids, widths).items():
                    keys = _key(runs, width)
                    near = np.flatnonzero(marked[(keys.view(np.uint64) >> np.uint64(64 - SLOT_BITS)).astype(np.int64)])
                    near = near[marked[SLOTS + (keys[near] & (SLOTS - 1))]]
                    found += [(width, p, h) for p, h in zip(near.tolist(), keys[near].tolist())]
                if found:
                    kinds, values = template(t)
                    found = [{"p": p, "width": w, "h": h, "kinds": kinds[p : p + w], "values": values[p : p + w]} for w, p, h in found]
                out.append(found)
            yield pd.Series(out)

    return docs.withColumn(out, of(docs[text]))


def consistent(n: int, runs: list[tuple]) -> tuple[int, int]:
    """(runs that count, runs that are verbatim) of an item of n windows on one diagonal; runs: (q, strong, kinds, item's values, document's values).

    A run's values are bound only if all of them are consistent with those bound before.
    """
    forth: dict[tuple[str, str], str] = {}
    back: dict[tuple[str, str], str] = {}

    def binds(slots: set[tuple[str, str, str]]) -> bool:
        new, old = dict(forth), dict(back)
        if not all(new.setdefault((s, a), b) == b and old.setdefault((s, b), a) == a for s, a, b in slots):
            return False
        forth.update(new)
        back.update(old)
        return True

    def slots(run) -> set[tuple[str, str, str]]:
        return {(s, a, b) for s, a, b in zip(run[2], run[3], run[4]) if s[0] == "\x00"}

    runs = sorted(runs)
    good = same = 0
    whole = None
    for run in runs:
        q, strong, kinds, theirs, ours = run
        if strong:
            if binds(slots(run)):
                good, same = good + 1, same + (theirs == ours)
        elif theirs == ours:
            good, same = good + 1, same + 1
        else:
            if whole is None:
                every = set().union(*map(slots, runs))
                whole = len(runs) == n and n + len(kinds) - 1 >= SHORTEST and any(x[0] != "\x00" for r in runs for x in r[2])
                whole = whole and len({(s, a) for s, a, _ in every}) == len(every) == len({(s, b) for s, _, b in every})
            good += whole
    return good, same


def matched(hits: DataFrame, windows: DataFrame) -> DataFrame:
    """key, item_id, runs, item_runs, verbatim of the items that texts leak; hits: key (of a text) and the fields of a hit."""
    theirs = windows.select("item_id", "n", "q", "width", "strong", "h", F.col("kinds").alias("k"), F.col("values").alias("v"))
    met = hits.join(theirs, ["h", "width"]).where(F.col("kinds") == F.col("k"))
    run = F.struct("q", "strong", "kinds", "v", "values")
    lines = met.groupBy("key", "item_id", "n", (F.col("p") - F.col("q")).alias("shift")).agg(F.collect_set(run).alias("runs"))

    @F.pandas_udf("runs int, verbatim int")
    def check(n: pd.Series, runs: pd.Series) -> pd.DataFrame:
        rows = [consistent(k, [(x["q"], x["strong"], list(x["kinds"]), list(x["v"]), list(x["values"])) for x in r]) for k, r in zip(n, runs)]
        return pd.DataFrame(rows, columns=["runs", "verbatim"])

    told = lines.select("key", "item_id", "n", check("n", "runs").alias("c")).where("c.runs > 0")
    return told.groupBy("key", "item_id").agg(F.sum("c.runs").cast("int").alias("runs"), F.first("n").alias("item_runs"), F.sum("c.verbatim").cast("int").alias("verbatim"))


def leaks(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, item_id, runs, item_runs, verbatim: one row for each document and item that it leaks."""
    windows = item_windows(benchmark)
    slim = docs.select(docs[doc_id].alias("doc_id"), docs[text].alias("text"))
    some = written(with_hits(slim, windows).where("size(hits) > 0").select(F.struct("doc_id", F.md5(F.col("text").cast("binary")).alias("t")).alias("key"), "hits"))
    found = matched(some.select("key", F.inline("hits")), windows)
    return found.select("key.doc_id", "item_id", "runs", "item_runs", "verbatim").distinct()


def clean(docs: DataFrame, benchmark: DataFrame, text: str = "text") -> DataFrame:
    """The documents that leak no item, with their columns. Those without a hit pass as they were read; only the others are moved."""
    windows = item_windows(benchmark)
    every = written(with_hits(docs, windows, text, "__hits").withColumn("__key", F.when(F.size("__hits") > 0, F.unhex(F.sha2(F.col(text).cast("binary"), 256)))))
    some = every.where(F.size("__hits") > 0)
    hits = some.dropDuplicates(["__key"]).select(F.col("__key").alias("key"), F.inline("__hits"))
    found = matched(hits, windows).select(F.col("key").alias("__leaky")).distinct()
    passed = every.where(F.size("__hits") == 0).select(*docs.columns)
    return passed.unionByName(some.join(found, F.col("__key") == F.col("__leaky"), "left_anti").select(*docs.columns))
