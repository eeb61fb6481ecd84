"""Rows violate an FD if their patterns are similar but not equal; the less frequent one is rewritten as the more frequent one.

Works on distinct patterns. Where the longer text allows ``FEW`` edits or fewer, two similar texts become equal after each has lost
at most so many letters, so what is left of them is joined (deletion neighbourhoods): keys of few digits have hardly any rare pair of letters, but few neighbours.
Longer texts whose edit distance is at most a share of the longer one's length have pairs of letters in
common, of each all but a few; so with pairs of letters put in order of their frequency, the rarest few of either text meet
(prefix filter). Candidates are joined on those, no pair is lost either way, and the distance is computed for candidates of near length alone.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import chase
from ..operators.chase import RepairResult
from ..operators.patterns import project, simple, x
from ..operators.store import written
from ..plans import FD, build_plan

GRAM = 2
FEW = 2  # edits up to which letters are deleted; the number of what may be left grows with the length to this power


def rare_grams(p: DataFrame, tau: float) -> DataFrame:
    """text, gram of the rarest pairs of letters of each text, as many as a similar text needs to meet one.

    p: text (different ones). A pair of letters and the number of its occurrence in the text are one gram. A partner's length is at most the
    text's own over tau, which bounds the distance; each edit changes ``GRAM`` grams at most.
    """
    far = F.floor(F.length("text") * (1 / tau - 1) + 1e-9)
    starts = F.sequence(F.lit(1), F.greatest(F.length("text") - GRAM + 1, F.lit(1)))
    each = p.select("text", (far * GRAM + 1).alias("wanted"), F.explode(F.transform(starts, lambda k: F.substr(F.col("text"), k, F.lit(GRAM)))).alias("letters"))
    nth = F.row_number().over(Window.partitionBy("text", "letters").orderBy(F.lit(1)))  # any order: occurrences are alike
    grams = each.withColumn("gram", F.concat_ws("\x1f", "letters", nth.cast("string")))
    often = grams.groupBy(F.col("gram").alias("g")).agg(F.count(F.lit(1)).alias("often"))
    rank = F.row_number().over(Window.partitionBy("text").orderBy("often", "gram"))
    return grams.join(often, F.col("gram") == F.col("g")).withColumn("rank", rank).where("rank <= wanted").select("text", "gram")


def left_overs(p: DataFrame, share: int) -> DataFrame:
    """text, rest: each text with what is left of it after the loss of as many letters as a text of its length may differ by, or fewer.

    p: text (different ones), share: edits allowed to a letter, in thousandths. The shorter of two similar texts loses no more than its own length allows, as the difference of lengths counts as edits.
    """

    def without_one(t):
        return F.transform(F.sequence(F.lit(1), F.length(t)), lambda k: F.concat(F.substr(t, F.lit(1), k - 1), F.substr(t, k + 1, F.length(t))))

    nothing = F.array().cast("array<string>")
    rest, last = F.array("text"), F.array("text")
    for n in range(1, FEW + 1):
        last = F.when(F.floor(F.length("text") * share / 1000) >= n, F.array_distinct(F.flatten(F.transform(last, without_one)))).otherwise(nothing)
        rest = F.concat(rest, last)
    return p.select("text", F.explode(F.array_distinct(rest)).alias("rest"))


def similar_texts(p: DataFrame, tau: float = 0.8) -> DataFrame:
    """text, text2: pairs of different texts with 1 - distance / longer length >= tau, both ways; p: text (different ones)."""
    share = int(round((1 - tau) * 1000))
    short = (1000 * (FEW + 1) - 1) // share if share else 1 << 30  # the greatest length that allows FEW edits at most
    longest = F.greatest(F.length("text"), F.length("text2"))
    close = F.abs(F.length("text") - F.length("text2")) * 1000 <= longest * share
    alike = F.levenshtein("text", "text2") * 1000 <= longest * share
    rests = left_overs(p.where(F.length("text") <= short), share)
    near = rests.join(rests.select(F.col("text").alias("text2"), "rest"), "rest").where((F.col("text") < F.col("text2")) & close & alike).select("text", "text2").distinct()
    grams = written(rare_grams(p.where(F.length("text") * 1000 >= (short + 1) * (1000 - share)), tau))
    other = grams.select(F.col("text").alias("text2"), "gram")
    met = grams.join(other, "gram").where((F.col("text") < F.col("text2")) & (longest > short) & close).select("text", "text2").distinct()
    near = written(near.unionByName(met.where(alike)))
    return near.union(near.select("text2", "text"))


def similar_pairs(t: DataFrame, f: FD, tau: float = 0.8) -> DataFrame:
    """lhs, rhs, cnt of a pattern and lhs2, rhs2, cnt2 of a more frequent similar one (ties: the smaller text)."""
    lhs = F.concat_ws("|", *[F.col(x(a)).cast("string") for a in f.lhs])
    p = written(t.select(lhs.alias("lhs"), F.col("y").cast("string").alias("rhs"), "cnt").withColumn("text", F.concat_ws("|", "lhs", "rhs")))
    q = p.select(*[F.col(c).alias(f"{c}2") for c in p.columns])
    order = (F.col("cnt2") > F.col("cnt")) | ((F.col("cnt2") == F.col("cnt")) & (F.col("text2") < F.col("text")))
    met = similar_texts(p.select("text").distinct(), tau).join(p, "text").join(q, "text2")
    return met.where(order).select("lhs", "rhs", "cnt", "lhs2", "rhs2", "cnt2")


def similarity(df: DataFrame, fds, tid: str, tau: float = 0.8, **options) -> RepairResult:
    """Each left side takes the right side of its most frequent pattern, or of the most frequent similar pattern if that is more frequent."""
    plan = build_plan(fds, df.schema, **options)
    projected = written(project(df, plan.attributes, tid))
    decisions = {}
    for f in plan.fds:
        t = written(simple(projected, f, plan.nulls))
        key = F.concat_ws("|", *[F.col(x(a)).cast("string") for a in f.lhs])
        better = similar_pairs(t, f, tau).groupBy(F.col("lhs").alias("k"), F.col("rhs").alias("r")).agg(F.min(F.struct((-F.col("cnt2")).alias("c"), "rhs2")).alias("b"))
        own = t.withColumn("k", key).withColumn("r", F.col("y").cast("string"))
        met = own.join(better, ["k", "r"], "left").withColumns({"to": F.coalesce(F.col("b.rhs2"), F.col("r")), "votes": F.coalesce(-F.col("b.c"), F.col("cnt"))})
        pick = met.groupBy(*map(x, f.lhs)).agg(F.min(F.struct((-F.col("votes")).alias("v"), (-F.col("cnt")).alias("c"), "to")).alias("b"), F.count(F.lit(1)).alias("rivals"))
        zero = F.lit(0).cast("long")
        decisions[f] = written(pick.select(*map(x, f.lhs), F.col("b.to").cast(df.schema[f.rhs].dataType).alias("y"), zero.alias("score_fp"), zero.alias("quality_fp"), (-F.col("b.v")).alias("cnt"), "rivals", F.lit("similar").alias("origin")))
    return chase.finish(df, plan, projected, None, decisions, tid)
