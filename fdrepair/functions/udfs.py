"""Functions that Spark has no built-in form for: Arrow-batched, and registered for SQL."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType, StringType, StructField, StructType


def _distance(a: str, b: str) -> int:
    """Edit distance by rows."""
    if len(a) < len(b):
        a, b = b, a
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


@F.pandas_udf(DoubleType())
def edit_similarity(left: pd.Series, right: pd.Series) -> pd.Series:
    """1 - distance / longer length; 1 for two empty texts, null with a null."""
    return pd.Series([None if a is None or b is None else 1.0 if not a and not b else round(1 - _distance(a, b) / max(len(a), len(b)), 6) for a, b in zip(left, right)], dtype="float64")


@F.pandas_udf(LongType())
def group_g3(values: pd.Series) -> int:
    """Rows of a group outside its most frequent value. The group is held by one task: for groups of bounded size; ``detect.fd_error`` counts any."""
    seen = Counter(v for v in values if v is not None)
    return int(sum(seen.values()) - max(seen.values(), default=0))


def group_g3_frame(df: DataFrame, lhs: str, rhs: str) -> DataFrame:
    """lhs, g3 by applyInPandas, for comparison."""

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        counts = frame[rhs].value_counts()
        return pd.DataFrame({lhs: [frame[lhs].iloc[0]], "g3": [int(counts.sum() - counts.max())]})

    return df.select(lhs, rhs).groupBy(lhs).applyInPandas(one, f"{lhs} {df.schema[lhs].dataType.simpleString()}, g3 long")


@F.udtf(returnType=StructType([StructField("attribute", StringType()), StructField("value", StringType())]))
class Cells:
    """Unfolds names and values, given as two lists of texts, to rows."""

    def eval(self, names: list, values: list) -> Iterator[tuple[str, str]]:
        for n, v in zip(names or [], values or []):
            yield n, v


def register(spark: SparkSession) -> None:
    """edit_similarity, group_g3 and cells for SQL."""
    spark.udf.register("edit_similarity", edit_similarity)
    spark.udf.register("group_g3", group_g3)
    spark.udtf.register("cells", Cells)


def register_views(result) -> None:
    """patterns, rtab, delta and repaired as temporary views of a repair."""
    result.edges.long().createOrReplaceTempView("patterns")
    result.repair_tables().createOrReplaceTempView("rtab")
    result.delta.createOrReplaceTempView("delta")
    result.df.createOrReplaceTempView("repaired")
