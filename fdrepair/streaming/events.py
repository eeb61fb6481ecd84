"""Streams: pattern counts kept up to date, repair by given tables, windows of violations, late and repeated rows, and first-writer tables."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

from ..sources.formats import folder


def source(spark: SparkSession, sf_dir: str, name: str = "events", files_per_batch: int = 1) -> DataFrame:
    """A table's files as a stream; times become timestamps that watermarks accept."""
    path = f"{sf_dir}/{name}.parquet"
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path + ("" if _is_folder(spark, path) else "*"))
    for field in schema.fields:
        if field.dataType.typeName() == "timestamp_ntz":
            stream = stream.withColumn(field.name, F.col(field.name).cast("timestamp"))
    return stream


def _is_folder(spark: SparkSession, path: str) -> bool:
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def finished(stream: DataFrame, mode: str = "append", name: str = "stream") -> DataFrame:
    """What a stream has written once all that is there now is processed; a restart would go on from its checkpoint.

    Complete and update results go through foreachBatch: the last batch of a complete result, or the last row of each key.
    """
    spark = stream.sparkSession
    place = folder(spark, name)
    out = f"{place}/out"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("checkpointLocation", f"{place}/checkpoint").option("path", out).outputMode("append").trigger(availableNow=True).start()
    else:

        def keep(batch: DataFrame, number: int) -> None:
            batch.withColumn("__batch", F.lit(number).cast("long")).write.mode("append").parquet(out)

        query = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{place}/checkpoint").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    schema = StructType(list(stream.schema.fields)) if mode == "append" else StructType(list(stream.schema.fields)).add("__batch", "long")
    rows = spark.read.schema(schema).parquet(out)
    if mode == "complete":
        last = rows.agg(F.max("__batch").alias("m"))
        rows = rows.crossJoin(F.broadcast(last)).where("__batch = m").drop("m", "__batch")
    return rows


def pattern_counts(stream: DataFrame, lhs: str, rhs: str) -> DataFrame:
    """Counts of patterns so far; counts add up, so nothing is read twice."""
    return stream.where(F.col(lhs).isNotNull() & F.col(rhs).isNotNull()).groupBy(lhs, rhs).agg(F.count(F.lit(1)).alias("cnt"))


def merged_counts(stream: DataFrame, lhs: str, rhs: str, name: str = "counts") -> DataFrame:
    """The same by merging each batch's counts into a table: batches are written side by side and summed when read."""
    place = folder(stream.sparkSession, name)

    def merge(batch: DataFrame, number: int) -> None:
        batch.groupBy(lhs, rhs).agg(F.count(F.lit(1)).alias("cnt")).write.mode("overwrite").parquet(f"{place}/counts/batch={number}")

    stream.writeStream.foreachBatch(merge).option("checkpointLocation", f"{place}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    kinds = f"{lhs} {stream.schema[lhs].dataType.simpleString()}, {rhs} {stream.schema[rhs].dataType.simpleString()}, cnt long"
    return stream.sparkSession.read.schema(kinds).parquet(f"{place}/counts/*").groupBy(lhs, rhs).agg(F.sum("cnt").alias("cnt"))


def repaired(stream: DataFrame, table: DataFrame, lhs: str, rhs: str) -> DataFrame:
    """Each row with the right side that a repair table gives (its own where the table has none)."""
    told = table.select(F.col(f"x_{lhs}").alias("__k"), F.col("y").alias("__y"))
    return stream.join(told, stream[lhs] == told["__k"], "left").withColumn(rhs, F.coalesce("__y", rhs)).drop("__k", "__y")


def first_writer(stream: DataFrame, lhs: str, rhs: str, tid: str) -> DataFrame:
    """lhs, rhs, rows, clashes: a repair table kept by state; the right side of the least id so far, and how many rows of each batch disagree with it, added up."""

    def update(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        tid, rhs, n, clashes = state.get if state.exists else (1 << 62, None, 0, 0)
        values: dict = {}
        for frame in frames:
            for t, v in zip(frame["tid"].tolist(), frame["rhs"]):
                if t < tid:
                    tid, rhs = t, v
                values[v] = values.get(v, 0) + 1
                n += 1
        clashes += sum(k for v, k in values.items() if v != rhs)
        state.update((tid, rhs, n, clashes))
        yield pd.DataFrame({"lhs": [key[0]], "rhs": [rhs], "rows": [n], "clashes": [clashes]})

    keyed = stream.select(F.col(lhs).cast("string").alias("lhs"), F.col(rhs).cast("string").alias("rhs"), F.col(tid).cast("long").alias("tid"))
    out, kept = "lhs string, rhs string, rows long, clashes long", "tid long, rhs string, rows long, clashes long"
    return keyed.groupBy("lhs").applyInPandasWithState(update, out, kept, "update", GroupStateTimeout.NoTimeout)
