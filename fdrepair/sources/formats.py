"""Files of FDs as a source of Spark, and round trips through file formats."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader

from ..operators.store import shared_folder


class FDSource(DataSource):
    """Reads dependencies, one "a, b -> c" to a line, from the option ``rules`` (text, ; or line breaks between rules)."""

    @classmethod
    def name(cls) -> str:
        return "fd_rules"

    def schema(self) -> str:
        return "name string, lhs array<string>, rhs string"

    def reader(self, schema) -> DataSourceReader:
        return FDReader(self.options.get("rules", ""))


class FDReader(DataSourceReader):
    def __init__(self, rules: str) -> None:
        self.rules = rules

    def read(self, partition):
        from fdrepair.plans.fd import parse

        for f in parse(self.rules) if self.rules.strip() else []:
            yield f.name, list(f.lhs), f.rhs


def rules(spark: SparkSession, text: str) -> DataFrame:
    spark.dataSource.register(FDSource)
    return spark.read.format("fd_rules").option("rules", text).load()


def folder(spark: SparkSession, name: str) -> str:
    """A new place in the shared checkpoint folder."""
    return f"{shared_folder(spark)}/{name}-{spark.sparkContext.applicationId}-{os.urandom(6).hex()}"


def round_trip(df: DataFrame, kind: str, partition_by: str | None = None) -> DataFrame:
    """The rows after they were written as parquet, orc, csv or json, and read with the schema they had."""
    path = folder(df.sparkSession, kind)
    writer = df.write.format(kind)
    if kind == "csv":
        writer = writer.option("header", True)
    if partition_by:
        writer = writer.partitionBy(partition_by)
    writer.save(path)
    reader = df.sparkSession.read.format(kind).schema(df.schema)
    if kind == "csv":
        reader = reader.option("header", True)
    return reader.load(path).select(*df.columns)


def write_result(result, path: str) -> None:
    """Repair tables by FD, the change log and the expressions of a repair as parquet."""
    result.repair_tables().write.partitionBy("fd").mode("overwrite").parquet(f"{path}/rtables")
    result.delta.write.mode("overwrite").parquet(f"{path}/delta")
    result.expressions.write.mode("overwrite").parquet(f"{path}/expressions")
