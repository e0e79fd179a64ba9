"""Fact files and result files: delimited text with a declared schema, Parquet, and keyed tables."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from ruleweave.lang.ast import Program

# Spark types of the surface language's column types.
SPARK_TYPES = {"number": T.LongType(), "unsigned": T.DecimalType(20, 0), "float": T.DoubleType(), "symbol": T.StringType(), "timestamp": T.TimestampType(), "date": T.DateType()}


def schema_of(program: Program, relation: str) -> T.StructType:
    """The declared schema; never inferred from data."""
    return T.StructType([T.StructField(c, SPARK_TYPES.get(t, T.LongType()), False) for c, t in program.schema[relation]])


def read_text(spark: SparkSession, program: Program, folder: str, separator: str = "\t", suffix: str = ".facts") -> dict[str, DataFrame]:
    """One delimited file for each declared input; a row that does not fit the schema fails the read."""
    return {p: spark.read.schema(schema_of(program, p)).option("mode", "FAILFAST").csv(f"{folder}/{p}{suffix}", sep=separator).dropna() for p in program.inputs}


def read_parquet(spark: SparkSession, program: Program, folder: str) -> dict[str, DataFrame]:
    """One Parquet table for each declared input, its columns picked and cast by name."""
    out = {}
    for p in program.inputs:
        df = spark.read.parquet(f"{folder}/{p}.parquet")
        out[p] = df.select([df[c].cast(SPARK_TYPES.get(t, T.LongType())).alias(c) for c, t in program.schema[p]]).dropna()
    return out


def write_outputs(relations: Mapping[str, DataFrame], outputs: list[str], folder: str, form: str = "parquet", separator: str = "\t") -> list[str]:
    """Writes output relations; gives their paths."""
    paths = []
    for p in outputs:
        path = f"{folder}/{p}.{form}"
        writer = relations[p].write.mode("overwrite")
        writer.parquet(path) if form == "parquet" else writer.csv(path, sep=separator)
        paths.append(path)
    return paths


def keyed_table(df: DataFrame, name: str, key: tuple[str, ...], buckets: int = 64) -> DataFrame:
    """A table bucketed and sorted by its key: joins on the key need no shuffle of this side."""
    df.write.mode("overwrite").format("parquet").bucketBy(buckets, *key).sortBy(*key).saveAsTable(name)
    return df.sparkSession.table(name)
