"""Reading the given tables and other formats, replaying tables as streams, saving sketches."""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tallymill.params import SketchParams


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str, schema: str | T.StructType | None = None, **options: str) -> DataFrame:
    """csv, json, orc, text or parquet; csv and json take an explicit schema."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError("give a schema")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def rows(spark: SparkSession, values: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(values, schema)


def replay(spark: SparkSession, sf_dir: str, name: str, schema: T.StructType | None = None, **options: str) -> DataFrame:
    """A table as a file stream; timestamps without zone are cast, as watermarks need."""
    schema = schema or load(spark, sf_dir, name).schema
    stream = spark.readStream.schema(schema).options(pathGlobFilter=f"{name}.parquet", **options).parquet(sf_dir)
    return zoned(stream)


def zoned(df: DataFrame) -> DataFrame:
    return df.select(*[F.col(f.name).cast("timestamp").alias(f.name) if f.dataType == T.TimestampNTZType() else F.col(f.name) for f in df.schema.fields])


def ticks(spark: SparkSession, per_second: int = 1000) -> DataFrame:
    """The rate source, for soak tests."""
    return spark.readStream.format("rate").option("rowsPerSecond", per_second).load()


def save_cells(cells: DataFrame, path: str, p: SketchParams, component: str = "k", block: int = 64) -> None:
    """Cells by block of components and hash row, sorted by column so that footers prune lookups; parameters beside them."""
    out = cells.withColumn("k_block", F.floor(F.col(component) / block).cast("int"))
    out.repartition("k_block", "i").sortWithinPartitions("col").write.mode("overwrite").partitionBy("k_block", "i").parquet(f"{path}/cells")
    cells.sparkSession.createDataFrame([(json.dumps(asdict(p)),)], "params string").coalesce(1).write.mode("overwrite").json(f"{path}/params")


def load_cells(spark: SparkSession, path: str) -> tuple[DataFrame, SketchParams]:
    p = SketchParams(**json.loads(spark.read.schema("params string").json(f"{path}/params").first()[0]))
    return spark.read.parquet(f"{path}/cells").drop("k_block"), p


def report(df: DataFrame, path: str, kind: str = "csv") -> None:
    """A small report as csv or json."""
    df.coalesce(1).write.mode("overwrite").options(**({"header": "true"} if kind == "csv" else {})).format(kind).save(path)
