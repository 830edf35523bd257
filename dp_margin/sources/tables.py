"""Sources and sinks: Parquet tables by name, other formats with fixed schemas, the registry of releases."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

EXAMPLE = T.StructType([T.StructField("row_id", T.LongType()), T.StructField("x", T.ArrayType(T.DoubleType())), T.StructField("y", T.DoubleType())])
NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_examples(spark: SparkSession, path: str, fmt: str, schema: T.StructType, **options) -> DataFrame:
    """Never infers a schema: bounds and types are an input of the privacy proof."""
    return spark.read.schema(schema).format(fmt).options(**options).load(path)


def check_examples(df: DataFrame) -> DataFrame:
    got = {f.name: f.dataType for f in df.schema}
    for f in EXAMPLE:
        if got.get(f.name) != f.dataType:
            raise TypeError(f"column {f.name} must be {f.dataType.simpleString()}")
    return df


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in NAMES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
