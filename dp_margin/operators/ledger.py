"""Budget accounting and the registry of releases."""

from __future__ import annotations

import time
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def balance(ledger: DataFrame, cap: float) -> DataFrame:
    """ledger (dataset, stratum, release_id, beta, ts) with ``granted`` and ``spent``, what the stratum's granted requests add up to so far.

    Requests are taken in order of ts; one is granted if it fits in what is left of the cap, and a refused one spends nothing, as in ``spend``.
    """
    schema = ledger.withColumn("spent", F.lit(0.0)).withColumn("granted", F.lit(True)).schema

    def replay(t: pa.Table) -> pa.Table:
        t = t.sort_by([("ts", "ascending"), ("release_id", "ascending")])
        spent, out, granted = 0.0, [], []
        for b in t["beta"].to_pylist():
            granted.append(spent + b <= cap)
            spent += b if granted[-1] else 0.0
            out.append(spent)
        return t.append_column("spent", pa.array(out, pa.float64())).append_column("granted", pa.array(granted, pa.bool_()))

    return ledger.groupBy("dataset", "stratum").applyInArrow(replay, schema)


def sequential(ledger: DataFrame) -> DataFrame:
    """(dataset, beta): releases on the same rows add up."""
    return ledger.groupBy("dataset").agg(F.sum("beta").alias("beta"))


def parallel(ledger: DataFrame, movable: bool = False) -> DataFrame:
    """(dataset, beta): releases on disjoint public strata cost their largest; twice that if a replaced row can change its stratum."""
    each = ledger.groupBy("dataset", "stratum").agg(F.sum("beta").alias("beta"))
    return each.groupBy("dataset").agg((F.max("beta") * (2.0 if movable else 1.0)).alias("beta"))


def group_privacy(beta, k):
    """k rows of one person: k times the level."""
    return beta * k


@contextmanager
def _locked(spark: SparkSession, path: str, patience: float):
    """Holds the ledger's lock file, which the file system creates for one writer only."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path, "_lock")
    fs = at.getFileSystem(spark._jsc.hadoopConfiguration())
    fs.mkdirs(at.getParent())
    end = time.monotonic() + patience
    while not fs.createNewFile(at):
        if time.monotonic() > end:
            raise TimeoutError(f"{at.toString()} is held by another writer")
        time.sleep(0.05)
    try:
        yield
    finally:
        fs.delete(at, False)


def spend(spark: SparkSession, path: str, dataset: str, release_id: str, beta: float, cap: float, stratum: str = "", patience: float = 60.0) -> None:
    """Appends a debit before the release is computed; refuses beyond the cap. Writers take turns by a lock file beside the ledger."""
    schema = "dataset string, stratum string, release_id string, beta double, ts timestamp"
    with _locked(spark, path, patience):
        spent = spark.read.schema(schema).parquet(path).where((F.col("dataset") == dataset) & (F.col("stratum") == stratum)).agg(F.sum("beta")).first()[0] or 0.0
        if spent + beta > cap:
            raise PermissionError(f"{dataset}: {spent + beta:g} would pass the cap of {cap:g}")
        spark.createDataFrame([(dataset, stratum, release_id, float(beta))], "dataset string, stratum string, release_id string, beta double").withColumn("ts", F.current_timestamp()).write.mode("append").parquet(path)


def register(release: DataFrame, path: str, dataset: str) -> None:
    release.withColumn("dataset", F.lit(dataset)).write.mode("append").partitionBy("dataset").parquet(path)


def export_json(release: DataFrame) -> DataFrame:
    return release.select(F.to_json(F.struct(*release.columns)).alias("json"))
