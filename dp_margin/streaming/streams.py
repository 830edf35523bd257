"""Streams: scoring, windows, contribution caps, late rows, and a release for each closed window."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupStateTimeout

from ..functions import vectors as v
from ..functions.rng import SecureRng
from ..operators.ledger import spend
from ..sources.tables import load

WATERMARK = "1 day"


def stream_events(spark: SparkSession, sf_dir: str, source: str | None = None) -> DataFrame:
    """events as a stream with a UTC timestamp; the schema is the batch table's, never inferred by the stream."""
    schema = load(spark, sf_dir, "events").schema
    return prepared(spark.readStream.schema(schema).parquet(source or f"{sf_dir}/events.parque[t]"))


def prepared(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("x", F.array(v.clip(F.col("value") / 100)))


def score_stream(events: DataFrame, w: list[float]) -> DataFrame:
    """Scores by a released w: stateless, and free of budget."""
    return events.withColumn("score", v.dot_literal(F.col("x"), w))


def windows(events: DataFrame, kind: str, size: str, slide: str | None = None, gap: str | None = None, watermark: str | None = WATERMARK) -> DataFrame:
    """(start, [user_id,] n, positives) of tumbling, sliding or per-user session windows."""
    e = events.withWatermark("ts", watermark) if watermark else events
    if kind == "session":
        g = e.groupBy(F.session_window("ts", gap).alias("win"), "user_id")
    else:
        g = e.groupBy(F.window("ts", size, slide or size).alias("win"))
    done = g.agg(F.count("*").alias("n"), F.sum(F.when(F.col("score") >= 0, 1).otherwise(0)).alias("positives"))
    keys = ["user_id"] if kind == "session" else []
    return done.select(F.col("win.start").alias("start"), *keys, "n", "positives")


def cap_contributions(events: DataFrame, k: int) -> DataFrame:
    """At most the first k rows of each user, as they arrive; one counter of state a user."""

    def step(key, frames, state):
        used = state.get[0] if state.exists else 0
        for pdf in frames:
            take = pdf.head(max(0, k - used))
            used = min(k, used + len(pdf))
            if len(take):
                yield take
        state.update((used,))

    cols = events.select("event_id", "user_id", "value")
    return cols.groupBy("user_id").applyInPandasWithState(step, cols.schema, "used long", "append", GroupStateTimeout.NoTimeout)


def read_batches(spark: SparkSession, folder: str, schema: T.StructType) -> DataFrame:
    """What ``run_to_table`` or ``release_per_window`` wrote; no rows if no batch had any."""
    at = spark._jvm.org.apache.hadoop.fs.Path(folder)
    if not at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at):
        return spark.createDataFrame([], schema)
    return spark.read.schema(schema).parquet(f"{folder}/batch=*")


def run_to_table(stream: DataFrame, folder: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs over what there is, writes the result below folder and returns it.

    Every batch overwrites its own folder, so one that is run again after a failure counts once; in complete mode the last batch stands for all.
    """

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/batch={0 if mode == 'complete' else number}")

    writer = stream.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", checkpoint or f"{folder}-state").trigger(availableNow=True)
    writer.start().awaitTermination()
    return read_batches(stream.sparkSession, folder, stream.schema)


#: A window's release: its start in epoch seconds, the noisy weights, the noisy number of rows and the level.
RELEASED = T.StructType([T.StructField("start", T.LongType()), T.StructField("w", T.ArrayType(T.DoubleType())), T.StructField("n", T.DoubleType()), T.StructField("beta", T.DoubleType())])


def release_per_window(events: DataFrame, size: str, features: int, C: float, beta: float, folder: str, ledger: str, cap: float, checkpoint: str, dataset: str = "events", rng: Callable | None = None):
    """One private release for every closed window, in the regime where the minimiser is a plain sum (C kappa² <= 1).

    A replaced row may move to another window, so a window's number of rows is private: half of beta buys noise on it, half noise on the sums of y x
    (features in [0, 1], so these change by at most ``features`` in L1), and the weights are C times their quotient. Windows are disjoint; as rows can move between
    them, a person's loss over all is 2 beta (``ledger.parallel`` with movable). A window's debit comes before its noise; a window that the cap refuses is not
    released. State is a count and sums, never rows. A closed window is not opened again: later rows are dropped.
    """
    y = F.when(F.col("event_type") == "purchase", 1.0).otherwise(-1.0)
    sums = [F.sum(y * F.get("x", F.lit(i))).alias(f"s{i}") for i in range(features)]
    closed = events.withWatermark("ts", WATERMARK).groupBy(F.window("ts", size).alias("win")).agg(F.count("*").alias("n"), *sums)

    def each(batch: DataFrame, number: int) -> None:
        spark, out = batch.sparkSession, []
        for r in batch.select(F.unix_timestamp("win.start").alias("start"), "n", *[f"s{i}" for i in range(features)]).orderBy("start").collect():  # a row a window
            try:
                spend(spark, ledger, dataset, f"{dataset}-{r.start}", beta, cap, str(r.start))
            except PermissionError:
                continue
            noise = rng(r.start) if rng else SecureRng()
            n = r.n + float(noise.laplace(1, 2 / beta)[0])
            s = [r[f"s{i}"] + float(e) for i, e in enumerate(noise.laplace(features, 2 * features / beta))]
            out.append((int(r.start), [C * v_ / max(n, 1.0) for v_ in s], n, float(beta)))
        if out:
            spark.createDataFrame(out, RELEASED).write.mode("overwrite").parquet(f"{folder}/batch={number}")

    return closed.writeStream.outputMode("append").foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def late_rows(events: DataFrame) -> DataFrame:
    """Batch twin of the watermark: rows more than WATERMARK behind the largest timestamp seen before them, in order of event_id."""
    from pyspark.sql.window import Window

    seen = F.max("ts").over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1))
    return events.select("event_id", (F.col("ts") < seen - F.expr(f"INTERVAL {WATERMARK}")).alias("late"))

