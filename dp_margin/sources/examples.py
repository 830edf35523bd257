"""Workloads: (row_id, x, y) from the given tables, with the public bounds of each.

Features are clipped row by row to public bounds and labels never drop rows, so the number of rows is public and fixed.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors as v
from .tables import load

# Public bounds of lineitem's numeric columns.
QUANTITY, PRICE, DISCOUNT, TAX = 50.0, 105000.0, 0.1, 0.08
REVENUE = 50000.0


@dataclass(frozen=True)
class Spec:
    """Public facts of a workload's feature map: number of features, bound of the norm, bound of a feature, diameter."""

    features: int
    kappa: float
    phi: float = 1.0
    diam: float = 2.0


def pm(flag: Column) -> Column:
    """+1 or -1; null is -1."""
    return F.when(flag, 1.0).otherwise(-1.0)


def lineitem_x() -> Column:
    return F.array(v.clip(F.col("l_quantity") / QUANTITY), v.clip(F.col("l_extendedprice") / PRICE), v.clip(F.col("l_discount") / DISCOUNT), v.clip(F.col("l_tax") / TAX))


def lineitem(spark: SparkSession, sf_dir: str, label: str = "revenue", intercept: bool = False) -> DataFrame:
    t = load(spark, sf_dir, "lineitem")
    y = pm(F.col("l_extendedprice") * (1 - F.col("l_discount")) > REVENUE) if label == "revenue" else pm(F.col("l_linestatus") == "O")
    x = F.concat(lineitem_x(), F.array(F.lit(1.0))) if intercept else lineitem_x()
    return t.select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("long").alias("row_id"), x.alias("x"), y.alias("y"))


def embeddings(spark: SparkSession, sf_dir: str, label: str = "low") -> DataFrame:
    t = load(spark, sf_dir, "embeddings")
    y = pm(F.col("label") < 5) if label == "low" else pm(F.col("label") == int(label))
    x = v.clip_ball(F.col("embedding").cast("array<double>"))
    return t.select(F.col("vec_id").alias("row_id"), x.alias("x"), y.alias("y"))


def embeddings_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row_id, x, label): all classes, for one-vs-rest."""
    x = v.clip_ball(F.col("embedding").cast("array<double>"))
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), x.alias("x"), "label")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(spark, sf_dir, "events")
    return t.select(F.col("event_id").alias("row_id"), F.array(v.clip(F.col("value") / 100)).alias("x"), pm(F.col("event_type") == "purchase").alias("y"))


def events_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(spark, sf_dir, "events")
    turn = F.hour("ts") * (2 * math.pi / 24)
    k = F.get_json_object("props", "$.k").cast("double")
    return t.select(F.col("event_id").alias("row_id"), F.array(v.clip(F.col("value") / 100), v.clip(k / 100), F.cos(turn), F.sin(turn)).alias("x"), pm(F.col("event_type") == "purchase").alias("y"))


def text_features(text: Column) -> list[Column]:
    """Length, share of symbols, share of distinct words, share of digits: each in [0, 1]."""
    n = F.length(text)
    safe = F.greatest(n, F.lit(1))
    words = F.filter(F.split(text, "[ \n]"), lambda w: w != "")
    return [
        v.clip(n / 20000.0),
        v.clip(F.length(F.regexp_replace(text, r"[^!#$%&*+/<=>@^_|~-]", "")) / safe),
        v.clip(F.size(F.array_distinct(words)) / F.greatest(F.size(words), F.lit(1))),
        v.clip(F.length(F.regexp_replace(text, "[^0-9]", "")) / safe),
    ]


def documents(spark: SparkSession, sf_dir: str, label: str = "quality") -> DataFrame:
    """Labelled documents; a missing label is -1 at the zero point, so every document counts."""
    t = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id", "left")
    f = [*text_features(F.coalesce("text", F.lit(""))), F.lit(1.0)]
    x = F.when(F.col(label).isNull(), F.array(*[F.lit(0.0) for _ in f])).otherwise(F.array(*f))
    return t.select(F.col("doc_id").alias("row_id"), x.alias("x"), pm(F.col(label) == 1).alias("y"))


SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


def one_hot(c: Column, domain) -> list[Column]:
    """Indicators over a public domain; other values are all zero."""
    return [F.when(c == d, 1.0).otherwise(0.0) for d in domain]


def orders(spark: SparkSession, sf_dir: str, hint: str | None = None) -> DataFrame:
    """Orders with their customer, nation and region; keys are public, joins are outer, so no order is lost."""
    o, c, n = (load(spark, sf_dir, t) for t in ("orders", "customer", "nation"))
    c = c.hint(hint) if hint else c
    t = o.join(c, o.o_custkey == c.c_custkey, "left").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"), "left")
    x = F.array(v.clip(F.col("o_totalprice") / 500000), v.clip((F.col("c_acctbal") + 1000) / 11000), *one_hot(F.col("c_mktsegment"), SEGMENTS), *one_hot(F.col("n_regionkey"), range(5)))
    y = pm(F.substring("o_orderpriority", 1, 1).isin("1", "2"))
    return t.select(F.col("o_orderkey").alias("row_id"), x.alias("x"), y.alias("y"))


def part(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(spark, sf_dir, "part")
    y = pm(F.regexp_extract("p_brand", "([0-9]+)", 1).cast("int") <= 12)
    return t.select(F.col("p_partkey").alias("row_id"), F.array(v.clip(F.col("p_size") / 50), v.clip(F.col("p_retailprice") / 2000)).alias("x"), y.alias("y"))


def supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(spark, sf_dir, "supplier")
    return t.select(F.col("s_suppkey").alias("row_id"), F.array(*one_hot(F.col("s_nationkey"), range(25))).alias("x"), pm(F.col("s_acctbal") > 0).alias("y"))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns of conversations: length, place and an intercept; whether the user speaks."""
    t = load(spark, sf_dir, "conversations")
    x = F.array(v.clip(F.length(F.coalesce("text", F.lit(""))) / 20000), v.clip(F.col("turn") / 20), F.lit(1.0))
    return t.select(F.xxhash64("conv_id", "turn").alias("row_id"), x.alias("x"), pm(F.col("role") == "user").alias("y"))


def passage_overlap(docs: DataFrame, passages: DataFrame, words: int = 8, limit: int = 1_000_000) -> DataFrame:
    """(doc_id, shared): how many distinct runs of so many words every document has in common with passages (item_id, text).

    The passages' runs are counted and broadcast only up to a limit; beyond it both sides meet in a shuffled join of distinct runs.
    """

    def runs(df: DataFrame, key: str) -> DataFrame:
        w = F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), "[ \n\t]"), lambda x: x != "")
        at = F.when(F.size("w") >= words, F.sequence(F.lit(1), F.size("w") - (words - 1))).otherwise(F.array().cast("array<int>"))
        return df.select(key, w.alias("w")).select(key, F.explode(F.transform(at, lambda p: F.xxhash64(F.array_join(F.slice("w", p, words), " ")))).alias("run"))

    known = runs(passages, "item_id").select("run").distinct()
    known = F.broadcast(known) if known.count() <= limit else known
    shared = runs(docs, "doc_id").join(known, "run", "left_semi").distinct().groupBy("doc_id").agg(F.count("*").alias("shared"))
    return docs.select("doc_id").join(shared, "doc_id", "left").select("doc_id", F.coalesce("shared", F.lit(0).cast("long")).alias("shared"))


BUILD = {"turns": turns, "lineitem": lineitem, "embeddings": embeddings, "events": events, "events_full": events_full, "documents": documents, "orders": orders, "part": part, "supplier": supplier}
SPECS = {
    "lineitem": Spec(4, 2.0), "embeddings": Spec(64, 1.0), "events": Spec(1, 1.0), "events_full": Spec(4, 2.0), "documents": Spec(5, math.sqrt(5)), "orders": Spec(12, 2.0), "part": Spec(2, math.sqrt(2)), "supplier": Spec(25, 1.0), "turns": Spec(3, math.sqrt(3)),
}


def build(spark: SparkSession, sf_dir: str, workload: str, **options) -> DataFrame:
    return BUILD[workload](spark, sf_dir, **options)


def collapse_duplicates(df: DataFrame) -> DataFrame:
    """Equal rows as one weighted row (row_id the least)."""
    return df.groupBy("x", "y").agg(F.min("row_id").alias("row_id"), F.count("*").cast("double").alias("weight")).select("row_id", "x", "y", "weight")
