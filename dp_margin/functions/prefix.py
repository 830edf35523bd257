"""Prefix sums over a total order without a single-task window: ranges, window sums inside them, and carries between them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

RANGES = 64


def prefix_sums(df: DataFrame, order: str, columns: list[str], ranges: int = RANGES) -> DataFrame:
    """df with ``<c>_to`` (sum of c up to and with the row) and ``<c>_from`` (from the row on) for distinct values of ``order``.

    The ranges' borders are approximate quantiles, so each window holds about 1/ranges of the rows; one row a range is broadcast.
    """
    cuts = sorted(set(df.approxQuantile(order, [k / ranges for k in range(1, ranges)], 0.002))) if ranges > 1 else []
    bucket = F.size(F.filter(F.array(*map(F.lit, cuts)), lambda q: q < F.col(order))) if cuts else F.lit(0)
    dealt = df.withColumn("pf_range", bucket)
    totals = dealt.groupBy("pf_range").agg(*[F.sum(c).alias(f"pf_{c}") for c in columns]).orderBy("pf_range").collect()  # a row a range
    carry, before = [], [0.0] * len(columns)
    after = [sum(r[f"pf_{c}"] for r in totals) for c in columns]
    for r in totals:
        own = [r[f"pf_{c}"] for c in columns]
        after = [a - o for a, o in zip(after, own, strict=True)]
        carry.append((r.pf_range, *before, *after))
        before = [b + o for b, o in zip(before, own, strict=True)]
    names = [f"pf_{k}_{c}" for k in ("before", "after") for c in columns]
    small = df.sparkSession.createDataFrame(carry, "pf_range int, " + ", ".join(f"`{x}` double" for x in names))
    up = Window.partitionBy("pf_range").orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    down = Window.partitionBy("pf_range").orderBy(order).rowsBetween(0, Window.unboundedFollowing)
    out = dealt.join(F.broadcast(small), "pf_range")
    for c in columns:
        out = out.withColumn(f"{c}_to", F.sum(c).over(up) + F.col(f"pf_before_{c}")).withColumn(f"{c}_from", F.sum(c).over(down) + F.col(f"pf_after_{c}"))
    return out.drop("pf_range", *names)
