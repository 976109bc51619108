"""Accuracy and cost measures."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def recall(result: DataFrame, truth: DataFrame) -> DataFrame:
    """Rows ``qid, recall``: the share of the true ids that were returned; queries without any true id have no row."""
    hit = truth.select("qid", "id").join(result.select("qid", "id").withColumn("hit", F.lit(1.0)), ["qid", "id"], "left")
    return hit.groupBy("qid").agg(F.avg(F.coalesce("hit", F.lit(0.0))).alias("recall"))


def rde(result: DataFrame, truth: DataFrame) -> DataFrame:
    """Rows ``qid, rde``: mean ratio of the i-th returned to the i-th true distance, less 1; two zeros have the ratio 1.

    A rank that was not returned counts as if the farthest true one had been returned twice as far (ratio 2 at least), so that short answers are not flattered.
    """
    worst = truth.groupBy("qid").agg((2 * F.max("dist")).alias("worst"))
    both = truth.select("qid", "rank", F.col("dist").alias("true")).join(worst, "qid").join(result.select("qid", "rank", "dist"), ["qid", "rank"], "left")
    dist = F.coalesce("dist", F.greatest("worst", 2 * F.col("true")))
    ratio = F.when(F.col("true") > 0, dist / F.col("true")).when(dist == 0, 1.0)
    return both.groupBy("qid").agg((F.avg(ratio) - 1).alias("rde"))


def mean(measure: DataFrame, column: str) -> DataFrame:
    return measure.agg(F.avg(column).alias(column))


def repeated(runs: list[DataFrame], column: str, *keys: str) -> DataFrame:
    """Mean of several runs."""
    return reduce(lambda a, b: a.unionByName(b), runs).groupBy(*keys).agg(F.avg(column).alias(column))


def curve(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Rows ``ef, recall, distances`` of walks with a column ``ef``."""
    got = found.where(F.col("id").isNotNull())
    efs = found.select("ef").distinct()
    hit = truth.select("qid", "id").crossJoin(F.broadcast(efs)).join(got.select("ef", "qid", "id").withColumn("hit", F.lit(1.0)), ["ef", "qid", "id"], "left")
    accuracy = hit.groupBy("ef").agg(F.avg(F.coalesce("hit", F.lit(0.0))).alias("recall"))
    cost = found.groupBy("ef").agg(F.sum("distances").alias("distances"))
    return accuracy.join(cost, "ef")


def speed_at(points: list[tuple[float, float]], wanted: float) -> float | None:
    """Queries a second at a recall, interpolated between measured points ``(recall, qps)``; None if it is never reached."""
    points = sorted(points)
    for (r0, q0), (r1, q1) in zip(points, points[1:], strict=False):
        if r0 <= wanted <= r1:
            return q1 if r1 == r0 else q0 + (q1 - q0) * (wanted - r0) / (r1 - r0)
    return max((q for r, q in points if r >= wanted), default=None)


def speedup(ours: list[tuple[float, float]], theirs: list[tuple[float, float]], wanted: float) -> float | None:
    a, b = speed_at(ours, wanted), speed_at(theirs, wanted)
    return a / b if a and b else None


def pivot_recall(points: DataFrame, efs: list[int]) -> DataFrame:
    """Recall by width as columns, a row a method."""
    return points.groupBy("method").pivot("ef", efs).agg(F.round(F.avg("recall"), 4))
