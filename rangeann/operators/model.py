"""The object model: validation with reasons, and the ranked domain."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangeann.sources.storage import staged


def reason(dimension: int) -> Column:
    """Why an object is refused; null where it is sound."""
    v = F.col("vec")
    return (
        F.when(F.col("id").isNull(), "null id")
        .when(v.isNull(), "null vector")
        .when(F.size(v) != dimension, "wrong length")
        .when(F.exists(v, lambda x: x.isNull() | F.isnan(x.cast("double"))), "null or NaN component")
        .when(F.col("l").isNull() | F.col("r").isNull(), "null bound")
        .when(F.isnan(F.col("l").cast("double")) | F.isnan(F.col("r").cast("double")), "NaN bound")
        .when(F.col("l") > F.col("r"), "bounds reversed")
    )


def validate(objects: DataFrame, dimension: int) -> tuple[DataFrame, DataFrame]:
    """The sound objects, and rows ``reason, n`` of the refused ones."""
    marked = objects.withColumn("reason", reason(dimension))
    return marked.where(F.col("reason").isNull()).drop("reason"), marked.where(F.col("reason").isNotNull()).groupBy("reason").agg(F.count("*").alias("n"))


def domain(objects: DataFrame, partitions: int = 8) -> DataFrame:
    """Rows ``value, rank`` of all different interval ends.

    Values are dealt out by range, counted in each range, and ranked within; only the counts of
    the ranges come together, so no task sorts the whole domain.
    """
    values = objects.select(F.col("l").alias("value")).unionByName(objects.select(F.col("r").alias("value"))).distinct()
    dealt = staged(values.repartitionByRange(partitions, "value").withColumn("range", F.spark_partition_id()), "domain")
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy("range").agg(F.count("*").alias("n")).withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")  # a row a range
    own = F.row_number().over(Window.partitionBy("range").orderBy("value"))
    return dealt.withColumn("own", own).join(F.broadcast(starts), "range").select("value", (F.col("own") + F.col("before")).cast("long").alias("rank"))


def domain_buckets(objects: DataFrame, buckets: int) -> list:
    """Bounds of about equal shares of the interval ends, for domains too large to rank one by one."""
    ends = objects.select(F.col("l").alias("value")).unionByName(objects.select(F.col("r").alias("value")))
    return ends.agg(F.percentile_approx("value", [i / buckets for i in range(1, buckets)], 10_000).alias("b")).first().b


def with_ranks(objects: DataFrame, ranks: DataFrame) -> DataFrame:
    """Objects with ``l_rank`` and ``r_rank``."""
    return objects.join(ranks.select(F.col("value").alias("l"), F.col("rank").alias("l_rank")), "l").join(ranks.select(F.col("value").alias("r"), F.col("rank").alias("r_rank")), "r")
