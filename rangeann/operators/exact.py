"""Exact filtered search, the truth that all other methods are held against."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangeann.functions.predicates import Box, boxes_expr, mask_expr, plan
from rangeann.functions.vectors import l2

#: A query batch is broadcast up to so many rows; more are taken in blocks of that size.
QUERY_ROWS = 20_000


def query_blocks(queries: DataFrame) -> list[DataFrame]:
    """The queries in blocks that are safe to broadcast."""
    n = queries.count()
    blocks = max(1, -(-n // QUERY_ROWS))
    return [queries] if blocks == 1 else [queries.where(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == b) for b in range(blocks)]


def pairs(objects: DataFrame, queries: DataFrame, condition: Column) -> DataFrame:
    """Each query with the objects that meet the condition (columns l, r, lq, rq): blocks of queries against all rows."""
    return reduce(lambda a, b: a.unionByName(b), [objects.join(F.broadcast(q), condition) for q in query_blocks(queries)])


def asked_of(queries: DataFrame) -> DataFrame:
    """A query side that is broadcast if it is small enough for one block, else left to a join by its key."""
    return F.broadcast(queries) if len(query_blocks(queries)) == 1 else queries


def top_k(found: DataFrame, k: int, digits: int | None = 6) -> DataFrame:
    """Rows ``qid, rank, id, dist`` of each query's k nearest; ties go to the smaller id."""
    w = Window.partitionBy("qid").orderBy("dist", "id")
    dist = F.round("dist", digits) if digits is not None else F.col("dist")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", F.col("rank").cast("long").alias("rank"), "id", dist.alias("dist"))


def knn_exact(objects: DataFrame, queries: DataFrame, mask: int | None, k: int = 10, residual: Column | None = None, digits: int | None = 6) -> DataFrame:
    """The k nearest objects that meet the mask (all objects without one) and the residual condition."""
    ends = [F.col(c) for c in ("l", "r", "lq", "rq")]
    condition = mask_expr(mask, *ends) if mask else F.lit(True)
    if residual is not None:
        objects = objects.where(residual)
    return top_k(pairs(objects, queries, condition).select("qid", "id", l2("vec", "qvec").alias("dist")), k, digits)


def pre_filter(objects: DataFrame, queries: DataFrame, mask: int, k: int = 10, boxes: list[Box] | None = None, digits: int | None = 6) -> DataFrame:
    """Filter by the mask's boxes, then exact search: one conjunction a box for the scan, duplicates dropped."""
    ends = [F.col(c) for c in ("l", "r", "lq", "rq")]
    found = pairs(objects, queries, boxes_expr(boxes or plan(mask), *ends))
    return top_k(found.select("qid", "id", l2("vec", "qvec").alias("dist")), k, digits)


def prknn(objects: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """Points (l = r) within the query's interval."""
    return knn_exact(objects.where(F.col("l") == F.col("r")), queries, 8, k)


def iiknn(objects: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """Intervals inside the query's interval."""
    return knn_exact(objects, queries, 8, k)


def stknn(objects: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """Intervals that hold the query's point."""
    return knn_exact(objects, queries.where(F.col("lq") == F.col("rq")), 2, k)


def selectivity(objects: DataFrame, queries: DataFrame, mask: int) -> DataFrame:
    """Rows ``qid, share`` of the objects that meet the mask."""
    ends = [F.col(c) for c in ("l", "r", "lq", "rq")]
    both = pairs(objects.select("id", "l", "r"), queries.select("qid", "lq", "rq"), F.lit(True))
    return both.groupBy("qid").agg(F.avg(F.when(mask_expr(mask, *ends), 1.0).otherwise(0.0)).alias("share"))
