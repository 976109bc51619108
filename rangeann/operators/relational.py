"""Joins, sets, windows and groupings over interval tables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangeann.functions.predicates import mask_expr
from rangeann.functions.tree import cover_nodes, height_of, path_nodes
from rangeann.operators.exact import QUERY_ROWS, pairs
from rangeann.sources.storage import staged


def node_join(points: DataFrame, intervals: DataFrame, point: str, low: str, high: str, height: int) -> DataFrame:
    """Points and intervals (as ranks) that hold them: the paths of one side meet the covers of the other.

    A cover node that holds a point is unique, so no pair comes twice; the cost follows the result.
    """
    paths = points.withColumn("node", F.explode(path_nodes(F.col(point), height)))
    covers = intervals.withColumn("node", F.explode(cover_nodes(F.col(low), F.col(high), height)))
    return paths.join(covers, "node").drop("node")


def overlap_join(left: DataFrame, right: DataFrame, size: int) -> DataFrame:
    """All pairs of overlapping intervals of rows ``a, a_l, a_r`` and ``b, b_l, b_r`` (ranks of a domain of ``size`` values).

    Two disjoint joins: the left interval begins inside the right one, or the right one begins inside the left one
    and not at its start.
    """
    height = height_of(size)
    starts = node_join(left, right, "a_l", "b_l", "b_r", height)
    within = node_join(right, left.withColumn("after", F.col("a_l") + 1), "b_l", "after", "a_r", height).drop("after")
    return starts.unionByName(within)


def theta_join(left: DataFrame, right: DataFrame, mask: int) -> DataFrame:
    """Pairs whose intervals stand in the mask's relation, by comparison of all pairs; the right side goes in blocks of a checked size."""
    condition = mask_expr(mask, *(F.col(c) for c in ("l", "r", "lq", "rq")))
    rows = right.count()
    blocks = max(1, -(-rows // QUERY_ROWS))
    parts = [right] if blocks == 1 else [right.where(F.pmod(F.xxhash64(*right.columns), F.lit(blocks)) == b) for b in range(blocks)]
    return reduce(lambda a, b: a.unionByName(b), [left.join(F.broadcast(p), condition) for p in parts])


def answered(queries: DataFrame, objects: DataFrame, mask: int) -> DataFrame:
    """The ids of queries that some object answers: queries are broadcast in blocks, objects stay where they are."""
    return pairs(objects.select("l", "r"), queries.select("qid", "lq", "rq"), mask_expr(mask, *(F.col(c) for c in ("l", "r", "lq", "rq")))).select("qid").distinct()


def queries_with_answer(queries: DataFrame, objects: DataFrame, mask: int) -> DataFrame:
    return queries.join(answered(queries, objects, mask), "qid", "left_semi")


def queries_without_answer(queries: DataFrame, objects: DataFrame, mask: int) -> DataFrame:
    return queries.join(answered(queries, objects, mask), "qid", "left_anti")


def as_of(asked: DataFrame, recorded: DataFrame, key: str, value: str, groups: int = 64) -> DataFrame:
    """Each row of ``asked`` with the last recorded ``value`` at or before its ``key``.

    Both sides are merged in order within ranges of the key, so no task sorts all rows; each
    range begins with the last value of those before it, of which there is one a range.
    """
    both = asked.withColumn(value, F.lit(None).cast(dict(recorded.dtypes)[value])).withColumn("side", F.lit(1)).unionByName(recorded.select(key, value).withColumn("side", F.lit(0)), allowMissingColumns=True)
    dealt = staged(both.repartitionByRange(groups, key).withColumn("range", F.spark_partition_id()), "as-of")
    last = dealt.where("side = 0").groupBy("range").agg(F.max_by(value, key).alias("carry"))
    carried = dealt.select("range").distinct().join(last, "range", "left").withColumn("carry", F.last("carry", ignorenulls=True).over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)))
    w = Window.partitionBy("range").orderBy(key, "side").rowsBetween(Window.unboundedPreceding, 0)
    filled = dealt.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("side = 1").join(F.broadcast(carried), "range")
    return filled.withColumn(value, F.coalesce(value, "carry")).drop("side", "range", "carry")


def edge_difference(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """Edges of one graph and not of the other, by a full outer join."""
    return a.select(*keys).distinct().withColumn("in_a", F.lit(1)).join(b.select(*keys).distinct().withColumn("in_b", F.lit(1)), keys, "full_outer").where("in_a IS NULL OR in_b IS NULL")


def members(objects: DataFrame, orient: str, size: int) -> DataFrame:
    """Rows ``orient, level, node, id, version, key`` of objects with ranks."""
    height = height_of(size)
    version, key = {"LU": (F.col("l_rank"), "r_rank"), "RD": (size + 1 - F.col("r_rank"), "l_rank"), "LD": (size + 1 - F.col("l_rank"), "r_rank")}[orient]
    return objects.select("id", version.cast("long").alias("version"), F.col(key).alias("key")).select(F.lit(orient).alias("orient"), F.posexplode(path_nodes(F.col("key"), height)).alias("level", "node"), "id", "version", "key")


def sizes(rows: DataFrame, how: str) -> DataFrame:
    """Member counts by orientation and level: ``cube``, ``rollup`` or ``grouping_sets``."""
    if how == "grouping_sets":
        return rows.groupingSets([["orient", "level"], ["orient"], []], "orient", "level").agg(F.count("*").alias("n"))
    return getattr(rows, how)("orient", "level").agg(F.count("*").alias("n"))


def by_range(rows: DataFrame, key: str, name: str, groups: int = 64) -> DataFrame:
    """Rows dealt by ranges of a key and staged, with the number of their ``range``."""
    return staged(rows.repartitionByRange(groups, key).withColumn("range", F.spark_partition_id()), name)


def running_births(objects: DataFrame, groups: int = 64) -> DataFrame:
    """Rows ``version, born, alive``: objects that begin at each l, and those begun so far.

    Sums run within ranges of l and begin with the sum of the ranges before (a row a range), so no task sorts all.
    """
    born = by_range(objects.groupBy(F.col("l").alias("version")).agg(F.count("*").alias("born")), "version", "births", groups)
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    carried = born.groupBy("range").agg(F.sum("born").alias("n")).withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    own = F.sum("born").over(Window.partitionBy("range").orderBy("version").rowsBetween(Window.unboundedPreceding, 0))
    return born.withColumn("own", own).join(F.broadcast(carried), "range").select("version", "born", (F.col("own") + F.col("before")).alias("alive"))


def version_ends(objects: DataFrame, groups: int = 64) -> DataFrame:
    """Rows ``version, ends``: each recorded version and the next one (null for the last); the last of a range reads the next range's first."""
    v = by_range(objects.select(F.col("l").alias("version")).distinct(), "version", "versions", groups)
    firsts = v.groupBy("range").agg(F.min("version").alias("first")).withColumn("next", F.lead("first").over(Window.orderBy("range"))).drop("first")
    own = v.withColumn("ends", F.lead("version").over(Window.partitionBy("range").orderBy("version")))
    return own.join(F.broadcast(firsts), "range").select("version", F.coalesce("ends", "next").alias("ends"))


def first_members(rows: DataFrame) -> DataFrame:
    """Rows ``orient, level, node, id``: each node's first-born member, its entry."""
    w = Window.partitionBy("orient", "level", "node").orderBy("version", "id")
    return rows.withColumn("entry", F.first("id").over(w)).select("orient", "level", "node", F.col("entry").alias("id")).distinct()


def standing(objects: DataFrame, group: str, value: str) -> DataFrame:
    """Each object's rank, dense rank, quarter, relative rank and share up to it within its group."""
    w = Window.partitionBy(group).orderBy(value)
    return objects.select("id", F.rank().over(w).cast("long").alias("rank"), F.dense_rank().over(w).cast("long").alias("dense"), F.ntile(4).over(Window.partitionBy(group).orderBy(value, "id")).cast("long").alias("quarter"), F.round(F.percent_rank().over(w), 9).alias("relative"), F.round(F.cume_dist().over(w), 9).alias("up_to"))


def hashed_join(left: DataFrame, right: DataFrame, keys: list[str]) -> DataFrame:
    """An equi join by a shuffled hash table of the right side, which is the smaller one but too large to broadcast."""
    return left.join(right.hint("shuffle_hash"), keys)
