"""The greedy walk as joins: a hop of all queries at a time, for graphs that no worker can hold."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangeann.functions.vectors import l2
from rangeann.operators.exact import asked_of
from rangeann.sources.storage import staged


def search(edges: DataFrame, objects: DataFrame, queries: DataFrame, k: int = 10, ef: int = 50, beam: int = 8, max_hops: int = 100) -> DataFrame:
    """Rows ``qid, rank, id, dist`` by walks over ``edges`` (rows ``src, dst``) from the object of least id.

    A query's pool holds its ``ef`` nearest objects met, each expanded or not; a hop expands the ``beam`` nearest that are not.  Queries whose pool is
    all expanded cost nothing more.  Each hop is a join with the edges and one with the vectors; the pool is staged, so no lineage grows.
    """
    vectors = objects.select("id", "vec")
    asked = queries.select("qid", "qvec")
    far = lambda rows: rows.join(vectors, "id").join(asked_of(asked), "qid").select("qid", "id", l2("vec", "qvec").alias("dist"))
    first = objects.agg(F.min("id").alias("id"))
    pool = staged(far(asked.select("qid").crossJoin(F.broadcast(first))).withColumn("done", F.lit(False)), "pool")
    nearest = Window.partitionBy("qid").orderBy("dist", "id")
    turn = Window.partitionBy("qid", "done").orderBy("dist", "id")
    for _ in range(max_hops):
        marked = pool.withColumn("turn", ~F.col("done") & (F.row_number().over(turn) <= beam))
        opened = staged(marked, "opened")
        if opened.where("turn").isEmpty():
            break
        met = opened.where("turn").join(edges, F.col("id") == F.col("src")).select("qid", F.col("dst").alias("id")).distinct()
        fresh = far(met.join(opened.select("qid", "id"), ["qid", "id"], "left_anti")).withColumn("done", F.lit(False))
        held = opened.select("qid", "id", "dist", (F.col("done") | F.col("turn")).alias("done")).unionByName(fresh)
        pool = staged(held.withColumn("place", F.row_number().over(nearest)).where(F.col("place") <= ef).drop("place"), "pool")
    return pool.withColumn("rank", F.row_number().over(nearest).cast("long")).where(F.col("rank") <= k).select("qid", "rank", "id", "dist")
