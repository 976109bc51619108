"""SQL surface: functions, aggregates and table functions to register on a session."""

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangeann.functions.predicates import ATOMS
from rangeann.functions.tree import cover

NODE = T.StructType([T.StructField("node", T.IntegerType())])
_ATOM_SQL = {1: "l <= lq AND lq <= r AND r <= rq", 2: "l <= lq AND rq <= r", 3: "lq <= l AND l <= rq AND rq <= r", 4: "lq <= l AND r <= rq"}


@F.pandas_udf(T.DoubleType())
def l2_np(a: pd.Series, b: pd.Series) -> pd.Series:
    """Euclidean distance by numpy, to compare with the column form."""
    return pd.Series([float(np.sqrt(((np.asarray(x, float) - np.asarray(y, float)) ** 2).sum())) for x, y in zip(a, b, strict=True)])


@F.pandas_udf(T.ArrayType(T.LongType()))
def topk_ids(ids: pd.Series, dist: pd.Series) -> list:
    """The ten nearest ids of a group."""
    order = np.lexsort((ids.to_numpy(), dist.to_numpy()))[:10]
    return ids.to_numpy()[order].tolist()


@F.udtf(returnType=NODE)
class TreePath:
    """The nodes above a rank, root first."""

    def eval(self, rank: int, height: int):
        for j in range(height + 1):
            yield ((1 << j) | ((rank - 1) >> (height - j)),)


@F.udtf(returnType=NODE)
class TreeCover:
    """The least set of nodes of a rank interval."""

    def eval(self, low: int, high: int, height: int):
        for n in cover(low, high, height):
            yield (n,)


def register(spark: SparkSession) -> None:
    """``rr_match(mask, l, r, lq, rq)`` (an SQL expression, so it is optimised as one), ``l2_dist``, ``l2_np``, ``topk_ids``, ``tree_path``, ``tree_cover``."""
    test = " OR ".join(f"((mask & {1 << (a - 1)}) <> 0 AND {_ATOM_SQL[a]})" for a in ATOMS)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION rr_match(mask INT, l DOUBLE, r DOUBLE, lq DOUBLE, rq DOUBLE) RETURNS BOOLEAN RETURN {test}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION l2_dist(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN sqrt(aggregate(zip_with(a, b, (x, y) -> (CAST(x AS DOUBLE) - CAST(y AS DOUBLE)) * (CAST(x AS DOUBLE) - CAST(y AS DOUBLE))), 0D, (s, x) -> s + x))")
    spark.udf.register("l2_np", l2_np)
    spark.udf.register("topk_ids", topk_ids)
    spark.udtf.register("tree_path", TreePath)
    spark.udtf.register("tree_cover", TreeCover)

