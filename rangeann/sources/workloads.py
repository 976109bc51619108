"""The experiment workloads on the given tables: vector sources, range sources, query sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangeann.functions.vectors import letter_counts
from rangeann.sources.storage import table

MICROS = "long"


def micros(column: str):
    """A timestamp without zone as microseconds, so that ranges are numbers."""
    return F.unix_micros(F.col(column).cast("timestamp"))


def formula_range(df: DataFrame, id_col: str) -> DataFrame:
    """R1: short ranges by formula from the id."""
    i = F.col(id_col)
    return df.withColumn("l", (i * 7919) % 1000).withColumn("r", F.col("l") + (i * i * 31 + i * 17) % 97)


def v1r1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main set: embeddings with formula ranges; ``label`` is a residual attribute."""
    return formula_range(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label"), "id").select("id", "vec", "l", "r", "label")


def price_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    """R2: least and largest price of each order's lines."""
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("id")).agg(F.min("l_extendedprice").alias("l"), F.max("l_extendedprice").alias("r"))


def ship_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    """R3, R7: first and last shipping date of each order, in microseconds."""
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("id")).agg(F.min(micros("l_shipdate")).alias("l"), F.max(micros("l_shipdate")).alias("r"))


def _embedded(spark: SparkSession, sf_dir: str, ranges: DataFrame) -> DataFrame:
    """Embeddings with ranges of their ids; ids outside those of the embeddings are left out before they are grouped."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    ids = e.agg(F.min("id").alias("least"), F.max("id").alias("most")).first()
    return e.join(ranges.where(F.col("id").between(ids.least, ids.most)), "id")


def v1r2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _embedded(spark, sf_dir, price_band(spark, sf_dir))


def v1r3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _embedded(spark, sf_dir, ship_window(spark, sf_dir))


def v1r5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points: the order date."""
    return _embedded(spark, sf_dir, table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), micros("o_orderdate").alias("l"), micros("o_orderdate").alias("r")))


def v2r1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as 26 letter counts."""
    return formula_range(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), letter_counts("text").alias("vec")), "id").select("id", "vec", "l", "r")


def sessions(spark: SparkSession, sf_dir: str, hours: int = 6) -> DataFrame:
    """R4 by gaps: an event more than ``hours`` after the user's last one begins a session."""
    e = table(spark, sf_dir, "events").select("user_id", "event_id", "event_type", "value", micros("ts").alias("at"))
    w = Window.partitionBy("user_id").orderBy("at", "event_id")
    gap = F.col("at") - F.lag("at").over(w)
    e = e.withColumn("begins", F.when(gap.isNull() | (gap > hours * 3_600_000_000), 1).otherwise(0))
    e = e.withColumn("number", F.sum("begins").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    kinds = ["click", "view", "purchase", "signup", "error"]
    counts = [F.count_if(F.col("event_type") == k).alias(f"n_{k}") for k in kinds]
    return e.groupBy("user_id", "number").agg(F.min("at").alias("l"), F.max("at").alias("r"), F.count("*").alias("n"), *counts, F.min("value").alias("low"), F.max("value").alias("high"))


def v4r4(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = sessions(spark, sf_dir)
    features = [c for c in s.columns if c.startswith("n_")] + ["low", "high"]
    return s.select((F.col("user_id") * 10000 + F.col("number")).alias("id"), F.array(*[F.col(c).cast("float") for c in features]).alias("vec"), "l", "r")


def v3r7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as seven features of their lines, for the scale test."""
    f = [F.count("*"), F.min("l_quantity"), F.max("l_quantity"), F.min(F.col("l_discount") * 100), F.max(F.col("l_discount") * 100), F.min(F.col("l_extendedprice") / 1000), F.max(F.col("l_extendedprice") / 1000)]
    at = micros("l_shipdate")
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("id")).agg(F.array(*[c.cast("float") for c in f]).alias("vec"), F.min(at).alias("l"), F.max(at).alias("r"))


def v3wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with formula ranges over a hundred thousand values, mean length 48: low selectivities."""
    i = F.col("id")
    return v3r7(spark, sf_dir).select("id", "vec", ((i * 7919) % 100_000).alias("l")).withColumn("r", F.col("l") + (i * i * 31 + i * 17) % 97)


def v1r1_200(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main set's objects under id 200, for what is built once a version."""
    return v1r1(spark, sf_dir).where("id < 200")


def v3r5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with their date as a point."""
    dates = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), micros("o_orderdate").alias("l"), micros("o_orderdate").alias("r"))
    return v3r7(spark, sf_dir).select("id", "vec").join(dates, "id")


def share(make, tenths: int):
    """Some tenths of a set, by a hash of the id."""
    return lambda spark, sf_dir: make(spark, sf_dir).where(F.pmod(F.xxhash64("id"), F.lit(10)) < tenths)


OBJECT_SETS = {"v3wide_4": share(v3wide, 4), "v3r7_4": share(v3r7, 4), "v3r7_1": share(v3r7, 1), "v3r5_4": share(v3r5, 4), "v3wide": v3wide, "v1r1_200": v1r1_200, "v1r1": v1r1, "v1r2": v1r2, "v1r3": v1r3, "v1r5": v1r5, "v2r1": v2r1, "v4r4": v4r4, "v3r7": v3r7}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return OBJECT_SETS[name](spark, sf_dir)


def windows(spark: SparkSession, sf_dir: str, width: int = 55) -> DataFrame:
    """The main query set: every fiftieth embedding with a window of the given width."""
    i = F.col("vec_id")
    return table(spark, sf_dir, "embeddings").where(i % 50 == 0).select(i.alias("qid"), F.col("embedding").alias("qvec"), (100 + (i * 37) % 800).alias("lq")).withColumn("rq", F.col("lq") + width)


def fixed_window(spark: SparkSession, sf_dir: str, lq, rq) -> DataFrame:
    """The same vectors, one window for all."""
    return windows(spark, sf_dir, 0).select("qid", "qvec", F.lit(lq).alias("lq"), F.lit(rq).alias("rq"))


def date_window(spark: SparkSession, sf_dir: str, first: str, last: str) -> DataFrame:
    of = lambda d: F.unix_micros(F.lit(d).cast("timestamp_ntz").cast("timestamp"))
    return windows(spark, sf_dir, 0).select("qid", "qvec", of(first).alias("lq"), of(last).alias("rq"))
