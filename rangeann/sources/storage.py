"""Tables in, tables out: typed readers, staging in the shared folder, and sinks."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Fixed schema of objects; ``l`` and ``r`` take any orderable type.
OBJECTS = T.StructType([T.StructField("id", T.LongType()), T.StructField("vec", T.ArrayType(T.FloatType())), T.StructField("l", T.LongType()), T.StructField("r", T.LongType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_objects(spark: SparkSession, path: str, schema: T.StructType = OBJECTS, format: str = "parquet", **options) -> DataFrame:
    """Objects from Parquet, ORC, JSON or CSV with a declared schema; in CSV and text a vector is its numbers between spaces."""
    if format == "csv":
        flat = T.StructType([T.StructField(f.name, T.StringType() if isinstance(f.dataType, T.ArrayType) else f.dataType) for f in schema])
        df = spark.read.schema(flat).options(**options).csv(path)
        return df.withColumns({f.name: F.split(f.name, " ").cast(f.dataType) for f in schema if isinstance(f.dataType, T.ArrayType)})
    if format == "text":
        parts = F.split("value", r"\|")
        return spark.read.text(path).select(*[(F.split(parts[i], " ") if isinstance(f.dataType, T.ArrayType) else parts[i]).cast(f.dataType).alias(f.name) for i, f in enumerate(schema)])
    return spark.read.format(format).schema(schema).options(**options).load(path)


def from_table(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name)


def to_objects(df: DataFrame, id: Column | str, vec: Column | str, l: Column | str, r: Column | str, *residual: str) -> DataFrame:  # noqa: A002, E741
    """Project, rename and cast to the model."""
    c = lambda x: F.col(x) if isinstance(x, str) else x
    return df.select(c(id).cast("long").alias("id"), c(vec).cast("array<float>").alias("vec"), c(l).alias("l"), c(r).alias("r"), *residual)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from ``spark.checkpoint.dir``; a local one only where none is set and the master is local."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="rangeann-"))
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


def staged(df: DataFrame, name: str) -> DataFrame:
    """Written to the shared folder and read back, so that lineage ends here."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
