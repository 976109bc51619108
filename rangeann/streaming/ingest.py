"""Objects from streams: event sessions, and insertion into an index in order of l.

Only the orientation whose versions rise with l can grow from a stream in time order.  Objects that arrive in order are inserted
into the last shard of such an index at once (its open edges are read back, the new objects linked in, the rows written as a new
generation); late ones go to a delta that searches read exactly.  Compaction builds all orientations over everything seen, and the stream
begins anew after it.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangeann.functions.predicates import plan
from rangeann.operators import index as ix
from rangeann.operators.exact import knn_exact, top_k
from rangeann.plans.kernel import Edges, Shard
from rangeann.plans.methods import BUCKETS, SMALL, Domain, level_edges
from rangeann.sources.storage import staged

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def stream_events(spark: SparkSession, path: str, schema: T.StructType = EVENTS, files_at_once: int = 1) -> DataFrame:
    """Parquet files that arrive in a folder, with ``at`` as a timestamp for watermarks."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_at_once).parquet(path).withColumn("at", F.col("ts").cast("timestamp"))


def session_objects(events: DataFrame, gap: str = "6 hours", late: str | None = "1 day") -> DataFrame:
    """Sessions of a user as objects: l and r are the first and last event (the window's own end is a gap later).

    ``late`` is None for a stream that has its watermark already.
    """
    if events.isStreaming and late:
        events = events.withWatermark("at", late)
    return events.groupBy("user_id", F.session_window("at", gap)).agg(F.min("at").alias("l"), F.max("at").alias("r"), F.count("*").alias("n")).drop("session_window")


def arrivals(events: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Event counts by window."""
    if events.isStreaming:
        events = events.withWatermark("at", late)
    w = F.window("at", length, slide) if slide else F.window("at", length)
    return events.groupBy(w).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def once_each(events: DataFrame, late: str = "1 day") -> DataFrame:
    return events.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def node_counts(objects: DataFrame, late: str = "1 day") -> DataFrame:
    """A running member count a shard, kept as streaming state."""

    def count(key, batches, state):
        n = state.getOption[0] if state.exists else 0
        for pdf in batches:
            n += len(pdf)
        state.update((n,))
        import pandas as pd

        yield pd.DataFrame({"shard": [key[0]], "n": [n]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    return objects.groupBy("shard").applyInPandasWithState(count, "shard int, n long", "n long", "update", GroupStateTimeout.NoTimeout)


def joined_counts(events: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """A stream joined with a static table and counted by event type."""
    return events.join(static, key).groupBy("event_type").agg(F.count("*").alias("n"))


def inserted(row: dict | None, fresh: pa.Table, name: int, number: type, m: int, ef_con: int, small: int, buckets: int) -> dict:
    """An index row (None: of no shard yet) with new objects, whose l is no less than any there."""
    new = ix.shard_of(fresh)
    order = np.lexsort((new.ids, new.left))
    new = new.take(order)
    old = ix.row_shard(row, number) if row else None
    n = len(old) if old else 0
    tie = np.arange(n + len(new))
    s = Shard(new.ids, new.vectors, new.left, new.right, tie) if old is None else Shard(*(np.concatenate([a, b]) for a, b in ((old.ids, new.ids), (old.vectors, new.vectors), (old.left, new.left), (old.right, new.right))), tie)
    domain = Domain(s, "LU", buckets, np.frombuffer(row["LU_cuts"], number) if row else None)
    rows = Edges.unpacked(row["LU"]).rows() if row else None
    late = np.arange(len(s)) >= n
    found = [level_edges(s, domain, j, m, ef_con, small, fresh=None if old is None else late, old=None if old is None else rows[rows[:, 0] == j]) for j in range(domain.height + 1)]
    edges = Edges.of(len(s), np.concatenate(found), domain.height + 1)
    return ix.member_row(s, s, name) | ix.edge_columns("LU", edges, ix.pack_array(domain.cuts)) | {"build_s": 0.0}


@dataclass
class StreamIndex:
    """A growing index in a folder: ``shards/batch=N`` (rows of the shards that batch N changed), ``late/batch=N``, ``compacted/batch=N``.

    Everything of a batch is written under its number, so a batch that runs again replaces its own files and reads only earlier ones.
    """

    folder: str
    m: int = 16
    ef_con: int = 100
    small: int = SMALL
    shard_rows: int = ix.SHARD_ROWS
    buckets: int = BUCKETS

    def read(self, spark: SparkSession, part: str, before: int | None = None) -> DataFrame | None:
        try:
            rows = spark.read.option("basePath", f"{self.folder}/{part}").parquet(f"{self.folder}/{part}")
        except Exception as e:  # nothing was written yet
            if "PATH_NOT_FOUND" in str(e) or "UNABLE_TO_INFER_SCHEMA" in str(e):
                return None
            raise
        return rows if before is None else rows.where(F.col("batch") < before)

    def mark(self, spark: SparkSession, before: int | None = None) -> int:
        """The batch after which the last compaction was made; -1 without one."""
        rows = self.read(spark, "marks", before)
        found = rows.agg(F.max("batch")).first()[0] if rows is not None else None
        return -1 if found is None else found

    def latest(self, spark: SparkSession, before: int | None = None) -> DataFrame | None:
        """The shards' rows since the last compaction, each of its last batch."""
        rows = self.read(spark, "shards", before)
        if rows is None:
            return None
        rows = rows.where(F.col("batch") > self.mark(spark, before))
        last = rows.groupBy("shard").agg(F.max("batch").alias("batch"))
        return rows.join(F.broadcast(last), ["shard", "batch"]).drop("batch")

    def upsert(self, batch: DataFrame, number: int) -> None:
        """Inserts a micro-batch: rows at or after the greatest l seen so far, in order; others go to the delta."""
        spark = batch.sparkSession
        batch = staged(ix.numbered(batch.select("id", "vec", "l", "r"), "l", "r"), "arrived")
        every = self.read(spark, "shards", number)
        top = every.agg(F.max("l_max")).first()[0] if every is not None else None
        (batch.limit(0) if top is None else batch.where(F.col("l") < F.lit(top))).write.mode("overwrite").parquet(f"{self.folder}/late/batch={number}")
        fresh = batch if top is None else batch.where(F.col("l") >= F.lit(top))
        n = fresh.count()
        if not n:
            return
        state = self.latest(spark, number)
        last = state.orderBy(F.desc("shard")).select("shard", "n").first() if state is not None else None
        kind = dict(fresh.dtypes)["l"].replace("bigint", "long")
        if last is not None and last.n + n <= self.shard_rows:
            fresh, held = fresh.withColumn("shard", F.lit(last.shard)), state.where(F.col("shard") == last.shard)
        else:
            first, many = (0 if last is None else last.shard + 1), -(-n // self.shard_rows)
            dealt = fresh if many == 1 else staged(fresh.repartitionByRange(many, "l", "id").withColumn("part", F.spark_partition_id()), "dealt")
            fresh, held = dealt.withColumn("shard", F.lit(first) + (F.lit(0) if many == 1 else F.col("part"))), None
        schema = ix.row_schema(kind, ("LU",))
        if held is None:
            held = spark.createDataFrame([], ix.ddl(schema))
        m, ef_con, small, buckets, real = self.m, self.ef_con, self.small, self.buckets, kind == "double"

        def grow(existing: pa.Table, new: pa.Table) -> pa.Table:
            row = existing.to_pylist()[0] if existing.num_rows else None
            made = inserted(row, new, new.column("shard")[0].as_py(), np.float64 if real else np.int64, m, ef_con, small, buckets)
            return pa.Table.from_pylist([made], schema=pa.schema([(c, t) for c, t, _ in schema]))

        names = [c for c, _, _ in schema]
        grown = held.select(*names).groupBy("shard").cogroup(fresh.select("id", "vec", "l", "r", "shard").groupBy("shard")).applyInArrow(grow, ix.ddl(schema))
        grown.write.mode("overwrite").parquet(f"{self.folder}/shards/batch={number}")

    def start(self, objects: DataFrame, checkpoint: str):
        return objects.writeStream.foreachBatch(self.upsert).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()

    def index(self, spark: SparkSession) -> ix.Index | None:
        """The growing index since the last compaction."""
        rows = self.latest(spark)
        return None if rows is None or rows.isEmpty() else ix.Index(rows, self.m, self.ef_con, self.small, ("LU",), "double" if dict(rows.dtypes)["l_min"] == "double" else "long")

    def objects(self, spark: SparkSession, part: str) -> DataFrame | None:
        """Rows ``id, vec, l, r`` since the last compaction: of the growing index ("shards"), of the delta ("late"); or those of the compacted index ("compacted")."""
        if part == "late":
            rows = self.read(spark, "late")
            return None if rows is None else rows.where(F.col("batch") > self.mark(spark)).drop("batch")
        rows = self.latest(spark) if part == "shards" else self.compacted(spark) and self.compacted(spark).rows
        if rows is None:
            return None
        end = dict(rows.dtypes)["l_min"]
        number = np.float64 if end == "double" else np.int64

        def unpack(batches: Iterable[pa.RecordBatch]):
            for row in ix.each_row(batches):
                s = ix.row_shard(row, number)
                yield pa.RecordBatch.from_arrays([pa.array(s.ids), pa.array(list(s.vectors.astype(np.float32)), pa.list_(pa.float32())), pa.array(s.left), pa.array(s.right)], names=["id", "vec", "l", "r"])

        return rows.select("n", "d", "ids", "vecs", "left", "right", "tie").mapInArrow(unpack, f"id long, vec array<float>, l {end}, r {end}")

    def everything(self, spark: SparkSession) -> DataFrame:
        parts = [self.objects(spark, p) for p in ("compacted", "shards", "late")]
        return reduce(lambda a, b: a.unionByName(b), [p for p in parts if p is not None])

    def compacted(self, spark: SparkSession) -> ix.Index | None:
        mark = self.mark(spark)
        return None if mark < 0 else ix.Index.load(spark, f"{self.folder}/compacted/batch={mark}")

    def compact(self, spark: SparkSession, number: int, **options) -> ix.Index:
        """Builds all orientations over everything that batches up to ``number`` brought; later batches begin a growing index anew."""
        made = ix.build(self.everything(spark), m=self.m, ef_con=self.ef_con, small=self.small, shard_rows=self.shard_rows, **options)
        made.save(f"{self.folder}/compacted/batch={number}")
        spark.createDataFrame([(True,)], "done boolean").coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/marks/batch={number}")  # from here on it counts
        return made

    def search(self, queries: DataFrame, mask: int, k: int = 10, ef: int = 100, check: bool = False) -> DataFrame:
        """The compacted index, the growing one (exactly, where the mask needs an orientation it has not), and the delta, exactly."""
        spark, parts = queries.sparkSession, []
        whole, growing = self.compacted(spark), self.index(spark)
        searched = [whole] * (whole is not None)
        exactly = [self.objects(spark, "late")]
        if growing is not None:
            if {b.orient for b in plan(mask)} == {"LU"}:
                searched.append(growing)
            else:
                exactly.append(self.objects(spark, "shards"))
        parts += [ix.search(i, queries, mask, k, ef, check=check).where(F.col("id").isNotNull()).select("qid", "id", "dist") for i in searched]
        parts += [knn_exact(o, queries, mask, k, digits=None).select("qid", "id", "dist") for o in exactly if o is not None]
        return top_k(reduce(lambda a, b: a.unionByName(b), parts).groupBy("qid", "id").agg(F.min("dist").alias("dist")), k)
