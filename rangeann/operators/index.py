"""Building, storing and searching the versioned tree of graphs, a shard a row.

Objects are dealt to shards by ranges of (l, r), so that a query concerns few shards where intervals are short; equal intervals are
dealt on by a hash of the id.  A shard's objects cross the exchange once where shards are many; where there are fewer than cores, the
levels of its trees are made by several tasks.  They are packed into one row: its members once, and the edges of each orientation in a
column of their own, so that a search reads only those it needs.  A search is a map over the
shards that the queries can concern, with the queries broadcast in checked blocks, and one top-k
merge; no step brings a graph to the driver or shuffles it.
"""

from __future__ import annotations

import ctypes
import json
import pickle
import time
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rangeann.functions.predicates import ORIENTATIONS, Box, atomic_plan, plan
from rangeann.operators.exact import query_blocks, top_k
from rangeann.plans.kernel import Edges, Shard, summed
from rangeann.plans.methods import BUCKETS, METHODS, SMALL, Domain, Method, Oriented, block_of, level_edges, margin, qualifies
from rangeann.sources.storage import staged

SHARD_ROWS = 2_048  # a search holds a shard in one row, some 1.5 KB an object and orientation; a build holds its distances in blocks
EDGE_ROWS = 65_536  # edges of a batch
SCANNED = 128  # queries that a scan takes at once
WARM_UP = 2  # queries that a timed run answers before its clock starts
EDGE_COLUMNS = ("level", "src", "dst", "begin", "end")
WORK = ("distances", "hops", "edges", "unqualified", "missed")
_FOUND = "qid long, id long, dist double, " + ", ".join(f"{c} long" for c in WORK) + ", search_s double"
_FOUND_NAMES = [c.split(" ")[0] for c in _FOUND.split(", ")]
_FLOATS = ("dist", "search_s", "build_s")


def number_kind(kind: str) -> str:
    return "double" if kind in ("double", "float") or kind.startswith("decimal") else "long"


def ordinal(column: str, kind: str) -> Column:
    """An interval end as a number that keeps its order."""
    c = F.col(column)
    if kind.startswith("timestamp"):
        return F.unix_micros(c.cast("timestamp"))
    if kind == "date":
        return F.unix_date(c).cast("long")
    return c.cast(number_kind(kind))


def numbered(df: DataFrame, *columns: str) -> DataFrame:
    kinds = dict(df.dtypes)
    return df.withColumns({c: ordinal(c, kinds[c]) for c in columns})


def shard_of(table: pa.Table) -> Shard:
    """A worker's objects, by id."""
    ids = np.asarray(table.column("id").combine_chunks()) if table.num_rows else np.zeros(0, np.int64)
    order = np.argsort(ids, kind="stable")
    flat = table.column("vec").combine_chunks()
    width = len(flat[0]) if len(flat) else 0
    vectors = np.asarray(flat.flatten(), dtype=np.float64).reshape(-1, width)[order]
    left, right = (np.asarray(table.column(c).combine_chunks())[order] for c in ("l", "r"))
    return Shard(ids[order], vectors, left, right)


def sharded(objects: DataFrame, shards: int) -> DataFrame:
    """Objects with their shard, by ranges of (l, r, hash of the id)."""
    objects = numbered(objects, "l", "r")
    if shards == 1:
        return objects.withColumn("shard", F.lit(0))
    return staged(objects.withColumn("spread", F.xxhash64("id")).repartitionByRange(shards, "l", "r", "spread").drop("spread").withColumn("shard", F.spark_partition_id()), "shards")


def shard_count(objects: DataFrame, shard_rows: int) -> int:
    return max(1, -(-objects.count() // shard_rows))


def each_alone(rows: DataFrame, unit: str, count: int) -> DataFrame:
    """Rows dealt so that each of ``count`` units (from 0) has a partition of its own, which adaptive execution leaves alone."""
    if count > 4_096:
        return rows
    spark = rows.sparkSession
    names = spark.range(64 * count + 64).select(F.col("id").cast("int").alias("id"), F.pmod(F.hash(F.col("id").cast("int")), F.lit(count)).alias("p")).groupBy("p").agg(F.min("id").alias("id")).collect()
    by = [r.id for r in sorted(names, key=lambda r: r.p)]
    if len(by) < count:
        return rows
    return rows.withColumn(unit, F.get(F.array(*map(F.lit, by)), F.col(unit))).repartition(count, unit)


def release() -> None:
    """Gives what a shard took back to the system, where the C library can do that."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def each_row(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
    """Index rows, of which each is a shard: one at a time as an object."""
    for batch in batches:
        for i in range(batch.num_rows):
            yield batch.slice(i, 1).to_pylist()[0]


def pack_array(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x).tobytes()


def row_shard(row: dict, number: type) -> Shard:
    """A shard from an index row."""
    vectors = np.frombuffer(row["vecs"], np.float32).astype(np.float64).reshape(row["n"], row["d"])
    return Shard(np.frombuffer(row["ids"], np.int64), vectors, np.frombuffer(row["left"], number), np.frombuffer(row["right"], number), np.frombuffer(row["tie"], np.int64))


def row_tree(row: dict, shard: Shard, orient: str, m: int, small: int) -> Oriented:
    number = shard.left.dtype.type
    return Oriented(shard, Domain(shard, orient, cuts=np.frombuffer(row[f"{orient}_cuts"], number)), Edges.unpacked(row[orient]), m, small)


def member_row(shard: Shard, s: Shard, name: int, residual: np.ndarray | None = None) -> dict:
    return {
        "shard": name, "n": len(s), "d": s.vectors.shape[1], "l_min": s.left.min(), "l_max": s.left.max(), "r_min": s.right.min(), "r_max": s.right.max(), "ids": pack_array(s.ids),
        "vecs": pack_array(s.vectors.astype(np.float32)), "left": pack_array(s.left), "right": pack_array(s.right), "tie": pack_array(s.tie.astype(np.int64)), "residual": None if residual is None else pack_array(residual),
    }


def edge_columns(orient: str, edges: Edges, cuts: bytes) -> dict:
    return {orient: edges.packed(), f"{orient}_cuts": cuts, f"{orient}_edges": edges.count}


def row_schema(kind: str, orientations: Iterable[str]) -> list[tuple[str, pa.DataType, str]]:
    """Names and types of an index row, for Arrow and for Spark."""
    end = (pa.float64(), "double") if kind == "double" else (pa.int64(), "long")
    out = [("shard", pa.int32(), "int"), ("n", pa.int64(), "long"), ("d", pa.int32(), "int"), *((c, *end) for c in ("l_min", "l_max", "r_min", "r_max")), *((c, pa.binary(), "binary") for c in ("ids", "vecs", "left", "right", "tie", "residual"))]
    return out + [("build_s", pa.float64(), "double")] + [c for o in orientations for c in ((o, pa.binary(), "binary"), (f"{o}_cuts", pa.binary(), "binary"), (f"{o}_edges", pa.int64(), "long"))]


def ddl(schema: list[tuple[str, pa.DataType, str]]) -> str:
    return ", ".join(f"{n} {t}" for n, _, t in schema)


@dataclass
class Index:
    """Rows of ``row_schema``: bounds, members, and three columns an orientation (edges, least keys of the leaves, how many edges)."""

    rows: DataFrame
    m: int
    ef_con: int
    small: int
    orientations: tuple[str, ...]
    kind: str  # of the interval ends

    def save(self, path: str) -> None:
        self.rows.sortWithinPartitions("l_min").write.mode("overwrite").parquet(f"{path}/shards")
        meta = {"m": self.m, "ef_con": self.ef_con, "small": self.small, "orientations": list(self.orientations), "kind": self.kind, "format": 2}
        self.rows.sparkSession.createDataFrame([(json.dumps(meta),)], "meta string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Index:
        meta = json.loads(spark.read.text(f"{path}/meta").first().value)
        return Index(spark.read.parquet(f"{path}/shards"), meta["m"], meta["ef_con"], meta["small"], tuple(meta["orientations"]), meta["kind"])

    def edges(self, *orientations: str) -> DataFrame:
        """Rows ``shard, orient, level, src, dst, begin, end``; src and dst are object ids, begin and end version ranks of the shard."""

        def unpack(batches: Iterable[pa.RecordBatch]):
            for row in each_row(batches):
                ids = np.frombuffer(row["ids"], np.int64)
                for o in orientations:
                    for e in Edges.unpacked(row[o]).parts(EDGE_ROWS):
                        columns = [pa.array(np.full(len(e), row["shard"], np.int32)), pa.array([o] * len(e)), pa.array(e[:, 0], pa.int32()), pa.array(ids[e[:, 1]]), pa.array(ids[e[:, 2]]), pa.array(e[:, 3], pa.int32()), pa.array(e[:, 4], pa.int32())]
                        yield pa.RecordBatch.from_arrays(columns, names=["shard", "orient", *EDGE_COLUMNS])

        orientations = orientations or self.orientations
        return self.rows.select("shard", "ids", *orientations).mapInArrow(unpack, "shard int, orient string, level int, src long, dst long, begin int, end int")

    def counted(self, count: Callable[[Shard, str, Edges], int]) -> DataFrame:
        """Rows ``shard, orient, n`` of a count over the edges of each shard, made where they are."""
        names, number = self.orientations, np.float64 if self.kind == "double" else np.int64

        def run(batches: Iterable[pa.RecordBatch]):
            for row in each_row(batches):
                shard = row_shard(row, number)
                yield pa.RecordBatch.from_arrays([pa.array([row["shard"]] * len(names), pa.int32()), pa.array(names), pa.array([count(shard, o, Edges.unpacked(row[o])) for o in names], pa.int64())], names=["shard", "orient", "n"])
                release()

        return self.rows.drop("build_s").mapInArrow(run, "shard int, orient string, n long")

    def size(self) -> DataFrame:
        """Rows ``orient, edges, bytes`` over all shards."""
        parts = [self.rows.agg(F.sum(f"{o}_edges").alias("edges"), F.sum(F.octet_length(o)).cast("long").alias("bytes")).select(F.lit(o).alias("orient"), "edges", "bytes") for o in self.orientations]
        return reduce(lambda a, b: a.unionByName(b), parts)


def build(objects: DataFrame, m: int = 16, ef_con: int = 100, orientations: Iterable[str] = tuple(ORIENTATIONS), shard_rows: int = SHARD_ROWS, small: int = SMALL, graph: str = "grown", buckets: int = BUCKETS, residual: str | None = None) -> Index:
    """The labelled index over sound objects (``model.validate``); ``residual`` names a whole-number column for further filters."""
    orientations = tuple(orientations)
    spark, shards = objects.sparkSession, shard_count(objects, shard_rows)
    base = sharded(objects, shards).select("shard", "id", "vec", "l", "r", (F.col(residual) if residual else F.lit(None)).cast("long").alias("residual"))
    kind = dict(base.dtypes)["l"].replace("bigint", "long")
    schema = row_schema(kind, orientations)
    tasks = max(1, min(8 * len(orientations), spark.sparkContext.defaultParallelism // shards))
    groups = max(1, tasks // len(orientations))  # of levels
    part = pa.schema([("shard", pa.int32()), ("orient", pa.string()), ("level", pa.int32()), ("edges", pa.binary()), ("cuts", pa.binary()), ("build_s", pa.float64())])

    def levels(s: Shard, orient: str, group: int) -> list[dict]:
        """A tree's levels of one group; the first levels, which cost most, are groups of their own."""
        start = time.perf_counter()
        domain, out = Domain(s, orient, buckets), []
        for j in range(domain.height + 1):
            if (j if j < groups else groups - 1 - (j - groups) % max(1, groups - 1)) == group:
                e = level_edges(s, domain, j, m, ef_con, small, graph)
                e = e[np.lexsort((e[:, 2], e[:, 1]))].astype(np.int32)
                now = time.perf_counter()
                out.append({"orient": orient, "level": j, "edges": pack_array(e[:, 1:].T), "cuts": pack_array(domain.cuts) if j == 0 else None, "build_s": now - start})
                start = now
        return out

    def merged(s: Shard, orient: str, found: list[dict]) -> dict:
        own = sorted(found, key=lambda f: f["level"])
        return edge_columns(orient, Edges.merged(len(s), [tuple(np.frombuffer(f["edges"], np.int32).reshape(4, -1)) for f in own]), own[0]["cuts"])

    def packed(s: Shard, found: list[dict]) -> dict:
        row = {"build_s": sum(f["build_s"] for f in found)}
        for o in orientations:
            row |= merged(s, o, [f for f in found if f["orient"] == o])
        return row

    def arrow(row: dict) -> pa.Table:
        return pa.Table.from_pylist([row], schema=pa.schema([(n, t) for n, t, _ in schema]))

    def residuals(t: pa.Table) -> np.ndarray | None:
        if residual is None:
            return None
        ids = np.asarray(t.column("id").combine_chunks())
        return np.asarray(t.column("residual").combine_chunks().fill_null(np.iinfo(np.int64).min))[np.argsort(ids, kind="stable")]

    def whole(t: pa.Table) -> pa.Table:
        """A shard's row by one task."""
        s = shard_of(t)
        row = member_row(s, s, t.column("shard")[0].as_py(), residuals(t)) | {"build_s": 0.0}
        for o in orientations:  # one at a time, so that only one's levels are held
            found = [f for g in range(groups) for f in levels(s, o, g)]
            row |= merged(s, o, found) | {"build_s": row["build_s"] + sum(f["build_s"] for f in found)}
            del found
            release()
        return arrow(row)

    if tasks == 1:
        return Index(staged(each_alone(base, "shard", shards).groupBy("shard").applyInArrow(whole, ddl(schema)), "index"), m, ef_con, small, orientations, kind)

    def some(t: pa.Table) -> pa.Table:
        unit = t.column("work")[0].as_py()
        found = levels(shard_of(t), orientations[unit // groups % len(orientations)], unit % groups)
        return pa.Table.from_pylist([{"shard": t.column("shard")[0].as_py(), **f} for f in found], schema=part)

    each = len(orientations) * groups
    split = base.withColumn("work", F.explode(F.sequence(F.lit(0), F.lit(each - 1)))).withColumn("unit", F.col("shard") * each + F.col("work"))
    grown = each_alone(split, "unit", shards * each).groupBy("unit").applyInArrow(some, "shard int, orient string, level int, edges binary, cuts binary, build_s double")

    def join(members: pa.Table, found: pa.Table) -> pa.Table:
        s = shard_of(members)
        return arrow(member_row(s, s, members.column("shard")[0].as_py(), residuals(members)) | packed(s, found.to_pylist()))

    made = base.groupBy("shard").cogroup(staged(grown, "levels").groupBy("shard")).applyInArrow(join, ddl(schema))
    return Index(staged(made, "index"), m, ef_con, small, orientations, kind)


def concerned(queries: DataFrame, boxes: list[Box]) -> Column:
    """Which shards any of the queries can concern, from the shards' ranges and the queries' extremes."""
    q = queries.agg(F.min("lq").alias("lq_min"), F.max("lq").alias("lq_max"), F.min("rq").alias("rq_min"), F.max("rq").alias("rq_max")).first()
    if q.lq_min is None:
        return F.lit(False)
    terms = []
    for b in boxes:
        attribute, order, key = ORIENTATIONS[b.orient]
        t = F.lit(True)
        if b.version:
            t &= F.col(f"{attribute}_min") <= q[f"{b.version}_max"] if order > 0 else F.col(f"{attribute}_max") >= q[f"{b.version}_min"]
        if b.low:
            t &= F.col(f"{key}_max") >= q[f"{b.low}_min"]
        if b.high:
            t &= F.col(f"{key}_min") <= q[f"{b.high}_max"]
        terms.append(t)
    return reduce(lambda a, b: a | b, terms)


def concerns(box: Box, lq, rq, row: dict) -> bool:
    """Whether a query's box can hold an object of a shard."""
    ends = {"lq": lq, "rq": rq}
    attribute, order, key = ORIENTATIONS[box.orient]
    if box.version and (row[f"{attribute}_min"] > ends[box.version] if order > 0 else row[f"{attribute}_max"] < ends[box.version]):
        return False
    return not (box.low and row[f"{key}_max"] < ends[box.low]) and not (box.high and row[f"{key}_min"] > ends[box.high])


def met(s: Shard, asked: list[tuple], mask: int) -> list[tuple]:
    """The queries that the ranges of a shard leave open."""
    ranges = {f"{c}_{n}": f(x) for c, x in (("l", s.left), ("r", s.right)) for n, f in (("min", np.min), ("max", np.max))}
    return [a for a in asked if any(concerns(b, *a[2:], ranges) for b in plan(mask))]


def opened(row: dict, index_m: int, small: int, number: type, boxes: list[Box]) -> tuple[Shard, dict[str, Oriented]]:
    """A shard of the index and those of its trees that the boxes need."""
    s = row_shard(row, number)
    return s, {o: row_tree(row, s, o, index_m, small) for o in sorted({b.orient for b in boxes})}


def answers(row: dict, s: Shard, trees: dict[str, Oriented], boxes: list[Box], asked: list[tuple], k: int, ef: int, mode: str = "layered", exact_below: int = 0, residual: int | None = None, check: bool = False) -> list[tuple]:
    """A shard's best k of each query, and the work of each box, as rows of ``_FOUND``."""
    if residual is None and not check and not exact_below and not any(b.residual for b in boxes):
        return together(row, s, trees, boxes, asked, k, ef, mode)
    extra = None if residual is None else np.frombuffer(row["residual"], np.int64) == residual
    rows = []
    for qid, q, lq, rq in [*asked[:WARM_UP], *asked]:
        start = time.perf_counter()
        best: dict[int, float] = {}
        total = [0] * len(WORK)
        for b in boxes:
            if concerns(b, lq, rq, row):
                marks = extra
                if b.residual:
                    marks = s.left == lq if extra is None else extra & (s.left == lq)
                got, w = trees[b.orient].find(q, *trees[b.orient].bounds(b, lq, rq), k, ef, mode, exact_below, marks, check)
                best |= {r: d for d, r in got}
                total = [a + getattr(w, c) for a, c in zip(total, WORK, strict=True)]
        top = sorted((d, s.ids[r]) for r, d in best.items())[:k]
        if check and len(top) == k:
            best = {r: d for r, d in best.items() if d <= margin(top[-1][0])}
        rows.append((qid, None, None, *total, time.perf_counter() - start))
        top = [(float(np.sqrt(d)), i) for d, i in top]
        if check:
            own = np.fromiter(best, np.int64, len(best))
            top = sorted(zip(np.sqrt(summed(s.vectors[own], q)).tolist(), s.ids[own].tolist(), strict=True))[:k]
        rows += [(qid, int(i), d, *[0] * len(WORK), 0.0) for d, i in top]
    warm = sum(r[1] is None for r in rows) - len(asked)
    at = [i for i, r in enumerate(rows) if r[1] is None]
    return rows[at[warm] :] if warm < len(at) else []


def together(row: dict, s: Shard, trees: dict[str, Oriented], boxes: list[Box], asked: list[tuple], k: int, ef: int, mode: str) -> list[tuple]:
    """``answers`` without further conditions: the queries of a block walk together, and share its time."""
    rows: list[tuple] = []
    open_, bound = {}, {}  # equal intervals have the same boxes and bounds
    for _, _, lq, rq in asked:
        if (lq, rq) not in open_:
            open_[lq, rq] = [b for b in boxes if concerns(b, lq, rq, row)]
            bound |= {(b, lq, rq): trees[b.orient].bounds(b, lq, rq) for b in open_[lq, rq]}
    near = [open_[a[2:]] for a in asked]
    met = [i for i, b in enumerate(near) if b]
    step = block_of(len(s))
    blocks = [met[a : a + step] for a in range(0, len(met), step)]
    for turn, block in enumerate([met[:WARM_UP], *blocks]):
        start = time.perf_counter()
        best, total = {i: {} for i in block}, {i: [0] * len(WORK) for i in block}
        for b in boxes:
            own = [i for i in block if b in near[i]]
            if own:
                for i, (got, w) in zip(own, trees[b.orient].find_many(np.array([asked[i][1] for i in own]), [bound[b, *asked[i][2:]] for i in own], k, ef, mode), strict=True):
                    best[i] |= {r: d for d, r in got}
                    total[i] = [a + getattr(w, c) for a, c in zip(total[i], WORK, strict=True)]
        tops = [nearest_of(best[i], s.ids, k) for i in block]
        took = (time.perf_counter() - start) / max(1, len(block))
        if turn:
            for i, top in zip(block, tops, strict=True):
                rows.append((asked[i][0], None, None, *total[i], took))
                rows += [(asked[i][0], int(r), float(np.sqrt(d)), *[0] * len(WORK), 0.0) for d, r in top]
    return rows + [(a[0], None, None, *[0] * len(WORK), 0.0) for a, b in zip(asked, near, strict=True) if not b]


def nearest_of(found: dict[int, float], ids: np.ndarray, k: int) -> list[tuple[float, int]]:
    """The k nearest of the found rows as (distance, id)."""
    most = sorted(found.values())[:k]
    return sorted((d, int(ids[r])) for r, d in found.items() if d <= most[-1])[:k]


def found_batch(rows: list[tuple], names: list[str] = _FOUND_NAMES) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [()] * len(names)
    return pa.RecordBatch.from_arrays([pa.array(c, pa.float64() if n in _FLOATS else pa.int64()) for n, c in zip(names, columns, strict=True)], names=names)


def search(index: Index, queries: DataFrame, mask: int | None = None, k: int = 10, ef: int = 100, boxes: list[Box] | None = None, mode: str = "layered", exact_below: int = 0, atomic: bool = False, residual: int | None = None, check: bool = False) -> DataFrame:
    """Rows ``qid, id, dist`` and the work of every shard's walk, before the merge.

    A walk may miss a near object: its width ends it, and pruned graphs do not reach every member.  With ``check`` each walk is followed by an
    exact check of the other qualifying members against its k-th distance, and the answers are those of exact search.

    ``boxes`` overrides the mask's plan (Allen's relations); with ``residual`` only objects of that value of the index' further column count.
    """
    boxes = boxes or (atomic_plan(mask) if atomic else plan(mask))
    return looked_up(index, queries, boxes, _FOUND, lambda row, s, trees, asked: [found_batch(answers(row, s, trees, boxes, asked, k, ef, mode, exact_below, residual, check))])


def looked_up(index: Index, queries: DataFrame, boxes: list[Box], schema: str, look: Callable[[dict, Shard, dict[str, Oriented], list[tuple]], Iterable[pa.RecordBatch]]) -> DataFrame:
    """What ``look`` makes of each shard that the queries can concern, its trees, and the queries; only orientations that the boxes need are read."""
    needed = sorted({b.orient for b in boxes})
    if missing := set(needed) - set(index.orientations):
        raise ValueError(f"the index has no orientation {sorted(missing)}")
    queries = numbered(queries.select("qid", "qvec", "lq", "rq"), "lq", "rq")
    m, small, number = index.m, index.small, np.float64 if index.kind == "double" else np.int64
    others = [c for o in index.orientations if o not in needed for c in (o, f"{o}_cuts", f"{o}_edges")]
    out = None
    for block in query_blocks(queries):
        asked = [(r.qid, np.array(r.qvec, float), r.lq, r.rq) for r in block.collect()]  # at most QUERY_ROWS
        shared = queries.sparkSession.sparkContext.broadcast(asked)

        def run(batches: Iterable[pa.RecordBatch], shared=shared):
            for row in each_row(batches):
                s, trees = opened(row, m, small, number, boxes)
                yield from look(row, s, trees, shared.value)
                del s, trees
                release()

        part = index.rows.where(concerned(block, boxes)).drop("build_s", *others).mapInArrow(run, schema)
        out = part if out is None else out.unionByName(part)
    return out


def scan(objects: DataFrame, queries: DataFrame, mask: int | None, k: int = 10) -> DataFrame:
    """``exact.knn_exact`` without rounding, by matrix products where the objects are: what may be among a batch's k nearest is measured as SQL does."""
    objects = numbered(objects.select("id", "vec", "l", "r"), "l", "r")
    out = None
    for block in query_blocks(numbered(queries.select("qid", "qvec", "lq", "rq"), "lq", "rq")):
        asked = [(r.qid, np.array(r.qvec, float), r.lq, r.rq) for r in block.collect()]  # at most QUERY_ROWS
        shared = objects.sparkSession.sparkContext.broadcast(asked)

        def run(batches: Iterable[pa.RecordBatch], shared=shared):
            for batch in batches:
                if batch.num_rows:
                    s = shard_of(pa.Table.from_batches([batch]))
                    for a in range(0, len(shared.value), SCANNED):
                        yield scanned(s, shared.value[a : a + SCANNED], mask, k)

        part = objects.mapInArrow(run, "qid long, id long, dist double")
        out = part if out is None else out.unionByName(part)
    return top_k(out, k, None)


def scanned(s: Shard, asked: list[tuple], mask: int | None, k: int) -> pa.RecordBatch:
    """A batch's k nearest qualifying objects of each query, and what is as near up to rounding."""
    q, square = np.array([a[1] for a in asked]), np.einsum("ij,ij->i", s.vectors, s.vectors)
    own = np.einsum("ij,ij->i", q, q)
    d = np.maximum(own[:, None] + square[None, :] - 2 * (q @ s.vectors.T), 0)
    if mask is not None:
        d[~qualifies(mask, s.left, s.right, np.array([a[2] for a in asked])[:, None], np.array([a[3] for a in asked])[:, None])] = np.inf
    worst = np.partition(d, k - 1, axis=1)[:, k - 1] if len(s) > k else np.full(len(q), np.inf)
    at, row = np.nonzero((d <= (margin(worst) + 1e-9 * (own + square.max()))[:, None]) & np.isfinite(d))
    dist = np.sqrt(summed(s.vectors[row], q[at].T)) if len(row) else np.zeros(0)
    return pa.RecordBatch.from_arrays([pa.array(np.array([a[0] for a in asked], np.int64)[at]), pa.array(s.ids[row]), pa.array(dist)], names=["qid", "id", "dist"])


def merge(found: DataFrame, k: int, digits: int | None = 6) -> DataFrame:
    """The best k of all shards, an id once a query."""
    return top_k(found.where(F.col("id").isNotNull()).groupBy("qid", "id").agg(F.min("dist").alias("dist")), k, digits)


def work(found: DataFrame) -> DataFrame:
    """Rows ``qid`` with the work of all walks."""
    return found.groupBy("qid").agg(*[F.sum(c).alias(c) for c in WORK])


def rrknn(index: Index, queries: DataFrame, mask: int, k: int = 10, ef: int = 100, digits: int | None = 6, **options) -> DataFrame:
    """The k nearest objects by the index: at most two boxes, one job."""
    return merge(search(index, queries, mask, k, ef, **options), k, digits)


_RUN_NAMES = ["ef", *_FOUND_NAMES, "build_s", "edge_count", "bytes"]
_RUN = "ef long, " + _FOUND + ", build_s double, edge_count long, bytes long"
#: What an index of its own can do of the versioned tree; other variants are built by one task a shard.
_INDEXED = {"orientations", "m", "ef_con", "small", "graph", "buckets", "mode", "exact_below"}


def run_method(objects: DataFrame, queries: DataFrame, method: str, mask: int, k: int = 10, efs: Iterable[int] = (100,), shard_rows: int = SHARD_ROWS, repeats: int = 1, made: dict | None = None, keep: bool = False, **options) -> DataFrame:
    """Any method of ``METHODS``, built once and searched at each width; rows as of ``search`` with ``ef``, and a row a shard and width with null qid that has build seconds, edges and bytes.

    ``search_s`` is the mean of ``repeats`` runs after a warm-up; queries of a block are searched together and share its time.  The queries are broadcast in checked blocks.
    ``made`` keeps indexes and dealt objects for further runs over the same objects, with ``keep`` also what the other methods built.  Shards in whose ranges nothing can qualify are not searched.
    """
    efs, made = tuple(efs), {} if made is None else made
    if method in ("vtg", "atomic_union") and set(options) <= _INDEXED:
        how = {a: b for a, b in options.items() if a not in ("mode", "exact_below")}
        key = (shard_rows, *sorted(how.items()))
        if key not in made:
            made[key] = build(objects, shard_rows=shard_rows, **how)
        index = made[key]
        looks = {a: b for a, b in options.items() if a in ("mode", "exact_below")}
        none = lambda names, kind: [F.lit(None).cast(kind).alias(c) for c in names]
        edges = sum(F.col(f"{o}_edges") for o in index.orientations)
        size = sum(F.octet_length(o).cast("long") for o in index.orientations)
        costs = ["build_s", "edge_count", "bytes"]
        width = F.explode(F.array(*[F.lit(ef).cast("long") for ef in efs])).alias("ef")
        built = index.rows.select(width, *none(["qid", "id"], "long"), *none(["dist"], "double"), *[F.lit(0).cast("long").alias(c) for c in WORK], F.lit(0.0).alias("search_s"), "build_s", edges.alias("edge_count"), size.alias("bytes")).select("ef", *_FOUND_NAMES, *costs)
        boxes = atomic_plan(mask) if method == "atomic_union" else plan(mask)

        def look(row: dict, s: Shard, trees: dict[str, Oriented], asked: list[tuple]) -> Iterator[pa.RecordBatch]:
            for ef in efs:
                rows = answers(row, s, trees, boxes, asked, k, ef, **looks)
                took = {r[0]: r[-1] for r in rows if r[1] is None}
                for _ in range(repeats - 1):
                    for r in answers(row, s, trees, boxes, asked, k, ef, **looks):
                        if r[1] is None:
                            took[r[0]] += r[-1]
                yield found_batch([(ef, *r[:-1], took[r[0]] / repeats if r[1] is None else 0.0, 0.0, 0, 0) for r in rows], _RUN_NAMES)

        return built.unionByName(looked_up(index, queries, boxes, _RUN, look))
    if ("dealt", shard_rows) not in made:
        shards = shard_count(objects, shard_rows)
        made["dealt", shard_rows] = sharded(objects, shards).select("shard", "id", "vec", "l", "r"), shards
    base, shards = made["dealt", shard_rows]
    if keep:
        key = (method, shard_rows, *sorted(options.items()))
        if key not in made:
            made[key] = staged(_built(each_alone(base, "shard", shards), method, options), "built")
        base = made[key]
    else:
        base = each_alone(base, "shard", shards)
    parts = [_run_block(base, q, method, mask, k, efs, repeats, options, keep) for q in query_blocks(numbered(queries.select("qid", "qvec", "lq", "rq"), "lq", "rq"))]
    return reduce(lambda a, b: a.unionByName(b), parts)


def _built(base: DataFrame, method: str, options: dict) -> DataFrame:
    """A row a shard with what the method built."""

    def build(t: pa.Table) -> pa.Table:
        return pa.table([pa.array([pickle.dumps(METHODS[method](**options).build(shard_of(t)))], pa.binary())], names=["built"])

    return base.groupBy("shard").applyInArrow(build, "built binary")


def _run_block(base: DataFrame, queries: DataFrame, method: str, mask: int, k: int, efs: tuple[int, ...], repeats: int, options: dict, kept: bool = False) -> DataFrame:
    asked = base.sparkSession.sparkContext.broadcast([(r.qid, np.array(r.qvec, float), r.lq, r.rq) for r in queries.collect()])

    def look(made: Method) -> Iterator[pa.RecordBatch]:
        own = met(made.shard, asked.value, mask) if made.filters else asked.value
        step = block_of(len(made.shard))
        for ef in efs:
            rows = []
            if own:
                made.search_many([a[1:] for a in own[:WARM_UP]], mask, k, ef)
            for at in range(0, len(own), step):
                block = own[at : at + step]
                start = time.perf_counter()
                for _ in range(repeats):
                    found = made.search_many([a[1:] for a in block], mask, k, ef)
                took = (time.perf_counter() - start) / repeats / len(block)
                for (qid, *_), (near, d, w) in zip(block, found, strict=True):
                    rows.append((ef, qid, None, None, *(getattr(w, c) for c in WORK), took, 0.0, 0, 0))
                    rows += [(ef, qid, int(made.shard.ids[r]), float(np.sqrt(x)), *[0] * len(WORK), 0.0, 0.0, 0, 0) for r, x in zip(near, d, strict=True)]
            rows.insert(0, (ef, None, None, None, *[0] * len(WORK), 0.0, made.build_s, made.edge_count, made.size))
            yield found_batch(rows, _RUN_NAMES)

    def run(t: pa.Table) -> pa.Table:
        return pa.Table.from_batches(list(look(METHODS[method](**options).build(shard_of(t)))))

    def again(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in each_row(batches):
            yield from look(pickle.loads(row["built"]))
            release()

    return base.mapInArrow(again, _RUN) if kept else base.groupBy("shard").applyInArrow(run, _RUN)


def nearest_first(found: DataFrame) -> DataFrame:
    """The nearest object of each query, without a window."""
    return found.groupBy("qid").agg(F.min_by("id", F.struct("dist", "id")).alias("id"), F.min("dist").alias("dist"))
