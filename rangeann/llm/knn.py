"""Exact top-k search by a Voronoi join.

Scores are integer inner products of vectors whose components x are taken as floor(64 * x).  One
more coordinate, sqrt(M - |v|^2) for data and 0 for queries (M the largest squared length), turns
the largest product into the least Euclidean distance, so the triangle inequality holds.  A
bounded sample gives the pivots; each vector belongs to the cell of its nearest pivot.  From
summaries of the cells (how many vectors, how far, the k + 1 nearest ids to the pivot) every query cell
gets a bound that holds the k-th distance of all its queries.  A vector serves a query cell only if
|p_i p_j| - radius of the queries - its own distance is within that cell's bound, and goes only to those groups of
query cells that it serves.  A group's queries and the data, in blocks, are both sized by ``UNIT_BYTES``, so that a
task holds one group and one block whatever the table's size, and data cross the exchange once a group, not once a
cell; within a unit each cell's queries meet only the vectors that serve them.  The blocks' best k are merged.

On vectors spread evenly over a sphere no bound excludes anything; on clustered ones most pairs are left out.

Products are exact: in floating point as long as no sum can pass its whole numbers, beyond that by error
bounds and whole-number arithmetic for all candidates that the bounds leave.

Cases: vectors that are null or hold null or non-finite components (or such that 64 * x is not finite) take no part, nor do null ids;
shorter vectors are read as if zeros followed; candidates are all rows of another id than the
query's; repeated rows of one query count once, repeated candidates each; ties go to the smaller
id; scores beyond a long count as the nearest long, also in the ranking; with fewer than k candidates all are
returned; empty tables give no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangeann.llm.common import staged

PIVOTS = 64
UNIT_BYTES = 64 << 20  # of a block's vectors as floats; a group of queries has a quarter
GROUP_QUERIES = BLOCK_ROWS = None  # rows a unit; by UNIT_BYTES unless set
SLACK = 1e-6  # of a bound, for rounding
WHOLE = 2.0**53  # floats below are exact
LONGS = (-(2**63), 2**63 - 1)


def whole(vec: str, scale: int) -> Column:
    """floor(scale * x) as doubles, which from 2^52 on are whole."""
    y = lambda x: F.lit(float(scale)) * x.cast("double")
    return F.transform(vec, lambda x: F.when(F.abs(y(x)) < 2.0**52, F.floor(y(x)).cast("double")).otherwise(y(x)))


def fit_for_search(df: DataFrame, is_query: Column, id_col: str, vec_col: str, scale: int) -> DataFrame:
    """Rows ``id, v, query`` of the vectors that take part."""
    finite = F.forall(vec_col, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double") * scale) < float("inf")))
    return df.where(F.col(id_col).isNotNull() & F.col(vec_col).isNotNull() & (F.size(vec_col) > 0) & finite).select(F.col(id_col).cast("long").alias("id"), whole(vec_col, scale).alias("v"), F.coalesce(is_query, F.lit(False)).alias("query"))


def rows_of(batch: pa.RecordBatch, width: int) -> np.ndarray:
    """The vectors as rows of one matrix."""
    column = batch.column(batch.schema.get_field_index("v"))
    ends = np.asarray(column.offsets)
    flat = np.asarray(column.values)[ends[0] : ends[-1]]
    if len(column) and (np.diff(ends) == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(column), width))
    for row, a, b in zip(out, ends - ends[0], ends[1:] - ends[0], strict=False):
        row[: b - a] = flat[a:b]
    return out


def carrier(most: float) -> type:
    """The least number type for components up to ``most``."""
    return next((t for t in (np.int8, np.int16, np.int32) if most <= np.iinfo(t).max), np.float64)


class Cells:
    """Pivots with one coordinate more, and distances to them, all in units of ``2 ** shift``."""

    def __init__(self, sample: list[np.ndarray], width: int, most: float, largest: float):
        self.width, self.shift = width, max(0, math.frexp(most)[1] - 400)
        top = math.ldexp(most, -self.shift)
        self.largest = math.ldexp(largest, -2 * self.shift) if math.isfinite(largest) else width * top * top
        self.pivots = np.zeros((len(sample), width + 1))
        for row, v in zip(self.pivots, sample, strict=True):
            row[: len(v)] = np.ldexp(v, -self.shift)
        self.pivots[:, width] = self.rest(self.pivots[:, :width])
        self.between = np.sqrt(np.maximum(0, ((self.pivots[:, None, :] - self.pivots[None, :, :]) ** 2).sum(axis=2)))

    def rest(self, x: np.ndarray) -> np.ndarray:
        return np.sqrt(np.maximum(0, self.largest - (x**2).sum(axis=1)))

    def nearest(self, x: np.ndarray, query: bool) -> tuple[np.ndarray, np.ndarray]:
        """Each row's cell and its distance to the pivot."""
        x = np.ldexp(x.astype(np.float64), -self.shift)
        full = np.column_stack([x, np.zeros(len(x)) if query else self.rest(x)])
        square = (full**2).sum(axis=1)[:, None] + (self.pivots**2).sum(axis=1)[None, :] - 2 * full @ self.pivots.T
        d = np.sqrt(np.maximum(square, 0))
        cell = d.argmin(axis=1)
        return cell, d[np.arange(len(x)), cell]

    def serves(self, i: int, far: float, bound: float, home: np.ndarray, own: np.ndarray) -> np.ndarray:
        """Which vectors may be among the best of a query of cell ``i``."""
        return self.between[i, home] - far - own <= bound + SLACK * (bound + math.sqrt(self.largest) + 1)


def best_of(score: np.ndarray, n: int) -> np.ndarray:
    """Places of the n largest, ties to the first."""
    edge = np.partition(score, -n)[-n]
    above, level = np.flatnonzero(score > edge), np.flatnonzero(score == edge)
    return np.concatenate([above, level[: n - len(above)]])


def exact_best(q: np.ndarray, s: np.ndarray, norms: np.ndarray, shift: int, own: slice, n: int) -> tuple[np.ndarray, list[int]]:
    """``best_of`` for products that floats cannot hold: error bounds, then whole numbers for what they leave."""
    a = np.ldexp(q, -shift)
    about = np.ldexp(s, -shift) @ a
    error = (len(q) + 4) * 2.0**-51 * norms * np.sqrt(a @ a) + 2.0**-1000
    low, high = (np.clip(about + e, math.ldexp(LONGS[0], -2 * shift), math.ldexp(LONGS[1], -2 * shift)) for e in (-error, error))
    low[own] = high[own] = -np.inf
    left = np.flatnonzero(high >= np.partition(low, -n)[-n])
    left = left[np.isfinite(high[left])]
    numbers = [int(x) for x in q]
    value = [min(max(sum(x * int(y) for x, y in zip(numbers, s[j].tolist(), strict=True)), LONGS[0]), LONGS[1]) for j in left]
    order = sorted(range(len(left)), key=lambda i: (-value[i], i))[:n]
    return left[order], [value[i] for i in order]


def top_k(df: DataFrame, is_query: Column, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 64, pivots: int = PIVOTS) -> DataFrame:
    """Rows ``query_id, rank, vec_id, score``: each query's k best of all other rows."""
    spark = df.sparkSession
    schema = "query_id long, rank int, vec_id long, score long"
    base = staged(fit_for_search(df, is_query, id_col, vec_col, scale), "vectors")
    shape = base.agg(F.count("*").alias("n"), F.max(F.size("v")).alias("width"), F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)).alias("m"), F.max(F.array_max(F.transform("v", F.abs))).alias("most")).first()
    if not shape.n:
        return spark.createDataFrame([], schema)
    width, most = shape.width, shape.most
    sample = base.orderBy(F.xxhash64("id"), "id").limit(pivots).select("v").distinct().orderBy("v").collect()  # at most ``pivots`` rows
    made = spark.sparkContext.broadcast(Cells([np.array(r.v) for r in sample], width, most, float(shape.m)))
    kind, top = carrier(most), width * most * most
    number = np.float32 if top < 2**24 else np.float64

    def summaries(batches: Iterable[pa.RecordBatch]):
        cells, held, near = made.value, {}, {}
        for batch in batches:
            x, ids, asks = rows_of(batch, width), np.asarray(batch.column(0)), np.asarray(batch.column(2)).astype(bool)
            for query, at in ((False, np.arange(len(x))), (True, np.flatnonzero(asks))):
                cell, d = cells.nearest(x[at], query)
                for c in np.unique(cell).tolist():
                    own = cell == c
                    n, far = held.get((c, query), (0, 0.0))
                    held[c, query] = n + int(own.sum()), max(far, float(d[own].max()))
                    if not query:
                        least = near.setdefault(c, {})
                        order = np.argsort(d[own], kind="stable")
                        for i, y in zip(ids[at][own][order].tolist(), d[own][order].tolist(), strict=True):
                            if len(least) > k and y >= max(least.values()):
                                break
                            least[i] = min(y, least.get(i, y))
                            if len(least) > k + 1:
                                del least[max(least, key=least.get)]
        rows = [(c, q, n, far, None, None) for (c, q), (n, far) in held.items()] + [(c, False, 0, 0.0, i, y) for c, least in near.items() for i, y in least.items()]
        kinds = (pa.int32(), pa.bool_(), pa.int64(), pa.float64(), pa.int64(), pa.float64())
        yield pa.RecordBatch.from_arrays([pa.array(list(a), t) for a, t in zip(list(zip(*rows, strict=True)) or [()] * 6, kinds, strict=True)], names=["cell", "query", "n", "far", "id", "d"])

    per = staged(base.mapInArrow(summaries, "cell int, query boolean, n long, far double, id long, d double").groupBy("cell", "query", "id").agg(F.sum("n").alias("n"), F.max("far").alias("far"), F.min("d").alias("d")), "cells")
    near = per.where("id IS NOT NULL").withColumn("place", F.row_number().over(Window.partitionBy("cell").orderBy("d", "id"))).where(F.col("place") <= k + 1)
    cells = per.where("id IS NULL").collect()  # at most two rows a pivot
    closest = [(r.cell, r.id, r.d) for r in near.select("cell", "id", "d").collect()]  # at most k + 1 rows a pivot
    asking = {r.cell: r for r in cells if r.query}
    if not asking:
        return spark.createDataFrame([], schema)
    between, far, bound = made.value.between, {i: q.far for i, q in asking.items()}, {}
    for i in asking:
        reach: dict[int, float] = {}
        for j, v, d in closest:
            y = far[i] + between[i, j] + d
            reach[v] = min(y, reach.get(v, y))
        bound[i] = sorted(reach.values())[k] if len(reach) > k else float("inf")  # k others besides the query itself
    most_queries = GROUP_QUERIES or max(256, UNIT_BYTES // (32 * width))
    block_rows = BLOCK_ROWS or max(1_024, UNIT_BYTES // (8 * width))
    group, held, g = {}, 0, 0
    for i in sorted(asking, key=lambda i: (between[0, i], i)):
        if held and held + asking[i].n > most_queries:
            g, held = g + 1, 0
        group[i] = g
        held += asking[i].n
    sizes = {g: sum(asking[i].n for i in asking if group[i] == g) for g in set(group.values())}
    slots = {g: max(1, -(-n // most_queries)) for g, n in sizes.items()}  # a large cell is several groups
    first = dict(zip(slots, np.cumsum([0, *slots.values()])[:-1].tolist(), strict=True))
    blocks = max(1, -(-shape.n // block_rows))

    def route(batches: Iterable[pa.RecordBatch]):
        cells = made.value
        of_cell = np.array([first[group[i]] if i in group else -1 for i in range(len(cells.pivots))])
        slots_of = np.array([slots[group[i]] if i in group else 1 for i in range(len(cells.pivots))])
        for batch in batches:
            x, ids, asks = rows_of(batch, width), np.asarray(batch.column(0)), np.asarray(batch.column(2)).astype(bool)
            home, own = cells.nearest(x, False)
            pick = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)
            parts = []
            for g, f in first.items():
                near = np.zeros(len(x), bool)
                for i in (i for i in group if group[i] == g):
                    near |= cells.serves(i, far[i], bound[i], home, own)
                at = np.flatnonzero(near)
                parts += [(np.full(len(at), f + s), pick[at] % np.uint64(blocks), at, np.zeros(len(at), bool)) for s in range(slots[g])]
            at = np.flatnonzero(asks)
            if len(at):
                cell, _ = cells.nearest(x[at], True)
                slot = of_cell[cell] + (pick[at] % slots_of[cell].astype(np.uint64)).astype(np.int64)
                parts += [(slot, np.full(len(at), b), at, np.ones(len(at), bool)) for b in range(blocks)]
            small = x.astype(kind)
            for slot, block, at, query in parts:
                if len(at):
                    yield pa.RecordBatch.from_arrays([pa.array(slot.astype(np.int64) * blocks + block.astype(np.int64)), pa.array(query), pa.array(ids[at]), pa.array([r.tobytes() for r in small[at]], pa.binary())], names=["unit", "query", "id", "v"])

    def solve(t: pa.Table) -> pa.Table:
        cells = made.value
        ids, asks = np.asarray(t.column("id")), np.asarray(t.column("query")).astype(bool)
        x = np.frombuffer(b"".join(t.column("v").to_pylist()), kind).reshape(-1, width)
        qid, once = np.unique(ids[asks], return_index=True)
        q = x[asks][once]
        order = np.argsort(ids[~asks], kind="stable")
        every_id, every = ids[~asks][order], x[~asks][order]
        out = []
        if len(q) and len(every):
            cell, _ = cells.nearest(q, True)
            home, own_distance = cells.nearest(every, False)
        for c in np.unique(cell).tolist() if len(q) and len(every) else ():
            fine = cells.serves(c, far[c], bound[c], home, own_distance)
            sid, s = (every_id, every) if fine.all() else (every_id[fine], every[fine])
            s, asked = s.astype(number), np.flatnonzero(cell == c)
            norms = np.sqrt((np.ldexp(s, -cells.shift) ** 2).sum(axis=1)) if top >= WHOLE else None
            for a in range(0, len(asked) if len(s) else 0, 64):
                rows = asked[a : a + 64]
                score = q[rows].astype(number) @ s.T if norms is None else [None] * len(rows)
                for i, row in zip(rows.tolist(), score, strict=True):
                    own = slice(*np.searchsorted(sid, [qid[i], qid[i] + 1]))
                    n = min(k, len(sid) - (own.stop - own.start))
                    if n <= 0:
                        continue
                    if norms is None:
                        row[own] = -np.inf
                        best = best_of(row, n)
                        value = row[best].astype(np.int64)
                    else:
                        best, value = exact_best(q[i].astype(np.float64), s, norms, cells.shift, own, n)
                    out.append((np.full(n, qid[i]), sid[best], np.array(value, np.int64)))
        columns = [np.concatenate(c) for c in zip(*out, strict=True)] if out else [np.zeros(0, np.int64)] * 3
        return pa.table([pa.array(c, pa.int64()) for c in columns], names=["query_id", "vec_id", "score"])

    routed = base.mapInArrow(route, "unit long, query boolean, id long, v binary")
    best = routed.groupBy("unit").applyInArrow(solve, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int"), "vec_id", "score")
