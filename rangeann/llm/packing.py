"""Packing of documents into token sequences: large-item matching, then best fit.

Pieces above a third of the capacity go at most two to a sequence, matched greedily from the
largest down with the largest partner that fits; smaller pieces, from the largest down, fill
the tightest gap that holds them.  The plan depends only on how many pieces have each length,
so it is made on the driver from at most ``capacity`` counts, as groups of equal sequences;
its size is bounded by the number of lengths, not by the number of documents (each group that
a length fills is left with under half its gap, so about 2 * capacity groups are touched
log2(capacity) times at most).  Every piece then finds its place by its rank among the pieces of
its length.  Ranks come from counts a salt, then a running number within (length, salt), so no
length is gathered in one task however many pieces share it.

Cases: null or empty text has the closing id alone, one piece of length 1; a document longer
than the capacity is cut, others never; repeated rows are packed each; an empty table gives
an empty result; other columns of the input are ignored; a null id stays null.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangeann.llm.common import column_slices, release, staged
from rangeann.llm.tokens import SUB_BATCH_BYTES, Lookup, read_vocabulary

ROWS_PER_SALT, MOST_SALTS = 4_096, 65_536
PIECES = "piece int, start long, length long, ids_crc32 long"


def pieces(docs: DataFrame, vocabulary_path: str, capacity: int = 4096, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False, cache_entries: int | None = None) -> DataFrame:
    """Each document's ids and the closing id, cut at ``capacity`` only if longer; ``cache_entries`` bounds a worker's cache of pre-tokens."""
    vocabulary = docs.sparkSession.sparkContext.broadcast(read_vocabulary(vocabulary_path))
    end, width = end_id.to_bytes(4, "little"), 4 * capacity

    def cut(batches):
        look = Lookup(vocabulary.value, {}, True, cache_entries)
        for batch in batches:
            ids = batch.column(0).cast(pa.int64()).to_pylist()
            for a, b, texts in column_slices(batch, text_col, SUB_BATCH_BYTES):
                rows = []
                stream, starts = look.streams(texts)
                for doc, i, j in zip(ids[a:b], starts.tolist(), starts[1:].tolist(), strict=False):
                    data = stream[i:j].tobytes() + end
                    for k, at in enumerate(range(0, len(data), width)):
                        part = data[at : at + width]
                        rows.append((doc, k, at // 4, len(part) // 4, zlib.crc32(part), part))
                columns = list(zip(*rows, strict=True))
                arrays = [pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=False)]
                if with_ids:
                    arrays.append(pa.array([np.frombuffer(x, "<u4").astype(np.int64) for x in columns[5]], pa.list_(pa.int64())))
                yield pa.RecordBatch.from_arrays(arrays, names=[id_col, "piece", "start", "length", "ids_crc32", *["ids"] * with_ids])
                del stream, rows, columns, arrays
            release()

    return docs.select(F.col(id_col).cast("long"), text_col).mapInArrow(cut, f"`{id_col}` long, {PIECES}" + ", ids array<long>" * with_ids)


class _Groups:
    """Groups of equal sequences, by the gap that each of them has left."""

    def __init__(self):
        self.at: dict[int, list[list]] = {}
        self.gaps: list[int] = []

    def add(self, gap: int, many: int, content: list[tuple[int, int]]) -> None:
        if many:
            if gap not in self.at:
                insort(self.gaps, gap)
                self.at[gap] = []
            self.at[gap].append([many, content])

    def tightest(self, size: int):
        """Takes out a group of the smallest gap that holds ``size``."""
        k = bisect_left(self.gaps, size)
        if k == len(self.gaps):
            return None
        gap = self.gaps[k]
        many, content = self.at[gap].pop()
        if not self.at[gap]:
            del self.at[gap]
            del self.gaps[k]
        return gap, many, content


def plan(counts: Mapping[int, int], capacity: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Groups ``(sequences, [(length, how many in each), ...])`` that hold ``counts`` pieces of each length."""
    left, groups = dict(counts), _Groups()
    large = sorted((n for n in left if 3 * n > capacity), reverse=True)
    rising = large[::-1]
    for n in large:
        while left[n]:
            k = bisect_left(rising, capacity - n + 1) - 1  # the largest partner that fits
            while k >= 0 and not left[rising[k]]:
                k -= 1
            mate = rising[k] if k >= 0 else None
            if mate is None or (mate == n and left[n] == 1):
                mate = next((m for m in rising[k::-1] if m < n and left[m]), None) if mate == n else None
            if mate is None:
                groups.add(capacity - n, left[n], [(n, 1)])
                left[n] = 0
            elif mate == n:
                pairs = left[n] // 2
                groups.add(capacity - 2 * n, pairs, [(n, 2)])
                left[n] -= 2 * pairs
            else:
                pairs = min(left[n], left[mate])
                groups.add(capacity - n - mate, pairs, [(n, 1), (mate, 1)])
                left[n] -= pairs
                left[mate] -= pairs
    for n in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        todo = left[n]
        while todo:
            gap, many, content = groups.tightest(n) or (capacity, -(-todo // (capacity // n)), [])
            each = gap // n
            full = min(many, todo // each)
            groups.add(gap - each * n, full, [*content, (n, each)])
            todo -= full * each
            if full < many:
                if todo:  # fewer than one sequence takes
                    groups.add(gap - todo * n, 1, [*content, (n, todo)])
                    full, todo = full + 1, 0
                groups.add(gap, many - full if content else 0, content)
    return [(many, content) for at in groups.at.values() for many, content in at]


def places(groups: list[tuple[int, list[tuple[int, int]]]]) -> np.ndarray:
    """Rows ``length, first rank, first sequence, offset, how many in each``, by length and first rank."""
    rows, ranks, base = [], {}, 0
    for many, content in groups:
        offset = 0
        for n, each in content:
            first = ranks.get(n, 0)
            rows.append((n, first, base, offset, each))
            ranks[n] = first + many * each
            offset += n * each
        base += many
    return np.array(sorted(rows), np.int64).reshape(-1, 5)


def pack_pieces(found: DataFrame, capacity: int, id_col: str = "doc_id") -> DataFrame:
    """``found`` (of ``pieces``, read more than once, so written before) with ``sequence_id`` and ``offset``."""
    spark = found.sparkSession
    by_length = {r.length: r.n for r in found.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most capacity rows
    table = spark.sparkContext.broadcast(places(plan(by_length, capacity)))
    salts = min(MOST_SALTS, max(1, -(-sum(by_length.values()) // ROWS_PER_SALT)))
    salted = found.withColumn("salt", F.pmod(F.xxhash64(id_col, "piece"), F.lit(salts)).cast("long"))
    before = salted.groupBy("length", "salt").agg(F.count("*").alias("n")).select("length", "salt", (F.sum("n").over(Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")).alias("before"))
    ranked = salted.withColumn("rank", F.row_number().over(Window.partitionBy("length", "salt").orderBy(id_col, "piece", "ids_crc32")) - 1).join(before, ["length", "salt"]).withColumn("rank", F.col("rank") + F.col("before")).drop("salt", "before")

    def place(batches):
        at = table.value
        keys = (at[:, 0] << 44) | at[:, 1]
        for batch in batches:
            length, rank = (np.asarray(batch.column(batch.schema.get_field_index(c))) for c in ("length", "rank"))
            row = at[np.searchsorted(keys, (length.astype(np.int64) << 44) | rank, side="right") - 1]
            k = rank - row[:, 1]
            names = [n for n in batch.schema.names if n != "rank"]
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(n)) for n in names), pa.array(row[:, 2] + k // row[:, 4]), pa.array(row[:, 3] + length * (k % row[:, 4]))], names=[*names, "sequence_id", "offset"])

    kept = [c for c in found.columns]
    kinds = dict(found.dtypes)
    return ranked.select(*kept, "rank").mapInArrow(place, ", ".join(f"`{c}` {kinds[c]}" for c in kept) + ", sequence_id long, offset long")


def pack(docs: DataFrame, vocabulary_path: str, capacity: int = 4096, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False, cache_entries: int | None = None) -> DataFrame:
    """A row a piece: its document, place in it, sequence and place there, and with ``with_ids`` its ids."""
    return pack_pieces(staged(pieces(docs, vocabulary_path, capacity, end_id, id_col, text_col, with_ids, cache_entries), "pieces"), capacity, id_col)
