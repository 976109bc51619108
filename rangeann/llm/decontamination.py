"""Benchmark decontamination by spaced seeds.

A seed is a fixed mask over four or five successive words: the words at its ones are hashed, those
at its zeros may differ.  The hashes of every benchmark position form a table; a text's
positions that meet it (a bit table first, then a search in the sorted hashes) are hits.  Around
each hit the benchmark item and the text are compared word by word on that diagonal; the
stretch with the best score, a match counting 1 and a substitution -2, is an overlap if it has
``MATCHED`` equal words or, for a shorter item, four fifths of them.  No stretch that this rule accepts
misses all three masks: up to its ``MATCHED``-th equal word its score is never negative, so it starts with one of
a few thousand patterns of equal and other words, and a test tries them all.  Items of fewer than
four words allow no substitution and are sought whole, by a mask of their own length.

The benchmark is broadcast in blocks of about ``BLOCK_WORDS`` words, however large it is, one at a time: with more than one, each
block's pass over the documents is written before the next block is made, so driver and workers hold one.
Documents are read whole, in place: nothing is shuffled.

Words are lower-cased runs of text between white space, less the marks at their edges.

Cases: null or empty texts and items overlap with nothing; items are told apart by id, repeated
items repeat no row; repeated documents repeat their rows; empty tables give no overlap; a null
id, of a document or an item, stays null; other columns are ignored (``keep_clean`` returns them all).
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangeann.llm.common import claim, slices, staged, text_slices

#: Fixed masks: four words count.
MASKS = ("1111", "11011", "11101")
SHORTEST = 4
MATCHED = 13
BLOCK_WORDS = 2_000_000
BITS = 22
EDGE = b".,;:!?\"'()[]{}|*_"
CACHE_ENTRIES = 400_000
HITS = 100_000
SUB_BATCH_BYTES = 2 << 20

_FACTORS = np.random.default_rng(7).integers(1, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SEEDS: dict[int, Seeds] = {}


def words(data: bytes) -> list[bytes]:
    return [w for w in (x.strip(EDGE) for x in data.lower().split()) if w]


class Seeds:
    """A block of the benchmark: its words by number, its items, and its hashes by mask."""

    def __init__(self, items: list[tuple[int | None, bytes]]):
        self.vocabulary: dict[bytes, int] = {}
        self.cache: dict[bytes, int] = {}
        self.ids, self.texts = [], []
        for item, data in items:
            numbers = [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words(data)]
            if numbers:
                self.ids.append(item)
                self.texts.append(np.array(numbers, np.uint64))
        short = sorted({len(t) for t in self.texts if len(t) < SHORTEST})
        self.masks = [np.flatnonzero([c == "1" for c in m]) for m in MASKS] + [np.arange(n) for n in short]
        spans = [*map(len, MASKS), *short]
        self.tables = []
        for mask, span in zip(self.masks, spans, strict=True):
            found = [(h, i, p) for i, t in enumerate(self.texts) if (len(t) == span if span < SHORTEST else len(t) >= max(span, SHORTEST)) for p, h in enumerate(hashes(t, mask, span))]
            rows = np.array(found, np.uint64).reshape(-1, 3)
            rows = rows[np.argsort(rows[:, 0], kind="stable")]
            bits = np.zeros(1 << BITS, bool)
            bits[rows[:, 0] >> np.uint64(64 - BITS)] = True
            self.tables.append((mask, span, rows, bits))

    def number(self, raw: bytes) -> int:
        """0 for a word that no item has; -1 for marks alone, which are no word."""
        n = self.cache.get(raw)
        if n is None:
            if len(self.cache) > CACHE_ENTRIES:
                self.cache.clear()
            core = raw.strip(EDGE)
            n = self.cache[raw] = self.vocabulary.get(core, 0) if core else -1
        return n

    def overlaps(self, texts: list[bytes]) -> list[tuple[int, int, int, int, int]]:
        """Rows ``text, item, equal words, first word, words compared``, the best of each text and item."""
        streams = []
        for data in texts:
            a = np.fromiter(map(self.number, data.lower().split()), np.int64)
            streams.append(a[a >= 0].astype(np.uint64))
        gap = np.zeros(max(map(len, MASKS)), np.uint64)
        lengths = [len(a) + len(gap) for a in streams]
        starts = np.cumsum([0, *lengths])
        stream = np.concatenate([x for a in streams for x in (a, gap)]) if streams else gap
        seen: set[tuple[int, int, int]] = set()
        for mask, span, rows, bits in self.tables:
            if not len(rows) or len(stream) < span:
                continue
            h = hashes(stream, mask, span)
            at = np.flatnonzero(bits[h >> np.uint64(64 - BITS)])
            low, high = (np.searchsorted(rows[:, 0], h[at], side=s) for s in ("left", "right"))
            found = high > low
            at, low, count = at[found], low[found], (high - low)[found]
            for a, b in slices(count.tolist(), HITS):
                n = count[a:b]
                row = rows[np.arange(n.sum()) + np.repeat(low[a:b] - np.cumsum(n) + n, n)].astype(np.int64)
                q = np.repeat(at[a:b], n)
                doc = np.searchsorted(starts, q, side="right") - 1
                seen.update(zip(doc.tolist(), row[:, 1].tolist(), (q - row[:, 2]).tolist(), strict=True))
        best: dict[tuple[int, int], tuple[int, int, int]] = {}
        for doc, item, diagonal in seen:
            t = self.texts[item]
            low, high = max(diagonal, int(starts[doc])), min(diagonal + len(t), int(starts[doc]) + len(streams[doc]))
            equal = stream[low:high] == t[low - diagonal : high - diagonal]
            total = np.concatenate([[0], np.cumsum(np.where(equal, 1, -2))])
            floor = np.minimum.accumulate(total)
            end = int(np.argmax(total - floor))
            begin = int(np.argmin(total[: end + 1]))
            matched = int(equal[begin:end].sum())
            if matched >= min(MATCHED, -(-len(t) * 4 // 5)) and matched > best.get((doc, item), (0,))[0]:
                best[doc, item] = (matched, low + begin - int(starts[doc]), end - begin)
        return [(doc, item, *v) for (doc, item), v in sorted(best.items())]


def hashes(numbers: np.ndarray, mask: np.ndarray, span: int) -> np.ndarray:
    """A hash of the masked words at every position that has ``span`` words."""
    n = len(numbers) - span + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for k, at in enumerate(mask.tolist()):
        h += numbers[at : at + n] * _FACTORS[k]
        h ^= h >> np.uint64(29)
        h *= _FACTORS[63]
    return h


def blocks(benchmark: DataFrame, id_col: str, text_col: str) -> Iterator[tuple[object, bool]]:
    """Broadcast lists of items, each of a bounded number of words, and whether it is the only one; made one at a time."""
    items = benchmark.select(F.col(id_col).cast("long").alias("item"), F.coalesce(F.col(text_col), F.lit("")).alias("body"))
    total = items.agg(F.sum(F.size(F.split("body", "\\s+")).cast("long"))).first()[0] or 0
    n = max(1, -(-total // BLOCK_WORDS))
    part = F.pmod(F.xxhash64("item", "body"), F.lit(n))
    for k in range(n):
        found = {(r.item, r.body.encode()) for r in items.where(part == k).toLocalIterator()}
        rows = sorted(found, key=lambda x: (x[0] is None, x[0] or 0, x[1]))
        if rows:
            yield benchmark.sparkSession.sparkContext.broadcast(rows), n == 1


def seeds_of(items: list[tuple[int, bytes]]) -> Seeds:
    claim("decontamination", _SEEDS)
    key = hash(tuple(items))
    if key not in _SEEDS:
        _SEEDS.clear()
        _SEEDS[key] = Seeds(items)
    return _SEEDS[key]


def overlaps(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """Rows ``id, item_id, matched_words, start_word, compared_words`` of every document and item that overlap."""
    schema = f"`{id_col}` long, item_id long, matched_words int, start_word long, compared_words int"
    chosen, found = docs.select(F.col(id_col).cast("long"), text_col), None
    for block, alone in blocks(benchmark, item_col, item_text):

        def search(batches: Iterable[pa.RecordBatch], block=block):
            seeds = seeds_of(block.value)
            for batch in batches:
                ids, rows = batch.column(0).to_pylist(), []
                for a, _, texts in text_slices(batch, text_col, SUB_BATCH_BYTES):
                    rows += [(ids[a + d], seeds.ids[i], *v) for d, i, *v in seeds.overlaps(texts)]
                columns = list(zip(*rows, strict=True)) or [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int32()), strict=True)], names=[id_col, "item_id", "matched_words", "start_word", "compared_words"])

        part = chosen.mapInArrow(search, schema)
        if not alone:
            part = staged(part, "overlaps")
            block.destroy()
        found = part if found is None else found.unionByName(part)
    return found if found is not None else docs.sparkSession.createDataFrame([], schema)


def keep_clean(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns, that overlap with no item."""
    for block, alone in blocks(benchmark, item_col, item_text):

        def clean(batches: Iterable[pa.RecordBatch], block=block):
            seeds = seeds_of(block.value)
            for batch in batches:
                keep = np.ones(batch.num_rows, bool)
                for a, _, texts in text_slices(batch, text_col, SUB_BATCH_BYTES):
                    for d, *_ in seeds.overlaps(texts):
                        keep[a + d] = False
                yield batch.filter(pa.array(keep))

        docs = docs.mapInArrow(clean, docs.schema)
        if not alone:
            docs = staged(docs, "clean")
            block.destroy()
    return docs
