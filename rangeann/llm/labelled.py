"""Bounded samples of labelled documents, taken without moving the texts of the others."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def remainder(id_col: str, folds: int) -> Column:
    """crc32 of the id as text, modulo ``folds``; null for a null id."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % folds


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, folds: int, held_out: int, most: dict[int, int], id_col: str = "doc_id", text_col: str = "text") -> tuple[list[tuple[bytes, int]], dict[int, int]]:
    """At most ``most[c]`` texts of each class outside the held-out fold, and the fold's true class counts.

    Ids come from the labels alone, in the order of a hash of the id, so only that many texts
    are ever joined; of several labels of an id the largest counts, of several texts one.
    """
    known = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label).cast("int").alias("label")).where((remainder(id_col, folds) != held_out) & F.col(label).isin(*most)).groupBy("id").agg(F.max("label").alias("label"))
    counts = {r.label: r.n for r in known.groupBy("label").agg(F.count("*").alias("n")).collect()}
    chosen = None
    for c, n in most.items():
        part = known.where(F.col("label") == c).orderBy(F.xxhash64("id"), "id").limit(n)
        chosen = part if chosen is None else chosen.unionByName(part)
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("body")).join(F.broadcast(chosen), "id").groupBy("id", "label").agg(F.min("body").alias("body"))
    rows = [((r.body or "").encode(), r.label, r.id) for r in texts.collect()]  # at most sum(most) texts
    return [(t, c) for t, c, _ in sorted(rows, key=lambda x: x[2])], {c: counts.get(c, 0) for c in most}
