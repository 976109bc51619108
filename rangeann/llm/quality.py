"""Quality by nearest-neighbour votes in a latent-semantic space.

A text's terms are its hashed byte pairs and a few bands of repetition (of lines and words); a
term weighs the root of its share times its inverse document frequency.  The labelled sample's
term matrix gives the latent axes (a truncated singular value decomposition); its vectors, of
unit length, are broadcast: at most ``SAMPLE`` rows of ``AXES`` numbers.  Every document's
vector meets all of them in exact blocked products, and its ``NEIGHBOURS`` nearest vote with
their cosine (to ``DIGITS`` digits), raised to ``SHARPNESS``.  The prior holds where no neighbour is similar.

Nothing is shuffled; all texts are read whole.

Cases: null and empty texts have no terms and get the prior (the share of label 1 among the
training labels; 0 without labels); without labelled documents every score is that prior;
repeated rows give repeated rows; no rows give none; equal cosines are taken in the order of
the sample; a null id stays null and counts as not held out; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangeann.llm.common import binary_column, slices
from rangeann.llm.labelled import labelled_sample, remainder

SAMPLE = {0: 1_000, 1: 3_000}  # documents of each class that the fit may read
PAIRS, BANDS = 4_096, 16
TERMS = PAIRS + 2 * BANDS
AXES, NEIGHBOURS, SHARPNESS = 48, 15, 4
BLOCK_BYTES, BLOCK_ROWS, TILE = 4 << 20, 512, 64
DIGITS = 6  # of a cosine


@dataclass
class Model:
    prior: float
    idf: np.ndarray | None = None
    axes: np.ndarray | None = None  # terms x axes
    vectors: np.ndarray | None = None  # sample x axes, unit rows
    labels: np.ndarray | None = None


def terms(data: bytes, out: np.ndarray) -> None:
    """Fills ``out`` with the roots of term shares."""
    b = np.frombuffer(data, np.uint8).astype(np.uint32)
    if not len(b):
        return
    pair = (b[:-1] * np.uint32(256) + b[1:]) * np.uint32(2654435761) >> np.uint32(20)
    np.sqrt(np.bincount(pair, minlength=PAIRS)[:PAIRS] / max(1, len(pair)), out=out[:PAIRS])
    for k, items in enumerate((data.split(b"\n"), data.split())):
        fresh = len(set(items)) / len(items) if items else 1.0
        out[PAIRS + k * BANDS + min(BANDS - 1, int(fresh * BANDS))] = 0.5


def matrix(texts: list[bytes]) -> np.ndarray:
    x = np.zeros((len(texts), TERMS), np.float32)
    for row, data in zip(x, texts, strict=True):
        terms(data, row)
    return x


def unit(x: np.ndarray) -> np.ndarray:
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return np.divide(x, n, out=np.zeros_like(x), where=n > 1e-9)


def latent_axes(x: np.ndarray) -> np.ndarray:
    """The leading right singular vectors of ``x``, by subspace iteration from a fixed start."""
    basis = np.random.default_rng(0).standard_normal((x.shape[1], min(AXES + 16, *x.shape))).astype(np.float32)
    for _ in range(6):
        basis = np.linalg.qr(x.T @ (x @ basis))[0]
    _, size, right = np.linalg.svd(x @ basis, full_matrices=False)
    keep = size[:AXES] > 1e-5 * max(size[0], 1e-30)
    return (basis @ right[:AXES][keep].T).astype(np.float32)


def fit(sample: list[tuple[bytes, int]], counts: dict[int, int]) -> Model:
    total = sum(counts.values())
    prior = counts.get(1, 0) / total if total else 0.0
    if not sample:
        return Model(prior)
    x = matrix([t for t, _ in sample])
    idf = np.log((1 + len(x)) / (1 + (x > 0).sum(axis=0))).astype(np.float32) + np.float32(0.1)
    x *= idf
    axes = latent_axes(x)
    return Model(prior, idf, axes, unit(x @ axes), np.array([c for _, c in sample], np.float64))


def votes(model: Model, texts: list[bytes]) -> np.ndarray:
    if model.vectors is None:
        return np.full(len(texts), model.prior)
    x = matrix(texts + [b""] * (-len(texts) % TILE))  # whole tiles, so that a row's products do not depend on its block
    close = np.round(unit((x * model.idf) @ model.axes) @ model.vectors.T, DIGITS)[: len(texts)]
    near = nearest(close, min(NEIGHBOURS, close.shape[1]))
    weight = np.clip(np.take_along_axis(close, near, axis=1), 0, 1).astype(np.float64) ** SHARPNESS
    return (0.05 * model.prior + (weight * model.labels[near]).sum(axis=1)) / (0.05 + weight.sum(axis=1))


def nearest(close: np.ndarray, k: int) -> np.ndarray:
    """The columns of each row's k largest numbers, in order of the columns; of equal ones the first."""
    edge = -np.partition(-close, k - 1, axis=1)[:, k - 1 : k]
    level = close == edge
    above = close > edge
    chosen = above | (level & (np.cumsum(level, axis=1) <= k - above.sum(axis=1, keepdims=True)))
    return np.nonzero(chosen)[1].reshape(len(close), k)


def fit_on(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", folds: int = 5, held_out: int = 0, sample: dict[int, int] | None = None) -> Model:
    return fit(*labelled_sample(docs, labels, "quality", folds, held_out, sample or SAMPLE, id_col, text_col))


def score(docs: DataFrame, model: Model, threshold: float = 0.3, id_col: str = "doc_id", text_col: str = "text", folds: int = 5, held_out: int = 0) -> DataFrame:
    """Rows ``id, held_out, score, predicted`` for every row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by SAMPLE, AXES and TERMS

    def rate(batches: Iterable[pa.RecordBatch]):
        model = shared.value
        for batch in batches:
            texts, got = binary_column(batch, text_col), []
            for a, b in slices([max(len(t), BLOCK_BYTES // BLOCK_ROWS) for t in texts], BLOCK_BYTES):
                got.append(votes(model, texts[a:b]))
            s = np.concatenate(got) if got else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32))], names=[id_col, "held_out", "score", "predicted"])

    held = F.coalesce(remainder(id_col, folds) == held_out, F.lit(False)).alias("held_out")
    return docs.select(F.col(id_col).cast("long"), held, text_col).mapInArrow(rate, f"`{id_col}` long, held_out boolean, score double, predicted int")
