"""Toxicity by compression distance to two zstandard dictionaries.

zstandard's trainer makes both.  They hold the same base, trained on ordinary text; the
toxic one goes on with a part trained on toxic text, the ordinary one with as many bytes
trained on ordinary text.  The toxic part's samples are the marked words of toxic documents, since their other
words are ordinary ones: a word is marked if it has a part (edges included) whose document frequency is significantly
higher in toxic text, among the parts that cover toxic documents best, several times over.
A window is one word of the text, set between two carriers that both
dictionaries know (short frames would else be stored raw).  What a window gains is its
length under the ordinary dictionary less that under the toxic one.  Each gain at each window
length has a calibrated weight, the log ratio of how many toxic and ordinary training
documents have such a window; a logistic curve fitted to a document's largest weights, and
moved to the true share of toxic documents, gives the score.

The model is fitted on a bounded sample (``SAMPLE`` documents a class); every document is
scored from its whole text.  Scoring is map-side only: nothing is shuffled.

Cases: null and empty texts have no windows and get the curve's lowest value; longer words are
cut into windows of ``WINDOW`` bytes; repeated rows give repeated rows; no rows give none; without
labelled documents of both classes every score is the training share of label 1 (0 if none);
a null id stays null and counts as not held out; other columns are ignored.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import zstandard as zs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangeann.llm.common import claim, text_slices
from rangeann.llm.labelled import labelled_sample, remainder

SAMPLE = {1: 1_000, 0: 2_000}  # documents of each class that the fit may read
WINDOW = 48
EDGE = b".,;:!?\"'()|[]{}<>*_#$%&@~^=+-/\\"
BASE_BYTES, TOXIC_BYTES = 16_384, 5_120  # of trained dictionaries, of which 1,024 are tables that windows do not use
PART_BYTES = 4_096  # a trained document's text beyond that is another sample
COVER_BYTES = 4_096
SHORTEST, LONGEST = 5, 12  # bytes of a segment, with the word's edges
RATIO, SIGNIFICANT, COVERS = 8.0, 20.0, 5
BEFORE, AFTER = b"\x01\x02\x03\x04carrier block before every window\x05", b"\x06block after every window\x07"
TOP = 3
REACH = 8.0
FEW = 4.0
CACHE_ENTRIES = 200_000
SUB_BATCH_BYTES = 2 << 20

_SCORERS: dict[int, Scorer] = {}


def windows(data: bytes) -> set[bytes]:
    """The distinct words in lower case; long ones in parts."""
    found = set((data.lower() if data.isascii() else data.decode("utf-8", "replace").lower().encode()).split())
    if any(len(w) > WINDOW for w in found):
        found = {w[i : i + WINDOW] for w in found for i in range(0, len(w), WINDOW)}
    return found


@dataclass
class Model:
    toxic: bytes = b""
    ordinary: bytes = b""
    weights: dict[tuple[int, int], float] = field(default_factory=dict)  # of a document that has such a window
    rates: dict[tuple[int, int], float] = field(default_factory=dict)  # of each such window
    plain: float = 0.0  # of each window without a rate
    curve: tuple[float, ...] = (0.0,) * (TOP + 2)
    constant: float | None = None  # the score where nothing could be learnt


class Scorer:
    def __init__(self, model: Model):
        self.model, self.cache = model, {}
        if model.constant is None:
            self.on_toxic, self.on_ordinary = compressor(model.toxic), compressor(model.ordinary)

    def gain(self, word: bytes) -> tuple[int, int]:
        """Bytes saved by the toxic dictionary, and the window's length."""
        core = word.strip(EDGE)
        framed = BEFORE + b" " + core + b" " + AFTER
        return len(self.on_ordinary.compress(framed)) - len(self.on_toxic.compress(framed)), min(len(core), 16)

    def key(self, word: bytes) -> tuple[int, int] | None:
        """The window's gain and length, None where they tell nothing."""
        k = self.cache.get(word, 0)
        if k == 0:
            if len(self.cache) > CACHE_ENTRIES:
                self.cache.clear()
            k = self.gain(word)
            k = self.cache[word] = k if k in self.model.rates else None
        return k

    def features(self, data: bytes) -> list[float]:
        """The largest weights of the text's windows, falling, and the sum of all windows' rates within ``REACH``."""
        m, found = self.model, windows(data)
        keys = [k for k in map(self.key, found) if k is not None]
        top = sorted((m.weights.get(k, 0.0) for k in keys), reverse=True)[:TOP]
        total = sum(m.rates[k] for k in keys) + (len(found) - len(keys)) * m.plain
        return top + [0.0] * (TOP - len(top)) + [max(-REACH, min(REACH, total))]

    def score(self, data: bytes) -> float:
        if self.model.constant is not None:
            return self.model.constant
        *slopes, shift = self.model.curve
        return 1 / (1 + math.exp(-max(-50.0, min(50.0, shift + sum(a * b for a, b in zip(slopes, self.features(data), strict=True))))))


def compressor(content: bytes):
    plan = zs.ZstdCompressionParameters(window_log=15, hash_log=14, chain_log=14, search_log=6, min_match=4, target_length=64, strategy=zs.STRATEGY_GREEDY, write_content_size=0, write_dict_id=0, write_checksum=0)
    return zs.ZstdCompressor(compression_params=plan, dict_data=zs.ZstdCompressionDict(content, dict_type=zs.DICT_TYPE_RAWCONTENT))


def parts(word: bytes, lengths: Iterable[int] = range(SHORTEST, LONGEST + 1)) -> Iterable[bytes]:
    w = b" " + word.strip(EDGE) + b" "
    return (w[i : i + n] for n in lengths for i in range(len(w) - n + 1)) if len(w) <= WINDOW else ()


def toxic_segments(toxic: list[set[bytes]], ordinary: list[set[bytes]]) -> list[bytes]:
    """Word parts that mark toxic documents, chosen to cover each of them ``COVERS`` times."""
    n1, n0 = len(toxic), len(ordinary)
    seen1: dict[bytes, int] = {}
    for length in range(SHORTEST, LONGEST + 1):  # one length at a time, for the driver's memory
        count = Counter(p for d in toxic for p in {p for w in d for p in parts(w, (length,))})
        seen1.update((p, n) for p, n in count.items() if n >= max(3, 0.01 * n1))
    in_word: dict[bytes, tuple[bytes, ...]] = {}

    def likely(d: set[bytes]) -> set[bytes]:
        for w in d:
            if w not in in_word:
                in_word[w] = tuple(p for p in parts(w) if p in seen1)
        return {p for w in d for p in in_word[w]}

    seen0 = Counter(p for d in ordinary for p in likely(d))
    for d in toxic:
        likely(d)

    def marks(p: bytes) -> bool:
        a, b = seen1[p], seen0[p]
        if a / n1 < RATIO * (b + 1) / n0:
            return False
        e1, e0 = (a + b) * n1 / (n1 + n0), (a + b) * n0 / (n1 + n0)
        return 2 * (a * math.log(a / e1) + (b * math.log(b / e0) if b else 0)) >= SIGNIFICANT

    good = {p for p in seen1 if marks(p)}
    of_word = {w: [p for p in found if p in good] for w, found in in_word.items() if found}
    docs = [[{p for w in d for p in of_word.get(w, ())}, COVERS] for d in toxic]
    left, chosen = Counter(p for d, _ in docs for p in d), []
    while left and sum(map(len, chosen)) < COVER_BYTES:
        best = max(left, key=lambda p: (left[p] * len(p), p))
        if left[best] < max(3, 0.01 * n1):
            break
        chosen.append(best)
        for p in [p for p in left if p in best or best in p]:
            del left[p]
        for entry in docs:
            if best in entry[0] and entry[1]:
                entry[1] -= 1
                if not entry[1]:
                    left.subtract(p for p in entry[0] if p in left)
    return chosen


def apart(docs: list[set[bytes]]) -> list[set[bytes]]:
    """Without documents that share half of their longer words with an earlier one: copies would pass for evidence."""
    kept: list[set[bytes]] = []
    holders: dict[bytes, list[int]] = {}
    for d in docs:
        long = [w for w in d if len(w) >= 8] or list(d)
        shared = Counter(i for w in long for i in holders.get(w, ()))
        if not shared or 2 * max(shared.values()) < len(long):
            for w in long:
                holders.setdefault(w, []).append(len(kept))
            kept.append(d)
    return kept


def trained(docs: list[set[bytes]], most: int) -> bytes:
    """Content of a dictionary that zstandard trains on the documents' words, all of them; their plain join if there are too few."""
    texts = [b" " + b" ".join(sorted(w.strip(EDGE) for w in d)) + b" " for d in docs if d]
    samples = [t[i : i + PART_BYTES] for t in texts for i in range(0, len(t), PART_BYTES)]
    try:
        return zs.train_dictionary(most, samples).as_bytes()[-(most - 1_024) :]
    except (zs.ZstdError, ValueError):
        return b"".join(samples)[-(most - 1_024) :]


def marked(docs: list[set[bytes]], segments: list[bytes]) -> list[set[bytes]]:
    """Each document's words that hold one of the segments."""
    known: dict[bytes, bool] = {}
    for w in {w for d in docs for w in d if len(w) <= WINDOW}:
        framed = b" " + w.strip(EDGE) + b" "
        known[w] = any(s in framed for s in segments)
    return [{w for w in d if known.get(w)} for d in docs]


def fit(sample: list[tuple[bytes, int]], counts: dict[int, int]) -> Model:
    same: dict[bytes, bytes] = {}  # equal words of all documents are one object
    ones, zeros = ([{same.setdefault(w, w) for w in windows(t)} for t, c in sample if c == k] for k in (1, 0))
    total = sum(counts.values())
    if not ones or not zeros:
        return Model(constant=counts.get(1, 0) / total if total else 0.0)
    ones, zeros = apart(ones), apart(zeros)
    base, toxic = trained(zeros, BASE_BYTES), trained(marked(ones, toxic_segments(ones, zeros)), TOXIC_BYTES)
    plain = trained(zeros[::2], len(toxic) + 1_024) if toxic else b""
    model = Model(base + toxic + BEFORE + AFTER, base + plain.rjust(len(toxic))[-len(toxic) :] + BEFORE + AFTER)
    scorer = Scorer(model)
    keys: dict[bytes, tuple[int, int]] = {}
    seen, every = {1: Counter(), 0: Counter()}, {1: Counter(), 0: Counter()}
    for k, docs in ((1, ones), (0, zeros)):
        for d in docs:
            for w in d:
                if w not in keys:
                    keys[w] = scorer.gain(w)
            seen[k].update({keys[w] for w in d})
            every[k].update(keys[w] for w in d)
    n1, n0 = (sum(every[k].values()) for k in (1, 0))
    share = n1 / (n1 + n0)
    for key in every[1] | every[0]:
        if key[0] < 1:
            continue
        # rates are drawn to one another by FEW windows' worth of evidence
        both = every[1][key] + every[0][key]
        rate = math.log((every[1][key] + FEW * share) / (both + FEW) / share) - math.log((every[0][key] + FEW * (1 - share)) / (both + FEW) / (1 - share))
        model.rates[key] = max(-2.0, min(4.0, rate))
        weight = math.log((seen[1][key] + 0.5) / (len(ones) + 1)) - math.log((seen[0][key] + 0.5) / (len(zeros) + 1))
        if key[0] >= 2 and weight > 1 and seen[1][key] >= 3:
            model.weights[key] = weight
    rest = {k: sum(n for key, n in every[k].items() if key not in model.rates) for k in (1, 0)}
    model.plain = math.log((rest[1] + 1) / (n1 + 1)) - math.log((rest[0] + 1) / (n0 + 1))
    scorer = Scorer(model)
    x = np.array([scorer.features(t) + [1.0] for t, _ in sample])
    y = np.array([c for _, c in sample], float)
    slopes = TOP + 1
    b = np.zeros(slopes + 1)
    for _ in range(40):  # Newton's steps, with a small ridge
        p = 1 / (1 + np.exp(-np.clip(x @ b, -50, 50)))
        ridge = np.diag([1e-1] * slopes + [1e-3])
        b = b + np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge, x.T @ (y - p) - ridge @ b)
    b[:slopes] = np.maximum(b[:slopes], 0)
    b[slopes] += math.log(max(counts[1], 1) / max(counts[0], 1)) - math.log(len(ones) / len(zeros))
    model.curve = tuple(map(float, b))
    return model


def scorer_of(model: Model) -> Scorer:
    claim("toxicity", _SCORERS)
    key = hash((model.toxic, model.ordinary, model.curve, model.constant))
    if key not in _SCORERS:
        _SCORERS.clear()
        _SCORERS[key] = Scorer(model)
    return _SCORERS[key]


def fit_on(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", folds: int = 3, held_out: int = 1, sample: dict[int, int] | None = None) -> Model:
    return fit(*labelled_sample(docs, labels, "toxic", folds, held_out, sample or SAMPLE, id_col, text_col))


def score(docs: DataFrame, model: Model, threshold: float = 0.7, id_col: str = "doc_id", text_col: str = "text", folds: int = 3, held_out: int = 1) -> DataFrame:
    """Rows ``id, held_out, score, predicted`` for every row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # two dictionaries of fixed size

    def rate(batches: Iterable[pa.RecordBatch]):
        s = scorer_of(shared.value)
        for batch in batches:
            got = [s.score(t) for _, _, texts in text_slices(batch, text_col, SUB_BATCH_BYTES) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(got, pa.float64()), pa.array([int(x >= threshold) for x in got], pa.int32())], names=[id_col, "held_out", "score", "predicted"])

    held = F.coalesce(remainder(id_col, folds) == held_out, F.lit(False)).alias("held_out")
    return docs.select(F.col(id_col).cast("long"), held, text_col).mapInArrow(rate, f"`{id_col}` long, held_out boolean, score double, predicted int")


def keep_clean(docs: DataFrame, model: Model, threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns, whose score is under the threshold."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def clean(batches: Iterable[pa.RecordBatch]):
        s = scorer_of(shared.value)
        for batch in batches:
            yield batch.filter(pa.array([s.score(t) < threshold for _, _, texts in text_slices(batch, text_col, SUB_BATCH_BYTES) for t in texts], pa.bool_()))

    return docs.mapInArrow(clean, docs.schema)
