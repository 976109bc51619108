"""Token counts by a two-tier, map-side lookup, and the id streams that packing needs.

A pre-token here is a run of text between ASCII white space.  The vocabulary's own
pre-tokenizer never joins across white space, so a text's ids are those of its pre-tokens
in order.  Tier one is a compact broadcast table of the most frequent pre-tokens (bounded by
``table_size`` entries of at most ``MAX_KEY`` bytes); tier two is a bounded dictionary in
each Python worker, which encodes what it has not seen in batches with the tokenizer library.
Both are asked once for each different pre-token of some megabytes of text.
No pre-token is ever shuffled: the only exchange is the sum of bounded per-task top lists
from which the frequent table is made, and that table never decides a count, only its speed.

Cases: null or empty text has 0 tokens; texts of any length are cut into pre-tokens and
handled whole; repeated rows give repeated rows; an empty table gives an empty result;
other columns of the input are ignored, whatever their names; a null id stays null.
"""

from __future__ import annotations

import json
import os
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangeann.llm.common import claim, column_slices, release

MAX_KEY = 64  # bytes of a pre-token that may enter a cache
CACHE_ENTRIES = 700_000  # of a worker's cache, half of them those of the last change
SUB_BATCH_BYTES = 3 << 20
COUNT_BYTES = 16 << 20  # of texts counted at once; what they have once is not frequent
TASK_TOP = 4_096  # pre-tokens that one task reports
TASK_DISTINCT = 200_000  # pre-tokens that one task counts at a time

GROUP = 256  # words encoded as one text
#: Marks that the vocabulary with word ends parts from a letter before them.
MARKS = b".,;:!?#%&*$@~^=+_/()[]{}\"-"

_TOKENIZERS: dict[int, object] = {}
_ENDS: dict[int, tuple[np.ndarray | None, bool]] = {}
_CACHES: dict[tuple, dict[bytes, object]] = {}


def read_vocabulary(path: str) -> str:
    with open(path, encoding="utf-8") as f:
        return f.read()


def tokenizer_of(vocabulary: str):
    """One tokenizer a worker and vocabulary."""
    key = hash(vocabulary)
    if key not in _TOKENIZERS:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        t = Tokenizer.from_str(vocabulary)
        t.no_truncation()
        t.no_padding()
        _TOKENIZERS[key] = t
    return _TOKENIZERS[key]


def split(texts: pa.Array, folds: bool) -> pa.ListArray:
    """The pre-tokens of each text, with A-Z folded where the vocabulary does so anyway; a run of white space at an end gives an empty one."""
    texts = pc.fill_null(texts, "")
    if folds:
        special = pc.match_substring(texts, "<|")
        low = pc.ascii_lower(texts)
        texts = pc.if_else(special, texts, low) if pc.any(special).as_py() else low
    return pc.ascii_split_whitespace(texts)


def repeated(texts: pa.Array, folds: bool) -> Iterator[tuple[str, int]]:
    """The pre-tokens that these texts have more than once, with how often."""
    found = split(texts, folds).flatten().value_counts()
    found = found.filter(pc.and_(pc.greater(found.field(1), 1), pc.not_equal(found.field(0), "")))
    return zip(found.field(0).to_pylist(), found.field(1).to_pylist(), strict=True)


class Lookup:
    """Pre-token to value, by the frequent table, then the worker's cache, then the library.

    The pre-tokens of some texts are numbered first, so each different one is looked up once.  One
    that no table has is parted into a core and the marks behind it, which the vocabulary never
    joins to a letter before them.  Cores of letters alone are one word each to it, so many
    of them are encoded as one text, whose ids fall apart where a word ends.
    """

    def __init__(self, vocabulary: str, frequent: dict[bytes, object], ids: bool, entries: int | None = None):
        self.tokenizer, self.frequent, self.ids = tokenizer_of(vocabulary), frequent, ids
        self.cache, self.old = (_CACHES.setdefault((hash(vocabulary), ids, age), {}) for age in ("young", "old"))
        self.entries = CACHE_ENTRIES if entries is None else entries
        claim("tokens", *_CACHES.values())
        self.ends, self.folds = word_ends(vocabulary)

    def value(self, ids: np.ndarray) -> object:
        return ids.tobytes() if self.ids else len(ids)

    def encode(self, keys: list[bytes]) -> list[object]:
        texts, found, rest = [k.decode("utf-8", "replace") for k in keys], [None] * len(keys), []
        if self.ends is None:
            rest = range(len(keys))
        else:
            alone = []
            for i, t in enumerate(texts):
                (alone if t.isalpha() else rest).append(i)
            groups = [alone[i : i + GROUP] for i in range(0, len(alone), GROUP)]
            joined = self.tokenizer.encode_batch_fast([" ".join([texts[i] for i in g]) for g in groups], add_special_tokens=False)
            for g, e in zip(groups, joined, strict=True):
                ids = np.array(e.ids, np.uint32)
                cuts = (np.flatnonzero(self.ends[ids]) + 1).tolist()
                if len(cuts) != len(g):
                    rest += g
                    continue
                if self.ids:
                    data = ids.tobytes()
                    for i, a, b in zip(g, [0, *cuts], cuts, strict=False):
                        found[i] = data[4 * a : 4 * b]
                else:
                    for i, a, b in zip(g, [0, *cuts], cuts, strict=False):
                        found[i] = b - a
        for i, e in zip(rest, self.tokenizer.encode_batch_fast([texts[i] for i in rest], add_special_tokens=False), strict=True):
            found[i] = self.value(np.array(e.ids, np.uint32))
        return found

    def learn(self, missing: list[bytes], cache: dict[bytes, object]) -> None:
        if self.ends is None:
            cache.update(zip(missing, self.encode(missing), strict=True))
            return
        parts, fresh = [], {}
        for w in missing:
            core = w.rstrip(MARKS)
            if len(core) == len(w) or not core[-1:].isalpha() and not core.decode("utf-8", "replace")[-1:].isalpha():
                fresh[w] = None
            else:
                marks = w[len(core) :]
                parts.append((w, core, marks))
                fresh[core] = fresh[marks] = None
        for k in fresh:
            if k in self.old:
                cache[k] = self.old[k]
        keys = [k for k in fresh if k not in cache]
        cache.update(zip(keys, self.encode(keys), strict=True))
        cache.update((w, cache[a] + cache[b]) for w, a, b in parts)

    def known(self, keys: list[bytes]) -> list[object]:
        """The value of each of different pre-tokens."""
        cache, frequent = self.cache, self.frequent
        if len(cache) > self.entries // 2:
            # what was not asked for since the last change goes
            self.old.clear()
            self.old.update(cache)
            cache.clear()
        got = list(map(cache.get, keys))
        gaps = [i for i, v in enumerate(got) if v is None]
        found = list(map(self.old.get, [keys[i] for i in gaps]))
        for i, v in zip(gaps, found, strict=True):
            if v is not None:
                got[i] = cache[keys[i]] = v
        gaps = [i for i, v in zip(gaps, found, strict=True) if v is None]
        if frequent:
            for i in gaps:
                got[i] = frequent.get(keys[i])
            gaps = [i for i in gaps if got[i] is None]
        if gaps:
            self.learn([keys[i] for i in gaps if 0 < len(keys[i]) <= MAX_KEY], cache)
            others = [i for i in gaps if not 0 < len(keys[i]) <= MAX_KEY]
            alone = dict(zip(others, self.encode([keys[i] for i in others]), strict=True))
            for i in gaps:
                got[i] = alone[i] if i in alone else cache[keys[i]]
        return got

    def numbered(self, texts: pa.Array) -> tuple[list[object], np.ndarray, np.ndarray]:
        """Values of the different pre-tokens, the number of each pre-token in order, and where each text begins among them."""
        lists = split(texts, self.folds)
        coded = lists.flatten().dictionary_encode()
        return self.known(coded.dictionary.cast(pa.binary()).to_pylist()), np.asarray(coded.indices), np.asarray(lists.offsets) - lists.offsets[0].as_py()

    def counts(self, texts: pa.Array) -> np.ndarray:
        """How many tokens each text has."""
        values, at, starts = self.numbered(texts)
        return np.diff(np.concatenate([[0], np.cumsum(np.array(values, np.int64)[at])])[starts])

    def streams(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts in order, and where each text begins among them."""
        values, at, starts = self.numbered(texts)
        pool = np.frombuffer(b"".join(values), "<u4")
        lengths = np.fromiter(map(len, values), np.int64, len(values)) // 4
        first, length = (np.cumsum(lengths) - lengths)[at], lengths[at]
        ends = np.concatenate([[0], np.cumsum(length)])
        return pool[np.arange(ends[-1]) + np.repeat(first - ends[:-1], length)], ends[starts]


def word_ends(vocabulary: str) -> tuple[np.ndarray | None, bool]:
    """Which ids end a word, if the vocabulary marks that and parts letters from marks; whether it folds A-Z.

    Only for the pre-tokenizer of letters, single digits and marks over white space that the
    vocabulary with word ends has; any other vocabulary is used pre-token by pre-token.
    """
    key = hash(vocabulary)
    if key not in _ENDS:
        v = json.loads(vocabulary)
        steps, model = (v.get("pre_tokenizer") or {}).get("pretokenizers", [{}]), v["model"]
        suffix = model.get("end_of_word_suffix")
        split = json.dumps(steps[0].get("pattern", {}))
        norm = [n.get("type") for n in (v.get("normalizer") or {}).get("normalizers", [])]
        if suffix and norm == ["NFC", "Replace", "Lowercase"] and "[\\\\p{L}]+" in split and "[^\\\\s\\\\p{L}\\\\p{N}]+" in split:
            ends = np.zeros(max([*model["vocab"].values(), *(t["id"] for t in v["added_tokens"])]) + 1, bool)
            ends[[i for t, i in model["vocab"].items() if t.endswith(suffix)]] = True
            _ENDS[key] = ends, True
        else:
            _ENDS[key] = None, False
    return _ENDS[key]


def frequent_pretokens(docs: DataFrame, text_col: str, table_size: int, folds: bool = False) -> list[bytes]:
    """The most frequent pre-tokens of all texts, by bounded counters in each task and one small sum."""

    def tops(batches):
        counts: Counter = Counter()
        for batch in batches:
            for _, _, texts in column_slices(batch, text_col, COUNT_BYTES):
                for k, n in repeated(texts, folds):
                    counts[k] += n
                if len(counts) > TASK_DISTINCT:
                    counts = Counter(dict(counts.most_common(TASK_DISTINCT // 4)))
        top = [(k.encode(), n) for k, n in counts.most_common(TASK_TOP) if len(k.encode()) <= MAX_KEY]
        yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in top], pa.binary()), pa.array([n for _, n in top], pa.int64())], names=["pretoken", "n"])

    best = docs.select(text_col).mapInArrow(tops, "pretoken binary, n long").groupBy("pretoken").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "pretoken").limit(table_size)
    return [bytes(r.pretoken) for r in best.collect()]  # at most table_size rows of MAX_KEY bytes


def count_tokens(docs: DataFrame, vocabulary_path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 2048, table_size: int = 32_768) -> DataFrame:
    """Rows ``id, n_bytes, n_tokens, over_limit`` for every row of ``docs``."""
    spark = docs.sparkSession
    vocabulary = read_vocabulary(vocabulary_path)
    keys = frequent_pretokens(docs, text_col, table_size, word_ends(vocabulary)[1])
    lengths = dict(zip(keys, Lookup(vocabulary, {}, ids=False).encode(keys), strict=True))
    shared = spark.sparkContext.broadcast((vocabulary, lengths))  # a vocabulary file and a table of fixed size

    def count(batches):
        look = Lookup(*shared.value, ids=False)
        for batch in batches:
            parts = [look.counts(texts) for _, _, texts in column_slices(batch, text_col, SUB_BATCH_BYTES)]
            n = np.concatenate(parts) if parts else np.zeros(0, np.int64)
            sizes = pc.fill_null(pc.binary_length(batch.column(1)), 0).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), sizes, pa.array(n), pa.array(n > limit)], names=[id_col, "n_bytes", "n_tokens", "over_limit"])
            release()

    return docs.select(F.col(id_col).cast("long"), text_col).mapInArrow(count, f"`{id_col}` long, n_bytes long, n_tokens long, over_limit boolean")
