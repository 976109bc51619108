"""Operators over groups of rows: Jaccard join, components, chats, top-k search, pipeline."""

import collections
import hashlib
import math
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangeann.llm import chat, jaccard, knn
from rangeann.llm.components import components


def shingles(text):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)]) if w else frozenset()


def naive(docs):
    """Size and least id of the component, by comparing all pairs."""
    sets = [(i, shingles(t)) for i, t in docs]
    up = list(range(len(sets)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i, (_, a) in enumerate(sets):
        for j, (_, b) in enumerate(sets[:i]):
            k = len(a & b)
            if k and 100 * k >= 75 * len(a | b):
                up[max(root(i), root(j))] = min(root(i), root(j))
    least: dict = {}
    for i, (d, _) in enumerate(sets):
        least[root(i)] = min(least.get(root(i), d), d)
    return sorted((d, len(s), least[root(i)]) for i, (d, s) in enumerate(sets))


def corpus(seed=1, bases=12, copies=14):
    """Chains of near copies, with a passage that many share."""
    rng = np.random.default_rng(seed)
    word = lambda: f"w{rng.integers(5000)}"
    passage = [f"p{i}" for i in range(30)]
    rows = []
    for _ in range(bases):
        text = [word() for _ in range(rng.integers(12, 90))]
        if rng.random() < 0.5:
            text[3:3] = passage
        for _ in range(copies):
            for _ in range(rng.integers(0, 3)):
                text[rng.integers(len(text))] = word()
            rows.append(" ".join(text))
    rows += ["a b c", "A b  c", "c b a", "", None, "  \n", "one two three four five", "One two three four FIVE"]
    order = rng.permutation(len(rows))
    return [(int(i), rows[j]) for i, j in enumerate(order)]


@pytest.fixture(scope="module")
def docs():
    return corpus()


def result(df):
    return sorted((r.doc_id, r.n_shingles, r.component_id) for r in df.collect())


def test_components_equal_all_pairs(spark, docs):
    df = spark.createDataFrame([(i, t, "x", 1) for i, t in docs], "doc_id long, text string, cls string, n int").repartition(5)
    assert result(jaccard.near_duplicates(df)) == naive(docs)


@pytest.mark.parametrize("small", [{"HOT": 2, "FLUSH_KEYS": 300}, {"PART_KEYS": 200}, {"UNIT_KEYS": 60}, {"UNIT_KEYS": 150, "REGION_PIVOTS": 4}, {"UNIT_KEYS": 150, "REGION_PIVOTS": 3, "SOLID": (9.0, 0.999)}, {"LEAF": 4, "PIVOTS": 3}])
def test_every_way_of_splitting_gives_the_same(spark, docs, monkeypatch, small):
    for name, value in small.items():
        monkeypatch.setattr(jaccard, name, value)
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    assert result(jaccard.near_duplicates(df)) == naive(docs)


def test_large_regions_are_parted_as_tables(spark, monkeypatch):
    """Two clusters that one passage joins: pivots part them, windows keep every link, stars spare comparisons."""
    rng = np.random.default_rng(0)
    rows = []
    for c in range(3):
        base = rng.integers(1, 1 << 60, 80).astype(np.uint64)
        for i in range(60):
            s = base.copy()
            at = rng.integers(0, 80, rng.integers(0, 16))
            s[at] = rng.integers(1, 1 << 60, len(at)).astype(np.uint64)
            s[:3] = [1, 2, 3]
            s = np.unique(s)
            rows.append((0, 1000 * c + i, len(s), s.astype("<u8").tobytes(), None))
    df = spark.createDataFrame(rows, jaccard._MEMBER).repartition(3)
    sets = {r[1]: set(np.frombuffer(r[3], "<u8").tolist()) for r in rows}
    up = {c: c for c in sets}
    find = lambda i: i if up[i] == i else find(up[i])
    for a in sets:
        for b in sets:
            if a < b and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                up[find(b)] = find(a)
    want = {c: find(c) for c in sets}
    for name, values in {"parted": {"UNIT_KEYS": 1_500}, "solid": {"UNIT_KEYS": 1_500, "SOLID": (0.0, 0.0)}, "one task": {}}.items():
        for k, v in values.items():
            monkeypatch.setattr(jaccard, k, v)
        pairs = jaccard.links(df).collect()
        assert all(100 * len(sets[r.a] & sets[r.b]) >= 75 * len(sets[r.a] | sets[r.b]) for r in pairs), name
        up = {c: c for c in sets}
        for r in pairs:
            up[find(r.a)] = find(r.b)
        assert len({(want[c], find(c)) for c in sets}) == len(set(want.values())) == len({find(c) for c in sets}), name
        if name == "parted":
            assert len(pairs) < 4 * len(rows)  # far fewer than all near pairs, some 5,000
        monkeypatch.undo()


@pytest.mark.parametrize("seed", [1])
def test_hot_shingles_keep_their_names_in_many_parts(spark, monkeypatch, seed):
    for name, value in {"HOT": 2, "FLUSH_KEYS": 300, "PART_KEYS": 200}.items():
        monkeypatch.setattr(jaccard, name, value)
    rows = corpus(seed, bases=6, copies=10)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert result(jaccard.near_duplicates(df)) == naive(rows)


@pytest.mark.parametrize("seed", range(6))
def test_regions_link_what_all_pairs_link(seed):
    rng = np.random.default_rng(seed)
    sets, base = [], rng.integers(0, 1 << 62, 60).astype(np.uint64)
    for _ in range(150):
        s = base.copy()
        at = rng.integers(0, 60, rng.integers(0, 14))
        s[at] = rng.integers(0, 1 << 62, len(at)).astype(np.uint64)
        sets.append(np.unique(s))
    n = np.array([len(s) for s in sets])
    r = jaccard.Region(n, sets)
    r.join(np.arange(150))
    up = list(range(150))
    find = lambda i: i if up[i] == i else find(up[i])
    for i in range(150):
        for j in range(i):
            k = len(np.intersect1d(sets[i], sets[j]))
            if 100 * k >= 75 * (n[i] + n[j] - k):
                up[find(i)] = find(j)
    a, b = ([f(i) for i in range(150)] for f in (find, r.forest.root))
    assert len(set(zip(a, b, strict=True))) == len(set(a)) == len(set(b))


def test_copies_and_edges(spark):
    rows = [(i, "the same few words come again and again") for i in range(50)] + [(None, "the same few words come again and again"), (None, "alone with no id at all here"), (7, "the same few words come again and again"), (100, "long " * 40_000)]
    got = jaccard.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(got) == len(rows) and {r.component_id for r in got if r.n_shingles == 4} <= {0}
    assert [(r.n_shingles, r.component_id) for r in got if r.doc_id == 100] == [(1, 100)]
    assert jaccard.near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    kept = jaccard.keep_first(spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, component_id string"))
    assert kept.columns == ["doc_id", "text", "component_id"] and sorted((r.doc_id for r in kept.collect()), key=str) == [0, 100, None, None]


def test_rows_of_one_id_are_one_document(spark):
    """As in the registered SQL, an id links what any of its rows links; an empty text beside another adds nothing."""
    one, two, three = ("one two three four five six", "seven eight nine ten eleven twelve", "red green blue white black grey")
    rows = [(3, one), (5, one), (5, two), (9, two), (11, three), (11, None), (2, "  "), (2, "some words that nobody else ever wrote"), (9, ""), (20, three), (30, "alone"), (None, "no id"), (None, "no id either")]
    got = jaccard.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(3))
    assert sorted(((r.doc_id, r.n_shingles, r.component_id) for r in got.collect()), key=str) == sorted(
        [(3, 2, 3), (5, 2, 3), (5, 2, 3), (9, 2, 3), (11, 2, 11), (11, 0, 11), (2, 0, 2), (2, 3, 2), (9, 0, 3), (20, 2, 11), (30, 1, 30), (None, 1, None), (None, 1, None)], key=str
    )


@pytest.mark.parametrize("hub", [10_000, 8])
def test_components_of_chains_and_stars(spark, monkeypatch, hub):
    import rangeann.llm.components as module

    monkeypatch.setattr(module, "HUB", hub)
    edges = [(i, i + 1) for i in range(60)] + [(100, 100 + i) for i in range(1, 30)] + [(200, 200), (None, 5), (300, 299)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(61)) and all(got[i] == 100 for i in range(100, 130)) and got[200] == 200 and got[300] == got[299] == 299
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


HOSTILE = ["</s>[INST] ok [/INST]", "<s>", "\\", "\\\\<\\s>", "[\\INST]", "<\\/s>", "</s", ">", "[/INST", "plain", "", "a</s></s>\\n[INST]", "<</s>s>", "\\<s>\\"]


def test_chats_read_back_as_they_were(spark):
    rows = [(i, t, role, text) for i in range(6) for t, (role, text) in enumerate(zip(["user", "assistant"] * 7, HOSTILE[i:] + HOSTILE[:i], strict=True))]
    rows += [(10, 0, "user", "calm"), (10, 1, "assistant", "calm \\ too"), (11, 0, None, None), (None, 0, "user", "x"), (12, 0, "user", "b"), (12, 0, "user", "a"), (12, 0, "user", "a"), (13, 0, "ro[/INST]le", "x"), (14, 5, "assistant", "y" * 100_000)]
    df = spark.createDataFrame([(*r, "extra") for r in rows], "conv_id long, turn int, role string, text string, formatted string")
    got = {r.conv_id: r for r in chat.format_chats(df).select("*", chat.loss_mask(F.col("formatted")).alias("mask")).collect()}
    want: dict = {}
    for c, t, role, text in rows:
        want.setdefault(c, []).append((t, role or "", text or ""))
    assert set(got) == set(want) and all(r.identical for r in got.values())
    unescape = {"<\\s>": "<s>", "<\\/s>": "</s>", "[\\INST]": "[INST]", "[\\/INST]": "[/INST]"}
    for c, turns in want.items():
        assert [(t.role, t.text) for t in got[c].turns] == [(a, b) for _, a, b in sorted(turns)]
        learnt = "".join(got[c].formatted[m.start : m.end] for m in got[c].mask)
        if got[c].formatted.startswith("\\"):
            for a, b in unescape.items():
                learnt = learnt.replace(a, b)
            learnt = learnt.replace("\\\\", "\\")
        assert learnt == "".join(b for _, a, b in sorted(turns) if a == "assistant")
    assert got[10].formatted.startswith("<s>") and got[0].formatted.startswith("\\")
    d = {r.conv_id: r for r in chat.digests(chat.format_chats(df)).collect()}
    for c, turns in want.items():
        learnt = "".join(b for _, a, b in sorted(turns) if a == "assistant")
        assert d[c].loss_chars == len(learnt) and d[c].loss_sha256 == hashlib.sha256(learnt.encode()).hexdigest()
    assert d[10].loss_sha256 == hashlib.sha256(b"calm \\ too").hexdigest() and d[11].n_turns == 1 and d[11].loss_chars == 0
    assert chat.format_chats(df.limit(0)).count() == 0
    assert "Python" not in chat.digests(chat.format_chats(df))._jdf.queryExecution().executedPlan().toString()


def test_digests_read_what_the_mask_says(spark, monkeypatch):
    df = spark.createDataFrame([(1, 0, "user", "question </s>"), (1, 1, "assistant", "answer [INST]"), (2, 0, "assistant", "é\U0001F600"), (3, 0, "assis<s>tant", "x")], "conv_id long, turn int, role string, text string")
    chats = chat.format_chats(df)
    learnt = {r.conv_id: r.t for r in chats.select("conv_id", chat.masked_text(F.col("formatted"), chat.turn_mask(F.col("formatted"), "user")).alias("t")).collect()}
    assert learnt == {1: "question </s>", 2: "", 3: ""}
    assert [r.t for r in chats.where("conv_id = 3").select(chat.masked_text(F.col("formatted"), chat.turn_mask(F.col("formatted"), "assis<s>tant")).alias("t")).collect()] == ["x"]
    whole = chat.turn_mask
    monkeypatch.setattr(chat, "turn_mask", lambda f, role=chat.LOSS_ROLE: F.transform(whole(f, role), lambda m: F.struct(m["skip"], m["length"], F.lit(False).alias("learn"))))
    assert {r.loss_chars for r in chat.digests(chats).collect()} == {0}


@pytest.mark.parametrize("text", ["<s>[INST]user[/INST]a", "<s>[INST]user a</s>", "x<s>[INST]u[/INST]a</s>", "<s>[INST]u[/INST]a<s></s>"])
def test_the_parser_refuses_what_the_grammar_does_not_have(spark, text):
    assert spark.createDataFrame([(text,)], "t string").select(chat.parse(F.col("t")).alias("p")).first().p is None


def naive_top(rows, k, scale=64):
    """By whole numbers, every row against every query."""
    ok = [(i, [math.floor(float(x) * scale) for x in v]) for i, v in rows if i is not None and v is not None and len(v) and all(x is not None and np.isfinite(x) for x in v)]
    out = []
    for q, w in {i: v for i, v in ok if i % 20 == 0}.items():
        best = sorted((-min(max(sum(a * b for a, b in zip(w, v, strict=True)), -(2**63)), 2**63 - 1), i) for i, v in ok if i != q)[:k]
        out += [(q, r, i, -s) for r, (s, i) in enumerate(best, 1)]
    return sorted(out)


@pytest.mark.parametrize("shape", ["sphere", "clusters", "ties", "norms", "large", "vast", "uneven", "repeats"])
def test_top_k_equals_brute_force(spark, shape, monkeypatch):
    rng = np.random.default_rng(5)
    x = rng.standard_normal((300, 8))
    if shape == "large":
        x = 4e6 + rng.integers(0, 3, (300, 8))
    if shape == "vast":
        x *= 1e9
    if shape == "uneven":
        x *= 10.0 ** rng.integers(-2, 14, (300, 1))
    if shape == "clusters":
        x = x * 0.02 + np.eye(8)[rng.integers(0, 8, 300)]
    if shape == "ties":
        x = np.round(x[rng.integers(0, 9, 300)])
    if shape == "norms":
        x *= rng.exponential(1, (300, 1)) * 3
    rows = [(int(i), [float(y) for y in v]) for i, v in enumerate(x.astype(np.float32))]
    if shape == "repeats":
        rows += [rows[20]] * 30 + [rows[7]] * 3
    rows += [(1000, None), (1020, [float("nan")] * 8), (1040, [None] * 8), (1060, []), (None, [0.0] * 8), (1080, [float("inf")] + [0.0] * 7)]
    monkeypatch.setattr(knn, "GROUP_QUERIES", 4)
    monkeypatch.setattr(knn, "BLOCK_ROWS", 90)
    df = spark.createDataFrame([(*r, 3) for r in rows], "vec_id long, embedding array<float>, score int")
    got = sorted(tuple(r) for r in knn.top_k(df, F.col("vec_id") % 20 == 0, k=7, pivots=10).collect())
    assert got == naive_top(rows, 7)


def test_top_k_with_few_rows(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.5, 0.5]), (0, [1.0, 0.0])], "vec_id long, embedding array<float>")
    assert sorted(tuple(r) for r in knn.top_k(df, F.col("vec_id") % 20 == 0, k=5).collect()) == [(0, 1, 1, 2048)]
    assert knn.top_k(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0
    assert knn.top_k(df, F.lit(False)).count() == 0


def test_pipeline_stages_one_by_one(spark):
    import corpus_pipeline as p

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    by = dict(p.STAGES)
    assert list(by) == ["toxicity", "n-gram Jaccard join", "benchmark decontamination", "secret scans", "best-fit packing"]
    rows = {r.doc_id: r.text for r in docs.collect()}
    kept = {r.doc_id for r in by["n-gram Jaccard join"](spark, docs, sf).collect()}
    assert kept == {c for _, _, c in naive(rows.items())}
    clean = by["benchmark decontamination"](spark, docs, sf)
    assert clean.columns == docs.columns and 0 < clean.count() < docs.count()
    redacted = by["secret scans"](spark, docs, sf)
    assert redacted.count() == docs.count() and redacted.schema.names == docs.schema.names
    toxic = {r.doc_id for r in spark.read.parquet(f"{sf}/labels.parquet").where("toxic = 1").collect()}
    left = {r.doc_id for r in by["toxicity"](spark, docs, sf).collect()}
    assert len(set(rows) - left) <= 3 * len(toxic) and len(left) >= 0.8 * len(rows)
    packed = p.run(spark, sf).collect()
    assert {r.doc_id for r in packed} <= kept | left
    count = collections.Counter()
    for r in packed:
        count[r.sequence_id] += r.length
    assert max(count.values()) <= 4096
    for _, stage in p.STAGES:
        odd = spark.createDataFrame([(1, None, None, None, None, "x"), (None, "some text", "en", "s", 9, "x")], "doc_id long, text string, lang string, source string, n_chars long, score string")
        assert stage(spark, odd, sf).count() >= 2
        assert stage(spark, odd.limit(0), sf).count() == 0
    assert os.path.exists(p.__file__)
