"""Near copies, passages, language, language models and the pipeline against brute force."""

import itertools
import math
import re
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from prefixcode.llm import brown, common, hdlang, icws, kneser, windows
from prefixcode.llm.components import components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, note string"
LOREM = [f"w{i}" for i in range(3000)]


def prose(seed: int, n: int) -> list[str]:
    r = np.random.default_rng(seed)
    return [LOREM[i] for i in r.integers(0, 3000, n)]


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def odd(spark):
    long = " ".join(prose(1, 20_000))
    rows = [(1, None, None, None, None, None), (2, "", "en", "a", 0, "x"), (3, "...", "en", "a", 3, "x"), (None, "one two", "en", None, 7, "x"), (None, "one two", "en", None, 7, "x"), (4, long, "de", "b", 1, "x"), (4, long, "de", "b", 1, "x"), (5, "日本語 テキスト", "ja", "c", 1, None), (6, "ÀÉ", None, "c", 1, None)]
    return spark.createDataFrame(rows, SCHEMA)


# ---------------------------------------------------------------- hashing
@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet="ab \t\n\x0b\x0c\réż", max_size=30), min_size=1, max_size=8))
def test_token_hashes(texts):
    h, sizes = common.TokenHasher().of([t.encode() for t in texts])
    words = [re.findall(r"[^\x20\x09-\x0D]+", t) for t in texts]
    assert sizes.tolist() == [len(w) for w in words]
    flat = [w for ws in words for w in ws]
    by = defaultdict(set)
    for w, x in zip(flat, h.tolist(), strict=True):
        by[w].add(x)
    assert all(len(v) == 1 for v in by.values()) and len({x for v in by.values() for x in v}) == len(by)


def test_token_hashes_in_parts(monkeypatch):
    r = np.random.default_rng(0)
    texts = [bytes(r.choice(list(b"abc \n"), int(n)).astype(np.uint8)) for n in (0, 5, 4000, 0, 900, 1, 2500)]
    h, sizes = common.TokenHasher().of(texts)
    monkeypatch.setattr(common.TokenHasher, "PART", 64)
    h2, sizes2 = common.TokenHasher().of(texts)
    assert (h == h2).all() and (sizes == sizes2).all() and sizes.tolist() == [len(t.split()) for t in texts]


def test_hash_index():
    r = np.random.default_rng(0)
    keys = np.unique(r.integers(0, 2**63, 5000).astype(np.uint64))
    at = common.HashIndex(keys)
    assert (at.find(keys) == np.arange(len(keys))).all()
    other = r.integers(0, 2**63, 1000).astype(np.uint64)
    assert ((at.find(other) >= 0) == np.isin(other, keys)).all()
    assert (common.HashIndex(keys[:0]).find(keys) == -1).all()


# ---------------------------------------------------------------- near copies
def test_samples_agree_as_often_as_texts_resemble():
    r = np.random.default_rng(4)
    s = icws.Sampler()
    for share in (0.5, 0.8, 0.95):
        same = 0
        for _ in range(60):
            h = np.sort(r.integers(0, 2**63, 200).astype(np.uint64))
            w = r.integers(1, 4, 200).astype(np.float32)
            v = np.where(r.random(200) < share, w, w * 2).astype(np.float32)
            a, b = s.samples(h, np.log(w), np.array([0])), s.samples(h, np.log(v), np.array([0]))
            same += (a == b).mean() - icws.similarity((h, w), (h, v))
        assert abs(same / 60) < 0.03


def test_gamma_quantiles():
    q = icws._gamma_quantiles(8)
    p = (np.arange(256) + 0.5) / 256
    assert np.allclose(1 - np.exp(-q) * (1 + q), p, atol=1e-9)


def test_near_copies_against_brute_force(spark):
    """Families of edited copies among unrelated texts; plain Jaccard similarity of 0.8 and more is found."""
    r = np.random.default_rng(7)
    rows, i = [], 0
    for family in range(12):
        base = prose(family, 200)
        for copy in range(1 + family % 4 * 9):
            w = list(base)
            for at in r.integers(0, 200, copy % 5):
                w[at] = "edit"
            rows.append((i, " ".join(w), None, None, 0, None))
            i += 1
    rows += [(i + k, " ".join(prose(100 + k, 60 + k)), None, None, 0, None) for k in range(60)]
    got = {x.doc_id: x for x in icws.near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect()}
    sets = {d: {tuple(t.split()[j : j + 5]) for j in range(len(t.split()) - 4)} for d, t, *_ in rows}
    for a in sets:
        for b in sets:
            if a < b and sets[a] & sets[b]:
                j = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
                if j >= 0.87:
                    assert got[a].class_id == got[b].class_id, (a, b, j)
    parent = {d: d for d in sets}

    def find(d):
        while parent[d] != d:
            d = parent[d]
        return d

    for a in sets:
        for b in sets:
            if a < b and len(sets[a] & sets[b]) >= 0.7 * len(sets[a] | sets[b]):
                parent[find(a)] = find(b)
    for d, x in got.items():
        assert find(d) == find(x.class_id)
    sizes = Counter(x.class_id for x in got.values())
    assert all(x.class_size == sizes[x.class_id] for x in got.values())
    assert Counter(x.class_id for x in got.values() if x.kept) == Counter(dict.fromkeys(sizes, 1))


def drifting(seed: int, n: int, size: int = 200, step: int = 3) -> list[str]:
    """Texts that change by a few words from one to the next: near to their neighbours only."""
    r, w, out = np.random.default_rng(seed), prose(seed, size), []
    for _ in range(n):
        out.append(" ".join(w))
        for at in r.integers(0, size, step):
            w[at] = LOREM[int(r.integers(0, 3000))]
    return out


def linked(spark, texts, keys):
    """Classes by links where all texts share the buckets ``keys`` and no other."""
    rows, idf = icws.signed(spark.createDataFrame([(i, t, None, None, 0, None) for i, t in enumerate(texts)], SCHEMA))
    nodes, found = icws.links(rows.withColumn(icws._BANDS, F.array(*[F.lit(k).cast("long") for k in keys])), idf)
    own = {r[icws._ROW]: r.doc_id for r in rows.select(icws._ROW, "doc_id").collect()}
    parent = {d: d for d in own.values()}

    def find(d):
        while parent[d] != d:
            d = parent[d]
        return d

    for r in found.collect():
        parent[find(own[r.a])] = find(own[r.b])
    by = defaultdict(set)
    for d in parent:
        by[find(d)].add(d)
    return {frozenset(x) for x in by.values()}


def around(seed: int, members: int, outliers: int) -> list[str]:
    """A text, members near to it, and outliers each near to one member only."""
    r, base, out = np.random.default_rng(seed), prose(seed, 200), []

    def edited(w, places):
        w = list(w)
        for at in places:
            w[at] = f"x{r.integers(10**9)}"
        return w

    own = [r.permutation(np.arange(5, 195, 5)) for _ in range(members)]
    near = [edited(base, p[:2]) for p in own]
    out = [base, *near, *(edited(near[i], own[i][2:5]) for i in range(outliers))]
    return [" ".join(w) for w in out]


def test_large_buckets_go_on_until_no_row_is_open(spark):
    """Texts near to their neighbours only, in one large bucket: more than a few leaders are needed."""
    assert linked(spark, drifting(40, 60), [7]) == {frozenset(range(60))}


def test_open_rows_meet_settled_members(spark):
    """Several outliers, each near to one settled member only, in two large buckets of the same rows."""
    assert linked(spark, around(41, 40, 8), [7, 8]) == {frozenset(range(49))}


def test_last_open_row_of_a_bucket_meets_all_members(spark):
    for seed in (42, 43):
        assert linked(spark, around(seed, 30, 1), [7]) == {frozenset(range(32))}


def test_near_copies_edges(odd, empty):
    got = icws.near_duplicates(odd).collect()
    assert len(got) == 9 and sum(x.kept for x in got) == 6
    assert {x.class_size for x in got if x.doc_id in (None, 4, 1, 2)} == {2}
    out = icws.representatives(odd)
    assert out.columns == odd.columns and out.count() == 6
    assert icws.near_duplicates(empty).count() == 0 and icws.representatives(empty).count() == 0


def test_near_copies_around_the_threshold(spark):
    """A family of hundreds whose members lie on both sides of 0.8: classes are those of all pairs."""
    r = np.random.default_rng(12)
    base, rows = prose(500, 150), []
    for i in range(260):
        w = list(base)
        for at in r.choice(150, int(r.integers(0, 9)), replace=False):
            w[at] = f"e{r.integers(10**9)}"
        rows.append((i, " ".join(w), None, None, 0, None))
    rows += [(1000 + k, " ".join(prose(900 + k, 90)), None, None, 0, None) for k in range(40)]
    x = spark.createDataFrame(rows, SCHEMA)
    got = {g.doc_id: g.class_id for g in icws.near_duplicates(x).collect()}
    idf = icws.idf_table(x)
    found = [(s[0], icws.weights(s, idf)) for s in icws.shingles([t for _, t, *_ in rows], common.TokenHasher())]
    ids = [d for d, *_ in rows]
    parent = {d: d for d in ids}

    def find(d):
        while parent[d] != d:
            d = parent[d]
        return d

    together = pairs = 0
    for i in range(len(ids)):
        for j in range(i):
            if icws.similarity(found[i], found[j]) >= icws.SIMILAR:
                parent[find(ids[i])] = find(ids[j])
                pairs += 1
                together += got[ids[i]] == got[ids[j]]
    assert pairs > 2500 and together >= 0.999 * pairs
    for d in ids:
        assert find(d) == find(got[d])  # no class holds what no chain of similar texts links


def test_components(spark):
    links = [(1, 2), (2, 3), (10, 11), (3, 7), (7, 1), (20, 20)] + [(100 + i, 101 + i) for i in range(60)]
    got = {r.node: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert {got[k] for k in (1, 2, 3, 7)} == {1} and {got[k] for k in (10, 11)} == {10} and {got[100 + i] for i in range(61)} == {100} and 20 not in got


# ---------------------------------------------------------------- passages
@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 6), min_size=1, max_size=80), st.integers(1, 9))
def test_compact_windows(values, least):
    h = np.array(values, dtype=np.uint64) << np.uint64(40)
    got = set(zip(*(x.tolist() for x in windows.compact_windows(h, least)), strict=True))
    want = set()
    for c in range(len(values)):
        lo, hi = c, c
        while lo and values[lo - 1] > values[c]:
            lo -= 1
        while hi + 1 < len(values) and values[hi + 1] >= values[c]:
            hi += 1
        if hi - lo + 1 >= least:
            want.add((lo, c, hi))
    assert got == want


def test_windows_stop_at_fences():
    r = np.random.default_rng(2)
    h = r.integers(1, 2**60, 300).astype(np.uint64)
    fence = np.zeros(300, dtype=bool)
    fence[[50, 51, 180]] = True
    got = set(zip(*(x.tolist() for x in windows.compact_windows(h, 5, fence)), strict=True))
    want = set()
    for a, b in ((0, 50), (52, 180), (181, 300)):
        want |= {(x + a, y + a, z + a) for x, y, z in zip(*(v.tolist() for v in windows.compact_windows(h[a:b], 5)), strict=True)}
    # ties can't occur among random hashes, so positions don't matter
    assert got == want


def test_windows_of_a_text_longer_than_its_places(monkeypatch):
    """Each run of the shortest length lies in a window of its minimum, behind 2 ** _POSITION too."""
    monkeypatch.setattr(windows, "_POSITION", 10)
    text = " ".join(f"w{i}" for i in range(5000))
    batch = pa.RecordBatch.from_pydict({"node": [1], "text": [text]})
    for got in windows._windows(iter([batch]), 46):
        left, right = got.column("at").to_numpy() >> 32, got.column("r").to_numpy()
        assert all(((left <= i) & (i + 45 <= right)).any() for i in range(5000 - 4 - 45)) and right.max() < 4996


def test_stretches():
    m = np.array([1] * 10 + [0] * 30 + [1] * 8 + [0] + [1] * 8, dtype=float)
    assert sorted(windows.stretches(m, 8, 0.8)) == [(0, 10), (40, 57)]
    assert windows.stretches(np.zeros(9), 3, 0.8) == []


def test_passages_against_brute_force(spark):
    """Passages of 60 words planted in unrelated texts: all found, where they are, and nothing else."""
    rows, places = [], []
    passages = [prose(500 + p, 60) for p in range(6)]
    r = np.random.default_rng(3)
    for i in range(120):
        w = prose(1000 + i, int(r.integers(20, 300)))
        if i % 3 == 0:
            at = int(r.integers(0, len(w)))
            p = i // 3 % 6
            w[at:at] = passages[p]
            places.append((i, at, at + 60, p))
        rows.append((i, " ".join(w), None, None, 0, None))
    near = prose(77, 100)
    edited = [*near[:40], "x1", *near[41:]]
    rows += [(200, " ".join(near), None, None, 0, None), (201, " ".join(edited), None, None, 0, None), (202, " ".join(edited), None, None, 0, None)]
    got = windows.repeated_passages(spark.createDataFrame(rows, SCHEMA)).collect()
    of = {i: p for i, _, _, p in places} | {200: 9, 201: 9, 202: 9}
    groups = defaultdict(set)
    for x in got:
        assert of[x.doc_id] == of[x.partner_id]
        groups[of[x.doc_id]] |= {x.doc_id, x.partner_id}
    assert groups == {p: {i for i in of if of[i] == p} for p in set(of.values())}
    spans = {i: (a, b) for i, a, b, _ in places}
    for x in got:
        if x.doc_id in spans:
            a, b = spans[x.doc_id]
            assert abs(x.start_word - a) <= 12 and abs(x.end_word - b) <= 12


def test_passages_at_the_thresholds(spark):
    """50 words, one of them replaced in the middle (41 of 51 shingles): 0.993 of the pairs are expected."""
    rows = []
    for k in range(150):
        one = prose(3000 + k, 50)
        for side, own in enumerate((one, [*one[:25], f"x{k}", *one[26:]])):
            rows.append((2 * k + side, " ".join([*prose(5000 + 2 * k + side, 60), *own, *prose(7000 + 2 * k + side, 60)]), None, None, 0, None))
    got = {frozenset((x.doc_id, x.partner_id)) for x in windows.repeated_passages(spark.createDataFrame(rows, SCHEMA)).collect()}
    want = {frozenset((2 * k, 2 * k + 1)) for k in range(150)}
    assert got <= want and len(got) >= 146


def test_passages_around_a_common_line(spark):
    """Twelve pairs of near passages hold the same line: more than two leaders of its group could find."""
    line, rows = prose(900, 44), []
    for k in range(12):
        own = prose(1000 + k, 12)
        for side in (0, 1):
            text = [*prose(2000 + 2 * k + side, 30), *own[:6], *line, *own[6:], *prose(3000 + 2 * k + side, 30)]
            rows.append((2 * k + side, " ".join(text), None, None, 0, None))
    got = {frozenset((x.doc_id, x.partner_id)) for x in windows.repeated_passages(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert {frozenset((2 * k, 2 * k + 1)) for k in range(12)} <= got


def test_passages_edges(odd, empty):
    got = windows.repeated_passages(odd).collect()
    assert {(x.doc_id, x.partner_id) for x in got} == {(4, 4)}
    assert windows.repeated_passages(empty).count() == 0


# ---------------------------------------------------------------- language
def test_gram_vectors_bind_and_permute():
    v = hdlang.letter_vectors(np.array([97, 98], dtype=np.uint32))
    assert set(np.unique(v)) == {-1.0, 1.0} and abs(v[0] @ v[1]) < 0.25 * hdlang.DIM
    g = hdlang.gram_vectors(np.array([[97, 98, 97], [98, 97, 97]], dtype=np.uint32))
    assert np.array_equal(g[0], np.roll(v[0], 2) * np.roll(v[1], 1) * v[0])
    assert abs(g[0] @ g[1]) < 0.25 * hdlang.DIM


def clean_grams(text):
    clean = re.sub(" +", " ", " " + "".join(c.lower() if c.isalpha() else " " for c in text) + " ")
    return Counter(tuple(map(ord, clean[i : i + 3])) for i in range(len(clean) - 2))


@pytest.mark.parametrize("part,grams", [(1 << 19, 1 << 13), (7, 3), (3, 1)])
def test_bundles_against_brute_force(part, grams, monkeypatch):
    """However texts are cut into parts and n-grams into shares, the sums are those of all n-grams."""
    monkeypatch.setattr(hdlang, "PART", part)
    monkeypatch.setattr(hdlang, "GRAMS", grams)
    texts = ["Hello, world", "", "a", "héllo  héllo", "123 --", "日本語 x", "one  two   three    four     five", "x" * 40, " " * 30 + "y", "1 2 3 4 a 5 6 7"]
    got, has = hdlang.bundles(texts)
    for t, row, n in zip(texts, got, has, strict=True):
        want = clean_grams(t)
        ids = np.array(list(want), dtype=np.uint32).reshape(-1, 3)
        assert np.array_equal(row, np.array(list(want.values()), dtype=float) @ hdlang.gram_vectors(ids) if want else row * 0)
        assert (n > 0) == any(c.isalpha() for c in t)


def test_bundles_of_long_varied_text():
    """Many different letters in few texts: memory follows parts, not texts times n-grams."""
    import tracemalloc

    r = np.random.default_rng(3)
    texts = ["".join(map(chr, r.integers(0x4E00, 0x9000, 4000))) for _ in range(100)] + ["".join(map(chr, r.integers(0x4E00, 0x9000, 600_000)))]
    tracemalloc.start()
    got, has = hdlang.bundles(texts)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 300 << 20 and len(got) == 101 and has.min() > 0


def test_language_held_out_accuracy(spark):
    x = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    lang = {r.doc_id: r.lang for r in x.select("doc_id", "lang").collect()}
    got = hdlang.identify(x).collect()
    assert len(got) == len(lang) and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) and 0 <= r.score <= 1 for r in got)
    held = [r for r in got if r.held_out]
    assert sum(r.lang_pred == lang[r.doc_id] for r in held) >= 0.98 * len(held)


def test_language_edges(odd, empty, docs):
    got = hdlang.identify(odd).collect()
    by = defaultdict(set)
    for r in got:
        by[r.doc_id].add((r.lang_pred, r.score))
    assert len(got) == 9 and by[1] == by[2] == by[3] == {("und", 0.0)} and len(by[4]) == 1
    assert hdlang.identify(empty).count() == 0
    unlabelled = odd.selectExpr("doc_id", "text", "CAST(NULL AS STRING) AS lang")
    assert {r.lang_pred for r in hdlang.identify(unlabelled).collect()} == {"und"}
    kept = hdlang.identified_documents(docs)
    assert kept.columns == docs.columns and kept.count() == docs.count()


# ---------------------------------------------------------------- regions of passages
def test_regions_of_many_windows():
    """A sweep finds what all windows against all do, and stays fast on a long pair."""
    r = np.random.default_rng(5)

    def plain(p, least):
        return [any(p[i, 0] != q[0] and min(p[i, 3], q[3]) - max(p[i, 1], q[1]) + 1 >= least and min(p[i, 6], q[6]) - max(p[i, 4], q[4]) + 1 >= least for q in p) for i in range(len(p))]

    def made(n, length):
        l1 = r.integers(0, length, n)
        shift = r.integers(-3, 4, n)
        wide = r.integers(4, 30, n)
        return np.stack([r.integers(0, 4, n), l1, l1 + wide // 2, l1 + wide, l1 + shift, l1 + shift + wide // 2, l1 + wide + shift], axis=1)

    for n, length in ((60, 400), (600, 1500)):
        p = made(n, length)
        boxes = windows.regions(p, 12)
        for ok, (_, l1, _, r1, l2, _, r2) in zip(plain(p, 12), p.tolist(), strict=True):
            if ok:
                assert any(l1 >= a and r1 < b and l2 >= c and r2 < d for a, b, c, d in boxes)
    start = time.time()
    windows.regions(made(40_000, 1_000_000), 12)
    assert time.time() - start < 5


# ---------------------------------------------------------------- class-based model
def tokens(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    return [*re.findall(r"[^\x20\x09-\x0D]+", low), "\n"]


def test_base_scores_and_counts(spark, docs, odd, empty):
    for df in (docs, odd):
        rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
        held = lambda d: d is not None and zlib.crc32(str(d).encode()) % 5 == 1
        count = Counter(t for d, x in rows if d is not None and not held(d) for t in tokens(x))
        n, v = sum(count.values()), len(count)
        want = Counter()
        for d, x in rows:
            t = tokens(x)
            want[(d, held(d), len(t), sum(count[w] > 0 for w in t), n, round(sum(math.log10((count[w] + 0.5) / (n + 0.5 * (v + 1))) for w in t), 4))] += 1
        got = brown.lm_scores(df).collect()
        assert Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 4)) for r in got) == want
    assert brown.lm_scores(empty).count() == 0


def test_classes_help_on_unseen_text(spark):
    x = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = [r for r in brown.lm_scores(x).collect() if r.held_out]
    assert sum(r.score for r in got) > sum(r.base_score for r in got)


def test_exchange_finds_classes_and_probabilities_sum_to_one(spark):
    """Text of two alternating word classes: exchange separates them, and P(. | v) is a distribution."""
    r = np.random.default_rng(0)
    texts = [(" ".join(f"{'ab'[i % 2]}{r.integers(0, 300)}" for i in range(60)),) for _ in range(500)]
    counts, model, said = brown.learn(spark.createDataFrame(texts, "text string"))
    assert said[-1] > said[0]
    own = brown.Tokens()
    seen = {x: model.classes[np.flatnonzero(model.hashes.view(np.uint64) == own.of([x])[0][0])[0]] for x in [f"{c}{i}" for c in "ab" for i in range(300)]}
    assert not {seen[f"a{i}"] for i in range(300)} & {seen[f"b{i}"] for i in range(300)}
    move = model.p_class[seen["a1"]]
    total = sum(0.95 * move[model.classes[i]] * model.p_word[i] + 0.05 * model.p_uni[i] for i in range(len(model.hashes)))
    total += 0.5 * (0.95 * move[model.rare] / model.rare_den + 0.05 / model.uni_den)
    unused = sum(move[c] for c in range(model.n_classes - 1) if c not in set(model.classes.tolist()))  # smoothing gives empty classes a little
    assert abs(total + 0.95 * unused - 1) < 1e-6


def test_rare_words_have_classes_too(spark, monkeypatch):
    """Words under KNOWN take the class that suits their neighbours; scores are those of the whole model."""
    monkeypatch.setattr(brown, "KNOWN", 2e-3)
    r = np.random.default_rng(0)
    words = [[f"{'ab'[i % 2]}{r.integers(0, 20) if r.random() < 0.8 else r.integers(20, 300)}" for i in range(60)] for _ in range(500)]
    rare, model, _ = brown.learn(spark.createDataFrame([(" ".join(w),) for w in words], "text string"))
    own, table = brown.Tokens(), {x.h: (x.c, x["class"]) for x in rare.collect()}
    of = lambda w: int(own.of([w])[0].view(np.int64)[0])
    known = {int(h): (int(c), int(k)) for h, c, k in zip(model.hashes, model.counts, model.classes, strict=True)}
    assert len(table) > 400 and not set(table) & set(known)
    said = {x: (known | table)[of(x)] for w in words for x in w}
    assert not {k for x, (_, k) in said.items() if x[0] == "a"} & {k for x, (_, k) in said.items() if x[0] == "b"}
    in_class, trans = Counter({brown.CLASSES: 500}), np.full((model.n_classes, model.n_classes), 0.5)
    for c, k in said.values():
        in_class[k] += c
    for w in words:
        seq = [brown.CLASSES, *(said[x][1] for x in w), brown.CLASSES]
        for x, y in zip(seq, seq[1:], strict=False):
            trans[x, y] += 1
    p = trans / trans.sum(axis=1, keepdims=True)
    n, v = 500 * 61, len(said) + 1
    tests = [["a1", "b250", "a260", "b2"], ["new", "a250"], ["b250", "new"], [], *words[:5]]
    got = {x.doc_id: x for x in brown.score(spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(tests)], "doc_id long, text string"), rare, model).collect()}
    for i, t in enumerate(tests):
        total, before = 0.0, brown.CLASSES
        for x in [*t, None]:
            c, k = (500, brown.CLASSES) if x is None else said.get(x, (0, model.rare))
            total += math.log10(0.95 * p[before, k] * (c / in_class[k] if c else 1) + 0.05 * (c + 0.5) / (n + 0.5 * (v + 1)))
            before = k
        assert abs(got[i].score - total) < 1e-6 * max(1, abs(total)) and got[i].n_known == sum(x in said for x in t) + 1


# ---------------------------------------------------------------- Kneser-Ney
def test_bigrams_are_packed_at_both_words(spark, monkeypatch):
    """Every pair of neighbours stands at its left and at its right word, words whole in a row, few rows for all."""
    monkeypatch.setattr(brown, "BUCKET", 4000)
    monkeypatch.setattr(brown, "PART", 64)
    rng = np.random.default_rng(3)
    texts = [" ".join(f"w{min(int(x), 300)}" for x in rng.zipf(1.3, size=40)) for _ in range(300)] + ["", "w1"]
    train = spark.createDataFrame([(t,) for t in texts], "text string")
    _, model = brown._known(train, "lm-counts")
    own = brown.Tokens()
    place = dict(zip(model.hashes.view(np.uint64).tolist(), range(len(model.hashes)), strict=True))
    end = -1 - brown.CLASSES
    want: Counter = Counter()
    for t in texts:
        seq = [end, *(place[own.hasher.one(w.encode())] for w in t.split()), end]
        for v, w in itertools.pairwise(seq):
            for key in [(2 * w, v)] * (w >= 0) + [(2 * v + 1, w)] * (v >= 0) + [(v, w)] * (v < 0 and w < 0):
                want[key] += 1
    rows = brown.contexts_of(train, model).collect()
    parts = [brown.pairs_of(bytes(r.pairs)) for r in rows]
    got: Counter = Counter()
    for first, other, n in parts:
        for f, o, c in zip(first.tolist(), other.tolist(), n.tolist(), strict=True):
            assert (f, o) not in got
            got[f, o] = c
    assert got == want and len(rows) < len(want) / 20
    at = [w for first, _, _ in parts for w in set((first[first >= 0] >> 1).tolist())]
    assert len(at) == len(set(at))
    assert brown.class_bigrams(model, brown.contexts_of(train, model)).sum() == sum(len(t.split()) + 1 for t in texts)


def reference_kneser(texts):
    """A plain trigram model with the same definitions, in dictionaries."""
    tri = Counter()
    for t in texts:
        w = ["<s>", "<s>", *t, "</s>"]
        tri.update(zip(w, w[1:], w[2:], strict=False))
    bi, uni = Counter(), Counter()
    for _, v, w in tri:
        bi[v, w] += 1
    for _, w in bi:
        uni[w] += 1

    def order(table):
        d = kneser.discounts(Counter(table.values()))
        cut = {k: d[min(c, 3) - 1] for k, c in table.items()}
        total, freed = Counter(), Counter()
        for k, c in table.items():
            total[k[:-1]] += c
            freed[k[:-1]] += cut[k]
        return {k: (c - cut[k]) / total[k[:-1]] for k, c in table.items()}, {h: freed[h] / total[h] for h in total}

    h3, f3 = order(tri)
    h2, f2 = order(bi)
    h1, f1 = order({(w,): c for w, c in uni.items()})
    free1 = f1[()] / (len(uni) + 1)

    def p(u, v, w):
        p1 = h1.get((w,), 0) + free1
        p2 = h2.get((v, w), 0) + f2.get((v,), 1) * p1
        return h3.get((u, v, w), 0) + f3.get((u, v), 1) * p2

    return lambda t: sum(math.log10(p(*x)) for x in zip(["<s>", "<s>", *t], ["<s>", *t, "</s>"], [*t, "</s>"], strict=False)), p, [*uni, "unseen"]


def test_kneser_ney_against_plain_model(spark):
    r = np.random.default_rng(1)
    texts = [[f"v{k}" for k in r.zipf(1.6, 30) % 25] for _ in range(150)]
    want, p, vocabulary = reference_kneser(texts)
    assert abs(sum(p("v1", "v2", w) for w in vocabulary) - 1) < 1e-9
    model = kneser.train(spark.createDataFrame([(" ".join(t),) for t in texts], "text string"))
    tests = [*texts[:20], ["v1", "new", "v2"], []]
    rows = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(tests)], "doc_id long, text string")
    got = {x["doc_id"]: x["__x_log10"] for x in kneser.perplexities(rows, model, ["doc_id"]).collect()}
    for i, t in enumerate(tests):
        assert abs(got[i] - want(t)) < 1e-3 * max(1, abs(want(t)))


def test_quality_keeps_trusted_and_drops_junk(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    kept = {r.doc_id: r.kept for r in kneser.classify(docs, labels).collect()}
    quality = {r.doc_id: r.quality for r in labels.collect()}
    good = [kept[d] for d, x in quality.items() if x == 1 and d in kept]
    bad = [kept[d] for d, x in quality.items() if x == 0 and d in kept]
    assert np.mean(good) > 0.97 and np.mean(bad) < 0.5


def test_every_trusted_row_trains_or_sets_thresholds(spark):
    """A language with 40 trusted rows beside one with 400 has its own threshold, over all rows not trained on."""
    r = np.random.default_rng(6)
    rows = [(i, " ".join(f"a{k}" for k in r.zipf(1.5, 40) % 50), "aa") for i in range(400)]
    rows += [(1000 + i, " ".join(f"b{k}" for k in r.integers(0, 2000, 40)), "bb") for i in range(40)]
    rows += [(2000 + i, " ".join(f"c{k}" for k in r.integers(0, 2000, 40)), "cc") for i in range(4)]  # too few: the threshold of all
    labels = spark.createDataFrame([(i, 1, 0) for i, *_ in rows], "doc_id long, quality int, toxic int")
    got = kneser.classify(spark.createDataFrame(rows, "doc_id long, text string, lang string"), labels).collect()
    limit = {x.lang: x.threshold for x in got}
    assert len(set(limit.values())) == 3
    assert sum(x.kept for x in got if x.lang == "bb") == 40 and np.mean([x.kept for x in got]) > 0.97


def test_all_trusted_rows_but_a_quarter_train(spark):
    """However many they are: 4,000 trusted rows of one language train with 3,000."""
    labels = spark.range(4000).selectExpr("id AS doc_id", "1 AS quality", "0 AS toxic")
    docs = spark.range(4000).selectExpr("id AS doc_id", "concat('w', id % 7, ' w', id % 11, ' w', id % 13) AS text", "'aa' AS lang")
    assert kneser.classify(docs, labels).where("trained_on").count() == 3000


def test_hashes_and_numbers_pack(spark):
    h = np.unique(np.random.default_rng(3).integers(0, 2**64, 1000, dtype=np.uint64))
    assert (kneser.unpacked(kneser.packed(h)) == h).all() and (np.diff(kneser._shards(h, 7)) >= 0).all() and set(kneser._shards(h, 7)) == set(range(7))
    values = np.arange(len(h), dtype=np.float32)
    assert (kneser._floats(kneser._planes(values)) == values).all()
    assert kneser.found(h[::2], values[::2], h, -1).tolist() == [x if i % 2 == 0 else -1 for i, x in enumerate(values.tolist())]


def test_blocks_ask_the_same_in_any_order():
    hasher, texts = common.TokenHasher(), ["a b c", "", "c a", "b"]
    whole = kneser._distinct([kneser._grams(texts, hasher)])
    assert (kneser._distinct([kneser._grams(texts[::-1], hasher)]) == whole).all()
    assert (kneser._distinct([kneser._grams([t], hasher) for t in texts]) == whole).all()


def test_trigrams_travel_packed_and_are_counted_whole():
    """Fewer than 16 bytes a trigram (three hashes take 24), in any number of shards and turns, with the same counts."""
    r = np.random.default_rng(5)
    texts = [" ".join(f"w{k}" for k in r.zipf(1.3, 400) % 5000) for _ in range(100)]
    tokens = kneser.token_hashes(texts, common.TokenHasher())
    want = Counter(x for t in tokens for x in zip(t.tolist(), t[1:].tolist(), t[2:].tolist(), strict=False))
    got, sent = Counter(), 0
    for turn in range(3):
        for b in kneser._trigrams(iter([pa.RecordBatch.from_pydict({"text": texts})]), 7, turn, 3):
            assert set(x % 3 for x in b.column("shard").to_pylist()) <= {turn}
            for shard, *packet in zip(*(b.column(c).to_pylist() for c in ("shard", "words", "places", "counts")), strict=True):
                words, n = kneser.unbundled(*packet)
                assert set(kneser._shards(kneser.gram(*words), 7).tolist()) == {shard} == set(kneser._shards(kneser.gram(*words[:2]), 7).tolist())
                sent += sum(map(len, packet))
                got.update(dict(zip(zip(*(w.tolist() for w in words), strict=True), n.tolist(), strict=True)))
    assert got == want and sent < 16 * len(want)


def test_quality_edges(spark, odd, empty):
    labels = spark.createDataFrame([(4, 1, 0), (4, 1, 0), (2, 1, None), (None, 1, 0), (5, 0, 1)], "doc_id long, quality int, toxic int")
    assert kneser.classify(odd, labels).count() == 9 and kneser.classify(empty, labels).count() == 0
    nothing = kneser.classify(odd, labels.limit(0)).collect()
    assert len(nothing) == 9 and all(r.kept and r.threshold is None for r in nothing)


# ---------------------------------------------------------------- pipeline
def test_pipeline_stages(spark, sf, odd):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    first = docs
    for name, stage in corpus_pipeline.STAGES:
        out = common.cut(stage(spark, docs, sf), name)
        if name != "best_fit_packing":
            assert out.columns == first.columns
        if name == "language_id":
            assert out.count() == docs.where("text rlike '[A-Za-z]'").count()
        if name == "exact_dedup":
            want = {}
            for r in docs.collect():
                want[r.text] = max(want.get(r.text, -1), r.doc_id)
            assert {r.doc_id for r in out.collect()} == set(want.values())
        if name == "near_dedup":
            assert 0.9 * docs.count() < out.count() <= docs.count()
        if name == "mix_sources":
            assert {r.doc_id for r in out.collect()} <= {r.doc_id for r in docs.collect()}
            assert max(Counter(r.doc_id for r in out.collect()).values()) <= 2
        if name == "best_fit_packing":
            assert {r.doc_id for r in out.collect()} == {r.doc_id for r in docs.collect()}
        docs = out
    for _, stage in corpus_pipeline.STAGES:
        stage(spark, odd, sf).count()
        stage(spark, odd.limit(0), sf).count()
    assert corpus_pipeline.run(spark, sf).count() == docs.count()


def test_kneser_training_drops_files_by_turns(spark, monkeypatch):
    """What a turn has read goes before the next one, and shuffles with what was executed."""
    docs = spark.createDataFrame([(" ".join(f"w{(i * j) % 41}" for j in range(1, 60)),) for i in range(80)], "text string")
    gone, real = [], kneser.remove
    monkeypatch.setattr(kneser, "SHARD", 200)
    monkeypatch.setattr(kneser, "remove", lambda s, path: (gone.append("/".join(path.split("/")[-2:])), real(s, path)))
    model = kneser.train(docs)
    model.drop()
    want = [f"what={what}/turn={turn}" for turn in range(kneser.TURNS) for what in (2, 20)] + [f"what={what}/turn={turn}" for turn in range(kneser.TURNS) for what in (3, 2)]
    assert gone[: len(want)] == want
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    with kneser.shuffles_freed(spark):
        assert spark.conf.get(key) == "true"
    assert spark.conf.get(key, None) == before
