"""Chat views, media, exact deduplication, mixing and packing: SQL, round trips and brute force."""

import hashlib
import os
import re
import struct
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from prefixcode.llm import chat, exthash, ogg, packing, pivotal

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, __x_note string"
#: nulls everywhere, empty and long texts, copies, ties on doc_id, whole rows repeated, an extra column.
ROWS = [
    (1, "a b c", "en", "s1", 5, "x"), (2, "a b c", "de", "s1", 5, None), (3, None, None, None, None, None), (4, "", "en", "s2", 0, "y"), (None, "a b c", "en", None, 5, "z"), (None, "lonely", None, "s2", 6, None),
    (5, "word " * 30_000, "en", "s1", 1, "w"), (5, "word " * 30_000, "en", "s1", 1, "w"), (6, "é ü <|endoftext|> ß", "fr", "s2", 3, "v"), (6, "tie", "fr", "s2", 3, "v"), (7, "\x0b\x1c nb\xa0sp", "fr", "s1", 9, "v"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


# ---------------------------------------------------------------- chat
def test_chat_against_sql(spark, sf):
    talk = spark.createDataFrame([(1, 0, "user", "hi <|x"), (1, 1, None, None), (1, 1, None, None), (None, 2, "bob", "a"), (None, None, "amy", ""), (2, 0, "system", "only"), (1, 700, "user", "late")], "conv_id long, turn int, role string, text string")
    for df in (talk, spark.read.parquet(f"{sf}/conversations.parquet")):
        con = duckdb.connect()
        con.register("conversations", df.toPandas().astype({"turn": "Int64", "conv_id": "Int64"}))
        key = lambda r: tuple(map(str, r))
        want = sorted(con.execute(chat.SQL).fetchall(), key=key)
        assert sorted(map(tuple, chat.views(df).collect()), key=key) == want


def test_chat_masks_are_the_speakers_words(spark):
    talk = spark.createDataFrame([(1, i, "abc"[i % 3], f"text {i}") for i in range(700)], "conv_id long, turn int, role string, text string")
    got = chat.texts(chat.views(talk)).collect()
    assert len(got) == 3
    for r in got:
        said = [r.text[s.start : s.end] for s in r.train_spans]
        assert said == [f"text {i}<|end|>" for i in range(700) if "abc"[i % 3] == r.view]


def test_chat_empty(spark):
    assert chat.views(spark.createDataFrame([], "conv_id long, turn int, role string, text string")).count() == 0


# ---------------------------------------------------------------- media
def crc_bitwise(data: bytes) -> int:
    r = 0
    for b in data:
        r ^= b << 24
        for _ in range(8):
            r = (r << 1 ^ 0x04C11DB7 if r & 0x80000000 else r << 1) & 0xFFFFFFFF
    return r


@settings(max_examples=40, deadline=None)
@given(st.binary(max_size=300))
def test_page_checksum(data):
    assert ogg.page_checksum(data) == crc_bitwise(data)


@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(0, 70_000), min_size=1, max_size=6), st.integers(0, 9))
def test_ogg_packets(sizes, seed):
    r = np.random.default_rng(seed)
    packets, end = [], 0
    for n in sizes:
        end += n
        packets.append((r.bytes(n), end))
    other = [(b"head", 0), (b"tail", 1)]
    back = ogg.demux(ogg.mux([ogg.write_stream(7, packets), ogg.write_stream(8, other)]))
    assert [p for p, _ in back[7]] == [p for p, _ in packets] and [p for p, _ in back[8]] == [b"head", b"tail"]
    assert ogg.timestamps(back[7], 10) == [e / 10 for _, e in packets]


def test_ogg_finds_damage():
    media = ogg.encode(ogg.pad(b"x" * 100_000), 100_000)
    for at in (30, len(media) // 2, len(media) - 1):
        with pytest.raises(ogg.OggError):
            ogg.decode(media[:at] + bytes([media[at] ^ 1]) + media[at + 1 :])
    with pytest.raises(ogg.OggError):
        ogg.decode(media[:-10])
    pages = list(ogg.pages_of(media))
    assert len({p[2] for p in pages}) == 2 and any(p[0] & 1 for p in pages)
    cutout = media.index(b"OggS", media.index(b"OggS", media.index(b"OggS", 1) + 1) + 1)
    after = media.index(b"OggS", cutout + 1)
    with pytest.raises(ogg.OggError):
        ogg.decode(media[:cutout] + media[after:])


def test_media_columns(odd, docs):
    for df in (odd, docs):
        texts = Counter((r.doc_id, (r.text or "").encode()) for r in df.select("doc_id", "text").collect())
        got = ogg.media_features(df).collect()
        assert len(got) == sum(texts.values())
        want = Counter()
        for (doc, raw), n in texts.items():
            payload = raw + bytes(max(64, -(-len(raw) // 64) * 64) - len(raw))
            want[(doc, len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))] += n
        assert Counter(tuple(r)[:5] for r in got) == want
        by = defaultdict(set)
        for r in got:
            by[r.payload_sha256, r.n_bytes].add((r.media_sha256, r.feature, r.media_bytes))
        assert all(len(v) == 1 for v in by.values())


def test_media_empty(empty):
    assert ogg.media_features(empty).count() == 0


# ---------------------------------------------------------------- exact copies
def expected_copies(rows):
    groups = defaultdict(list)
    for doc, text in rows:
        groups[text or ""].append(doc)
    out = Counter()
    for text, ids in groups.items():
        known = [i for i in ids if i is not None]
        keep = max(known) if known else None
        done = False
        for i in ids:
            first = i == keep and not done
            done |= first
            out[(i, keep, len(ids), first, hashlib.sha256(text.encode()).hexdigest())] += 1
    return out


@pytest.mark.parametrize("window", [1, 1 << 24])
def test_exact_copies(odd, docs, empty, window, monkeypatch):
    monkeypatch.setattr(exthash, "WINDOW_BYTES", window)
    monkeypatch.setattr(exthash, "BUCKET_BYTES", 1 << 14)
    for df in (odd, docs, empty):
        got = Counter(map(tuple, exthash.deduplicate(df).collect()))
        assert got == expected_copies([(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()])


def test_clashing_names(spark):
    from prefixcode.llm import hdlang, icws

    rows = [(i, f"some words that make a text number {i} and more", "en", "a", 3, 1, 2, 3, 4) for i in range(6)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, k int, node int, size int, digest int")
    for stage in (hdlang.identified_documents, exthash.distinct_documents, icws.representatives, pivotal.mix_documents):
        out = stage(df)
        assert out.columns == df.columns and out.count() > 0
    assert packing.packed(df).count() == 6


def test_distinct_documents(odd):
    out = exthash.distinct_documents(odd)
    assert out.columns == odd.columns
    assert sorted(r.text for r in out.collect()) == sorted({r[1] or "" for r in ROWS})


def test_hot_text_is_folded_in_shares(spark, monkeypatch):
    """A text in every window, and a directory of many buckets, with columns of clashing names."""
    monkeypatch.setattr(exthash, "WINDOW_BYTES", 1)
    monkeypatch.setattr(exthash, "BUCKET_BYTES", 200)
    monkeypatch.setattr(exthash, "HOT", 8)
    monkeypatch.setattr(exthash, "slices", lambda b, t: (x.slice(i, 1) for x in b for i in range(x.num_rows)))
    rows = [(i, "same" if i % 3 else f"own {i}", "b", i, "e") for i in range(240)] + [(None, "same", "b", 1, "e")]
    x = spark.createDataFrame(rows, "doc_id long, text string, __bucket string, __entry long, __sieve string").repartition(2)
    want = expected_copies([(d, t) for d, t, *_ in rows])
    assert Counter(map(tuple, exthash.deduplicate(x).collect())) == want
    kept = exthash.distinct_documents(x)
    assert kept.columns == x.columns and sorted(r.doc_id for r in kept.collect()) == sorted(k[0] for k in want if k[3])


def test_directory_splits():
    r = np.random.default_rng(0)
    sizes = {int(p): int(n) for p, n in zip(r.integers(0, 1 << 10, 4000), r.integers(1, 50, 4000), strict=True)}
    depth, directory = exthash.split_directory(sizes, 10, 500)
    assert len(directory) == 1 << depth and directory == sorted(directory)
    load = Counter()
    for p, n in sizes.items():
        load[directory[p >> (10 - depth)]] += n
    assert max(load.values()) <= 500 or depth == 10
    assert exthash.split_directory({}, 10, 5) == (0, [0])


def test_colliding_hashes_are_told_apart():
    import pyarrow as pa

    rows = [(5, "a", 1, 10, 1), (5, "b", 2, 11, 1), (5, "a", 3, 12, 2), (6, "a", 4, 1, 1)]
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], names=[exthash._HASH, exthash._TEXT, exthash._REP, exthash._ID, exthash._N])
    got = [tuple(r.values()) for b in exthash._chain([batch]) for r in b.to_pylist()]
    assert sorted(got) == [(1, 12, 3, False), (2, 11, 1, True), (3, 12, 3, True), (4, 1, 1, True)]


# ---------------------------------------------------------------- mixing
def targets(sizes: dict, weights=(3.0, 1.0, 2.0)):
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    w = {s: weights[i % 3] for i, s in enumerate(order)}
    left, fixed, total = set(sizes), {}, 1.5 * sum(sizes.values())
    while left:
        rest = total - sum(fixed.values())
        share = {s: rest * w[s] / sum(w[x] for x in left) for s in left}
        over = [s for s in left if share[s] > 2 * sizes[s]]
        if not over:
            return fixed | share
        for s in over:
            fixed[s] = 2.0 * sizes[s]
            left.remove(s)
    return fixed


def test_mixture(odd, docs):
    for df in (docs, odd):
        rows = [(r.doc_id, r.source, len(WORD.findall(r.text or ""))) for r in df.collect()]
        sizes = Counter()
        for _, s, n in rows:
            sizes[s] += n
        got = pivotal.mixed(df).collect()
        assert Counter((r.doc_id, r.source, r["size"]) for r in got) == Counter(rows)
        want, taken, largest = targets(sizes), Counter(), Counter()
        for r in got:
            assert r.source_size == sizes[r.source] and abs(r.target - want[r.source]) < 1e-6 * max(1, r.target)
            assert r.taken == r.copies * r["size"] <= 2 * r["size"]
            taken[r.source] += r.taken
            largest[r.source] = max(largest[r.source], r["size"])
        for s in sizes:
            assert abs(taken[s] - want[s]) <= largest[s] + 1e-6
        assert Counter(map(tuple, pivotal.mixed(df).collect())) == Counter(map(tuple, got))
        mixed = pivotal.mix_documents(df)
        assert mixed.columns == df.columns
        assert Counter((r.doc_id, r.source) for r in mixed.collect()) == +Counter({k: n for k, n in _copies(got).items()})


def _copies(got):
    out = Counter()
    for r in got:
        out[(r.doc_id, r.source)] += r.copies
    return out


def test_mixture_keeps_means(spark):
    rows = [(i, f"s{i % 2}", 1 + i % 9) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, source string, size long")
    units, sources = pivotal.copies(df, fold=8)
    t = {r.source: r.target / r.source_size for r in sources.collect()}
    for s, q in t.items():
        own = units.where(F.col("source") == s).collect()
        assert all(r.copies in (int(q), int(q) + 1) for r in own)
        assert abs(np.mean([r.copies for r in own]) - q) < 0.15


def test_mixture_empty_and_wordless(spark, empty):
    assert pivotal.mixed(empty).count() == 0 and pivotal.mix_documents(empty).count() == 0
    x = spark.createDataFrame([(1, "", None, "a", 0, None), (2, None, None, None, 0, None)], SCHEMA)
    assert [(r.taken, r.target) for r in pivotal.mixed(x).collect()] == [(0, 0.0)] * 2


def test_mixture_is_native(docs):
    plan = pivotal.mixed(docs)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


# ---------------------------------------------------------------- packing
@pytest.mark.parametrize("seed", range(4))
def test_knapsack_prices(seed):
    r = np.random.default_rng(seed)
    lengths = np.unique(r.integers(1, 40, 8))
    values = r.random(len(lengths))
    best, choice = packing.price(values, lengths, 60)
    brute = np.zeros(61)
    for c in range(1, 61):
        brute[c] = max([brute[c - 1], *(brute[c - n] + v for n, v in zip(lengths, values, strict=True) if n <= c)])
    assert np.allclose(best, brute)
    found = packing._configuration(choice, lengths, 60)
    assert sum(lengths[i] * n for i, n in found.items()) <= 60 and abs(sum(values[i] * n for i, n in found.items()) - brute[60]) < 1e-9


@pytest.mark.parametrize("low,high,n", [(1, 2048, 3000), (300, 1000, 3000), (600, 2048, 2000), (1, 30, 500), (2048, 2049, 10)])
def test_plan_holds_the_histogram(low, high, n):
    h = Counter(np.random.default_rng(1).integers(low, high, n).tolist())
    out = packing.plan(dict(h))
    held = Counter()
    for config, often in out:
        assert sum(k * m for k, m in config) <= 2048 and often > 0
        for k, m in config:
            held[k] += m * often
    assert held == h
    lengths, counts = (np.array(x) for x in zip(*sorted(h.items()), strict=True))
    assert sum(o for _, o in out) <= 1.03 * sum(packing.best_fit(lengths, counts, 2048).values()) + 1


def test_packing(odd, docs, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for df in (odd, docs):
        want = Counter()
        for r in df.select("doc_id", "text").collect():
            ids = [*tok.encode(r.text or "", add_special_tokens=False).ids, 0]
            first = len(ids) % 2048 or 2048
            cuts = [0, *range(first, len(ids) + 1, 2048)]
            for p, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                want[(r.doc_id, p, a, b - a, zlib.crc32(struct.pack(f"<{b - a}I", *ids[a:b])))] += 1
        got = packing.packed(df).collect()
        assert Counter(tuple(r)[:5] for r in got) == want
        sequences = defaultdict(list)
        for r in got:
            sequences[r.sequence_id].append((r.offset, r.length))
        for parts in sequences.values():
            at = 0
            for offset, length in sorted(parts):
                assert offset == at
                at += length
            assert at <= 2048
        assert len(sequences) <= 1.05 * sum(r.length for r in got) / 2048 + 2
    assert packing.packed(empty).count() == 0


def test_long_runs_of_blanks():
    """Ids are those of the named tokenizer, whatever the run."""
    import public_tokenizers
    from tokenizers import Tokenizer

    named = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    own = packing._tokenizer("byte_bpe_50k")
    for text in (" " * 1_000_000, "a" + "\n" * 5000 + "b", "x " + "\t" * 4096, " " * 4095 + "y", "\u00a0" * 9000, "word " * 3000):
        assert own(text) == named.encode(text, add_special_tokens=False).ids


def test_ranks_in_shares(docs, monkeypatch):
    monkeypatch.setattr(packing, "SHARE_ROWS", 3)
    got = packing.packed(docs).collect()
    assert len({(r.sequence_id, r.offset) for r in got}) == len(got)


@pytest.mark.parametrize("also", ["corpus_pipeline.py", "nothing else"])
def test_package_without_training_data_operators(tmp_path, also):
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    shutil.copytree(root, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", also))
    code = "import __spark_entry__ as e; q = e.queries(); assert q and not [n for n in q if n.startswith('op') or n == 'pipeline']"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", check=True, env={k: v for k, v in os.environ.items() if k != "PYTHONPATH"})
