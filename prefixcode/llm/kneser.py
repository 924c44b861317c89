"""Quality classifier: interpolated modified Kneser-Ney trigrams of trusted text.

Trusted are rows that ``labels`` calls good and not toxic. Three quarters of each language's, chosen by
hash, train the model; all others set, for each language, the perplexity above which a document is turned
down: a quantile of theirs, with some slack. Of a language's trusted rows LEAST_ROWS, where it has more
than that, are never trained on.

n-grams travel and wait packed: distinct word hashes, places among them and counts, some hundred thousand in a
row. A shard holds the trigrams of some contexts, so it counts them and sums up their contexts; the pairs that end them go on
to shards of their own, and those pairs' words to theirs. The model is a table of shards, each the sorted
hashes of some n-grams with their counts; discounts come in when it is asked. Documents are dealt into blocks; a block asks each shard once for its
distinct n-grams, by sorted hashes, and gets the numbers in the same order. No task holds more than a shard
or a block and what they ask of each other. A document's score is the sum of logs over its tokens.

Cases: null text is empty and scores its end token; a null language is a language of its own; a
language with few trusted rows takes the threshold of all; without trusted rows everything is kept
with a null threshold; a null doc_id has no label; repeated labels count once; an empty table gives
an empty result; extra columns are left alone.
"""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from prefixcode.llm.common import TokenHasher, cut, done_with, fresh_path, lowered, mix64, release, remove, shuffles_freed, slices, table, whole_text

SHARD = 1_000_000  # entries, about
BLOCK = 6 << 20  # bytes of text, about
PASSES = 12
ROOM = 2_000_000  # tokens that are counted before they are sent on
TURNS = 4  # in which pairs are counted, so that little waits on disk at once
QUANTILE = 0.99
SLACK = 1.15
LEAST_ROWS = 30
_ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)]
_START, _END = 11, 13  # hashes of the marks before and after a text


def token_hashes(texts: list[str], hasher: TokenHasher) -> list[np.ndarray]:
    """Of each text: hashes of two start marks, the lower-cased words and the end mark."""
    words, sizes = hasher.of(lowered(texts))
    out, at = [], 0
    for n in sizes.tolist():
        t = np.empty(n + 3, dtype=np.uint64)
        t[:2], t[-1], t[2:-1] = _START, _END, words[at : at + n]
        out.append(t)
        at += n
    return out


_OWN = np.uint64((1 << 44) - 1)


def gram(*parts: np.ndarray) -> np.ndarray:
    """Hash of an n-gram from its words' hashes; never 0. A trigram's first bits are its context's: both are in one shard."""
    h = np.zeros(len(parts[0]), dtype=np.uint64)
    for i, p in enumerate(parts):
        h = (h ^ (h >> np.uint64(31))) * _ODD[i] + p
    h = mix64(h + np.uint64(len(parts)))
    if len(parts) == 3:
        h = (gram(*parts[:2]) & ~_OWN) | (h & _OWN)
    return h | np.uint64(1)


def discounts(of_counts: dict[int, int]) -> tuple[float, float, float]:
    """D1, D2, D3+ from the numbers of n-grams that occur once, twice, three and four times."""
    n1, n2, n3, n4 = (of_counts.get(k, 0) for k in (1, 2, 3, 4))
    if not (n1 and n2 and n3):
        return 0.5, 0.75, 0.9
    y = n1 / (n1 + 2 * n2)
    clip = lambda d, k: min(max(d, 0.1), k - 0.05)
    return clip(1 - 2 * y * n2 / n1, 1), clip(2 - 3 * y * n3 / n2, 2), clip(3 - 4 * y * n4 / n3, 3)


def _shards(h: np.ndarray, shards: int) -> np.ndarray:
    """The shard of each hash; it ascends with the hash."""
    return (((h >> np.uint64(33)) * np.uint64(shards)) >> np.uint64(31)).astype(np.int32)


def packed(sorted_: np.ndarray) -> bytes:
    """Differences of ascending hashes, first bytes first: the upper ones are 0 and cost nothing when compressed."""
    return np.diff(sorted_, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T.tobytes()


def unpacked(b: bytes) -> np.ndarray:
    return np.cumsum(np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(8, -1).T).view(np.uint64).ravel(), dtype=np.uint64)


def _planes(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x, dtype=np.float32).view(np.uint8).reshape(-1, 4).T.tobytes()


def _floats(b: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(4, -1).T).view(np.float32).ravel()


def squeezed(b: bytes) -> bytes:
    return len(b).to_bytes(8, "little") + (pa.compress(b, codec="zstd", asbytes=True) if b else b"")


def released(b: bytes) -> bytes:
    size = int.from_bytes(b[:8], "little")
    return pa.decompress(b[8:], size, codec="zstd", asbytes=True) if size else b""


def ints(x: np.ndarray) -> bytes:
    """Whole numbers from 0; small ones cost little."""
    return squeezed(np.ascontiguousarray(x, dtype=np.uint64).view(np.uint8).reshape(-1, 8).T.tobytes())


def of_ints(b: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(released(b), np.uint8).reshape(8, -1).T).view(np.int64).ravel()


def bundled(words: list[np.ndarray], n: np.ndarray) -> tuple[bytes, bytes, bytes]:
    """n-grams by their words' hashes, with counts: (distinct words, places among them, counts)."""
    known, at = np.unique(np.concatenate(words), return_inverse=True)
    at = at.reshape(len(words), -1)
    order = np.lexsort(at[::-1])
    at = at[:, order]
    at[0] = np.diff(at[0], prepend=0)
    return squeezed(packed(known)), ints(at.ravel()), ints(n[order])


def unbundled(known: bytes, at: bytes, n: bytes) -> tuple[list[np.ndarray], np.ndarray]:
    words, count = unpacked(released(known)), of_ints(n)
    places = of_ints(at).reshape(-1, len(count))
    places[0] = np.cumsum(places[0])
    return [words[x] for x in places], count


def summed(keys: np.ndarray, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct keys, ascending; sums of the numbers' columns; where each key stood first)."""
    order = np.argsort(keys, kind="stable")
    first = np.flatnonzero(np.diff(keys[order], prepend=~keys[order[:1]]))
    if not len(first):
        return keys, numbers, order
    return keys[order[first]], np.add.reduceat(numbers[:, order], first, axis=1), order[first]


def found(keys: np.ndarray, values: np.ndarray, ask: np.ndarray, missing: float) -> np.ndarray:
    """The value of each hash asked for; both ascend."""
    out = np.full(len(ask), missing, dtype=np.float32)
    if len(keys):
        at = np.minimum(np.searchsorted(keys, ask), len(keys) - 1)
        hit = keys[at] == ask
        out[hit] = values[at[hit]]
    return out


#: Numbers of an n-gram: its count; as a context the sum of counts, and how many occur once, twice, more often.
NUMBERS = 5


class Model:
    """p3(w|uv) = held[uvw] / t[uv] + free[uv] p2(w|v), p2 = held[vw] / t[v] + free[v] p1(w), p1 = held[w] + free1.

    held is a count less its discount (of a word: its share of all), t a context's sum, free what was taken off as a share of it.
    parts: shard, keys (of all orders), held, free, t; a table of buckets by shard, so that it isn't moved when it is asked.
    """

    def __init__(self, parts: DataFrame, shards: int, free1: float, name: str):
        self.parts, self.shards, self.free1, self.name = parts, shards, free1, name

    def drop(self) -> None:
        done_with(self.parts)
        self.parts.sparkSession.sql(f"DROP TABLE IF EXISTS {self.name}")


_PACKET = "shard int, words binary, places binary, counts binary"
_PART = "what int, shard int, words binary, places binary, counts binary, keys binary, numbers binary, seen long, total long, c1 long, c2 long, c3 long, c4 long"
_PAIRS = 20  # what: pairs that end trigrams; else the order of n-grams with numbers


def _by_shard(h: np.ndarray, shards: int) -> Iterator[tuple[int, np.ndarray]]:
    own = _shards(h, shards)
    order = np.argsort(own, kind="stable")
    own = own[order]
    at = np.flatnonzero(np.diff(own, prepend=-1))
    return zip(own[at].tolist(), np.split(order, at[1:]), strict=True)


def _trigrams(batches: Iterator[pa.RecordBatch], shards: int, turn: int, turns: int) -> Iterator[pa.RecordBatch]:
    """Those of the turn's shards."""
    hasher, held, size = TokenHasher(), [], 0

    def sent() -> pa.RecordBatch:
        words = [np.concatenate(x) for x in zip(*((t[:-2], t[1:-1], t[2:]) for t in held), strict=True)]
        g = gram(*words)
        now = np.flatnonzero(_shards(g, shards) % turns == turn)
        words = [w[now] for w in words]
        g, n, first = summed(g[now], np.ones((1, len(now)), np.int64))
        rows = [(shard, *bundled([w[first[at]] for w in words], n[0, at])) for shard, at in _by_shard(g, shards)]
        columns = zip(*rows, strict=True) if rows else [[]] * 4
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int32(), *[pa.binary()] * 3), strict=True)], names=[x.split()[0] for x in _PACKET.split(", ")])

    for batch in slices(batches, most_bytes=1 << 20):
        new = token_hashes(batch.column("text").to_pylist(), hasher)
        held += new
        size += sum(map(len, new))
        if size >= ROOM:
            yield sent()
            held, size = [], 0
    if held:
        yield sent()


def _parts(rows: list[dict]) -> pa.Table:
    types = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    return pa.Table.from_pylist(rows, pa.schema([(x.split()[0], types[x.split()[1]]) for x in _PART.split(", ")]))


def _part(what: int, shard: int, keys: np.ndarray, numbers: np.ndarray) -> dict:
    """Ascending keys with their numbers. seen, total and c1 to c4 are of counts."""
    c = numbers[0]
    out = {"what": what, "shard": shard, "keys": squeezed(packed(keys)), "numbers": ints(numbers.ravel()), "seen": int((c > 0).sum()), "total": int(c.sum())}
    return out | {f"c{k}": int((c == k).sum()) for k in (1, 2, 3, 4)}


def _as_contexts(c: np.ndarray) -> np.ndarray:
    """What n-grams of these counts add to the numbers of their contexts."""
    return np.stack((np.zeros_like(c), c, c == 1, c == 2, c > 2)).astype(np.int64)


def _as_counts(c: np.ndarray) -> np.ndarray:
    return np.concatenate((c[None, :], np.zeros((NUMBERS - 1, len(c)), np.int64)))


def _all_bundles(packets: pa.Table) -> tuple[list[np.ndarray], np.ndarray]:
    all_ = [unbundled(*x) for x in zip(*(packets.column(c).to_pylist() for c in ("words", "places", "counts")), strict=True)]
    return [np.concatenate(x) for x in zip(*(w for w, _ in all_), strict=True)], np.concatenate([n for _, n in all_])


def _all_numbers(parts: pa.Table) -> tuple[list[np.ndarray], list[np.ndarray]]:
    return [unpacked(released(x)) for x in parts.column("keys").to_pylist()], [of_ints(x).reshape(NUMBERS, -1) for x in parts.column("numbers").to_pylist()]


def _count_trigrams(packets: pa.Table, shards: int) -> pa.Table:
    """Of a shard: its trigrams, the numbers of their contexts, and the pairs that end them by shards."""
    own = packets.column("shard")[0].as_py()
    (u, v, w), n = _all_bundles(packets)
    g, c, first = summed(gram(u, v, w), n[None, :])
    u, v, w = u[first], v[first], w[first]
    rows = [_part(3, own, g, _as_counts(c[0]))]
    keys, numbers, _ = summed(gram(u, v), _as_contexts(c[0]))
    rows.append(_part(2, own, keys, numbers))
    pairs, n, first = summed(gram(v, w), np.ones((1, len(v)), np.int64))
    for shard, at in _by_shard(pairs, shards):
        rows.append({"what": _PAIRS, "shard": shard} | dict(zip(("words", "places", "counts"), bundled([v[first[at]], w[first[at]]], n[0, at]), strict=True)))
    return _parts(rows)


def _count_pairs(parts: pa.Table, shards: int) -> pa.Table:
    """Of a shard: pairs by the different words before them, with their numbers as contexts; and what they say of words."""
    own = parts.column("shard")[0].as_py()
    keys, numbers = _all_numbers(parts.filter(pa.compute.equal(parts.column("what"), 2)))
    ends, rows = parts.filter(pa.compute.equal(parts.column("what"), _PAIRS)), []
    if ends.num_rows:
        (v, w), n = _all_bundles(ends)
        g, c, first = summed(gram(v, w), n[None, :])
        v, w, c = v[first], w[first], c[0]
        keys.append(g)
        numbers.append(_as_counts(c))
        said = summed(np.concatenate((gram(v), gram(w))), np.concatenate((_as_contexts(c), _as_counts(np.ones_like(c))), axis=1))
        rows = [_part(1, shard, said[0][at], said[1][:, at]) for shard, at in _by_shard(said[0], shards)]
    g, numbers, _ = summed(np.concatenate(keys), np.concatenate(numbers, axis=1))
    return _parts([_part(2, own, g, numbers), *rows])


def _count_words(parts: pa.Table) -> pa.Table:
    keys, numbers = _all_numbers(parts)
    g, numbers, _ = summed(np.concatenate(keys), np.concatenate(numbers, axis=1))
    return _parts([_part(1, parts.column("shard")[0].as_py(), g, numbers)])


def _ready(parts: pa.Table, off: dict[int, tuple[float, float, float]], total: int) -> pa.Table:
    """What a shard says of all its n-grams."""
    said = []
    for order, k, x in zip(*(parts.column(c).to_pylist() for c in ("what", "keys", "numbers")), strict=True):
        c, t, *n = of_ints(x).reshape(NUMBERS, -1)
        held = np.where(c > 0, c - np.take(np.array((0.0, *off[order])), np.minimum(c, 3)), 0.0) / (total if order == 1 else 1)
        freed = sum(d * m for d, m in zip(off[order + 1], n, strict=True)) if order < 3 else 0.0
        said.append((unpacked(released(k)), held, np.where(t > 0, freed / np.maximum(t, 1), 1.0), np.maximum(t, 1)))
    keys, *numbers = (np.concatenate(x) for x in zip(*said, strict=True))
    order = np.argsort(keys)
    row = [parts.column("shard")[0].as_py(), squeezed(packed(keys[order])), *(squeezed(_planes(x[order])) for x in numbers)]
    return pa.table([pa.array([v], t) for v, t in zip(row, (pa.int32(), *[pa.binary()] * 4), strict=True)], names=["shard", "keys", "held", "free", "t"])


def train(trusted: DataFrame) -> Model | None:
    """trusted: text. Shards take turns, so that little waits on disk at once."""
    spark = trusted.sparkSession
    size = trusted.agg(F.sum(F.octet_length("text"))).first()[0]
    if size is None:
        return None
    shards = 1 + int(size) // 3 // SHARD  # about six bytes a word, twice as many trigrams and pairs
    turns = min(TURNS, shards)
    paths = {k: fresh_path(spark, f"quality-{k}") for k in ("trigrams", "pairs")}

    turn_of = F.col("shard") % turns

    def kept(made: DataFrame, k: str) -> None:
        """In a folder for each what and turn, so that a turn reads no other's and its files can go."""
        with shuffles_freed(spark):
            made.withColumn("turn", turn_of).write.mode("append").option("compression", "zstd").partitionBy("what", "turn").parquet(paths[k])

    def those(k: str, what: str, turn: int) -> DataFrame:
        return spark.read.schema(f"{_PART}, turn int").parquet(paths[k]).where(what).where(F.col("turn") == turn).drop("turn")

    def gone(k: str, what: int, turn: int) -> None:
        remove(spark, f"{paths[k]}/what={what}/turn={turn}")

    for turn in range(turns):
        sent = trusted.select("text").mapInArrow(lambda b, turn=turn: _trigrams(b, shards, turn, turns), _PACKET)
        kept(sent.groupBy("shard").applyInArrow(lambda x: _count_trigrams(x, shards), _PART), "trigrams")
        del sent
        release(spark)
    done_with(trusted)
    for turn in range(turns):
        kept(those("trigrams", "what <> 3", turn).groupBy("shard").applyInArrow(lambda x: _count_pairs(x, shards), _PART), "pairs")
        for what in (2, _PAIRS):
            gone("trigrams", what, turn)
        release(spark)
    with shuffles_freed(spark):
        words = cut(spark.read.schema(f"{_PART}, turn int").parquet(paths["pairs"]).where("what = 1").drop("turn").groupBy("shard").applyInArrow(_count_words, _PART), "quality-words").select(*(x.split()[0] for x in _PART.split(", ")))

    def model(turn: int) -> DataFrame:
        return those("trigrams", "what = 3", turn).unionByName(those("pairs", "what = 2", turn)).unionByName(words.where(turn_of == turn))

    numbers = [c.split()[0] for c in _PART.split(", ") if c.endswith(" long")]
    said: dict[int, dict[str, int]] = {k: dict.fromkeys(numbers, 0) for k in (1, 2, 3)}
    for turn in range(turns):
        for r in model(turn).groupBy("what").agg(*[F.sum(c).alias(c) for c in numbers]).collect():  # a row for each order
            for c in numbers:
                said[r["what"]][c] += r[c]
    off = {k: discounts({i: r[f"c{i}"] for i in (1, 2, 3, 4)}) for k, r in said.items()}
    one = said[1]
    freed = sum(d * n for d, n in zip(off[1], (one["c1"], one["c2"], one["seen"] - one["c1"] - one["c2"]), strict=True))
    name, path = f"quality_{uuid.uuid4().hex}", fresh_path(spark, "quality-model")
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(shards, 1000))
    for turn in range(turns):
        ready = model(turn).select("shard", "what", "keys", "numbers").groupBy("shard").applyInArrow(lambda x: _ready(x, off, one["total"]), "shard int, keys binary, held binary, free binary, t binary")
        writer = ready.write.mode("append").bucketBy(buckets, "shard").sortBy("shard").option("compression", "zstd")
        with shuffles_freed(spark):
            (writer if turn else writer.option("path", path)).saveAsTable(name)
        del ready, writer
        gone("trigrams", 3, turn)
        gone("pairs", 2, turn)
        release(spark)
    for p in paths.values():
        remove(spark, p)
    done_with(words)
    return Model(spark.table(name), shards, freed / one["total"] / (one["seen"] + 1), name)


def _grams(texts: list[str], hasher: TokenHasher) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of all trigrams, then pairs, then words of the texts one after another, texts' numbers of tokens)"""
    tokens = token_hashes(texts, hasher)
    t = np.concatenate(tokens)
    return np.concatenate((gram(t[:-2], t[1:-1], t[2:]), gram(t[:-1], t[1:]), gram(t))), np.array([len(x) for x in tokens])


def _unique(x: np.ndarray) -> np.ndarray:
    """np.unique by sorting, which for hashes is many times faster than its table."""
    x = np.sort(x)
    return x[np.diff(x, prepend=~x[:1]) != 0]


def _distinct(grams: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Distinct hashes within texts, ascending: the same for any order of the texts."""
    each = []
    for g, sizes in grams:
        last, n = np.cumsum(sizes)[:-1], int(sizes.sum())
        inside = np.ones(len(g), dtype=bool)
        inside[last - 2] = inside[last - 1] = inside[n - 2 + last - 1] = False  # those over the end of a text
        each.append(_unique(g[inside]))
    return _unique(np.concatenate(each))


def _ask(block: pa.Table, shards: int) -> pa.Table:
    hasher = TokenHasher()
    asked = _distinct([_grams(b.column("__x_text").to_pylist(), hasher) for b in slices(block.to_batches(), "__x_text", most_bytes=1 << 20)])
    own = _shards(asked, shards)
    at = np.flatnonzero(np.diff(own, prepend=-1))
    parts = [squeezed(packed(x)) for x in np.split(asked, at[1:])]
    return pa.table([pa.array(own[at]), pa.array([block.column("__x_block")[0].as_py()] * len(at), pa.int32()), pa.array(parts, pa.binary())], names=["shard", "block", "keys"])


def _answer(asked: pa.Table, parts: pa.Table) -> pa.Table:
    keys, numbers = np.zeros(0, np.uint64), [np.zeros(0, np.float32)] * 3
    if parts.num_rows:
        keys, numbers = unpacked(released(parts.column("keys")[0].as_py())), [_floats(released(parts.column(c)[0].as_py())) for c in ("held", "free", "t")]
    asks = [unpacked(released(b.as_py())) for b in asked.column("keys")]
    out = [[squeezed(_planes(found(keys, x, ask, missing))) for ask in asks] for x, missing in zip(numbers, (0.0, 1.0, 1.0), strict=True)]
    return pa.table([asked.column("block"), asked.column("shard"), *(pa.array(x, pa.binary()) for x in out)], names=["block", "shard", "held", "free", "t"])


def _sums(block: pa.Table, answers: pa.Table, keep: list[str], free1: float) -> Iterator[pa.RecordBatch]:
    answers = answers.sort_by("shard")
    held, free, t = (np.concatenate([_floats(released(x.as_py())) for x in answers.column(c)]) for c in ("held", "free", "t"))
    hasher, batches = TokenHasher(), list(slices(block.to_batches(), "__x_text", most_bytes=1 << 20))
    grams = [_grams(b.column("__x_text").to_pylist(), hasher) for b in batches]
    asked = _distinct(grams)
    for batch, (g, sizes) in zip(batches, grams, strict=True):
        order = np.argsort(g)  # ascending, they are found much faster
        at = np.empty(len(g), dtype=np.int64)
        at[order] = np.minimum(np.searchsorted(asked, g[order]), len(asked) - 1)
        n = int(sizes.sum())
        three, two, one = at[: n - 2], at[n - 2 : 2 * n - 3], at[2 * n - 3 :]
        p1 = held[one[2:]].astype(np.float64) + free1
        p2 = held[two[1:]] / t[one[1:-1]] + free[one[1:-1]] * p1
        logs = np.log10(held[three] / t[two[:-1]] + free[two[:-1]] * p2)
        starts = np.cumsum(sizes) - sizes
        # between two texts stand two places that belong to neither
        sums = np.array([logs[s : s + m - 2].sum() for s, m in zip(starts.tolist(), sizes.tolist(), strict=True)])
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(sizes - 2), pa.array(sums)], names=[*keep, "__x_tokens", "__x_log10"])


def perplexities(docs: DataFrame, model: Model, keep: list[str]) -> DataFrame:
    """Columns keep and __x_tokens, __x_log10. Blocks take turns, so that little waits on disk at once."""
    plain = docs.select(*[f"`{c}`" for c in keep], whole_text(docs).alias("__x_text"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in plain.schema if f.name != "__x_text") + ", __x_tokens long, __x_log10 double"
    size = plain.agg(F.sum(F.octet_length("__x_text"))).first()[0] or 0
    passes = min(PASSES, 1 + int(size) // BLOCK)
    blocks = passes * (1 + int(size) // (BLOCK * passes))
    shards, free1 = model.shards, model.free1
    dealt = plain.withColumn("__x_block", F.pmod(F.xxhash64("__x_text", *[f"`{c}`" for c in keep]), F.lit(blocks)).cast("int"))

    def sums(_: tuple, block: pa.Table, answers: pa.Table) -> pa.Table:
        if not block.num_rows:
            return pa.Table.from_batches([], schema=arrow)
        return pa.Table.from_batches(list(_sums(block, answers, keep, free1))).cast(arrow)

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    arrow = to_arrow_schema(StructType.fromDDL(schema))
    out = None
    for turn in range(passes):
        part = dealt.where(F.col("__x_block") % passes == turn)
        asked = part.groupBy("__x_block").applyInArrow(lambda x: _ask(x, shards), "shard int, block int, keys binary")
        answers = asked.groupBy("shard").cogroup(model.parts.groupBy("shard")).applyInArrow(_answer, "block int, shard int, held binary, free binary, t binary")
        with shuffles_freed(docs.sparkSession):
            scored = cut(part.groupBy("__x_block").cogroup(answers.groupBy("block")).applyInArrow(sums, schema), f"quality-sums{turn}")
        del part, asked, answers
        release(docs.sparkSession)
        out = scored if out is None else out.unionAll(scored)
    return out


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """One row per document: doc_id, lang, n_tokens, perplexity, threshold, kept, trained_on.

    trained_on marks the rows the model has seen: their perplexity is low for that reason alone.
    """
    good = labels.where("quality = 1 and coalesce(toxic, 0) = 0").select(F.col("doc_id").cast("long").alias("__good")).distinct()
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), "text")
    order = F.xxhash64(F.lit(7), "__good")
    known = own.select("doc_id", "lang").join(good, F.col("doc_id") == F.col("__good")).groupBy("__good").agg(F.min("lang").alias("__l"))
    sizes = known.groupBy(F.col("__l").alias("__m")).agg(F.count(F.lit(1)).alias("n"))
    ranked = known.withColumn("rank", F.row_number().over(Window.partitionBy("__l").orderBy(order, "__good")))
    room = F.expr(f"rank <= n - greatest(n div 4, least({LEAST_ROWS}, n - 1))")
    chosen = cut(ranked.join(F.broadcast(sizes), F.col("__l").eqNullSafe(F.col("__m"))).where(room).select("__good"), "quality-chosen")  # sizes: a row for each language
    trusted = cut(own.join(chosen, F.col("doc_id") == F.col("__good"), "left_semi").select(whole_text(own)), "quality-trusted")
    model = train(trusted)
    if model is None:
        return own.select("doc_id", "lang", F.lit(None).cast("long").alias("n_tokens"), F.lit(None).cast("double").alias("perplexity"), F.lit(None).cast("double").alias("threshold"), F.lit(True).alias("kept"), F.lit(False).alias("trained_on"))
    scored = perplexities(own, model, ["doc_id", "lang"]).withColumn("ppl", F.pow(F.lit(10.0), F.least(-F.col("__x_log10") / F.col("__x_tokens"), F.lit(300.0))))
    model.drop()
    held = scored.join(good.join(chosen, "__good", "left_anti"), F.col("doc_id") == F.col("__good"), "left_semi")
    quantile = F.percentile_approx("ppl", QUANTILE, 10_000) * SLACK
    everywhere = held.agg(quantile.alias("t")).first()[0]
    each = held.groupBy(F.col("lang").alias("__lang")).agg(quantile.alias("t"), F.count(F.lit(1)).alias("n")).where(F.col("n") >= LEAST_ROWS).select("__lang", "t")
    threshold = F.coalesce(F.col("t"), F.lit(everywhere).cast("double"))
    seen = chosen.select(F.col("__good").alias("__seen"))
    scored = scored.join(seen, F.col("doc_id") == F.col("__seen"), "left")
    return scored.join(each, F.col("lang").eqNullSafe(F.col("__lang")), "left").select(
        "doc_id", "lang", F.col("__x_tokens").alias("n_tokens"), F.col("ppl").alias("perplexity"), threshold.alias("threshold"), F.coalesce(F.col("ppl") <= threshold, F.lit(True)).alias("kept"), F.col("__seen").isNotNull().alias("trained_on")
    )


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
