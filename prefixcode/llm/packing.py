"""Best-fit packing: a configuration linear program over the histogram of piece lengths.

Only the histogram (at most ``room`` numbers, whatever the corpus) comes to the driver. There,
multiplicative weights solve the covering program "use each configuration x times so that every
length is covered": the price of a length falls as it is covered, and a knapsack dynamic program
prices configurations. The solution is rounded down and what is left over is packed by best fit,
decreasing, over (length, count) classes. Pieces then find their places in parallel: the rank of a
piece among those of its length gives configuration, repetition and offset.

Cases: null text is empty; an empty text is the end token alone; a text longer than the room is cut
into pieces of which only the first may be shorter; repeated rows are packed each for itself; a null
doc_id is passed on; an empty table gives an empty result; other columns are left alone.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from prefixcode.llm.common import cut, id_text, slices, table

ROOM = 2048
END = 0
#: Rows of one length are ranked in shares of about so many.
SHARE_ROWS = 1 << 20


# ---------------------------------------------------------------- the program, on the histogram
def price(values: np.ndarray, lengths: np.ndarray, room: int) -> tuple[np.ndarray, np.ndarray]:
    """Unbounded knapsack. best[c]: the most value in c tokens; choice[c]: index of an item, or -1.

    lengths ascend.
    """
    best = np.zeros(room + 1)
    choice = np.full(room + 1, -1, dtype=np.int64)
    upto = np.searchsorted(lengths, np.arange(room + 1), side="right")
    for c in range(1, room + 1):
        k = upto[c]
        if k:
            with_item = best[c - lengths[:k]] + values[:k]
            i = int(with_item.argmax())
            if with_item[i] > best[c - 1]:
                best[c], choice[c] = with_item[i], i
                continue
        best[c], choice[c] = best[c - 1], -1
    return best, choice


def _configuration(choice: np.ndarray, lengths: np.ndarray, room: int) -> Counter:
    out: Counter = Counter()
    while room > 0:
        i = choice[room]
        if i < 0:
            room -= 1
        else:
            out[int(i)] += 1
            room -= int(lengths[i])
    return out


def solve(lengths: np.ndarray, counts: np.ndarray, room: int, rounds: int = 60, rate: float = 0.02, near: float = 0.99) -> dict[tuple[tuple[int, int], ...], float]:
    """The fractional program: configuration -> how often.

    A schedule says which share of each length may be covered after each round. In a round a
    dynamic program prices what is still open; for each length the best configuration that holds it
    is used, if its value is near the best one's, up to the schedule. Then the prices of lengths that
    are behind the schedule rise by a factor, and all are scaled so that no configuration is worth
    more than one sequence. Lengths that no good configuration takes stay open.
    """
    x: dict[tuple[tuple[int, int], ...], float] = {}
    need = counts.astype(float)
    left, y = need.copy(), lengths / room
    for t in range(rounds):
        allowed = need * (1 - (t + 1) / rounds) + 1e-9
        for _ in range(2):
            active = np.flatnonzero(left > allowed)
            if not len(active):
                break
            own = lengths[active]
            best, choice = price(y[active], own, room)
            held = y[active] + best[room - own]
            for a in np.argsort(-held, kind="stable"):
                if held[a] < near * held.max():
                    break
                if left[active[a]] <= allowed[active[a]]:
                    continue
                found = _configuration(choice, own, room - int(own[a]))
                found[int(a)] += 1
                idx = active[np.fromiter(found, dtype=np.int64)]
                times = np.fromiter(found.values(), dtype=float)
                much = float(((left[idx] - allowed[idx]) / times).min())
                if much > 0:
                    key = tuple(sorted((int(i), int(n)) for i, n in zip(idx, times, strict=True)))
                    x[key] = x.get(key, 0.0) + much
                    left[idx] -= much * times
        y = y * np.exp(rate * np.minimum((left - allowed) / need * rounds, 4))
        y /= price(y, lengths, room)[0][room]
    return x


def best_fit(lengths: np.ndarray, counts: np.ndarray, room: int) -> Counter:
    """Best fit, decreasing, with equal lengths and equal bins handled as classes."""
    bins: dict[int, Counter] = {}  # free room -> configuration -> how many bins
    for i in np.argsort(-lengths):
        size, left = int(lengths[i]), int(counts[i])
        while left:
            free = next((f for f in range(size, room) if bins.get(f)), room)
            if free == room:
                each = min(left, room // size)
                some = left // each
                bins.setdefault(room - each * size, Counter())[((int(i), each),)] += some
                left -= each * some
                continue
            config, many = next(iter(bins[free].items()))
            each = min(left, free // size)
            some = min(many, left // each)
            bins[free][config] -= some
            if not bins[free][config]:
                del bins[free][config]
            grown = (*config, (int(i), each))
            bins.setdefault(free - each * size, Counter())[grown] += some
            left -= each * some
    out: Counter = Counter()
    for found in bins.values():
        out += found
    return out


def plan(histogram: dict[int, int], room: int = ROOM) -> list[tuple[list[tuple[int, int]], int]]:
    """[([(length, times), ...], how many sequences), ...] that hold the histogram exactly."""
    out: list[tuple[list[tuple[int, int]], int]] = []
    if histogram.get(room):
        out.append(([(room, 1)], histogram[room]))
    items = sorted((k, v) for k, v in histogram.items() if k < room and v > 0)
    if not items:
        return out
    lengths, counts = (np.array(x, dtype=np.int64) for x in zip(*items, strict=True))
    left, whole, chosen = counts.copy(), Counter(), None
    for _ in range(4):  # what stays open or is rounded away is priced anew
        used = left > 0
        if not used.any():
            break
        ids = np.flatnonzero(used)
        for config, often in sorted(solve(lengths[ids], left[ids], room).items(), key=lambda kv: (-kv[1], kv[0])):
            real = tuple((int(ids[i]), n) for i, n in config)
            often = min(int(often), *(int(left[i]) // n for i, n in real))
            if often > 0:
                whole[real] += often
                for i, n in real:
                    left[i] -= n * often
        ids = np.flatnonzero(left > 0)
        total = whole.copy()
        for config, often in best_fit(lengths[ids], left[ids], room).items():
            total[tuple((int(ids[i]), n) for i, n in config)] += often
        if chosen is None or sum(total.values()) < sum(chosen.values()):
            chosen = total
        if sum(chosen.values()) * room < int((lengths * counts).sum()) + room:  # no fewer sequences can hold all
            break
    for config, often in sorted(chosen.items()):
        out.append(([(int(lengths[i]), n) for i, n in config], often))
    return out


# ---------------------------------------------------------------- pieces
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


#: A text with a longer run of blanks goes through the JSON file: the rank file's library runs out of stack on it.
BLANKS = 4096


def _tokenizer(name: str):
    """Byte-level BPE ids. The rank file holds the same vocabulary and merges as the JSON file and
    is several times faster; a text with a special token's string or a very long run of blanks goes
    through the JSON file."""
    import base64
    import re

    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(public_tokenizers.path(f"{name}.json"))
    special = [t.content for t in slow.get_added_tokens_decoder().values()]
    with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    fast = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    long_blank = re.compile(r"\s{%d}" % BLANKS)

    def ids(text: str) -> list[int]:
        if any(s in text for s in special) or len(text) >= BLANKS and long_blank.search(text):
            return slow.encode(text, add_special_tokens=False).ids
        return fast.encode_ordinary(text)

    return ids


def _pieces(batches: Iterator[pa.RecordBatch], room: int, name: str) -> Iterator[pa.RecordBatch]:
    encode = _tokenizer(name)
    for batch in slices(batches):
        out: tuple[list, ...] = ([], [], [], [], [])
        for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
            ids = np.array([*encode(text), END], dtype="<u4")
            at, piece = 0, 0
            while at < len(ids):
                end = at + ((len(ids) - at) % room or room)
                for col, v in zip(out, (doc_id, piece, at, end - at, zlib.crc32(ids[at:end].tobytes())), strict=True):
                    col.append(v)
                at, piece = end, piece + 1
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=[f.split()[0] for f in PIECES.split(", ")])


def pieces(docs: DataFrame, room: int = ROOM, tokenizer: str = "byte_bpe_50k") -> DataFrame:
    return id_text(docs).mapInArrow(lambda b: _pieces(b, room, tokenizer), PIECES)


def pack(found: DataFrame, room: int = ROOM) -> DataFrame:
    """pieces with a ``length`` of at most ``room`` -> the same and sequence_id, offset."""
    per = {r["length"]: r["n"] for r in found.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most room rows
    shares = max(1, -(-max(per.values(), default=0) // SHARE_ROWS))
    salted = found.withColumn("__salt", F.pmod(F.xxhash64(*found.columns), F.lit(shares)))
    own = W.partitionBy("length", "__salt").orderBy(*found.columns)
    before = W.partitionBy("length").orderBy("__salt").rowsBetween(W.unboundedPreceding, -1)
    if shares > 1:
        base = salted.groupBy("length", "__salt").agg(F.count(F.lit(1)).alias("__c")).withColumn("__base", F.coalesce(F.sum("__c").over(before), F.lit(0))).drop("__c")
        salted = salted.join(F.broadcast(base), ["length", "__salt"])  # room x shares rows
    else:
        salted = salted.withColumn("__base", F.lit(0).cast("long"))
    ranked = salted.withColumn("__rank", F.row_number().over(own) - 1 + F.col("__base"))
    starts: dict[int, list[tuple[int, int, int, int]]] = {}
    used: Counter = Counter()
    first = 0
    for config, often in plan(per, room):
        at = 0
        for length, n in config:
            starts.setdefault(length, []).append((used[length], n, first, at))
            used[length] += n * often
            at += n * length
        first += often
    slots = {k: np.array(v, dtype=np.int64).T for k, v in starts.items()}

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(c).to_numpy() for c in ("length", "__rank"))
            seq, off = np.empty(len(length), dtype=np.int64), np.empty(len(length), dtype=np.int64)
            for v in np.unique(length):
                here = np.flatnonzero(length == v)
                start, n, base, at = slots[int(v)]
                k = np.searchsorted(start, rank[here], side="right") - 1
                i = rank[here] - start[k]
                seq[here] = base[k] + i // n[k]
                off[here] = at[k] + (i % n[k]) * v
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(seq), pa.array(off)], names=[*names, "sequence_id", "offset"])

    names = found.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in found.schema) + ", sequence_id long, offset long"
    return ranked.select(*names, "__rank").mapInArrow(place, schema)


def packed(docs: DataFrame, room: int = ROOM) -> DataFrame:
    return pack(cut(pieces(docs, room), "pack-pieces"), room)


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed(table(spark, sf_dir, "documents"))
