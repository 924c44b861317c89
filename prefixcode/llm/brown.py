"""Language-model scoring with a class-based bigram model (exchange clustering).

log10 P(w | v) = log10(mix * P(class w | class v) * P(w | class w) + (1 - mix) * P(w)), all smoothed.

* Words are counted over all training rows. Words at or above ``KNOWN`` of all tokens (so at most
  1 / KNOWN of them) travel with the model and are assigned to classes by exchange: in each round every word
  of one half moves to the class under which its left and right neighbours' classes are most likely, given
  the other words' classes. Bigrams are counted once and laid out by word, many packed in a row; a word's class is
  found where its neighbours are, and only that is sent to the driver.
* All rarer words, however many, then take the class that suits their neighbours in the same way, in a table of
  their own. Scoring sends a text's rare tokens to that table, with the class before and the word after
  them, and adds what comes back.

Cases: null text is empty and has the end token only; a null doc_id has no remainder:
it is scored as not held out and not trained on; with no training rows N and V are 0;
repeated rows count each; the longest text is read whole; extra columns are left alone.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefixcode.llm.common import HashIndex, TokenHasher, cut, done_with, id_text, mix64, slices, table

KNOWN = 5e-7
CLASSES = 64
ROUNDS = 6
MIX = 0.95
BUCKET = 500_000  # tokens whose pairs are counted in one task, about
PART = 1 << 15  # pairs in a row of contexts, about
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


class Tokens:
    """Hashes of all tokens of texts, A-Z lower-cased, an end after each text."""

    def __init__(self) -> None:
        self.hasher = TokenHasher()
        self.end = np.uint64(self.hasher.one(b"the end of a text") ^ 1)

    def of(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(hashes, where each text ends)."""
        words, sizes = self.hasher.of([t.encode("utf-8", "surrogatepass").translate(_LOWER) for t in texts])
        ends = np.cumsum(sizes + 1)
        out = np.empty(int(ends[-1]), dtype=np.uint64)
        out[ends - 1] = self.end
        out[np.arange(len(words)) + np.repeat(np.arange(len(texts)), sizes)] = words
        return out, ends


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    tokens, held, size = Tokens(), [], 0

    def flush() -> Iterator[pa.RecordBatch]:
        h, c = np.unique(np.concatenate(held), return_counts=True)
        held.clear()
        for at in range(0, len(h), 50_000):
            yield pa.RecordBatch.from_arrays([pa.array(h[at : at + 50_000].view(np.int64)), pa.array(c[at : at + 50_000])], names=["h", "c"])

    for batch in slices(batches, most_bytes=1 << 20):
        held.append(tokens.of(batch.column("text").to_pylist())[0])
        size += len(held[-1])
        if size > 2_000_000:
            yield from flush()
            size = 0
    if held:
        yield from flush()


def _previous(codes: np.ndarray, ends: np.ndarray, end: int) -> np.ndarray:
    out = np.empty_like(codes)
    out[1:] = codes[:-1]
    out[0] = end
    out[ends[:-1]] = end
    return out


class Model:
    """What a scoring task needs. All arrays are bounded by 1 / KNOWN and classes."""

    def __init__(self, hashes: np.ndarray, counts: np.ndarray, total: int, distinct: int):
        self.hashes, self.counts, self.total, self.distinct = hashes, counts, total, distinct
        end = Tokens().end.view(np.int64)
        at = np.flatnonzero(hashes == end)
        self.end = int(at[0]) if len(at) else -1
        self.clustered = np.flatnonzero(hashes != end)
        self.n_classes = CLASSES + 2  # the end's and that of words without training tokens
        self.classes = np.zeros(len(hashes), dtype=np.int16)
        order = self.clustered[np.lexsort((hashes[self.clustered], -counts[self.clustered]))]
        self.classes[order] = np.arange(len(order)) % CLASSES
        if self.end >= 0:
            self.classes[self.end] = CLASSES
        self.transitions = np.zeros((self.n_classes, self.n_classes))
        self.rare_in_class = np.zeros(self.n_classes)  # tokens of rarer words
        self.mix = MIX

    @property
    def rare(self) -> int:
        return self.n_classes - 1

    def class_of(self, codes: np.ndarray) -> np.ndarray:
        if not len(self.classes):
            return np.full(len(codes), self.rare)
        return np.where(codes >= 0, self.classes[np.maximum(codes, 0)], self.rare).astype(np.int64)

    def prepare(self) -> None:
        """Log tables from counts and transitions."""
        t = self.transitions + 0.5
        self.p_class = t / t.sum(axis=1, keepdims=True)
        self.uni_den = self.total + 0.5 * (self.distinct + 1)
        self.in_class = np.maximum(np.bincount(self.classes.astype(np.int64), weights=self.counts, minlength=self.n_classes) + self.rare_in_class, 1)
        self.p_word = self.counts / self.in_class[self.classes]
        self.p_uni = (self.counts + 0.5) / self.uni_den
        self.base_log = np.log10(self.p_uni)
        self.rare_den = 0.5


def _known(train: DataFrame, label: str) -> tuple[DataFrame, Model]:
    counts = cut(train.mapInArrow(_count, "h long, c long").groupBy("h").agg(F.sum("c").alias("c")), label)
    total, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    known = counts.where(F.col("c") >= F.lit(KNOWN * total)).toArrow()  # at most 1 / KNOWN rows
    h, c = (np.asarray(known.column(x).to_numpy(), dtype=np.int64) for x in ("h", "c"))
    order = np.argsort(h)
    return counts, Model(h[order], c[order], int(total), int(distinct))


def _planes(x: np.ndarray) -> bytes:
    return x.view(np.uint8).reshape(len(x), -1).T.tobytes()


def packed_pairs(first: np.ndarray, other: np.ndarray, n: np.ndarray) -> bytes:
    """Pairs by ascending ``first`` as bytes, first bytes first: differences and upper bytes are mostly 0."""
    return _planes(np.diff(first, prepend=np.int32(0))) + _planes(other) + _planes(n.astype(np.int64))


def pairs_of(b: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first, other, count). first: twice a word's place, and one more where ``other`` follows the word; or, of two
    that aren't clustered, -1 - class of the left one. other: a clustered word's place, or -1 - class of any other."""
    raw, m = np.frombuffer(b, np.uint8), len(b) // 16
    first, other = (np.ascontiguousarray(raw[4 * m * i : 4 * m * (i + 1)].reshape(4, m).T).view(np.int32).ravel() for i in (0, 1))
    return np.cumsum(first, dtype=np.int32), other, np.ascontiguousarray(raw[8 * m :].reshape(8, m).T).view(np.int64).ravel()


def _bigrams(batches: Iterator[pa.RecordBatch], model: Model, buckets: int) -> Iterator[pa.RecordBatch]:
    """(bucket, pairs): each pair of tokens at both of its words, dealt by word."""
    tokens, places = Tokens(), HashIndex(model.hashes.view(np.uint64))
    moves = np.zeros(len(model.hashes) + 1, dtype=bool)
    moves[model.clustered] = True
    held: list[tuple[np.ndarray, np.ndarray]] = []
    shift = model.n_classes + 2
    base, span = len(model.hashes) + shift, 2 * len(model.hashes) + shift

    def ids(codes: np.ndarray) -> np.ndarray:
        clustered = (codes >= 0) & moves[np.maximum(codes, 0)]
        return np.where(clustered, codes, -1 - model.class_of(codes))

    def keys(bucket: np.ndarray | int, first: np.ndarray, other: np.ndarray) -> np.ndarray:
        return (bucket * span + first + shift) * base + other + shift

    def flush() -> Iterator[pa.RecordBatch]:
        if not held:
            return
        left, right = (np.concatenate([h[i] for h in held]) for i in (0, 1))
        held.clear()
        r, l, none = right >= 0, left >= 0, (right < 0) & (left < 0)
        key, n = np.unique(np.concatenate((keys(right[r] % buckets, right[r] * 2, left[r]), keys(left[l] % buckets, left[l] * 2 + 1, right[l]), keys(0, left[none], right[none]))), return_counts=True)
        place, other = key // base, (key % base - shift).astype(np.int32)
        bucket, first = place // span, (place % span - shift).astype(np.int32)
        at = np.flatnonzero(np.diff(bucket, prepend=-1))
        pairs = [packed_pairs(first[i:j], other[i:j], n[i:j]) for i, j in zip(at.tolist(), [*at[1:].tolist(), len(key)], strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array(bucket[at].astype(np.int32)), pa.array(pairs, pa.binary())], names=["bucket", "pairs"])

    size = 0
    for batch in slices(batches, most_bytes=1 << 20):
        hashes, ends = tokens.of(batch.column("text").to_pylist())
        codes = places.find(hashes)
        now = ids(codes)
        held.append((_previous(now, ends, -1 - CLASSES), now))
        size += len(codes)
        if size >= 600_000:
            yield from flush()
            size = 0
    yield from flush()


def _contexts(bucket: pa.Table, half: np.ndarray) -> pa.Table:
    """A bucket's pairs, counted and laid out by word, PART or a few more in a row; a word is whole in one row."""
    first, other, n = (np.concatenate(x) for x in zip(*(pairs_of(b.as_py()) for b in bucket.column("pairs")), strict=True))
    order = np.lexsort((other, first))
    first, other, n = first[order], other[order], n[order]
    new = np.flatnonzero(np.concatenate(([True], (first[1:] != first[:-1]) | (other[1:] != other[:-1]))))
    first, other, n = first[new], other[new], np.add.reduceat(n, new)
    out: list[tuple[bool, bytes]] = []
    mine = np.where(first >= 0, half[np.maximum(first, 0) >> 1], False)
    for side in (False, True):
        x = [c[mine == side] for c in (first, other, n)]
        if len(x[0]):
            begins = np.flatnonzero(np.diff(x[0] >> 1, prepend=~(x[0][0] >> 1)))  # of words
            cuts = begins[np.flatnonzero(np.diff(begins // PART, prepend=-1))].tolist()
            out += [(side, packed_pairs(*(c[i:j] for c in x))) for i, j in zip(cuts, [*cuts[1:], len(x[0])], strict=True)]
    return pa.table([pa.array([h for h, _ in out], pa.bool_()), pa.array([b for _, b in out], pa.binary())], names=["half", "pairs"])


def contexts_of(train: DataFrame, model: Model) -> DataFrame:
    """(half, pairs): all pairs of neighbours in training text at the words of each, by ``pairs_of``."""
    half = (mix64(model.hashes.view(np.uint64)) & np.uint64(1)).astype(bool)
    buckets = 1 + model.total // BUCKET
    dealt = train.mapInArrow(lambda b: _bigrams(b, model, buckets), "bucket int, pairs binary")
    return cut(dealt.groupBy("bucket").applyInArrow(lambda x: _contexts(x, half), "half boolean, pairs binary"), "lm-contexts")


def _whole_words(batches: Iterator[pa.RecordBatch], rows: int = 1 << 15) -> Iterator[list[np.ndarray]]:
    """Columns of many rows at once, cut between two words; rows of a word follow each other."""
    held, size = [], 0
    for b in batches:
        for at in range(0, b.num_rows, rows):
            held.append([c.to_numpy() for c in b.slice(at, rows).columns])
            size += len(held[-1][0])
            if size < rows:
                continue
            x = [np.concatenate(c) for c in zip(*held, strict=True)]
            at_last = int(np.flatnonzero(x[0] == x[0][-1])[0])
            if at_last:
                yield [c[:at_last] for c in x]
            held = [[c[at_last:] for c in x]]
            size = len(held[0][0])
    if size:
        yield [np.concatenate(c) for c in zip(*held, strict=True)]


class Gains:
    """How well each class suits words, from their neighbours' classes, under given transitions."""

    def __init__(self, trans: np.ndarray):
        row, col = trans.sum(axis=1), trans.sum(axis=0)
        t = len(trans)
        self.to = np.log(trans[:, :CLASSES] + 0.5) - np.log(row[:, None] + 0.5 * t)  # from any class into b
        self.out = np.log(trans[:CLASSES] + 0.5) - np.log(row[:CLASSES, None] + 0.5 * t)  # from b into any class
        self.size = np.log(np.maximum(col[:CLASSES], 1))

    def of(self, word: np.ndarray, side: np.ndarray, c: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(words, a row of gains for each)."""
        ids, local = np.unique(word, return_inverse=True)
        t = self.to.shape[0]
        sums = np.bincount((local * 2 + side) * t + c, weights=n, minlength=len(ids) * 2 * t).reshape(len(ids), 2, t)
        left, right = sums[:, 0], sums[:, 1]
        return ids, left @ self.to + right @ self.out.T - left.sum(axis=1)[:, None] * self.size[None, :]


def _choose(batches: Iterator[pa.RecordBatch], gains: Gains, class_of: Callable[[np.ndarray], np.ndarray]) -> Iterator[pa.RecordBatch]:
    for word, side, other, n in _whole_words(batches):
        ids, gain = gains.of(word, side, class_of(other), n)
        yield pa.RecordBatch.from_arrays([pa.array(ids.astype(np.int64)), pa.array(gain.argmax(axis=1).astype(np.int32))], names=["word", "class"])


def exchange(model: Model, contexts: DataFrame, rounds: int = ROUNDS) -> list[float]:
    """Assign classes; gives the training log likelihood (class part) before each round."""
    t = model.n_classes
    said = []
    for k in range(rounds if len(model.clustered) else 0):
        trans = class_bigrams(model, contexts)
        row, col = trans.sum(axis=1), trans.sum(axis=0)
        said.append(float((trans * np.log((trans + 0.5) / (row[:, None] + 0.5 * t))).sum() - (col[:CLASSES] * np.log(np.maximum(col[:CLASSES], 1))).sum()))

        def choose(batches: Iterator[pa.RecordBatch], gains: Gains = Gains(trans), classes: np.ndarray = model.classes) -> Iterator[pa.RecordBatch]:  # noqa: B008
            for batch in batches:
                for pairs in batch.column("pairs"):
                    first, other, n = pairs_of(pairs.as_py())
                    own = first >= 0
                    first, other, n = first[own], other[own], n[own]
                    if len(first):
                        ids, gain = gains.of(first >> 1, first & 1, _class_of(other, classes), n)
                        yield pa.RecordBatch.from_arrays([pa.array(ids.astype(np.int64)), pa.array(gain.argmax(axis=1).astype(np.int32))], names=["word", "class"])

        mine = contexts.where(F.col("half") == bool(k % 2 == 0)).select("pairs")
        got = mine.mapInArrow(choose, "word long, class int").toArrow()  # at most 1 / KNOWN rows
        word, to = (got.column(c).to_numpy() for c in ("word", "class"))
        moved = model.classes.copy()
        moved[word] = to
        model.classes = moved
    return said


def _class_of(ids: np.ndarray, classes: np.ndarray) -> np.ndarray:
    """Of ids as in ``pairs_of``."""
    return np.where(ids >= 0, classes[np.maximum(ids, 0)], -1 - ids).astype(np.int64)


def _rare_contexts(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    """(h, side, class of the neighbour, the neighbour if it is rare too or else 0) of words that don't travel."""
    tokens, places = Tokens(), HashIndex(model.hashes.view(np.uint64))
    for batch in slices(batches, most_bytes=1 << 20):
        hashes, ends = tokens.of(batch.column("text").to_pylist())
        codes = places.find(hashes)
        now, rare = model.class_of(codes), codes < 0
        for side in (0, 1):
            at = np.flatnonzero(rare)
            if side:
                at = at[~np.isin(at, ends - 1)]  # nothing follows an end
                c, beside = now[at + 1], np.where(rare[at + 1], hashes[at + 1], np.uint64(0))
            else:
                first = np.isin(at, np.concatenate(([0], ends[:-1])))
                before = np.maximum(at - 1, 0)
                c, beside = np.where(first, CLASSES, now[before]), np.where(~first & rare[before], hashes[before], np.uint64(0))
            if len(at):
                yield pa.RecordBatch.from_arrays([pa.array(hashes[at].view(np.int64)), pa.array(np.full(len(at), side, np.int32)), pa.array(c), pa.array(beside.view(np.int64))], names=["h", "side", "c", "beside"])


def rare_classes(train: DataFrame, counts: DataFrame, model: Model) -> DataFrame:
    """(h, c, class) of all words that don't travel; their tokens come into the model's transitions and class sizes."""
    rare = counts.where(F.col("c") < F.lit(KNOWN * model.total))
    trans = model.transitions
    if not rare.limit(1).count():
        return rare.select("h", "c", F.lit(None).cast("int").alias("class"))
    found = cut(train.mapInArrow(lambda b: _rare_contexts(b, model), "h long, side int, c long, beside long").withColumn("n", F.lit(1).cast("long")), "lm-rare-contexts")
    gains = Gains(trans)
    laid = found.select("h", "side", "c", "n").repartition("h").sortWithinPartitions("h")
    chosen = cut(laid.mapInArrow(lambda b: _choose(b, gains, lambda x: x), "h long, class int"), "lm-rare-chosen")
    out = cut(rare.join(chosen, "h").select("h", "c", "class"), "lm-rare-classes")
    for r in out.groupBy("class").agg(F.sum("c").alias("n")).collect():
        model.rare_in_class[r["class"]] = r["n"]
    trans[model.rare] = trans[:, model.rare] = 0
    own = found.join(chosen, "h")
    for r in own.where("beside = 0").groupBy("side", "c", "class").agg(F.sum("n").alias("n")).collect():  # at most classes squared rows, twice
        at = (r["c"], r["class"]) if r["side"] == 0 else (r["class"], r["c"])
        trans[at] += r["n"]
    both = own.where("beside <> 0 and side = 0").join(chosen.select(F.col("h").alias("beside"), F.col("class").alias("left")), "beside")
    for r in both.groupBy("left", "class").agg(F.sum("n").alias("n")).collect():
        trans[r["left"], r["class"]] += r["n"]
    done_with(found, chosen)
    return out


def class_bigrams(model: Model, contexts: DataFrame) -> np.ndarray:
    t, classes = model.n_classes, model.classes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(t * t)
        for b in batches:
            for pairs in b.column("pairs"):
                first, other, n = pairs_of(pairs.as_py())
                own, beside = _class_of(np.where(first >= 0, first >> 1, first), classes), _class_of(other, classes)
                after = (first >= 0) & (first & 1 == 1)  # these stand at the word they follow, too, if that is clustered
                left, right = np.where((first >= 0) & ~after, beside, own), np.where((first >= 0) & ~after, own, beside)
                once = ~after | (other < 0)
                total += np.bincount(left[once] * t + right[once], weights=n[once], minlength=t * t)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at].astype(np.int64))], names=["at", "n"])

    got = contexts.select("pairs").mapInArrow(run, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()  # at most classes squared rows
    out = np.zeros(t * t)
    out[got.column("at").to_numpy()] = got.column("n").to_numpy()
    return out.reshape(t, t)


def learn(train: DataFrame) -> tuple[DataFrame, Model, list[float]]:
    """train: text. Gives words that don't travel (h, c, class), the model, and the exchange's likelihoods."""
    counts, model = _known(train, "lm-counts")
    said: list[float] = []
    rare = counts.limit(0).select("h", "c", F.lit(None).cast("int").alias("class"))
    if model.total:
        contexts = contexts_of(train, model)
        said = exchange(model, contexts)
        model.transitions = class_bigrams(model, contexts)
        done_with(contexts)
        rare = rare_classes(train, counts, model)
    model.prepare()
    return rare, model, said


SCORED = "row long, doc_id long, n_tokens long, n_sure long, base double, class double, rare array<long>, left array<int>, next array<int>"


def _score(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    """Sums over tokens whose own and previous word travel with the model. Of the others: the hash, the class before
    (-1: rare too) and the place of the word after (-1: rare too, or none)."""
    from pyspark import TaskContext

    row = TaskContext.get().partitionId() << 36
    tokens, places = Tokens(), HashIndex(model.hashes.view(np.uint64))
    for batch in slices(batches, most_bytes=1 << 19):
        hashes, ends = tokens.of(batch.column("text").to_pylist())
        codes = places.find(hashes)
        sure, at = codes >= 0, np.maximum(codes, 0)
        starts = np.concatenate(([0], ends[:-1]))
        now = model.class_of(codes)
        before = _previous(now, ends, CLASSES)
        after_rare = np.concatenate(([False], ~sure[:-1]))
        after_rare[starts] = False
        base_den = math.log10(model.uni_den)
        if len(model.hashes):
            base = np.where(sure, model.base_log[at], -base_den)
            own = np.log10(model.mix * model.p_class[before, now] * model.p_word[at] + (1 - model.mix) * model.p_uni[at])
        else:
            base, own = np.full(len(codes), -base_den), np.zeros(len(codes))
        own = np.where(sure & ~after_rare, own, 0.0)
        where = np.flatnonzero(~sure)
        left = np.where(after_rare[where], -1, before[where])
        follow = np.concatenate((codes[1:], [-1]))
        follow[ends - 1] = -1
        cuts = pa.array(np.searchsorted(where, np.concatenate((starts, ends[-1:]))).astype(np.int32))
        lists = [pa.ListArray.from_arrays(cuts, pa.array(x)) for x in (hashes[where].view(np.int64), left.astype(np.int32), follow[where].astype(np.int32))]
        k = batch.num_rows
        cols = [pa.array(np.arange(row, row + k)), batch.column("doc_id"), pa.array(ends - starts), pa.array(np.add.reduceat(sure.astype(np.int64), starts)), pa.array(np.add.reduceat(base, starts)), pa.array(np.add.reduceat(own, starts)), *lists]
        row += k
        yield pa.RecordBatch.from_arrays(cols, names=[f.split()[0] for f in SCORED.split(", ")])


def _add_rare(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    """Log probabilities of rare tokens and of those after them, and how many have been seen."""
    for b in batches:
        logs, own, hits = np.zeros(b.num_rows), np.zeros(b.num_rows), np.zeros(b.num_rows, dtype=np.int64)
        for i, (words, left, follow) in enumerate(zip(*(b.column(c) for c in ("words", "left", "next")), strict=True)):
            if not words.is_valid:
                continue
            c, cls = (words.values.field(x).to_numpy() for x in ("c", "class"))
            left, follow = left.values.to_numpy(), follow.values.to_numpy()
            prev = np.where(left >= 0, left, np.concatenate(([model.rare], cls[:-1])))
            p = np.where(c > 0, c / model.in_class[cls], 0.5 / model.rare_den)
            total = np.log10(model.mix * model.p_class[prev, cls] * p + (1 - model.mix) * (c + 0.5) / model.uni_den).sum()
            f = follow >= 0
            if f.any():
                n = follow[f]
                total += np.log10(model.mix * model.p_class[cls[f], model.classes[n].astype(np.int64)] * model.p_word[n] + (1 - model.mix) * model.p_uni[n]).sum()
            logs[i], own[i], hits[i] = np.log10(c + 0.5).sum(), total, (c > 0).sum()
        plain = [b.column(c) for c in ("doc_id", "n_tokens", "n_sure", "base", "class")]
        yield pa.RecordBatch.from_arrays([*plain, pa.array(logs), pa.array(own), pa.array(hits)], names=["doc_id", "n_tokens", "n_sure", "base", "class", "logs", "own", "hits"])


def score(docs: DataFrame, rare: DataFrame, model: Model) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score for each row of docs."""
    part = cut(id_text(docs).mapInArrow(lambda b: _score(b, model), SCORED), "lm-scored")
    tokens = part.select("row", F.posexplode("rare").alias("i", "h"))
    word = F.struct("i", F.coalesce(F.col("c"), F.lit(0)).alias("c"), F.coalesce(F.col("class"), F.lit(model.rare)).alias("class"))
    found = tokens.join(rare, "h", "left").groupBy("row").agg(F.sort_array(F.collect_list(word)).alias("words"))
    whole = part.drop("rare").join(found, "row", "left").drop("row")
    return whole.mapInArrow(lambda b: _add_rare(b, model), "doc_id long, n_tokens long, n_sure long, base double, class double, logs double, own double, hits long").select(
        "doc_id",
        "n_tokens",
        (F.col("n_sure") + F.col("hits")).alias("n_known"),
        F.lit(model.total).cast("long").alias("train_tokens"),
        (F.col("base") + F.col("logs")).alias("base_score"),
        (F.col("class") + F.col("own")).alias("score"),
    )


def held_out(docs: DataFrame):
    return F.crc32(F.col("doc_id").cast("string")) % 5 == 1


def lm_scores(docs: DataFrame) -> DataFrame:
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    train = id_text(own.where(F.col("doc_id").isNotNull() & ~held_out(own))).select("text")
    rare, model, _ = learn(train)
    out = score(own, rare, model)
    return out.select("doc_id", F.coalesce(held_out(out), F.lit(False)).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score", (-F.col("score") / F.col("n_tokens")).alias("log10_perplexity"))


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scores(table(spark, sf_dir, "documents"))
