"""Helpers shared by the training-data operators."""

from __future__ import annotations

import atexit
import contextlib
import gc
import re
import tempfile
import uuid
import weakref
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of anything but blank, tab, line feed, vertical tab, form feed, carriage return.
WORD = r"[^\x20\x09-\x0D]+"

_MADE: list[tuple[weakref.ref, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder all executors and the driver see.

    It is the one named by ``spark.checkpoint.dir``; only where that is unset (local tests) a
    temporary folder is made.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = f"file://{tempfile.gettempdir()}/checkpoints"
    return root.rstrip("/")


def _remove_all() -> None:
    for ref, path in _MADE:
        spark = ref()
        try:
            if spark is not None:
                remove(spark, path)
        except Exception:  # noqa: BLE001  the session may be gone already
            pass


atexit.register(_remove_all)


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def fresh_path(spark: SparkSession, label: str) -> str:
    path = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
    _MADE.append((weakref.ref(spark), path))
    return path


def cut(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: the lineage ends there.

    Lost executors then cost a re-read, not a re-computation, and columnar files prune columns
    for later passes. The files go when the driver exits.
    """
    spark = df.sparkSession
    path = fresh_path(spark, label)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def done_with(*frames: DataFrame) -> None:
    """Remove the files of tables from ``cut`` that nothing reads any more: what was made of them is written."""
    for df in frames:
        for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            if any(path.split("://")[-1].lstrip("/") == made.split("://")[-1].lstrip("/") for _, made in _MADE):
                remove(df.sparkSession, path)


def release(spark: SparkSession) -> None:
    """Let go of the shuffle files of frames that nothing refers to any more."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


@contextlib.contextmanager
def shuffles_freed(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of what is executed inside go when it has been, not when the driver collects garbage. Nothing executed inside may be asked again."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


def id_text(docs: DataFrame) -> DataFrame:
    """``doc_id`` and the whole text, null read as empty."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text(docs))


def whole_text(docs: DataFrame) -> Column:
    return F.coalesce(docs["text"].cast("string"), F.lit("")).alias("text")


def n_words(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def slices(batches: Iterator[pa.RecordBatch], text: str = "text", most_bytes: int = 8 << 20, most_rows: int = 4096) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that each holds few bytes of text (or one row)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = np.cumsum(np.nan_to_num(np.asarray(pa.compute.binary_length(batch.column(text)).to_numpy(zero_copy_only=False), dtype=float)))
        at = 0
        while at < batch.num_rows:
            base = size[at - 1] if at else 0
            end = max(at + 1, min(at + most_rows, int(np.searchsorted(size, base + most_bytes, side="right"))))
            yield batch.slice(at, end - at)
            at = end


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (xor-shift and odd multiplications)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def shingle_hashes(words: np.ndarray, n: int = 5) -> np.ndarray:
    """Hashes of all runs of ``n`` words; a shorter non-empty text is one shingle of all its words."""
    if not len(words):
        return words
    n = min(n, len(words))
    h = np.zeros(len(words) - n + 1, dtype=np.uint64)
    for i in range(n):
        h *= np.uint64(0x9E3779B97F4A7C15)
        h += words[i : len(words) - n + 1 + i]
        h ^= h >> np.uint64(29)
    return mix64(h)


#: Buckets of ``only_of``: at most so many rows are ever broadcast.
SIEVE = 1 << 20


def only_of(rows: DataFrame, ids: DataFrame, name: str) -> DataFrame:
    """Rows whose id occurs in ids (one bigint column of the same name, without repeats).

    Ids are hashed to SIEVE buckets; those in use, a table of bounded size, sieve the rows where
    they are read, so few others are moved; an exact join of what is left follows.
    """
    bucket = F.pmod(F.xxhash64(name), F.lit(SIEVE))
    used = ids.select(bucket.alias("__sieve")).distinct()
    sieved = rows.withColumn("__sieve", bucket).join(F.broadcast(used), "__sieve", "left_semi").drop("__sieve")
    return sieved.join(ids.hint("merge"), name, "left_semi")


class TokenHasher:
    """64-bit hashes of all words of many texts at once, without making the words.

    A word is a run of bytes other than the six blanks. Its hash is a polynomial in its bytes modulo
    2**64, from differences of a running sum, then mixed.
    """

    PART = 1 << 19
    _BLANKS = re.compile(rb"[\x20\x09-\x0D]")
    _P = 0x9E3779B97F4A7C15 * 2 + 1 & (1 << 64) - 1

    def __init__(self) -> None:
        self.blank = np.zeros(256, dtype=bool)
        self.blank[[0x20, *range(0x09, 0x0E)]] = True
        self.up = self.down = np.ones(1, dtype=np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) < n:
            n = max(n, 1 << 16)
            for name, base in (("up", self._P), ("down", pow(self._P, -1, 1 << 64))):
                p = np.full(n, base, dtype=np.uint64)
                p[0] = 1
                setattr(self, name, np.multiply.accumulate(p))

    def of(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(hash of every word, how many words each text has). Memory follows the longest word, not
        the texts: they are taken in parts of about PART bytes, cut at blanks."""
        parts: list[list[bytes]] = [[]]
        owner: list[list[int]] = [[]]
        room = self.PART
        for k, text in enumerate(texts):
            at = 0
            while at < len(text) or not text:
                end = len(text)
                if end - at > self.PART:
                    cut_at = self._BLANKS.search(text, at + self.PART)
                    end = cut_at.start() if cut_at else end
                if room < end - at and parts[-1]:
                    parts.append([])
                    owner.append([])
                    room = self.PART
                parts[-1].append(text[at:end] if at or end < len(text) else text)
                owner[-1].append(k)
                room -= end - at + 1
                at = end
                if not text:
                    break
        sizes = np.zeros(len(texts), dtype=np.int64)
        out = []
        for part, own in zip(parts, owner, strict=True):
            if part:
                h, n = self._of(part)
                out.append(h)
                np.add.at(sizes, own, n)
        return np.concatenate(out) if out else np.zeros(0, dtype=np.uint64), sizes

    def _of(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        raw = np.frombuffer(b" ".join(texts) + b" ", dtype=np.uint8)
        gap = self.blank[raw]
        edge = np.flatnonzero(gap[1:] != gap[:-1]) + 1
        if not gap[0]:
            edge = np.concatenate(([0], edge))
        start, end = edge[0::2], edge[1::2]
        self._powers(len(raw))
        total = np.zeros(len(raw) + 1, dtype=np.uint64)
        np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * self.up[: len(raw)], out=total[1:])
        h = mix64((total[end] - total[start]) * self.down[start] + (end - start).astype(np.uint64))
        sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
        stops = np.cumsum(sizes + 1)
        upto = np.searchsorted(start, stops, side="left")
        return h, np.diff(upto, prepend=0)

    def one(self, word: bytes) -> int:
        return int(self.of([word])[0][0])


class HashIndex:
    """Places of 64-bit keys: an open-addressing table, looked up for many keys at once."""

    def __init__(self, keys: np.ndarray):
        size = 1 << max(4, int(np.ceil(np.log2(max(len(keys), 1) * 2 + 1))))
        self.mask = np.uint64(size - 1)
        self.keys = np.zeros(size, dtype=np.uint64)
        self.at = np.full(size, -1, dtype=np.int32)
        todo = np.arange(len(keys))
        spot = (keys & self.mask).astype(np.int64)
        while len(todo):
            free = self.at[spot] < 0
            first = np.full(size, -1, dtype=np.int64)
            first[spot[free][::-1]] = todo[free][::-1]
            won = free & (first[spot] == todo)
            self.keys[spot[won]], self.at[spot[won]] = keys[todo[won]], todo[won]
            todo, spot = todo[~won], (spot[~won] + 1) % size

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The place of each key among those given at the start, or -1."""
        spot = (keys & self.mask).astype(np.int64)
        out = self.at[spot]
        miss = np.flatnonzero((self.keys[spot] != keys) & (out >= 0))
        out[miss] = -1
        spot = spot[miss]
        while len(miss):
            spot = (spot + 1) & int(self.mask)
            hit = self.at[spot]
            same = (hit >= 0) & (self.keys[spot] == keys[miss])
            out[miss[same]] = hit[same]
            go = (hit >= 0) & ~same
            miss, spot = miss[go], spot[go]
        return out.astype(np.int64)


def lowered(texts: list[str]) -> list[bytes]:
    return [t.lower().encode("utf-8", "surrogatepass") for t in texts]


def shingled(texts: list[str], hasher: TokenHasher, n: int = 5) -> list[np.ndarray]:
    """Each text's shingles of ``n`` lower-cased words, in order. 1 to n - 1 words are one shingle."""
    words, sizes = hasher.of(lowered(texts))
    all_ = shingle_hashes(words, n) if len(words) >= n else words[:0]
    out, at = [], 0
    for size in sizes.tolist():
        out.append(all_[at : at + size - n + 1] if size >= n else shingle_hashes(words[at : at + size], n))
        at += size
    return out
