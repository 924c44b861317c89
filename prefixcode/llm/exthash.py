"""Exact deduplication over an extendible-hash index on shared files.

1. Each scan task collapses equal texts of a window of rows (compared byte by byte). A window's
   survivor, the row with the largest doc_id, is a representative and keeps the text; the other rows
   keep only the representative's number. All rows go to shared files once, so later passes can't
   disagree and a lost executor costs a re-read.
2. The directory: representatives are counted by the first bits of their hash; starting from one
   bucket, each overfull bucket is split on its next bit, and the directory doubles when a bucket
   has used all its bits. It has at most 2**MAX_DEPTH entries, whatever the corpus.
3. Owner tasks get key ranges: representatives are dealt out by bucket and sorted by hash. A task
   holds one hash value's chain at a time: each distinct text with that hash is one link, found by
   comparing bytes, so colliding hashes never merge different texts. A bucket that stays overfull at
   the greatest depth is simply read on in order, page after page.
   A text with very many representatives (copies all over the corpus) is folded in shares first,
   also by comparing bytes, so its owner gets one for each share.
4. The owner's verdict for each representative (who stays, how many rows) joins the rows by the
   representative's number, which at most one window of rows shares: no key is hot.

Cases: null text equals the empty text; among equal texts the largest doc_id stays, a null doc_id
counts below all others, and of rows that tie on doc_id exactly one stays; an empty table gives an
empty result; extra columns may have any names but those starting with __x_.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, LongType, StringType, StructField, StructType

from prefixcode.llm.common import cut, slices, table, whole_text

MAX_DEPTH = 16
#: A bucket may hold so many bytes of representatives' texts before it is split.
BUCKET_BYTES = 4 << 20
#: Rows collapsed together in a scan task hold at most so many bytes of text.
WINDOW_BYTES = 24 << 20
#: Representatives of one hash that go to its owner as they are.
HOT = 1024
_HASH, _REP, _IS, _SHA, _N, _ID, _TEXT = "__x_hash", "__x_rep", "__x_is_rep", "__x_sha", "__x_rows", "__x_id", "__x_text"
_BUCKET, _ENTRY, _SALT = "__x_bucket", "__x_entry", "__x_salt"
_VERDICT = "__x_v_rep long, __x_v_keep long, __x_v_size long, __x_v_stays boolean"


def split_directory(sizes: dict[int, int], depth: int = MAX_DEPTH, most: int = BUCKET_BYTES) -> tuple[int, list[int]]:
    """sizes: first ``depth`` bits -> load. Gives the global depth and the directory.

    directory[first bits of that depth] is a bucket's number; buckets are numbered by key range.
    """
    load = [0] * (1 << depth)
    for prefix, n in sizes.items():
        load[prefix] += n
    total = [load]
    while len(total[-1]) > 1:  # total[-1 - d][p]: the load under the prefix p of d bits
        level = total[-1]
        total.append([a + b for a, b in zip(level[::2], level[1::2], strict=True)])
    leaves: list[tuple[int, int]] = []  # (local depth, prefix)
    todo = [(0, 0)]
    while todo:
        local, prefix = todo.pop()
        if total[depth - local][prefix] > most and local < depth:
            todo += [(local + 1, 2 * prefix + 1), (local + 1, 2 * prefix)]
        else:
            leaves.append((local, prefix))
    deepest = max(local for local, _ in leaves)
    directory: list[int] = []
    for bucket, (local, _) in enumerate(leaves):
        directory += [bucket] * (1 << (deepest - local))
    return deepest, directory


def _collapse(batches: Iterator[pa.RecordBatch], names: list[str]) -> Iterator[pa.RecordBatch]:
    """Rows of a window with equal texts share a representative; only that one keeps the text."""
    from pyspark import TaskContext
    from xxhash import xxh3_64_intdigest

    part, number = TaskContext.get().partitionId(), 0
    held: list[pa.RecordBatch] = []
    size = 0

    def flush() -> Iterator[pa.RecordBatch]:
        nonlocal number, held, size
        if not held:
            return
        window = pa.Table.from_batches(held)
        held, size = [], 0
        texts, ids = window.column(_TEXT).to_pylist(), window.column(_ID).to_pylist()
        first: dict[str, int] = {}
        count: dict[int, int] = {}
        of = []
        for k, text in enumerate(texts):
            g = first.setdefault(text, k)
            of.append(g)
            count[g] = count.get(g, 0) + 1
        stays: dict[int, int] = {}
        for k, g in enumerate(of):
            s = stays.get(g)
            if s is None or (ids[k] is not None and (ids[s] is None or ids[k] > ids[s])):
                stays[g] = k
        digest, sha = {}, {}
        for text, g in first.items():
            raw = text.encode("utf-8", "surrogatepass")
            digest[g] = xxh3_64_intdigest(raw) - (1 << 63)
            sha[g] = hashlib.sha256(raw).hexdigest()
        numbers = {g: (part << 36) + number + i for i, g in enumerate(first.values())}
        number += len(first)
        is_rep = [stays[g] == k for k, g in enumerate(of)]
        added = {
            _TEXT: pa.array([t if r else None for t, r in zip(texts, is_rep, strict=True)], pa.string()),
            _HASH: pa.array([digest[g] for g in of], pa.int64()),
            _REP: pa.array([numbers[g] for g in of], pa.int64()),
            _IS: pa.array(is_rep, pa.bool_()),
            _SHA: pa.array([sha[g] for g in of], pa.string()),
            _N: pa.array([count[g] for g in of], pa.int64()),
        }
        for name in names:
            if name not in added:
                added[name] = window.column(name).combine_chunks()
        for b in pa.table({n: added[n] for n in names}).combine_chunks().to_batches(max_chunksize=8192):
            yield b

    for batch in slices(batches, _TEXT):
        held.append(batch)
        size += batch.column(_TEXT).nbytes
        if size >= WINDOW_BYTES:
            yield from flush()
    yield from flush()


def _chain(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Representatives in order of hash -> for each: who stays of its group, and the group's size."""

    def verdicts(chain: list[tuple[str, list]]) -> list[tuple]:
        out = []
        for _, reps in chain:
            best = max(reps, key=lambda r: (r[1] is not None, r[1] if r[1] is not None else 0, -r[0]))
            size = sum(r[2] for r in reps)
            out += [(r[0], best[1], size, r[0] == best[0]) for r in reps]
        return out

    now, chain, out = None, [], []
    names = ["__x_v_rep", "__x_v_keep", "__x_v_size", "__x_v_stays"]
    types = [pa.int64(), pa.int64(), pa.int64(), pa.bool_()]

    def pack(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

    for batch in slices(batches, _TEXT):
        for h, text, rep, doc_id, n in zip(*(batch.column(c).to_pylist() for c in (_HASH, _TEXT, _REP, _ID, _N)), strict=True):
            if h != now:
                out += verdicts(chain)
                now, chain = h, []
            for known, reps in chain:
                if known == text:
                    reps.append((rep, doc_id, n))
                    break
            else:
                chain.append((text, [(rep, doc_id, n)]))
        if len(out) > 20_000:
            yield pack(out)
            out = []
    out += verdicts(chain)
    if out:
        yield pack(out)


def _fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Representatives of a share of a hot hash, in order of hash: equal texts, compared by bytes, become
    one, the row that stays of them, with the rows of all. Gives what each was folded into."""
    names = [_REP, _HASH, _ID, _N, "__x_into"]
    now, chain = None, {}

    def done(h: tuple) -> Iterator[pa.RecordBatch]:
        for reps in chain.values():
            best = max(reps, key=lambda r: (r[1] is not None, r[1] if r[1] is not None else 0, -r[0]))
            total = sum(r[2] for r in reps)
            rows = [(r[0], h[0], r[1], total if r[0] == best[0] else 0, best[0]) for r in reps]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=names)

    for batch in slices(batches, _TEXT):
        for h, salt, text, rep, doc_id, n in zip(*(batch.column(c).to_pylist() for c in (_HASH, _SALT, _TEXT, _REP, _ID, _N)), strict=True):
            if (h, salt) != now:
                if chain:
                    yield from done(now)
                now, chain = (h, salt), {}
            chain.setdefault(text, []).append((rep, doc_id, n))
    if chain:
        yield from done(now)


def _fold_hot(rows: DataFrame, reps: DataFrame, hot: int | None = None) -> tuple[DataFrame, DataFrame | None]:
    """Hashes with more than HOT representatives are folded in shares first, so that an owner gets one
    for each share, not one for each window of rows. Gives the representatives left, and those folded
    (their number and __x_into). Without hot hashes nothing is moved."""
    hot = hot or HOT
    many = reps.groupBy(F.col(_HASH).alias("__x_hot")).agg(F.count(F.lit(1)).alias("__x_many")).where(F.col("__x_many") > hot)
    many = cut(many, "dedup-hot")
    if not many.limit(1).count():
        return reps, None
    salt = F.pmod(F.xxhash64(_REP), F.expr(f"(__x_many + {hot - 1}) div {hot}")).alias(_SALT)
    shares = reps.join(many, F.col(_HASH) == F.col("__x_hot")).select(_HASH, salt, _TEXT, _REP, _ID, _N)
    shares = shares.repartition(_HASH, _SALT).sortWithinPartitions(_HASH, _SALT)
    done = cut(shares.mapInArrow(_fold, f"{_REP} long, {_HASH} long, {_ID} long, {_N} long, __x_into long"), "dedup-folded")
    lead = done.where(F.col(_REP) == F.col("__x_into")).select(F.col(_REP).alias("__x_lead"), F.col(_N).alias("__x_all"))
    folded = done.where(F.col(_REP) != F.col("__x_into")).select(_REP, "__x_into")
    left = reps.join(folded.select(_REP), _REP, "left_anti").join(lead, F.col(_REP) == F.col("__x_lead"), "left")
    return left.withColumn(_N, F.coalesce("__x_all", _N)).drop("__x_lead", "__x_all"), folded


def index(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rows, verdicts).

    rows: the columns of docs, and hash, representative's number, whether the row is it, sha256 and
    rows represented; the text is there for representatives only. verdicts: __x_v_rep, __x_v_keep (doc_id
    that stays), __x_v_size (rows of the group), __x_v_stays (whether this representative is the one).
    """
    spark = docs.sparkSession
    plain = docs.select(*[c for c in docs.columns if c != "text"], F.col("doc_id").cast("long").alias(_ID), whole_text(docs).alias(_TEXT))
    fields = [*plain.schema.fields, StructField(_HASH, LongType()), StructField(_REP, LongType()), StructField(_IS, BooleanType()), StructField(_SHA, StringType()), StructField(_N, LongType())]
    schema = StructType([StructField(f.name, f.dataType, True) for f in fields])
    names = schema.names
    rows = cut(plain.mapInArrow(lambda b: _collapse(b, names), schema), "dedup-rows")
    reps = rows.where(F.col(_IS))
    prefix = F.shiftrightunsigned(F.col(_HASH).bitwiseXOR(F.lit(-(1 << 63))), 64 - MAX_DEPTH)
    reps, folded = _fold_hot(rows, reps)
    load = reps.groupBy(prefix.alias("p")).agg(F.sum(F.octet_length(_TEXT) + 64).alias("n")).collect()  # at most 2**MAX_DEPTH rows
    depth, directory = split_directory({r["p"]: r["n"] for r in load})
    numbers = F.array(*map(F.lit, directory)) if len(directory) <= 64 else None
    entry = F.shiftrightunsigned(F.col(_HASH).bitwiseXOR(F.lit(-(1 << 63))), 64 - depth) if depth else F.lit(0).cast("long")
    if numbers is not None:
        dealt = reps.withColumn(_BUCKET, F.element_at(numbers, (entry + 1).cast("int")))
    else:
        known = spark.createDataFrame(list(enumerate(directory)), f"{_ENTRY} long, {_BUCKET} int")
        dealt = reps.withColumn(_ENTRY, entry).join(F.broadcast(known), _ENTRY)  # at most 2**MAX_DEPTH rows
    owned = dealt.select(_BUCKET, _HASH, _TEXT, _REP, _ID, _N).repartition(_BUCKET).sortWithinPartitions(_BUCKET, _HASH)
    verdicts = cut(owned.drop(_BUCKET).mapInArrow(_chain, _VERDICT), "dedup-verdicts")
    if folded is not None:  # a folded representative has the verdict of the one that it was folded into
        theirs = folded.join(verdicts.withColumnRenamed("__x_v_rep", "__x_into"), "__x_into").select(F.col(_REP).alias("__x_v_rep"), "__x_v_keep", "__x_v_size", F.lit(False).alias("__x_v_stays"))
        verdicts = cut(verdicts.unionByName(theirs), "dedup-all-verdicts")
    return rows, verdicts


def deduplicate(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    rows, verdicts = index(docs)
    return rows.join(verdicts, F.col(_REP) == F.col("__x_v_rep")).select(
        F.col(_ID).alias("doc_id"), F.col("__x_v_keep").alias("keep_id"), F.col("__x_v_size").alias("group_size"), (F.col(_IS) & F.col("__x_v_stays")).alias("kept"), F.col(_SHA).alias("text_sha256")
    )


def distinct_documents(docs: DataFrame) -> DataFrame:
    """The rows that stay, with the columns of docs. A null text that stays comes back empty."""
    rows, verdicts = index(docs)
    kept = rows.where(F.col(_IS)).join(verdicts.where("__x_v_stays").select("__x_v_rep").hint("merge"), F.col(_REP) == F.col("__x_v_rep"), "left_semi")
    return kept.select(*[F.col(_TEXT).alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns])


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicate(table(spark, sf_dir, "documents"))


SQL = """
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
g AS (SELECT text, max(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY text)
SELECT t.doc_id, g.keep_id, g.group_size, t.doc_id = g.keep_id AS kept, sha256(t.text) AS text_sha256
FROM t JOIN g ON t.text = g.text
"""
