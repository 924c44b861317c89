"""Near-duplicate documents: consistent weighted sampling over TF-IDF shingles.

Similarity is the weighted Jaccard coefficient, the sum of smaller over the sum of larger weights. A
shingle (five words) weighs tf * idf, idf = 1 + min(1, ln(N / df) / ln(1 / RARE)): between 1 for a
shingle in all documents and 2 for one in a hundredth of them or fewer. So common passages count
less, yet a large family of copies still resembles itself. df comes from a counting table of fixed
width over all documents (a shingle shares its counter with others; the mean excess is the number of
shingles a document has over the width, in units of N, at any scale).

Improved consistent weighted sampling draws, for each shingle and hash function, r and c from
Gamma(2, 1) and b from U(0, 1), all by hash; t = floor(ln w / r + b); the sample is the (shingle, t)
with the smallest c / exp(r (t - b) + r). Two texts draw the same sample with a probability equal to
their similarity. Bands of samples give buckets. A small bucket is compared all with all. In a large
one leaders, drawn by hash, meet all members that aren't in their class yet, then classes are made anew
from the links, then rows outside the largest class of the bucket that haven't led yet give the next
leaders, sixteen times as many each turn, until there are none. So any two texts that share a bucket
were compared or are in one class, and classes are those of all pairs in all buckets. Work is in
proportion to a bucket's rows times those outside its largest class, in arithmetic; rows moved are a
bucket's rows times its packs of leaders, as leaders are held in a task and members stream by, first
with their sample bytes, then, those that may be near, with their texts. Sample agreement screens
pairs, then the exact similarity of the whole texts decides. Of the links found in one task those that
join classes are kept: classes are connected components, so the others change nothing.

Cases: null text is empty; texts without words resemble only their exact copies; a text of fewer
than five words is one shingle; exact copies share a class and are compared once; a null doc_id is
passed on; repeated rows are documents of their own; an empty table gives an empty result; extra
columns may have any names but those starting with __x_.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, LongType, StructField, StructType

from prefixcode.llm.common import TokenHasher, cut, mix64, only_of, release, shingled, slices, table, whole_text
from prefixcode.llm.components import components

WORDS = 5
SIMILAR = 0.8
BANDS, ROWS = 12, 4
HASHES = BANDS * ROWS
RARE = 0.01
WIDTH = 1 << 20
CHUNK = 1 << 14
#: Pairs with fewer agreeing samples aren't compared: 5 standard deviations below the mean at 0.8.
AGREE = int(SIMILAR * HASHES - 5 * math.sqrt(SIMILAR * (1 - SIMILAR) * HASHES))
#: So many leaders' sample bytes are held at once, and met by shares of about so many members.
LEADERS = MEMBERS = 1024
#: Leaders whose texts are held at once: about so many, of about so many bytes in all (or one).
PACK, PACK_BYTES = 512, 4 << 20
#: A bucket of no more than this is compared all with all.
FEW = 16
SEED = 0x1C35


# ---------------------------------------------------------------- weights
def shingles(texts: list[str], hasher: TokenHasher) -> list[tuple[np.ndarray, np.ndarray]]:
    """Of each text the distinct shingle hashes, ascending, and how often each occurs."""
    return [np.unique(x, return_counts=True) for x in shingled(texts, hasher, WORDS)]


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hasher, seen, docs = TokenHasher(), np.zeros(WIDTH, dtype=np.int64), 0
    for batch in slices(batches, most_bytes=2 << 20):
        found = [x for x, _ in shingles(batch.column("text").to_pylist(), hasher)]
        docs += len(found)
        seen += np.bincount((np.concatenate(found) >> np.uint64(44)).astype(np.int64), minlength=WIDTH)
    if docs:
        parts = [seen[at : at + CHUNK].astype("<i4").tobytes() for at in range(0, WIDTH, CHUNK)]
        yield pa.RecordBatch.from_arrays([pa.array(range(-1, len(parts)), pa.int32()), pa.array([np.array([docs], "<i4").tobytes(), *parts], pa.binary())], names=["chunk", "counts"])


def _add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: dict[int, np.ndarray] = {}
    for batch in batches:
        for chunk, counts in zip(batch.column("chunk").to_pylist(), batch.column("counts").to_pylist(), strict=True):
            total[chunk] = total.get(chunk, 0) + np.frombuffer(counts, dtype="<i4").astype(np.int64)
    if total:
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([v.astype("<i8").tobytes() for v in total.values()], pa.binary())], names=["chunk", "counts"])


def idf_table(docs: DataFrame) -> np.ndarray:
    """idf by the first 20 bits of a shingle's hash; WIDTH numbers whatever the corpus."""
    parts = docs.select(whole_text(docs)).mapInArrow(_sketch, "chunk int, counts binary")
    rows = parts.repartition(64, "chunk").mapInArrow(_add, "chunk int, counts binary").collect()
    got = {r["chunk"]: np.frombuffer(r["counts"], dtype="<i8") for r in rows}
    if not got:
        return np.full(WIDTH, 2.0, dtype=np.float32)
    n = float(got.pop(-1)[0])
    df = np.concatenate([got[k] for k in sorted(got)])
    return (1 + np.clip(np.log(n / np.maximum(df, 1)) / math.log(1 / RARE), 0, 1)).astype(np.float32)


def weights(found: tuple[np.ndarray, np.ndarray], idf: np.ndarray) -> np.ndarray:
    return found[1].astype(np.float32) * idf[(found[0] >> np.uint64(44)).astype(np.int64)]


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard of (hashes ascending, weights)."""
    if not len(a[0]) or not len(b[0]):
        return 0.0
    at = np.searchsorted(b[0], a[0])
    at[at == len(b[0])] = 0
    same = b[0][at] == a[0]
    low = float(np.minimum(a[1][same], b[1][at[same]]).sum(dtype=np.float64))
    return low / (float(a[1].sum(dtype=np.float64)) + float(b[1].sum(dtype=np.float64)) - low)


# ---------------------------------------------------------------- samples
def _gamma_quantiles(bits: int) -> np.ndarray:
    """Quantiles of Gamma(2, 1) at the middles of 2**bits equal parts, by bisection."""
    p = (np.arange(1 << bits) + 0.5) / (1 << bits)
    low, high = np.zeros(len(p)), np.full(len(p), 40.0)
    for _ in range(60):
        mid = (low + high) / 2
        under = 1 - np.exp(-mid) * (1 + mid) < p
        low, high = np.where(under, mid, low), np.where(under, high, mid)
    return (low + high) / 2


class Sampler:
    """The samples of many texts at once, one hash function after another."""

    def __init__(self) -> None:
        self.r = _gamma_quantiles(12).astype(np.float32)
        self.ln_c = np.log(_gamma_quantiles(16)).astype(np.float32)
        self.odd = mix64(np.arange(1, 2 * HASHES + 1, dtype=np.uint64) + np.uint64(SEED)) | np.uint64(1)

    def samples(self, hashes: np.ndarray, ln_w: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Rows of HASHES 64-bit samples; text k has hashes[starts[k]:starts[k + 1]], at least one."""
        sizes = np.diff(np.append(starts, len(hashes)))
        out = np.empty((len(starts), HASHES), dtype=np.uint64)
        for k in range(HASHES):
            z = hashes * self.odd[2 * k]
            z ^= z >> np.uint64(32)
            z *= self.odd[2 * k + 1]
            r = self.r[(z >> np.uint64(52)).astype(np.int64)]
            b = ((z >> np.uint64(28)) & np.uint64(0xFFFFFF)).astype(np.float32) * np.float32(2.0**-24)
            ln_c = self.ln_c[((z >> np.uint64(12)) & np.uint64(0xFFFF)).astype(np.int64)]
            t = np.floor(ln_w / r + b)
            ln_a = ln_c - r * (t - b) - r
            low = np.minimum.reduceat(ln_a, starts)
            at = np.flatnonzero(ln_a == np.repeat(low, sizes))
            owner = np.searchsorted(starts, at, side="right") - 1
            first = at[np.flatnonzero(np.diff(owner, prepend=-1))]
            out[:, k] = mix64(hashes[first] + t[first].astype(np.int64).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        return out


def bands(samples: np.ndarray) -> np.ndarray:
    """Rows of BANDS bucket keys."""
    keys = np.zeros((len(samples), BANDS), dtype=np.uint64)
    for i in range(ROWS):
        keys = mix64(keys + samples[:, i::ROWS])
    return mix64(keys + np.arange(BANDS, dtype=np.uint64)[None, :])


_ROW, _KEY, _BANDS, _PRINT, _TEXT = "__x_row", "__x_key", "__x_bands", "__x_print", "__x_text"


def _sign(batches: Iterator[pa.RecordBatch], idf: np.ndarray, names: list[str]) -> Iterator[pa.RecordBatch]:
    from pyspark import TaskContext
    from xxhash import xxh3_128_digest

    row = TaskContext.get().partitionId() << 36
    hasher, sampler = TokenHasher(), Sampler()
    for batch in slices(batches, _TEXT, most_bytes=1 << 20, most_rows=1024):
        texts = batch.column(_TEXT).to_pylist()
        n = len(texts)
        found = shingles(texts, hasher)
        some = [i for i in range(n) if len(found[i][0])]
        keys: list = [[] for _ in range(n)]
        prints: list = [b""] * n
        if some:
            sizes = np.array([len(found[i][0]) for i in some])
            starts = np.concatenate(([0], np.cumsum(sizes)[:-1]))
            drawn = sampler.samples(np.concatenate([found[i][0] for i in some]), np.log(np.concatenate([weights(found[i], idf) for i in some])), starts)
            small = (drawn & np.uint64(0xFF)).astype(np.uint8)
            for i, own, p in zip(some, bands(drawn).view(np.int64).tolist(), small, strict=True):
                keys[i], prints[i] = own, p.tobytes()
        added = {
            _ROW: pa.array(np.arange(row, row + n)),
            _KEY: pa.array([xxh3_128_digest(t.encode("utf-8", "surrogatepass")) for t in texts], pa.binary()),
            _BANDS: pa.array(keys, pa.list_(pa.int64())),
            _PRINT: pa.array(prints, pa.binary()),
        }
        row += n
        yield pa.RecordBatch.from_arrays([added[c] if c in added else batch.column(c) for c in names], names=names)


def signed(docs: DataFrame) -> tuple[DataFrame, np.ndarray]:
    """The rows of docs with a number, the text's digest, bucket keys and sample bytes; and idf."""
    idf = idf_table(docs)
    plain = docs.select(*[f"`{c}`" for c in docs.columns], whole_text(docs).alias(_TEXT))
    schema = StructType([*(StructField(f.name, f.dataType, True) for f in plain.schema.fields), StructField(_ROW, LongType()), StructField(_KEY, BinaryType()), StructField(_BANDS, ArrayType(LongType())), StructField(_PRINT, BinaryType())])
    names = schema.names
    return cut(plain.mapInArrow(lambda b: _sign(b, idf, names), schema), "near-signed"), idf


# ---------------------------------------------------------------- pairs
def _agree(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs (a, p, b, q) whose samples agree often enough."""
    for whole in batches:
        for start in range(0, whole.num_rows, 4096):
            batch = whole.slice(start, 4096)
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), dtype=np.uint8).reshape(-1, HASHES) for c in ("p", "q"))
            yield batch.select(["a", "b"]).filter(pa.array((x == y).sum(axis=1) >= AGREE))


def _verify(batches: Iterator[pa.RecordBatch], idf: np.ndarray) -> Iterator[pa.RecordBatch]:
    hasher, known = TokenHasher(), {}
    for batch in slices(batches, "ta", most_rows=512):
        first, second = batch.column("a").to_pylist(), batch.column("b").to_pylist()
        new = {a: t for a, t in zip(first, batch.column("ta").to_pylist(), strict=True) if a not in known}
        if len(known) > 64:
            known = {a: known[a] for a in set(first) & set(known)}
        for a, s in zip(new, shingles(list(new.values()), hasher), strict=True):
            known[a] = s[0], weights(s, idf)
        out = []
        for a, b, s in zip(first, second, shingles(batch.column("tb").to_pylist(), hasher), strict=True):
            out.append((a, b, similarity(known[a], (s[0], weights(s, idf)))))
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], names=["a", "b", "sim"])


def _groups(batches: Iterator[pa.RecordBatch], by: list[str]) -> Iterator[tuple[bool, pa.RecordBatch]]:
    """(whether a group begins, its rows of one kind) of batches sorted by group, then kind (0 leads, 1 follows)."""
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        key = np.stack([batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in [*by, "kind"]])
        edge = np.concatenate(([0], np.flatnonzero((key[:, 1:] != key[:, :-1]).any(axis=0)) + 1, [batch.num_rows]))
        for start, end in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
            group = tuple(key[:-1, start].tolist())
            yield group != last, batch.slice(start, end - start)
            last = group


def _prints(part: pa.RecordBatch) -> np.ndarray:
    return np.frombuffer(b"".join(part.column("print").to_pylist()), dtype=np.uint8).reshape(-1, HASHES)


def _screen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Leaders of a bucket, then its members: for every member the leaders of another class whose
    samples agree often enough, by the pack they travel in. No more than LEADERS leaders are held."""
    held: list[pa.RecordBatch] = []
    lead = None
    for begins, part in _groups(batches, ["k", "pack", "salt"]):
        if begins:
            held, lead = [], None
        if part.column("kind")[0].as_py() == 0:
            held.append(part)
            continue
        if not held:
            continue
        if lead is None:
            own = [(r["home"], r["sub"]) for x in held for r in x.select(["home", "sub"]).to_pylist()]
            packs = {v: i for i, v in enumerate(dict.fromkeys(own))}
            ids, cls = (np.concatenate([x.column(c).to_numpy() for x in held]) for c in ("node", "c"))
            lead = ids, cls, np.concatenate([_prints(x) for x in held]), np.array([packs[v] for v in own]), np.array(list(packs), dtype=np.int64)
        ids, cls, prints, code, packs = lead
        step = max(1, (1 << 13) // len(ids))
        for start in range(0, part.num_rows, step):
            some = part.slice(start, step)
            node, c, q = some.column("node").to_numpy(), some.column("c").to_numpy(), _prints(some)
            good = (c[:, None] != cls[None, :]) & ((q[:, None, :] == prints[None, :, :]).sum(axis=2, dtype=np.int16) >= AGREE)
            i, j = np.nonzero(good)
            if not len(i):
                continue
            to = i * len(packs) + code[j]
            order = np.argsort(to, kind="stable")
            at = np.flatnonzero(np.diff(to[order], prepend=-1))
            i, j = i[order], j[order]
            leads = pa.ListArray.from_arrays(pa.array(np.append(at, len(j)), pa.int32()), pa.array(ids[j]))
            pack = packs[code[j[at]]]
            yield pa.RecordBatch.from_arrays([pa.array(node[i[at]]), pa.array(c[i[at]]), pa.array(pack[:, 0]), pa.array(pack[:, 1]), leads], names=["node", "c", "home", "sub", "leads"])


class _Pack:
    """Leaders held in one task: similarities of one text with many of them at once."""

    def __init__(self, ids: list[int], found: list[tuple[np.ndarray, np.ndarray]]):
        self.place = {a: i for i, a in enumerate(ids)}
        self.found = found
        sizes = np.array([len(x) for x, _ in found])
        self.some = np.flatnonzero(sizes)
        self.starts = np.concatenate(([0], np.cumsum(sizes[self.some])[:-1])).astype(np.int64)
        self.words, at = np.unique(np.concatenate([x for x, _ in found]), return_inverse=True)
        self.at, self.w = at, np.concatenate([w for _, w in found])
        self.total = np.array([float(w.sum(dtype=np.float64)) for _, w in found])
        self.dense = np.zeros(len(self.words), dtype=np.float32)

    def similarities(self, own: tuple[np.ndarray, np.ndarray], places: list[int]) -> np.ndarray:
        if not len(own[0]) or not len(self.words):
            return np.zeros(len(places))
        if len(places) * 8 < len(self.found):
            return np.array([similarity(self.found[i], own) for i in places])
        spot = np.searchsorted(self.words, own[0])
        spot[spot == len(self.words)] = 0
        same = self.words[spot] == own[0]
        spot = spot[same]
        self.dense[spot] = own[1][same]
        low = np.zeros(len(self.found))
        low[self.some] = np.add.reduceat(np.minimum(self.dense[self.at], self.w), self.starts, dtype=np.float64)
        self.dense[spot] = 0
        low = low[places]
        return low / (self.total[places] + float(own[1].sum(dtype=np.float64)) - low)


def _confirm(batches: Iterator[pa.RecordBatch], idf: np.ndarray, similar: float) -> Iterator[pa.RecordBatch]:
    """Leaders with their texts, then members with theirs and the leaders to compare with: links that
    join classes which no link before them in this group has joined."""
    hasher = TokenHasher()
    held: list[tuple[int, int, np.ndarray, np.ndarray]] = []
    pack, over = None, {}

    def top(c: int) -> int:
        while over.get(c, c) != c:
            over[c] = c = over.get(over[c], over[c])
        return c

    for begins, whole in _groups(batches, ["home", "sub", "salt"]):
        if begins:
            held, pack, over = [], None, {}
        leads = whole.column("kind")[0].as_py() == 0
        for part in slices(iter([whole]), "t", most_bytes=1 << 20, most_rows=512):
            ids, cls = part.column("node").to_pylist(), part.column("c").to_pylist()
            found = [(s[0], weights(s, idf)) for s in shingles(part.column("t").to_pylist(), hasher)]
            if leads:
                held += [(a, c, *s) for a, c, s in zip(ids, cls, found, strict=True)]
                continue
            if pack is None:
                pack = _Pack([x[0] for x in held], [(x[2], x[3]) for x in held])
            out = []
            for b, cb, own, wanted in zip(ids, cls, found, part.column("leads").to_pylist(), strict=True):
                places = [pack.place[a] for a in wanted]
                for i, sim in zip(places, pack.similarities(own, places).tolist(), strict=True):
                    if sim >= similar and (x := top(held[i][1])) != (y := top(cb)):
                        over[x] = y
                        out.append((min(held[i][0], b), max(held[i][0], b), sim, held[i][1], cb))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], names=["a", "b", "sim", "ca", "cb"])


def _meet(state: DataFrame, lead: DataFrame, texts: DataFrame, idf: np.ndarray, similar: float, label: str) -> DataFrame:
    """Links (a, b, sim, and the classes ca, cb that they join) between leaders (k, node, print, c, n) and all
    members of their buckets.

    Leaders and members stream through (bucket, pack of leaders, share of members), first by their
    sample bytes; then those that may be near, each text once for a pack, with whole texts. What a
    task holds is one pack.
    """
    # leaders that share buckets travel together, under the largest bucket that any of them is in
    own = lead.select("k", "node", F.struct("n", "k").alias("x"))
    widest = own.groupBy("node").agg(F.max("x").alias("x"))
    spread = own.select("k", "node").join(widest, "node").groupBy("k").agg(F.max("x").alias("x"))
    homes = own.select("k", "node").join(spread, "k").groupBy("node").agg(F.max("x")["k"].alias("home"))
    homes = homes.join(lead.select("node", "c").distinct(), "node").join(texts.select("node", "size"), "node")
    rooms = homes.groupBy("home").agg(F.expr(f"greatest((count(1) + {PACK - 1}) div {PACK}, sum(size) div {PACK_BYTES} + 1)").alias("subs"))
    homes = cut(homes.join(rooms, "home").select("node", "home", F.expr("pmod(xxhash64(node), subs)").alias("sub"), "c"), f"near-homes{label}")
    led = lead.groupBy("k").agg(F.expr(f"(count(1) + {LEADERS - 1}) div {LEADERS}").alias("packs"))
    sizes = state.groupBy("k").agg(F.expr(f"(count(1) + {MEMBERS - 1}) div {MEMBERS}").alias("salts")).join(led, "k")
    first = lead.drop("n").join(homes.select("node", "home", "sub"), "node").join(sizes, "k")
    first = first.select("k", F.expr("pmod(xxhash64(node, 1), packs)").alias("pack"), F.explode(F.expr("sequence(0L, salts - 1)")).alias("salt"), F.lit(0).alias("kind"), "node", "print", "c", "home", "sub")
    then = state.join(sizes, "k")
    then = then.select("k", F.explode(F.expr("sequence(0L, packs - 1)")).alias("pack"), F.expr("pmod(xxhash64(node, 2), salts)").alias("salt"), F.lit(1).alias("kind"), "node", "print", "c", F.lit(0).cast("long").alias("home"), F.lit(0).cast("long").alias("sub"))
    dealt = first.unionByName(then).repartition("k", "pack", "salt").sortWithinPartitions("k", "pack", "salt", "kind")
    near = dealt.mapInArrow(_screen, "node long, c long, home long, sub long, leads array<long>")
    met = cut(near.groupBy("home", "sub", "node", "c").agg(F.array_distinct(F.flatten(F.collect_list("leads"))).alias("leads")), f"near-met{label}")
    salts = met.groupBy("home", "sub").agg(F.expr(f"(count(1) + {MEMBERS - 1}) div {MEMBERS}").alias("salts"))
    full = texts.select("node", "t")
    first = homes.join(salts, ["home", "sub"]).join(full, "node").select("home", "sub", F.explode(F.expr("sequence(0L, salts - 1)")).alias("salt"), F.lit(0).alias("kind"), "node", "c", F.lit(None).cast("array<long>").alias("leads"), "t")
    then = met.join(salts, ["home", "sub"]).join(full, "node").select("home", "sub", F.expr("pmod(xxhash64(node, 3), salts)").alias("salt"), F.lit(1).alias("kind"), "node", "c", "leads", "t")
    dealt = first.unionByName(then).repartition("home", "sub", "salt").sortWithinPartitions("home", "sub", "salt", "kind")
    return cut(dealt.mapInArrow(lambda x: _confirm(x, idf, similar), "a long, b long, sim double, ca long, cb long"), f"near-links{label}")


def links(rows: DataFrame, idf: np.ndarray, similar: float = SIMILAR) -> tuple[DataFrame, DataFrame]:
    """(nodes, links). nodes: node, digest and class of each distinct text; links: a, b, sim."""
    first = F.min(F.struct(F.col(_ROW).alias("node"), F.col(_BANDS).alias("bands"), F.col(_PRINT).alias("print")))
    nodes = cut(rows.groupBy(F.col(_KEY).alias("digest")).agg(first.alias("x")).select("digest", "x.*"), "near-nodes")
    buckets = nodes.select(F.explode("bands").alias("k"), "node", "print")
    full = buckets.groupBy("k").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    todo = cut(buckets.join(full, "k"), "near-buckets")
    wanted = todo.select(F.col("node").alias(_ROW)).distinct()
    texts = cut(only_of(rows.select(_ROW, _TEXT), wanted, _ROW).select(F.col(_ROW).alias("node"), F.col(_TEXT).alias("t"), F.octet_length(_TEXT).cast("long").alias("size")), "near-texts")
    release(rows.sparkSession)
    few = todo.where(F.col("n") <= FEW)
    one, other = (few.select("k", F.col("node").alias(x), F.col("print").alias(y)) for x, y in (("a", "p"), ("b", "q")))
    pairs = one.join(other, "k").where("a < b").drop("k").mapInArrow(_agree, "a long, b long").distinct()
    both = pairs.join(texts.select(F.col("node").alias("a"), F.col("t").alias("ta")), "a").join(texts.select(F.col("node").alias("b"), F.col("t").alias("tb")), "b")
    compared = cut(both.select("a", "b", "ta", "tb").mapInArrow(lambda x: _verify(x, idf), "a long, b long, sim double"), "near-pairs")
    found = compared.where(F.col("sim") >= similar)
    members = todo.where(F.col("n") > FEW).select("k", "node", "print")
    part = components(found, "near-part")
    state = cut(members.join(part, "node", "left").select("k", "node", "print", F.coalesce("component", "node").alias("c")), "near-state")
    led, moved, turn = None, None, 0
    while True:
        main = state.groupBy("k", "c").agg(F.count(F.lit(1)).alias("n")).groupBy("k").agg(F.max(F.struct("n", "c")).alias("m")).select("k", F.col("m.c").alias("main"))
        open_ = state.join(main, "k").where("c <> main").select("k", "node", "print", "c", F.xxhash64(F.lit(turn), "node").alias("h"))
        if led is not None:
            open_ = open_.join(led, ["k", "node"], "left_anti")
        open_ = cut(open_, f"near-open{turn}")
        if not open_.limit(1).count():
            break
        # about 4 * 16 ** turn of a bucket's open rows, and one at least
        crowd = open_.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.min("h").alias("least"))
        lead = cut(open_.join(crowd, "k").where(f"h = least or pmod(h, greatest(1, shiftright(n, {min(4 * turn + 2, 62)}))) = 0").select("k", "node", "print", "c", "n"), f"near-lead{turn}")
        new = _meet(state, lead, texts, idf, similar, str(turn))
        found = found.unionAll(new.select("a", "b", "sim"))
        # only classes that new links join get a new name: the graph is one of classes, not of texts
        step = components(new.select(F.col("ca").alias("a"), F.col("cb").alias("b")), f"near-step{turn}").select(F.col("node").alias("c"), F.col("component").alias("to"))
        state = cut(state.join(step, "c", "left").select("k", "node", "print", F.coalesce("to", "c").alias("c")), f"near-state{turn}")
        if moved is None:
            moved = step
        else:
            on = step.select(F.col("c").alias("to"), F.col("to").alias("last"))
            moved = cut(moved.join(on, "to", "left").select("c", F.coalesce("last", "to").alias("to")).unionAll(step.join(moved.select("c"), "c", "left_anti").select("c", "to")), f"near-moved{turn}")
        now = lead.select("k", "node")
        led = now if led is None else led.unionAll(now)
        turn += 1
    named = nodes.select("digest", "node").join(part, "node", "left").select("digest", "node", F.coalesce("component", "node").alias("c"))
    if moved is not None:
        named = named.join(moved, "c", "left").select("digest", "node", F.coalesce("to", "c").alias("c"))
    return named, found


# ---------------------------------------------------------------- classes
def classes(docs: DataFrame, similar: float = SIMILAR) -> tuple[DataFrame, DataFrame]:
    """(signed rows, their classes): __x_row, __x_class (a number), __x_stays, __x_class_id (doc_id of the
    row that stays, the largest of the class) and __x_size."""
    rows, idf = signed(docs)
    nodes, _ = links(rows, idf, similar)
    labelled = cut(nodes.select("digest", F.col("c").alias("__x_class")), "near-labels")
    slim = cut(rows.select(_ROW, F.col("doc_id").cast("long").alias("__x_id"), F.col(_KEY).alias("digest")).join(labelled, "digest").drop("digest"), "near-rows")
    heads = slim.groupBy("__x_class").agg(F.max(F.struct("__x_id", F.col(_ROW).alias("r"))).alias("m"), F.count(F.lit(1)).alias("__x_size"))
    heads = heads.select("__x_class", "__x_size", F.col("m.__x_id").alias("__x_class_id"), F.col("m.r").alias("__x_head"))
    own = slim.join(heads, "__x_class").withColumn("__x_stays", F.col(_ROW) == F.col("__x_head"))
    return rows, own


def near_duplicates(docs: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """One row per document: doc_id, class_id, class_size, kept."""
    _, own = classes(docs.select("doc_id", "text"), similar)
    return own.select(F.col("__x_id").alias("doc_id"), F.col("__x_class_id").alias("class_id"), F.col("__x_size").alias("class_size"), F.col("__x_stays").alias("kept"))


def representatives(docs: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """One document of each class, with the columns of docs."""
    rows, own = classes(docs, similar)
    return rows.join(own.where("__x_stays").select(_ROW).hint("merge"), _ROW, "left_semi").select(*[f"`{c}`" for c in docs.columns])


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
