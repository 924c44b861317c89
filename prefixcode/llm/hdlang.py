"""Language identification with hyperdimensional profiles.

Every letter has a random vector of +1 and -1. An n-gram's vector binds (multiplies) its letters'
vectors, each permuted (rotated) by its place. A text's vector bundles (adds) those of its n-grams,
a language's prototype those of its documents. A text gets the language whose prototype has the
largest cosine with its vector, after the mean prototype, which all languages share, is taken off
prototypes.

The vector of a part's distinct n-grams is made once; bundling is then a product of the documents'
n-gram counts with it, some n-grams at a time. Letters are Unicode letters, lower-cased one by one; all else is one blank.
Training sends one count for each language and n-gram from a task; prototypes are a few KB.

Cases: null, empty or letterless text gives ``und`` with score 0; a language label that is null is
not learned; with nothing to learn from every text is ``und``; ties go to the first language by
name; equal texts get equal answers; extra columns may have any names but those starting with __x_.
"""

from __future__ import annotations

import sys
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefixcode.llm.common import mix64, slices, table, whole_text

DIM = 512
N = 3
BLANK = 0x20
#: Letters coded at once, and n-grams whose vectors are held at once: memory follows these, not texts.
PART = 1 << 19
GRAMS = 1 << 13


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """code point -> lower-case letter's code point, or a blank."""
    out = np.full(sys.maxunicode + 1, BLANK, dtype=np.uint32)
    for c in range(sys.maxunicode + 1):
        s = chr(c)
        if s.isalpha() and not 0xD800 <= c < 0xE000:
            low = s.lower()
            out[c] = ord(low) if len(low) == 1 else c
    return out


def letter_vectors(letters: np.ndarray) -> np.ndarray:
    """+1/-1 vectors, a row for each code point, from a hash of code point and place."""
    words = mix64((letters.astype(np.uint64)[:, None] << np.uint64(16)) + np.arange(DIM // 64, dtype=np.uint64)[None, :] + np.uint64(0x51ED27 << 40))
    bits = np.unpackbits(words.view(np.uint8), axis=1)
    return bits.astype(np.float32) * 2 - 1


def gram_vectors(grams: np.ndarray) -> np.ndarray:
    """grams: rows of N code points -> rows of bound vectors; the place decides the rotation."""
    letters, where = np.unique(grams, return_inverse=True)
    vectors = letter_vectors(letters)
    where = where.reshape(grams.shape)
    out = vectors[where[:, N - 1]].copy()
    for k in range(N - 1):
        out *= np.roll(vectors, N - 1 - k, axis=1)[where[:, k]]
    return out


def _parts(texts: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(symbols, which text each is of), at most about PART of them at a time; a run of blanks is one
    blank. A part that goes on with a text repeats its last N - 1 symbols, so no n-gram is lost."""
    table_ = _letters()
    held: list[np.ndarray] = []
    owner: list[np.ndarray] = []
    room = PART
    for k, text in enumerate(texts):
        before = np.zeros(0, dtype=np.uint32)
        for at in range(0, max(1, len(text)), PART):
            some = text[at : at + PART]
            some = (" " if not at else "") + some + (" " if at + PART >= len(text) else "")
            now = np.concatenate((before, table_[np.frombuffer(some.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)]))
            keep = np.ones(len(now), dtype=bool)
            keep[1:] = (now[1:] != BLANK) | (now[:-1] != BLANK)
            now = now[keep]
            before = now[max(0, len(now) - N + 1) :]
            if (at or room < len(now)) and held:  # two parts of a text don't stand side by side
                yield np.concatenate(held), np.concatenate(owner)
                held, owner, room = [], [], PART
            held.append(now)
            owner.append(np.full(len(now), k))
            room -= len(now)
    if held:
        yield np.concatenate(held), np.concatenate(owner)


def counts(flat: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of a part: (distinct grams, which one each place holds, which text it is of)."""
    letters, symbol = np.unique(flat, return_inverse=True) if flat.max(initial=0) > 0xFFFF else _small(flat)
    k = len(letters)
    places = max(0, len(flat) - N + 1)
    same = doc[len(doc) - places :] == doc[:places]
    gram = np.zeros(places, dtype=np.int64)
    for i in range(N):
        gram = gram * k + symbol[i : len(symbol) - N + 1 + i]
    gram, doc = gram[same], doc[:places][same]
    if k**N <= 1 << 18:
        there = np.bincount(gram, minlength=k**N)
        ids = np.flatnonzero(there)
        place = np.zeros(k**N, dtype=np.int64)
        place[ids] = np.arange(len(ids))
        column = place[gram]
    else:
        ids, column = np.unique(gram, return_inverse=True)
    grams = np.empty((len(ids), N), dtype=np.uint32)
    for i in range(N - 1, -1, -1):
        grams[:, i] = letters[ids % k]
        ids = ids // k
    return grams, column, doc


def bundles(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(a bundle for each text, how many letters it has). Vectors of GRAMS n-grams at a time; all sums
    are whole numbers, so equal texts get equal bundles however they are cut."""
    out = np.zeros((len(texts), DIM))
    has = np.zeros(len(texts), dtype=np.int64)
    for flat, doc in _parts(texts):
        has += np.bincount(doc[flat != BLANK], minlength=len(texts))
        grams, column, doc = counts(flat, doc)
        if len(grams) <= GRAMS:
            slots = [(0, column, doc)]
        else:
            order = np.argsort(column, kind="stable")
            column, doc = column[order], doc[order]
            edges = np.searchsorted(column, np.arange(0, len(grams) + GRAMS, GRAMS))
            slots = [(i * GRAMS, column[a:b] - i * GRAMS, doc[a:b]) for i, (a, b) in enumerate(zip(edges[:-1], edges[1:], strict=True)) if a < b]
        for at, col, own in slots:
            some = grams[at : at + GRAMS]
            ids, row = np.unique(own, return_inverse=True)
            matrix = np.bincount(row * len(some) + col, minlength=len(ids) * len(some)).reshape(len(ids), len(some))
            out[ids] += matrix.astype(np.float32) @ gram_vectors(some)
    return out, has


def _small(flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    seen = np.zeros(0x10000, dtype=bool)
    seen[flat] = True
    letters = np.flatnonzero(seen).astype(np.uint32)
    place = np.zeros(0x10000, dtype=np.int64)
    place[letters] = np.arange(len(letters))
    return letters, place[flat]


def _learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A bundle for each language that the task has seen."""
    sums: dict[str, np.ndarray] = {}
    docs: dict[str, int] = {}
    for batch in slices(batches, most_bytes=1 << 20, most_rows=256):
        langs = batch.column("lang").to_pylist()
        bundle, has = bundles(batch.column("text").to_pylist())
        for lang in set(langs):
            rows = np.array([x == lang for x in langs]) & (has > 0)
            if rows.any():
                sums[lang] = sums.get(lang, 0) + bundle[rows].sum(axis=0)
                docs[lang] = docs.get(lang, 0) + int(rows.sum())
    if sums:
        yield pa.RecordBatch.from_arrays([pa.array(list(sums)), pa.array([docs[x] for x in sums]), pa.array([[int(round(v)) for v in sums[x]] for x in sums], pa.list_(pa.int64()))], names=["lang", "docs", "bundle"])


def learn(labelled: DataFrame) -> dict[str, np.ndarray]:
    """text, lang -> language -> prototype of unit length. Sums are whole numbers, so order is nothing."""
    parts = labelled.where(F.col("lang").isNotNull()).select(whole_text(labelled), F.col("lang").cast("string").alias("lang"))
    bundles = parts.mapInArrow(_learn, "lang string, docs long, bundle array<bigint>")
    total = bundles.select("lang", F.posexplode("bundle").alias("at", "v")).groupBy("lang", "at").agg(F.sum("v").alias("v"))
    rows = total.groupBy("lang").agg(F.sort_array(F.collect_list(F.struct("at", "v"))).alias("b")).collect()  # a row for each language
    units = {r["lang"]: np.array([x["v"] for x in r["b"]], dtype=np.float64) for r in rows}
    units = {k: v / np.linalg.norm(v) for k, v in sorted(units.items()) if np.linalg.norm(v) > 0}
    if len(units) > 1:
        mean = np.mean(list(units.values()), axis=0)
        mean /= np.linalg.norm(mean)
        units = {k: v - (v @ mean) * mean for k, v in units.items()}
        units = {k: v / np.linalg.norm(v) for k, v in units.items() if np.linalg.norm(v) > 1e-9}
    return units


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], keep: list[str]) -> DataFrame:
    """Columns ``keep`` of docs, and lang_pred and score: half of 1 + cosine."""
    names = list(prototypes)
    matrix_t = np.array([prototypes[x] for x in names], dtype=np.float64).T if names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "__x_text", most_bytes=1 << 20, most_rows=256):
            texts = batch.column("__x_text").to_pylist()
            lang, score = ["und"] * len(texts), [0.0] * len(texts)
            if matrix_t is not None:
                bundle, has = bundles(texts)
                norm = np.linalg.norm(bundle, axis=1)
                cosine = (bundle @ matrix_t) / np.where(norm > 0, norm, 1)[:, None]
                best = cosine.round(5).argmax(axis=1)
                for i in np.flatnonzero((has > 0) & (norm > 0)):
                    lang[i] = names[best[i]]
                    score[i] = min(1.0, max(0.0, round((1 + float(cosine[i, best[i]])) / 2, 4)))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(lang), pa.array(score)], names=[*keep, "__x_lang", "__x_score"])

    plain = docs.select(*[f"`{c}`" for c in keep], whole_text(docs).alias("__x_text"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in plain.schema if f.name != "__x_text")
    return plain.mapInArrow(run, f"{schema}, __x_lang string, __x_score double")


def held_out(docs: DataFrame):
    return F.crc32(F.col("doc_id").cast("string")) % 3 == 1


def training_rows(docs: DataFrame) -> DataFrame:
    return docs.where(F.col("doc_id").isNotNull() & ~held_out(docs))


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score; learned from rows that aren't held out."""
    out = predict(docs.select("text", F.col("doc_id").cast("long").alias("doc_id")), learn(training_rows(docs)), ["doc_id"])
    return out.select("doc_id", F.coalesce(held_out(out), F.lit(False)).alias("held_out"), F.col("__x_lang").alias("lang_pred"), F.col("__x_score").alias("score"))


def identified_documents(docs: DataFrame) -> DataFrame:
    """Rows in a language that was learned, with the columns of docs; letterless texts go."""
    out = predict(docs, learn(training_rows(docs)), docs.columns)
    return out.where("__x_lang <> 'und'").select(*[f"`{c}`" for c in docs.columns])


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(table(spark, sf_dir, "documents"))
