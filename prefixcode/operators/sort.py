"""External merge sort with codes, the order-preserving exchange, merging of coded runs.

At scale the JVM sorts: one range exchange, one local sort, codes derived from neighbours
(``derive``). The kernels here do run generation, spilling, merging, early aggregation and duplicate
removal themselves, inside one task for each key range, and count what they do. Key cells are exact
(``functions.cells``), so keys that only share a normalised number stay apart. A task holds
``memory`` rows; runs wait in the task's own folder and go with it, as any sort's spill does, so a lost
executor costs a task's rerun.
"""

from __future__ import annotations

import functools
import os
import pickle
import tempfile
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from prefixcode.functions.cells import cells_of
from prefixcode.functions.codes import pack
from prefixcode.functions.keys import KeyCol, key_spec, kinds, normalize
from prefixcode.functions.measures import lower_bound
from prefixcode.kernels import baselines, formats, lockstep
from prefixcode.kernels import tree as kernel
from prefixcode.operators import external
from prefixcode.operators.derive import stitch_parts, value_at
from prefixcode.plans.frame import CODE, OFFSET
from prefixcode.sources import scratch

_COUNTS = "row_cmp long, by_code long, columns long, bypassed long, runs long, spilled_bytes long, plain_bytes long"
_BLOCK = 4096
_WHOLE = (T.BooleanType, T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.DateType, T.TimestampType, T.TimestampNTZType)
Run = Iterable[tuple[int, tuple]]
Fold = Callable[[tuple, tuple], tuple]


class Spill:
    """A run in a task's own folder, in blocks. layout: "plain" (rows and offsets), "truncate" (shared prefixes left
    out), "rle" (key columns as runs, one after another) or "bare" (rows alone: codes are made anew on reading)."""

    def __init__(self, folder: str, k: int, layout: str):
        self.k, self.layout = k, layout
        fd, self.path = tempfile.mkstemp(dir=folder)
        os.close(fd)
        self.bytes = 0

    def write(self, run: Run) -> Spill:
        k = self.k
        with open(self.path, "wb") as f:

            def put(block: list[tuple[int, tuple]]) -> None:
                if self.layout == "rle":
                    # a block stands alone: its first row is whole, the offset it had is kept beside
                    stored = [(n if i else 0, row[(n if i else 0) : k]) for i, (n, row) in enumerate(block)]
                    columns = formats.to_columns(stored, k, kernel.Counters())
                    block = (block[0][0] if block else k, columns, [row[k:] for _, row in block])
                elif self.layout == "truncate":
                    block = [(n, row[n:]) for n, row in block]
                elif self.layout == "bare":
                    block = [row for _, row in block]
                pickle.dump(block, f, protocol=5)

            block: list[tuple[int, tuple]] = []
            for c, row in run:
                block.append((kernel.offset(c, k), row))
                if len(block) == _BLOCK:
                    put(block)
                    block = []
            if block:
                put(block)
        self.bytes = os.path.getsize(self.path)
        return self

    def _blocks(self) -> Iterator:
        with open(self.path, "rb") as f:
            while True:
                try:
                    yield pickle.load(f)
                except EOFError:
                    break

    def read(self) -> Iterator[tuple[int, tuple]]:
        """The run with its codes; no column is compared for them, but in a bare run."""
        k = self.k
        if self.layout == "truncate":
            yield from formats.expand((x for block in self._blocks() for x in block), k)
        elif self.layout == "bare":
            yield from kernel.coded((row for block in self._blocks() for row in block), None, k)
        elif self.layout == "rle":
            for first, columns, rest in self._blocks():
                for i, ((c, row), more) in enumerate(zip(formats.coded_rows(columns, kernel.Counters()), rest, strict=True)):
                    if not i:
                        c = kernel.code(first, kernel.number(row[first]), k) if first < k else 0
                    yield c, (*row, *more)
        else:
            for block in self._blocks():
                for n, row in block:
                    yield (kernel.code(n, kernel.number(row[n]), k) if n < k else 0), row
        os.remove(self.path)


def _layout(compress: bool | str) -> str:
    return compress if isinstance(compress, str) else "truncate" if compress else "plain"


def _first(a: tuple, _: tuple) -> tuple:
    return a


def _collapsed(run: Run, k: int, fold: Fold | None) -> Run:
    if fold is _first:
        return (x for x in run if x[0])
    return kernel.folded(run, k, fold) if fold else run


def _merged(spills: list[Spill], k: int, ctr: kernel.Counters, merge: str, lossless: bool) -> Run:
    if merge == "heap":
        return kernel.coded(baselines.heap_merge([(row for _, row in s.read()) for s in spills], ctr, k=k), None, k)
    return kernel.LoserTree(k, ctr, lossless=lossless).merge([s.read() for s in spills])


def merge_runs(runs: list[Spill], k: int, fan_in: int, ctr: kernel.Counters, folder: str, layout: str = "truncate", fold: Fold | None = None, merge: str = "tree", lossless: bool = True, sizes: dict | None = None) -> Run:
    """Runs into one, ``fan_in`` at a time; groups of equal keys are folded in every merge."""
    runs = list(runs)
    while len(runs) > fan_in:
        now, runs = runs[:fan_in], runs[fan_in:]
        runs.append(Spill(folder, k, layout).write(_collapsed(_merged(now, k, ctr, merge, lossless), k, fold)))
        if sizes is not None:
            sizes["spilled"] = sizes.get("spilled", 0) + runs[-1].bytes
    yield from _collapsed(_merged(runs, k, ctr, merge, lossless), k, fold)


def sort_rows(
    rows: Iterable[tuple], k: int, memory: int, fan_in: int, ctr: kernel.Counters, run_gen: str = "tree", compress: bool | str = True, dedup: bool = False, sizes: dict | None = None, fold: Fold | None = None, merge: str = "tree", lossless: bool = True
) -> Run:
    """Sort with at most ``memory`` rows in memory: runs, then merges of ``fan_in`` runs at a time.

    run_gen: tree, replacement (queue of losers), quick (full comparisons) or index (with dedup or fold: a
    table of ``memory`` keys takes in repeats before they are sorted). merge: tree or heap (full comparisons). dedup or fold: repeated keys are dropped or folded while runs are written,
    in every merge and on output, by codes alone.
    """
    sizes = sizes if sizes is not None else {}
    fold = _first if dedup else fold
    layout = _layout(compress)
    with tempfile.TemporaryDirectory() as folder:
        runs: list[Spill] = []

        def keep(run: Run) -> None:
            s = Spill(folder, k, layout).write(_collapsed(run, k, fold))
            sizes["spilled"] = sizes.get("spilled", 0) + s.bytes
            runs.append(s)

        if run_gen == "replacement":
            for run in kernel.replacement_selection(rows, k, memory, ctr, lossless):
                keep(run)
        elif run_gen == "index":
            if fold is None:
                raise ValueError("an index takes in repeats; say how")
            index: dict[tuple, tuple] = {}
            for row in rows:
                key = row[:k]
                if key in index:
                    index[key] = fold(index[key], row[k:])
                    continue
                if len(index) == memory:
                    keep(kernel.generate([(*a, *b) for a, b in index.items()], k, ctr, lossless))
                    index = {}
                index[key] = row[k:]
            if index:
                keep(kernel.generate([(*a, *b) for a, b in index.items()], k, ctr, lossless))
        else:
            part: list[tuple] = []

            def form() -> None:
                if run_gen == "tree":
                    keep(kernel.generate(part, k, ctr, lossless))
                else:
                    keep(kernel.coded(baselines.quicksort(part, baselines.full_compare(ctr, k)), ctr if merge == "tree" else None, k))

            for row in rows:
                part.append(row)
                if len(part) == memory:
                    form()
                    part = []
            if part:
                form()
        sizes["runs"] = len(runs)
        yield from merge_runs(runs, k, fan_in, ctr, folder, layout, fold, merge, lossless, sizes)


# ---------------------------------------------------------------- rows of a DataFrame in and out of a task
class Rows:
    """How a task reads rows (cells, then carried values) from Arrow batches, and writes them back."""

    def __init__(self, df: DataFrame, spec: list[KeyCol], carried: list[str]):
        columns, self.makers, self.lossless = cells_of(df, spec)
        self.k = len(spec)
        self.cells = [f"__c{i}" for i in range(self.k)]
        self.carried = carried
        types = kinds(df, spec)
        self.whole = all(x.ascending and isinstance(t, _WHOLE) for x, t in zip(spec, types, strict=True))
        self.plain = all(x.ascending and isinstance(t, (*_WHOLE, T.DoubleType, T.FloatType, T.StringType, T.BinaryType)) for x, t in zip(spec, types, strict=True))
        self.columns: list[Column] = [*[c.alias(n) for c, n in zip(columns, self.cells, strict=True)], *[F.col(f"`{c}`") for c in carried]]
        self.fields = [T.StructField(f.name, f.dataType, True) for f in df.select(*[f"`{c}`" for c in carried]).schema.fields]

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "columns"}  # a task has no use for expressions

    def read(self, batch: pa.RecordBatch) -> Iterator[tuple]:
        cells = [make(batch.column(c)) for make, c in zip(self.makers, self.cells, strict=True)]
        return zip(*cells, *(batch.column(c).to_pylist() for c in self.carried), strict=True)

    def numbers(self, batches: list[pa.RecordBatch]) -> list[np.ndarray] | None:
        """The key columns as whole numbers in key order, if they are such (no nulls, none that a cell adds one to in vain)."""
        if not self.whole or any(b.column(c).null_count for b in batches for c in self.cells):
            return None
        out = [np.concatenate([b.column(c).to_numpy() for b in batches]) for c in self.cells]
        return out if all((c < np.iinfo(np.int64).max).all() for c in out) else None

    def numeric(self, df: DataFrame) -> bool:
        """Whether all cells are numbers: ascending, no nulls, no texts of over six bytes."""
        if not self.plain:
            return False
        keys = df.select(*self.columns[: self.k])
        texts = [f.name for f in keys.schema.fields if isinstance(f.dataType, T.BinaryType)]
        other = [F.col(c).isNull() for c in self.cells] + [F.octet_length(c) > 6 for c in texts]
        return not keys.where(functools.reduce(lambda a, b: a | b, other)).limit(1).count()

    def cell_numbers(self, batch: pa.RecordBatch) -> list[np.ndarray]:
        """The key columns as whole numbers in key order, where they are ``numeric``. Equal ones for equal keys."""
        out = []
        for make, c in zip(self.makers, self.cells, strict=True):
            a = batch.column(c)
            if pa.types.is_floating(a.type):
                x = a.to_numpy() + 0.0
                x[np.isnan(x)] = np.nan
                bits = x.view(np.int64)
                out.append(bits ^ ((bits >> 63) & np.int64(0x7FFFFFFFFFFFFFFF)))
            elif pa.types.is_integer(a.type):
                out.append(a.to_numpy())
            else:
                few = a.dictionary_encode()
                out.append(np.array([n for n, _ in make(few.dictionary)], dtype=np.int64)[few.indices.to_numpy()])
        return out

    def types(self, batch: pa.RecordBatch) -> list[pa.DataType]:
        return [batch.schema.field(c).type for c in self.carried]


def _written(run: Run, k: int, names: list[str], types: list[pa.DataType], first: list[tuple[str, int]]) -> Iterator[pa.RecordBatch]:
    """(code, row) -> batches: fixed int columns, __pos, carried columns, offset."""
    pos, block = 0, []

    def out() -> pa.RecordBatch:
        n = len(block)
        cols = list(zip(*(row[k:] for _, row in block), strict=True)) if names else []
        fixed = [pa.array(np.full(n, v, np.int32)) for _, v in first]
        data = [pa.array(c, t) for c, t in zip(cols, types, strict=True)]
        off = pa.array(np.array([kernel.offset(c, k) for c, _ in block], dtype=np.int32))
        return pa.RecordBatch.from_arrays([*fixed, pa.array(np.arange(pos, pos + n)), *data, off], names=[*(c for c, _ in first), "__pos", *names, OFFSET])

    for x in run:
        block.append(x)
        if len(block) == 8192:
            yield out()
            pos, block = pos + len(block), []
    if block:
        yield out()


def _with_codes(pieces: DataFrame, spec: list[KeyCol]) -> DataFrame:
    return pieces.withColumn(CODE, pack(F.col(OFFSET), value_at(pieces, spec, F.col(OFFSET)), len(spec)))


def _schema(fixed: list[str], fields: list[T.StructField]) -> T.StructType:
    return T.StructType([*(T.StructField(c, T.IntegerType()) for c in fixed), T.StructField("__pos", T.LongType()), *fields, T.StructField(OFFSET, T.IntegerType())])


_COMBINE: dict[str, Callable] = {
    "count": lambda a, b: a + b,
    "sum": lambda a, b: b if a is None else a if b is None else a + b,
    "min": lambda a, b: b if a is None else a if b is None else min(a, b),
    "max": lambda a, b: b if a is None else a if b is None else max(a, b),
}


def external_sort(
    df: DataFrame, keys: list, partitions: int, memory: int = 10_000, fan_in: int = 8, run_gen: str = "tree", compress: bool | str = True, dedup: bool = False, aggs: dict[str, tuple[str, str]] | None = None, merge: str = "tree", stitched: bool = True
) -> DataFrame:
    """The rows of df in key order: __part, __pos (place in the part), the columns, __off and __code.

    Parts are ranges of the whole key, so equal keys meet in one task. dedup: one row for each key;
    aggs: name -> (sum | count | min | max, column or "*"): one row for each key with these, both inside
    run generation and merges. stitched: each part's first row is coded relative to the last row of
    the part before (by a table with a row for each part), so codes hold over the whole table.
    """
    spec = key_spec(keys)
    names = [x.name for x in spec]
    aggs = aggs or {}
    source = df
    for name, (kind, column) in aggs.items():
        value = F.lit(1).cast("long") if column == "*" else F.col(column).isNotNull().cast("long") if kind == "count" else F.col(column)
        wide = kind == "sum" and column != "*" and isinstance(df.schema[column].dataType, (T.ByteType, T.ShortType, T.IntegerType))
        source = source.withColumn(name, value.cast("long") if wide else value)
    carried = [*names, *aggs] if aggs else df.columns
    rows = Rows(source, spec, carried)
    k, lossless = rows.k, rows.lossless
    combine = [_COMBINE[kind] for kind, _ in aggs.values()]

    def fold(a: tuple, b: tuple) -> tuple:
        return (*a[:k], *(f(x, y) for f, x, y in zip(combine, a[k:], b[k:], strict=True)))

    ranged = source.repartitionByRange(partitions, *[x.order() for x in spec]).select(*rows.columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        types: list[pa.DataType] = []

        def source_rows() -> Iterator[tuple]:
            for b in batches:
                types[:] = rows.types(b)
                yield from rows.read(b)

        out = sort_rows(source_rows(), k, memory, fan_in, kernel.Counters(), run_gen, compress, dedup, None, fold if aggs else None, merge, lossless)
        yield from _written(out, k, carried, types, [("__part", TaskContext.get().partitionId())])

    pieces = ranged.mapInArrow(run, _schema(["__part"], rows.fields))
    if stitched:
        pieces = stitch_parts(scratch.cut(pieces, "sorted"), spec)
    return _with_codes(pieces, spec)


def measured(df: DataFrame, keys: list, partitions: int, method: str, memory: int = 10_000, fan_in: int = 8, compress: bool | str = True, at_once: int = 1 << 17) -> DataFrame:
    """Counters of one method over all key ranges, a row for each range.

    method: tree, replacement, quick (external sorts; quick forms runs by full comparisons and merges
    with codes), traditional (quicksorted plain runs, binary-heap merges, full comparisons throughout),
    generate, full, pmnk1, pmnk2 (sorts of at most ``at_once`` rows in memory), merge_tree,
    merge_heap (``fan_in`` sorted runs, dealt by position, of at most ``at_once`` rows together). Sorts in memory
    make their comparisons many at once (``kernels.lockstep``) where keys are whole numbers; tree and traditional do where all keys' cells
    are numbers (``operators.external``), in the same runs and merges. plain_bytes is of external sorts.
    """
    spec = key_spec(keys)
    names = [x.name for x in spec]
    reader = Rows(df, spec, [])
    k, lossless = reader.k, reader.lossless
    traditional = method == "traditional"
    layout = "plain" if traditional else _layout(compress)
    many = 2 <= fan_in <= external.MOST_INPUTS and (traditional or (method == "tree" and layout in ("plain", "truncate"))) and reader.numeric(df)
    ranged = (df.select(*names).repartitionByRange(partitions, *[x.order() for x in spec]) if partitions > 1 else df.select(*names).coalesce(1)).select(*reader.columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ctr, sizes, n, plain, bound = kernel.Counters(), {}, 0, 0, 0.0

        def counted() -> Iterator[tuple]:
            nonlocal n, plain
            for b in batches:
                some = list(reader.read(b))
                n += len(some)
                plain += len(pickle.dumps(some, protocol=5))
                yield from some

        def portions() -> Iterator[list[pa.RecordBatch]]:
            nonlocal n, bound
            part: list[pa.RecordBatch] = []
            size = 0
            for b in batches:
                while b.num_rows:
                    part.append(b.slice(0, at_once - size))
                    b = b.slice(part[-1].num_rows)
                    size += part[-1].num_rows
                    if size == at_once:
                        n, bound = n + size, bound + lower_bound(size)
                        yield part
                        part, size = [], 0
            if size:
                n, bound = n + size, bound + lower_bound(size)
                yield part

        if many:
            with tempfile.TemporaryDirectory() as folder:
                sorter = external.Sorter(k, memory, fan_in, ctr, traditional, layout == "truncate", at_once, folder)
                for columns in external.portions(map(reader.cell_numbers, batches), max(1, at_once // memory) * memory):
                    n += len(columns[0])
                    sorter.form(columns)
                for _ in sorter.merged():
                    pass
            sizes, plain, bound = {"runs": sorter.formed, "spilled": sorter.spilled}, 8 * k * n, lower_bound(n)
        elif method in ("tree", "quick", "replacement", "traditional"):
            for _ in sort_rows(counted(), k, memory, fan_in, ctr, "quick" if traditional else method, layout, sizes=sizes, merge="heap" if traditional else "tree", lossless=lossless):
                pass
            bound = lower_bound(n)
        else:
            for part in portions():
                whole = reader.numbers(part) if method in ("generate", "full") or method.startswith("pmnk") else None
                if whole is not None:
                    if method == "generate":
                        lockstep.generate(whole, ctr)
                    elif method == "full":
                        lockstep.quicksort(whole, ctr)
                    else:
                        whole = [np.maximum(c, -1) + 1 for c in whole]  # small numbers, so that a prefix holds some
                        lockstep.quicksort(whole, ctr, lockstep.prefixes(whole, int(method[4:] or 1)))
                    continue
                rows = [r for b in part for r in reader.read(b)]
                if method == "generate":
                    out: Iterable = kernel.generate(rows, k, ctr, lossless)
                elif method == "full":
                    out = baselines.quicksort(rows, baselines.full_compare(ctr))
                elif method.startswith("pmnk"):
                    rows = [tuple(max(0, kernel.number(c) - (1 << 63)) for c in r) for r in rows]  # small numbers, so that a prefix holds some
                    entry, compare = baselines.prefix_compare(ctr, int(method[4:] or 1))
                    out = baselines.quicksort([entry(r) for r in rows], compare)
                elif method in ("merge_tree", "merge_heap"):
                    parts = [sorted(rows[i::fan_in]) for i in range(fan_in)]
                    out = kernel.LoserTree(k, ctr, lossless=lossless).merge([list(kernel.coded(p)) for p in parts]) if method == "merge_tree" else baselines.heap_merge(parts, ctr, duplicates=True)
                else:
                    raise ValueError(method)
                for _ in out:
                    pass
        values = [n, ctr.rows, ctr.by_code, ctr.columns, ctr.bypassed, sizes.get("runs", 0), sizes.get("spilled", 0), plain]
        names_out = ["n", *[c.split()[0] for c in _COUNTS.split(", ")], "lower_bound"]
        yield pa.RecordBatch.from_arrays([*(pa.array([v], pa.int64()) for v in values), pa.array([float(bound)])], names=names_out)

    return ranged.mapInArrow(run, f"n long, {_COUNTS}, lower_bound double")


# ---------------------------------------------------------------- exchange
def packets(runs: DataFrame, keys: list, run_id: str, bucket: Column) -> DataFrame:
    """Producers of an order-preserving exchange: the columns of runs, __bucket, __run, __off and __seq.

    A producer streams its sorted run once. A row's code in its packet is relative to the last row that
    went to the same bucket: the greatest code of all rows since, that is, the smallest offset. No
    column is compared for it; consumers need no more than the offset, as the value is in the row.
    """
    spec = key_spec(keys)
    names = [x.name for x in spec]
    x = runs.withColumn("__bucket", bucket.cast("int")).withColumn("__run", F.col(run_id).cast("long"))
    x = x.repartition("__run").sortWithinPartitions("__run", *[s.order() for s in spec])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, open_, seq = None, {}, 0
        for b in batches:
            if not b.num_rows:
                continue
            off = neighbour_offsets(b, ["__run", *names], last)
            off = np.maximum(off - 1, 0)  # a new run begins with offset 0
            to = b.column("__bucket").to_numpy()
            out = np.empty(b.num_rows, dtype=np.int32)
            for v in {*np.unique(to).tolist(), *open_}:
                at = np.flatnonzero(to == v)
                before = open_.get(v, 0 if last is not None else len(names))
                if len(at):
                    low = np.minimum.reduceat(off[: at[-1] + 1], np.concatenate(([0], at[:-1] + 1)))
                    low[0] = min(low[0], before)
                    out[at] = low
                    rest = off[at[-1] + 1 :]
                    open_[v] = int(rest.min()) if len(rest) else len(names)
                else:
                    open_[v] = min(before, int(off.min()))
            last = b.slice(b.num_rows - 1, 1)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out), pa.array(np.arange(seq, seq + b.num_rows))], names=[*b.schema.names, OFFSET, "__seq"])
            seq += b.num_rows

    schema = T.StructType([*(T.StructField(f.name, f.dataType, True) for f in x.schema.fields), T.StructField(OFFSET, T.IntegerType()), T.StructField("__seq", T.LongType())])
    return x.mapInArrow(run, schema)


def neighbour_offsets(b: pa.RecordBatch, names: list[str], last: pa.RecordBatch | None) -> np.ndarray:
    """Index of the first of ``names`` in which a row differs from the row before, or how many there are."""
    offset = np.full(b.num_rows, len(names), dtype=np.int32)
    for j in range(len(names) - 1, -1, -1):
        c = b.column(names[j])
        if last is not None:
            c = pa.concat_arrays([last.column(names[j]), c])
        x, y = c.slice(0, len(c) - 1), c.slice(1)
        same = pa.compute.equal(x, y)
        if pa.types.is_floating(c.type):
            same = pa.compute.or_(same, pa.compute.and_(pa.compute.is_nan(x), pa.compute.is_nan(y)))
        same = pa.compute.or_(pa.compute.fill_null(same, False), pa.compute.and_(x.is_null(), y.is_null())).to_numpy(zero_copy_only=False)
        offset[np.flatnonzero(~same) + (0 if last is not None else 1)] = j
    if last is None:
        offset[0] = 0
    return offset


def merge_packets(dealt: DataFrame, keys: list, fan_in: int = 16, counters: bool = False) -> DataFrame:
    """Consumers: the packets of a bucket are merged by the codes they carry; none is made anew.

    The host's exchange mixes the rows of packets; their places in the run, __seq, put them in order
    again, not their keys. Gives bucket, __pos, the columns and __off; or with counters a row for each
    task with what the merge did. A task holds one row of each run it merges: packets wait in its folder.
    """
    spec = key_spec(keys)
    rest = [c for c in dealt.columns if c not in ("__bucket", "__run", "__seq", OFFSET)]
    rows = Rows(dealt, spec, [*rest, OFFSET])
    k, lossless = rows.k, rows.lossless
    x = dealt.repartition("__bucket").sortWithinPartitions("__bucket", "__run", "__seq")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types: list[pa.DataType] = []
        ctr, total = kernel.Counters(), 0

        def tagged() -> Iterator[tuple[tuple[int, int], tuple[int, tuple]]]:
            for b in batches:
                types[:] = rows.types(b)[:-1]
                for bucket, own, row in zip(b.column("__bucket").to_pylist(), b.column("__run").to_pylist(), rows.read(b), strict=True):
                    n, row = row[-1], row[:-1]
                    yield (bucket, own), ((kernel.code(n, kernel.number(row[n]), k) if n < k else 0), row)

        def done(bucket: int, runs: list[Spill], folder: str) -> Iterator[pa.RecordBatch]:
            nonlocal total
            merged = merge_runs(runs, k, fan_in, ctr, folder, "truncate", lossless=lossless)
            if counters:
                total += sum(1 for _ in merged)
            else:
                yield from _written(merged, k, rest, types, [("bucket", bucket)])

        with tempfile.TemporaryDirectory() as folder:
            bucket, runs = None, []
            stream = tagged()
            item = next(stream, None)
            while item is not None:
                now = item[0]
                if now[0] != bucket:
                    if runs:
                        yield from done(bucket, runs, folder)
                    bucket, runs = now[0], []

                def one() -> Iterator[tuple[int, tuple]]:
                    nonlocal item
                    while item is not None and item[0] == now:
                        yield item[1]
                        item = next(stream, None)

                runs.append(Spill(folder, k, "truncate").write(one()))
            if runs:
                yield from done(bucket, runs, folder)
        if counters:
            yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (total, ctr.rows, ctr.by_code, ctr.columns, ctr.bypassed)], names=["n", "row_cmp", "by_code", "columns", "bypassed"])

    y = x.select("__bucket", "__run", *rows.columns)
    return y.mapInArrow(run, "n long, row_cmp long, by_code long, columns long, bypassed long" if counters else _schema(["bucket"], rows.fields[:-1]))


def bucket_by(runs: DataFrame, keys: list, buckets: int, by: str) -> Column:
    """range (bounds are quantiles of the first key's number, one for each bucket), hash (of all keys) or single."""
    spec = key_spec(keys)
    if by == "single":
        return F.lit(0)
    if by == "hash":
        return F.pmod(F.xxhash64(*[x.name for x in spec]), F.lit(buckets)).cast("int")
    first = normalize(spec[0], kinds(runs, spec)[0])
    bounds = runs.agg(F.percentile_approx(first, [i / buckets for i in range(1, buckets)], 10_000)).first()[0] or []
    bucket = F.lit(0)
    for b in sorted(set(bounds)):
        bucket = bucket + (first > F.lit(b)).cast("int")
    return bucket


def merging_exchange(runs: DataFrame, keys: list, run_id: str, buckets: int, by: str = "range", counters: bool = False) -> DataFrame:
    """Sorted runs of many producers -> sorted streams of consumers, merged by the codes in packets."""
    return merge_packets(packets(runs, keys, run_id, bucket_by(runs, keys, buckets, by)), keys, counters=counters)
