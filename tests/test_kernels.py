"""Worked examples, counts and round trips of the kernels."""

import itertools
import os
import random
import tempfile
import time

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from prefixcode.functions import codes
from prefixcode.functions.measures import column_bound, key_depth, lower_bound
from prefixcode.kernels import baselines, formats, lockstep
from prefixcode.kernels.tree import Counters, LoserTree, coded, generate, indexed_aggregate, offset, replacement_selection, variable_runs
from prefixcode.operators import external, sort
from prefixcode.workloads import experiments

RUNS = [
    [(1, 1, 2, 5, 1, 1, 1, 1, 1), (1, 1, 2, 5, 1, 2, 1, 1, 1), (1, 1, 2, 5, 1, 3, 0, 0, 0)],
    [(1, 1, 1, 1, 1, 1, 1, 1, 1), (1, 1, 1, 2, 10, 1, 1, 1, 1), (1, 1, 2, 5, 1, 3, 0, 1, 0)],
    [(1, 1, 2, 5, 1, 3, 0, 0, 1), (1, 1, 2, 5, 1, 3, 0, 0, 2), (1, 1, 2, 5, 1, 3, 0, 0, 3), (2, 0, 0, 0, 0, 0, 0, 0, 0), (2, 0, 0, 0, 0, 0, 0, 0, 1), (2, 0, 1, 0, 9, 9, 9, 9, 9), (2, 0, 2, 0, 0, 0, 0, 0, 0)],
]


def test_merge_example():
    ctr = Counters()
    out = list(LoserTree(9, ctr).merge([list(coded(r)) for r in RUNS]))
    assert [r for _, r in out] == sorted(itertools.chain(*RUNS))
    prefixes = [offset(c, 9) for c, _ in out]
    assert prefixes == [0, 3, 2, 5, 5, 8, 8, 8, 7, 0, 8, 2, 2]
    before = sum(offset(c, 9) for r in RUNS for c, _ in coded(r))
    assert ctr.columns == 15 == sum(prefixes) - before


def test_decimal_code():
    assert (4 - 3) * 100 + 44 == 144
    low, high = (11, 22, 33, 43), (11, 22, 33, 44)
    assert codes.of_pair(low, high) == codes.pack_one(3, 44, 4)


def test_algebra():
    rows = list(itertools.product(range(3), repeat=3))
    for a, b, c in itertools.combinations_with_replacement(rows, 3):
        ab, bc, ac = codes.of_pair(a, b), codes.of_pair(b, c), codes.of_pair(a, c)
        assert ac == max(ab, bc)
        if ab < ac:
            assert codes.of_pair(b, c) == ac


rows_strategy = st.integers(1, 4).flatmap(lambda k: st.lists(st.tuples(*[st.integers(0, 3)] * k), max_size=60).map(lambda rows: (k, rows)))


@settings(max_examples=60, deadline=None)
@given(rows_strategy)
def test_run_generation(case):
    k, rows = case
    ctr = Counters()
    out = list(generate(rows, k, ctr))
    assert [r for _, r in out] == sorted(rows)
    assert [c for c, _ in out] == [c for c, _ in coded(sorted(rows))]
    assert ctr.columns <= column_bound(len(rows), k)
    if rows:
        assert ctr.columns == sum(min(offset(c, k) + 1, k) for c, _ in out) - 1


@settings(max_examples=60, deadline=None)
@given(rows_strategy, st.integers(1, 7), st.booleans())
def test_merge_any(case, fan_in, bypass):
    k, rows = case
    runs = [sorted(rows[i::fan_in]) for i in range(fan_in)]
    ctr = Counters()
    out = list(LoserTree(k, ctr, bypass_duplicates=bypass).merge([list(coded(r)) for r in runs]))
    assert [r for _, r in out] == sorted(rows)
    assert [c for c, _ in out] == [c for c, _ in coded(sorted(rows))]


@settings(max_examples=60, deadline=None)
@given(rows_strategy, st.booleans())
def test_format_round_trips(case, carry):
    k, rows = case
    rows = sorted(rows)
    stored = list(formats.truncate(coded(rows), k))
    assert [r for _, r in formats.expand(stored, k)] == rows
    assert list(formats.expand(stored, k)) == list(coded(rows))
    columns = formats.to_columns(stored, k, Counters(), carry)
    assert columns == formats.to_columns(stored, k, Counters(), not carry)
    if rows:
        assert list(formats.to_rows(columns, Counters(), carry)) == stored
        assert list(formats.coded_rows(columns, Counters())) == list(coded(rows))
    assert sum(len(tail) for _, tail in stored) == sum(len(c) for c in columns)


def test_translation_example():
    row, stored = [0] * 5, []
    for p in (0, 1, 2, 4, 4, 4, 3, 1, 0):
        row = row[:p] + [row[p] + 1] + [0] * (4 - p)
        stored.append((p, tuple(row[p:])))
    with_carry, plain = Counters(), Counters()
    columns = formats.to_columns(stored, 5, with_carry)
    formats.to_columns(stored, 5, plain, carry=False)
    assert [sum(e for _, e in c) for c in columns] == [7, 5, 4, 3, 0]
    assert sum(p for p, _ in stored) == 19 == plain.translated
    assert with_carry.translated == 7 + 3


@pytest.mark.parametrize("order", ["uniform", "sorted", "reversed", "few", "none"])
def test_replacement_selection(order):
    r = random.Random(3)
    rows = [(r.randrange(10**6), r.randrange(3)) for _ in range(2000)]
    rows = {"uniform": rows, "sorted": sorted(rows), "reversed": sorted(rows, reverse=True), "few": [(a % 5, b) for a, b in rows], "none": []}[order]
    runs = list(replacement_selection(rows, 2, 50, Counters()))
    for run in runs:
        assert run == list(coded([x for _, x in run]))
    assert sorted(x for run in runs for _, x in run) == sorted(rows)
    if order == "uniform":
        assert 1.7 < 2000 / len(runs) / 50 < 2.2
    if order == "sorted":
        assert len(runs) == 1
    if order == "reversed":
        assert len(runs) == -(-2000 // 50)


def test_variable_rows_make_shorter_runs():
    r = random.Random(3)
    rows = [(r.randrange(10**6),) for _ in range(4000)]
    for fit in ("first", "best"):
        runs = list(variable_runs(rows, 1, 5000, Counters(), lambda x: 50 + x[0] % 101, fit))
        assert 1.4 < sum(map(len, runs)) / len(runs) / 50 < 1.95
        assert sorted(x for run in runs for _, x in run) == sorted(rows)


def test_indexed_aggregate():
    rows = [((i % 7,), 1.0) for i in range(100)]
    assert [(k, n) for k, n, _ in next(iter(indexed_aggregate(rows, 10)))] == [((i,), 15 if i < 2 else 14) for i in range(7)]


def test_row_comparisons():
    (uniform, *_, worst) = experiments.run_generation(1000)
    assert uniform["tree"] < uniform["quicksort"] and uniform["factor"] < 1.03
    assert worst["quicksort"] > 1000 * 999 / 2 - 1
    (merge,) = experiments.merging(1000)
    assert abs(merge["factor"] - 1.642) < 0.02 and merge["tree"] <= 24_000


def test_column_comparisons_with_constant_prefix():
    rows = list(experiments.constant_prefix(300))
    for x in rows:
        assert x["columns_with"] == x["expected_with"]
        assert x["columns_without"] == (x["prefix"] + 1) * x["row_cmp_without"]


def test_duplicates_bypass_more_with_more_copies():
    rows = list(experiments.duplicates(300))
    assert [x["bypassed"] for x in rows] == sorted(x["bypassed"] for x in rows)
    assert all(x["columns_codes"] < x["columns_full"] for x in rows)


def test_compression_ratio():
    assert all(x["same_cells"] for x in experiments.compression(500))
    stored = lambda n, c: c + sum(9**j * (1 - (1 - 9.0**-j) ** n) for j in range(1, 11 - c))
    assert [int(10 * 1e6 / stored(10**6, c)) for c in (2, 4, 6, 8)] == [4, 19, 1353, 102040]


def test_measures():
    assert abs(lower_bound(1000) - 8529.4) < 0.1
    assert round(key_depth(1e10, 3)) == 21


@settings(max_examples=40, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 20), st.integers(0, 3)), max_size=80))
def test_baselines_sort(rows):
    assert baselines.quicksort(rows, baselines.full_compare(Counters())) == sorted(rows)
    assert baselines.plain_quicksort(rows, baselines.full_compare(Counters())) == sorted(rows)
    entry, compare = baselines.prefix_compare(Counters(), 1)
    assert [x[1] for x in baselines.quicksort([entry(r) for r in rows], compare)] == sorted(rows)
    assert list(baselines.heap_merge([sorted(rows[i::3]) for i in range(3)], Counters(), True)) == sorted(rows)


@settings(max_examples=150, deadline=None)
@given(st.integers(1, 4), st.sampled_from([0, 1, 2, 9, 1000]), st.sampled_from(["mixed", "sorted", "reversed"]), st.integers(1, 300), st.integers(0, 1 << 30))
def test_lockstep_makes_the_same_comparisons(k, most, order, n, seed):
    """Rows, decisions by codes and columns are those of the kernels that go row by row, and so is the order."""
    rng = np.random.default_rng(seed)
    columns = [rng.integers(0, most + 1, n) for _ in range(k)]
    if order != "mixed":
        columns = [np.sort(c)[:: 1 if order == "sorted" else -1].copy() for c in columns]
    rows = list(zip(*(c.tolist() for c in columns), strict=True))
    one, many = Counters(), Counters()
    want = [r for _, r in generate(rows, k, one)]
    assert want == [rows[i] for i in lockstep.generate(columns, many)] and one == many
    one, many = Counters(), Counters()
    want = baselines.quicksort(rows, baselines.full_compare(one))
    assert want == [rows[i] for i in lockstep.quicksort(columns, many)] and one == many
    for count in (1, 2):
        one, many = Counters(), Counters()
        entry, compare = baselines.prefix_compare(one, count)
        want = [r for _, r in baselines.quicksort([entry(r) for r in rows], compare)]
        assert want == [rows[i] for i in lockstep.quicksort(columns, many, lockstep.prefixes(columns, count))] and one == many


def test_lockstep_sorts_many_rows_fast():
    """A portion of 131,072 rows takes well under a second; row by row it takes several."""
    column = np.random.default_rng(5).integers(0, 4000, 1 << 17)
    start = time.perf_counter()
    tree, quick = Counters(), Counters()
    lockstep.generate([np.ones_like(column), column], tree)
    lockstep.quicksort([np.ones_like(column), column], quick)
    assert time.perf_counter() - start < 4
    assert tree.rows <= 1.04 * lower_bound(len(column)) and quick.columns == 2 * quick.rows > 2 * tree.rows


@settings(max_examples=120, deadline=None)
@given(st.integers(1, 3), st.sampled_from([0, 1, 3, 30, 1000]), st.integers(1, 700), st.integers(2, 9), st.integers(2, 5), st.sampled_from([1, 40, 1 << 17]), st.booleans(), st.integers(0, 1 << 30))
def test_external_sorts_make_the_same_comparisons_many_at_once(k, most, n, memory, fan_in, at_once, traditional, seed):
    """Runs, merges, counts, rows and offsets are those of the external sort that goes row by row, in parts or at once."""
    rng = np.random.default_rng(seed)
    columns = [rng.integers(0, most + 1, n) for _ in range(k)]
    rows, one, many, sizes = list(zip(*(c.tolist() for c in columns), strict=True)), Counters(), Counters(), {}
    gen, merge, layout = ("quick", "heap", "plain") if traditional else ("tree", "tree", "truncate")
    want = [(offset(c, k), r) for c, r in sort.sort_rows(rows, k, memory, fan_in, one, gen, layout, sizes=sizes, merge=merge)]
    with tempfile.TemporaryDirectory() as folder, pytest.MonkeyPatch.context() as m:
        m.setattr(external, "_BLOCK", 3)
        m.setattr(external, "_FILE", 200)
        sorter = external.Sorter(k, memory, fan_in, many, traditional, not traditional, at_once, folder)
        for part in external.portions(iter([columns]), max(1, at_once // memory) * memory):
            sorter.form(part)
        got = [(int(o), tuple(int(c[i]) for c in x)) for x, off in sorter.merged() for i, o in enumerate(off)]
        assert not os.listdir(folder)
    assert got == want and many == one and sorter.formed == sizes["runs"]
