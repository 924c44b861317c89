"""Comparing coded rows, and a priority queue that keeps losers in its nodes.

Rows are tuples whose first K entries are key cells; what follows is carried along. A cell is a whole
number below 2**66 that stands for its value exactly, or, where no number can (texts), a pair of such
a number, which never falls as the value rises, and the value itself (empty where the number says all). A code is (K - offset) * 2**66 +
number at the offset; FRESH rows of run generation have looked at no column yet. All rows that meet
were coded relative to the same row, the last one to leave the queue.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

SHIFT = 66
RUN = 80  # bits below the number of the run, in replacement selection
MASK = (1 << SHIFT) - 1
EARLY = -1  # before any row
LATE = 1 << 100  # after any row


@dataclass
class Counters:
    """What was done. Comparisons with fences aren't row comparisons."""

    rows: int = 0  # comparisons of two rows
    by_code: int = 0  # of these, decided by the codes alone
    columns: int = 0  # pairs of column values looked at
    bypassed: int = 0  # repeated keys that never entered the queue
    translated: int = 0  # updates of run-length counters


def code(offset: int, value: int, k: int) -> int:
    return 0 if offset >= k else (k - offset) << SHIFT | value


def fresh(k: int) -> int:
    """The code of a row of which nothing is known: offset 0, no value read."""
    return (k + 1) << SHIFT


def offset(c: int, k: int) -> int:
    return min(k, max(0, k - (c >> SHIFT)))


def number(cell: int | tuple) -> int:
    return cell if type(cell) is int else cell[0]


def derive(before: tuple | None, row: tuple, ctr: Counters | None = None, k: int | None = None) -> int:
    """A row's code relative to its predecessor, by comparing columns."""
    k = len(row) if k is None else k
    if before is None:
        return code(0, number(row[0]), k)
    for i in range(k):
        if ctr:
            ctr.columns += 1
        if before[i] != row[i]:
            return code(i, number(row[i]), k)
    return 0


class LoserTree:
    """Merges coded inputs. One pass from leaf to root for each row that leaves.

    lossless: all cells are plain numbers, so equal codes prove the column at the offset equal. Rows
    of equal keys leave in the order of their inputs.
    """

    def __init__(self, k: int, ctr: Counters, bypass_duplicates: bool = True, lossless: bool = True):
        self.k, self.ctr, self.bypass, self.lossless = k, ctr, bypass_duplicates, lossless

    def _less(self, a: int, b: int) -> bool:
        """Whether entry a leaves before entry b; the loser's code is made relative to the winner."""
        x, y = self.codes[a], self.codes[b]
        if x >= LATE or y >= LATE or x == EARLY or y == EARLY:
            return x < y or (x == y and a < b)
        ctr = self.ctr
        ctr.rows += 1
        if x != y:
            ctr.by_code += 1
            return x < y
        run = x >> RUN << RUN
        k, at = self.k, self.k - ((x - run) >> SHIFT)
        if at >= k:  # both repeat the base
            ctr.by_code += 1
            return a < b
        ra, rb = self.rows[a], self.rows[b]
        # the column at the offset is equal too, unless its number doesn't say all
        again = not self.lossless and at >= 0 and type(ra[at]) is tuple and ra[at][1]
        for i in range(at if again else at + 1, k):
            ctr.columns += 1
            if ra[i] != rb[i]:
                if ra[i] < rb[i]:
                    self.codes[b] = run | (k - i) << SHIFT | (rb[i] if self.lossless else number(rb[i]))
                    return True
                self.codes[a] = run | (k - i) << SHIFT | (ra[i] if self.lossless else number(ra[i]))
                return False
        self.codes[b if a < b else a] = run
        return a < b

    def merge(self, inputs: list[Iterable[tuple[int, tuple]]]) -> Iterator[tuple[int, tuple]]:
        """inputs: (code relative to the row before, row) in order. Gives the same, merged."""
        sources = [iter(x) for x in inputs]
        n = max(2, len(sources))
        self.codes, self.rows = [LATE] * n, [None] * n
        for i, source in enumerate(sources):
            self._fetch(i, source)
        nodes = [0] * n  # nodes[1..n-1]: losers
        win = [0] * (2 * n)
        win[n:] = range(n)
        for i in range(n - 1, 0, -1):
            a, b = win[2 * i], win[2 * i + 1]
            win[i], nodes[i] = (a, b) if self._less(a, b) else (b, a)
        top = win[1]
        while self.codes[top] < LATE:
            yield self.codes[top], self.rows[top]
            self._fetch(top, sources[top])
            while self.bypass and self.codes[top] == 0:
                self.ctr.bypassed += 1
                yield 0, self.rows[top]
                self._fetch(top, sources[top])
            entry, node = top, (n + top) >> 1
            while node:
                if not self._less(entry, nodes[node]):
                    entry, nodes[node] = nodes[node], entry
                node >>= 1
            top = entry

    def _fetch(self, i: int, source: Iterator[tuple[int, tuple]]) -> None:
        self.codes[i], self.rows[i] = next(source, (LATE, None))


def generate(rows: list[tuple], k: int, ctr: Counters, lossless: bool = True) -> Iterator[tuple[int, tuple]]:
    """One run from unsorted rows, as a merge of runs of one row each. Reads columns when needed."""
    start = fresh(k)
    for c, row in LoserTree(k, ctr, bypass_duplicates=False, lossless=lossless).merge([[(start, r)] for r in rows]):
        yield (code(0, number(row[0]), k) if c == start else c), row


def coded(rows: Iterable[tuple], ctr: Counters | None = None, k: int | None = None) -> Iterator[tuple[int, tuple]]:
    """Codes for rows that are in order, as when a run is written or read."""
    before = None
    for row in rows:
        yield derive(before, row, ctr, k), row
        before = row


def folded(run: Iterable[tuple[int, tuple]], k: int, fold: Callable[[tuple, tuple], tuple]) -> Iterator[tuple[int, tuple]]:
    """Rows that repeat a key are taken into the one before, which keeps its code: a group's code is
    its first row's. Only codes are looked at. fold: (carried, carried) -> carried."""
    held: tuple[int, tuple] | None = None
    for c, row in run:
        if held is not None and c == 0:
            held = held[0], (*held[1][:k], *fold(held[1][k:], row[k:]))
            continue
        if held is not None:
            yield held
        held = c, row
    if held is not None:
        yield held


def replacement_selection(rows: Iterable[tuple], k: int, memory: int, ctr: Counters, lossless: bool = True) -> Iterator[list[tuple[int, tuple]]]:
    """Runs about twice as long as memory (in rows), each with its codes.

    The number of its run is the most significant part of a row's code. A new row is compared with
    the row that left last: if it isn't smaller, it gets its code from that comparison and takes the
    free place in the queue, whose path has that same row as its base. A smaller row waits for the
    next run, coded as the first row of a run of its own.
    """
    source = iter(rows)
    run_of = lambda c: c >> RUN
    last: list = [0, None]

    def feed(first: tuple) -> Iterator[tuple[int, tuple]]:
        yield code(0, number(first[0]), k), first
        for row in source:
            run, before = last
            ctr.rows += 1
            smaller = False
            for a, b in zip(row[:k], before[:k], strict=True):
                ctr.columns += 1
                if a != b:
                    smaller = a < b
                    break
            if smaller:
                yield (run + 1) << RUN | code(0, number(row[0]), k), row
            else:
                yield run << RUN | derive(before, row, None, k), row

    head = []
    for row in source:
        head.append(row)
        if len(head) == memory:
            break
    tree = LoserTree(k, ctr, bypass_duplicates=False, lossless=lossless)
    out: list[tuple[int, tuple]] = []
    for c, row in tree.merge([feed(r) for r in head]):
        if run_of(c) != last[0]:
            yield out
            out = []
        last[0], last[1] = run_of(c), row
        out.append((c & ((1 << RUN) - 1), row))
    if out:
        yield out


def variable_runs(rows: Iterable[tuple], k: int, memory: int, ctr: Counters, size: Callable[[tuple], int], fit: str = "first") -> Iterator[list[tuple[int, tuple]]]:
    """Replacement selection in a workspace of bytes. A row needs one free place that holds it: the
    first or the best. If none does, more rows leave first; so runs are shorter than with equal rows.

    Rows enter at places that aren't the last winner's, so codes can't decide; they are made on output.
    """
    source = iter(rows)
    compare_columns = ctr
    holes: list[tuple[int, int]] = [(0, memory)]  # (start, length), by start
    heap: list[tuple[int, tuple, int, int]] = []
    run, before, out = 0, None, []
    pending = next(source, None)
    while heap or pending is not None:
        while pending is not None:
            need = size(pending)
            fits = [h for h in holes if h[1] >= need]
            if not fits:
                break
            start, length = min(fits, key=lambda h: h[1]) if fit == "best" else fits[0]
            at = holes.index((start, length))
            holes[at : at + 1] = [(start + need, length - need)] if length > need else []
            ctr.rows += before is not None
            target = run if before is None or pending >= before else run + 1
            heapq.heappush(heap, (target, pending, start, need))
            pending = next(source, None)
        if not heap:
            raise ValueError("a row is larger than memory")
        target, row, start, length = heapq.heappop(heap)
        holes = _join_holes(holes, start, length)
        if target != run:
            yield out
            run, out, before = target, [], None
        out.append((derive(before, row, compare_columns), row))
        before = row
    if out:
        yield out


def _join_holes(holes: list[tuple[int, int]], start: int, length: int) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for s, n in sorted([*holes, (start, length)]):
        if out and out[-1][0] + out[-1][1] == s:
            out[-1] = (out[-1][0], out[-1][1] + n)
        else:
            out.append((s, n))
    return out


def indexed_aggregate(rows: Iterable[tuple[tuple, float]], memory: int) -> Iterator[list[tuple[tuple, int, float]]]:
    """Runs of groups (key, count, sum): an in-memory index takes in repeated keys while runs form."""
    index: dict[tuple, list] = {}
    for key, value in rows:
        if key not in index and len(index) == memory:
            yield [(x, n, s) for x, (n, s) in sorted(index.items())]
            index = {}
        entry = index.setdefault(key, [0, 0.0])
        entry[0] += 1
        entry[1] += value
    if index:
        yield [(x, n, s) for x, (n, s) in sorted(index.items())]
