"""The methods that coded sorting is held against, with the same counters."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

from prefixcode.kernels.tree import Counters

Compare = Callable[[tuple, tuple], int]


def full_compare(ctr: Counters, k: int | None = None) -> Compare:
    """Column by column from the first, all or ``k``."""

    def compare(a: tuple, b: tuple) -> int:
        ctr.rows += 1
        for x, y in zip(a[:k], b[:k], strict=True):
            ctr.columns += 1
            if x != y:
                return -1 if x < y else 1
        return 0

    return compare


def prefix_compare(ctr: Counters, columns: int, bits: int = 60) -> tuple[Callable[[tuple], tuple[int, tuple]], Compare]:
    """(entry of a row, comparison of entries): a fixed normalised prefix first, all columns on a tie."""
    full = full_compare(ctr)
    each = bits // columns

    def entry(row: tuple) -> tuple[int, tuple]:
        p = 0
        for v in row[:columns]:
            p = p << each | min(v, (1 << each) - 1)
        return p, row

    def compare(a: tuple, b: tuple) -> int:
        if a[0] != b[0]:
            ctr.rows += 1
            ctr.by_code += 1
            return -1 if a[0] < b[0] else 1
        return full(a[1], b[1])

    return entry, compare


def quicksort(rows: list, compare: Compare) -> list:
    """Median of three, two pointers, the larger part later; no shortcut for small parts."""
    a = list(rows)
    stack = [(0, len(a) - 1)]
    while stack:
        lo, hi = stack.pop()
        while lo < hi:
            if hi - lo == 1:
                if compare(a[hi], a[lo]) < 0:
                    a[lo], a[hi] = a[hi], a[lo]
                break
            mid = (lo + hi) // 2
            if compare(a[mid], a[lo]) < 0:
                a[mid], a[lo] = a[lo], a[mid]
            if compare(a[hi], a[mid]) < 0:
                a[hi], a[mid] = a[mid], a[hi]
                if compare(a[mid], a[lo]) < 0:
                    a[mid], a[lo] = a[lo], a[mid]
            if hi - lo == 2:
                break
            pivot, i, j = a[mid], lo + 1, hi - 1
            while i <= j:
                while compare(a[i], pivot) < 0:
                    i += 1
                while compare(pivot, a[j]) < 0:
                    j -= 1
                if i <= j:
                    a[i], a[j] = a[j], a[i]
                    i, j = i + 1, j - 1
            if j - lo < hi - i:
                stack.append((i, hi))
                hi = j
            else:
                stack.append((lo, j))
                lo = i
    return a


def plain_quicksort(rows: list, compare: Compare) -> list:
    """The last row is the pivot: quadratic on rows that are in order already."""
    a = list(rows)
    stack = [(0, len(a) - 1)]
    while stack:
        lo, hi = stack.pop()
        if lo >= hi:
            continue
        p = lo
        for i in range(lo, hi):
            if compare(a[i], a[hi]) < 0:
                a[i], a[p] = a[p], a[i]
                p += 1
        a[p], a[hi] = a[hi], a[p]
        stack += [(lo, p - 1), (p + 1, hi)]
    return a


def heap_merge(inputs: list[Iterable[tuple]], ctr: Counters, duplicates: bool = False, k: int | None = None) -> Iterator[tuple]:
    """A binary heap with two passes for a row: down from the root on removal, up from a leaf on insertion.

    duplicates: a full comparison tells whether the next row of the same input repeats the last one,
    which then goes straight to the output.
    """
    compare = full_compare(ctr, k)
    sources = [iter(x) for x in inputs]
    heap: list[tuple[tuple, int]] = []
    for i, s in enumerate(sources):
        row = next(s, None)
        if row is not None:
            heap.append((row, i))

    def less(a: tuple[tuple, int], b: tuple[tuple, int]) -> bool:
        return (compare(a[0], b[0]) or a[1] - b[1]) < 0

    def up(i: int) -> None:
        item = heap[i]
        while i and less(item, heap[(i - 1) // 2]):
            heap[i], i = heap[(i - 1) // 2], (i - 1) // 2
        heap[i] = item

    def pop() -> None:
        """The hole at the root sinks to a leaf; the last entry fills it and rises."""
        last = heap.pop()
        if not heap:
            return
        i, n = 0, len(heap)
        while 2 * i + 1 < n:
            c = 2 * i + 1
            if c + 1 < n and less(heap[c + 1], heap[c]):
                c += 1
            heap[i], i = heap[c], c
        heap[i] = last
        up(i)

    for i in range(1, len(heap)):
        up(i)
    while heap:
        row, source = heap[0]
        yield row
        new = next(sources[source], None)
        while duplicates and new is not None and compare(new, row) == 0:
            ctr.bypassed += 1
            yield new
            new = next(sources[source], None)
        pop()
        if new is not None:
            heap.append((new, source))
            up(len(heap) - 1)
