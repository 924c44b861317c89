"""Row format with truncated prefixes, column format with run lengths, and translation between them."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

from prefixcode.kernels.tree import Counters, code, number, offset


def truncate(run: Iterable[tuple[int, tuple]], k: int) -> Iterator[tuple[int, tuple]]:
    """(code, row) -> (prefix size, the columns that are stored)."""
    for c, row in run:
        n = offset(c, k)
        yield n, row[n:]


def expand(stored: Iterable[tuple[int, tuple]], k: int) -> Iterator[tuple[int, tuple]]:
    """(prefix size, tail) -> (code, row): codes are free, no column is compared."""
    row: tuple = ()
    for n, tail in stored:
        row = row[:n] + tail
        yield (code(n, number(tail[0]), k) if n < k else 0), row


def to_columns(stored: Iterable[tuple[int, tuple]], k: int, ctr: Counters, carry: bool = True) -> list[list[tuple[object, int]]]:
    """Truncated rows -> for each column its runs (value, how many rows more).

    With carry, a row moves only the counter of its last truncated column; when a shorter prefix
    comes, a counter is closed and passed on to the column at its left.
    """
    values: list[list] = [[] for _ in range(k)]
    extra: list[list[int]] = [[] for _ in range(k)]
    open_ = [0] * (k + 1)  # by the number of the column, from 1
    for n, tail in stored:
        if carry:
            for j in range(k, n, -1):
                if open_[j]:
                    extra[j - 1][-1] += open_[j]
                    if j > 1:
                        open_[j - 1] += open_[j]
                        ctr.translated += 1
                    open_[j] = 0
            if n:
                open_[n] += 1
                ctr.translated += 1
        else:
            for j in range(n):
                extra[j][-1] += 1
                ctr.translated += 1
        for j, v in enumerate(tail, n):
            values[j].append(v)
            extra[j].append(0)
    if carry:
        for j in range(k, 0, -1):
            if open_[j]:
                extra[j - 1][-1] += open_[j]
                if j > 1:
                    open_[j - 1] += open_[j]
                    ctr.translated += 1
    return [list(zip(v, e, strict=True)) for v, e in zip(values, extra, strict=True)]


def to_rows(columns: list[list[tuple[object, int]]], ctr: Counters, carry: bool = True) -> Iterator[tuple[int, tuple]]:
    """Runs -> (prefix size, tail). A row stores from the first column whose run begins with it.

    With carry, only the last column steps; a column is looked at when the one at its right ends.
    """
    k = len(columns)
    at = [0] * k
    left = [runs[0][1] for runs in columns] if columns and columns[0] else []
    if not left:
        return
    yield 0, tuple(runs[0][0] for runs in columns)
    done = 1
    total = sum(e + 1 for _, e in columns[-1])
    steps = [0] * k  # rows of the present run used so far
    while done < total:
        first = k
        if carry:
            j = k - 1
            while j >= 0:
                ctr.translated += 1
                if steps[j] < columns[j][at[j]][1]:
                    steps[j] += 1
                    break
                # this run ends; the column to the left must account for the rows of this run
                if j:
                    steps[j - 1] += steps[j]
                at[j], steps[j], first = at[j] + 1, 0, j
                j -= 1
        else:
            for j in range(k):
                ctr.translated += 1
                if left[j]:
                    left[j] -= 1
                else:
                    at[j] += 1
                    left[j], first = columns[j][at[j]][1], min(first, j)
        yield first, tuple(columns[j][at[j]][0] for j in range(first, k))
        done += 1


def coded_rows(columns: list[list[tuple[object, int]]], ctr: Counters) -> Iterator[tuple[int, tuple]]:
    """Merge input straight from runs: of each row only the values that begin runs are read."""
    return expand(to_rows(columns, ctr), len(columns))
