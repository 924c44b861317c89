"""Merge join of two coded inputs. Which key is next, and whether it is the same, the codes say."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

from prefixcode.kernels.tree import Counters, LoserTree


def merge_rows(
    left: Iterable[tuple[int, tuple]], right: Iterable[tuple[int, tuple]], k: int, ctr: Counters, how: str, is_left: Callable[[tuple], bool], is_null: Callable[[tuple], bool], lossless: bool = True
) -> Iterator[tuple[int, tuple | None, tuple | None]]:
    """(code, left row or None, right row or None) in key order.

    Both inputs run through one queue of two; a row that leaves it with code 0 has the key of the row
    before it. Left rows of a key come first. A key's first output row has the greatest code of all
    rows since the last output key, its other output rows repeat the key: code 0. Rows for which is_null
    holds match nothing.
    """
    keep_left, keep_right = how in ("left", "full"), how in ("right", "full")
    since = 0  # the greatest code since the last output key
    held: list[tuple] = []
    matched = fresh = False

    def code() -> int:
        nonlocal since, fresh
        c, since, fresh = (since, 0, False) if fresh else (0, since, fresh)
        return c

    def close() -> Iterator[tuple[int, tuple | None, tuple | None]]:
        """What the left rows of a finished key still give."""
        if held and ((how == "semi" and matched) or (how == "anti" and not matched) or (keep_left and not matched)):
            for row in held:
                yield code(), row, None

    for c, row in LoserTree(k, ctr, lossless=lossless).merge([left, right]):
        if c:
            yield from close()
            held, matched, fresh = [], False, True
            since = max(since, c)
        if is_left(row):
            held.append(row)
        elif held and not is_null(row):
            matched = True
            if how not in ("semi", "anti"):
                for a in held:
                    yield code(), a, row
        elif keep_right:
            yield code(), None, row
    yield from close()
