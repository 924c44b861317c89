"""A DataFrame whose order is known, with its codes as ordinary columns."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

from prefixcode.functions.keys import KeyCol

CODE = "__code"
OFFSET = "__off"


@dataclass(frozen=True)
class OrderedFrame:
    df: DataFrame
    keys: list[KeyCol]
    scope: str = "global"  # codes are relative to the predecessor in the table, or in a block
    partitioned_by: tuple[str, ...] = ()
    source: DataFrame | None = None  # the same rows before they were put in this order

    @property
    def names(self) -> list[str]:
        return [k.name for k in self.keys]

    @property
    def k(self) -> int:
        return len(self.keys)

    def with_df(self, df: DataFrame) -> OrderedFrame:
        """Other rows in the same order. An order that was lost with a key or code column is noticed."""
        lost = [c for c in (*self.names, CODE, OFFSET) if c not in df.columns]
        changed = [c for c in self.names if c in df.columns and df.schema[c].dataType != self.df.schema[c].dataType]
        if lost or changed:
            raise ValueError(f"the order is lost: {', '.join([*(f'no {c}' for c in lost), *(f'another type of {c}' for c in changed)])}")
        return replace(self, df=df, source=None)

    def need_global(self, what: str) -> None:
        if self.scope != "global":
            raise ValueError(f"{what} needs codes over the whole table; these are by {self.partitioned_by}")

    def plain(self) -> DataFrame:
        return self.df.drop(CODE, OFFSET)

    def explain(self) -> str:
        order = ", ".join(f"{k.name}{'' if k.ascending else ' desc'}" for k in self.keys)
        return f"ordered by ({order}); codes: {self.scope}; rows with equal {self.partitioned_by or '-'} together"
