"""Which work an order that is wanted costs, given the order that is there."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from prefixcode.functions.keys import KeyCol, key_spec
from prefixcode.operators.derive import attach
from prefixcode.operators.stream import extend_sort, shorten
from prefixcode.plans.frame import OrderedFrame


@dataclass(frozen=True)
class Step:
    kind: str  # none, shorten, segmented sort, full sort
    shared: int


def choose(present: list[KeyCol], wanted: list[KeyCol]) -> Step:
    shared = 0
    for a, b in zip(present, wanted, strict=False):
        if a != b:
            break
        shared += 1
    if shared == len(wanted):
        return Step("none" if shared == len(present) else "shorten", shared)
    return Step("segmented sort" if shared else "full sort", shared)


def order(frame: OrderedFrame | DataFrame, keys: list, lead: int = 1) -> tuple[OrderedFrame, Step]:
    """The rows in the wanted order with codes, by the cheapest step."""
    wanted = key_spec(keys)
    if isinstance(frame, DataFrame):
        return attach(frame, keys, lead), Step("full sort", 0)
    step = choose(frame.keys, wanted)
    if step.kind == "none":
        return frame, step
    if step.kind == "shorten" and set(frame.partitioned_by) <= {k.name for k in wanted}:
        return shorten(frame, len(wanted)), step
    if step.kind == "segmented sort" and set(frame.partitioned_by) <= {k.name for k in wanted[: step.shared]}:
        return extend_sort(frame, step.shared, wanted[step.shared :]), step
    return attach(frame.plain(), wanted, lead), Step("full sort", step.shared)


def grouping_covers(frame: OrderedFrame, groups: list[str]) -> bool:
    """Whether rows of a group stand together: the groups are the leading keys in some order."""
    return set(frame.names[: len(groups)]) == set(groups)
