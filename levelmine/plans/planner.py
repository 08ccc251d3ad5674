"""Choices that Catalyst cannot make: how to grow a level, and where to keep it."""

from __future__ import annotations

from dataclasses import dataclass

from levelmine.graph.model import PropertyGraph

#: Above this degree a vertex's neighbours are not put into one row; positions are joined anew instead.
WIDEST_ROW = 50_000


@dataclass(frozen=True)
class Plan:
    carry: bool
    reason: str


def plan(graph: PropertyGraph, k: int, strategy: str | None = None) -> Plan:
    if strategy is not None:
        return Plan(strategy == "carry", "as asked")
    widest = graph.max_degree()
    if widest * max(1, k - 1) > WIDEST_ROW:
        return Plan(False, f"a vertex has {widest} neighbours")
    return Plan(True, f"at most {widest} neighbours")
