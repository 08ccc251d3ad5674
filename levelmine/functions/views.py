"""Graphs as temporary views for SQL."""

from __future__ import annotations

from levelmine.graph.model import PropertyGraph


def register(graph: PropertyGraph, prefix: str = "") -> None:
    """vertices, edges and neighbours (both directions), with a prefix if several graphs are used at once."""
    graph.vertices.createOrReplaceTempView(f"{prefix}vertices")
    graph.edges.createOrReplaceTempView(f"{prefix}edges")
    graph.sym.createOrReplaceTempView(f"{prefix}neighbours")
