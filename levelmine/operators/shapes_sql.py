"""DuckDB SQL of labelled patterns, generated from the shapes: all ways to lay a shape's vertices on the graph, its label
vectors up to the shape's symmetries, minimum image numbers and embeddings. Starts from e, s and v of the graphs' SQL."""

from __future__ import annotations

from itertools import permutations

from levelmine.pattern.names import SHAPES

#: Connected shapes by their number of edges.
BY_EDGES: dict[int, list[tuple[int, list[tuple[int, int]]]]] = {
    1: [(2, [(0, 1)])],
    2: [(3, [(0, 1), (1, 2)])],
    3: [(4, [(0, 1), (1, 2), (2, 3)]), (4, [(0, 1), (0, 2), (0, 3)]), (3, [(0, 1), (1, 2), (0, 2)])],
    4: [
        (5, [(0, 1), (1, 2), (2, 3), (3, 4)]),
        (5, [(0, 1), (0, 2), (0, 3), (0, 4)]),
        (5, [(0, 1), (0, 2), (0, 3), (3, 4)]),
        (4, [(0, 1), (1, 2), (2, 3), (0, 3)]),
        (4, [(0, 1), (1, 2), (0, 2), (2, 3)]),
    ],
}


def degrees(k: int, edges: list[tuple[int, int]]) -> list[int]:
    return [sum(i in e for e in edges) for i in range(k)]


def symmetries(k: int, edges: list[tuple[int, int]]) -> list[tuple[int, ...]]:
    """Permutations of the vertices that keep the edges."""
    own = {frozenset(e) for e in edges}
    return [p for p in permutations(range(k)) if {frozenset((p[i], p[j])) for i, j in edges} == own]


def _vector(order, name: str = "l") -> str:
    return f"[{', '.join(f'{name}{i}' for i in order)}]"


def laid(k: int, edges: list[tuple[int, int]], more: str = "") -> str:
    """x0.., l0..: every injective way to lay the shape on the graph, its label vector the least of its symmetric ones."""
    joins, where, known = ["s j0"], [], {}
    i, j = edges[0]
    known[i], known[j] = "j0.a", "j0.b"
    for n, (i, j) in enumerate(edges[1:], 1):
        if i not in known:
            i, j = j, i
        joins.append(f"JOIN s j{n} ON j{n}.a = {known[i]}" + (f" AND j{n}.b = {known[j]}" if j in known else ""))
        if j not in known:
            where += [f"{x} <> j{n}.b" for x in known.values()]
            known[j] = f"j{n}.b"
    joins += [f"JOIN v v{i} ON v{i}.id = {known[i]}" for i in range(k)]
    cols = ", ".join([f"{known[i]} AS x{i}" for i in range(k)] + [f"v{i}.label AS l{i}" for i in range(k)])
    inner = f"SELECT {cols} FROM {' '.join(joins)}" + (f" WHERE {' AND '.join(where)}" if where else "")
    least = " AND ".join(f"{_vector(range(k))} <= {_vector(p)}" for p in symmetries(k, edges) if p != tuple(range(k))) or "true"
    return f"SELECT * FROM ({inner}){more} WHERE {least}"


def said(k: int, edges: list[tuple[int, int]]) -> str:
    """A pattern's vertices as text: label and degree of each, sorted."""
    each = ", ".join(f"l{i} || ':' || {d}" for i, d in enumerate(degrees(k, edges)))
    return f"array_to_string(list_sort([{each}]), ' ')"


def supports(n_edges: int, at_least: str) -> str:
    """(n_edges, vertices, mni, embeddings) of the frequent patterns of exactly so many edges."""
    out = []
    for k, edges in BY_EDGES[n_edges]:
        mni = f"least({', '.join(f'count(DISTINCT x{i})' for i in range(k))})"
        same = " + ".join(f"CAST({_vector(range(k))} = {_vector(p)} AS INTEGER)" for p in symmetries(k, edges))
        labels = ", ".join(f"l{i}" for i in range(k))
        out.append(f"SELECT CAST({n_edges} AS INTEGER) AS n_edges, {said(k, edges)} AS vertices, {mni} AS mni, CAST(count(*) / ({same}) AS BIGINT) AS embeddings FROM ({laid(k, edges)}) GROUP BY {labels} HAVING {mni} >= {at_least}")
    return " UNION ALL ".join(out)


def frequent(most_edges: int, at_least: str) -> str:
    return " UNION ALL ".join(supports(n, at_least) for n in range(1, most_edges + 1))


def labelled_classes(k: int, sets: str, shape_of: str) -> str:
    """(vertices, classes, frequency) of vertex-induced subgraphs of k vertices. sets(w, shape_of): each vertex set and
    its sorted degrees as text."""
    out = []
    for n, edges in SHAPES.values():
        if n != k:
            continue
        ds = "".join(map(str, sorted(degrees(k, edges))))
        more = f" JOIN {sets} ON w = list_sort({_vector(range(k), 'x')}) AND {shape_of} = '{ds}'"
        same = " + ".join(f"CAST({_vector(range(k))} = {_vector(p)} AS INTEGER)" for p in symmetries(k, edges))
        labels = ", ".join(f"l{i}" for i in range(k))
        out.append(f"SELECT {said(k, edges)} AS vertices, count(*) / ({same}) AS n FROM ({laid(k, edges, more)}) GROUP BY {labels}")
    return f"SELECT vertices, count(*) AS classes, CAST(sum(n) AS BIGINT) AS frequency FROM ({' UNION ALL '.join(out)}) GROUP BY 1"
