"""Exact canonical form of small labelled graphs: refine positions, then the least code over the orders that remain."""

from __future__ import annotations

import functools
from itertools import permutations, product

from levelmine.pattern.encode import bit, check_size, matrix


def refine(labels: tuple[int, ...], m: list[list[int]]) -> list[int]:
    """Stable colours of the positions: label and edges first, then the colours around. Invariant under renaming.

    m has the label of each edge, 0 where there is none.
    """
    k = len(labels)
    colour = [(labels[i], tuple(sorted(x for x in m[i] if x))) for i in range(k)]
    ranks = {c: r for r, c in enumerate(sorted(set(colour)))}
    now = [ranks[c] for c in colour]
    while True:
        seen = [(now[i], tuple(sorted((now[j], m[i][j]) for j in range(k) if m[i][j]))) for i in range(k)]
        ranks = {c: r for r, c in enumerate(sorted(set(seen)))}
        new = [ranks[c] for c in seen]
        if len(ranks) == len(set(now)):
            return new
        now = new


def _orders(colours: list[int]):
    """All orders of the positions that put the colours in rising order."""
    cells = {}
    for i, c in enumerate(colours):
        cells.setdefault(c, []).append(i)
    for parts in product(*(permutations(cells[c]) for c in sorted(cells))):
        yield [i for part in parts for i in part]


@functools.lru_cache(maxsize=100_000)
def canonical(labels: tuple[int, ...], bits: int, edge_labels: tuple[tuple[int, int], ...] = ()) -> tuple[str, tuple[int, ...], tuple[int, ...]]:
    """(code, place of each position in the canonical order, orbit of each position).

    edge_labels: (bit, label) of the edges whose label is not 1, or of all.

    The orbit is named by the least canonical place that an automorphism can bring the position to.
    """
    k = len(labels)
    check_size(k)
    m = matrix(k, bits)
    said = dict(edge_labels)
    for j in range(k):
        for i in range(j):
            if m[i][j]:
                m[i][j] = m[j][i] = said.get(bit(i, j), 1)
    best, found = None, []
    for order in _orders(refine(labels, m)):
        bits_, names = 0, []
        for j in range(1, k):
            row = m[order[j]]
            for i in range(j):
                if row[order[i]]:
                    bits_ |= 1 << bit(i, j)
                    names.append(row[order[i]])
        code = bits_, tuple(names)
        if best is None or code < best:
            best, found = code, [order]
        elif code == best:
            found.append(order)
    order = found[0]
    place = [0] * k
    for p, i in enumerate(order):
        place[i] = p
    reach = [{place[i]} for i in range(k)]
    for other in found:  # every best order is the first one after an automorphism
        for p, i in enumerate(other):
            reach[i].add(p)
    orbit = [min(r) for r in reach]
    code = f"{'.'.join(str(labels[i]) for i in order)}|{best[0] if best else 0:x}"
    if best and any(x != 1 for x in best[1]):
        code += f"|{'.'.join(map(str, best[1]))}"
    return code, tuple(place), tuple(orbit)


def isomorphic(a: tuple[tuple[int, ...], int], b: tuple[tuple[int, ...], int]) -> bool:
    return len(a[0]) == len(b[0]) and canonical(*a)[0] == canonical(*b)[0]
