"""Names of small shapes, by canonical code of their unlabelled form."""

from __future__ import annotations

import functools

from levelmine.pattern.encode import bits_of
from levelmine.pattern.exact import canonical

#: Shapes of three, four and five vertices: fixed values. Path, star, cycle and clique of five are named by rule below.
SHAPES = {
    "chain": (3, [(0, 1), (1, 2)]),
    "triangle": (3, [(0, 1), (1, 2), (0, 2)]),
    "path": (4, [(0, 1), (1, 2), (2, 3)]),
    "star": (4, [(0, 1), (0, 2), (0, 3)]),
    "cycle": (4, [(0, 1), (1, 2), (2, 3), (0, 3)]),
    "tailed_triangle": (4, [(0, 1), (1, 2), (0, 2), (2, 3)]),
    "diamond": (4, [(0, 1), (1, 2), (2, 3), (0, 3), (0, 2)]),
    "clique": (4, [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3)]),
    "fork": (5, [(0, 1), (0, 2), (0, 3), (3, 4)]),
    "cricket": (5, [(0, 1), (0, 2), (1, 2), (0, 3), (0, 4)]),
    "bull": (5, [(0, 1), (0, 2), (1, 2), (0, 3), (1, 4)]),
    "lollipop_3_2": (5, [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4)]),
    "banner": (5, [(0, 1), (1, 2), (2, 3), (0, 3), (0, 4)]),
    "butterfly": (5, [(0, 1), (0, 2), (1, 2), (0, 3), (0, 4), (3, 4)]),
    "dart": (5, [(0, 1), (1, 2), (2, 3), (0, 3), (0, 2), (0, 4)]),
    "kite": (5, [(0, 1), (1, 2), (2, 3), (0, 3), (0, 2), (1, 4)]),
    "house": (5, [(0, 1), (1, 2), (2, 3), (0, 3), (0, 4), (1, 4)]),
    "bipartite_2_3": (5, [(0, 2), (0, 3), (0, 4), (1, 2), (1, 3), (1, 4)]),
    "book": (5, [(0, 1), (0, 2), (0, 3), (0, 4), (1, 2), (1, 3), (1, 4)]),
    "gem": (5, [(0, 1), (1, 2), (2, 3), (0, 4), (1, 4), (2, 4), (3, 4)]),
    "lollipop_4_1": (5, [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3), (0, 4)]),
    "wheel_less_a_spoke": (5, [(0, 1), (1, 2), (2, 3), (0, 3), (0, 4), (1, 4), (2, 4)]),
    "wheel": (5, [(0, 1), (1, 2), (2, 3), (0, 3), (0, 4), (1, 4), (2, 4), (3, 4)]),
    "clique_less_two_at_a_vertex": (5, [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3), (0, 4), (1, 4)]),
    "clique_less_an_edge": (5, [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3), (0, 4), (1, 4), (2, 4)]),
}


@functools.cache
def names() -> dict[str, str]:
    out = {canonical((1,) * k, bits_of(k, edges))[0]: name for name, (k, edges) in SHAPES.items()}
    for k in (1, 2):
        out[canonical((1,) * k, (1 << k * (k - 1) // 2) - 1)[0]] = "vertex" if k == 1 else "edge"
    for k in range(5, 9):
        out[canonical((1,) * k, bits_of(k, [(i, i + 1) for i in range(k - 1)]))[0]] = f"path_{k}"
        out[canonical((1,) * k, bits_of(k, [(0, i) for i in range(1, k)]))[0]] = f"star_{k}"
        out[canonical((1,) * k, bits_of(k, [(i, (i + 1) % k) for i in range(k)]))[0]] = f"cycle_{k}"
        out[canonical((1,) * k, (1 << k * (k - 1) // 2) - 1)[0]] = f"clique_{k}"
    return out


def name_of(code: str) -> str | None:
    """The shape's name, whatever the labels; None for shapes without one."""
    labels, _, _ = code.partition("|")
    if set(labels.split(".")) == {"1"}:
        return names().get(code)
    return None
