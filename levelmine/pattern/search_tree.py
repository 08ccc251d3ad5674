"""The labelling-library baseline: canonical form by a search tree of individualisation and refinement."""

from __future__ import annotations

from levelmine.pattern.encode import bit, check_size, matrix


def _refined(cells: list[list[int]], m: list[list[int]]) -> list[list[int]]:
    """The coarsest equitable partition below `cells`, in an order that renaming does not change."""
    queue = list(cells)
    while queue:
        pivot = queue.pop(0)
        out = []
        for cell in cells:
            parts: dict[int, list[int]] = {}
            for v in cell:
                parts.setdefault(sum(m[v][u] for u in pivot), []).append(v)
            pieces = [parts[n] for n in sorted(parts)]
            out += pieces
            if len(pieces) > 1:
                queue += pieces
        cells = out
    return cells


def canonical(labels: tuple[int, ...], bits: int) -> str:
    """Code of the least leaf of the search tree."""
    k = len(labels)
    check_size(k, "search tree")
    m = matrix(k, bits)
    start = [[i for i in range(k) if labels[i] == lab] for lab in sorted(set(labels))]
    best: list[int | None] = [None]

    def walk(cells: list[list[int]]) -> None:
        cells = _refined(cells, m)
        target = next((n for n, c in enumerate(cells) if len(c) > 1), None)
        if target is None:
            at = [c[0] for c in cells]
            code = 0
            for j in range(k):
                for i in range(j):
                    if m[at[i]][at[j]]:
                        code |= 1 << bit(i, j)
            best[0] = code if best[0] is None else min(best[0], code)
            return
        for v in cells[target]:
            walk([*cells[:target], [v], [u for u in cells[target] if u != v], *cells[target + 1 :]])

    walk(start)
    return f"{'.'.join(map(str, sorted(labels)))}|{best[0]:x}"
