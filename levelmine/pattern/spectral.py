"""Isomorphism keys from labels, degrees and the characteristic polynomial of a label-weighted adjacency matrix.

The polynomial stands for the spectrum; its coefficients are exact integers, so no eigenvalue is computed. The key is an
invariant: isomorphic graphs have equal keys. The converse fails for a few pairs from 7 labelled or 8 unlabelled
vertices on, so `verified` classification lets the exact form decide within a bucket of equal keys.
"""

from __future__ import annotations

import numpy as np

from levelmine.pattern.encode import check_size, matrix

Key = tuple[tuple[int, ...], tuple[int, ...], tuple[int, ...]]


def order(labels: tuple[int, ...], m: list[list[int]]) -> list[int]:
    """Positions by label, then degree inside the embedding."""
    return sorted(range(len(labels)), key=lambda i: (labels[i], sum(m[i])))


def weighted(labels: tuple[int, ...], m: list[list[int]], width: int) -> list[list[int]]:
    """An edge weighs the two labels side by side, the smaller first, each in `width` bits."""
    if min(labels, default=1) < 1:
        raise ValueError("labels start at 1: a zero would make an edge vanish")
    if max(labels, default=1) >> width:
        raise ValueError(f"labels do not fit {width} bits")
    k = len(labels)
    return [[(min(labels[i], labels[j]) << width | max(labels[i], labels[j])) * m[i][j] for j in range(k)] for i in range(k)]


def charpoly(m: list[list[int]]) -> tuple[int, ...]:
    """Coefficients of det(xI - M) below the leading 1, from the highest power down, by traces of running products."""
    k = len(m)
    out, running = [], [row[:] for row in m]
    for step in range(1, k + 1):
        c = -sum(running[i][i] for i in range(k)) // step
        out.append(c)
        if step < k:
            for i in range(k):
                running[i][i] += c
            running = [[sum(a * b for a, b in zip(row, col, strict=True)) for col in zip(*running, strict=True)] for row in m]
    return tuple(out)


def key(labels: tuple[int, ...], bits: int, width: int = 8, use_labels: bool = True, use_degrees: bool = True) -> Key:
    """(labels, degrees, polynomial), labels and degrees in the order of positions by label and degree."""
    k = len(labels)
    check_size(k, "spectral")
    m = matrix(k, bits)
    if not use_labels:
        labels = (1,) * k
    at = order(labels, m)
    poly = charpoly(weighted(labels, m, width) if use_labels else m)
    return tuple(labels[i] for i in at) if use_labels else (), tuple(sum(m[i]) for i in at) if use_degrees else (), poly


def key_text(k: Key) -> str:
    return "/".join(".".join(map(str, part)) for part in k)


def eigenvalues(labels: tuple[int, ...], bits: int, width: int = 8, use_labels: bool = True) -> list[float]:
    m = matrix(len(labels), bits)
    return sorted(np.linalg.eigvalsh(np.array(weighted(labels, m, width) if use_labels else m, float)).tolist())
