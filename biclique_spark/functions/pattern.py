"""The broom: a fixed spanning tree of a (p,q)-biclique whose p + q - 1 edges form a staircase."""

from __future__ import annotations

from itertools import groupby


def broom_edges(p: int, q: int) -> list[tuple[int, int]]:
    """Index pairs (i, j), from 1, in increasing order. Left i hangs on a right vertex at the same share of the way,
    rounded down; right j > 1 hangs on a left vertex at its share, rounded up."""
    if p < 2 or q < 2:
        raise ValueError("p and q must be at least 2")
    down = {(i, (i - 1) * (q - 1) // (p - 1) + 1) for i in range(1, p + 1)}
    up = {(-(-(j - 1) * (p - 1) // (q - 1)), j) for j in range(2, q + 1)}
    return sorted(down | up)


def broom_steps(p: int, q: int) -> str:
    """A letter for each pair of neighbouring edges: the side on which they share their endpoint, U or V."""
    edges = broom_edges(p, q)
    return "".join("U" if a[0] == b[0] else "V" for a, b in zip(edges, edges[1:], strict=False))


def broom_runs(p: int, q: int) -> list[tuple[str, int]]:
    """Runs of equal letters: each needs its edges grouped by one side only once."""
    return [(side, len(list(run))) for side, run in groupby(broom_steps(p, q))]
