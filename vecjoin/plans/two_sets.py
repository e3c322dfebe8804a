"""Order and cache of a join of two sets: one side is streamed in an order, the other side's buckets are cached.

Either side can be streamed. A bucket of the streamed side is loaded once, with all its partners after it; the
order puts buckets that share partners next to each other, so that the cached side is loaded less often.
"""

from __future__ import annotations

from .orchestrate import Edge, neighbours, order_nodes, plan_cache, segments


def _numbered(edges: list[Edge]) -> list[Edge]:
    return [(2 * i, 2 * j + 1) for i, j in edges]


def two_set_tasks(edges: list[Edge], slots: int, streamed: int = 0, order: str = "overlap") -> list[Edge]:
    """(left, right) pairs, grouped by the buckets of the ``streamed`` side (0 left, 1 right); partners that the next group needs as well come last."""
    numbered = _numbered(edges)
    if not numbered:
        return []
    near = neighbours(numbered)
    lead = [x for x in order_nodes(numbered, slots, order) if x % 2 == streamed]
    out: list[Edge] = []
    for x, following in zip(lead, [*lead[1:], None], strict=True):
        ahead = set(near.get(following, ()))
        for p in sorted(near[x], key=lambda p: (p in ahead, p)):
            out.append((x // 2, p // 2) if streamed == 0 else (p // 2, x // 2))
    return out


def two_set_loads(tasks: list[Edge], slots: int, policy: str = "opt") -> dict[str, float]:
    """Counts of a run through ``tasks`` with room for ``slots`` buckets of either side."""
    return plan_cache(_numbered(tasks), slots, policy)[1]


def two_set_segments(tasks: list[Edge], slots: int) -> list[int]:
    """Runs of tasks that touch at most ``slots`` buckets of both sides together."""
    return segments(_numbered(tasks), slots)
