"""Plain-Python oracles for tests: sequential push-relabel and exhaustive cuts, for graphs of bounded size."""

from __future__ import annotations

from collections import defaultdict, deque


def sequential_push_relabel(arcs: list[tuple[int, int, int]], s: int, t: int, most: int = 100_000) -> int:
    """First-in first-out push-relabel; the flow value."""
    if len(arcs) > most:
        raise ValueError("too many arcs for the sequential oracle")
    room: dict[int, dict[int, int]] = defaultdict(lambda: defaultdict(int))
    for u, v, c in arcs:
        if u != v:
            room[u][v] += c
            room[v][u] += 0
    n = len(set(room) | {s, t})
    height, excess = defaultdict(int, {s: n}), defaultdict(int)
    queue: deque[int] = deque()
    for v in list(room[s]):
        d, room[s][v] = room[s][v], 0
        room[v][s] += d
        excess[v] += d
        if d and v != t:
            queue.append(v)
    while queue:
        u = queue.popleft()
        while excess[u]:
            open_to = [v for v, r in room[u].items() if r]
            if not open_to:
                break
            v = min(open_to, key=lambda x: (height[x], x))
            if height[u] <= height[v]:
                height[u] = height[v] + 1
                if height[u] > 2 * n:
                    break
                continue
            d = min(excess[u], room[u][v])
            room[u][v] -= d
            room[v][u] += d
            excess[u] -= d
            if v not in (s, t) and not excess[v]:
                queue.append(v)
            excess[v] += d
    return excess[t]


def smallest_cut(arcs: list[tuple[int, int, int]], s: int, t: int) -> int:
    """The least capacity over all cuts; at most 20 vertices."""
    inner = sorted({x for u, v, _ in arcs for x in (u, v)} - {s, t})
    best = None
    for bits in range(1 << len(inner)):
        side = {s} | {x for k, x in enumerate(inner) if bits >> k & 1}
        total = sum(c for u, v, c in arcs if u in side and v not in side)
        best = total if best is None else min(best, total)
    return best or 0
