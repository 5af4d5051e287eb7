"""Plain-Python references."""

from itertools import combinations


def adjacency(pairs):
    near = {}
    for a, b in pairs:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    return near


def bfs(near, s, without=frozenset()):
    dist, queue = {s: 0}, [s]
    for v in queue:
        for w in near[v]:
            if w not in dist and w not in without:
                dist[w] = dist[v] + 1
                queue.append(w)
    return dist


def gateway_labels(near, marks):
    """Entries by definition: every shortest path avoids the other landmarks."""
    full = {r: bfs(near, r) for r in marks}
    out = set()
    for r in marks:
        for v, d in full[r].items():
            if v not in marks and not any(q != r and q in full[r] and full[r][q] + full[q].get(v, 10**9) == d for q in marks):
                out.add((v, r, d))
    return out


def some_path_labels(near, marks):
    """The wrong reading: some shortest path avoids the other landmarks."""
    out = set()
    for r in marks:
        full, free = bfs(near, r), bfs(near, r, frozenset(marks) - {r})
        out |= {(v, r, d) for v, d in free.items() if v not in marks and full[v] == d}
    return out


def all_pairs(near):
    return {(s, t): d for s in near for t, d in bfs(near, s).items()}


GRAPHS = {
    "single_edge": [(1, 2)],
    "path10": [(i, i + 1) for i in range(9)],
    "star": [(0, i) for i in range(1, 8)],
    "clique": list(combinations(range(6), 2)),
    "two_triangles": [(0, 1), (1, 2), (0, 2), (10, 11), (11, 12), (10, 12)],
    "square": [(0, 1), (1, 2), (2, 3), (3, 0)],
    "cycle9": [(i, (i + 1) % 9) for i in range(9)],
    "grid5": [(5 * r + c, 5 * r + c + 1) for r in range(5) for c in range(4)] + [(5 * r + c, 5 * r + c + 5) for r in range(4) for c in range(5)],
    "two_ways": [(0, 1), (0, 2), (1, 3), (2, 3), (3, 4)],
}
