"""Plain-Python references."""

from collections import defaultdict, deque


def adjacency(pairs):
    near = defaultdict(set)
    for a, b in pairs:
        if a != b:
            near[a].add(b)
            near[b].add(a)
    return {v: sorted(n) for v, n in near.items()}


def depths(near, source):
    seen, queue = {source: 0}, deque([source])
    while queue:
        v = queue.popleft()
        for w in near[v]:
            if w not in seen:
                seen[w] = seen[v] + 1
                queue.append(w)
    return seen


def parents(near, seen):
    return {v: min((w for w in near[v] if seen.get(w) == d - 1), default=None) for v, d in seen.items()}


def trace(near, seen):
    """(iter, nnz_f, nnz_u, out_edges_f, in_edges_u, parents_checked) level by level."""
    out = []
    for level in range(max(seen.values()) + 1):
        front = {v for v, d in seen.items() if d == level}
        rest = [v for v in near if seen.get(v, 10**9) > level]
        checked = sum(next((i for i, w in enumerate(near[v], 1) if w in front), len(near[v])) for v in rest)
        out.append((level + 1, len(front), len(rest), sum(len(near[v]) for v in front), sum(len(near[v]) for v in rest), checked))
    return out
