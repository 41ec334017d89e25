"""Independent plain-Python samplers and metrics, used by tests only."""

import hashlib
import itertools
from collections import defaultdict


def unit(seed, stream, *ids):
    text = ":".join([str(seed), stream, *map(str, ids)])
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16) / 4294967296.0


def neighbor_sets(edges):
    n = defaultdict(set)
    for _, a, b in edges:
        if a != b:
            n[a].add(b)
            n[b].add(a)
    return n


def measure(ids, edges):
    n = neighbor_sets(edges)
    tri = {v: sum(1 for a, b in itertools.combinations(sorted(n[v]), 2) if b in n[a]) for v in ids}
    triples = sum(len(n[v]) * (len(n[v]) - 1) // 2 for v in ids)
    local = [tri[v] / (len(n[v]) * (len(n[v]) - 1) / 2) if len(n[v]) > 1 else 0.0 for v in ids]
    parent = {v: v for v in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    degree = dict.fromkeys(ids, 0)
    for _, a, b in edges:
        degree[a] += 1
        degree[b] += 1
        x, y = find(a), find(b)
        if x != y:
            parent[max(x, y)] = min(x, y)
    t = sum(tri.values()) // 3
    return {
        "vertices": len(ids),
        "edges": len(edges),
        "triangles": t,
        "global_clustering": 3 * t / triples if triples else 0.0,
        "local_clustering": sum(local) / len(local),
        "wcc": len({find(v) for v in ids}),
        "d_avg": sum(degree.values()) / len(ids),
        "d_min": min(degree.values()),
        "d_max": max(degree.values()),
    }


def walk(index, edges, target, seed, walkers, jump):
    """Shared-memory walk by supersteps: (trace rows, visited). ``index``: id -> dense number."""
    out = defaultdict(list)
    for e, a, b in edges:
        out[a].append((unit(seed, "edge", e), e, b))
    for a in out:
        out[a].sort()
    by_number = {k: v for v, k in index.items()}
    starts = sorted(index, key=lambda v: (unit(seed, "start", v), v))[:walkers]
    at, gone, visited, step = dict(enumerate(starts)), defaultdict(int), set(starts), 0
    trace = [(w, 0, v, "start") for w, v in at.items()]
    while len(visited) < target:
        step += 1
        taken, moves = defaultdict(int), {}
        for w in sorted(at):
            v = at[w]
            kind = "jump" if unit(seed, "jump", w, step) <= jump else None
            if kind is None:
                k = gone[v] + taken[v]
                taken[v] += 1
                if k < len(out[v]):
                    moves[w] = (out[v][k][2], "walk")
                    continue
                kind = "stuck"
            t = int(unit(seed, "to", w, step) * (len(index) - 1))
            moves[w] = (by_number[t + (t >= index[v])], kind)
        for v, k in taken.items():
            gone[v] += min(k, len(out[v]) - gone[v])
        for w, (v, kind) in moves.items():
            at[w] = v
            visited.add(v)
            trace.append((w, step, v, kind))
    return trace, visited
