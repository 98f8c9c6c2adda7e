"""The ten-vertex example and plain sequential references."""

from collections import deque

EDGES = [(1, 5), (5, 2), (2, 7), (7, 5), (7, 3), (3, 9), (9, 5), (4, 8), (5, 1), (6, 6)]
VERTICES = list(range(10))


def lists(edges):
    out = {}
    for a, b in edges:
        if a != b:
            out.setdefault(a, set()).add(b)
            out.setdefault(b, set()).add(a)
    return out


def far_end(edges, seed):
    """Eccentricity of a vertex, and the least (degree, id) among the vertices farthest from it."""
    adj, d = lists(edges), depths(edges, seed)
    ecc = max(d.values())
    return ecc, min((len(adj[v]), v) for v in d if d[v] == ecc)[1]


def peripheral(edges, seed):
    """The vertex from which walking to the far end stops raising the eccentricity."""
    ecc, end = far_end(edges, seed)
    while True:
        grown, next_end = far_end(edges, end)
        if grown <= ecc:
            return seed
        seed, ecc, end = end, grown, next_end


def visit(edges, start=lambda edges, seed: seed):
    """Sequential visit: components by least (degree, id), children by (degree, id)."""
    adj = lists(edges)
    deg = {v: len(n) for v, n in adj.items()}
    seen, order = set(), []
    for seed in sorted(adj, key=lambda v: (deg[v], v)):
        if seed in seen:
            continue
        seed = start(edges, seed)
        seen.add(seed)
        queue = deque([seed])
        while queue:
            v = queue.popleft()
            order.append(v)
            for w in sorted(adj[v], key=lambda x: (deg[x], x)):
                if w not in seen:
                    seen.add(w)
                    queue.append(w)
    return order


def depths(edges, source):
    adj = lists(edges)
    out, queue = {source: 0}, deque([source])
    while queue:
        v = queue.popleft()
        for w in adj.get(v, ()):
            if w not in out:
                out[w] = out[v] + 1
                queue.append(w)
    return out
