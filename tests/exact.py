"""Exact answers in plain Python, for tests only."""

import heapq
from collections import defaultdict, deque


def dijkstra(edges, sources):
    out = defaultdict(list)
    for u, v, w in edges:
        out[u].append((v, w))
    dist, heap = {}, [(0, s) for s in sources]
    while heap:
        d, u = heapq.heappop(heap)
        if u in dist:
            continue
        dist[u] = d
        for v, w in out[u]:
            if v not in dist:
                heapq.heappush(heap, (d + w, v))
    return dist


def components(edges, ids=()):
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for i in ids:
        find(i)
    for u, v, *_ in edges:
        a, b = sorted((find(u), find(v)))
        root[b] = a
    return {x: find(x) for x in list(root)}


def levels(edges, root):
    out = defaultdict(list)
    for u, v, *_ in edges:
        out[u].append(v)
    level, queue = {root: 0}, deque([root])
    while queue:
        u = queue.popleft()
        for v in out[u]:
            if v not in level:
                level[v] = level[u] + 1
                queue.append(v)
    return level


def pagerank_fixed(edges, rounds):
    ids = sorted({x for u, v, *_ in edges for x in (u, v)})
    deg = defaultdict(int)
    for u, *_ in edges:
        deg[u] += 1
    n = len(ids)
    rank = dict.fromkeys(ids, 10**12 // n)
    for _ in range(rounds):
        acc = dict.fromkeys(ids, 0)
        for u, v, *_ in edges:
            acc[v] += rank[u] // deg[u] * 85 // 100
        rank = {i: 150_000_000_000 // n + acc[i] for i in ids}
    return rank
