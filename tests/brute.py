"""Plain Python versions of the methods, by their definitions."""

import random


def forward(nodes, edges):
    """node -> smallest node that is bisimilar to it; also ranks."""
    below = {i: set() for i, _ in nodes}
    for p, c in edges:
        below[p].add(c)
    rank, seen = {}, {}

    def rank_of(x):
        if x not in rank:
            rank[x] = 1 + max((rank_of(c) for c in below[x]), default=-1)
        return rank[x]

    for i, _ in nodes:
        rank_of(i)
    label, block = dict(nodes), {}
    for i in sorted(label, key=lambda i: (rank[i], i)):
        key = (rank[i], label[i], frozenset(block[c] for c in below[i]))
        block[i] = seen.setdefault(key, i)
    return block, rank


def k_partition(nodes, edges, k):
    near = {i: set() for i, _ in nodes}
    for a, b in edges:
        near[a].add(b)
    now = dict(nodes)
    for _ in range(k):
        now = {i: (now[i], frozenset(now[x] for x in near[i])) for i in now}
    first = {}
    for i in sorted(now):
        first.setdefault(now[i], i)
    return {i: first[now[i]] for i in now}


def random_graph(seed, n=60, labels=3, degree=3):
    r = random.Random(seed)
    nodes = [(i, r.choice("abc"[:labels])) for i in range(n)]
    edges = {(i, r.randrange(i)) for i in range(1, n) for _ in range(r.randrange(degree + 1))}
    return nodes, sorted(edges)
