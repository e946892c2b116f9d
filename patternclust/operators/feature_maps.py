"""Feature maps that need the whole graph in memory: shortest paths, walks, graphlets, spectra, distances."""

from __future__ import annotations

import hashlib
from collections import Counter, deque

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from ..functions import mcs
from ..model import Graph


def wl_labels(g: Graph, rounds: int) -> list[str]:
    labels = [str(x) for x in g.labels]
    for _ in range(rounds):
        labels = [hashlib.md5((labels[v] + "|" + ",".join(sorted(f"{x}:{labels[w]}" for w, x in g.adj[v].items()))).encode()).hexdigest() for v in range(len(labels))]
    return labels


def wl_shortest_paths(g: Graph, rounds: int = 1) -> Counter:
    """Labels at both ends with their distance, for all pairs that a path joins."""
    labels, out = wl_labels(g, rounds), Counter()
    for s in range(len(labels)):
        dist, queue = {s: 0}, deque([s])
        while queue:
            v = queue.popleft()
            for w in g.adj[v]:
                if w not in dist:
                    dist[w] = dist[v] + 1
                    queue.append(w)
        for t, d in dist.items():
            if t > s:
                out["/".join((*sorted((labels[s], labels[t])), str(d)))] += 1
    return out


def walks(g: Graph, length: int = 2) -> Counter:
    """Label sequences of all walks with a fixed number of edges."""
    now: Counter = Counter({(v, (str(x),)): 1 for v, x in enumerate(g.labels)})
    for _ in range(length):
        nxt: Counter = Counter()
        for (v, seq), n in now.items():
            for w, x in g.adj[v].items():
                nxt[(w, (*seq, str(x), str(g.labels[w])))] += n
        now = nxt
    return Counter({"/".join(k): n for k, n in _by_word(now).items()})


def _by_word(now: Counter) -> Counter:
    out: Counter = Counter()
    for (_, seq), n in now.items():
        out[seq] += n
    return out


def graphlets(g: Graph) -> Counter:
    """Connected induced subgraphs on three and four vertices by shape, labels aside."""
    out: Counter = Counter()
    n, near = len(g.labels), [set(x) for x in g.adj]

    def grow(chosen: frozenset, least: int, border: set):
        if len(chosen) in (3, 4):
            degrees = tuple(sorted(len(near[v] & chosen) for v in chosen))
            out[f"{len(chosen)}:{''.join(map(str, degrees))}"] += 1
        if len(chosen) == 4:
            return
        border = set(border)
        while border:
            v = border.pop()
            grow(chosen | {v}, least, border | {w for w in near[v] if w > least and w not in chosen and not near[w] & chosen})

    for s in range(n):
        grow(frozenset({s}), s, {w for w in near[s] if w > s})
    return out


def spectrum(g: Graph) -> list[float]:
    """Eigenvalues of the Laplacian, ascending."""
    a = np.zeros((len(g.labels),) * 2)
    for u, w, _ in g.edges():
        a[u, w] = a[w, u] = 1
    return [round(float(x), 9) + 0.0 for x in np.linalg.eigvalsh(np.diag(a.sum(axis=1)) - a)] if len(g.labels) else []


def mcs_distance(a: Graph, b: Graph, connected: bool = False) -> float:
    return 1 - mcs.similarity(a, b, connected)


def edit_distance_small(a: Graph, b: Graph) -> int:
    """Least number of insertions, deletions and relabelings of vertices and edges; exhaustive, for a few vertices."""
    if len(a.labels) > len(b.labels):
        a, b = b, a
    n, m = len(a.labels), len(b.labels)
    best = [n + m + a.n_edges + b.n_edges]
    ea, eb = {(u, w): x for u, w, x in a.edges()}, {(u, w): x for u, w, x in b.edges()}

    def cost(image):
        total = sum(1 if w is None else a.labels[v] != b.labels[w] for v, w in enumerate(image)) + m - sum(w is not None for w in image)
        met = 0
        for (u, v), x in ea.items():
            p, q = image[u], image[v]
            y = eb.get((min(p, q), max(p, q))) if p is not None and q is not None else None
            total += 1 if y is None else x != y
            met += y is not None
        return total + len(eb) - met

    def walk(image, used):
        if len(image) == n:
            best[0] = min(best[0], cost(image))
            return
        for w in [*(w for w in range(m) if w not in used), None]:
            walk([*image, w], used | {w})

    walk([], frozenset())
    return best[0]


def subgraph_indicator(g: Graph) -> set[bytes]:
    """Codes of all connected subgraphs, for tiny graphs."""
    from ..functions import canon

    found, edges = {canon.code(Graph([x])) for x in g.labels}, g.edges()
    for mask in range(1, 1 << len(edges)):
        own = [e for i, e in enumerate(edges) if mask >> i & 1]
        vertices = sorted({v for e in own for v in e[:2]})
        place = {v: i for i, v in enumerate(vertices)}
        s = Graph.of([g.labels[v] for v in vertices], *zip(*[(place[u], place[w], x) for u, w, x in own]))
        reach, todo = {0}, [0]
        while todo:
            for w in s.adj[todo.pop()]:
                if w not in reach:
                    reach.add(w)
                    todo.append(w)
        if len(reach) == len(vertices):
            found.add(canon.code(s))
    return found


def per_graph(graphs: DataFrame, extract) -> DataFrame:
    """``(graph_id, feature, cnt)`` by a function from a graph to counts, row by row."""

    def kernel(batches):
        for pdf in batches:
            rows = [(k, f, n) for k, *cols in zip(pdf["graph_id"], pdf["vl"], pdf["eu"], pdf["ew"], pdf["el"]) for f, n in extract(Graph.of(*cols)).items()]
            yield pd.DataFrame(rows, columns=["graph_id", "feature", "cnt"])

    return graphs.select("graph_id", "vl", "eu", "ew", "el").mapInPandas(kernel, "graph_id bigint, feature string, cnt bigint")
