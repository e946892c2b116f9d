"""Label-preserving subgraph isomorphism (injective, not induced) on small graphs."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from functools import cached_property

from ..model import Graph


class StepsExceeded(RuntimeError):
    """A containment test took more steps than it was given."""


class Pattern:
    """A pattern with its matching order: rarest label first, then always beside what is matched."""

    def __init__(self, graph: Graph, rarity: Counter | None = None):
        self.graph, self.size = graph, graph.size
        self.label_counts = Counter(graph.labels)
        self.triples = triple_counts(graph)
        n = len(graph.labels)
        left, order = set(range(n)), []
        rare = lambda v: ((rarity or self.label_counts)[graph.labels[v]], -len(graph.adj[v]), v)
        while left:
            near = {w for v in order for w in graph.adj[v]} & left
            nxt = min(near, key=lambda v: (-sum(u not in left for u in graph.adj[v]), rare(v))) if near else min(left, key=rare)
            order.append(nxt)
            left.discard(nxt)
        place = {v: i for i, v in enumerate(order)}
        self.order = order
        self.plan = [
            (graph.labels[v], len(graph.adj[v]), sorted((place[w], label) for w, label in graph.adj[v].items() if place[w] < i)) for i, v in enumerate(order)
        ]


def triple_counts(g: Graph) -> Counter:
    key = lambda u, w, label: (min(g.labels[u], g.labels[w]), label, max(g.labels[u], g.labels[w]))
    return Counter(key(u, w, label) for u, w, label in g.edges())


class Host:
    """A graph with what containment tests look up."""

    def __init__(self, graph: Graph):
        self.graph = graph
        self.by_label: dict = {}
        for v, label in enumerate(graph.labels):
            self.by_label.setdefault(label, []).append(v)

    @cached_property
    def triples(self) -> Counter:
        return triple_counts(self.graph)

    def may_contain(self, p: Pattern) -> bool:
        by = self.by_label
        if not all(len(by.get(x, ())) >= n for x, n in p.label_counts.items()):
            return False
        return not p.triples or all(self.triples.get(k, 0) >= n for k, n in p.triples.items())


def embeddings(host: Host, p: Pattern, steps: int | None = None) -> Iterator[tuple[int, ...]]:
    """Every embedding, as host vertices in the order of the pattern's vertices."""
    if not p.plan:
        yield ()
        return
    adj, plan, n = host.graph.adj, p.plan, len(p.plan)
    labels = host.graph.labels
    used, image = set(), [0] * n
    taken = 0

    def choices(i):
        label, degree, back = plan[i]
        if not back:
            return iter([v for v in host.by_label.get(label, ()) if len(adj[v]) >= degree])
        j, edge = back[0]
        return iter([v for v, x in adj[image[j]].items() if x == edge and labels[v] == label and len(adj[v]) >= degree])

    stack = [choices(0)]
    back_to = [0] * n
    for i, v in enumerate(p.order):
        back_to[v] = i
    while stack:
        i = len(stack) - 1
        for v in stack[-1]:
            taken += 1
            if steps is not None and taken > steps:
                raise StepsExceeded
            if v in used or any(adj[v].get(image[j]) != edge for j, edge in plan[i][2][1:]):
                continue
            image[i] = v
            if i + 1 == n:
                yield tuple(image[back_to[x]] for x in range(n))
                continue
            used.add(v)
            stack.append(choices(i + 1))
            break
        else:
            stack.pop()
            if stack:
                used.discard(image[len(stack) - 1])


def find_embedding(host: Host, p: Pattern, steps: int | None = None) -> tuple[int, ...] | None:
    if not host.may_contain(p):
        return None
    return next(embeddings(host, p, steps), None)


def contains(host: Graph | Host, pattern: Graph | Pattern, steps: int | None = None) -> bool:
    host = host if isinstance(host, Host) else Host(host)
    pattern = pattern if isinstance(pattern, Pattern) else Pattern(pattern)
    return find_embedding(host, pattern, steps) is not None


def count_embeddings(host: Graph, pattern: Graph) -> int:
    h, p = Host(host), Pattern(pattern)
    return sum(1 for _ in embeddings(h, p)) if h.may_contain(p) else 0


def isomorphic(a: Graph, b: Graph) -> bool:
    return len(a.labels) == len(b.labels) and a.n_edges == b.n_edges and contains(a, b)


def is_common(s: Graph, g: Graph, h: Graph) -> bool:
    return contains(g, s) and contains(h, s)
