"""Exact support, frequency and maximality of patterns, many in one scan."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..config import Config
from ..functions import canon
from ..functions.iso import contains
from ..model import Graph
from .graph_stats import frequent_paths
from .scan import support

#: frequent length-1 paths that the driver takes; there are at most (vertices of the largest graph)^2 / minsup
MOST_PATHS = 100_000


def exact(graphs: DataFrame, patterns: list[Graph], cfg: Config | None = None) -> list[tuple[int, int]]:
    """``(supporters, graphs)`` of each pattern. The pair stays exact and adds up over parts of a set."""
    return support(graphs, patterns, cfg)


def is_frequent(graphs: DataFrame, patterns: list[Graph], minsup: float) -> list[bool]:
    return [bool(n) and k >= minsup * n - 1e-9 for k, n in exact(graphs, patterns)]


def extensions(pattern: Graph, paths: set[tuple]) -> list[Graph]:
    """Every pattern with one edge more whose edge is one of ``paths`` (la, le, lb), without isomorphic ones."""
    found: dict[bytes, Graph] = {}

    def keep(g: Graph) -> None:
        found.setdefault(canon.code(g), g)

    for v, label in enumerate(pattern.labels):
        for la, le, lb in paths:
            for mine, other in {(la, lb), (lb, la)}:
                if mine != label:
                    continue
                g = pattern.copy()
                g.link(v, g.add(other), le)
                keep(g)
        for u in range(v):
            if u not in pattern.adj[v]:
                for le in {e for la, e, lb in paths if {la, lb} == {label, pattern.labels[u]}}:
                    g = pattern.copy()
                    g.link(u, v, le)
                    keep(g)
    return list(found.values())


def is_maximal(graphs: DataFrame, pattern: Graph, minsup: float) -> bool:
    """Whether no extension by one edge is frequent: by monotonicity, then no larger pattern is. One scan for all extensions."""
    rows = frequent_paths(graphs, minsup).limit(MOST_PATHS + 1).collect()
    if len(rows) > MOST_PATHS:
        raise ValueError(f"more than {MOST_PATHS} frequent paths")
    paths = {(r.la, r.le, r.lb) for r in rows}
    bigger = extensions(pattern, paths)
    return not bigger or not any(is_frequent(graphs, bigger, minsup))


def prune_by_subset(infrequent: list[Graph], patterns: list[Graph]) -> list[Graph]:
    """Patterns that contain none of the infrequent ones; the others cannot be frequent."""
    return [p for p in patterns if not any(contains(p, q) for q in infrequent)]


def mining_error(graphs: DataFrame, candidates: list[Graph], minsup: float) -> float:
    """Share of candidates that are not frequent or not maximal; the sampled mode allows ``max_error`` for each."""
    if not candidates:
        return 0.0
    frequent = is_frequent(graphs, candidates, minsup)
    return sum(not (f and is_maximal(graphs, c, minsup)) for c, f in zip(candidates, frequent, strict=True)) / len(candidates)
