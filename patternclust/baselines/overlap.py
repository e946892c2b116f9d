"""Overlapping clusters that share a connected common substructure, within fingerprint partitions.

Graphs are parted by a coarse fingerprint; in each partition every cluster starts with a graph and takes those that share
with its core a connected substructure of the least size, the core shrinking to what is common. A graph may join several.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.iso import Host, Pattern, embeddings
from ..model import Graph


def common_core(core: Graph, g: Graph, least: int, steps: int = 400, host: Host | None = None, p: Pattern | None = None) -> Graph | None:
    """A large connected part of ``core`` that ``g`` contains, of at least ``least`` vertices; greedy from several starts.

    ``host`` and ``p`` are the two graphs unpacked, where they are at hand. Without enough labels in common no start is tried.
    """
    host = host or Host(g)
    shared = sum(min(n, len(host.by_label.get(x, ()))) for x, n in Counter(core.labels).items())
    if shared < min(least, len(core.labels)):
        return None
    p = p or Pattern(core)
    if host.may_contain(p) and next(embeddings(host, p, None), None) is not None:
        return core
    room = reach(core, host)
    if max(room, default=0) < least:
        return None
    best: dict[int, int] = {}
    tried = 0
    for v in range(len(core.labels)):
        for w in host.by_label.get(core.labels[v], ()):
            tried += 1
            if room[v] <= len(best):  # what it reaches cannot be more
                if tried >= steps:
                    break
                continue
            image, used, border = {v: w}, {w}, [v]
            while border:
                u = border.pop()
                for t, x in core.adj[u].items():
                    if t in image:
                        continue
                    options = [z for z, y in g.adj[image[u]].items() if y == x and z not in used and g.labels[z] == core.labels[t]]
                    if options:
                        z = max(options, key=lambda z: sum(1 for q, y in core.adj[t].items() if q in image and g.adj[z].get(image[q]) == y))
                        image[t] = z
                        used.add(z)
                        border.append(t)
            if len(image) > len(best):
                best = image
            if tried >= steps or len(best) == len(core.labels):
                break
        if tried >= steps:
            break
    if len(best) < least:
        return None
    place = {v: i for i, v in enumerate(sorted(best))}
    out = Graph([core.labels[v] for v in sorted(best)])
    for u, w, x in core.edges():
        if u in best and w in best and g.adj[best[u]].get(best[w]) == x:
            out.link(place[u], place[w], x)
    return out


def reach(core: Graph, host: Host) -> list[int]:
    """For each vertex of the core how many are joined to it, itself too, by edges that the host has somewhere, by labels."""
    labels, triples = core.labels, host.triples
    room, left = [0] * len(labels), set(range(len(labels)))
    while left:
        own, border = [], [left.pop()]
        while border:
            u = border.pop()
            own.append(u)
            for t, x in core.adj[u].items():
                if t in left and ((labels[u], x, labels[t]) if labels[u] <= labels[t] else (labels[t], x, labels[u])) in triples:
                    left.discard(t)
                    border.append(t)
        for u in own:
            room[u] = len(own)
    return room


def join(cores: list[tuple[Graph, Pattern]], g: Graph, least: int, host: Host | None = None, among: Iterable[int] | None = None) -> list[int]:
    """Numbers of the clusters (of ``among``, if given) that ``g`` joins, whose cores shrink; of a new one, if none."""
    host, own = host or Host(g), []
    for i in range(len(cores)) if among is None else among:
        held, p = cores[i]
        core = common_core(held, g, least, host=host, p=p)
        if core is not None:
            if core is not held:
                cores[i] = (core, Pattern(core))
            own.append(i)
    if not own:
        cores.append((g, Pattern(g)))
        own.append(len(cores) - 1)
    return own


class Cores:
    """Clusters in the order they began, with a table of what their cores hold, so that a graph is compared with those only that can share enough.

    An item is a label or a length-1 path with the number of its turn: as many as two graphs share, so many labels or edges they may match.
    """

    def __init__(self, least: int):
        self.least = least
        self.held: list[tuple[Graph, Pattern]] = []
        self.items: dict[tuple, int] = {}
        self.has = np.zeros((64, 64), bool)  # items by clusters
        self.n_labels, self.n_edges = np.zeros(64, np.int64), np.zeros(64, np.int64)

    def _items(self, counts: Counter, fresh: bool) -> list[int]:
        keys = [(x, j) for x, n in counts.items() for j in range(n)]
        if fresh:
            for k in keys:
                self.items.setdefault(k, len(self.items))
        return [self.items[k] for k in keys if k in self.items]

    def note(self, i: int) -> None:
        core, p = self.held[i]
        own = self._items(p.label_counts, True) + self._items(p.triples, True)
        if len(self.items) > self.has.shape[0] or i >= self.has.shape[1]:
            wide = np.zeros((max(self.has.shape[0], 2 * len(self.items)), max(self.has.shape[1], 2 * i)), bool)
            wide[: self.has.shape[0], : self.has.shape[1]] = self.has
            more = wide.shape[1] - len(self.n_labels)
            self.has, self.n_labels, self.n_edges = wide, np.pad(self.n_labels, (0, more)), np.pad(self.n_edges, (0, more))
        self.has[:, i] = False
        self.has[own, i] = True
        self.n_labels[i], self.n_edges[i] = len(core.labels), core.n_edges

    def near(self, host: Host) -> list[int]:
        """Numbers of the clusters whose cores can share a part of the least size with the host, or lie in it."""
        n = len(self.held)
        shared = lambda counts: self.has[self._items(counts, False), :n].sum(0)
        labels, edges = shared(Counter({x: len(v) for x, v in host.by_label.items()})), shared(host.triples)
        enough = (labels >= self.least) & (edges >= self.least - 1)  # a connected part has an edge less than vertices, at least
        return np.flatnonzero(enough | ((labels == self.n_labels[:n]) & (edges == self.n_edges[:n]))).tolist()

    def join(self, g: Graph) -> list[int]:
        """As ``join``, with those clusters only that ``g`` can join."""
        host = Host(g)
        near = self.near(host)
        before = {i: self.held[i][0] for i in near}
        own = join(self.held, g, self.least, host, near)
        for i in own:
            if before.get(i) is not self.held[i][0]:
                self.note(i)
        return own


def fit(graphs: DataFrame, min_common: int, granularity: float = 0.2, buckets: int = 64) -> DataFrame:
    """``(graph_id, cluster)`` memberships, several a graph. ``granularity``: tenths of it are the most frequent length-1 paths that
    part graphs, 0 for none.

    Only this fingerprint parts graphs. A partition passes in the order of ids and only its cores are held;
    the work in it grows with its graphs times its clusters.
    """
    end = lambda i: F.element_at("vl", i + 1)
    paths = F.transform(F.arrays_zip("eu", "ew", "el"), lambda e: F.struct(F.least(end(e["eu"]), end(e["ew"])).alias("a"), e["el"].alias("x"), F.greatest(end(e["eu"]), end(e["ew"])).alias("b")))
    graphs = graphs.withColumn("paths", paths)
    counted = F.array_sort(F.transform(F.array_distinct("paths"), lambda t: F.struct((-F.size(F.filter("paths", lambda u: u == t))).alias("n"), t.alias("t"))))
    most = max(0, round(granularity * 10))
    key = F.pmod(F.xxhash64(F.array_sort(F.transform(F.slice(counted, 1, most), lambda x: x["t"]))), F.lit(buckets)) if most else F.lit(0)
    keyed = graphs.select("graph_id", "vl", "eu", "ew", "el", key.cast("bigint").alias("bucket"))

    def grown(batches):
        name, cores = None, Cores(min_common)
        for batch in batches:
            rows = []
            for bucket, key, vl, eu, ew, el in zip(*(batch.column(c).to_pylist() for c in ("bucket", "graph_id", "vl", "eu", "ew", "el")), strict=True):
                if bucket != name:
                    name, cores = bucket, Cores(min_common)
                rows += [(key, f"{name}-{i}") for i in cores.join(Graph.of(vl, eu, ew, el))]
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in rows], pa.int64()), pa.array([c for _, c in rows], pa.string())], ["graph_id", "cluster"])

    # a task for each partition: rows are light and the work on them is not, so no two may be put together by their bytes
    return keyed.repartitionById(buckets if most else 1, F.col("bucket").cast("int")).sortWithinPartitions("bucket", "graph_id").mapInArrow(grown, "graph_id bigint, cluster string")
