"""Kernels on single graphs against brute force and worked examples."""

import itertools
import json
import math
import random
from collections import Counter
from dataclasses import replace
from fractions import Fraction

import pytest

from patternclust.config import Config
from patternclust.functions import binomial, canon, fingerprint, iso, mcs
from patternclust.model import Graph
from patternclust.operators import feature_maps, mining, separation
from patternclust.plans import clustering


def random_graph(rng, n, p=0.4, labels="ab", edge_labels="xy"):
    g = Graph([rng.choice(labels) for _ in range(n)])
    for u, w in itertools.combinations(range(n), 2):
        if rng.random() < p:
            g.link(u, w, rng.choice(edge_labels))
    return g


def brute_embeddings(host, pattern):
    n = len(pattern.labels)
    return {
        m for m in itertools.permutations(range(len(host.labels)), n)
        if all(host.labels[m[v]] == pattern.labels[v] for v in range(n)) and all(host.adj[m[u]].get(m[w]) == x for u, w, x in pattern.edges())
    }


PATH = Graph.of("abc", [0, 1], [1, 2], "xx")
TRIANGLE = Graph.of("abc", [0, 1, 0], [1, 2, 2], "xxx")


def test_containment():
    assert iso.contains(TRIANGLE, PATH) and not iso.contains(PATH, TRIANGLE)
    assert not iso.contains(Graph.of("ab", [0], [1], "y"), Graph.of("ab", [0], [1], "x"))
    assert iso.contains(Graph(["a"]), Graph(["a"])) and not iso.contains(Graph(["a"]), Graph(["b"]))
    rng = random.Random(0)
    for _ in range(300):
        host, pattern = random_graph(rng, rng.randint(1, 6)), random_graph(rng, rng.randint(1, 4))
        want = brute_embeddings(host, pattern)
        assert set(iso.embeddings(iso.Host(host), iso.Pattern(pattern))) == want
        assert iso.count_embeddings(host, pattern) == len(want)
        assert iso.contains(host, pattern) == bool(want)


def test_step_budget():
    ring = Graph.of("a" * 12, range(12), [*range(1, 12), 0], "x" * 12)
    with pytest.raises(iso.StepsExceeded):
        list(iso.embeddings(iso.Host(ring), iso.Pattern(ring), steps=5))


def shuffled(rng, g):
    order = list(range(len(g.labels)))
    rng.shuffle(order)
    place = {v: i for i, v in enumerate(order)}
    out = Graph([g.labels[v] for v in order])
    for u, w, x in g.edges():
        out.link(place[u], place[w], x)
    return out


def test_canonical_codes():
    rng = random.Random(1)
    graphs = [random_graph(rng, rng.randint(1, 5)) for _ in range(60)] + [Graph.of("aaaaaa", range(6), [1, 2, 3, 4, 5, 0], "xxxxxx"), Graph.of("aaaaaa", [0, 1, 0, 3, 4, 3], [1, 2, 2, 4, 5, 5], "xxxxxx")]
    for g in graphs:
        assert canon.code(g) == canon.code(shuffled(rng, g))
    for g, h in itertools.combinations(graphs, 2):
        assert (canon.code(g) == canon.code(h)) == iso.isomorphic(g, h)


def brute_mcs(a, b, connected):
    best = 0
    for k in range(1, len(a.labels) + 1):
        for own in itertools.combinations(range(len(a.labels)), k):
            for m in itertools.permutations(range(len(b.labels)), k):
                if any(a.labels[v] != b.labels[w] for v, w in zip(own, m)):
                    continue
                to = dict(zip(own, m))
                shared = [(u, w) for u, w, x in a.edges() if u in to and w in to and b.adj[to[u]].get(to[w]) == x]
                if connected:
                    reach, todo = {own[0]}, [own[0]]
                    while todo:
                        v = todo.pop()
                        for u, w in shared:
                            for p, q in ((u, w), (w, u)):
                                if p == v and q not in reach:
                                    reach.add(q)
                                    todo.append(q)
                    if len(reach) < k:
                        continue
                best = max(best, k + len(shared))
    return best


def test_mcs():
    assert mcs.size(PATH, TRIANGLE) == 5 and mcs.similarity(Graph.of("ab", [0], [1], "x"), PATH) == 0.6
    rng = random.Random(2)
    for _ in range(120):
        a, b = random_graph(rng, rng.randint(1, 4), labels="abc"), random_graph(rng, rng.randint(1, 5), labels="abc")
        for connected in (True, False):
            want = brute_mcs(a, b, connected)
            assert mcs.size(a, b, connected) == want
            assert mcs.upper_bound(a, b) >= want
            for t in range(1, 8):
                assert mcs.at_least(a, b, t, connected, 10**6) == (want >= t)


def test_fingerprints_never_miss():
    rng = random.Random(3)
    for _ in range(200):
        host, pattern = random_graph(rng, 7), random_graph(rng, 3)
        if iso.contains(host, pattern):
            assert fingerprint.features(pattern) <= fingerprint.features(host)
            assert fingerprint.fingerprint(pattern) & ~fingerprint.fingerprint(host) == 0
    assert any(f.startswith("C") for f in fingerprint.features(TRIANGLE))


def exact_tail(k, n, p, upper):
    p = Fraction(p).limit_denominator(10**6)
    terms = range(k, n + 1) if upper else range(k + 1)
    return float(sum(math.comb(n, i) * p**i * (1 - p) ** (n - i) for i in terms))


def test_binomial():
    for n, k, p in itertools.product((1, 30, 60), (0, 1, 7, 25), (0.05, 0.4, 0.99)):
        if k <= n:
            for upper in (True, False):
                assert binomial.tail(k, n, p, upper) == pytest.approx(exact_tail(k, n, p, upper), rel=1e-9, abs=1e-300)
    bound = binomial.test_bound(10_000, 30, 35, 165)
    alpha = binomial.corrected_alpha(0.5, bound)
    assert (bound, binomial.doublings(10_000)) == (1_871_100, 9) and alpha == pytest.approx(2.672e-7, rel=1e-3)
    assert [binomial.cuts(n, 0.4, alpha) for n in (30, 60, 120)] == [(0, 26), (6, 44), (21, 76)]
    assert binomial.decide(0, 30, 0.4, alpha) == "INFREQUENT" and binomial.decide(1, 30, 0.4, alpha) == "UNDECIDED" and binomial.decide(26, 30, 0.4, alpha) == "FREQUENT"


@pytest.mark.parametrize("cap", [1, 4, 10_000])
@pytest.mark.parametrize("mode", ["sampled", "exact"])
def test_mined_patterns_are_frequent_and_maximal(cap, mode):
    rng = random.Random(4)
    hosts = [iso.Host(random_graph(rng, 6, 0.35)) for _ in range(24)]
    cfg = Config(n_candidates=12, embedding_cap=cap, mode=mode)
    rows = mining.mine(hosts, mining.facts_here(hosts, 0.5), 0.5, cfg, 0, dict.fromkeys(range(12)))
    assert rows
    for row in rows:
        pattern = Graph.of(*row[2:6])
        support = lambda g: sum(iso.contains(h, g) for h in hosts) / len(hosts)
        assert support(pattern) >= 0.5 and row[6] == round(support(pattern) * len(hosts))
        for u, w in itertools.combinations(range(len(pattern.labels)), 2):
            if w not in pattern.adj[u]:
                for x in "xy":
                    bigger = pattern.copy()
                    bigger.link(u, w, x)
                    assert support(bigger) < 0.5
        for v in range(len(pattern.labels)):
            for label, x in itertools.product("ab", "xy"):
                bigger = pattern.copy()
                bigger.link(v, bigger.add(label), x)
                assert support(bigger) < 0.5


def test_sampled_decisions_stay_under_the_bound():
    rng = random.Random(5)
    hosts = [iso.Host(random_graph(rng, 5, 0.4)) for _ in range(300)]
    facts = mining.facts_here(hosts, 0.4)
    sizes = sorted(len(h.graph.labels) for h in hosts)
    assert facts.v_max == sizes[int(0.6 * 300) - 1]
    for row in mining.mine(hosts, facts, 0.4, Config(), 0, dict.fromkeys(range(4))):
        assert row[8] <= binomial.test_bound(300, 30, facts.v_max, len(facts.paths)) + len(row[2]) * 1000
        assert 0 < row[9] and row[9] * 30 <= row[10] <= row[9] * 300 and row[11] is None
        support = sum(iso.contains(h, Graph.of(*row[2:6])) for h in hosts) / 300
        assert support >= 0.3


def test_what_a_sample_leaves_open_is_told():
    rng = random.Random(5)
    hosts = [iso.Host(random_graph(rng, 5, 0.4)) for _ in range(300)]
    facts = mining.facts_here(hosts, 0.4)
    rows = mining.mine(hosts[:60], facts, 0.4, Config(), 0, dict.fromkeys(range(8)))
    open_ = [r for r in rows if r[12] is not None]
    assert open_  # 60 of 300 graphs cannot tell all supports near 0.4
    for r in open_:
        start = (Graph.of(*r[2:6]), [tuple(x) for x in json.loads(r[11])])
        (again,) = mining.mine(hosts, facts, 0.4, Config(), 0, {r[1]: start}, 1)
        pattern = Graph.of(*again[2:6])
        assert again[12] is None and iso.contains(pattern, start[0])
        assert sum(iso.contains(h, pattern) for h in hosts) >= 0.4 * 300


def test_dissimilar_sets_and_merging(monkeypatch):
    p, p2, q = PATH, PATH.copy(), Graph.of("zz", [0], [1], "x")
    cfg = Config()
    similar = separation.is_similar(cfg)
    for order in itertools.permutations(range(3)):
        chosen = separation.dissimilar_set([p, p2, q], similar, list(order))
        assert 2 in chosen and len(chosen) == 2
    assert len(separation.largest_dissimilar_set([p, p2, q], cfg)) == 2
    reps = {1: [PATH, PATH, PATH], 2: [TRIANGLE], 3: [q, q, q]}
    assert separation.cluster_pairs(reps, cfg) == [(1, 2)]
    assert separation.cluster_pairs({1: [PATH], 2: [PATH]}, cfg) == []
    asked = []
    monkeypatch.setattr(mcs, "similar", lambda *a, **k: asked.append(a) or True)
    many = {c: [PATH] * 3 for c in range(40)}
    # the cost of separating depends on representatives only, and equal ones are compared once
    assert len(separation.cluster_pairs(many, cfg)) == 40 * 39 // 2 and len(asked) == 1
    assert separation.merged_ids([(1, 2), (2, 5), (7, 8)]) == {2: 1, 5: 1, 8: 7}


def test_merge_bound_property():
    rng = random.Random(6)
    for _ in range(60):
        g, r, r2 = random_graph(rng, 6, 0.6), random_graph(rng, 3, 0.8), random_graph(rng, 3, 0.8)
        if iso.contains(g, r):
            common = mcs.size(r, r2)
            assert common / g.size <= max(r.size, r2.size) / g.size * (common / max(r.size, r2.size)) + 1e-12


def test_objective_stop_and_thresholds():
    assert not any(clustering.should_stop([1, 2, 3, 4, 4, 4, 4, 4, 4][:c], 3, 3, 0.01) for c in range(1, 9))
    assert clustering.should_stop([1, 2, 3, 4, 4, 4, 4, 4, 4], 3, 3, 0.01)
    cfg = Config(pre_minsup=0.4)
    assert [round(clustering.minsup_for(r, cfg), 4) for r in (0.5, 1.5, 0.0)] == [0.7278, 0.99, 0.4]
    reps = {1: [Graph.of("ab", [0], [1], "x"), PATH], 2: [Graph(["a"])]}
    stats = {1: clustering.Stats(3, 16), 2: clustering.Stats(2, 8)}
    assert clustering.coverages(reps, stats)[1] == pytest.approx(0.75)
    assert clustering.objective(reps, stats, cfg) == pytest.approx((3 * 0.75 + 2 * 0.25) / 2)
    with pytest.raises(ValueError):
        Config(hr=1.0).validate()


def test_feature_maps():
    assert feature_maps.walks(PATH, 1)["a/x/b"] == 1 and sum(feature_maps.walks(PATH, 2).values()) == 6
    assert sum(feature_maps.wl_shortest_paths(TRIANGLE, 0).values()) == 3
    assert feature_maps.graphlets(TRIANGLE) == Counter({"3:222": 1})
    square = Graph.of("aaaa", [0, 1, 2, 0], [1, 2, 3, 3], "xxxx")
    assert feature_maps.graphlets(square) == Counter({"3:112": 4, "4:2222": 1})
    assert feature_maps.spectrum(PATH) == [0.0, 1.0, 3.0]
    assert feature_maps.mcs_distance(PATH, PATH) == 0 and feature_maps.edit_distance_small(PATH, TRIANGLE) == 1
    # containment is inclusion of subgraph sets
    assert feature_maps.subgraph_indicator(PATH) <= feature_maps.subgraph_indicator(TRIANGLE)
    assert not feature_maps.subgraph_indicator(TRIANGLE) <= feature_maps.subgraph_indicator(PATH)


def test_overlap_unpacks_a_graph_once(monkeypatch):
    """However many cores it meets; and cores without enough labels in common are passed over before any start is tried."""
    from patternclust.baselines import overlap

    made, tried = [], []
    host, may = overlap.Host, overlap.Host.may_contain
    monkeypatch.setattr(overlap, "Host", lambda g: made.append(g) or host(g))
    monkeypatch.setattr(host, "may_contain", lambda self, p: tried.append(p) or may(self, p))
    path = lambda *labels: Graph.of(labels, range(len(labels) - 1), range(1, len(labels)), ["x"] * (len(labels) - 1))
    cores: list = []
    assert [overlap.join(cores, path(*w), 3) for w in ("abcd", "efgh", "abcx", "abxy", "pq", "pqr", "efg")] == [[0], [1], [0], [2], [3], [3], [1]]
    assert len(made) == 7 and len(tried) == 3  # of 11 meetings


def test_groups_of_equal_weight_get_a_slot_each():
    from patternclust.operators import mining

    assert sorted(mining.dealt_slots({(0, i): 1.0 for i in range(8)}, 8).values()) == list(range(8))  # sampled ranges put two in one
    slots = mining.dealt_slots({(0, 0): 9.0, (1, 0): 5.0, (2, 0): 4.0, (3, 0): 1.0}, 2)
    assert slots == {(0, 0): 0, (1, 0): 1, (2, 0): 1, (3, 0): 0}


@pytest.mark.parametrize("cap", [2, 300])
def test_graphs_side_by_side_are_matched_as_one_by_one(cap):
    """Embeddings by arrays are those of the search; beyond the cap as many as it says; disconnected patterns and foreign labels too."""
    from patternclust.functions.packed import Packed

    rng = random.Random(5)
    graphs = [random_graph(rng, rng.randint(1, 7), 0.45) for _ in range(60)]
    side = Packed.of_graphs(graphs)
    assert [side.graph(i).row() for i in range(60)] == [g.row() for g in graphs]
    patterns = [random_graph(rng, rng.randint(1, 4), 0.8, "abc") for _ in range(60)]
    for p in map(iso.Pattern, patterns):
        rows, cut = side.embedded(p, 0, 60, cap)
        own = [rows[side.of[rows[:, 0]] == i] - side.base[i] for i in range(60)]
        for i, g in enumerate(graphs):
            want = set(iso.embeddings(iso.Host(g), p)) if iso.Host(g).may_contain(p) else set()
            got = set(map(tuple, own[i].tolist()))
            assert len(got) == len(own[i]) == min(cap, len(want)) and got <= want and (i in cut) == (len(want) > cap)
        assert side.contains(p, many=cap).tolist() == [iso.contains(g, p) for g in graphs]


def test_growth_searches_no_graph_on_its_own(monkeypatch):
    """Where no embeddings are cut, patterns grow by arrays over all graphs, to what counting shows."""
    rng = random.Random(8)
    hosts = [iso.Host(random_graph(rng, 6, 0.3)) for _ in range(400)]
    facts, searched, may = mining.facts_here(hosts, 0.2), [], iso.Host.may_contain
    monkeypatch.setattr(iso.Host, "may_contain", lambda self, p: searched.append(p) or may(self, p))
    rows = mining.mine(hosts, facts, 0.2, Config(), 0, dict.fromkeys(range(6)))
    monkeypatch.undo()
    assert not searched and len(rows) == 6
    assert max(len(r[2]) for r in rows) > 2
    for r in rows:
        assert r[6] == sum(iso.contains(h, Graph.of(*r[2:6])) for h in hosts[: r[7]])


def test_fingerprints_of_many_graphs_at_once():
    """Marks by arrays are those of single graphs, whatever is enumerated and however labels are written; graphs with many walks too."""
    from patternclust.functions.packed import Packed

    rng = random.Random(3)
    graphs = [random_graph(rng, rng.randint(0, 8), rng.random(), ["a", "b/", ":c", "é", "ab"], ["x", "xy", "/"]) for _ in range(120)]
    side = Packed.of_graphs(graphs)
    for bits, tree, cycle in ((1024, 3, 6), (256, 2, 4), (1024, 1, 3), (64, 3, 3)):
        want = [fingerprint.to_words(fingerprint.fingerprint(g, bits, tree, cycle), bits) for g in graphs]
        assert fingerprint.marks(side, bits, tree, cycle).tolist() == want
    walks, fingerprint.WALKS = fingerprint.WALKS, 50
    assert fingerprint.marks(side).tolist() == [fingerprint.to_words(fingerprint.fingerprint(g)) for g in graphs]
    fingerprint.WALKS = walks


def test_hits_of_a_batch_are_those_of_its_graphs(monkeypatch):
    """Few graphs are searched one by one, many by arrays; fingerprints rule out no hit."""
    import pyarrow as pa

    from patternclust.functions.packed import Packed
    from patternclust.operators import scan

    rng = random.Random(4)
    graphs = [random_graph(rng, rng.randint(1, 6), 0.4) for _ in range(90)]
    columns = [pa.array(list(c), t) for c, t in zip(zip(*(g.row() for g in graphs)), (pa.list_(pa.string()), *[pa.list_(pa.int32())] * 2, pa.list_(pa.string())))]
    batch = pa.RecordBatch.from_arrays(columns, ["vl", "eu", "ew", "el"])
    patterns = [(rng.randint(0, 3), random_graph(rng, rng.randint(1, 4), 0.9)) for _ in range(30)]
    known, marks = scan.Known.of(patterns, Config()), fingerprint.marks(Packed.of_graphs(graphs))
    for few in (0, 1000):
        monkeypatch.setattr(scan, "FEW", few)
        for held in (marks, None):
            found = list(scan.hits_in(batch, held, known))
            assert [known.cluster[i] for i, *_ in found] == sorted(c for c, _ in patterns)
            for i, tested, hits in found:
                assert hits.tolist() == [g for g in range(90) if iso.contains(graphs[g], patterns[i][1])] and set(hits) <= set(tested)


@pytest.mark.parametrize("labels", ["ab", "abcdefgh"])
def test_clusters_that_cannot_share_enough_are_not_met(labels, monkeypatch):
    """Memberships and cores are those of meeting every cluster, in fewer meetings."""
    from patternclust.baselines import overlap

    rng, met, common = random.Random(6), [], overlap.common_core
    graphs = [random_graph(rng, rng.randint(1, 7), rng.choice((0.1, 0.3, 0.6)), labels) for _ in range(150)]
    monkeypatch.setattr(overlap, "common_core", lambda *a, **k: met.append(1) or common(*a, **k))
    for least in (1, 3, 4):
        plain, own = [], overlap.Cores(least)
        want = [overlap.join(plain, g, least) for g in graphs]
        all_, met[:] = len(met), []
        assert [own.join(g) for g in graphs] == want and len(met) < all_
        assert [c.row() for c, _ in own.held] == [c.row() for c, _ in plain]
        met.clear()


def test_document_graphs_of_a_batch():
    """Followers counted in one table for many documents are those counted text by text; several texts of a document do not run on."""
    import pyarrow as pa

    from patternclust import corpora

    rng = random.Random(9)
    docs = [[[rng.choice("abcdé") for _ in range(rng.randint(0, 12))] for _ in range(rng.randint(1, 3))] for _ in range(80)]
    keys = [None if i == 7 else i for i in range(80)]
    out = corpora.document_batch(pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(docs, pa.list_(pa.list_(pa.string())))], ["g", "ts"])).to_pylist()
    for key, texts, row in zip(keys, docs, out, strict=True):
        labels, edges = sorted({w for t in texts for w in t}), {}
        for step, label in ((2, "s"), (1, "a")):
            seen = Counter(p for t in texts for p in zip(t, t[step:]) if p[0] != p[1])
            for x in {x for x, _ in seen}:
                y = min((-n, b) for (a, b), n in seen.items() if a == x)[1]
                edges[min(x, y), max(x, y)] = label
        want = sorted((labels.index(a), labels.index(b), label) for (a, b), label in edges.items()) if key is not None else []
        assert row == {"graph_id": key, "vl": labels, "eu": [e[0] for e in want], "ew": [e[1] for e in want], "el": [e[2] for e in want]}


def test_steps_are_counted_over_a_batch_as_graph_by_graph(monkeypatch):
    """Counts of a scan in exact mode: by arrays over all graphs, none searched on its own unless its embeddings are cut."""
    from patternclust.functions.packed import Packed

    rng = random.Random(12)
    hosts = [iso.Host(random_graph(rng, rng.randint(1, 6), 0.5)) for _ in range(80)]
    facts, side, cfg = mining.facts_here(hosts, 0.1), Packed.of_graphs([h.graph for h in hosts]), Config(mode="exact")
    searched, find = [], mining.find_embedding
    monkeypatch.setattr(mining, "find_embedding", lambda h, p: searched.append(p) or find(h, p))
    for start in (Graph(["a"]), Graph.of("ab", [0], [1], "x"), Graph.of("aab", [0, 1], [1, 2], "xy")):
        for cap in (300, 1):
            growth = mining.Growth(None, facts, 0.1, replace(cfg, embedding_cap=cap), random.Random(1))
            growth.begin(start)
            counts = growth.shown(side)
            assert counts.pop(None) == sum(iso.contains(h, start) for h in hosts) > 0
            want = {x: sum(iso.contains(h, mining.extended(start, x)) for h in hosts) for own in growth.alive for x in own}
            assert counts == {x: n for x, n in want.items() if n} and bool(searched) == (cap == 1)
            searched.clear()
