"""The loop, baselines, model, sources and streams on small corpora."""

import random
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from patternclust import corpora, model, planted, sqlapi
from patternclust.baselines import kernel_kmeans, kmedoids, overlap
from patternclust.config import Config
from patternclust.functions.fingerprint import with_fingerprint
from patternclust.functions.iso import contains
from patternclust.model import Graph
from patternclust.operators import graph_stats, measures, mining, relational_match, scan
from patternclust.plans import clustering
from patternclust.sources import tables
from patternclust.streaming import graphs as streams


@pytest.fixture(scope="module")
def keys(spark):
    return tables.table(spark, "/root/testdata/sf0.001", "orders").where("o_orderkey < 300")


@pytest.fixture(scope="module")
def fitted(spark, keys):
    g = planted.planted_corpus(keys)
    cfg = Config(n_candidates=10, pre_minsup=0.02, least_minsup=0.01, max_iter=6)
    return g, clustering.fit(g, cfg)


def test_planted_corpus(spark, keys):
    g = planted.planted_corpus(keys)
    assert model.violations(g).count() == 0
    d = graph_stats.describe(g).first()
    assert d.n_graphs == 300 and 30 < d.v_avg < 42 and 38 < d.e_avg < 60 and d.n_vlabels == 10 and d.n_elabels == 3
    truth = {r.graph_id: (r["class"], r.noise) for r in planted.planted_truth(keys).collect()}
    assert all(truth[k] == (planted.planted_class(k), planted.is_noise(k)) for k in truth)
    for r in g.limit(15).collect():
        if not planted.is_noise(r.graph_id):
            assert contains(Graph.of(r.vl, r.eu, r.ew, r.el), planted.seed_graph("class", planted.planted_class(r.graph_id), 1))


def test_fit_finds_the_classes(keys, fitted):
    g, m = fitted
    assert m.assignment.count() == 300 and m.assignment.select("graph_id").distinct().count() == 300
    assert clustering.check_invariant(m, g) == 0
    q = measures.all_measures(m.assignment, planted.planted_truth(keys), True)
    assert q["nvi"] >= 0.6 and q["purity"] >= 0.6, q
    assert all(len(r) <= m.cfg.r_max for r in m.representatives.values()) and m.history[-1]["k"] == m.k and m.describe()


def test_filter_changes_nothing(fitted):
    g, m = fitted
    plain = clustering.Model(Config(filter="none"), m.representatives, None).predict(g)
    other = m.predict(g)
    pick = lambda d: sorted(tuple(r) for r in d.select("graph_id", "cluster_id", "similarity").collect())
    assert pick(plain) == pick(other)
    tests = lambda d: d.agg(F.sum("n_tests")).first()[0]
    assert tests(other) < tests(plain)


def test_assignment_has_no_exchange(fitted):
    g, m = fitted
    plan = m.predict(g)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInArrow" in plan


def test_exact_and_random_variants(keys):
    g = planted.planted_corpus(keys.where("o_orderkey < 60"))
    for options in ({"mode": "exact"}, {"precluster": "random", "random_clusters": 4}, {"balance": False}, {"specificity": False}, {"split_on": "hcov"}):
        m = clustering.fit(g, Config(n_candidates=5, pre_minsup=0.1, least_minsup=0.05, max_iter=2, **options))
        assert m.assignment.count() == 60 and clustering.check_invariant(m, g) == 0


def test_degenerate_sets(spark):
    rows = [(1, ["a"], [], [], []), (2, ["a"], [], [], []), (3, ["zz"], [], [], []), (4, [], [], [], [])]
    g = spark.createDataFrame(rows, model.GRAPH_SCHEMA)
    m = clustering.fit(g, Config(n_candidates=3, max_iter=2))
    assert m.assignment.count() == 4
    assert m.assignment.where("graph_id = 4").first().cluster_id == -1
    assert clustering.fit(g.limit(0), Config(n_candidates=3, max_iter=2)).assignment.count() == 0


def test_relational_match_equals_kernel(spark, sf_dir):
    v, e = corpora.session_corpus(spark, sf_dir)
    g = model.assemble(v, e).cache()
    assert model.violations(g).count() == 0
    rng = random.Random(0)
    types = [r.l for r in v.select("l").distinct().orderBy("l").collect()]
    for _ in range(4):
        pattern = Graph.of([rng.choice(types) for _ in range(3)], [0, 1], [1, 2], ["next", rng.choice(["next", "same"])])
        want = {r.graph_id for r in g.collect() if contains(Graph.of(r.vl, r.eu, r.ew, r.el), pattern)}
        assert {r.g for r in relational_match.match(v, e, pattern).collect()} == want
        assert {r.graph_id for r in scan.search(with_fingerprint(g), pattern).collect()} == want
        assert scan.support(g, [pattern])[0] == (len(want), g.count())


def test_sources(spark, sf_dir, tmp_path):
    g = corpora.graphs(spark, sf_dir, "dom")
    assert model.violations(g).count() == 0
    rows = lambda d: sorted((r.graph_id, list(r.vl), sorted(zip(r.eu, r.ew, r.el))) for r in d.collect())
    tables.write_graph_text(g, str(tmp_path / "text"))
    assert rows(tables.read_graph_text(spark, str(tmp_path / "text"))) == rows(g)
    g.write.json(str(tmp_path / "json"))
    assert rows(tables.read_graph_json(spark, str(tmp_path / "json"))) == rows(g)
    v, e = model.normal_form(g)
    v.write.option("header", True).csv(str(tmp_path / "v"))
    e.write.option("header", True).csv(str(tmp_path / "e"))
    v2, e2 = tables.read_edge_lists(spark, str(tmp_path / "v"), str(tmp_path / "e"))
    assert model.assemble(v2, e2).agg(F.sum(F.size("vl")), F.sum(F.size("eu"))).first() == g.agg(F.sum(F.size("vl")), F.sum(F.size("eu"))).first()
    spark.dataSource.register(tables.PlantedGraphs)
    assert spark.read.format("planted_graphs").option("n", 20).load().count() == 20
    tables.write_assignment(spark.createDataFrame([(1, 5), (2, -1)], "graph_id bigint, cluster_id int"), str(tmp_path / "a"))
    assert spark.read.parquet(str(tmp_path / "a")).where("bucket = 5").count() == 1


def test_sql_functions(spark):
    sqlapi.register(spark)
    g = "named_struct('vl', array('a','b'), 'eu', array(0), 'ew', array(1), 'el', array('x'))"
    h = "named_struct('vl', array('a','b','c'), 'eu', array(0,1), 'ew', array(1,2), 'el', array('x','x'))"
    r = spark.sql(f"SELECT graph_contains({h}, {g}) a, graph_contains({g}, {h}) b, graph_mcs({g}, {h}) m, graph_code({g}) = graph_code({g}) c, support_decision(0, 30, 0.4D, 2.672e-7D) d").first()
    assert (r.a, r.b, r.m, r.c, r.d) == (True, False, 3, True, "INFREQUENT")


def test_baselines(spark, keys):
    rng = np.random.default_rng(0)
    centres = rng.normal(0, 6, (4, 12))
    rows = [(i, (centres[i % 4] + rng.normal(0, 0.3, 12)).tolist()) for i in range(200)]
    v = spark.createDataFrame(rows, "vec_id bigint, v array<double>")
    truth = spark.createDataFrame([(i, i % 4) for i in range(200)], "graph_id bigint, class int")
    as_pairs = lambda d: d.select(F.col("vec_id").alias("graph_id"), F.col("cluster").alias("cluster_id"))
    assert measures.all_measures(as_pairs(kmedoids.fit(v, 4, 6)), truth)["purity"] > 0.7
    x = np.array([r[1] for r in rows])
    assert measures.all_measures(kernel_kmeans.fit(spark, np.arange(200), x, 4), truth)["nvi"] > 0.6
    dims = kmedoids.choose_dimensions(np.array([[0.1, 5.0, 0.2, 9.0], [4.0, 0.1, 7.0, 0.3]]), 2)
    assert [d.tolist() for d in dims] == [[0, 2], [1, 3]]
    members = overlap.fit(planted.planted_corpus(keys.where("o_orderkey < 40")), 10, 0.2)
    assert members.select("graph_id").distinct().count() == 40


def test_exact_support_and_maximality(spark):
    from patternclust.operators import support

    rng = random.Random(3)
    rows = []
    for k in range(20):
        g = Graph([rng.choice("ab") for _ in range(4)])
        for u in range(4):
            for w in range(u):
                if rng.random() < 0.6:
                    g.link(w, u, "x")
        rows.append((k, *g.row()))
    df = spark.createDataFrame(rows, model.GRAPH_SCHEMA)
    edge, path = Graph.of("ab", [0], [1], "x"), Graph.of("aba", [0, 1], [1, 2], "xx")
    (k1, n), (k2, _) = support.exact(df, [edge, path])
    assert n == 20 and k2 <= k1
    assert support.is_frequent(df, [edge], 1 / 20) == [True]
    bigger = support.extensions(edge, {("a", "x", "a"), ("a", "x", "b"), ("b", "x", "b")})
    assert len(bigger) == 4 and all(contains(b, edge) for b in bigger)
    assert support.is_maximal(df, edge, k1 / 20) == (not any(support.is_frequent(df, bigger, k1 / 20)))
    assert support.prune_by_subset([edge], [path, Graph(["a"])])[0].labels == ["a"]
    assert 0 <= support.mining_error(df, [edge], 0.05) <= 1


def test_plain_kmeans(spark):
    from patternclust.baselines import kmeans

    v = spark.createDataFrame([(i, [float(i % 2) * 10 + 0.01 * i, 1.0]) for i in range(40)], "vec_id bigint, v array<double>")
    got = {r.vec_id % 2: r.cluster for r in kmeans.fit(v, 2).collect()}
    assert len(set(got.values())) == 2


def test_measures_of_a_small_table(spark):
    t = spark.createDataFrame([(1, "a", 2), (1, "b", 1), (2, "b", 1)], "cluster int, class string, n bigint")
    assert tuple(measures.nvi(t).first()) == (1.188722, 0.792481, 0.207519)
    assert measures.fowlkes_mallows(t).first()[0] == 0.408248 and measures.purity(t).first()[0] == 0.75


def test_streams(spark, sf_dir, tmp_path):
    from patternclust import method_queries as mq

    streamed = {tuple(r) for r in mq.stream_assign_sessions(spark, sf_dir).collect()}
    batch = {tuple(r) for r in mq.session_assign_batch(spark, sf_dir).collect()}
    assert streamed and streamed <= batch and len(streamed) > 0.5 * len(batch)
    # drift windows and duplicates, in batch form
    m = mq.session_model()
    assigned = spark.createDataFrame([("2024-01-01 00:10:00", 1, 3), ("2024-01-01 05:00:00", 1, 30)], "ts string, cluster_id int, gsize int").withColumn("ts", F.to_timestamp("ts"))
    assert [r.drifting for r in streams.drift(assigned, m, "1 hour").orderBy("start").collect()] == [False, True]


def test_running_support(spark, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    spark.createDataFrame([("p", i % 10 == 0) for i in range(200)] + [("q", True)] * 200, "pattern string, hit boolean").write.parquet(str(tmp_path / "hits"))
    s = spark.readStream.schema("pattern string, hit boolean").parquet(str(tmp_path / "hits"))
    q = streams.running_support(s, 0.6, 1e-6).writeStream.format("memory").queryName("running").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {r.pattern: r.decision for r in spark.table("running").collect()}
    assert got == {"p": "INFREQUENT", "q": "FREQUENT"}


def test_refit_noise(spark):
    called = []
    on_batch = streams.refit_noise(None, 0.5, lambda rows, number: called.append((rows.count(), number)))
    on_batch(spark.createDataFrame([(1, -1), (2, -1), (3, 0)], "graph_id bigint, cluster_id int"), 7)
    on_batch(spark.createDataFrame([(1, 0)], "graph_id bigint, cluster_id int"), 8)
    assert called == [(2, 7)]


def test_overlap_partition_is_never_split(spark):
    alike = spark.range(4001).selectExpr("id AS graph_id", "array('a', 'b', 'c') AS vl", "array(0, 1) AS eu", "array(1, 2) AS ew", "array('x', 'x') AS el")
    members = overlap.fit(alike, 3, 0.2)
    assert (members.count(), members.select("cluster").distinct().count()) == (4001, 1)


def test_medoid_rounds_read_all_vectors(spark, monkeypatch):
    x = np.random.default_rng(5).normal(size=(400, 6))
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id bigint, v array<double>")
    seen, cost_of = [], kmedoids.round_cost

    def recorded(vectors, medoids, dims):
        cost, counts = cost_of(vectors, medoids, dims)
        reach = [np.sort(np.abs(medoids - m).mean(axis=1))[1] for m in medoids]
        gaps = np.abs(x[:, None, :] - medoids[None, :, :])
        near = gaps.mean(axis=2) <= reach
        dev = np.stack([gaps[near[:, i] if near[:, i].sum() > 1 else slice(None), i].mean(axis=0) for i in range(3)])
        assert [d.tolist() for d in dims] == [d.tolist() for d in kmedoids.choose_dimensions(dev, 3)]
        assert np.isclose(cost, kmedoids._distances(x, medoids, dims).min(axis=1).mean())
        seen.append(int(counts.sum()))
        return cost, counts

    monkeypatch.setattr(kmedoids, "round_cost", recorded)
    assert kmedoids.fit(v, 3, 3, rounds=2, sample_rows=40).count() == 400
    assert seen == [400, 400]


def test_candidates_are_ranked_on_all_graphs(spark, monkeypatch):
    g = with_fingerprint(spark.range(20_400).selectExpr("id AS graph_id", "array('a', 'b') AS vl", "array(0) AS eu", "array(1) AS ew", "array('x') AS el"))
    clustered = g.selectExpr("*", "0 AS cluster_id", "3 AS gsize")
    seen, hit_counts = [], scan.hit_counts

    def recorded(graphs, patterns, cfg):
        counts = hit_counts(graphs, patterns, cfg)
        seen.extend(counts[i][0] for i in counts)
        return counts

    monkeypatch.setattr(scan, "hit_counts", recorded)
    clustering.update(clustered, clustering._stats(clustered), {}, Config(n_candidates=2, group_cap=200))
    assert seen and set(seen) == {20_400}


def test_open_decisions_end_in_exact_counts(spark, keys):
    """With samples far under the set, candidates are settled by counts over all graphs, and err less often than the knob allows."""
    from patternclust.operators import mining, support

    g = with_fingerprint(planted.planted_corpus(keys)).withColumn("cluster_id", F.lit(0)).cache()
    cfg = Config(n_candidates=6, group_cap=60, cap_top=120)
    facts = mining.facts_of(g, {0: 300}, {0: 0.3})[0]
    hosts = [mining.Host(Graph.of(r.vl, r.eu, r.ew, r.el)) for r in g.collect()]
    assert facts == mining.facts_here(hosts, 0.3)
    found = mining.candidates(g, {0: 300}, {0: 0.3}, cfg)
    assert len(found) == 6 and max(x.n_drawn / max(1, x.n_decided) for x in found) > 60
    assert support.mining_error(g, [x.pattern for x in found], 0.3) <= cfg.max_error
    exact = mining.candidates(g, {0: 300}, {0: 0.3}, Config(n_candidates=6, mode="exact"))
    assert support.mining_error(g, [x.pattern for x in exact], 0.3) == 0.0


def test_clusters_far_from_merging_in_tasks(spark):
    from patternclust.operators import separation

    reps = {c: [Graph.of([f"l{c // 2}", "x", f"r{c // 2}"], [0, 1], [1, 2], "ee")] * 3 for c in range(40)}
    cfg = Config(t_sim=0.9)
    assert separation.cluster_pairs(reps, cfg, None, spark) == separation.cluster_pairs(reps, cfg) == [(c, c + 1) for c in range(0, 40, 2)]


def test_fingerprints_lose_no_hit(spark, sf_dir):
    from patternclust import method_queries  # noqa: F401  registers its queries
    from patternclust.queries import QUERIES

    native = {r.cluster_id: r for r in QUERIES["fingerprint_filter_power"](spark, sf_dir).collect()}
    for r in QUERIES["fingerprint_power"](spark, sf_dir).collect():
        assert r.n_hits == native[r.cluster_id].n_hits <= r.n_candidates <= native[r.cluster_id].n_candidates


def test_kernel_kmeans_of_embeddings(spark, sf_dir):
    """Where it stops, one more step changes nothing (labels say little here: their vectors are near to random)."""
    from patternclust import method_queries as mq

    e = tables.table(spark, sf_dir, "embeddings")
    found = {r.graph_id: r.cluster_id for r in mq.kernel_kmeans_embeddings(spark, sf_dir).collect()}
    rows = e.select("vec_id", "embedding").collect()
    x, own = np.array([r.embedding for r in rows]), np.array([found[r.vec_id] for r in rows])
    means = np.stack([x[own == c].mean(axis=0) if (own == c).any() else np.full(64, 9.0) for c in range(10)])
    again = ((x[:, None, :] - means[None]) ** 2).sum(axis=2).argmin(axis=1)
    assert len(found) == len(rows) and (again == own).mean() > 0.99


def test_what_medoids_do_not_hold_comes_last():
    dev = np.array([[0.0, 0.0, 1.0, 2.0], [3.0, 0.0, 0.0, 1.0]])
    present = np.array([[False, False, True, True], [True, False, False, True]])
    assert [d.tolist() for d in kmedoids.choose_dimensions(dev, 2, present)] == [[2, 3], [0, 3]]
    assert [d.tolist() for d in kmedoids.choose_dimensions(dev, 2)] == [[0, 1], [1, 2]]


def test_kernel_kmeans_of_more_objects_than_a_matrix_holds(spark, tmp_path, monkeypatch):
    """No number of objects is refused; with the linear kernel the sums give what the whole matrix gives."""
    from patternclust import method_queries as mq

    monkeypatch.setattr(kernel_kmeans, "MAX_OBJECTS", 50)
    rng = np.random.default_rng(0)
    centres = rng.normal(0, 6, (4, 12))
    rows = [(i, str(i % 4), (centres[i % 4] + rng.normal(0, 0.3, 12)).tolist()) for i in range(400)]
    spark.createDataFrame(rows, "vec_id bigint, label string, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    found = {r.graph_id: r.cluster_id for r in mq.kernel_kmeans_embeddings(spark, str(tmp_path)).collect()}
    assert len(found) == 400 and len({(i % 4, c) for i, c in found.items()}) == 4
    cnt = [(i, f, 1 + (i + len(f)) % 3) for i in range(200) for f in (("a", "bb") if i % 2 else ("ccc", "a", "dddd"))]
    features = spark.createDataFrame(cnt, "graph_id bigint, feature string, cnt bigint")
    units = kernel_kmeans.unit_rows(features)
    found = {r.graph_id: r.cluster_id for r in kernel_kmeans.fit_linear(units, 2).collect()}
    assert len(found) == 200 and len({(i % 2, c) for i, c in found.items()}) == 2
    assert kernel_kmeans.fit_linear(units.where("false"), 2).count() == 0 and {r[1] for r in kernel_kmeans.fit_linear(units, 1).collect()} == {0}


def test_exact_candidates_of_a_large_cluster_are_held_by_no_task(spark, monkeypatch):
    """Beyond what a task may hold all patterns grow by scans, to the same candidates; embeddings that are cut change nothing."""
    g = with_fingerprint(planted.planted_corpus(spark.range(120).withColumnRenamed("id", "o_orderkey"))).withColumn("cluster_id", F.lit(0))
    cfg = Config(mode="exact", n_candidates=6, max_vertices=6)
    whole = [mining.candidates(g, {0: 120}, {0: 0.1}, replace(cfg, embedding_cap=cap)) for cap in (300, 2)]
    grown, held = mining._grown, []
    monkeypatch.setattr(mining, "_grown", lambda graphs, sizes, facts, minsups, tasks, *rest: held.extend(tasks) or grown(graphs, sizes, facts, minsups, tasks, *rest))
    for cap, want in zip((300, 2), whole, strict=True):
        assert mining.candidates(g, {0: 120}, {0: 0.1}, replace(cfg, embedding_cap=cap, cap_top=100)) == want and len(want) == 6
    assert not held


def test_overlap_partitions_are_not_put_together(spark):
    """Their rows are light and the work on them is not: each is a task, whatever the size in bytes."""
    g = planted.planted_corpus(spark.range(60).withColumnRenamed("id", "o_orderkey"))
    assert overlap.fit(g, 10, 0.2).rdd.getNumPartitions() == 64
