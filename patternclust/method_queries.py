"""Whole methods over whole corpora: no SQL; tests hold them against brute force, truth and invariants."""

from __future__ import annotations

import uuid
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .baselines import kernel_kmeans, kmedoids, overlap
from .config import Config
from .corpora import graphs
from .functions.fingerprint import with_fingerprint
from .model import Graph
from .operators import graph_stats, measures, mining, vectors
from .planted import planted_corpus
from .plans import clustering
from .plans.state import commit, folder
from .queries import query
from .sources.tables import table
from .streaming.graphs import session_graphs

#: corpora of one structure throughout: at the 0.01 that suits a hundred planted classes, initial patterns would be single graphs
CORPUS_CONFIG = Config(pre_minsup=0.05, least_minsup=0.02)


def _fit(graph_rows: DataFrame, cfg: Config) -> DataFrame:
    return clustering.fit(graph_rows, cfg).assignment.select("graph_id", "cluster_id", "similarity", "gsize")


def _planted(spark, sf) -> DataFrame:
    """A graph for each customer, made by all cores: the table is small, and the graphs are most of the work."""
    keys = table(spark, sf, "customer").select("c_custkey")
    return planted_corpus(keys.repartition(8 * spark.sparkContext.defaultParallelism), "c_custkey")


@query()
def fit_planted_sampled(spark, sf):
    """The synthetic corpus with the published parameters, one graph for each customer, until the stop rule."""
    return _fit(_planted(spark, sf), Config())


@query()
def fit_planted_exact(spark, sf):
    """The same with every support counted on the whole cluster."""
    return _fit(_planted(spark, sf), Config(mode="exact"))


@query()
def fit_doc(spark, sf):
    return _fit(graphs(spark, sf, "doc"), CORPUS_CONFIG)


@query()
def fit_doc_exact(spark, sf):
    return _fit(graphs(spark, sf, "doc"), replace(CORPUS_CONFIG, mode="exact"))


@query()
def fit_doc_random_start(spark, sf):
    return _fit(graphs(spark, sf, "doc"), replace(CORPUS_CONFIG, precluster="random"))


@query()
def fit_dom(spark, sf):
    """Element trees of pages. Patterns end at twelve vertices: among equal siblings the embeddings of larger ones grow without bound."""
    return _fit(graphs(spark, sf, "dom"), replace(CORPUS_CONFIG, pre_minsup=0.4, least_minsup=0.1, n_candidates=10, pre_candidates=20, max_vertices=12))


@query()
def fit_orders(spark, sf):
    return _fit(graphs(spark, sf, "order"), CORPUS_CONFIG)


@query()
def fit_sessions(spark, sf):
    return _fit(graphs(spark, sf, "session"), CORPUS_CONFIG)


@query()
def mine_candidates(spark, sf):
    """Candidates of one set, the document corpus, at a fixed threshold."""
    g = commit(with_fingerprint(graphs(spark, sf, "doc")).withColumn("cluster_id", F.lit(0)), "corpus")
    rows = [x.row() for x in mining.candidates(g, {0: g.count()}, {0: 0.2}, CORPUS_CONFIG)]
    return spark.createDataFrame(rows, ", ".join(mining.CANDIDATES.split(", ")[:11]))


@query()
def precluster_patterns(spark, sf):
    g = commit(graphs(spark, sf, "order"), "corpus")
    patterns, minsup, _ = clustering.precluster(g, g.count(), CORPUS_CONFIG)
    rows = [(i, p.size, *p.row(), minsup) for i, p in enumerate(patterns)]
    return spark.createDataFrame(rows, "cluster_id int, rsize int, vl array<string>, eu array<int>, ew array<int>, el array<string>, minsup double")


@query()
def fit_overlap_purity(spark, sf):
    """Purity of overlapping clusters on documents, by language."""
    members = overlap.fit(graphs(spark, sf, "doc"), 8, 0.2)
    truth = table(spark, sf, "documents").select(F.col("doc_id").alias("graph_id"), "lang")
    return measures.purity(measures.contingency(members.join(truth, "graph_id"), "cluster", "lang"))


@query()
def projected_medoids_embeddings(spark, sf):
    e = vectors.doubles(table(spark, sf, "embeddings"))
    return kmedoids.fit(e, 10, 20).select("vec_id", "cluster", F.round("dist", 6).alias("dist"))


@query()
def kernel_kmeans_sessions(spark, sf):
    return kernel_kmeans.fit_linear(kernel_kmeans.unit_rows(graph_stats.three_vertex_features(graphs(spark, sf, "session"))), 8)


@query()
def kernel_kmeans_embeddings(spark, sf):
    """Kernel k-means of the embeddings with as many clusters as labels."""
    e = table(spark, sf, "embeddings").where("embedding IS NOT NULL")
    k = e.agg(F.count_distinct("label") + F.max(F.col("label").isNull().cast("int"))).first()[0] or 0  # null is a label too
    v = F.col("embedding").cast("array<double>")
    return kernel_kmeans.fit_linear(e.select(F.col("vec_id").alias("graph_id"), F.transform(v, lambda x, i: i).alias("f"), v.alias("v")), k)


def session_model() -> clustering.Model:
    """A small frozen model of event paths."""
    path = lambda *labels: Graph.of(labels, range(len(labels) - 1), range(1, len(labels)), ["next"] * (len(labels) - 1))
    reps = {1: [path("view", "purchase")], 2: [path("click", "purchase")], 3: [path("view", "click"), path("view", "view")]}
    return clustering.Model(Config(filter="none"), reps, None)


@query()
def stream_assign_sessions(spark, sf):
    """Events as a file stream, closed sessions as graphs, assigned by a frozen model into a table."""
    schema = table(spark, sf, "events").schema
    events = spark.readStream.schema(schema).parquet(f"{sf}/events.parque[t]")  # a pattern: the table is a file or a folder
    assigned = session_model().predict(session_graphs(events))
    base = f"{folder(spark)}/stream-{uuid.uuid4().hex}"
    run = assigned.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.parquet(f"{base}/out").select("graph_id", "cluster_id", "similarity", "gsize")


@query()
def session_assign_batch(spark, sf):
    """The same sessions in one batch, the open ones included."""
    return session_model().predict(session_graphs(table(spark, sf, "events"))).select("graph_id", "cluster_id", "similarity", "gsize")


@query("""WITH e AS (SELECT *, lag(ts) OVER w AS before FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
n AS (SELECT *, sum(CASE WHEN before IS NULL OR ts - before >= INTERVAL 12 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS s FROM e),
p AS (SELECT user_id, s, ts, event_type AS b, lag(event_type) OVER (PARTITION BY user_id, s ORDER BY ts, event_id) AS a FROM n),
f AS (SELECT user_id, min(ts) AS start, 2 * count(*) - 1 AS gsize, max(CASE WHEN (a, b) IN (('view', 'purchase'), ('purchase', 'view')) THEN 9 ELSE 0 END) AS s1,
        max(CASE WHEN (a, b) IN (('click', 'purchase'), ('purchase', 'click')) THEN 9 ELSE 0 END) AS s2,
        max(CASE WHEN (a, b) IN (('view', 'click'), ('click', 'view')) THEN 9 ELSE 0 END) + max(CASE WHEN a = 'view' AND b = 'view' THEN 9 ELSE 0 END) AS s3 FROM p GROUP BY user_id, s)
SELECT user_id, strftime(start, '%Y-%m-%d %H:%M:%S') AS start, CASE WHEN greatest(s1, s2, s3) = 0 THEN -1 WHEN s1 = greatest(s1, s2, s3) THEN 1 WHEN s2 = greatest(s1, s2, s3) THEN 2 ELSE 3 END AS cluster_id,
       greatest(s1, s2, s3)::BIGINT AS similarity, gsize::INTEGER AS gsize FROM f""")
def session_assign_by_user(spark, sf):
    """The batch assignment by user and start, which SQL can follow."""
    sessions = commit(session_graphs(table(spark, sf, "events")), "sessions")
    start = F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start")
    return session_model().predict(sessions).join(sessions.select("graph_id", "user_id", start), "graph_id").select("user_id", "start", "cluster_id", "similarity", "gsize")
