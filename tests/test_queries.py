"""Every query with SQL gives DuckDB's rows at the smallest scale; golden values at the next."""

import re

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = sorted(n for n in entry.oracle_sql() if not re.match(r"op\d", n) and n != "pipeline")


def connect(sf):
    db = duckdb.connect()
    for t in TABLES:
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return db


def rows(df):
    columns = sorted(df.columns)
    clean = df[columns].astype(object).where(df[columns].notna(), None)
    return columns, sorted(map(str, clean.map(lambda x: x if x is None or isinstance(x, str) else float(x)).values.tolist()))


@pytest.mark.parametrize("name", NAMES)
def test_against_sql(spark, sf_dir, name):
    got = entry.queries()[name](spark, sf_dir).toPandas()
    assert rows(got) == rows(connect(sf_dir).execute(entry.oracle_sql()[name]).df())


def test_golden_values(spark):
    sf = "/root/testdata/sf0.01"
    run = lambda name: entry.queries()[name](spark, sf).toPandas()
    assert run("order_cluster_stats").set_index("cluster_id").n.to_dict() == {-1: 7141, 1: 1280, 2: 2157, 3: 1459, 4: 1068, 5: 1638}
    assert run("order_assign").similarity.value_counts().to_dict() == {0: 7141, 9: 6885, 18: 344, 25: 318, 34: 52, 43: 3}
    assert run("order_rank").set_index(["cluster_id", "rep_id"])["rank"].sort_index().loc[1].round(6).tolist() == [0.069301, 0.063764, 0.009893]
    assert run("vmax_quantile").set_index("minsup").vmax.to_dict() == {0.4: 9, 0.9: 5, 0.99: 3}
    merged = run("merge_pairs")
    assert (merged.n_similar == 3).all() and merged.merged.all()


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_merge_pairs_follow_the_orders(spark, tmp_path):
    """Without standard parts, one representative of each cluster has no supporters: two similar ones do not merge."""
    import shutil

    shutil.copytree("/root/testdata/sf0.01", tmp_path / "sf")
    path = str(tmp_path / "sf" / "part.parquet")
    duckdb.sql(f"COPY (SELECT * REPLACE (CASE WHEN p_type LIKE 'STANDARD%' THEN 'ECONOMY' ELSE p_type END AS p_type) FROM '/root/testdata/sf0.01/part.parquet') TO '{path}' (FORMAT parquet)")
    got = entry.queries()["merge_pairs"](spark, str(tmp_path / "sf")).toPandas()
    assert rows(got) == rows(connect(str(tmp_path / "sf")).execute(entry.oracle_sql()["merge_pairs"]).df())
    assert len(got) == 10 and (got.n_similar == 2).all() and not got.merged.any()


def test_document_graphs_are_those_of_the_normal_form(spark, sf_dir, tmp_path):
    from pyspark.sql import functions as F

    from patternclust import corpora
    from patternclust.model import assemble

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(60)
    odd = [(1, "The cat and the dog and the end of THE"), (10**6, "der la la la of of"), (10**6, "of the of the"), (None, "the end of it"), (10**6 + 1, "12 !"), (10**6 + 2, None), (10**6 + 3, "of")]
    more = spark.createDataFrame(odd, "doc_id bigint, text string")
    docs.select("doc_id", "text").unionByName(more).write.parquet(f"{tmp_path}/documents.parquet")
    key = lambda r: (r["graph_id"] is None, r["graph_id"] or 0)
    within = corpora.graphs(spark, str(tmp_path), "doc")
    assert "Join" not in within._jdf.queryExecution().executedPlan().toString()
    got, want = (sorted(map(lambda r: r.asDict(), d.collect()), key=key) for d in (within, assemble(*corpora.document_corpus(spark, str(tmp_path)))))
    assert got == want and len(got) == docs.select(F.col("doc_id")).distinct().count() + 3


def test_planted_graphs_are_made_by_all_cores(spark, sf_dir):
    from patternclust import method_queries, planted

    made = method_queries._planted(spark, sf_dir)
    assert made.rdd.getNumPartitions() > 1
    rows = lambda d: sorted(map(repr, d.collect()))
    assert rows(made) == rows(planted.planted_corpus(spark.read.parquet(f"{sf_dir}/customer.parquet"), "c_custkey"))
