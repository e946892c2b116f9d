"""Mixing, quality, URLs, search, packages and the pipeline: brute force, round trips, edge cases."""

import hashlib
import io
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from patternclust.llm import mixing, quality, topk_search, url_filter, warc_zip


# mixing
def docs_of(spark, rows):
    return spark.createDataFrame([(k, t, s, 1, "y") for k, t, s in rows], "doc_id bigint, text string, source string, size int, target string")


def test_targets_share_out_the_excess(spark):
    sizes = {"a": 1000, "b": 10, "c": 500, None: 90, "B": 0}
    df = spark.createDataFrame(list(sizes.items()), "source string, source_size bigint")
    got = {r["source"]: r["target"] for r in mixing.source_targets(df).collect()}
    order = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    open_, want, left = set(sizes), {}, float(sum(sizes.values()))
    while open_:
        share = {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
        full = {s for s in open_ if share[s] > 3 * sizes[s]}
        if not full:
            want |= share
            break
        for s in full:
            want[s] = 3.0 * sizes[s]
            left -= want[s]
        open_ -= full
    assert got.keys() == want.keys() and all(abs(got[s] - want[s]) < 1e-6 for s in want)
    assert abs(sum(got.values()) - sum(sizes.values())) < 1e-6


def test_mixture(spark):
    rng = np.random.default_rng(0)
    rows = [(i, " ".join(["w"] * int(rng.integers(1, 40))), ["a", "b", "c", None][int(rng.integers(0, 4))]) for i in range(600)]
    rows += [(1000, None, "a"), (1001, " \t", "zero"), (0, rows[0][1], rows[0][2]), (None, "null id", "b")]
    df = docs_of(spark, rows)
    got = mixing.mixture(df).toPandas()
    assert len(got) == len(rows)
    assert (got.taken <= 3 * got["size"]).all() and (got.taken % got["size"].clip(lower=1) == 0).all()
    per = got.groupby(["source_size", "target"]).taken.sum().reset_index()
    assert (abs(per.taken - per.target) <= 40).all()
    assert mixing.mixture(df.repartition(5)).toPandas().taken.sum() == got.taken.sum()
    mixed = mixing.mix_documents(df)
    assert mixed.columns == df.columns and mixed.count() >= (got.copies[got["size"] > 0].sum())
    assert mixing.mixture(df.limit(0)).count() == 0 and mixing.mix_documents(df.limit(0)).count() == 0


def test_repeated_rows_are_taken_as_planned(spark):
    rows = [(1, "one two three", "a")] * 6 + [(2, "w " * 4, "a")] * 3 + [(None, f"text {i}", "b") for i in range(9)] + [(5, "x y", "b"), (5, "x y", "c"), (5, "z y", "c")]
    df = docs_of(spark, rows)
    plan, mixed = mixing.mixture(df).toPandas(), mixing.mix_documents(df).toPandas()
    got = mixed.groupby(["doc_id", "source"], dropna=False).size().to_dict()
    want = plan[plan.copies > 0].groupby(["doc_id", "source"], dropna=False).copies.sum().to_dict()
    assert {str(k): v for k, v in got.items()} == {str(k): int(v) for k, v in want.items()}
    assert plan.copies.max() <= 3 and len(mixed) == plan[plan["size"] > 0].copies.sum()


# quality
def test_quality_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = quality.train(docs, labels)
    scored = quality.score(docs, model).select("doc_id", "score", quality.held_out(F.col("doc_id")).alias("held")).join(labels, "doc_id").where("held").toPandas()
    assert ((scored.score >= 0.3) == (scored.quality == 1)).mean() > 0.97
    ids = scored.doc_id.tolist()
    assert all(zlib.crc32(str(i).encode()) % 5 == 0 for i in ids)


def test_prior_from_positives_and_unlabelled():
    rng = np.random.default_rng(2)
    for share in (0.2, 0.5, 0.8):
        good, bad = rng.normal(1, 1, (3000, 4)), rng.normal(-1, 1, (3000, 4))
        mixed = np.concatenate([good[1000 : 1000 + int(2000 * share)], bad[: int(2000 * (1 - share))]])
        rng.shuffle(mixed)
        assert abs(quality.estimate_prior(good[:1000], mixed) - share) < 0.1


def test_quality_against_a_plain_implementation(spark):
    """The risk written out row by row falls to the same place, and scores are the model's formula."""
    import math

    rng = np.random.default_rng(3)
    p, u = rng.normal(0.7, 1, (60, 2)), rng.normal(0, 1, (90, 2))
    model = quality.fit_nnpu(p, u, 0.4, rounds=400, decay=0.0)

    def risk(w, b):
        z = lambda row: sum(max(-8, min(8, (x - m) / s)) * c for x, m, s, c in zip(row, model.mean, model.scale, w)) + b
        loss = lambda v: math.log1p(math.exp(-v)) if v > -30 else -v
        plus = sum(loss(z(r)) for r in p) / len(p)
        bracket = sum(loss(-z(r)) for r in u) / len(u) - 0.4 * sum(loss(-z(r)) for r in p) / len(p)
        return 0.4 * plus + max(0.0, bracket)

    best = risk(model.weights, model.bias)
    for dw in (-0.3, 0.3):
        assert best <= risk(model.weights + np.array([dw, 0]), model.bias) + 1e-3
        assert best <= risk(model.weights, model.bias + dw) + 1e-3
    docs = spark.createDataFrame([(i, "some words here " * i + "!" * (i % 3)) for i in range(20)], "doc_id bigint, text string")
    own = quality.QualityModel(np.zeros(quality.WIDTH), np.ones(quality.WIDTH), rng.normal(0, 1, quality.WIDTH), 0.3, 0.5)
    for r in quality.score(docs, own).collect():
        z = sum(max(-8, min(8, x)) * w for x, w in zip(quality.statistics(r.text.encode()).tolist(), own.weights)) + 0.3
        assert abs(r.score - 1 / (1 + math.exp(-max(-60, min(60, z))))) < 1e-9


def test_quality_risk_is_not_negative_and_edges(spark):
    rng = np.random.default_rng(0)
    good, bad = rng.normal(1, 1, (400, 3)), rng.normal(-1, 1, (400, 3))
    model = quality.fit_nnpu(good[:200], np.concatenate([good[200:], bad]), 0.35)
    assert (model.scores(good) >= 0.5).mean() > 0.85 and (model.scores(bad) < 0.5).mean() > 0.85
    docs = spark.createDataFrame([(1, None, 0.5), (1, None, 0.5), (None, "", 0.1), (3, "word " * 50000, 0.2)], "doc_id bigint, text string, SCORE double")
    none = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    out = quality.score(docs, quality.train(docs, none)).toPandas()
    assert out.score.between(0, 1).all() and len(out) == 4 and list(out.columns) == ["doc_id", "text", "score"]
    assert quality.drop_low_quality(docs.limit(0), none).count() == 0


# URLs
def brute_url(url):
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
    host, tail = rest[:cut], rest[cut:]
    end = min([tail.find(c) for c in "?#" if c in tail], default=len(tail))
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in host), tail[:end]


def brute_rule(host, path):
    fits = [(h, p, v) for h, p, v in url_filter.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, key=lambda r: len(r[0] + r[1]), default=None)
    return (best[0] + best[1], best[2]) if best else (None, None)


def test_urls(spark):
    urls = [None, "", "no scheme", "http://", "HTTP://WWW.Example.NET/EN/1", "https://example.net/en/5?x=1#y", "https://a.b.net", "https://a.b.net/", "ftp://xexample.net/en/", "http://É.ORG/fr/a://b", "https://casino-poker.example.com/en/1", "https://library.example.com/en/1", "https://example.com/de/", "http://x.org?/fr/", "http://x" * 3000, "https://example.com#a/de/"]
    df = spark.createDataFrame([(i, u, "h", "r") for i, u in enumerate(urls)] + [(0, None, "h", "r")], "page_id bigint, url string, host string, rule string")
    got = url_filter.judge_urls(df).toPandas()
    assert len(got) == len(urls) + 1
    for row in got.itertuples():
        host, path = brute_url(urls[row.page_id])
        rule, verdict = brute_rule(host, path)
        assert (row.host, row.path) == (host, path) and (row.rule or None) == rule
        assert row.verdict == verdict if rule else row.verdict in ("allow", "block")
    by = dict(zip(got.page_id, got.verdict))
    assert by[10] == "block" and by[11] == "allow" and by[0] == "allow"
    assert url_filter.judge_urls(df.limit(0)).count() == 0


def test_url_model_against_plain_python(spark):
    df = spark.createDataFrame([("http://ab.c/de",)], "url string")
    row = url_filter.with_host_path(df).select(url_filter.hashed_grams(F.col("host"), F.col("path"), 64).alias("g")).first()
    import xxhash

    def chained(tag, gram):  # Spark hashes columns one after the other, each seeded by the last
        return (xxhash.xxh64_intdigest(gram.encode(), xxhash.xxh64_intdigest(tag.encode(), 42)) ^ (1 << 63)) - (1 << 63)

    want = [chained(t, s[i : i + n]) % 64 for t, s in (("h", "^ab.c$"), ("p", "/de$")) for n in (3, 4) for i in range(len(s) - n + 1)]
    assert row["g"] == want
    with pytest.raises(ValueError):
        url_filter.train(url_filter.default_labels(spark), max_rows=10)


def plain_probability(url, model):
    import math

    import xxhash

    host, path = brute_url(url)
    weights, bias = model
    total, n = 0.0, 0
    for tag, text in (("h", f"^{host}$"), ("p", f"{path}$")):
        for size in url_filter.SIZES:
            for i in range(len(text) - size + 1):
                mark = xxhash.xxh64_intdigest(text[i : i + size].encode(), xxhash.xxh64_intdigest(tag.encode(), 42))
                total += weights[mark % len(weights)]
                n += 1
    return 1 / (1 + math.exp(-(bias + total / math.sqrt(max(n, 1)))))


def test_url_verdicts_against_plain_python_and_held_out(spark):
    labels = url_filter.default_labels(spark)
    held = F.pmod(F.xxhash64("url"), F.lit(5)) == 0
    model = url_filter.train(labels.where(~held))
    rest = labels.where(held).withColumn("page_id", F.monotonically_increasing_id())
    judged = url_filter.judge_urls(rest, model, rules=()).join(rest.select("page_id", "url", "label"), "page_id").toPandas()
    assert len(judged) > 60 and ((judged.verdict == "block") == (judged.label == 1)).mean() > 0.88
    for row in judged.itertuples():
        want = plain_probability(row.url, model)
        assert abs(row.p_block - want) < 1e-9 and row.verdict == ("block" if want >= 0.5 else "allow")
    long = spark.createDataFrame([(1, "http://x.example.com/" + "a/b" * 40000)], "page_id bigint, url string")
    got = url_filter.judge_urls(long, model, rules=()).first()
    assert abs(got.p_block - plain_probability("http://x.example.com/" + "a/b" * 40000, model)) < 1e-6


# search
@pytest.mark.parametrize("block", [4, 64])
def test_top_products(spark, block):
    rng = np.random.default_rng(5)
    rows = [(i, (rng.normal(size=6) * rng.choice([0.1, 1, 5])).tolist()) for i in range(150)]
    rows += [(200 + i, rows[3][1]) for i in range(20)] + [(500, None), (501, [1.0, None]), (502, [float("nan")] * 6), (503, [float("inf")] * 6), (504, []), (505, [0.0] * 6), (506, [2.0, 1.0]), (507, [1e9] * 6)]
    df = spark.createDataFrame([(k, v, 1, 2) for k, v in rows], "vec_id bigint, embedding array<double>, score int, rank int")
    got = sorted(tuple(r) for r in topk_search.top_products(df, df.where("vec_id % 10 = 0"), block=block, cell_blocks=2).collect())
    ints = {k: [int(np.floor(256 * x)) for x in v] for k, v in rows if v is not None and all(x is not None and np.isfinite(x) for x in v)}
    want = []
    for q in ints:
        if q % 10 == 0:
            scores = sorted((-sum(a * b for a, b in zip(ints[q], v)), k) for k, v in ints.items() if k != q)[:5]
            want += [(q, i + 1, k, -s) for i, (s, k) in enumerate(scores)]
    assert got == sorted(want)
    assert topk_search.top_products(df.limit(0), df.limit(0)).count() == 0
    assert topk_search.top_products(df.where("vec_id = 200"), df.where("vec_id = 200")).count() == 0


def test_coordinate_bounds_lose_nothing():
    rng = np.random.default_rng(1)
    for dims in (2, 3, 5, 8, 64):
        unit = rng.normal(size=(300, dims))
        unit[:40, 0] = -np.abs(unit[:40, 0]) * 6
        unit[40:80, dims - 1] = np.abs(unit[40:80, dims - 1]) * 6
        unit /= np.linalg.norm(unit, axis=1)[:, None]
        for query in unit:
            for cosine in (0.8, 0.9, 0.99):
                kept = set(topk_search._survivors(unit, {}, {}, query, cosine).tolist())
                assert set(np.flatnonzero(unit @ query >= cosine).tolist()) <= kept
    assert 0 in topk_search._survivors(np.array([[-0.99, 0.1411, 0.0]]), {}, {}, np.array([-0.9, 0.4359, 0.0]), 0.8)


@pytest.mark.parametrize("block,dims", [(8, 2), (40, 3), (2048, 3), (32, 16)])
def test_every_row_as_query(spark, block, dims):
    rng = np.random.default_rng(dims)
    unit = rng.normal(size=(240, dims))
    unit[:60, 0] = -np.abs(unit[:60, 0]) * 4
    unit = unit / np.linalg.norm(unit, axis=1)[:, None] * rng.choice([0.5, 1.0, 1.0, 3.0], size=240)[:, None]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(unit)], "vec_id bigint, embedding array<double>")
    got = sorted(tuple(r) for r in topk_search.top_products(df, df, block=block, cell_blocks=2).collect())
    ints = np.floor(256 * unit).astype(np.int64)
    scores = ints @ ints.T
    want = []
    for q in range(240):
        order = sorted((-scores[q, k], k) for k in range(240) if k != q)[:5]
        want += [(q, i + 1, k, -s) for i, (s, k) in enumerate(order)]
    assert got == sorted(want)


# packages
@pytest.mark.parametrize("zip64", [False, True])
def test_zip_round_trip(zip64):
    import zipfile

    sink = io.BytesIO()
    w = warc_zip.StoredZipWriter(sink, zip64)
    parts = {"archive/data.warc": [b"one", b"", b"two" * 1000], "indexes/index.cdx": [b"x"]}
    for name, data in parts.items():
        w.begin(name)
        for d in data:
            w.write(d)
        w.end()
    w.close()
    blob = sink.getvalue()
    with zipfile.ZipFile(io.BytesIO(blob)) as z:
        assert z.testzip() is None and z.read("archive/data.warc") == b"one" + b"two" * 1000
    r = warc_zip.ZipRangeReader(lambda at, n: blob[at : at + n], len(blob))
    for name, data in parts.items():
        at, n = r.locate(name)
        assert blob[at : at + n] == b"".join(data)
    with pytest.raises(ValueError):
        warc_zip.ZipRangeReader(lambda at, n: b"x" * n, 100)


def test_compressed_members_are_refused():
    import zipfile

    sink = io.BytesIO()
    with zipfile.ZipFile(sink, "w", zipfile.ZIP_DEFLATED) as z:
        z.writestr("a", "b" * 1000)
    blob = sink.getvalue()
    with pytest.raises(ValueError):
        warc_zip.ZipRangeReader(lambda at, n: blob[at : at + n], len(blob)).locate("a")


def test_archives(spark):
    big, small = "é" * 600, "s" * 999
    rows = [(1, "u", big), (5, "u\r\nx", big), (3, None, big), (4, "u", small), (6, "u", small), (7, "u", None), (8, "u", ""), (9, "u", "\r\n\r\nx" * 500), (9, "u", "\r\n\r\nx" * 500), (None, "u", big)]
    df = spark.createDataFrame([(k, u, h, 1) for k, u, h in rows], "page_id bigint, url string, html string, payload int")
    got = warc_zip.archive_pages(df, with_payload=True, most_bytes=2000).toPandas().astype(object).where(lambda x: x.notna(), None)
    data = [(k, (h or "").encode()) for k, _, h in rows]
    for row in got.itertuples():
        own = [b for k, b in data if k == row.page_id or (k is None and row.page_id is None)][0]
        top = max(k for k, b in data if b == own and k is not None)
        revisit = len(own) >= 1000 and row.page_id != top
        assert (row.payload_bytes, row.payload_digest) == (len(own), hashlib.sha1(own).hexdigest())
        assert row.record_type == ("revisit" if revisit else "response") and row.refers_to == (top if revisit else None)
        assert revisit or row.payload == own
    assert len(got) == len(rows)
    assert warc_zip.archive_pages(df.limit(0)).count() == 0


# pipeline
def test_pipeline(spark, sf_dir):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = pipeline.run(spark, sf_dir).toPandas()
    assert set(docs.columns) <= set(out.columns) and out.round_trip.all()
    assert set(out.doc_id) <= {r[0] for r in docs.select("doc_id").collect()}
    copies = out.groupby("doc_id").size()
    assert copies.max() <= 3
    norm = out.drop_duplicates("doc_id").text.map(lambda t: t.encode().lower())
    assert norm.is_unique


def written(spark, tmp_path, docs, labels):
    for name, rows, schema in (("documents", docs, "doc_id bigint, text string, lang string, source string, n_chars bigint, score double, piece_count int"), ("labels", labels, "doc_id bigint, quality int, toxic int")):
        spark.createDataFrame(rows, schema).write.parquet(str(tmp_path / f"{name}.parquet"))
    return str(tmp_path)


def test_pipeline_on_empty_null_and_clashing_tables(spark, sf_dir, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    assert pipeline.run(spark, written(spark, tmp_path / "none", [], [])).count() == 0
    rows = [(None, None, None, None, None, None, None), (1, None, "en", "a", 0, 0.5, 1), (2, "", None, "a", 0, 0.5, 1)]
    text = "The quick brown fox walks along the river and looks for a quiet place to rest before the night comes."
    rows += [(10, text, "en", "a", 1, 0.1, 1), (11, text.upper(), "en", "a", 1, 0.1, 2), (12, text + " So it does.", "en", "b", 1, 0.1, 3), (12, text + " So it does.", "en", "b", 1, 0.1, 3), (None, text + " Or not at all, as it were, if truth be told.", "en", "b", 1, None, 3)]
    out = pipeline.run(spark, written(spark, tmp_path / "odd", rows, [(10, 1, 0), (2, 0, 0)])).toPandas()
    assert list(out.columns) == ["doc_id", "text", "lang", "source", "n_chars", "score", "piece_count", "piece_ids", "n_pieces", "round_trip"]
    assert out.round_trip.all() and set(out.doc_id.dropna()) <= {10, 11, 12} and len(out)


def test_pipeline_against_its_stages_in_plain_python(spark, sf_dir):
    """Each stage's rows against brute force over its own input."""
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    from patternclust.llm import exact_dedup, simhash
    from patternclust.llm.store import materialize

    model = quality.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    kept = materialize(pipeline.STAGES[0][1](spark, docs, sf_dir), "t0")
    want = {r.doc_id for r in docs.collect() if model.scores(quality.statistics((r.text or "").encode())[None, :])[0] >= 0.3}
    assert {r.doc_id for r in kept.collect()} == want
    last = {}
    for r in kept.collect():
        last[(r.text or "").encode().lower()] = max(last.get((r.text or "").encode().lower(), -1), r.doc_id)
    alone = materialize(pipeline.STAGES[1][1](spark, kept, sf_dir), "t1")
    assert {r.doc_id for r in alone.collect()} == set(last.values()) and exact_dedup
    rows = [(r.doc_id, r.text) for r in alone.collect()]

    def shingles(text):
        w = (text or "").lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets = {k: shingles(t) for k, t in rows}
    near = materialize(pipeline.STAGES[2][1](spark, alone, sf_dir), "t2")
    left = {r.doc_id for r in near.collect()}
    ids = sorted(sets)
    alike = [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :] if sets[a] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    assert sum(b in left and a in left for a, b in alike) <= 0.5 * len(alike)  # pairs at the very limit can be missed
    for gone in set(ids) - left:  # what went had a near copy
        assert any(len(sets[gone] & sets[o]) >= 0.6 * len(sets[gone] | sets[o]) for o in ids if o != gone) and simhash
    mixed = pipeline.STAGES[3][1](spark, near, sf_dir)
    plan = mixing.mixture(near).toPandas()
    assert mixed.count() == plan[plan["size"] > 0].copies.sum() and mixed.columns == docs.columns


def test_queries_over_whole_tables(spark):
    from patternclust.llm.queries import ORACLES, QUERIES

    assert sorted(int(n[2:].split("_")[0]) for n in QUERIES) == list(range(1, 11))
    import duckdb

    sf = "/root/testdata/sf0.001"
    db = duckdb.connect()
    for t in ("documents", "embeddings", "pages"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    for name, sql in ORACLES.items():
        got, want = QUERIES[name](spark, sf).toPandas(), db.execute(sql).df()
        columns = sorted(want.columns)
        assert sorted(got.columns) == columns
        shape = lambda d: sorted(map(str, d[columns].astype(object).where(d[columns].notna(), None).map(lambda x: float(x) if isinstance(x, (int, float)) else x).values.tolist()))
        assert shape(got) == shape(want), name
