"""SimHash groups and exact duplicates against brute force."""

import hashlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from patternclust.llm import exact_dedup, simhash
from patternclust.llm.components import connected_components

SCHEMA = "doc_id bigint, text string, fp string, n int, component_id string"


def brute_fp(text):
    words = (text or "").encode().lower().split()
    grams = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) > 3 else [b" ".join(words)] if words else []
    out = 0
    for bit in range(64):
        if 2 * sum(xxhash.xxh64_intdigest(g, 42) >> bit & 1 for g in grams) > len(grams):
            out |= 1 << bit
    return out


def brute_groups(rows):
    marks = [brute_fp(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if (marks[i] ^ marks[j]).bit_count() <= 2:
                root[find(i)] = find(j)
    least = {}
    for i, (k, _) in enumerate(rows):
        r = find(i)
        least[r] = min((x for x in (least.get(r), k) if x is not None), default=None)
    return sorted(((k, f"{marks[i]:016x}", least[find(i)]) for i, (k, _) in enumerate(rows)), key=str)


def table(spark, rows):
    return spark.createDataFrame([(k, t, "x", 1, "y") for k, t in rows], SCHEMA)


def sample(spark, sf_dir, n=120):
    return [tuple(r) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").orderBy("doc_id").limit(n).collect()]


def test_simhash_groups(spark, sf_dir):
    base = " ".join(f"w{i}" for i in range(400))
    rows = sample(spark, sf_dir) + [(900, base), (901, base.replace("w7 ", "q7 ")), (902, base.upper()), (903, None), (904, " \t"), (904, " \t"), (None, base), (905, "one"), (906, "one two"), (907, "long " * 30000)]
    got = sorted((tuple(r) for r in simhash.near_duplicate_groups(table(spark, rows)).collect()), key=str)
    assert got == brute_groups(rows)


def test_simhash_matches_native_hash(spark):
    df = spark.createDataFrame([("ab cd ef",)], "s string")
    assert df.select(F.xxhash64("s")).first()[0] & (2**64 - 1) == xxhash.xxh64_intdigest(b"ab cd ef", 42)


def test_links_span_all_close_pairs(spark):
    rng = np.random.default_rng(3)
    centre = int(rng.integers(0, 2**63))
    marks = {centre ^ int(sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 4), replace=False))) for _ in range(150)}
    marks = [m - (1 << 64) if m >> 63 else m for m in marks]
    links = simhash.fingerprint_links(spark.createDataFrame([(m,) for m in marks], "fp bigint"))
    roots = {r["node"]: r["root"] for r in connected_components(links).collect()}
    want = {m: m for m in marks}
    changed = True
    while changed:
        changed = False
        for a in marks:
            for b in marks:
                if ((a ^ b) & (2**64 - 1)).bit_count() <= 2 and want[b] < want[a]:
                    want[a], changed = want[b], True
    assert {m: roots.get(m, m) for m in marks} == want


def test_components_chain_and_empty(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (7, 7)], "a bigint, b bigint")
    got = {r["node"]: r["root"] for r in connected_components(chain).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100}
    assert connected_components(chain.limit(0)).count() == 0


def test_exact_duplicates(spark, sf_dir):
    rows = sample(spark, sf_dir) + [(900, "Abc"), (901, "aBC"), (902, None), (903, ""), (904, "É"), (905, "é"), (905, "é"), (906, "z" * 200000)]
    got = sorted(tuple(r) for r in exact_dedup.exact_duplicates(table(spark, rows)).collect())
    norm = [(k, (t or "").encode().lower()) for k, t in rows]
    want = []
    for k, t in norm:
        same = [j for j, u in norm if u == t]
        want.append((k, max(same), len(same), k == max(same), hashlib.sha256(t).hexdigest()))
    assert got == sorted(want)
    left = exact_dedup.drop_exact_duplicates(table(spark, rows))
    assert left.columns == ["doc_id", "text", "fp", "n", "component_id"]
    assert left.count() == len({t for _, t in norm})


def test_empty_tables(spark):
    none = table(spark, [])
    assert simhash.near_duplicate_groups(none).count() == 0
    assert exact_dedup.exact_duplicates(none).count() == 0
    assert simhash.drop_near_duplicates(none).count() == 0 and exact_dedup.drop_exact_duplicates(none).count() == 0


def test_quotient_filters_merge_without_loss():
    rng = np.random.default_rng(1)
    Filter = exact_dedup.QuotientFilter
    for p_bits, spread, n in ((48, 50, 500), (48, 2**48, 5000), (20, 2**20, 3000), (12, 4, 70_000), (56, 2**56, 0)):
        marks = rng.integers(0, spread, n).astype(np.uint64) << np.uint64(0 if spread > 50 else 3)
        parts = [Filter.build(x, p_bits) for x in np.array_split(marks, 7)]
        whole = parts[0].merge(*[Filter.from_bytes(p.to_bytes()) for p in parts[1:]])
        values, counts = np.unique(marks, return_counts=True)
        got, n_got = whole.items()
        assert (got == values).all() and (n_got == counts).all()
        places = whole.places()
        assert (np.diff(places) > 0).all()
        homes = np.repeat((values >> np.uint64(p_bits - whole.q_bits)).astype(np.int64), 1)
        digit = np.unpackbits(whole.digit, count=len(whole.slots)).astype(bool)
        assert (places[~digit] >= homes).all()
        for v in values[:20].tolist():
            assert whole.count(v) == counts[values == v][0]
        assert whole.count(2**p_bits - 1) == int(counts[values == np.uint64(2**p_bits - 1)].sum())
    alone = Filter.build(rng.integers(0, 2**48, 4096).astype(np.uint64), 48)
    assert len(alone.to_bytes()) < 4096 * 8  # smaller than the plain hashes


def test_leading_bits_that_meet_by_chance_are_told_apart(spark, monkeypatch):
    monkeypatch.setattr(exact_dedup, "FINGERPRINT_BITS", 10)
    rows = [(i, f"text {i % 300}") for i in range(900)]
    got = exact_dedup.exact_duplicates(table(spark, rows)).toPandas()
    assert (got.group_size == 3).all() and got.kept.sum() == 300


def test_crowded_keys_lose_no_link(spark, monkeypatch):
    monkeypatch.setattr(simhash, "CROWDED", 5)
    test_links_span_all_close_pairs(spark)


def test_similar_groups(spark):
    rng = np.random.default_rng(4)
    vocabulary = [f"w{i}" for i in range(5000)]
    rows, want = [], {}
    for k in range(0, 120, 4):
        base = rng.choice(vocabulary, 300).tolist()
        for j in range(4):
            words = list(base)
            for at in rng.choice(300, j * 2, replace=False):  # j * 2 edited words: similarity 1, 0.94, 0.88, 0.82 or so
                words[at] = f"edit{k}{j}{at}"
            rows.append((k + j, " ".join(words)))
            want[k + j] = k
    rows += [(900, None), (901, ""), (902, "one"), (903, "one"), (None, rows[0][1]), (0, rows[0][1])]
    rows += [(1000 + i, " ".join(rng.choice(vocabulary, 200))) for i in range(100)]
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar_groups(table(spark, rows)).collect()}
    right = sum(got.get(k) == v for k, v in want.items())
    assert right >= 0.9 * len(want) and got[902] == got[903] == 902 and not set(got) - set(want) - {902, 903}
    left = simhash.drop_near_duplicates(table(spark, rows))
    assert left.columns == ["doc_id", "text", "fp", "n", "component_id"]
    ids = [r["doc_id"] for r in left.collect()]
    assert {900, 901, 902, None, 0, *range(1000, 1100)} <= set(ids) and 903 not in ids and ids.count(0) == 2


def test_pairs_are_found_by_similarity(spark):
    """Planted pairs at several similarities: nearly all from 0.88 on, most at the limit of 0.8."""
    rng = np.random.default_rng(6)
    vocabulary = [f"w{i}" for i in range(5000)]
    rows, edits = [], (2, 4, 7)  # of 300 words: similarity 0.94, 0.88, 0.8 or so
    for kind, n in enumerate(edits):
        for k in range(60):
            base = rng.choice(vocabulary, 300).tolist()
            words = list(base)
            for at in rng.choice(300, n, replace=False):
                words[at] = f"edit{at}"
            rows += [(kind * 1000 + 2 * k, " ".join(base)), (kind * 1000 + 2 * k + 1, " ".join(words))]
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar_groups(table(spark, rows)).collect()}
    found = [sum(got.get(kind * 1000 + 2 * k + 1) == kind * 1000 + 2 * k for k in range(60)) / 60 for kind in range(3)]
    print("found by similarity", found)
    assert found[0] >= 0.97 and found[1] >= 0.9 and found[2] >= 0.5
    assert all(c // 2 == d // 2 for d, c in got.items())


def test_a_large_group_of_near_copies_is_one(spark):
    rng = np.random.default_rng(5)
    base = [f"w{i}" for i in range(200)]
    rows = []
    for k in range(150):
        words = list(base)
        words[int(rng.integers(0, 200))] = f"edit{k}"
        rows.append((k, " ".join(words)))
    got = simhash.similar_groups(table(spark, rows)).toPandas()
    assert len(got) == 150 and (got.component_id == 0).all()
    assert simhash.allowed_bits(0.8, 256) == 44 and simhash.allowed_bits(0.8, 384) == 65 and simhash.similar_groups(table(spark, [])).count() == 0


@pytest.mark.parametrize("n_pairs", [5, 30, 200])
def test_no_link_is_lost_under_a_crowded_key(spark, n_pairs):
    """Pairs whose only common segment is one that all share: each is found, whoever is drawn."""
    rng, rows, names = np.random.default_rng(3), [], ["fp", *(f"fp{k}" for k in range(1, 6))]
    for i in range(n_pairs):
        one = rng.integers(0, 1 << 32, 12, dtype=np.uint64)
        one[0] = 77
        two = one ^ np.uint64(0b10101)
        two[0] = 77
        rows += [(2 * i + j, *((x[0::2] | (x[1::2] << np.uint64(32))).view(np.int64).tolist())) for j, x in enumerate((one, two))]
    near = [one] * 300 if n_pairs == 200 else []  # and a large group that is joined at once
    for i, x in enumerate(near):
        y = x.copy()
        y[1 + i % 11] ^= np.uint64(1 << (i // 11))
        rows.append((1000 + i, *((y[0::2] | (y[1::2] << np.uint64(32))).view(np.int64).tolist())))
    marks = spark.createDataFrame(rows, "node bigint, " + ", ".join(f"{x} bigint" for x in names))
    found = {r["node"]: r["root"] for r in simhash.similar_roots(marks, names, 65).collect()}
    assert found == {r[0]: 2 * n_pairs - 2 if r[0] >= 1000 else r[0] // 2 * 2 for r in rows}


def test_roots_are_looked_up_once_a_node(spark):
    crowd = spark.createDataFrame([(key, node) for key in range(40) for node in range(30)], "key bigint, node bigint")
    roots = spark.createDataFrame([(n, n % 3) for n in range(20)], "node bigint, root bigint")
    got = simhash._rooted(crowd, roots).collect()
    assert len(got) == 30  # not 1,200, one for each key of a node
    assert all(sorted(r["keys"]) == list(range(40)) and r["root"] == (r["node"] % 3 if r["node"] < 20 else r["node"]) for r in got)


def test_a_near_group_does_not_come_back_under_each_shared_key(spark, monkeypatch):
    """300 rows of one group that share some 300 table keys: no table between steps grows with both."""
    names, rows, counts = ["fp", *(f"fp{k}" for k in range(1, 6))], [], {}
    base = np.random.default_rng(8).integers(0, 1 << 32, 12, dtype=np.uint64)
    for i in range(300):
        x = base.copy()
        x[i % 12] ^= np.uint64(1 << (i // 12))
        rows.append((i, *((x[0::2] | (x[1::2] << np.uint64(32))).view(np.int64).tolist())))
    marks = spark.createDataFrame(rows, "node bigint, " + ", ".join(f"{x} bigint" for x in names))
    kept = simhash.materialize

    def counted(df, label):
        out = kept(df, label)
        counts[label] = max(counts.get(label, 0), out.count())
        return out

    monkeypatch.setattr(simhash, "materialize", counted)
    found = {r["node"]: r["root"] for r in simhash.similar_roots(marks, names, 65).collect()}
    assert found == dict.fromkeys(range(300), 0)
    assert max(counts.values()) <= 12 * 300, counts


def test_near_values_of_a_group_make_a_pair_each(spark, monkeypatch):
    """400 rows of one group whose values of every segment lie within four bits, some 60 within two bits of each: pairs grow with the values, not with their square."""
    names, rows, counts = ["fp", *(f"fp{k}" for k in range(1, 6))], [], []
    rng = np.random.default_rng(11)
    base = rng.integers(0, 1 << 32, 12, dtype=np.uint64)
    flips = np.array([(1 << i) | (1 << j) for i in range(32) for j in range(i)], dtype=np.uint64)
    orders = np.stack([rng.permutation(flips) for _ in range(12)])
    for i in range(400):
        x = base ^ orders[:, i]
        rows.append((i, *((x[0::2] | (x[1::2] << np.uint64(32))).view(np.int64).tolist())))
    marks = spark.createDataFrame(rows, "node bigint, " + ", ".join(f"{x} bigint" for x in names))
    verified = simhash._verified

    def counted(pairs, *args):
        counts.append(pairs.count())
        return verified(pairs, *args)

    monkeypatch.setattr(simhash, "_verified", counted)
    found = {r["node"]: r["root"] for r in simhash.similar_roots(marks, names, 65).collect()}
    assert found == dict.fromkeys(range(400), 0)
    assert sum(counts) <= 12 * 400, counts
