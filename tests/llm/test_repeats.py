"""Repeated passages and substrings against brute force."""

import hashlib
import random

import numpy as np
import pytest

from patternclust.llm import repeats, substring_dedup, suffix_array_dedup

SCHEMA = "doc_id bigint, text string, doc string, spans int, start string"


def table(spark, rows):
    return spark.createDataFrame([(k, t, "x", 1, "y") for k, t in rows], SCHEMA)


def brute_words(rows, length):
    first = {}
    split = [(k, (t or "").encode().split()) for k, t in rows]
    for k, w in split:
        for i in range(len(w) - length + 1):
            g = tuple(w[i : i + length])
            first[g] = min(first.get(g, k), k)
    out = []
    for k, w in split:
        gone = set()
        for i in range(len(w) - length + 1):
            if first[tuple(w[i : i + length])] < k:
                gone |= set(range(i, i + length))
        out.append((k, len(w), len(gone), hashlib.sha256(b" ".join(x for i, x in enumerate(w) if i not in gone)).hexdigest()))
    return sorted(out)


def brute_bytes(rows, length):
    first = {}
    data = [(k, (t or "").encode()) for k, t in rows]
    for k, b in data:
        for i in range(len(b) - length + 1):
            g = b[i : i + length]
            first[g] = min(first.get(g, (k, i)), (k, i))
    out = []
    for k, b in data:
        gone = [False] * len(b)
        for i in range(len(b) - length + 1):
            if first[b[i : i + length]] < (k, i):
                gone[i : i + length] = [True] * length
        spans = sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone))
        out.append((k, len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest()))
    return sorted(out)


def corpus(seed, n=40, words=60):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(300)] + ["é", "x" * 30]
    passage = [" ".join(rng.choices(vocabulary, k=rng.randint(10, 60))) for _ in range(6)]
    rows = []
    for k in rng.sample(range(1000), n):
        parts = [" ".join(rng.choices(vocabulary, k=rng.randint(0, words)))]
        for p in rng.sample(passage, rng.randint(0, 3)):
            cut = p.split()
            if rng.random() < 0.4:
                cut[rng.randrange(len(cut))] = "edit"
            parts += [" ".join(cut), " ".join(rng.choices(vocabulary, k=rng.randint(0, 20)))]
        rows.append((k, "  ".join(parts)))
    rows += [(1001, None), (1002, ""), (1003, "a b " * 200), (1004, "b a " * 150), (1005, "z" * 1000), (1006, "z" * 120), (1007, "short text"), (2000, rows[0][1]), (3, rows[1][1]), (2001, rows[0][1] + " tail")]
    return list({k: (k, t) for k, t in rows}.values())


def test_words(spark):
    for seed in (1, 2):
        rows = corpus(seed)
        got = sorted(tuple(r) for r in substring_dedup.drop_repeated_passages(table(spark, rows)).collect())
        assert got == brute_words(rows, 13)


def test_bytes(spark):
    for seed in (3, 4):
        rows = corpus(seed)
        got = sorted(tuple(r) for r in suffix_array_dedup.drop_repeated_substrings(table(spark, rows)).collect())
        assert got == brute_bytes(rows, 100)


def some_block(rng, unit, length):
    n = np.array([rng.randint(1, 9) for _ in range(40)])
    rows = [[rng.randrange(2) + 97 for _ in range(k + length - 1)] for k in n.tolist()]
    bodies = [bytes(r) if unit == "byte" else np.array(r, np.uint64).tobytes() for r in rows]
    scheme = repeats.Scheme(length, 2, unit, unit == "byte")
    return repeats.Block(scheme, np.arange(40), np.zeros(40, np.int64), n, bodies)


def suffixes(block):
    return [tuple(block.symbols[a : a + k].tolist()) for a, k in zip(block.at.tolist(), block.size.tolist())]


def brute_nodes(block, least):
    own, nodes = suffixes(block), set()
    for t in set(own):
        for d in range(least, len(t) + 1):
            within = [i for i, u in enumerate(own) if u[:d] == t[:d]]
            after = [own[i][d] if len(own[i]) > d else ("end", i) for i in within]
            if len(set(after)) > 1:
                nodes.add((d, tuple(within)))
    return nodes


def test_suffix_arrays_and_their_intervals():
    for seed in range(5):
        block = some_block(random.Random(seed), "byte", 10)
        array, own = suffix_array_dedup.EnhancedSuffixArray(block), suffixes(block)
        texts = [own[i] for i in array.order]
        assert texts == sorted(texts)
        for i in range(1, len(texts)):
            a, b = texts[i - 1], texts[i]
            assert array.lcp[i] == next((j for j, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
        got = {(d, tuple(sorted(array.order[i:j].tolist()))) for i, j, d in zip(*suffix_array_dedup.prefix_intervals(array.lcp, 10))}
        assert got == brute_nodes(block, 10)


def test_subtrees():
    for seed in range(5):
        block = some_block(random.Random(seed), "word", 5)
        tree = substring_dedup.Subtree(block, 5)
        got = {(d, tuple(sorted(tree.order[i:j].tolist()))) for i, j, d in zip(tree.low, tree.high, tree.depth)}
        assert got == brute_nodes(block, 5) and len(got) == len(tree.low)
        left = {(d, o) for d, o in got if len({block.before[i] for i in o}) > 1 or block.before[o[0]] < 0}
        assert {(d, tuple(sorted(tree.order[i:j].tolist()))) for i, j, d in zip(*tree.maximal())} == left


def brute_covered(block):
    L, own = block.scheme.length, [t[: block.scheme.length] for t in suffixes(block)]
    ages = block.ages()
    first = {}
    for t, a in zip(own, ages):
        first[t] = min(first.get(t, a), a)
    return {(d, s) for t, a, d, s in zip(own, ages, block.doc.tolist(), block.start.tolist()) if a > first[t] and L}


def test_later_occurrences_of_maximal_repeats_are_all_that_repeats():
    for unit, solve in (("byte", suffix_array_dedup.covered_by_repeats), ("word", substring_dedup.covered_by_nodes)):
        for seed in range(20):
            block = some_block(random.Random(seed), unit, 6)
            got = {(d, s + i) for d, s, n in zip(*(x.tolist() for x in solve(block))) for i in range(n)}
            assert got == brute_covered(block)


def test_leaves_are_scanned_alike_whatever_the_batches(monkeypatch):
    import pyarrow as pa

    rng = random.Random(3)
    rows = sorted((rng.randrange(4), rng.randrange(30), rng.randrange(50), rng.randrange(9) * 100, 3) for _ in range(600))
    rows = [r for r in rows if r[0] != 2 or r[1] == 7]  # a prefix with one leaf content
    key, content, doc, start, n = map(list, zip(*rows))
    batch = pa.RecordBatch.from_pydict({"kind": pa.array([0] * len(rows), pa.int32()), "key": key, "content": content, "doc": doc, "start": start, "n": pa.array(n, pa.int32())})

    def scanned(size, within):
        scan, out = repeats.LeafScan(within), []
        for i in range(0, len(rows), size):
            out += list(scan.feed(batch.slice(i, size)))
        return [r for b in out + list(scan.close()) for r in b.to_pylist()]

    def seen(found):
        windows = {(r["doc"], r["start"] + i) for r in found if r["kind"] == repeats.COVERED for i in range(r["n"])}
        return windows, sorted((r["key"], r["doc"], r["start"], r["kind"]) for r in found if r["kind"] != repeats.COVERED)

    for within in (True, False):
        for most, wide in ((500, 1000), (5, 1000), (5, 20)):
            monkeypatch.setattr(repeats, "MOST_LEAVES", most)
            monkeypatch.setattr(repeats, "MOST_WIDE", wide)
            whole = seen(scanned(len(rows), within))
            assert all(seen(scanned(size, within)) == whole for size in (1, 7, 100))
            assert {r[3] for r in whole[1]} == ({repeats.OPEN} if most == 500 else {repeats.WIDE} if wide == 1000 else {repeats.FULL})


def test_contents_met_before_are_settled_in_the_task():
    import pyarrow as pa

    rng = random.Random(8)
    passage = " ".join(rng.choices("abcdefghij", k=60))
    ids = rng.sample(range(1000), 60)
    texts = [(" ".join(rng.choices("klmnop", k=20)) + " " + passage).encode() for _ in ids]
    batch = pa.RecordBatch.from_pydict({"doc": ids, "text": texts})
    scheme = substring_dedup.word_scheme()
    found = [r for b in repeats.records_of([batch], scheme, chunk_size=100) for r in b.to_pylist()]
    whole = [r for b in repeats.records_of([batch], scheme) for r in b.to_pylist()]
    count = lambda rows: sum(r["kind"] == repeats.OPEN for r in rows)
    assert count(whole) <= count(found) < count(whole) + 200
    one = min(ids)
    assert all(r["doc"] != one for r in found if r["kind"] == repeats.COVERED)


LINE = "shared header line of some sixty bytes that many documents hold; "


def many_contexts():
    rng = random.Random(11)
    rows = [(k, "".join(rng.choices("abcdefgh ", k=rng.randint(0, 80))) + LINE + "".join(rng.choices("abcdefgh ", k=80)) + rng.choice(["", LINE * 2])) for k in range(700)]
    return rows + [(k + 1000, rows[k][1][:150] + "x" + rows[k][1][150:]) for k in range(0, 700, 7)]


def test_wide_prefixes_give_the_same(spark):
    rows = many_contexts()
    got = sorted(tuple(r) for r in suffix_array_dedup.drop_repeated_substrings(table(spark, rows)).collect())
    assert got == brute_bytes(rows, 100)


def test_longer_prefixes_in_one_process(monkeypatch):
    """The stages one after the other without Spark, with limits that make prefixes long."""
    import pyarrow as pa

    rows = many_contexts()[::3]
    batch = pa.RecordBatch.from_pydict({"doc": [k for k, _ in rows], "text": [t.encode() for _, t in rows]})
    for scheme, solve in ((suffix_array_dedup.byte_scheme(), suffix_array_dedup.covered_by_repeats), (substring_dedup.word_scheme(5), substring_dedup.covered_by_nodes)):
        answers = []
        for most, wide in ((500, 1 << 15), (3, 1 << 15), (3, 8)):
            monkeypatch.setattr(repeats, "MOST_LEAVES", most)
            monkeypatch.setattr(repeats, "MOST_WIDE", wide)
            records = [r for b in repeats.records_of([batch], scheme) for r in b.to_pylist()]
            spans = [r for r in records if r["kind"] == repeats.COVERED]
            runs = sorted((r for r in records if r["kind"] != repeats.COVERED), key=lambda r: (r["key"], r["content"], r["doc"], r["start"]))
            scan = repeats.LeafScan(scheme.within)
            leaves = [r for b in [*scan.feed(pa.RecordBatch.from_pylist(runs, records and repeats._records(0, np.zeros(1, np.uint64), 0, np.zeros(1, np.int64), np.zeros(1), np.zeros(1)).schema)), *scan.close()] for r in b.to_pylist()]
            spans += [r for r in leaves if r["kind"] == repeats.COVERED]
            groups, texts = {}, dict(rows)
            for r in leaves:
                if r["kind"] != repeats.COVERED:
                    text = texts[r["doc"]].encode()
                    codes = np.frombuffer(text, np.uint8) if scheme.unit == "byte" else repeats.text_codes(text, "word", repeats.WordCodes()).view(np.int64)
                    for key, start, n in repeats._refined(scheme, codes, r) if r["kind"] != repeats.OPEN else ((r["key"], r["start"], r["n"]),):
                        groups.setdefault(key, []).append((r["doc"], start, n, codes[start : start + n + scheme.length - 1].tobytes()))
            for own in groups.values():
                doc, start, n, bodies = zip(*own)
                found = solve(repeats.Block(scheme, np.array(doc), np.array(start), np.array(n), list(bodies)))
                spans += [{"doc": d, "start": s, "n": k} for d, s, k in zip(*(x.tolist() for x in found))]
            answers.append({(r["doc"], r["start"] + i) for r in spans for i in range(r["n"])})
        assert answers[0] == answers[1] == answers[2] and answers[0]


def test_a_run_alone_repeats_within_itself(spark):
    line = "a line of exactly forty bytes, repeated\n"
    rule = "= " * 80
    mixed = "".join(random.Random(2).choices("abcdefgh ", k=300))
    for text in ("z" * 120, "z" * 237, "z" * 100, line * 4, rule, mixed + "-" * 150 + mixed[::-1], line + mixed[:90] + line):
        rows = [(1, text)]
        got = sorted(tuple(r) for r in suffix_array_dedup.drop_repeated_substrings(table(spark, rows)).collect())
        assert got == brute_bytes(rows, 100)


def test_partitions_change_nothing(spark):
    rows = corpus(5)
    whole = sorted(tuple(r) for r in suffix_array_dedup.drop_repeated_substrings(table(spark, rows).repartition(7)).collect())
    assert whole == brute_bytes(rows, 100)


def test_pieces_cover_every_window_once():
    scheme = suffix_array_dedup.byte_scheme()
    codes = np.arange(9 * repeats.CHUNK + 7, dtype=np.uint64)
    seen = [(first + i) for first, piece in repeats._pieces(scheme, codes) for i in (0, len(piece) - scheme.length)]
    assert seen[0] == 0 and seen[-1] == len(codes) - scheme.length
    assert all(b == a + 1 for a, b in zip(seen[1::2], seen[2::2]))


def test_null_ids_repeated_rows_and_empty(spark):
    long = " ".join(f"v{i}" for i in range(50))
    rows = [(5, long), (5, long), (None, long), (6, long)]
    got = sorted((tuple(r) for r in substring_dedup.drop_repeated_passages(table(spark, rows)).collect()), key=str)
    assert [(r[0], r[2]) for r in got] == [(5, 0), (5, 0), (6, 50), (None, 0)]
    got = sorted((tuple(r) for r in suffix_array_dedup.drop_repeated_substrings(table(spark, rows)).collect()), key=str)
    assert [(r[0], r[2]) for r in got] == [(5, 0), (5, 0), (6, len(long)), (None, 0)]
    assert substring_dedup.drop_repeated_passages(table(spark, [])).count() == 0
    assert suffix_array_dedup.drop_repeated_substrings(table(spark, [])).count() == 0
    named = spark.createDataFrame([("a", long)], "doc_id string, text string")
    for drop in (substring_dedup.drop_repeated_passages, suffix_array_dedup.drop_repeated_substrings):
        with pytest.raises(TypeError):
            drop(named)


def brute_maximal(texts, least):
    places = {}
    for k, t in texts.items():
        for i in range(len(t)):
            for j in range(i + least, len(t) + 1):
                places.setdefault(t[i:j], []).append((k, i))
    out = []
    for s, where in places.items():
        left = {texts[k][i - 1] if i else (k, "start") for k, i in where}
        right = {texts[k][i + len(s)] if i + len(s) < len(texts[k]) else (k, "end") for k, i in where}
        if len(where) > 1 and len(left) > 1 and len(right) > 1:
            out.append((s, sorted(where)))
    return sorted(out)


def test_maximal_repeats():
    rng = random.Random(9)
    for _ in range(30):
        texts = {k: bytes(rng.choices(b"abc", k=rng.randint(0, 25))) for k in range(4)}
        assert sorted(suffix_array_dedup.maximal_repeats(texts, 3)) == brute_maximal(texts, 3)
    assert suffix_array_dedup.maximal_repeats({}, 3) == []
