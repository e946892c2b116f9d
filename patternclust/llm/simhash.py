"""SimHash near-duplicate groups by multi-index hashing.

A fingerprint is cut into segments of 32 bits, and each segment's value is a key of a table. A
query enumerates the Hamming ball of radius one in each of its segments, fetches the fingerprints
that the table holds under these values, and the complete distances are verified.

``near_duplicate_groups`` links 64-bit fingerprints (two segments) within at most two bits. Two bits over
two segments leave one segment with at most one, so no link is lost. Where a table key holds more than ``CROWDED``
different fingerprints its pairs are not listed: whoever probes such a key is linked through words instead, the
fingerprint with no bit or one bit flipped. Two fingerprints are within two bits exactly if they share such a
word, and a word is met by at most 65 different fingerprints whatever the data, so links stay linear.

``similar_groups`` is for wider distances, five-word shingles and a similarity of 0.8 or more: fingerprints of 384 bits,
twelve segments, balls of radius one on both sides (so that two bits of a segment may differ) around its different values, complete distances verified.
That finds a pair with a chance that grows with its similarity: by the binomial law of the bits some 0.7 at 0.8, 0.9 at 0.85, 0.99 at 0.9.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .components import connected_components
from .store import materialize

SEGMENT_BITS = 32
#: different fingerprints under one table key beyond which pairs are not listed
CROWDED = 64
#: parts that the segments of a wide fingerprint are taken in
TURNS = 3
#: fingerprints compared at once with as many others
BLOCK = 128
#: odd multipliers that derive further words of a wide fingerprint from a shingle's hash
_STRETCH = np.random.Generator(np.random.PCG64(7)).integers(0, 2**63, 16, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _stretched(votes: np.ndarray, k: int) -> np.ndarray:
    """The ``k``-th word of each shingle: its hash itself, then mixtures of it."""
    if not k:
        return votes
    x = votes * _STRETCH[k]
    x ^= x >> np.uint64(31)
    x *= _STRETCH[-k]
    return x ^ (x >> np.uint64(29))


def simhash(text: bytes | None, width: int = 3, seed: int = 42, n_words: int = 1) -> list[int]:
    """Unsigned 64-bit words of the fingerprint of the lower-cased (A-Z) words' shingles; no words: zeros."""
    words = text.lower().split() if text else []
    if not words:
        return [0] * n_words
    joined = b" ".join(words)
    digest = xxhash.xxh64_intdigest
    if len(words) <= width:
        votes = np.array([digest(joined, seed)], dtype=np.uint64)
    else:
        sizes = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
        ends = np.cumsum(sizes + 1) - 1
        first = (ends - sizes)[: 1 - width].tolist() if width > 1 else (ends - sizes).tolist()
        last = ends[width - 1 :].tolist()
        votes = np.array([digest(joined[i:j], seed) for i, j in zip(first, last, strict=True)], dtype=np.uint64)
    out = []
    for k in range(n_words):
        set_in = np.zeros(64, dtype=np.int64)
        for at in range(0, len(votes), 1 << 16):
            block = _stretched(votes[at : at + (1 << 16)], k)
            set_in += np.unpackbits(block.view(np.uint8), bitorder="little").reshape(-1, 64).sum(axis=0, dtype=np.int64)
        out.append(int(np.packbits(2 * set_in > len(votes), bitorder="little").view(np.uint64)[0]))
    return out


def simhash64(text: bytes | None, width: int = 3, seed: int = 42) -> int:
    return simhash(text, width, seed)[0]


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, seed: int = 42, n_words: int = 1) -> DataFrame:
    """``(doc_id, fp, fp1, ...)``: signed 64-bit words of each row's fingerprint, from the whole text; null text: zeros."""
    names = ["fp", *(f"fp{k}" for k in range(1, n_words))]

    def kernel(batches):
        for batch in batches:
            marks = np.array([simhash(t, width, seed, n_words) for t in batch.column(1).to_pylist()], dtype=np.uint64).reshape(-1, n_words).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(np.ascontiguousarray(marks[:, k])) for k in range(n_words))], ["doc_id", *names])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("binary").alias("t")).mapInArrow(
        kernel, f"doc_id {kind}, " + ", ".join(f"{x} bigint" for x in names)
    )


def _flips(bits: int) -> list[int]:
    """Signed masks of the ball of radius one: no flip, then each single bit."""
    masks = [0, *(1 << b for b in range(bits))]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def _segments(words: list[str]) -> list:
    """Table keys of a fingerprint's segments: the segment's number beside its value."""
    low = F.lit((1 << SEGMENT_BITS) - 1)
    values = [v for w in words for v in (F.col(w).bitwiseAND(low), F.shiftrightunsigned(F.col(w), SEGMENT_BITS))]
    return [v.bitwiseOR(F.lit(i << SEGMENT_BITS)) for i, v in enumerate(values)]


def _spread(df: DataFrame, rows: int, each: int) -> DataFrame:
    """Enough partitions for rows that give ``each`` others."""
    return df.repartition(max(1, min(1 << 15, -(-rows * each // 1_000_000))))


def _balls(words: list[str]):
    """Array of all keys within one bit of a segment's own, as a short expression: some hundred literals in a plan weigh on the driver."""
    flips = F.array(*[F.lit(m).cast("bigint") for m in _flips(SEGMENT_BITS)])
    return F.flatten(F.transform(F.array(*_segments(words)), lambda key: F.transform(flips, lambda m: key.bitwiseXOR(m))))


def fingerprint_links(marks: DataFrame, distance: int = 2) -> DataFrame:
    """Links ``(a, b)`` between the different fingerprints ``fp`` of ``marks`` that span all pairs
    within ``distance`` (0, 1 or 2) bits."""
    if distance not in (0, 1, 2):
        raise ValueError("distance must be 0, 1 or 2: balls have radius one in two segments")
    marks = materialize(_spread(marks.select("fp").distinct(), marks.count(), 2 * (SEGMENT_BITS + 1)), "marks")
    entries = marks.select(F.explode(F.array(*_segments(["fp"]))).alias("key"), F.col("fp").alias("held"))
    probes = marks.select(F.explode(_balls(["fp"])).alias("key"), "fp")
    crowded = materialize(entries.groupBy("key").count().where(F.col("count") > CROWDED).select("key"), "crowded")
    full = not crowded.isEmpty()
    if full:
        entries, fetched = entries.join(crowded, "key", "left_anti"), probes.join(crowded, "key", "left_anti")
    else:
        fetched = probes
    verified = F.bit_count(F.col("fp").bitwiseXOR(F.col("held"))) <= distance
    found = fetched.join(entries, "key").where((F.col("fp") < F.col("held")) & verified).select(F.col("fp").alias("a"), F.col("held").alias("b"))
    if full:
        found = found.unionByName(_word_links(probes.join(crowded, "key", "left_semi").select("fp").distinct(), distance))
    return found.distinct()


def _word_links(marks: DataFrame, distance: int) -> DataFrame:
    """Links between fingerprints that share a word within one bit of both: whoever meets at a word is joined to the smallest there."""
    near = F.array(*[F.col("fp").bitwiseXOR(F.lit(m).cast("bigint")) for m in _flips(64)])
    met = marks.select("fp", F.explode(near).alias("word")).groupBy("word").agg(F.collect_list("fp").alias("met")).where(F.size("met") > 1)  # 65 at most
    if distance < 2:
        met = met.where(F.array_contains("met", F.col("word"))).select(F.col("word").alias("a"), "met")
    else:
        met = met.select(F.array_min("met").alias("a"), "met")
    found = met.select("a", F.explode("met").alias("b")).where(F.col("a") != F.col("b"))
    return found.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= distance)


def allowed_bits(similarity: float, bits: int) -> int:
    """Bits that fingerprints may differ in where the shingle sets, of equal size, share ``similarity`` of their union: the
    expected number (the angle between the sets over pi) and one standard deviation more, so that five of six pairs
    at the very limit are caught, and nearly all above it."""
    share = math.acos(2 * similarity / (1 + similarity)) / math.pi
    return int(bits * share + math.sqrt(bits * share * (1 - share)))


def _verified(pairs: DataFrame, marks: DataFrame, words: list[str], distance: int) -> DataFrame:
    """The rows of ``pairs`` whose nodes ``a`` and ``b`` lie within ``distance`` bits, complete fingerprints compared."""
    side = lambda name: marks.select(F.col("node").alias(name), F.array(*words).alias(f"{name}_words"))
    off = reduce(lambda x, y: x + y, [F.bit_count(F.col("a_words")[k].bitwiseXOR(F.col("b_words")[k])) for k in range(len(words))])
    return pairs.join(side("a"), "a").join(side("b"), "b").where(off <= distance).select(*pairs.columns)


def _onwards(roots: DataFrame, links: DataFrame) -> DataFrame:
    """``(node, root)`` of groups that ``links`` between their roots (or rows of no group) join further."""
    joined = materialize(connected_components(links).select(F.col("node").alias("root"), F.col("root").alias("top")), "joined")
    lone = joined.join(roots, joined["root"] == roots["node"], "left_anti").select(F.col("root").alias("node"), F.col("top").alias("root"))
    return materialize(roots.join(joined, "root", "left").select("node", F.coalesce("top", "root").alias("root")).unionByName(lone), "onwards")


def _met_values(values: DataFrame) -> DataFrame:
    """``(word, key, to, to_k)``: the different ``key`` of ``values(key, k, lo, hi)`` under each word that balls of several meet at, but for words met by one
    root only. Under a word only the bits flipped on the way to it are summed up, which say whose balls meet there: at most 33, whatever the data, and
    nothing is fetched again. Two values within two bits meet at two words; the smaller one (``_counts_here``) has them. ``to`` is the value at
    a word that most rows (``to_k``) hold."""
    flips = F.array(*[F.lit(m).cast("bigint") for m in _flips(SEGMENT_BITS)])
    probes = values.select("key", "k", "lo", "hi", F.posexplode(flips).alias("i", "m"))
    most = F.shiftleft("k", 6).bitwiseOR(F.col("i").cast("bigint"))
    probes = probes.select(F.col("key").bitwiseXOR(F.col("m")).alias("word"), F.expr("shiftleft(1L, i)").alias("bit"), most.alias("most"), "lo", "hi")
    met = probes.groupBy("word").agg(F.bit_or("bit").alias("mask"), F.max("most").alias("most"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    met = met.where((F.bit_count("mask") > 1) & (F.col("lo") != F.col("hi"))).withColumn("flips", flips)
    back = F.expr("array_compact(transform(flips, (m, i) -> if(getbit(mask, i) = 1, word ^ m, null)))")
    met = met.select("word", "most", back.alias("near"), F.expr("word ^ flips[int(most & 63)]").alias("to"))
    own = F.filter("near", lambda x: F.exists("near", lambda y: (x != y) & _counts_here(x, y)))
    return met.select("word", F.explode(own).alias("key"), "to", F.shiftright("most", 6).alias("to_k"))


def _counts_here(x, y):
    """Of the two words at which values ``x`` and ``y`` meet, whether ``word`` is the smaller: the other one is their difference away."""
    return F.col("word") < x.bitwiseXOR(y).bitwiseXOR(F.col("word"))


def _one_each(met: DataFrame) -> DataFrame:
    """``(key, to)``: one link for each value of ``met``, to the one near it that most rows hold; none for those that hold the most."""
    best = met.groupBy("key").agg(F.max(F.struct("to_k", F.xxhash64("to").alias("h"), "to"))["to"].alias("to"))
    return best.where("key != to")


def similar_roots(marks: DataFrame, words: list[str], distance: int) -> DataFrame:
    """``(node, root)`` of the rows of different fingerprints that chains of links within ``distance`` bits join, where linked rows have segments within two bits.

    Balls of radius one are those of the different values of a segment, not of its rows, so rows of one value do not come back
    under each of its 33 keys. One row of each value, drawn by hash, is verified against the others of its value and against the one drawn for one value near it,
    so a value or a row of it makes one pair, however many lie near it. Segments are taken some at a time, and values whose rows the earlier ones have joined are
    not met again. What is still apart within a value or between two near ones is then verified pair by pair (``_links_apart``), so no link is lost.
    """
    n, segments = marks.count(), range(2 * len(words))
    marks = materialize(_spread(marks, n, len(segments) * (SEGMENT_BITS + 1)), "marks")
    by_key, ordered = Window.partitionBy("key"), (F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    drawn = F.min(F.struct(F.xxhash64(F.shiftright("key", SEGMENT_BITS), "node").alias("h"), F.col("node").alias("n"))).over(by_key)["n"]
    facts = [drawn.alias("drawn"), F.count(F.lit(1)).over(by_key).alias("k"), F.min("root").over(by_key).alias("lo"), F.max("root").over(by_key).alias("hi")]
    roots, crowd, met = None, [], []
    for turn in range(TURNS):
        keys = [_segments(words)[i] for i in segments[turn::TURNS]]
        rooted = marks.withColumn("root", F.col("node")) if roots is None else marks.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
        own = rooted.select(F.explode(F.array(*keys)).alias("key"), "node", "root")
        own = materialize(own.select("key", "node", *facts), "values")
        heads = own.where("drawn = node")
        near = materialize(_met_values(_spread(heads.select("key", "k", "lo", "hi"), n, len(keys) * (SEGMENT_BITS + 1))), "met")
        head = heads.select(F.col("key").alias("to"), F.col("node").alias("b"))
        edges = _one_each(near).join(heads.select("key", F.col("node").alias("a")), "key").join(head, "to").select("a", "b")
        stars = own.where("drawn != node and lo != hi").select(F.col("drawn").alias("a"), F.col("node").alias("b"))
        pairs = stars.unionByName(edges).where("a != b").select(*ordered).distinct()
        links = _verified(pairs, marks, words, distance)
        links = links if roots is None else links.unionByName(roots.select(F.col("root").alias("a"), F.col("node").alias("b")))
        roots = materialize(connected_components(links), "roots")
        named = near.select("key").unionByName(heads.where("k > 2 and lo != hi").select("key")).distinct()
        crowd.append(own.select("key", "node").join(named, "key", "left_semi"))
        met.append(near.select("word", "key"))
    crowd, met = reduce(DataFrame.unionByName, crowd), reduce(DataFrame.unionByName, met)
    apart = materialize(_links_apart(crowd, met, marks, roots, words, distance), "apart")
    return roots if apart.isEmpty() else _onwards(roots, apart)


def _rooted(crowd: DataFrame, roots: DataFrame) -> DataFrame:
    """``(node, keys, root)``, a row for each node of ``crowd``: roots are looked up once a node, not once for each of its keys (12 balls of 33 at most)."""
    own = crowd.groupBy("node").agg(F.collect_list("key").alias("keys")).join(roots, "node", "left")
    return own.select("node", "keys", F.coalesce("root", "node").alias("root"))


def _links_apart(crowd: DataFrame, met: DataFrame, marks: DataFrame, roots: DataFrame, words: list[str], distance: int) -> DataFrame:
    """Links ``(a, b)`` between the roots of all rows of ``crowd`` that share a key, or whose keys meet at a word of ``met``, that are not yet
    joined and lie within ``distance`` bits.

    Words whose rows are all joined drop out before their keys are paired, and keys that hold the same rows count as one. Two keys of a row each
    are a pair to verify. Rows of the others are dealt into blocks: a joined group of ``BLOCK`` rows or more has its own, what is left
    shares some. Each pair of blocks is compared at once, but for those of one joined group.
    """
    own = materialize(_rooted(crowd, roots).select(F.explode("keys").alias("key"), "node", "root"), "rooted")
    digest = [F.bit_xor(F.xxhash64("node", F.lit(i))).alias(f"x{i}") for i in range(2)]
    spans = own.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("k"), F.min("node").alias("first"), *digest)
    spans = materialize(spans.withColumn("same", F.min("key").over(Window.partitionBy("k", "x0", "x1"))).select("key", "lo", "hi", "k", "first", "same"), "spans")
    facts = F.struct("lo", "hi", "k", "first", "same")
    held = met.join(spans, "key").groupBy("word").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.collect_list(F.struct("key", facts.alias("at"))).alias("near"))
    held = held.where("lo != hi").select("word", F.posexplode("near").alias("i", "x"), "near")  # 33 under a word at most
    later = F.filter(F.slice("near", F.col("i") + 2, F.size("near")), lambda y: _counts_here(F.col("x.key"), y["key"]))
    pairs = held.select(F.col("x.at").alias("a"), F.explode(F.transform(later, lambda y: y["at"])).alias("b"))
    pairs = pairs.where(F.least("a.lo", "b.lo") != F.greatest("a.hi", "b.hi"))
    pairs = pairs.unionByName(spans.where("k > 2 and lo != hi").select(facts.alias("a"), facts.alias("b")))
    pairs = materialize(pairs, "open")
    lone = (F.col("a.k") == 1) & (F.col("b.k") == 1)
    single = pairs.where(lone).select(F.col("a.first").alias("a"), F.col("b.first").alias("b"), F.col("a.lo").alias("x"), F.col("b.lo").alias("y"))
    single = single.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).distinct()
    single = _verified(single, marks, words, distance).select(F.col("x").alias("a"), F.col("y").alias("b"))
    open_ = pairs.where(~lone).select(F.least("a.same", "b.same").alias("a_key"), F.greatest("a.same", "b.same").alias("b_key")).distinct()
    open_ = materialize(open_, "wide")
    named = open_.select(F.col("a_key").alias("key")).unionByName(open_.select(F.col("b_key").alias("key"))).distinct()
    own = materialize(own.join(named, "key", "left_semi"), "mixed")
    sizes = own.groupBy("key", "root").agg(F.count(F.lit(1)).alias("n"))
    sizes = materialize(sizes.withColumn("kind", F.when(F.col("n") >= BLOCK, F.col("root"))), "sizes")
    kinds = sizes.groupBy("key", "kind").agg(F.ceil(F.sum("n") / BLOCK).alias("blocks")).withColumnsRenamed({"key": "k_key", "kind": "k_kind"})
    dealt = own.join(sizes.select("key", "root", "kind"), ["key", "root"])
    dealt = dealt.join(kinds, (F.col("key") == F.col("k_key")) & F.col("kind").eqNullSafe(F.col("k_kind")))
    dealt = dealt.withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks"))).join(marks.select("node", F.array(*words).alias("fp")), "node")
    blocks = materialize(dealt.groupBy("key", "kind", "block").agg(F.collect_list("root").alias("roots"), F.flatten(F.collect_list("fp")).alias("fps")), "blocks")
    a, b = blocks.alias("a"), blocks.alias("b")
    pooled = F.col("b.kind").isNull() & (F.col("a.kind").isNotNull() | (F.col("a.block") <= F.col("b.block")))
    once = F.when(F.col("a.key") == F.col("b.key"), F.coalesce(pooled | (F.col("a.kind") < F.col("b.kind")), F.lit(False)))
    sides = open_.join(a, F.col("a_key") == F.col("a.key")).join(b, F.col("b_key") == F.col("b.key"))
    sides = sides.where(once.otherwise(F.coalesce(F.col("a.kind") != F.col("b.kind"), F.lit(True))))
    width = len(words)

    def near(batches):
        for batch in batches:
            kind, out_a, out_b = batch.column(0).type.value_type, [], []
            for row in range(batch.num_rows):
                here, there = batch.column(0)[row].values, batch.column(2)[row].values
                x, y = (batch.column(c)[row].values.to_numpy().view(np.uint64).reshape(-1, width) for c in (1, 3))
                names = pa.chunked_array([here, there]).combine_chunks().dictionary_encode()
                number = names.indices.to_numpy()
                i, j = number[: len(here)], number[len(here) :]
                off = sum(np.bitwise_count(x[:, k][:, None] ^ y[:, k][None, :]).astype(np.int64) for k in range(width))
                p, q = np.nonzero((off <= distance) & (i[:, None] != j[None, :]))
                if len(p):
                    ends = np.unique(np.stack([i[p], j[q]]), axis=1)
                    out_a.append(names.dictionary.take(pa.array(ends[0])))
                    out_b.append(names.dictionary.take(pa.array(ends[1])))
            yield pa.RecordBatch.from_arrays([pa.chunked_array(out, kind).combine_chunks() for out in (out_a, out_b)], ["a", "b"])

    kind = roots.schema["root"].dataType.simpleString()
    found = sides.select("a.roots", "a.fps", F.col("b.roots").alias("b_roots"), F.col("b.fps").alias("b_fps")).mapInArrow(near, f"a {kind}, b {kind}")
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).unionByName(single).distinct()


def similar_groups(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, similarity: float = 0.8, bits: int = 384, seed: int = 42
) -> DataFrame:
    """``(doc_id, component_id)`` of the rows that have a near duplicate, their shingles alike by ``similarity`` or more.

    Equal fingerprints are alike. Rows of a null id or without words take no part; repeated rows stay repeated; other columns
    are ignored; an empty table gives an empty result.
    """
    words = ["fp", *(f"fp{k}" for k in range(1, bits // 64))]
    told = docs.where(F.col(id_col).isNotNull() & F.col(text_col).rlike(r"[^\x20\x09-\x0D]"))
    marks = materialize(fingerprints(told, id_col, text_col, width, seed, len(words)), "fingerprints")
    first = materialize(marks.groupBy(*words).agg(F.min("doc_id").alias("node"), F.count(F.lit(1)).alias("n")), "distinct")
    roots = materialize(similar_roots(first, words, allowed_bits(similarity, bits)), "near_roots")
    named = materialize(
        first.join(roots, "node", "left").where(F.col("root").isNotNull() | (F.col("n") > 1)).select(*words, F.coalesce("root", "node").alias("component_id")), "named"
    )
    return marks.join(named, words).select("doc_id", "component_id")


def near_duplicate_groups(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, distance: int = 2, seed: int = 42
) -> DataFrame:
    """``(doc_id, fingerprint, component_id)`` for each row of ``docs``.

    ``component_id`` is the smallest id reachable over links of at most ``distance`` bits. Null
    or blank texts have fingerprint zero and link like any other; a null id takes part but is
    never a component id unless its group has no other; repeated rows stay repeated; other
    columns are ignored; an empty table gives an empty result.
    """
    marks = materialize(fingerprints(docs, id_col, text_col, width, seed), "fingerprints")
    first = materialize(marks.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "distinct")
    links = fingerprint_links(first, distance)
    roots = materialize(connected_components(links), "roots")
    linked = materialize(
        first.join(roots, first["fp"] == roots["node"]).select("fp", "root", "first_id"), "linked"
    )
    smallest = materialize(linked.groupBy("root").agg(F.min("first_id").alias("component_id")), "smallest")
    grouped = linked.join(smallest, "root").select("fp", "component_id")
    alone = first.join(roots, first["fp"] == roots["node"], "left_anti").select("fp", F.col("first_id").alias("component_id"))
    named = materialize(grouped.unionByName(alone), "named")
    return marks.join(named, "fp").select(
        "doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id"
    )


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, similarity: float = 0.8) -> DataFrame:
    """``docs`` without the rows whose id is not the smallest of its group of near duplicates (``similar_groups``).

    Keeps all columns; rows of a null id or without words stay. Identity is the id: rows that share a kept id stay.
    """
    groups = similar_groups(docs, id_col, text_col, width, similarity)
    gone = materialize(groups.where(F.col("doc_id") != F.col("component_id")).select(F.col("doc_id").alias("__gone")).distinct(), "near_copies")
    return docs.join(gone, docs[id_col] == F.col("__gone"), "left_anti")


def op1_simhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return near_duplicate_groups(docs).select("doc_id", "fingerprint", "component_id")
