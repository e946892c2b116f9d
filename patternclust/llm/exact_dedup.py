"""Exact duplicates through counting quotient filters.

Each partition builds filters over the fingerprints of its texts, one for each slab (a range of leading
bits): the high bits (quotient) name a slot, the low bits (remainder) are kept sorted in a run of slots, counters
as digits behind their remainder, so nothing is lost and filters merge by merging sorted remainders. Each slab is merged
apart from the others. Fingerprints whose merged counter exceeds
one route their rows to verification over all bytes (length and SHA-256 of the normalised text).
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .store import materialize

#: bits that filters keep of a text's hash; two texts that share them by chance only meet at verification
FINGERPRINT_BITS = 56


class QuotientFilter:
    """Counting quotient filter over ``p_bits``-bit fingerprints, without loss among them.

    A fingerprint's high ``q_bits`` name its home slot, the rest is the remainder. Remainders of a home form a run of sorted
    slots that begins at the home slot or behind the run before it. Three bits tell the slots apart: ``occupied`` (a
    home has a run), ``run_end`` (last slot of a run) and ``digit`` (the slot holds a digit of the counter, less one,
    of the remainder before it; a remainder without digits occurs once).
    """

    def __init__(self, p_bits: int, q_bits: int, occupied: np.ndarray, run_end: np.ndarray, digit: np.ndarray, slots: np.ndarray):
        #: the bit vectors are packed, ``slots`` holds the used slots only, ``width`` bytes each
        self.p_bits, self.q_bits, self.occupied, self.run_end, self.digit, self.slots = p_bits, q_bits, occupied, run_end, digit, slots

    @property
    def width(self) -> int:
        return max(1, -(-(self.p_bits - self.q_bits) // 8))

    @staticmethod
    def homes_for(n: int, p_bits: int) -> int:
        """Bits of the home slots for ``n`` fingerprints at a load under 0.95."""
        return min(p_bits - 1, max(6, int(np.ceil(np.log2(max(1, n) / 0.95)))))

    @classmethod
    def build(cls, marks: np.ndarray, p_bits: int) -> QuotientFilter:
        return cls.of(*np.unique(marks.astype(np.uint64), return_counts=True), p_bits)

    @classmethod
    def of(cls, marks: np.ndarray, counts: np.ndarray, p_bits: int) -> QuotientFilter:
        """From different sorted fingerprints and their counters."""
        q_bits = cls.homes_for(len(marks), p_bits)
        shift = np.uint64(p_bits - q_bits)
        home, rest = (marks >> shift).astype(np.int64), marks & ((np.uint64(1) << shift) - np.uint64(1))
        width = max(1, -(-(p_bits - q_bits) // 8))
        base = np.uint64(8 * width) if width < 8 else np.uint64(63)
        more = counts.astype(np.uint64) - np.uint64(1)
        digits = np.zeros(len(marks), np.int64)
        left = more.copy()
        while left.any():
            digits += left > 0
            left >>= base
        used = np.cumsum(1 + digits)
        first = used - 1 - digits
        total = int(used[-1]) if len(used) else 0
        value, is_digit = np.zeros(total, np.uint64), np.zeros(total, bool)
        value[first] = rest
        for k in range(int(digits.max(initial=0))):
            has = digits > k
            value[first[has] + 1 + k] = (more[has] >> (base * np.uint64(k))) & ((np.uint64(1) << base) - np.uint64(1))
            is_digit[first[has] + 1 + k] = True
        ends = np.zeros(total, bool)
        last_of_home = np.r_[home[1:] != home[:-1], True] if len(home) else np.zeros(0, bool)
        ends[used[last_of_home] - 1] = True
        occupied = np.zeros(1 << q_bits, bool)
        occupied[home] = True
        slots = np.ascontiguousarray(value).view(np.uint8).reshape(-1, 8)[:, :width]
        return cls(p_bits, q_bits, np.packbits(occupied), np.packbits(ends), np.packbits(is_digit), np.ascontiguousarray(slots))

    def places(self) -> np.ndarray:
        """Slot number of each used slot: a run begins at its home or right behind the run before it."""
        homes = np.flatnonzero(np.unpackbits(self.occupied))
        ends = np.flatnonzero(np.unpackbits(self.run_end, count=len(self.slots)))
        sizes = np.diff(np.r_[-1, ends])
        before = np.cumsum(sizes) - sizes
        begin = before + np.maximum.accumulate(homes - before) if len(homes) else homes
        return np.arange(len(self.slots)) + np.repeat(begin - before, sizes)

    def items(self) -> tuple[np.ndarray, np.ndarray]:
        """``(fingerprints, counters)``, sorted."""
        n = len(self.slots)
        wide = np.zeros((n, 8), np.uint8)
        wide[:, : self.width] = self.slots
        value = wide.view(np.uint64).reshape(-1)
        ends = np.unpackbits(self.run_end, count=n).astype(bool)
        digit = np.unpackbits(self.digit, count=n).astype(bool)
        homes = np.flatnonzero(np.unpackbits(self.occupied)).astype(np.uint64)
        home = homes[np.cumsum(ends) - ends] if n else homes
        head = np.flatnonzero(~digit)
        marks = (home[head] << np.uint64(self.p_bits - self.q_bits)) | value[head]
        counts = np.ones(len(head), np.int64)
        nth = np.arange(n) - head[np.cumsum(~digit) - 1] - 1 if n else np.zeros(0, np.int64)
        base = 8 * self.width if self.width < 8 else 63
        at = np.flatnonzero(digit)
        np.add.at(counts, (np.cumsum(~digit) - 1)[at], (value[at] << (nth[at] * base).astype(np.uint64)).astype(np.int64))
        return marks, counts

    def merge(self, *others: QuotientFilter) -> QuotientFilter:
        """The filter of all inputs together, with as many home slots as it needs; counters of equal fingerprints add up."""
        parts = [x.items() for x in (self, *others)]
        marks, counts = np.concatenate([m for m, _ in parts]), np.concatenate([c for _, c in parts])
        order = np.argsort(marks, kind="stable")  # merges the sorted runs
        marks, counts = marks[order], counts[order]
        starts = np.flatnonzero(np.r_[True, marks[1:] != marks[:-1]]) if len(marks) else np.zeros(0, np.int64)
        return QuotientFilter.of(marks[starts], np.add.reduceat(counts, starts) if len(starts) else counts, self.p_bits)

    def count(self, mark: int) -> int:
        """How often a fingerprint was put in."""
        marks, counts = self.items()
        at = int(np.searchsorted(marks, np.uint64(mark)))
        return int(counts[at]) if at < len(marks) and int(marks[at]) == mark else 0

    def to_bytes(self) -> bytes:
        head = np.array([self.p_bits, self.q_bits, len(self.slots)], np.int64).tobytes()
        return head + self.occupied.tobytes() + self.run_end.tobytes() + self.digit.tobytes() + self.slots.tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> QuotientFilter:
        p_bits, q_bits, n = np.frombuffer(data, np.int64, 3).tolist()
        sizes = [-(-(1 << q_bits) // 8), -(-n // 8), -(-n // 8)]
        cuts = np.cumsum([24, *sizes])
        bits = [np.frombuffer(data, np.uint8, k, int(at)) for k, at in zip(sizes, cuts)]
        slots = np.frombuffer(data, np.uint8, offset=int(cuts[-1])).reshape(n, -1) if n else np.zeros((0, 1), np.uint8)
        return cls(p_bits, q_bits, *bits, slots)


def text_hashes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fp, n_bytes, sha)`` of each whole text, A-Z lower-cased; null counts as empty."""

    def kernel(batches):
        for batch in batches:
            texts = [(t or b"").lower() for t in batch.column(1).to_pylist()]
            marks = np.array([xxhash.xxh3_64_intdigest(t) for t in texts], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0),
                    pa.array(marks),
                    pa.array([len(t) for t in texts], pa.int64()),
                    pa.array([hashlib.sha256(t).hexdigest() for t in texts], pa.string()),
                ],
                ["doc_id", "fp", "n_bytes", "sha"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("binary").alias("t")).mapInArrow(
        kernel, f"doc_id {kind}, fp bigint, n_bytes bigint, sha string"
    )


def repeated_fingerprints(marks: DataFrame, slab_bits: int | None = None, chunk_rows: int = 1 << 20) -> DataFrame:
    """``(fp, n)`` of the fingerprints in column ``fp`` that occur more than once, by their first ``FINGERPRINT_BITS`` bits.

    Filters are built per partition and slab (a range of leading bits) and merged by slab. ``slab_bits`` None: from the row
    count, about a million fingerprints a slab, 256 slabs at least. ``fp`` holds the leading bits, the others zero.
    """
    if slab_bits is None:
        slab_bits = max(8, (max(1, marks.count()) >> 20).bit_length())
    p_bits = FINGERPRINT_BITS - slab_bits
    dropped, low = np.uint64(64 - FINGERPRINT_BITS), (np.uint64(1) << np.uint64(p_bits)) - np.uint64(1)

    def build(batches):
        held, n = [], 0
        for batch in batches:
            held.append(batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64) >> dropped)
            n += len(held[-1])
            if n >= chunk_rows:
                yield packed(held)
                held, n = [], 0
        if n:
            yield packed(held)

    def packed(held):
        marks, counts = np.unique(np.concatenate(held), return_counts=True)
        slab = (marks >> np.uint64(p_bits)).astype(np.int64)
        cuts = np.flatnonzero(np.r_[True, slab[1:] != slab[:-1], True])
        parts = [QuotientFilter.of(marks[i:j] & low, counts[i:j], p_bits).to_bytes() for i, j in zip(cuts[:-1], cuts[1:], strict=True)]
        return pa.RecordBatch.from_arrays([pa.array(slab[cuts[:-1]], pa.int64()), pa.array(parts, pa.binary())], ["slab", "part"])

    def merged(table: pa.Table) -> pa.Table:
        parts = [QuotientFilter.from_bytes(x) for x in table.column("part").to_pylist()]
        marks, counts = parts[0].merge(*parts[1:]).items()
        many = counts > 1
        whole = ((np.uint64(table.column("slab")[0].as_py()) << np.uint64(p_bits)) | marks[many]) << dropped
        return pa.table({"fp": pa.array(whole.view(np.int64)), "n": pa.array(counts[many])})

    return (
        marks.select("fp").mapInArrow(build, "slab bigint, part binary")
        .groupBy("slab").applyInArrow(merged, "fp bigint, n bigint")
    )


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, keep_id, group_size, kept, text_sha256)`` for each row of ``docs``.

    Equal texts form a group; its largest id stays. Null text counts as empty. Rows that repeat
    both id and text count twice in ``group_size`` and are both marked kept; a null id stays only
    where the whole group is null. Other columns are ignored; an empty table gives an empty result.
    """
    hashes = materialize(text_hashes(docs, id_col, text_col), "hashes")
    repeated = materialize(repeated_fingerprints(hashes), "repeated")
    leading = F.col("fp").bitwiseAND(F.lit(-1 << (64 - FINGERPRINT_BITS)))
    routed = hashes.withColumn("fp", leading).join(repeated.select("fp"), "fp", "left_semi")
    groups = materialize(
        routed.groupBy("sha", "n_bytes").agg(F.max("doc_id").alias("top"), F.count(F.lit(1)).alias("n")).where("n > 1"),
        "groups",
    )
    keep = F.when(F.col("n").isNull(), F.col("doc_id")).otherwise(F.col("top"))
    return hashes.join(groups, ["sha", "n_bytes"], "left").select(
        "doc_id",
        keep.alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("bigint").alias("group_size"),
        F.col("doc_id").eqNullSafe(keep).alias("kept"),
        F.col("sha").alias("text_sha256"),
    )


def drop_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row for each different normalised text, all columns kept; of rows that repeat id and text the first by a hash over all columns."""
    verdicts = materialize(exact_duplicates(docs, id_col, text_col).select("doc_id", "kept", "text_sha256"), "verdicts")
    gone = verdicts.where(~F.col("kept")).select(F.col("doc_id").alias("__id"), F.col("text_sha256").alias("__sha"))
    sha = F.sha2(F.translate(F.coalesce(F.col(text_col), F.lit("")), UPPER, UPPER.lower()), 256)
    lost = verdicts.where("kept").groupBy("doc_id", "text_sha256").count().where("count > 1")
    left = docs.withColumn("__text_sha", sha)
    left = left.join(gone.distinct(), left[id_col].eqNullSafe(F.col("__id")) & (F.col("__text_sha") == F.col("__sha")), "left_anti")
    if not lost.isEmpty():  # rows that repeat id and text
        own = F.xxhash64(*[F.col(f.name) for f in docs.schema.fields if "map" not in f.dataType.simpleString()])
        nth = F.row_number().over(Window.partitionBy(id_col, "__text_sha").orderBy(own))
        left = left.withColumn("__nth", nth).where("__nth = 1")
    return left.select(*docs.columns)


UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def op6_exact_dedup(spark, sf_dir: str) -> DataFrame:
    return exact_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP6_SQL = """
WITH n AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t
  FROM documents
)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, sha256(t) AS text_sha256
FROM n WINDOW w AS (PARTITION BY t)
"""
