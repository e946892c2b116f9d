"""Suffix-array duplicates among bytes, and maximal repeat groups.

A block of suffixes becomes an enhanced suffix array: their order, and the length that neighbours share. One scan with a
stack gives the common-prefix intervals; those whose occurrences differ in the byte to their left are
the maximal repeats, each with all of its occurrences. The dedup operator judges whole corpora: ``repeats`` deals out the
suffixes that can repeat at all, and what goes is every occurrence but the first of each maximal repeat.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .repeats import Block, Scheme, removal, with_spans
from .store import materialize, small_batches


def byte_scheme(length: int = 100) -> Scheme:
    gram = 1
    while 2 * gram <= max(1, length // 2):
        gram *= 2
    return Scheme(length, gram, "byte", within=True)


class EnhancedSuffixArray:
    """Suffixes of a block in lexicographic order, one that is the beginning of another before it; ``lcp[i]`` is shared by
    ``order[i - 1]`` and ``order[i]``.

    Groups of equal beginnings are sorted by their next eight bytes until all are told apart.
    """

    def __init__(self, block: Block):
        self.block, self.order, self.lcp = block, np.arange(len(block)), np.zeros(len(block), np.int64)
        padded = np.r_[block.symbols, np.zeros(8, np.uint8)]
        eight = np.zeros(len(block.symbols) + 1, np.uint64)
        for j in range(8):
            eight = (eight << np.uint64(8)) | padded[j : j + len(eight)]
        at, group, level = self.order.copy(), np.zeros(len(block), np.int64), 0
        while len(at):
            own = self.order[at]
            left = np.clip(block.size[own] - 8 * level, 0, 8)
            word = eight[np.minimum(block.at[own] + 8 * level, len(eight) - 1)]
            short = left < 8
            if short.any():
                drop = (8 * (8 - np.maximum(left, 1))).astype(np.uint64)
                word = np.where(left > 0, word >> drop << drop, np.uint64(0))
                by = np.lexsort((left, word, group))
            else:
                by = np.lexsort((word, group))
            own, word, left = own[by], word[by], left[by]
            self.order[at] = own
            head = np.r_[True, group[1:] != group[:-1]]
            split = ~head & np.r_[False, (word[1:] != word[:-1]) | (left[1:] != left[:-1])]
            rows = np.flatnonzero(split)
            differ = word[rows] ^ word[rows - 1]
            alike = sum((differ < (np.uint64(1) << np.uint64(8 * k))).astype(np.int64) for k in range(8))
            self.lcp[at[rows]] = 8 * level + np.minimum(alike, np.minimum(left[rows], left[rows - 1]))
            ended = ~head & ~split & (left < 8)
            self.lcp[at[ended]] = block.size[own[ended]]
            group = np.cumsum(head | split) - 1
            shared = (np.bincount(group)[group] > 1) & (left == 8)
            at, group, level = at[shared], group[shared], level + 1

    def maximal(self, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``low, high, depth`` of the intervals ``least`` deep or more whose occurrences have different left neighbours."""
        low, high, depth = prefix_intervals(self.lcp, least)
        wide = self.block.diverse(self.order, low, high)
        return low[wide], high[wide], depth[wide]


def prefix_intervals(lcp: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``low, high, depth`` of the intervals of the tree at least ``least`` deep, by one scan with a stack over the deep entries."""
    deep = np.flatnonzero(lcp >= least)
    if not len(deep):
        return (np.zeros(0, np.int64),) * 3
    found: list[tuple[int, int, int]] = []
    stack: list[tuple[int, int]] = []
    last = -1
    for i, depth in zip([*deep.tolist(), len(lcp) + 1], [*lcp[deep].tolist(), 0], strict=True):
        low = i - 1
        if low != last:  # an entry less deep lies between
            while stack:
                deeper, begin = stack.pop()
                found.append((begin, last + 1, deeper))
        while stack and stack[-1][0] > depth:
            deeper, low = stack.pop()
            found.append((low, i, deeper))
        if not stack or stack[-1][0] < depth:
            stack.append((depth, low))
        last = i
    out = np.array(found, np.int64)
    return out[:, 0], out[:, 1], out[:, 2]


def covered_by_repeats(block: Block):
    """Windows in the later occurrences of the maximal repeats of a block."""
    array = EnhancedSuffixArray(block)
    return block.covered_by(array.order, *array.maximal(block.scheme.length))


def maximal_repeats(texts: dict[int, bytes], least: int) -> list[tuple[bytes, list[tuple[int, int]]]]:
    """Every maximal repeat of ``least`` bytes or more among the texts of one block, with all occurrences ``(id, offset)``; no match crosses texts."""
    long = {k: t for k, t in texts.items() if len(t) >= least}
    if not long:
        return []
    ids, sizes = np.array(list(long), np.int64), np.array([len(t) - least + 1 for t in long.values()])
    block = Block(Scheme(least, 1, "byte", within=True), ids, np.zeros(len(ids), np.int64), sizes, list(long.values()))
    array = EnhancedSuffixArray(block)
    found = []
    for low, high, depth in zip(*array.maximal(least), strict=True):
        own = array.order[low:high]
        text = block.symbols[block.at[own[0]] : block.at[own[0]] + depth].tobytes()
        found.append((text, sorted(zip(block.doc[own].tolist(), block.start[own].tolist(), strict=True))))
    return found


def kept_bytes(text: bytes | None, spans, scheme: Scheme):
    """``(bytes, removed, maximal removed runs, kept bytes)``"""
    text = text or b""
    gone = removal(scheme, len(text), spans)
    runs = int((gone & ~np.r_[False, gone[:-1]]).sum()) if len(text) else 0
    kept = np.frombuffer(text, np.uint8)[~gone].tobytes() if runs else text
    return len(text), len(text) - len(kept), runs, kept


def drop_repeated_substrings(docs: DataFrame, length: int = 100, id_col: str = "doc_id", text_col: str = "text", with_bytes: bool = False) -> DataFrame:
    """``(doc_id, n_bytes, n_removed, n_spans, kept_sha256[, kept])`` for each row of ``docs``.

    A byte goes where a window of ``length`` bytes over it also starts earlier: in a document with a smaller id,
    or earlier in its own. Null text counts as empty; rows of a null id keep all bytes; rows that share an id
    count as one document (equal places in them are not earlier than each other, and what goes from one goes from all);
    ids are whole numbers, another type is an error.
    Other columns are ignored; an empty table gives an empty result.
    """
    scheme = byte_scheme(length)
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + ["kept"] * with_bytes

    def kernel(batches):
        for batch in batches:
            rows = [kept_bytes(t, s, scheme) for t, s in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
            arrays = [batch.column(0), *(pa.array([r[k] for r in rows], pa.int64()) for k in range(3)), pa.array([hashlib.sha256(r[3]).hexdigest() for r in rows], pa.string())]
            yield pa.RecordBatch.from_arrays(arrays + [pa.array([r[3] for r in rows], pa.binary())] * with_bytes, names)

    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"doc_id {kind}, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + ", kept binary" * with_bytes
    judged = with_spans(docs, scheme, covered_by_repeats, id_col, text_col).mapInArrow(kernel, schema)
    with small_batches(docs.sparkSession):
        return materialize(judged, "judged")


def op9_suffix_array_dedup(spark, sf_dir: str) -> DataFrame:
    return drop_repeated_substrings(spark.read.parquet(f"{sf_dir}/documents.parquet"))
