"""Substring duplicates among words: long passages that an earlier document has already.

The suffixes of the word sequences are split by prefixes into groups that fit in memory, and a prefix that too many share
is made longer (see ``repeats``). Each group becomes a suffix subtree, built from its prefix down, one word a
level; its deep internal nodes with different left neighbours are the maximal repeats, whose later occurrences go.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .repeats import Block, Scheme, removal, with_spans
from .store import materialize, small_batches


def word_scheme(length: int = 13) -> Scheme:
    return Scheme(length, 5 if length >= 9 else max(1, length // 2), "word", within=False)


class Subtree:
    """The suffix subtree of a block: internal nodes as ``low``, ``high`` (their leaves in ``order``) and ``depth`` in symbols.

    Built level by level: groups of suffixes that share a prefix are split by their next symbol; a group that splits is an
    internal node, one that does not is the inside of an edge. A suffix that ends is a leaf of its own.
    """

    def __init__(self, block: Block, least: int):
        self.block, self.order = block, np.arange(len(block))
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        at, group, level = self.order.copy(), np.zeros(len(block), np.int64), 0
        while len(at):
            own = self.order[at]
            goes_on = block.size[own] > level
            symbol = np.where(goes_on, block.symbols[np.minimum(block.at[own] + level, len(block.symbols) - 1)], 0)
            by = np.lexsort((symbol, goes_on, group) if level >= least else (symbol, group))
            self.order[at] = own[by]
            symbol, goes_on = symbol[by], goes_on[by]
            head = np.r_[True, group[1:] != group[:-1]]
            child = head | np.r_[True, symbol[1:] != symbol[:-1]] | ~goes_on
            if level >= least:
                first = np.flatnonzero(head)
                node = np.add.reduceat(child.astype(np.int64), first) > 1
                size = np.diff(np.r_[first, len(at)])
                found.append((at[first[node]], at[first[node]] + size[node], np.full(int(node.sum()), level)))
            group = np.cumsum(child) - 1
            shared = np.bincount(group)[group] > 1
            at, group, level = at[shared], group[shared], level + 1
        nothing = (np.zeros(0, np.int64),) * 3
        self.low, self.high, self.depth = (np.concatenate(x) for x in zip(nothing, *found, strict=True))

    def maximal(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``low, high, depth`` of the nodes whose leaves have different left neighbours."""
        wide = self.block.diverse(self.order, self.low, self.high)
        return self.low[wide], self.high[wide], self.depth[wide]


def covered_by_nodes(block: Block):
    """Windows in the later occurrences of the maximal repeats of a block."""
    tree = Subtree(block, block.scheme.length)
    return block.covered_by(tree.order, *tree.maximal())


def kept_words(text: bytes | None, spans, scheme: Scheme):
    """``(words, removed, kept text)``"""
    words = (text or b"").split()
    gone = removal(scheme, len(words), spans)
    return len(words), int(gone.sum()), b" ".join(w for w, g in zip(words, gone.tolist(), strict=True) if not g)


def drop_repeated_passages(docs: DataFrame, length: int = 13, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """``(doc_id, n_words, n_removed, kept_sha256[, kept])`` for each row of ``docs``.

    A word goes where a window of ``length`` words over it also begins in a document with a smaller id. Null text
    has no words; rows of a null id keep all words; rows that share an id count as one document (what goes from
    one goes from all at the same places); ids are whole numbers, another type is an error. Other columns are ignored; an empty table gives an empty result.
    """
    scheme = word_scheme(length)
    names = ["doc_id", "n_words", "n_removed", "kept_sha256"] + ["kept"] * with_text

    def kernel(batches):
        for batch in batches:
            rows = [kept_words(t, s, scheme) for t, s in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
            arrays = [
                batch.column(0), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()),
                pa.array([hashlib.sha256(r[2]).hexdigest() for r in rows], pa.string()),
            ]
            yield pa.RecordBatch.from_arrays(arrays + [pa.array([r[2].decode("utf-8", "replace") for r in rows], pa.string())] * with_text, names)

    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"doc_id {kind}, n_words bigint, n_removed bigint, kept_sha256 string" + ", kept string" * with_text
    judged = with_spans(docs, scheme, covered_by_nodes, id_col, text_col).mapInArrow(kernel, schema)
    with small_batches(docs.sparkSession):
        return materialize(judged, "judged")


def op2_substring_dedup(spark, sf_dir: str) -> DataFrame:
    return drop_repeated_passages(spark.read.parquet(f"{sf_dir}/documents.parquet"))
