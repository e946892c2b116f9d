"""Windows of a fixed length that occur again: how suffixes reach the blocks that both substring operators solve.

A document is a sequence of symbols (bytes, or words by their hash). All of its windows of
``length`` symbols are judged, but few records travel:

1. *Sampled suffixes.* Each window elects the smallest hash among its ``gram``-symbol substrings;
   neighbours that elect the same form a run. Equal windows elect the same substring wherever they
   are, so whatever repeats meets under it: it is the prefix by which suffixes are dealt out.
   Runs of equal content are one leaf with several occurrences: all but the first
   are covered whole. A prefix with one leaf is done; one with several is branching.
   Where a run holds its elected value more than once (a short period), its own windows are compared on the spot.
2. *Suffixes under branching prefixes.* Only there the symbols themselves travel, dealt out by the same
   prefix, or, where too many leaves share it, by a longer one (``WIDE``), up to the whole window (``FULL``). What
   arrives is a ``Block``, which the operators solve each in its own way: a suffix subtree built from its prefix down
   (``substring_dedup``), an enhanced suffix array with its interval tree (``suffix_array_dedup``).

Runs that repeat within a chunk of a task are settled there, and contents that a task has met before are settled against a
table of fixed size, so a passage in a third of all documents meets as a few records per task.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from .store import materialize, release_shuffles, small_batches

CHUNK = 1 << 19
_RNG = np.random.Generator(np.random.PCG64(20240229))
BYTE_CODES = _RNG.integers(0, 2**64, 256, dtype=np.uint64)
_ODD = _RNG.integers(0, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
NO_TEXT = np.zeros(0, np.uint64)


@dataclass(frozen=True)
class Scheme:
    """What repeats: ``length`` symbols; ``unit`` byte or word; ``within``: also within one document."""

    length: int
    gram: int
    unit: str
    within: bool

    @property
    def span(self) -> int:
        """Windows that can share an elected value at one place."""
        return self.length - self.gram + 1


class WordCodes(dict):
    """64-bit codes of words, remembered up to a bound."""

    def of(self, words: list[bytes]) -> np.ndarray:
        if len(self) > 100_000:
            self.clear()
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))

    def __missing__(self, word: bytes) -> int:
        self[word] = code = xxhash.xxh3_64_intdigest(word)
        return code


def _mix(x: np.ndarray) -> np.ndarray:
    x ^= x >> np.uint64(29)
    x *= _ODD[0]
    x ^= x >> np.uint64(32)
    return x


def ladder(codes: np.ndarray, top: int) -> dict[int, np.ndarray]:
    """Hashes of the 1, 2, 4, ... symbols that begin at each position, up to ``top``."""
    rungs, m = {1: codes}, 1
    while 2 * m <= top:
        a = rungs[m]
        rungs[2 * m] = _mix(a[: max(0, len(a) - m)] * _ODD[m.bit_length()] + a[m:])
        m *= 2
    return rungs


def digest(rungs: dict[int, np.ndarray], length: int, at: np.ndarray | None = None) -> np.ndarray:
    """Hash of the ``length`` symbols at the positions ``at`` (None: at all)."""
    n = len(rungs[1]) - length + 1
    if n <= 0:
        return NO_TEXT
    out, offset = None, 0
    for m in sorted((m for m in rungs if m & length), reverse=True):
        part = rungs[m][offset : offset + n] if at is None else rungs[m][at + offset]
        out = part.copy() if out is None else _mix(out * _ODD[40] + part)
        offset += m
    return out


def sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    size = 1
    while 2 * size <= width:
        values = np.minimum(values[:-size], values[size:])
        size *= 2
    return np.minimum(values[: len(values) - (width - size)], values[width - size :]) if size < width else values


def _each(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``(i, nth)``: every i as often as its count says, numbered from 0."""
    return np.repeat(np.arange(len(counts)), counts), np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)


class Chunk:
    """Some documents' symbols end to end, with the places where windows may begin."""

    def __init__(self, scheme: Scheme):
        self.scheme, self.parts, self.ids, self.firsts, self.sizes, self.total = scheme, [], [], [], [], 0
        #: document and place of windows that begin earlier in their own run, known with the runs
        self.again = (np.zeros(0, np.int64),) * 2

    def add(self, doc_id: int, codes: np.ndarray, first: int = 0) -> None:
        self.parts.append(codes)
        self.ids.append(doc_id)
        self.firsts.append(first)
        self.sizes.append(len(codes))
        self.total += len(codes)

    def open(self) -> None:
        self.codes = np.concatenate(self.parts)
        self.starts = np.cumsum([0] + self.sizes)[:-1]
        sizes = np.array(self.sizes)
        self.windows = np.maximum(0, sizes - self.scheme.length + 1)
        self.rungs = ladder(self.codes, self.scheme.length)

    def runs(self):
        """``key, content, doc, start, n``: windows start .. start + n - 1 of doc elect the same."""
        L, span = self.scheme.length, self.scheme.span
        if len(self.codes) < L:
            return (NO_TEXT, NO_TEXT, *(np.zeros(0, np.int64),) * 3)
        grams = digest(self.rungs, self.scheme.gram)
        elected = sliding_min(grams, span)
        breaks = np.empty(len(elected), bool)
        breaks[0] = True
        np.not_equal(elected[1:], elected[:-1], out=breaks[1:])
        inside = self.windows > 0
        breaks[self.starts[inside]] = True
        ends = self.starts[inside] + self.windows[inside]
        breaks[ends[ends < len(elected)]] = True
        begin = np.flatnonzero(breaks)
        size = np.diff(np.r_[begin, len(elected)])
        part = np.searchsorted(self.starts, begin, side="right") - 1
        real = begin - self.starts[part] < self.windows[part]
        begin, size, part = begin[real], size[real], part[real]
        if (size > span).any():  # an elected value that comes again and again: cut
            pieces = -(-size // span)
            nth = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
            begin, left, part = np.repeat(begin, pieces) + nth * span, np.repeat(size, pieces) - nth * span, np.repeat(part, pieces)
            size = np.minimum(left, span)
        content = digest(self.rungs, L, begin) * _ODD[41] + digest(self.rungs, L, begin + size - 1)
        content = _mix(content + size.astype(np.uint64))
        if self.scheme.within:
            owner, at = self._again(grams, elected, begin, size)
            self.again = self._places(at, part[owner])
        return elected[begin], content, *self._places(begin, part), size

    def _again(self, grams, elected, begin, size):
        """``(run, place)`` of the windows that begin earlier in their own run too: it holds its elected value more than once."""
        span = self.scheme.span
        # a value is elected somewhere if the greatest that windows over it elect is itself
        around = np.r_[np.zeros(span - 1, np.uint64), elected, np.zeros(span - 1, np.uint64)]
        chosen = np.flatnonzero(~sliding_min(~around, span) == grams)
        low, high = np.searchsorted(chosen, begin), np.searchsorted(chosen, begin + size + span - 1)
        owner, nth = _each(high - low)
        met = grams[chosen[low[owner] + nth]] == elected[begin[owner]]
        several = np.bincount(owner, met, len(begin)) > 1
        owner, nth = _each(np.where(several, size, 0))
        at = begin[owner] + nth
        window = digest(self.rungs, self.scheme.length, at)
        order = np.lexsort((at, window, owner))
        owner, at, window = owner[order], at[order], window[order]
        gone = np.zeros(len(at), bool)
        gone[1:] = (owner[1:] == owner[:-1]) & (window[1:] == window[:-1])
        return owner[gone], at[gone]

    def _places(self, at, part):
        return np.array(self.ids, np.int64)[part], at - self.starts[part] + np.array(self.firsts, np.int64)[part]


def covered(within: bool, same: np.ndarray, doc: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Of rows sorted by content, doc, start: which have an earlier equal one. ``same``: equal to the row before."""
    if within:
        # the first of an interval is the earliest; equal places (a repeated row) are not earlier than each other
        head = np.maximum.accumulate(np.where(same, 0, np.arange(len(same))))
        return (doc != doc[head]) | (start != start[head])
    head = np.maximum.accumulate(np.where(same, 0, np.arange(len(same))))
    return doc > doc[head]


def settle(within: bool, keys: list[np.ndarray], doc: np.ndarray, start: np.ndarray):
    """``(order, gone)``: the sorting of rows by keys, doc, start, and which of them are covered."""
    order = np.lexsort((start, doc, *reversed(keys)))
    same = np.zeros(len(order), bool)
    if len(order):
        same[1:] = np.logical_and.reduce([k[order][1:] == k[order][:-1] for k in keys])
    return order, covered(within, same, doc[order], start[order])


def merged_spans(doc: np.ndarray, start: np.ndarray, n: np.ndarray):
    """Sorted, overlapping and adjoining window ranges of a document joined."""
    if not len(doc):
        return doc, start, n
    order = np.lexsort((start, doc))
    doc, start, end = doc[order], start[order], (start + n)[order]
    new = np.r_[True, doc[1:] != doc[:-1]]
    rank = np.cumsum(new)
    far = np.int64(1) << 40
    top = np.maximum.accumulate(rank * far + end) - rank * far
    begin = new | np.r_[True, start[1:] > top[:-1]]
    first = np.flatnonzero(begin)
    last = np.r_[first[1:], len(doc)] - 1
    return doc[first], start[first], top[last] - start[first]


def text_codes(text: bytes, unit: str, words: WordCodes) -> np.ndarray:
    if unit == "byte":
        return BYTE_CODES[np.frombuffer(text, np.uint8)]
    return words.of(text.split())


def _pieces(scheme: Scheme, codes: np.ndarray):
    """A long text in pieces that share length - 1 symbols, so that no task's memory grows with it."""
    step = 4 * CHUNK
    for first in range(0, max(1, len(codes) - scheme.length + 1), step):
        yield first, codes[first : first + step + scheme.length - 1]


RECORDS = "kind int, key bigint, content bigint, doc bigint, start bigint, n int"
COVERED, OPEN, WIDE, FULL = 1, 0, 2, 3
#: leaves that may share a prefix before it is made longer, and before it is made as long as the window
MOST_LEAVES, MOST_WIDE = 500, 1 << 12


def _records(kind, key, content, doc, start, n) -> pa.RecordBatch:
    size = len(doc)
    column = lambda x, t: pa.array(np.broadcast_to(np.asarray(x), (size,)).astype(t, copy=False))
    signed = lambda x: np.broadcast_to(np.asarray(x, np.uint64), (size,)).view(np.int64) if np.ndim(x) else np.zeros(size, np.int64)
    return pa.RecordBatch.from_arrays(
        [column(kind, np.int32), pa.array(np.ascontiguousarray(signed(key))), pa.array(np.ascontiguousarray(signed(content))), column(doc, np.int64), column(start, np.int64), column(n, np.int32)],
        ["kind", "key", "content", "doc", "start", "n"],
    )


class Met:
    """The first occurrence that a task has sent on of the contents met before: a table of fixed size, newer ones replace older ones."""

    def __init__(self, within: bool, bits: int = 18):
        self.within, self.shift = within, np.uint64(64 - bits)
        self.key, self.content = np.zeros(1 << bits, np.uint64), np.zeros(1 << bits, np.uint64)
        self.doc, self.start = np.full(1 << bits, np.iinfo(np.int64).max), np.zeros(1 << bits, np.int64)

    def covered(self, key, content, doc, start) -> np.ndarray:
        """Which runs have an earlier one of equal content among those remembered; then remembers the earlier of both."""
        at = (content >> self.shift).astype(np.int64)
        known = (self.content[at] == content) & (self.key[at] == key)
        later = doc > self.doc[at]
        if self.within:
            later |= (doc == self.doc[at]) & (start > self.start[at])
        gone = known & later
        new = ~gone
        self.key[at[new]], self.content[at[new]], self.doc[at[new]], self.start[at[new]] = key[new], content[new], doc[new], start[new]
        return gone


def records_of(batches, scheme: Scheme, chunk_size: int = CHUNK):
    """Open runs, and spans covered within their chunk or by what the task met before, from batches of ``(doc, text binary)``."""
    words, met, chunk = WordCodes(), Met(scheme.within), Chunk(scheme)

    def closed(chunk):
        chunk.open()
        key, content, doc, start, n = chunk.runs()
        order, gone = settle(scheme.within, [content], doc, start)
        lost, left = order[gone], order[~gone]
        again = met.covered(key[left], content[left], doc[left], start[left])
        lost, left = np.r_[lost, left[again]], left[~again]
        yield _records(OPEN, key[left], content[left], doc[left], start[left], n[left])
        again_doc, again_start = chunk.again
        if len(lost) or len(again_doc):
            once = np.ones(len(again_doc), np.int64)
            doc, start, n = merged_spans(np.r_[doc[lost], again_doc], np.r_[start[lost], again_start], np.r_[n[lost], once])
            yield _records(COVERED, doc.view(np.uint64) * _ODD[5] + start.view(np.uint64) * _ODD[6], 0, doc, start, n)

    for batch in batches:
        for doc_id, text in zip(*batch.columns, strict=True):
            doc_id, text = doc_id.as_py(), text.as_py()
            for first, codes in _pieces(scheme, text_codes(text, scheme.unit, words)):
                if len(codes) >= scheme.length:
                    chunk.add(doc_id, codes, first)
                if chunk.total >= chunk_size:
                    yield from closed(chunk)
                    chunk = Chunk(scheme)
    if chunk.total:
        yield from closed(chunk)


class LeafScan:
    """Covered spans, and the leaves under branching prefixes, from runs sorted by key, content, document and place.

    Only the leaves of the prefix that is open are held, and of those no more than ``MOST_WIDE``.
    """

    def __init__(self, within: bool):
        self.within = within
        self.held = (np.zeros(0, np.int64),) * 5
        self.full = False

    def feed(self, batch: pa.RecordBatch):
        key, content, doc, start, n, kind = (batch.column(x).to_numpy(zero_copy_only=False) for x in ("key", "content", "doc", "start", "n", "kind"))
        settled = kind == COVERED
        if settled.any():
            yield _records(COVERED, 0, 0, doc[settled], start[settled], n[settled])
        yield from self._scan([np.r_[h, x[~settled]] for h, x in zip(self.held, (key, content, doc, start, n), strict=True)], last=False)

    def close(self):
        yield from self._scan(list(self.held), last=True)

    def _scan(self, rows, last: bool):
        key, content, doc, start, n = rows
        if not len(key):
            return
        new_key = np.r_[True, key[1:] != key[:-1]]
        same = ~(new_key | np.r_[True, content[1:] != content[:-1]])
        gone = covered(self.within, same, doc, start)
        if gone.any():
            yield _records(COVERED, 0, 0, *merged_spans(doc[gone], start[gone], n[gone]))
        group = np.cumsum(new_key) - 1
        contents, leaves = np.bincount(group, ~same), np.bincount(group, ~gone)
        branching = contents > 1
        kinds = np.where(leaves > MOST_WIDE, FULL, np.where(leaves > MOST_LEAVES, WIDE, OPEN))
        if self.full:  # the first prefix was open, and other leaves of it were sent on before
            branching[0], kinds[0] = True, FULL
        open_group = -1 if last else group[-1]
        closed = ~gone & branching[group] & (group != open_group)
        if closed.any():
            yield _records(kinds[group[closed]], key[closed], 0, doc[closed], start[closed], n[closed])
        keep = ~gone & (group == open_group)
        self.held = tuple(x[keep] for x in rows)
        self.full = not last and bool((self.full and open_group == 0) or (leaves[-1] > MOST_WIDE and contents[-1] > 1))
        if self.full:
            # leaves of all contents but the last are sent on; those of the last stay, as later runs may equal them
            done = self.held[1] != self.held[1][-1]
            if done.any():
                key, _, doc, start, n = (x[done] for x in self.held)
                yield _records(FULL, key, 0, doc, start, n)
                self.held = tuple(x[~done] for x in self.held)


def settle_runs(records: DataFrame, scheme: Scheme) -> DataFrame:
    """Covered spans, and the leaves of branching prefixes (kinds OPEN, WIDE, FULL) that need their windows compared."""

    def kernel(batches):
        scan = LeafScan(scheme.within)
        for batch in batches:
            if batch.num_rows:
                yield from scan.feed(batch)
        yield from scan.close()

    return records.repartition(F.col("key")).sortWithinPartitions("key", "content", "doc", "start").mapInArrow(kernel, RECORDS)


BODIES = "key bigint, doc bigint, start bigint, n int, body binary"


def run_bodies(docs: DataFrame, scheme: Scheme) -> DataFrame:
    """The symbols of each open run, from ``(doc, text, open)`` with ``open`` an array of key, start, n, kind: ``key, doc, start, n, body``.

    Wide runs are cut where their windows elect different values among longer substrings, which join the key; full ones are
    cut into single windows, which are their own prefix.
    """

    def kernel(batches):
        words = WordCodes()
        for batch in batches:
            rows = []
            for doc_id, text, runs in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                codes = np.frombuffer(text, np.uint8) if scheme.unit == "byte" else text_codes(text, "word", words).view(np.int64)
                for r in runs:
                    for key, start, n in _refined(scheme, codes, r) if r["kind"] != OPEN else ((r["key"], r["start"], r["n"]),):
                        rows.append((key, doc_id, start, n, codes[start : start + n + scheme.length - 1].tobytes()))
                if len(rows) >= 20_000:
                    yield packed(rows)
                    rows = []
            if rows:
                yield packed(rows)

    def packed(rows):
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["key", "doc", "start", "n", "body"])

    return docs.mapInArrow(kernel, BODIES)


def _refined(scheme: Scheme, codes: np.ndarray, run) -> list[tuple[int, int, int]]:
    """``(key, start, n)`` of the parts of a run under the longer prefix."""
    start, n = run["start"], run["n"]
    body = codes[start : start + n + scheme.length - 1]
    body = BYTE_CODES[body] if scheme.unit == "byte" else body.view(np.uint64)
    gram = scheme.length - (max(1, scheme.length // 12) if run["kind"] == WIDE else 0)
    elected = sliding_min(digest(ladder(body, gram), gram), scheme.length - gram + 1)
    cuts = np.flatnonzero(np.r_[True, elected[1:] != elected[:-1]]) if run["kind"] == WIDE else np.arange(n)
    keys = (elected[cuts] ^ np.int64(run["key"]).view(np.uint64)).view(np.int64)
    return list(zip(keys.tolist(), (start + cuts).tolist(), np.diff(np.r_[cuts, n]).tolist(), strict=True))


class Block:
    """The suffixes that begin at the windows of some runs, each to the end of its run.

    ``at`` is a suffix's place in ``symbols``, ``size`` its length (the window's at least), ``before`` the symbol to its
    left, or -1 for the first of a run, whose left neighbour is dealt out elsewhere.
    """

    def __init__(self, scheme: Scheme, doc, start, n, bodies: list[bytes]):
        self.scheme = scheme
        self.symbols = np.frombuffer(b"".join(bodies), np.uint8 if scheme.unit == "byte" else np.uint64)
        n = n.astype(np.int64)
        firsts = np.cumsum(np.r_[0, n + scheme.length - 1])[:-1]
        owner, nth = _each(n)
        self.at, self.size = firsts[owner] + nth, n[owner] - nth + scheme.length - 1
        self.doc, self.start = doc[owner], start[owner] + nth
        self.before = np.where(nth > 0, self.symbols[self.at - 1].astype(np.int64) & (2**62 - 1), -1) if len(self.at) else self.at

    def __len__(self) -> int:
        return len(self.at)

    def ages(self) -> np.ndarray:
        """Numbers by which suffixes are earlier or later: documents, within one also places."""
        if not self.scheme.within or not len(self):
            return self.doc
        order = np.lexsort((self.start, self.doc))
        doc, start = self.doc[order], self.start[order]
        out = np.empty(len(self), np.int64)
        out[order] = np.cumsum(np.r_[0, (doc[1:] != doc[:-1]) | (start[1:] != start[:-1])])
        return out

    def diverse(self, order: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Which groups ``order[low:high]`` of suffixes do not all have the same symbol to their left."""
        before = self.before[order]
        changes = np.cumsum(np.r_[0, 0, before[1:] != before[:-1]]) if len(before) else np.zeros(1, np.int64)
        firsts = np.cumsum(np.r_[0, before < 0])
        return (changes[high] != changes[low + 1]) | (firsts[high] != firsts[low])

    def covered_by(self, order: np.ndarray, low: np.ndarray, high: np.ndarray, depth: np.ndarray):
        """``doc, start, n`` of the windows in all occurrences but the earliest of the repeats ``order[low:high]``, ``depth`` long."""
        ages, found = self.ages(), []
        size = high - low
        cuts = np.searchsorted(np.cumsum(size), np.arange(0, int(size.sum()) + 1, 1 << 21), side="right")
        for i, j in zip(cuts, np.r_[cuts[1:], len(low)], strict=True):
            if i == j:
                continue
            owner, nth = _each(size[i:j])
            own = order[low[i:j][owner] + nth]
            first = np.minimum.reduceat(ages[own], np.cumsum(size[i:j]) - size[i:j])
            gone = ages[own] > first[owner]
            own, n = own[gone], depth[i:j][owner[gone]] - self.scheme.length + 1
            found.append(merged_spans(self.doc[own], self.start[own], n))
        if not found:
            return (np.zeros(0, np.int64),) * 3
        return merged_spans(*(np.concatenate(x) for x in zip(*found, strict=True)))


Solve = Callable[[Block], tuple[np.ndarray, np.ndarray, np.ndarray]]


def settle_bodies(bodies: DataFrame, scheme: Scheme, solve: Solve) -> DataFrame:
    """Covered spans of all blocks: whole prefixes, dealt out by key, are given to ``solve`` together."""

    def solved(held):
        table = pa.Table.from_batches(held)
        column = lambda x: table.column(x).to_numpy()
        block = Block(scheme, column("doc"), column("start"), column("n"), table.column("body").to_pylist())
        doc, start, n = solve(block)
        if len(doc):
            yield _records(COVERED, 0, 0, doc, start, n)

    def kernel(batches):
        held: list[pa.RecordBatch] = []
        rows = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column("key").to_numpy()
            cut = int(np.searchsorted(key, key[-1]))  # the last prefix may go on in the next batch
            if cut:
                yield from solved([*held, batch.slice(0, cut)])
                held, rows = [], 0
            held.append(batch.slice(cut))
            rows += held[-1].num_rows
            if rows > MOST_WIDE:  # windows that are their own prefix: the earliest stands for the others
                table = pa.Table.from_batches(held)
                if pa.compute.max(table.column("n")).as_py() == 1 and pa.compute.count_distinct(table.column("body")).as_py() == 1:
                    yield from solved(held)
                    held, rows = [held[0].slice(0, 1)], 1
        if held:
            yield from solved(held)

    return bodies.repartition(F.col("key")).sortWithinPartitions("key", "doc", "start").mapInArrow(kernel, RECORDS)


def covered_windows(docs: DataFrame, scheme: Scheme, solve: Solve, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc, spans)``: for each document with any, ranges ``(start, n)`` of windows that occur earlier.

    Ids are whole numbers (another type is an error). Rows without id or text take no part. Rows that share an id count as one
    document: no row is earlier than another at the same place, and what is covered in one is covered in all.
    """
    kind = docs.schema[id_col].dataType
    if not isinstance(kind, IntegralType):
        raise TypeError(f"ids must be whole numbers, {id_col} is {kind.simpleString()}")
    held = docs.where(F.col(id_col).isNotNull() & F.col(text_col).isNotNull()).select(
        F.col(id_col).cast("bigint").alias("doc"), F.col(text_col).cast("binary").alias("text")
    )
    # spans that are covered within their chunk pass through the exchange under spread keys, so that texts are read once
    with small_batches(docs.sparkSession):
        first = materialize(settle_runs(held.mapInArrow(lambda batches: records_of(batches, scheme), RECORDS), scheme), "runs")
    release_shuffles(docs.sparkSession)
    branching = first.where(F.col("kind") != COVERED).groupBy("doc").agg(F.collect_list(F.struct("key", "start", "n", "kind")).alias("open"))
    bodies = run_bodies(held.join(branching, "doc").select("doc", "text", "open"), scheme)
    with small_batches(docs.sparkSession):
        second = materialize(settle_bodies(bodies, scheme, solve), "suffixes")
    release_shuffles(docs.sparkSession)
    spans = first.where(F.col("kind") == COVERED).unionByName(second)
    return spans.groupBy("doc").agg(F.collect_list(F.struct("start", "n")).alias("spans"))


def removal(scheme: Scheme, size: int, spans) -> np.ndarray:
    """Which of ``size`` symbols lie in a covered window."""
    edges = np.zeros(size + 1, np.int64)
    if spans:
        begin = np.array([s["start"] for s in spans])
        end = np.minimum(begin + np.array([s["n"] for s in spans]) + scheme.length - 1, size)
        ok = begin < size  # another row of the same id can be shorter
        np.add.at(edges, begin[ok], 1)
        np.add.at(edges, end[ok], -1)
    return np.cumsum(edges[:-1]) > 0


def with_spans(docs: DataFrame, scheme: Scheme, solve: Solve, id_col: str, text_col: str) -> DataFrame:
    """``(doc_id, t, spans)`` for every row of ``docs``."""
    spans = covered_windows(docs, scheme, solve, id_col, text_col)
    held = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("binary").alias("t"))
    return held.join(spans, held["doc_id"] == spans["doc"], "left").select("doc_id", "t", "spans")
