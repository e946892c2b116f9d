"""SentencePiece encoding and decoding: unigram Viterbi over a double-array trie.

Pieces come from a public model file. Its scores are merge ranks, not probabilities, so log scores
follow from them by a rule (Zipf: rank r gets -log(r + 2)); a unigram file's own scores can be kept.
No piece holds a character after which a whitespace marker follows, so a text falls into words that
begin with their markers, and the best path of a text is the best paths of its words end to end.
The words that are new to a batch are all solved at once, position by position, on numpy arrays.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import types as T

MARK = "▁"
DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNKNOWN_PENALTY = 10.0
WORDS = regex.compile(f"{MARK}*[^{MARK}]+|{MARK}+\\Z")
VECTOR_LIMIT = 48


def _fields(data: bytes):
    """``(field number, wire type, value)`` of a protocol buffer message."""
    at = 0

    def varint():
        nonlocal at
        value = shift = 0
        while True:
            byte = data[at]
            at += 1
            value |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return value

    while at < len(data):
        tag = varint()
        if tag & 7 == 0:
            yield tag >> 3, 0, varint()
        elif tag & 7 == 2:
            n = varint()
            yield tag >> 3, 2, data[at : at + n]
            at += n
        else:
            n = 4 if tag & 7 == 5 else 8
            yield tag >> 3, tag & 7, data[at : at + n]
            at += n


def read_pieces(model: bytes) -> list[tuple[str, float, int]]:
    """``(piece, score, kind)`` in the order of their ids."""
    pieces = []
    for number, _, value in _fields(model):
        if number == 1:
            own = {n: v for n, _, v in _fields(value)}
            pieces.append((own.get(1, b"").decode(), struct.unpack("<f", own[2])[0] if 2 in own else 0.0, own.get(3, NORMAL)))
    return pieces


def zipf_scores(pieces) -> list[float]:
    """Log scores by rank: the best merge ranks first, pieces outside the ranking last."""
    order = sorted((i for i, p in enumerate(pieces) if p[2] == NORMAL), key=lambda i: (-pieces[i][1], i))
    scores = [0.0] * len(pieces)
    for rank, i in enumerate(order):
        scores[i] = -float(np.log(rank + 2.0))
    for i, (piece, _, kind) in enumerate(pieces):
        if kind == USER_DEFINED:  # as good as the same number of best pieces, nearly
            scores[i] = len(piece) * -float(np.log(2.0)) - 0.1
    return scores


class DoubleArrayTrie:
    """Characters are coded densely; child of state s by code c is base[s] + c if check there is s."""

    def __init__(self, keys: dict[str, int]):
        self.codes = {c: i + 1 for i, c in enumerate(sorted({c for k in keys for c in k}))}
        tree: list[dict[int, int]] = [{}]
        ends = [-1]
        for key, value in keys.items():
            at = 0
            for c in key:
                code = self.codes[c]
                if code not in tree[at]:
                    tree[at][code] = len(tree)
                    tree.append({})
                    ends.append(-1)
                at = tree[at][code]
            ends[at] = value
        width = len(self.codes) + 2
        size = 2 * len(tree) + 2 * width
        base, check, value = np.zeros(size, np.int64), np.full(size, -1, np.int64), np.full(size, -1, np.int64)
        check[0] = 0
        free = 1
        waiting = [(0, 0)]
        for node, state in waiting:
            value[state] = ends[node]
            children = sorted(tree[node].items())
            if not children:
                continue
            steps = np.array([c for c, _ in children])
            while check[free] >= 0:
                free += 1
            at = max(0, free - int(steps[0]))
            while (check[at + steps] >= 0).any():
                at += 1
            if at + 2 * width >= len(base):
                base, check, value = (np.concatenate([a, np.full(len(a), f, np.int64)]) for a, f in ((base, 0), (check, -1), (value, -1)))
            base[state] = at
            for code, child in children:
                check[at + code] = state
                waiting.append((child, at + code))
        top = int(np.flatnonzero(check >= 0).max()) + 1 + width
        self.base, self.check, self.value = base[:top], check[:top], value[:top]


@dataclass
class Codec:
    """Everything that encoding needs; a few MB whatever the corpus, sent with the task."""

    trie: DoubleArrayTrie
    scores: np.ndarray
    pieces: list
    byte_ids: np.ndarray
    unknown_id: int
    longest: int

    @classmethod
    def load(cls, model: bytes, score_rule=zipf_scores) -> Codec:
        pieces = read_pieces(model)
        scores = score_rule(pieces) if score_rule else [p[1] for p in pieces]
        keys = {p: i for i, (p, _, kind) in enumerate(pieces) if kind in (NORMAL, USER_DEFINED) and p}
        if any(MARK in p.lstrip(MARK) for p in keys):
            raise ValueError("a piece holds a whitespace marker after another character")
        bytes_of = {int(p[3:5], 16): i for i, (p, _, kind) in enumerate(pieces) if kind == BYTE}
        unknown = next((i for i, p in enumerate(pieces) if p[2] == UNKNOWN), 0)
        byte_ids = np.array([bytes_of.get(b, unknown) for b in range(256)])
        return cls(DoubleArrayTrie(keys), np.array(scores), [p[0] for p in pieces], byte_ids, unknown, max(map(len, keys)))

    def best_paths(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """``(ids end to end, ids per word)`` of the best segmentations; among equal scores the first found from the left."""
        sizes = np.array([len(w) for w in words], np.int64)
        flat, counts, order = [], [], []
        for low, high in ((0, 6), (6, 9), (9, 12), (12, 16), (16, 24), (24, VECTOR_LIMIT)):
            picked = np.flatnonzero((sizes > low) & (sizes <= high))
            for k in range(0, len(picked), 1 << 15):
                some = picked[k : k + (1 << 15)]
                ids, n = self._together([words[i] for i in some.tolist()], high)
                flat.append(ids)
                counts.append(n)
                order.append(some)
        for i in np.flatnonzero(sizes > VECTOR_LIMIT).tolist():
            ids = np.array(self._alone(words[i]), np.int32)
            flat.append(ids)
            counts.append(np.array([len(ids)]))
            order.append(np.array([i]))
        if not order:
            return np.zeros(0, np.int32), np.zeros(0, np.int64)
        flat, counts, order = np.concatenate(flat), np.concatenate(counts), np.concatenate(order)
        back = np.argsort(order)
        return gathered(flat, (np.cumsum(counts) - counts)[back], counts[back]), counts[back]

    def _together(self, words: list[str], width: int) -> tuple[np.ndarray, np.ndarray]:
        n = len(words)
        points = np.frombuffer("".join(w.ljust(width, "\0") for w in words).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(n, width)
        alphabet, spots = np.unique(points, return_inverse=True)
        codes = np.array([self.trie.codes.get(chr(c), 0) for c in alphabet.tolist()])[spots].reshape(n, width)
        sizes = np.array([len(w) for w in words])
        base, check, value = self.trie.base, self.trie.check, self.trie.value
        unknown = self.scores.min() - UNKNOWN_PENALTY
        best = np.full((n, width + 1), -np.inf)
        best[:, 0] = 0
        came, piece = np.zeros((n, width + 1), np.int32), np.full((n, width + 1), -1, np.int32)
        for i in range(int(sizes.max())):
            rows = np.flatnonzero(sizes > i)
            state, here = np.zeros(len(rows), np.int64), best[rows, i]
            single = np.zeros(n, bool)
            alive = rows
            for d in range(i, min(width, i + self.longest)):
                code = codes[alive, d]
                nxt = base[state] + code
                ok = (code > 0) & (check[nxt] == state) & (sizes[alive] > d)
                alive, here, state = alive[ok], here[ok], nxt[ok]
                if not len(alive):
                    break
                ends = value[state]
                hit = ends >= 0
                to, total, ids = alive[hit], here[hit] + self.scores[ends[hit]], ends[hit]
                if d == i:
                    single[to] = True
                better = total > best[to, d + 1]
                to = to[better]
                best[to, d + 1], came[to, d + 1], piece[to, d + 1] = total[better], i, ids[better]
            lone = rows[~single[rows]]
            total = best[lone, i] + unknown
            better = total > best[lone, i + 1]
            lone = lone[better]
            best[lone, i + 1], came[lone, i + 1], piece[lone, i + 1] = total[better], i, -1
        # walk back from the ends of all words together; columns fill from the right
        trail, at, every = np.full((n, width), -1, np.int32), sizes.copy(), np.arange(n)
        counts, odd = np.zeros(n, np.int64), np.zeros(n, bool)
        for column in range(width - 1, -1, -1):
            rows = every[at > 0]
            if not len(rows):
                break
            ids = piece[rows, at[rows]]
            trail[rows, column] = ids
            odd[rows[ids < 0]] = True
            counts[rows] += 1
            at[rows] = came[rows, at[rows]]
        taken = np.arange(width) >= (width - counts)[:, None]
        if not odd.any():
            return trail[taken], counts
        spelled = {k: self._back(words[k], came[k].tolist(), piece[k].tolist()) for k in np.flatnonzero(odd).tolist()}
        rows = [np.array(spelled[k], np.int32) if k in spelled else trail[k, width - counts[k] :] for k in range(n)]
        return np.concatenate(rows), np.array([len(r) for r in rows])

    def _alone(self, word: str) -> list[int]:
        """The same for one long word; memory grows with its length."""
        base, check, value, codes, scores = self.trie.base, self.trie.check, self.trie.value, self.trie.codes, self.scores
        unknown = float(scores.min()) - UNKNOWN_PENALTY
        best, came, piece = [0.0] + [-np.inf] * len(word), [0] * (len(word) + 1), [-1] * (len(word) + 1)
        steps = [codes.get(c, 0) for c in word]
        for i, here in enumerate(best[:-1]):
            here, state, single = best[i], 0, False
            for d in range(i, min(len(word), i + self.longest)):
                nxt = int(base[state]) + steps[d]
                if not steps[d] or check[nxt] != state:
                    break
                state, end = nxt, int(value[nxt])
                if end >= 0:
                    single |= d == i
                    if (total := here + float(scores[end])) > best[d + 1]:
                        best[d + 1], came[d + 1], piece[d + 1] = total, i, end
            if not single and here + unknown > best[i + 1]:
                best[i + 1], came[i + 1], piece[i + 1] = here + unknown, i, -1
        return self._back(word, came, piece)

    def _back(self, word: str, came, piece) -> list[int]:
        at, ids = len(word), []
        while at:
            frm = came[at]
            if piece[at] >= 0:
                ids.append(piece[at])
            else:
                ids += [int(self.byte_ids[b]) for b in reversed(word[frm:at].encode("utf-8", "replace"))]
            at = frm
        return ids[::-1]

    def encode(self, texts: list[str], known: WordTable) -> tuple[np.ndarray, np.ndarray]:
        """``(ids end to end, ids per text)``; ``known`` remembers words between calls."""
        split = [WORDS.findall(MARK + t.replace(" ", MARK)) if t else [] for t in texts]
        words = pa.array([w for own in split for w in own], pa.string()).dictionary_encode()
        rows = known.rows(words.dictionary.to_pylist(), self)[words.indices.to_numpy()] if len(words) else np.zeros(0, np.int64)
        sizes = known.counts[rows]
        ids = gathered(known.flat, known.starts[rows], sizes)
        upto = np.r_[0, np.cumsum(sizes)]
        ends = np.cumsum([0] + [len(own) for own in split])
        return ids, upto[ends[1:]] - upto[ends[:-1]]

    def decode(self, ids: np.ndarray, counts: np.ndarray) -> list[str]:
        """Texts of sequences laid end to end: bytes are joined, markers become spaces, the first is dropped."""
        ids = np.asarray(ids, np.int64)
        sizes = self.piece_sizes[ids]
        data = gathered(self.piece_bytes, self.piece_starts[ids], sizes).tobytes()
        upto = np.r_[0, np.cumsum(sizes)]
        ends = upto[np.cumsum(np.r_[0, counts])].tolist()
        parts = [data[i:j].decode("utf-8", "replace") for i, j in zip(ends[:-1], ends[1:], strict=True)]
        return [t[1:] if t.startswith(" ") else t for t in parts]

    def __post_init__(self):
        spelled = {int(i): bytes([b]) for b, i in enumerate(self.byte_ids) if i != self.unknown_id}
        table = [spelled.get(i, p.replace(MARK, " ").encode()) for i, p in enumerate(self.pieces)]
        self.piece_sizes = np.array([len(x) for x in table], np.int64)
        self.piece_starts = np.cumsum(self.piece_sizes) - self.piece_sizes
        self.piece_bytes = np.frombuffer(b"".join(table), np.uint8)


def gathered(flat: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The stretches of ``flat`` at ``starts``, end to end."""
    ends = np.cumsum(sizes)
    if not len(ends):
        return flat[:0]
    return flat[np.arange(ends[-1]) + np.repeat(starts - (ends - sizes), sizes)]


class WordTable:
    """Segmentations of words met so far; forgets all when there are more than ``most``, which changes no result."""

    def __init__(self, most: int = 300_000):
        self.most = most
        self.forget()

    def forget(self) -> None:
        self.index: dict[str, int] = {}
        self.flat, self.starts, self.counts = np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def rows(self, words: list[str], codec: Codec) -> np.ndarray:
        if len(self.index) > self.most:
            self.forget()
        new = [w for w in words if w not in self.index]
        if new:
            ids, counts = codec.best_paths(new)
            self.starts = np.r_[self.starts, len(self.flat) + np.cumsum(counts) - counts]
            self.counts, self.flat = np.r_[self.counts, counts], np.r_[self.flat, ids]
            self.index.update(zip(new, range(len(self.index), len(self.index) + len(new)), strict=True))
        return np.fromiter(map(self.index.__getitem__, words), np.int64, len(words))


def load_codec(spark, path: str = DEFAULT_MODEL, score_rule=zipf_scores) -> Codec:
    """Reads the model file on the driver, once."""
    with open(path, "rb") as f:
        return Codec.load(f.read(), score_rule)


def _coded(df: DataFrame, fields: list, kernel_of, codec: Codec) -> DataFrame:
    """``df`` with more columns, made by ``kernel_of(codec, table)(batch)`` from slices of a thousand rows; columns of the same name are replaced."""
    shared = df.sparkSession.sparkContext.broadcast(codec)  # pieces only: bounded by the model file
    new = {f.name.lower() for f in fields}
    held = [i for i, c in enumerate(df.columns) if c.lower() not in new]
    names = [*(df.columns[i] for i in held), *(f.name for f in fields)]

    def kernel(batches):
        work = kernel_of(shared.value, WordTable())
        for whole in batches:
            for k in range(0, whole.num_rows, 1000):
                batch = whole.slice(k, 1000)
                yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in held), *work(batch)], names)

    return df.mapInArrow(kernel, T.StructType([*(df.schema.fields[i] for i in held), *fields]))


def _id_lists(ids: np.ndarray, counts: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(counts)], pa.int32()), pa.array(ids.astype(np.int32, copy=False)))


def encode(docs: DataFrame, text_col: str = "text", ids_col: str = "piece_ids", codec: Codec | None = None) -> DataFrame:
    """``docs`` with a column of piece ids for each whole text; null or empty text: an empty array. All columns are kept, repeated rows too; a column of the new name is replaced."""
    at = docs.columns.index(text_col)

    def kernel_of(own, known):
        return lambda batch: [_id_lists(*own.encode([t or "" for t in batch.column(at).to_pylist()], known))]

    return _coded(docs, [T.StructField(ids_col, T.ArrayType(T.IntegerType()))], kernel_of, codec or load_codec(docs.sparkSession))


def decode(encoded: DataFrame, ids_col: str = "piece_ids", text_col: str = "decoded", codec: Codec | None = None) -> DataFrame:
    """``encoded`` with a column of decoded texts; a null array decodes to the empty text; a column of the new name is replaced."""
    at = encoded.columns.index(ids_col)

    def kernel_of(own, known):
        def work(batch):
            lists = batch.column(at)
            counts = lists.value_lengths().fill_null(0).to_numpy()
            return [pa.array(own.decode(lists.flatten().to_numpy(), counts), pa.string())]

        return work

    return _coded(encoded, [T.StructField(text_col, T.StringType())], kernel_of, codec or load_codec(encoded.sparkSession))


def encode_documents(docs: DataFrame, codec: Codec | None = None, text_col: str = "text") -> DataFrame:
    """``docs`` with ``piece_ids``, ``n_pieces`` and ``round_trip`` (decoding gives the text back), in one pass.

    A marker character in a text decodes to a space, which counts as given back; a null text is empty. Columns of the three names are replaced.
    """
    at = docs.columns.index(text_col)

    def kernel_of(own, known):
        def work(batch):
            texts = [t or "" for t in batch.column(at).to_pylist()]
            ids, counts = own.encode(texts, known)
            same = [d == t.replace(MARK, " ") for d, t in zip(own.decode(ids, counts), texts, strict=True)]
            return [_id_lists(ids, counts), pa.array(counts, pa.int32()), pa.array(same, pa.bool_())]

        return work

    fields = [T.StructField("piece_ids", T.ArrayType(T.IntegerType())), T.StructField("n_pieces", T.IntegerType()), T.StructField("round_trip", T.BooleanType())]
    return _coded(docs, fields, kernel_of, codec or load_codec(docs.sparkSession))


def op4_sentencepiece(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return encode_documents(docs).drop("text")
