"""Byte-level BPE encoding and decoding with vectorised pre-tokenisation.

Code points become class symbols with one character of look-ahead folded in. Each symbol is a
transition function on eight states; functions compose associatively, so blocks of text are
composed side by side, block results are scanned, and a last pass reads off where tokens begin.
Distinct slices are merged once per worker and cached.

Cases: null text is the empty text (no ids); repeated rows are encoded each; other columns are
ignored; texts of any length are encoded whole.
"""

from __future__ import annotations

import base64
import heapq
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinward.llm import textscan as ts

# Unicode White_Space.
WHITE_SPACE = (
    [*range(9, 14), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
)
# What may follow an apostrophe to make a contraction.
SHORT_ENDINGS, LONG_ENDINGS = ("s", "t", "m", "d"), ("re", "ve", "ll")

# Symbols: letter, digit, other, last blank before ink, other last space before ink, space before space,
# apostrophe of a one-letter contraction, of a two-letter contraction; plus 8 where a document begins.
LETTER, DIGIT, OTHER, BLANK, BREAK, SPACES, APOS1, APOS2 = range(8)
# States after a character: in letters, in digits, in others, blank that joins what follows, in spaces,
# one or two contraction letters to come, closed.
S_LETTER, S_DIGIT, S_OTHER, S_BLANK, S_SPACES, S_ONE, S_TWO, S_CLOSED = range(8)


def _machine() -> tuple[np.ndarray, np.ndarray]:
    """Next state and whether a token begins, by (symbol, state)."""
    step, begins = np.zeros((16, 8), np.uint8), np.ones((16, 8), bool)
    for s in range(8):
        for run, symbol in ((S_LETTER, LETTER), (S_DIGIT, DIGIT), (S_OTHER, OTHER)):
            step[symbol, s], begins[symbol, s] = run, s not in (run, S_BLANK)
        step[BLANK, s] = S_BLANK
        step[BREAK, s] = S_CLOSED
        step[SPACES, s], begins[SPACES, s] = S_SPACES, s != S_SPACES
        for symbol, wait in ((APOS1, S_ONE), (APOS2, S_TWO)):
            joined = s in (S_OTHER, S_BLANK)
            step[symbol, s], begins[symbol, s] = (S_OTHER if joined else wait), not joined
    step[LETTER, S_ONE], begins[LETTER, S_ONE] = S_CLOSED, False
    step[LETTER, S_TWO], begins[LETTER, S_TWO] = S_ONE, False
    step[8:] = step[:8, S_CLOSED][:, None]
    begins[8:] = True
    return step, begins


STEP, BEGINS = _machine()


@lru_cache(1)
def _classes() -> np.ndarray:
    """LETTER, DIGIT, OTHER or SPACES for every code point."""
    import regex

    points = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    out = np.full(0x110000, OTHER, np.uint8)
    for pattern, value in ((r"\p{L}+", LETTER), (r"\p{N}+", DIGIT)):
        for m in regex.finditer(pattern, points):
            shift = [0x800 * (i >= 0xD800) for i in (m.start(), m.end() - 1)]
            out[m.start() + shift[0] : m.end() + shift[1]] = value
    out[0xD800:0xE000] = OTHER
    out[WHITE_SPACE] = SPACES
    return out


def symbols(points: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Class symbols with look-ahead; ``first`` marks the first character of each document."""
    sym = _classes()[points]
    n = len(points)
    last = np.append(first[1:], True)  # of its document
    ink_next = np.zeros(n, bool)
    ink_next[:-1] = (sym[1:] != SPACES) & ~last[:-1]
    edge = (sym == SPACES) & ink_next
    sym[edge] = np.where(points[edge] == 32, BLANK, BREAK)
    apos = np.flatnonzero(points == 39)
    if len(apos):
        pad = np.append(points, [0, 0])
        one = np.where(last[apos], 0, pad[apos + 1])
        two = np.where(last[apos] | np.append(last, True)[apos + 1], 0, pad[apos + 2])
        sym[apos[np.isin(one, [ord(x) for x in SHORT_ENDINGS])]] = APOS1
        for a, b in LONG_ENDINGS:
            sym[apos[(one == ord(a)) & (two == ord(b))]] = APOS2
    sym[first] += 8
    return sym


def token_starts(sym: np.ndarray, width: int = 256) -> np.ndarray:
    """Positions where a token begins: a block scan over transition functions."""
    n = len(sym)
    if n < 4 * width:
        at, out = S_CLOSED, []
        step, begins = STEP.tolist(), BEGINS.tolist()
        for i, c in enumerate(sym.tolist()):
            if begins[c][at]:
                out.append(i)
            at = step[c][at]
        return np.array(out, dtype=np.int64)
    rows = -(-n // width)
    grid = np.zeros(rows * width, np.uint8)
    grid[:n] = sym
    grid = np.ascontiguousarray(grid.reshape(rows, width).T)
    flat = STEP.ravel()
    whole = np.tile(np.arange(8, dtype=np.uint8), (rows, 1))
    for column in grid:  # compose each block's functions
        whole = flat[(column.astype(np.int16)[:, None] << 3) + whole]
    enter = np.zeros(rows, np.uint8)
    at = S_CLOSED
    for i, f in enumerate(whole.tolist()):  # scan of the blocks' results
        enter[i] = at
        at = f[at]
    hits = np.zeros((width, rows), bool)
    begin = BEGINS.ravel()
    for k, column in enumerate(grid):
        cell = (column.astype(np.int16) << 3) + enter
        hits[k] = begin[cell]
        enter = flat[cell]
    return np.flatnonzero(np.ascontiguousarray(hits.T).ravel()[:n])


def slice_starts(buf: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Byte positions where the slices of the documents begin."""
    if not len(buf):
        return np.zeros(0, np.int64)
    points = np.frombuffer(buf.tobytes().decode("utf-8").encode("utf-32-le"), np.uint32)
    lead = np.flatnonzero((buf & 0xC0) != 0x80)  # byte position of each character
    first = np.zeros(len(buf), bool)
    first[off[:-1][off[:-1] < off[1:]]] = True
    return lead[token_starts(symbols(points, first[lead]))]


class Vocabulary:
    """Ranks of byte strings, merges with a bounded cache, and flat bytes for decoding."""

    def __init__(self, path: str, cache_size: int = 500_000):
        with open(path, "rb") as f:
            pairs = [line.split() for line in f if line.strip()]
        self.ranks = {base64.b64decode(a): int(b) for a, b in pairs}
        size = max(self.ranks.values()) + 1
        self.words = [b""] * size
        for word, rank in self.ranks.items():
            self.words[rank] = word
        self.length = np.array([len(w) for w in self.words], np.int64)
        self.begin = np.cumsum(self.length) - self.length
        self.bytes = np.frombuffer(b"".join(self.words), np.uint8)
        self.decimal = [str(i) for i in range(size)]
        self.cache_size, self.known = cache_size, {}

    def merge(self, word: bytes) -> list[int]:
        """Ids of one slice: repeatedly join the neighbouring pair of least rank, leftmost first."""
        ranks = self.ranks
        whole = ranks.get(word)
        if whole is not None:
            return [whole]
        if len(word) > 40:
            return self._merge_long(word)
        parts = [word[i : i + 1] for i in range(len(word))]
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                rank = ranks.get(parts[i] + parts[i + 1])
                if rank is not None and (best is None or rank < best):
                    best, at = rank, i
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [ranks[p] for p in parts]

    def _merge_long(self, word: bytes) -> list[int]:
        """The same by a heap over a linked list."""
        ranks, n = self.ranks, len(word)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        end = list(range(1, n + 1))
        heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
        heapq.heapify(heap)
        alive = [True] * n
        while heap:
            _, i, stop = heapq.heappop(heap)
            j = after[i] if alive[i] else n
            if j >= n or end[j] != stop:
                continue
            alive[j] = False
            end[i], after[i] = stop, after[j]
            if after[i] < n:
                before[after[i]] = i
                if (r := ranks.get(word[i : end[after[i]]])) is not None:
                    heapq.heappush(heap, (r, i, end[after[i]]))
            if (h := before[i]) >= 0 and (r := ranks.get(word[h:stop])) is not None:
                heapq.heappush(heap, (r, h, stop))
        return [ranks[word[i : end[i]]] for i in range(n) if alive[i]]

    def encode(self, buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all documents and their offsets."""
        start = slice_starts(buf, off)
        end = np.append(start[1:], len(buf))
        sums = ts.prefix_sums(ts.byte_codes(buf))
        _, at, inverse = np.unique(ts.span_hash(sums, start, end), return_index=True, return_inverse=True)
        names = ts.span_hash(sums, start[at], end[at]).tolist()
        if len(self.known) > self.cache_size:
            self.known.clear()
        known, data = self.known, buf.tobytes()
        made = []
        for name, i, j in zip(names, start[at].tolist(), end[at].tolist()):
            got = known.get(name)
            if got is None:
                got = known[name] = np.array(self.merge(data[i:j]), np.int32).tobytes()
            made.append(got)
        count = np.array([len(x) for x in made], np.int64) // 4
        flat = np.frombuffer(b"".join(made), np.int32)
        begin = np.cumsum(count) - count
        ids = flat[ts.ranges(begin[inverse], count[inverse])]
        total = np.append(0, np.cumsum(count[inverse]))
        at_doc = total[np.searchsorted(start, off)]
        if not np.array_equal(self.decode(ids), buf):  # a hash collision: encode this piece without the cache
            lists = [self.merge(data[i:j]) for i, j in zip(start.tolist(), end.tolist())]
            total = np.append(0, np.cumsum([len(x) for x in lists])).astype(np.int64)
            ids, at_doc = np.array([i for x in lists for i in x], np.int32), total[np.searchsorted(start, off)]
        return ids, at_doc

    def decode(self, ids: np.ndarray) -> np.ndarray:
        """The bytes of all ids, scattered into one buffer."""
        return self.bytes[ts.ranges(self.begin[ids], self.length[ids])]


@lru_cache(4)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


_ENCODED = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids", pa.list_(pa.int32()))])


def _encoded(batches: Iterator[pa.RecordBatch], vocab: Vocabulary) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        buf, off = ts.as_bytes(batch.column(1))
        for i, j in ts.pieces(buf, off):
            ids, at = vocab.encode(buf[off[i] : off[j]], off[i : j + 1] - off[i])
            lists = pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(ids, pa.int32()))
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(np.diff(at)), lists], schema=_ENCODED)


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def encode_documents(docs: DataFrame, vocab_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids): the ids of every whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _encoded(batches, vocabulary(vocab_path))

    return _texts(docs, id_col, text_col).mapInArrow(run, "doc_id long, n_tokens long, ids array<int>")


def decode_documents(encoded: DataFrame, vocab_path: str) -> DataFrame:
    """(doc_id, data): the bytes that the ids stand for."""
    arrow = pa.schema([("doc_id", pa.int64()), ("data", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(vocab_path)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                ids = part.column(1)
                data = [vocab.decode(np.asarray(x.values)).tobytes() if x.is_valid else b"" for x in ids]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(data, pa.binary())], schema=arrow)

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, data binary")


def encode_and_digest(docs: DataFrame, vocab_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of what encoding gives; the ids are decoded again.

    One Python pass: the encoder's batches feed the digests without a way back through the JVM.
    """
    import hashlib

    arrow = pa.schema(
        [("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())]
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(vocab_path)
        word = vocab.decimal.__getitem__
        for batch in _encoded(batches, vocab):
            lists = batch.column(2)
            at, flat = lists.offsets.to_numpy(), lists.values.to_numpy()
            said, read = [], []
            for i, j in zip(at[:-1].tolist(), at[1:].tolist()):
                ids = flat[i:j]
                said.append(hashlib.sha256(" ".join(map(word, ids.tolist())).encode()).hexdigest())
                read.append(hashlib.sha256(vocab.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(said), pa.array(read)], schema=arrow)

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    return _texts(docs, id_col, text_col).mapInArrow(run, schema)
