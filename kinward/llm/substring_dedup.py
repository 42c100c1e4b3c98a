"""Substring dedup over words by recompression.

Rounds name pairs of neighbouring symbols: a symbol's own bit says whether it opens or closes a
pair, so a passage is cut the same way wherever it stands, but for its ends. Names are 64-bit
fingerprints of what they stand for, which makes them global without a shuffle. Each round can
lose one symbol at either end of a window; two rounds on a window of 20 words leave its middle
(words 3 to 16) with the same interior symbols everywhere. The least of these, with the words
around it that every such window holds, is what occurrences share. Runs of one symbol are named
last (key, count), since a run named early could reach out of a window. Windows around shared
symbols are then verified by two independent 61-bit hashes of their words.

A word goes if a window that covers it also starts earlier: smaller doc_id (null first; rows of one
id by a hash of their text), or the same document and an earlier word. Cases: null text has no
words; texts under 20 words stay whole; a document stored again (id and text) counts once; other
columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinward.llm import exchange as ex
from kinward.llm import repeats as rp
from kinward.llm import textscan as ts

WINDOW = 20
ROUNDS = 2


def reach(rounds: int) -> int:
    """Words at either end of a window that ``rounds`` of pairing can lose."""
    return (1 << rounds) - 1


def compress(codes: np.ndarray, off: np.ndarray, rounds: int = ROUNDS) -> tuple[np.ndarray, np.ndarray]:
    """(start, name) of the symbols after some rounds of pairing; pairs never cross documents."""
    n = len(codes)
    start, name = np.arange(n), codes
    head = np.zeros(n + 1, bool)
    head[off] = True
    for r in range(rounds):
        bit = (ts.mix64(name ^ np.uint64(0x5851F42D4C957F2D * (r + 1) % (1 << 64))) >> np.uint64(7)) & np.uint64(1)
        opens = (bit[:-1] == 1) & (bit[1:] == 0) & ~head[start[1:]]
        second = np.append(False, opens)
        first = np.append(opens, False)
        with np.errstate(over="ignore"):
            pair = ts.mix64(name[:-1] * np.uint64(0x9E3779B97F4A7C15) + ts.mix64(name[1:] + np.uint64(r + 1)))
        made = name.copy()
        made[:-1][opens] = pair[opens]
        keep = ~second
        start, name = start[keep], np.where(first, made, ts.mix64(name + np.uint64(77)))[keep]
    return start, name


def word_codes(buf: np.ndarray, off: np.ndarray):
    """64-bit codes of the words under either base, and word offsets of the documents."""
    s, e, doc = ts.word_spans(buf, off)
    letters = ts.byte_codes(buf)
    codes = [ts.span_hash(ts.prefix_sums(letters, w), s, e, w) for w in (0, 1)]
    return codes, np.searchsorted(doc, np.arange(len(off)))


def scan(buf, off, ids, tags) -> np.ndarray:
    (codes, others), woff = word_codes(buf, off)
    if len(codes) < WINDOW:
        return np.zeros(0, rp.PLACE)
    start, name = compress(codes, woff)
    score = np.full(len(codes), np.iinfo(np.uint64).max, np.uint64)
    score[start] = ts.mix64(name) >> np.uint64(1)
    edge, widest = reach(ROUNDS), 1 << ROUNDS
    zone = (edge, WINDOW - edge - widest + 1)
    at, lo, many, doc = rp.anchors(score, woff, WINDOW, zone)
    sums = ts.prefix_sums(codes), ts.prefix_sums(others, 1)
    key = ts.span_hash(sums[0], at - zone[0], at + WINDOW - zone[1] + 1)
    return rp.places(key, at, lo, many, doc, sums, woff, ids, tags, WINDOW)


CLAIM = np.dtype([("hash", "u8"), ("hash2", "u8"), ("doc", "i8"), ("tag", "i4"), ("start", "i4")])


def _first(rec: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first of equal windows, and the others."""
    rec = rec[np.lexsort([rec[c] for c in ("start", "tag", "doc", "hash2", "hash")])]
    at = ts.group_bounds(rec["hash"], rec["hash2"])
    first = np.repeat(rec[at[:-1]], np.diff(at))  # a row that is stored again has the same place
    other = (rec["doc"] != first["doc"]) | (rec["tag"] != first["tag"]) | (rec["start"] != first["start"])
    return rec[at[:-1]], rec[other]


def _later(rec: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Round-2 bucket: of equal windows all but the first go."""
    _, gone = _first(rec)
    gone = gone[np.lexsort([gone[c] for c in ("start", "tag", "doc")])]
    run = np.empty(len(gone), rp.RUN)
    run["lo"], run["many"], run["n"] = gone["start"], 1, 1
    yield from ex.reply_batches(gone["doc"], gone["tag"], run)


def _answer(asked: DataFrame, buckets: int) -> DataFrame:
    """Deal every window of the contexts asked for by its content, and compare."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made: list[np.ndarray] = []

        def flush() -> Iterator[pa.RecordBatch]:
            first, gone = _first(np.concatenate(made))
            made.clear()
            yield from ex.deal(first, first["hash"], buckets)
            passed = np.empty(len(gone), rp.PASSED)
            passed["doc"], passed["tag"], passed["lo"], passed["many"], passed["n"] = gone["doc"], gone["tag"], gone["start"], 1, 1
            yield from rp.deal_passed(passed, buckets)

        for batch in batches:
            buf, off = ts.as_bytes(batch.column(2))
            ids, tags, cells = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(3)
            for i, j in ts.pieces(buf, off):
                codes, woff = word_codes(buf[off[i] : off[j]], off[i : j + 1] - off[i])
                qs = [rp.joined_blocks(cells[k].as_py(), rp.QUESTION) for k in range(i, j)]
                of = np.repeat(np.arange(i, j), [len(q) for q in qs])
                q = np.concatenate(qs)
                many = q["many"].astype(np.int64)
                begin = ts.ranges(woff[of - i] + q["pos"] - q["left"], many)
                rec = np.empty(len(begin), CLAIM)
                for w, name in enumerate(("hash", "hash2")):
                    rec[name] = ts.span_hash(ts.prefix_sums(codes[w], w), begin, begin + WINDOW, w)
                who = np.repeat(of, many)
                rec["doc"], rec["tag"], rec["start"] = ids[who], tags[who], begin - woff[who - i]
                made.append(rec)
                if sum(map(len, made)) > rp.FOLD:
                    yield from flush()
        if made:
            yield from flush()

    return ex.per_bucket(asked.mapInArrow(run, ex.BLOCK_SCHEMA), CLAIM, _later, ex.REPLY_SCHEMA, buckets, (rp.PASSED, rp.pass_on))


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_words, n_removed, kept_text): the words left, joined by one space."""
    rows, runs = rp.find_runs(ex.keyed(docs, id_col, text_col), scan, _answer, earlier=True)
    arrow = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_text", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = ts.as_bytes(batch.column(2))
            cells = batch.column(3)
            for i, j in ts.pieces(buf, off):
                part = buf[off[i] : off[j]]
                s, e, doc = ts.word_spans(part, off[i : j + 1] - off[i])
                woff = np.searchsorted(doc, np.arange(j - i + 1))
                gone = [
                    rp.covered(rp.joined_blocks(cells[k].as_py(), rp.RUN), int(woff[k - i + 1] - woff[k - i]), WINDOW)
                    for k in range(i, j)
                ]
                stay = ~np.concatenate(gone) if gone else np.zeros(0, bool)
                ends = np.append(0, np.cumsum(stay))[woff]
                s, e = s[stay], e[stay]
                size = e - s + 1
                flat = np.full(int(size.sum()), 32, np.uint8)
                to = np.cumsum(size) - size
                flat[ts.ranges(to, size - 1)] = part[ts.ranges(s, size - 1)]
                flat, to = flat.tobytes(), np.append(to, len(flat))
                kept = [flat[a : max(a, b - 1)] for a, b in zip(to[ends[:-1]].tolist(), to[ends[1:]].tolist())]
                n = np.diff(woff)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, j - i), pa.array(n), pa.array(n - np.diff(ends)), pa.array(kept, pa.binary())],
                    schema=arrow,
                )

    out = rows.join(runs, ["doc_key", "doc_tag"], "left").select("doc_key", "doc_tag", "text", "blocks")
    out = out.mapInArrow(run, "doc_id long, n_words long, n_removed long, kept_text binary")
    return out.select(ex.id_back("doc_id"), "n_words", "n_removed", "kept_text")


def report(docs: DataFrame) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256)."""
    return dedup(docs).select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


def brute_force(rows: list[tuple[int, str | None]]) -> dict[int, tuple[int, int, str]]:
    """The contract by a dictionary of windows."""
    import re

    seen: dict[tuple, bool] = {}
    out = {}
    for doc, text in sorted(rows, key=lambda r: r[0]):
        words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
        gone = [False] * len(words)
        for i in range(len(words) - WINDOW + 1):
            w = tuple(words[i : i + WINDOW])
            if w in seen:
                gone[i : i + WINDOW] = [True] * WINDOW
            seen[w] = True
        kept = " ".join(w for w, g in zip(words, gone) if not g)
        out[doc] = (len(words), sum(gone), hashlib.sha256(kept.encode()).hexdigest())
    return out
