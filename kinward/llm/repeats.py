"""Windows that repeat across a corpus, found exactly with folded shuffles.

Texts are sequences of symbols (words or bytes). Every window of ``width`` symbols names one anchor
inside itself from its own content alone, so equal windows name equal anchors at equal offsets.
An anchor's key is a hash of symbols that every window naming it holds, and its context is what
those windows cover together.

Round 1 deals (key, context hashes, place) to buckets of keys. Places whose contexts agree in both
61-bit hashes (two independent bases, 122 bits: for 10^14 windows a chance under 10^-8 of any false
match) are settled there; a key with several contexts asks the first place of each. Round 2 deals
what was asked for, and compares contexts. Answers go back to the documents as runs of window starts.
A passage that a third of all documents hold is no hot bucket: a task settles the equal contexts of
its own documents (``folded``) and sends one or two places of each context, so a bucket gets as many
records of a context as there are tasks, not documents.
Consecutive anchors with equal contexts (periodic text) travel as one record with a count and stride.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinward.llm import exchange as ex
from kinward.llm import textscan as ts

FULL, ASK = 0, 1
PLACE = np.dtype(
    [("key", "u8"), ("ctx", "u8"), ("ctx2", "u8"), ("doc", "i8"), ("tag", "i4"), ("pos", "i4"), ("left", "i4"), ("many", "i4"), ("n", "i4")]
)
#: Window starts lo..lo+many-1, n times, ``many`` apart.
RUN = np.dtype([("lo", "i4"), ("many", "i4"), ("n", "i4")])
QUESTION = np.dtype([("key", "u8"), ("pos", "i4"), ("left", "i4"), ("many", "i4"), ("settled", "i4")])


def sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every ``width`` consecutive entries, by block prefix and suffix minima."""
    n = len(x) - width + 1
    if n <= 0:
        return x[:0]
    rows = -(-len(x) // width)
    grid = np.full(rows * width, np.iinfo(x.dtype).max, x.dtype)
    grid[: len(x)] = x
    grid = grid.reshape(rows, width)
    head = np.minimum.accumulate(grid, axis=1).ravel()
    tail = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(tail[:n], head[width - 1 : width - 1 + n])


def anchors(score: np.ndarray, off: np.ndarray, width: int, zone: tuple[int, int]):
    """(anchor, first window, number of windows, document) of every anchor.

    A window at p takes the least score at p+zone[0] .. p+zone[1]-1, the leftmost among equals.
    """
    n = len(score)
    none = np.zeros(0, np.int64)
    if n < width:
        return none, none, none, none
    bits = np.uint64(max(1, int(n).bit_length()))
    ranked = ((score >> bits) << bits) | np.arange(n, dtype=np.uint64)
    least = sliding_least(ranked[zone[0] :], zone[1] - zone[0])
    lens = np.diff(off)
    long = np.flatnonzero(lens >= width)
    if not len(long):
        return none, none, none, none
    count = lens[long] - width + 1
    p = ts.ranges(off[long], count)
    doc = np.repeat(long, count)
    at = (least[p] & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)
    cut = np.flatnonzero(np.append(True, (at[1:] != at[:-1]) | (doc[1:] != doc[:-1])))
    many = np.diff(np.append(cut, len(p)))
    return at[cut], p[cut], many, doc[cut]


def places(key, at, lo, many, doc, sums, off, ids, tags, width) -> np.ndarray:
    """Round-1 records; a run of neighbours with equal contexts is named once, with its length.

    ``sums`` are the prefix sums of the codes under both bases.
    """
    ctx, ctx2 = (ts.span_hash(sums[w], lo, lo + many + width - 1, w) for w in (0, 1))
    same = np.zeros(len(at), bool)
    same[1:] = (
        (doc[1:] == doc[:-1]) & (key[1:] == key[:-1]) & (ctx[1:] == ctx[:-1]) & (ctx2[1:] == ctx2[:-1]) & (many[1:] == many[:-1])
        & (at[1:] - lo[1:] == at[:-1] - lo[:-1])
    )
    cut = np.flatnonzero(~same)
    out = np.empty(len(cut), PLACE)
    d = doc[cut]
    out["key"], out["ctx"], out["ctx2"], out["doc"], out["tag"] = key[cut], ctx[cut], ctx2[cut], ids[d], tags[d]
    out["pos"], out["left"], out["many"] = at[cut] - off[d], (at - lo)[cut], many[cut]
    out["n"] = np.diff(np.append(cut, len(at)))
    return out


#: A run of windows that was settled where it was found.
PASSED = np.dtype([("doc", "i8"), ("tag", "i4"), ("lo", "i4"), ("many", "i4"), ("n", "i4")])
FOLD = 400_000  # records that a task folds at a time


def folded(rec: np.ndarray, earlier: bool) -> tuple[np.ndarray, np.ndarray]:
    """(places that others must know of, settled runs) of a task's records.

    ``earlier``: the first place of a context is sent and later ones are settled; else the first two
    are sent, which tells that there are several, and the rest is settled.
    """
    rec = rec[np.lexsort([rec[c] for c in ("n", "pos", "tag", "doc", "many", "left", "ctx2", "ctx", "key")])]
    twin = np.zeros(len(rec), bool)  # of a row that is stored again
    twin[1:] = rec[1:] == rec[:-1]
    rec = rec[~twin]
    at = ts.group_bounds(rec["key"], rec["ctx"], rec["ctx2"], rec["left"], rec["many"])
    nth = np.arange(len(rec)) - np.repeat(at[:-1], np.diff(at))
    gone = rec[nth >= (1 if earlier else 2)]
    out = np.empty(len(gone), PASSED)
    for c in ("doc", "tag", "many", "n"):
        out[c] = gone[c]
    out["lo"] = gone["pos"] - gone["left"]
    return rec[nth < (1 if earlier else 2)], out


def pass_on(rec: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Settled runs as replies."""
    rec = rec[np.lexsort((rec["tag"], rec["doc"]))]
    run = np.empty(len(rec), RUN)
    for c in ("lo", "many", "n"):
        run[c] = rec[c]
    yield from ex.reply_batches(rec["doc"], rec["tag"], run, FULL)


def deal_passed(rec: np.ndarray, buckets: int) -> Iterator[pa.RecordBatch]:
    yield from ex.deal(rec, ts.mix64(rec["doc"].view(np.uint64)), buckets, beyond=buckets)


def settle(rec: np.ndarray, earlier: bool) -> Iterator[pa.RecordBatch]:
    """Round-1 bucket: settle equal contexts, ask about keys that have several."""
    rec = rec[np.argsort(rec["key"], kind="stable")]
    at = ts.group_bounds(rec["key"])
    alone = np.repeat(np.diff(at) == 1, np.diff(at)) & (rec["n"] == 1)
    rec = rec[~alone]
    if not len(rec):
        return
    rec = rec[np.lexsort([rec[c] for c in ("n", "pos", "tag", "doc", "many", "left", "ctx2", "ctx", "key")])]
    twin = np.zeros(len(rec), bool)  # of a row that is stored again
    twin[1:] = rec[1:] == rec[:-1]
    rec = rec[~twin]
    at = ts.group_bounds(rec["key"], rec["ctx"], rec["ctx2"], rec["left"], rec["many"])
    size = np.diff(at)
    first = rec[at[:-1]]
    total = np.add.reduceat(rec["n"].astype(np.int64), at[:-1])
    by_key = ts.group_bounds(first["key"])
    several = np.repeat(np.diff(by_key) > 1, np.diff(by_key))
    settled = (total > 1) & (not earlier)
    if earlier:
        gone = np.ones(len(rec), bool)
        gone[at[:-1]] = first["n"] > 1
        skip = np.zeros(len(rec), np.int32)
        skip[at[:-1]] = 1
        gone, skip = rec[gone], skip[gone]
    else:
        gone = rec[np.repeat(settled, size)]
        skip = np.zeros(len(gone), np.int32)
        open_keys = np.repeat(np.add.reduceat((~settled).astype(int), by_key[:-1]) > 0, np.diff(by_key))
        several &= open_keys
    run = np.empty(len(gone), RUN)
    run["lo"], run["many"], run["n"] = gone["pos"] - gone["left"] + skip * gone["many"], gone["many"], gone["n"] - skip
    order = np.lexsort((gone["tag"], gone["doc"]))
    yield from ex.reply_batches(gone["doc"][order], gone["tag"][order], run[order], FULL)
    asked = first[several]
    q = np.empty(len(asked), QUESTION)
    for c in ("key", "pos", "left", "many"):
        q[c] = asked[c]
    q["settled"] = settled[several]
    order = np.lexsort((asked["tag"], asked["doc"]))
    yield from ex.reply_batches(asked["doc"][order], asked["tag"][order], q[order], ASK)


def covered(runs: np.ndarray, n: int, width: int) -> np.ndarray:
    """Which of n symbols lie in a window of the runs."""
    edge = np.zeros(n + 1, np.int32)
    if len(runs):
        lo = runs["lo"].astype(np.int64)
        np.add.at(edge, lo, 1)
        np.add.at(edge, lo + runs["many"].astype(np.int64) * runs["n"] + width - 1, -1)
    return np.cumsum(edge[:-1]) > 0


def find_runs(
    docs: DataFrame,
    scan: Callable[[np.ndarray, np.ndarray, np.ndarray, np.ndarray], np.ndarray],
    answer: Callable[[DataFrame, int], DataFrame],
    earlier: bool,
) -> tuple[DataFrame, DataFrame]:
    """(keyed documents, their runs) of (doc_key, doc_tag, text) rows.

    ``scan(buf, off, ids, tags)`` gives round-1 records of a piece; ``answer`` takes documents with
    their questions and gives runs.
    """
    buckets = ex.bucket_count(docs)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made: list[np.ndarray] = []

        def flush() -> Iterator[pa.RecordBatch]:
            rec, passed = folded(np.concatenate(made), earlier)
            made.clear()
            yield from ex.deal(rec, rec["key"], buckets)
            yield from deal_passed(passed, buckets)

        for batch in batches:
            buf, off = ts.as_bytes(batch.column(2))
            ids, tags = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for i, j in ts.pieces(buf, off):
                made.append(scan(buf[off[i] : off[j]], off[i : j + 1] - off[i], ids[i:j], tags[i:j]))
                if sum(map(len, made)) > FOLD:
                    yield from flush()
        if made:
            yield from flush()

    blocks = docs.select("doc_key", "doc_tag", "text").mapInArrow(first, ex.BLOCK_SCHEMA)
    settled = ex.per_bucket(blocks, PLACE, lambda rec: settle(rec, earlier), ex.REPLY_SCHEMA, buckets, (PASSED, pass_on))
    replies = ex.cut(settled)
    asked = ex.gathered(replies.filter(F.col("kind") == ASK))
    answers = answer(docs.join(asked, ["doc_key", "doc_tag"]).select("doc_key", "doc_tag", "text", "blocks"), buckets)
    runs = replies.filter(F.col("kind") == FULL).select("doc_key", "doc_tag", "block").unionByName(
        answers.select("doc_key", "doc_tag", "block")
    )
    return docs, ex.gathered(runs)


def joined_blocks(cell, dtype: np.dtype) -> np.ndarray:
    """Records of a list-of-binary cell."""
    if cell is None or not len(cell):
        return np.zeros(0, dtype)
    return np.concatenate([np.frombuffer(b, dtype) for b in cell])
