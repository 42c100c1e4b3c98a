"""Suffix-array dedup over bytes: every byte in a 400-byte string found elsewhere goes, all copies alike.

Equal windows are brought together by anchors (see ``repeats``). A key's differing contexts are
aligned at the anchor and cut where any two of them part, so that what two of them share around the
anchor is a run of whole segments. Segments become symbols, and one suffix array per bucket, built
by grouping on Lyndon prefixes, gives each suffix its longest match with any other occurrence;
matches of 400 bytes and more mark window starts.

Strings are judged on the input and never cross documents; a repeat inside one document counts, and
so does an overlapping one. Cases: null text is empty; shorter texts stay whole; a document stored
again (id and text) counts once, so its copies under one id do not remove each other, while equal
texts under two ids do; other columns are ignored; an empty table gives an empty result.
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
from kinward.llm.lyndon_suffixes import common_prefixes, suffix_order

WIDTH = 400
GRAM = 100


def scan(buf, off, ids, tags) -> np.ndarray:
    if len(buf) < WIDTH:
        return np.zeros(0, rp.PLACE)
    codes = ts.byte_codes(buf)
    sums = ts.prefix_sums(codes), ts.prefix_sums(codes, 1)
    p = np.arange(len(buf) - GRAM + 1)
    gram = np.full(len(buf), np.iinfo(np.uint64).max, np.uint64)
    gram[: len(p)] = ts.span_hash(sums[0], p, p + GRAM)
    at, lo, many, doc = rp.anchors(gram, off, WIDTH, (0, WIDTH - GRAM + 1))
    return rp.places(gram[at], at, lo, many, doc, sums, off, ids, tags, WIDTH)


HEAD = np.dtype(
    [("key", "u8"), ("doc", "i8"), ("tag", "i4"), ("lo", "i4"), ("left", "i4"), ("many", "i4"), ("settled", "i4"), ("size", "i4")]
)


def _pack(head: np.ndarray, body: bytes) -> bytes:
    return np.int64(len(head)).tobytes() + ex.packed(head) + body


def _unpack(block) -> tuple[np.ndarray, np.ndarray]:
    n = int(np.frombuffer(block[:8], np.int64)[0])
    cut = 8 + n * HEAD.itemsize
    return ex.unpacked(block[8:cut], HEAD), np.frombuffer(block[cut:], np.uint8)


def _deal_contexts(asked: DataFrame, buckets: int) -> DataFrame:
    arrow = pa.schema([("bucket", pa.int32()), ("block", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = ts.as_bytes(batch.column(2))
            ids, tags, cells = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(3)
            qs = [rp.joined_blocks(c.as_py(), rp.QUESTION) for c in cells]
            q = np.concatenate(qs) if qs else np.zeros(0, rp.QUESTION)
            if not len(q):
                continue
            who = np.repeat(np.arange(len(qs)), [len(x) for x in qs])
            head = np.empty(len(q), HEAD)
            for c in ("key", "left", "many", "settled"):
                head[c] = q[c]
            head["doc"], head["tag"], head["lo"] = ids[who], tags[who], q["pos"] - q["left"]
            head["size"] = q["many"] + WIDTH - 1
            begin = off[who] + head["lo"]
            to = ((head["key"] >> np.uint64(24)) % np.uint64(buckets)).astype(np.int32)
            order = np.argsort(to, kind="stable")
            at = np.append(np.flatnonzero(np.append(True, np.diff(to[order]) != 0)), len(order))
            blocks = []
            for a, b in zip(at[:-1], at[1:]):
                o = order[a:b]
                blocks.append(_pack(head[o], buf[ts.ranges(begin[o], head["size"][o].astype(np.int64))].tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array(to[order][at[:-1]]), pa.array(blocks, pa.binary())], schema=arrow)

    return asked.mapInArrow(run, ex.BLOCK_SCHEMA)


def _shared(rows: np.ndarray, reach: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Longest common prefix of each row with any other row, within both rows' reach; and those of sorted neighbours.

    Rows are padded with zeros, so a row stands before those that it begins.
    """
    g = len(rows)
    order = np.lexsort((reach, np.ascontiguousarray(rows).view(f"S{rows.shape[1]}").ravel()))
    up, down = rows[order[:-1]], rows[order[1:]]
    differ = up != down
    lcp = np.where(differ.any(axis=1), differ.argmax(axis=1), rows.shape[1])
    lcp = np.minimum(lcp, np.minimum(reach[order[:-1]], reach[order[1:]]))
    best = np.zeros(g, np.int64)
    best[order[:-1]] = lcp
    best[order[1:]] = np.maximum(best[order[1:]], lcp)
    return best, lcp


def segments(contexts: list[np.ndarray], left: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int, list[bytes]]]]:
    """Cut aligned contexts where any two part.

    Gives the cut columns (from the anchor) and for every context the range of segments that it may
    share and their bytes.
    """
    right = np.array([len(c) for c in contexts]) - left
    a, b = int(left.max()), int(right.max())
    g = len(contexts)
    fore, back = np.zeros((g, b), np.uint8), np.zeros((g, max(a, 1)), np.uint8)
    for i, c in enumerate(contexts):
        fore[i, : right[i]] = c[left[i] :]
        back[i, : left[i]] = c[: left[i]][::-1]
    far, far_cuts = _shared(fore, right)
    near, near_cuts = _shared(back, left)
    edges = np.concatenate([far, -near, far_cuts, -near_cuts, [0]])
    reach_r, reach_l = int(far.max()), int(near.max())
    ends = np.concatenate([right[right < reach_r], -left[left < reach_l]])
    cuts = np.unique(np.concatenate([edges, ends]))
    cuts = cuts[(cuts >= -reach_l) & (cuts <= reach_r)]
    coded = []
    lo, hi = np.searchsorted(cuts, -near), np.searchsorted(cuts, far)
    for i, c in enumerate(contexts):
        x, data = (cuts[lo[i] : hi[i] + 1] + left[i]).tolist(), c.tobytes()
        coded.append((int(lo[i]), int(hi[i]), [data[a:b] for a, b in zip(x, x[1:])]))
    return cuts, coded


def match_runs(groups: list[tuple[list[np.ndarray], np.ndarray]]) -> list[tuple[int, int, int, int]]:
    """(group, context, column, length): longest matches of at least WIDTH from each cut column.

    One suffix array over the segment symbols of all groups. A symbol names group, column and bytes:
    contexts of two keys, or of two columns, may be the same place of a document, which is no repeat.
    """
    names: dict[tuple[int, int, bytes], int] = {}
    coded_as, owner, column, spans = [], [], [], []
    for gi, (contexts, left) in enumerate(groups):
        cuts, coded = segments(contexts, left)
        for ci, (lo, hi, bodies) in enumerate(coded):
            if hi <= lo:
                continue
            coded_as += [names.setdefault((gi, k, body), len(names)) for k, body in enumerate(bodies, lo)]
            owner.append((gi, ci))
            column.append(cuts[lo : hi + 1])
            spans.append(hi - lo)
    if not names:
        return []
    text, home = [], []
    at = 0
    for i, n in enumerate(spans):  # a separator of its own after every context
        text += [x + len(spans) + 1 for x in coded_as[at : at + n]]
        text.append(i + 1)
        home += [(i, k) for k in range(n)]
        home.append((i, -1))
        at += n
    text.append(0)
    order = suffix_order(text)
    lcp = common_prefixes(text, order)
    lcp.append(0)
    found = []
    for r in range(1, len(order)):
        most = max(lcp[r], lcp[r + 1])
        if most:
            i, k = home[order[r]]
            x = column[i]
            if x[k + most] - x[k] >= WIDTH:
                found.append((*owner[i], int(x[k]), int(x[k + most] - x[k])))
    return found


def _compare(blocks: DataFrame, buckets: int) -> DataFrame:
    def fold(heads: list[np.ndarray], bodies: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        head = np.concatenate(heads)
        body = np.concatenate(bodies)
        begin = np.cumsum(head["size"].astype(np.int64)) - head["size"]
        order = np.lexsort([head[c] for c in ("many", "left", "lo", "tag", "doc", "key")])
        head, begin = head[order], begin[order]
        once = np.append(True, head[1:] != head[:-1])  # a row that is stored again asks again
        head, begin = head[once], begin[once]
        at = ts.group_bounds(head["key"])
        out = []
        groups, bases, held = [], [], 0

        def flush():
            for gi, ci, x, length in match_runs(groups):
                h = head[bases[gi] + ci]
                lo = max(0, x + int(h["left"]))
                hi = min(int(h["many"]), x + int(h["left"]) + length - WIDTH + 1)
                if hi > lo and not h["settled"]:
                    out.append((int(h["doc"]), int(h["tag"]), int(h["lo"]) + lo, hi - lo))

        for i, j in zip(at[:-1].tolist(), at[1:].tolist()):
            if j - i < 2:
                continue
            groups.append(([body[begin[k] : begin[k] + head["size"][k]] for k in range(i, j)], head["left"][i:j].astype(np.int64)))
            bases.append(i)
            held += j - i
            if held > 20_000:
                flush()
                groups, bases, held = [], [], 0
        flush()
        if out:
            rows = np.array(sorted(set(out)), dtype=[("doc", "i8"), ("tag", "i4"), ("lo", "i4"), ("many", "i4")])
            run = np.empty(len(rows), rp.RUN)
            run["lo"], run["many"], run["n"] = rows["lo"], rows["many"], 1
            yield from ex.reply_batches(rows["doc"], rows["tag"], run)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, heads, bodies = None, [], []
        for batch in batches:
            for b, block in zip(batch.column(0).to_pylist(), batch.column(1)):
                if b != at and heads:
                    yield from fold(heads, bodies)
                    heads, bodies = [], []
                at = b
                h, body = _unpack(block.as_buffer())
                heads.append(h)
                bodies.append(body)
        if heads:
            yield from fold(heads, bodies)

    return blocks.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(run, ex.REPLY_SCHEMA)


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept): the bytes that stay."""
    rows, runs = rp.find_runs(
        ex.keyed(docs, id_col, text_col), scan, lambda asked, n: _compare(_deal_contexts(asked, n), n), earlier=False
    )
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary"
    arrow = pa.schema(
        [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept", pa.binary())]
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = ts.as_bytes(batch.column(2))
            cells = batch.column(3)
            for lo in range(0, batch.num_rows, 512):
                hi = min(lo + 512, batch.num_rows)
                removed, spans, kept = [], [], []
                for k in range(lo, hi):
                    text = buf[off[k] : off[k + 1]]
                    if cells[k].is_valid:
                        gone = rp.covered(rp.joined_blocks(cells[k].as_py(), rp.RUN), len(text), WIDTH)
                        removed.append(int(gone.sum()))
                        spans.append(int((gone & ~np.append(False, gone[:-1])).sum()))
                        kept.append(text[~gone].tobytes())
                    else:
                        removed.append(0)
                        spans.append(0)
                        kept.append(text.tobytes())
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(lo, hi - lo), pa.array(np.diff(off[lo : hi + 1])), pa.array(removed, pa.int64()),
                        pa.array(spans, pa.int64()), pa.array(kept, pa.binary()),
                    ],
                    schema=arrow,
                )

    out = rows.join(runs, ["doc_key", "doc_tag"], "left").select("doc_key", "doc_tag", "text", "blocks").mapInArrow(run, schema)
    return out.select(ex.id_back("doc_id"), "n_bytes", "n_removed", "n_spans", "kept")


def report(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256)."""
    return dedup(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def brute_force(rows: list[tuple[int, str | None]], width: int = WIDTH) -> dict[int, tuple[int, int, int, str]]:
    """The contract by a dictionary of strings."""
    from collections import Counter

    data = {doc: (text or "").encode() for doc, text in rows}
    seen = Counter(hash(t[i : i + width]) for t in data.values() for i in range(len(t) - width + 1))
    out = {}
    for doc, t in data.items():
        gone = np.zeros(len(t) + 1, np.int32)
        for i in range(len(t) - width + 1):
            if seen[hash(t[i : i + width])] > 1:
                gone[i] += 1
                gone[i + width] -= 1
        gone = np.cumsum(gone[:-1]) > 0
        kept = np.frombuffer(t, np.uint8)[~gone].tobytes()
        out[doc] = (len(t), int(gone.sum()), int((gone & ~np.append(False, gone[:-1])).sum()) if len(t) else 0, hashlib.sha256(kept).hexdigest())
    return out
