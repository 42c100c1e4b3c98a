"""Benchmark decontamination by greedy string tiling.

Rolling (Karp-Rabin) hashes of ``seed`` tokens of the benchmark are looked up in every document.
Each document and item that share a seed are tiled: the longest match of unmarked tokens is marked,
again and again, down to the seed length, so passages count whatever their order. A document is
contaminated by an item if the tiles cover enough of it.

Tokens are runs of letters and digits, case folded. The driver holds one block of the benchmark at a
time (``block_bytes``): a benchmark of one block travels with the scan of the documents, a larger
one takes a scan a block, whose hits are checkpointed and brought together by document.

Cases: null texts have no tokens; items under ``seed`` tokens are matched whole, those under
``least_tokens`` (default 2, so that one common word contaminates nothing) match nothing; repeated documents are judged each, repeated items count each; ties go
to the smaller position; other columns are ignored; an empty benchmark leaves all documents clean.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinward.llm import textscan as ts
from kinward.llm.exchange import cut

SEED, COVER, LEAST_TOKENS = 4, 0.5, 2
BLOCK_BYTES = 8 << 20

#: Bytes that separate tokens: ASCII but letters and digits.
_BREAKS = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


def tokens(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """64-bit codes of all tokens and their offsets by text."""
    buf, off = ts.as_bytes(pc.utf8_lower(texts.cast(pa.large_string())))
    s, e, doc = ts.word_spans(buf, off, _BREAKS)
    return ts.span_hash(ts.prefix_sums(ts.byte_codes(buf)), s, e), np.searchsorted(doc, np.arange(len(off)))


def _grams(codes: np.ndarray, off: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(position, hash) of every k tokens within one text."""
    n = np.maximum(np.diff(off) - k + 1, 0)
    p = ts.ranges(off[:-1], n)
    return p, ts.span_hash(ts.prefix_sums(codes), p, p + k)


class Benchmark:
    """Seeds of a block of benchmark items, sorted by hash."""

    def __init__(self, items: list[tuple[int, str]], seed: int = SEED, least_tokens: int = LEAST_TOKENS):
        self.ids = [i for i, _ in items]
        self.codes, self.off = tokens(pa.array([t or "" for _, t in items], pa.large_string()))
        self.size = np.diff(self.off)
        self.seed = seed
        self.seeds: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for k in sorted({min(seed, int(n)) for n in self.size if n >= max(1, least_tokens)}):
            p, h = _grams(self.codes, self.off, k)
            item = np.searchsorted(self.off, p, "right") - 1
            use = self.size[item] >= seed if k == seed else self.size[item] == k
            order = np.argsort(h[use], kind="stable")
            self.seeds[k] = h[use][order], (p[use] - self.off[item[use]])[order], item[use][order]

    def tiles(self, k: int, doc_codes: np.ndarray, item: int, at: np.ndarray, to: np.ndarray) -> int:
        """Tokens of the item that tiles cover; seeds start at ``at`` in the document, ``to`` in the item."""
        mine = self.codes[self.off[item] : self.off[item + 1]]
        order = np.lexsort((at, at - to))
        at, to = at[order], to[order]
        new = np.append(True, (np.diff(at - to) != 0) | (np.diff(at) != 1))
        cut = np.append(np.flatnonzero(new), len(at))
        heap = [(-(int(j - i) + k - 1), int(at[i]), int(to[i])) for i, j in zip(cut[:-1], cut[1:])]
        heapq.heapify(heap)
        used_doc: set[int] = set()
        used_item = np.zeros(len(mine), bool)
        while heap:
            size, a, b = heapq.heappop(heap)
            size = -size
            free, run = [], 0
            for x in range(size + 1):  # stretches of the match that are still unmarked
                if x < size and not used_item[b + x] and (a + x) not in used_doc:
                    run += 1
                else:
                    if run >= k:
                        free.append((run, x - run))
                    run = 0
            if not free:
                continue
            if free[0][0] == size:
                if np.array_equal(doc_codes[a : a + size], mine[b : b + size]):
                    used_item[b : b + size] = True
                    used_doc.update(range(a, a + size))
                continue
            for run, x in free:
                heapq.heappush(heap, (-run, a + x, b + x))
        return int(used_item.sum())

    def judge(self, codes: np.ndarray, off: np.ndarray) -> Iterator[tuple[int, int, int]]:
        """(text, item, tokens covered) of all that share a seed."""
        for k, (hashes, to, item) in self.seeds.items():
            p, h = _grams(codes, off, k)
            lo, hi = np.searchsorted(hashes, h, "left"), None
            hit = lo < len(hashes)
            hit[hit] = hashes[lo[hit]] == h[hit]
            p, h, lo = p[hit], h[hit], lo[hit]
            if not len(p):
                continue
            hi = np.searchsorted(hashes, h, "right")
            each = np.repeat(np.arange(len(p)), hi - lo)
            row = ts.ranges(lo, hi - lo)
            text = np.searchsorted(off, p[each], "right") - 1
            order = np.lexsort((item[row], text))
            each, row, text = each[order], row[order], text[order]
            at = ts.group_bounds(text, item[row])
            for i, j in zip(at[:-1].tolist(), at[1:].tolist()):
                d, it = int(text[i]), int(item[row[i]])
                yield d, it, self.tiles(k, codes[off[d] : off[d + 1]], it, p[each[i:j]] - off[d], to[row[i:j]])


def _items(benchmark: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return benchmark.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("t"))


def _block_count(items: DataFrame, block_bytes: int) -> int:
    total = items.agg(F.sum(F.octet_length("t").cast("long") + 16)).first()[0] or 0
    return max(1, math.ceil(total / block_bytes))


def _block(items: DataFrame, b: int, n: int) -> list[tuple[int, str]]:
    """One of n blocks of the items, dealt by content."""
    part = items if n == 1 else items.filter(F.pmod(F.xxhash64("id", "t"), F.lit(n)) == b)
    return [(r.id, r.t) for r in part.sort("id", "t").collect()]


VERDICT = "doc_id long, contaminated boolean, item_ids array<bigint>, coverage double"


def judge(
    docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id",
    item_text_col: str = "text", seed: int = SEED, cover: float = COVER, pass_columns: bool = False,
    least_tokens: int = LEAST_TOKENS, block_bytes: int = BLOCK_BYTES,
) -> DataFrame:
    """One row per document: whether an item is covered, which items, and the best coverage.

    ``pass_columns`` puts the rows' own columns first and the verdict's behind, prefixed by kw_.
    """
    items = _items(benchmark, item_col, item_text_col)
    n = _block_count(items, block_bytes)
    limits = (seed, cover, least_tokens)
    if n == 1:
        return _scan(docs, _block(items, 0, 1), id_col, text_col, *limits, pass_columns)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.withColumn("kw_doc", F.col(id_col).cast("long")).withColumn("kw_tag", F.xxhash64(text))
    texts = rows.select("kw_doc", "kw_tag", text.alias("kw_body"))
    hits = None
    for b in range(n):
        found = _scan(texts, _block(items, b, n), "kw_doc", "kw_body", *limits, True).filter("kw_coverage > 0")
        found = cut(found.select("kw_doc", "kw_tag", "kw_item_ids", "kw_coverage").dropDuplicates(["kw_doc", "kw_tag"]))
        hits = found if hits is None else hits.unionByName(found)
    hits = hits.groupBy("kw_doc", "kw_tag").agg(
        F.sort_array(F.flatten(F.collect_list("kw_item_ids"))).alias("item_ids"), F.max("kw_coverage").alias("coverage")
    )
    same = (F.col("r.kw_tag") == F.col("h.kw_tag")) & F.col("r.kw_doc").eqNullSafe(F.col("h.kw_doc"))
    out = rows.alias("r").join(hits.alias("h"), same, "left")
    own = [F.col(f"r.`{c}`") for c in docs.columns] if pass_columns else [F.col("r.kw_doc").alias("doc_id")]
    prefix = "kw_" if pass_columns else ""
    ids = F.coalesce("h.item_ids", F.array().cast("array<bigint>"))
    return out.select(
        *own, (F.size(ids) > 0).alias(f"{prefix}contaminated"), ids.alias(f"{prefix}item_ids"),
        F.coalesce("h.coverage", F.lit(0.0)).alias(f"{prefix}coverage"),
    )


def _scan(
    docs: DataFrame, block: list[tuple[int, str]], id_col: str, text_col: str, seed: int, cover: float, least_tokens: int, pass_columns: bool
) -> DataFrame:
    """``judge`` against one block of items, which goes with the tasks."""
    arrow = pa.schema(
        [("contaminated", pa.bool_()), ("item_ids", pa.list_(pa.int64())), ("coverage", pa.float64())]
    )
    text = F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("kw_text")
    own = [F.col(f"`{c}`") for c in docs.columns] if pass_columns else [F.col(id_col).cast("long").alias("doc_id")]
    rows = docs.select(*own, text)
    kept = rows.schema.fields[:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        b = Benchmark(block, seed, least_tokens)
        for batch in batches:
            last = batch.num_columns - 1
            _, sizes = ts.as_bytes(batch.column(last))
            for i, j in ts.pieces(sizes, sizes):
                part = batch.slice(i, j - i)
                codes, off = tokens(part.column(last))
                found: list[list[int]] = [[] for _ in range(j - i)]
                best = [0.0] * (j - i)
                for d, it, n in b.judge(codes, off):
                    share = n / int(b.size[it])
                    best[d] = max(best[d], share)
                    if share >= cover:
                        found[d].append(b.ids[it])
                made = [pa.array([bool(x) for x in found]), pa.array([sorted(x, key=lambda v: (v is not None, v or 0)) for x in found], pa.list_(pa.int64())), pa.array(best)]
                fields = [part.schema.field(x) for x in range(last)]
                names = ["kw_" + f.name for f in arrow] if pass_columns else arrow.names
                yield pa.RecordBatch.from_arrays(
                    [part.column(x) for x in range(last)] + made,
                    schema=pa.schema(fields + [pa.field(n, f.type) for n, f in zip(names, arrow)]),
                )

    from pyspark.sql import types as T

    prefix = "kw_" if pass_columns else ""
    out = T.StructType(
        [
            *kept,
            T.StructField(f"{prefix}contaminated", T.BooleanType()),
            T.StructField(f"{prefix}item_ids", T.ArrayType(T.LongType())),
            T.StructField(f"{prefix}coverage", T.DoubleType()),
        ]
    )
    return rows.mapInArrow(run, out)


def keep_clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The documents that no item contaminates, with all their columns."""
    out = judge(docs, benchmark, pass_columns=True, **options)
    return out.filter(~F.col("kw_contaminated")).select(*[F.col(f"`{c}`") for c in docs.columns])


def report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, contaminated, item_ids, coverage) with ids joined by commas."""
    return judge(docs, benchmark).select(
        "doc_id", "contaminated", F.array_join(F.col("item_ids").cast("array<string>"), ",").alias("item_ids"), F.round("coverage", 6).alias("coverage")
    )


def brute_force(docs: list[tuple], items: list[tuple], seed: int = SEED, cover: float = COVER, least_tokens: int = LEAST_TOKENS) -> list[tuple]:
    """(id, contaminated, items, coverage) by tiling every document with every item, all matches searched anew for each tile."""
    import re

    split = lambda t: re.findall(r"[^\x00-\x2f\x3a-\x40\x5b-\x60\x7b-\x7f]+", (t or "").lower())
    out = []
    for doc, text in docs:
        d, hits, best = split(text), [], 0.0
        for item, body in items:
            m = split(body)
            if len(m) < max(1, least_tokens):
                continue
            least, free_d, free_m = min(seed, len(m)), [True] * len(d), [True] * len(m)
            while True:
                longest = (0, 0, 0)
                for a in range(len(d)):
                    for b in range(len(m)):
                        n = 0
                        while a + n < len(d) and b + n < len(m) and d[a + n] == m[b + n] and free_d[a + n] and free_m[b + n]:
                            n += 1
                        if n > longest[0]:
                            longest = (n, a, b)
                n, a, b = longest
                if n < least:
                    break
                free_d[a : a + n] = [False] * n
                free_m[b : b + n] = [False] * n
            share = free_m.count(False) / len(m)
            best = max(best, share)
            if share >= cover:
                hits.append(-1 if item is None else item or -1)
        out.append((doc, bool(hits), sorted(hits), round(best, 6)))
    return out
