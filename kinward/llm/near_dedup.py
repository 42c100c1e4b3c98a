"""MinHash near-dedup with weighted signatures (BagMinHash) over multisets of word shingles.

A shingle of weight w owns the levels 1..w. Levels lie in dyadic blocks (1), (2), (3,4), (5..8) ...;
each block of a shingle is a Poisson process in time whose points carry a signature slot and a
level, and points above the weight are passed over. A slot keeps its earliest point, so two
documents agree in a slot with probability equal to their weighted Jaccard similarity. Processes are
run up to a time that all slots will have been hit by, and longer where one has not.

Signatures are banded; documents of equal multisets travel as one. Within a band group, documents
whose short signatures agree well enough are joined to a spanning forest (searched breadth first, so
a group of alike documents costs one comparison each); the forests' components over all bands are
families. The forest's own edges are verified first, on the whole multisets; where they hold, a
family is one class and no more is compared, however large it is. Of the other families, what lies
outside the largest class is compared with all members in blocks of bounded size, so that no pairs
travel: pairs come in the order of their signatures' agreement, and those already in one class are
passed over. Classes are the connected components of all that was verified.

What the signatures can miss: a pair at the similarity 0.8 shares no band with a probability of
5e-5, and falls below either agreement bound (4.5 standard deviations down) with one below 1e-5.

Cases: null and empty texts have no shingles and are classes of their own; texts under five words
are one shingle; repeated rows fall in one class; unlike texts of one id are nodes of their own, so
two classes may bear one number in ``report`` (``first`` of ``classes`` tells them apart); null ids
are told apart by their text; ties go to the least id; other columns are ignored by ``classes`` and
passed on by ``keep_one``, one row of every class; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinward.llm import exchange as ex
from kinward.llm import textscan as ts
from kinward.llm.components import components

WORDS, SIMILARITY = 5, 0.8
SLOTS, BANDS, ROWS = 128, 25, 5
FLUSH = 250_000  # shingles whose signatures are made at a time


def shingles(buf: np.ndarray, off: np.ndarray, words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of every shingle, sorted; a shorter text is one shingle."""
    s, e, doc = ts.word_spans(buf, off)
    codes = ts.span_hash(ts.prefix_sums(ts.byte_codes(buf)), s, e)
    woff = np.searchsorted(doc, np.arange(len(off)))
    n = np.diff(woff)
    count = np.where(n >= words, n - words + 1, (n > 0).astype(np.int64))
    p = ts.ranges(woff[:-1], count)
    of = np.repeat(np.arange(len(n)), count)
    h = ts.span_hash(ts.prefix_sums(codes), p, p + np.minimum(words, n)[of])
    order = np.lexsort((h, of))
    return of[order], h[order]


def multiset(of: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, hash, weight) of the distinct shingles."""
    at = ts.group_bounds(of, h)
    return of[at[:-1]], h[at[:-1]], np.diff(at)


def signatures(of: np.ndarray, h: np.ndarray, w: np.ndarray, n_docs: int, slots: int = SLOTS) -> np.ndarray:
    """Earliest point of every slot, as (n_docs, slots) times; rows without shingles stay infinite."""
    sig = np.full(n_docs * slots, np.inf)
    total = np.bincount(of, weights=w, minlength=n_docs)
    parts = [(of, ts.mix64(h ^ np.uint64(0xA5A5)), np.ones(len(of)), np.zeros(len(of)), w)]
    block, more = 1, w > 1
    while more.any():
        low = float(1 << (block - 1))
        k = np.flatnonzero(more)
        seed = ts.mix64(h[k] ^ np.uint64(0xA5A5 + 7919 * block))
        parts.append((of[k], seed, np.full(len(k), low), np.full(len(k), low), w[k]))
        more = w > (1 << block)
        block += 1
    doc, seed, length, base, weight = (np.concatenate(x) for x in zip(*parts))
    weight = weight.astype(float)
    with np.errstate(divide="ignore"):
        horizon = (np.log(slots) + 5) / total
    todo = np.flatnonzero(total > 0)
    while len(todo):
        open_doc = np.zeros(n_docs, bool)
        open_doc[todo] = True
        live = np.flatnonzero(open_doc[doc])
        t, k = np.zeros(len(live)), 0
        d, s, r, b, x = doc[live], seed[live], length[live] * slots, base[live], weight[live]
        plain = b + length[live] <= x  # the whole block lies under the weight
        while len(d):
            bits = ts.mix64(s + np.uint64(k * 0x9E3779B97F4A7C15 % (1 << 64)))
            t = t - np.log(((bits >> np.uint64(11)).astype(float) + 0.5) * 2.0**-53) / r
            on = t < horizon[d]
            if not on.all():
                d, s, r, b, x, t, bits, plain = d[on], s[on], r[on], b[on], x[on], t[on], bits[on], plain[on]
            slot = d * slots + (bits & np.uint64(slots - 1)).astype(np.int64)
            if plain.all():
                np.minimum.at(sig, slot, t)
            else:
                level = (ts.mix64(bits) >> np.uint64(11)).astype(float) * 2.0**-53 * (r / slots) + b
                use = plain | (level < x)
                np.minimum.at(sig, slot[use], t[use])
            k += 1
        todo = todo[np.isinf(sig.reshape(n_docs, slots)[todo]).any(axis=1)]
        horizon[todo] *= 2
    return sig.reshape(n_docs, slots)


def band_keys(sig: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """64-bit key of every band."""
    bits = np.ascontiguousarray(sig[:, : bands * rows]).view(np.uint64).reshape(len(sig), bands, rows)
    key = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93), (len(sig), bands))
    for r in range(rows):
        key = ts.mix64(key * np.uint64(0x9E3779B97F4A7C15) + bits[:, :, r])
    return key


def node_of(id_col: str, text_col: str) -> Column:
    """A hash of id and text; of the text alone where the id is null."""
    return F.xxhash64(F.col(id_col).cast("long"), F.coalesce(F.col(text_col).cast("string"), F.lit("")))


def _number() -> Column:
    """The id; a null id is replaced by one from the far negative range, made of the text."""
    return F.coalesce(F.col("doc_id"), F.shiftrightunsigned("node", 2) + F.lit(-(2**63)))


SIGNED = "node long, doc_id long, print1 long, print2 long, n int, bands binary, sig binary"
_SIGNED = pa.schema(
    [("node", pa.int64()), ("doc_id", pa.int64()), ("print1", pa.int64()), ("print2", pa.int64()), ("n", pa.int32()), ("bands", pa.binary()), ("sig", pa.binary())]
)


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def flush(rows, of, h, w, n):
        of, h, w = np.concatenate(of), np.concatenate(h), np.concatenate(w)
        prints = []
        for salt in (0x1234567, 0x89ABCDE):
            with np.errstate(over="ignore"):
                x = ts.mix64(h + np.uint64(salt)) * w.astype(np.uint64)
                sums = np.append(np.uint64(0), np.cumsum(x, dtype=np.uint64))
                at = np.searchsorted(of, np.arange(n + 1))
                prints.append((sums[at[1:]] - sums[at[:-1]]).view(np.int64))
        size = np.bincount(of, weights=w, minlength=n).astype(np.int32)
        times = signatures(of, h, w, n)
        keys = band_keys(times)
        short = (ts.mix64(times.view(np.uint64)) & np.uint64(255)).astype(np.uint8)
        sig = [x.tobytes() for x in short]
        bands = [keys[i].tobytes() if size[i] else None for i in range(n)]
        ids = pa.chunked_array([r[0] for r in rows]).combine_chunks(), pa.chunked_array([r[1] for r in rows]).combine_chunks()
        yield pa.RecordBatch.from_arrays(
            [*ids, pa.array(prints[0]), pa.array(prints[1]), pa.array(size), pa.array(bands, pa.binary()), pa.array(sig, pa.binary())], schema=_SIGNED
        )

    rows, held, n, most = [], ([], [], []), 0, 0
    for batch in batches:
        buf, off = ts.as_bytes(batch.column(2))
        for i, j in ts.pieces(buf, off):
            of, h, w = multiset(*shingles(buf[off[i] : off[j]], off[i : j + 1] - off[i]))
            rows.append((batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i)))
            for cell, value in zip(held, (of + n, h, w)):
                cell.append(value)
            n += j - i
            most += len(h)
            if most > FLUSH:
                yield from flush(rows, *held, n)
                rows, held, n, most = [], ([], [], []), 0, 0
    if n:
        yield from flush(rows, *held, n)


MEMBER = np.dtype([("key", "u8"), ("node", "i8"), ("n", "i4"), ("bits", "u8", (4,))])


def agreement_bound(bits: int, sigmas: float = 4.5) -> int:
    """Slots that must agree, of SLOTS kept to some bits each."""
    p = SIMILARITY + (1 - SIMILARITY) / (1 << bits)
    return int(SLOTS * p - sigmas * np.sqrt(SLOTS * p * (1 - p)))


TWO_BITS, EIGHT_BITS = agreement_bound(2), agreement_bound(8)
_LOW = np.uint64(0x5555555555555555)


def _deal_bands(reps: DataFrame, buckets: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, _ = ts.as_bytes(batch.column(2))
            sig, _ = ts.as_bytes(batch.column(3))
            two = (sig & 3).reshape(-1, SLOTS // 4, 4)
            packed = (two[:, :, 0] | two[:, :, 1] << 2 | two[:, :, 2] << 4 | two[:, :, 3] << 6).view(np.uint64)
            rec = np.empty(batch.num_rows * BANDS, MEMBER)
            rec["key"] = np.frombuffer(keys.tobytes(), np.uint64)
            for name, i in (("node", 0), ("n", 1)):
                rec[name] = np.repeat(batch.column(i).to_numpy(), BANDS)
            rec["bits"] = np.repeat(packed, BANDS, axis=0)
            yield from ex.deal(rec, rec["key"], buckets)

    return reps.select("node", "n", "bands", "sig").mapInArrow(run, ex.BLOCK_SCHEMA)


def _fits(x, y):
    """Whether sizes allow the similarity at all."""
    return np.minimum(x, y) >= SIMILARITY * np.maximum(x, y) - 1e-9


def _forest(node: np.ndarray, n: np.ndarray, bits: np.ndarray) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the members that may be alike, from the least node on: bands give the same stars."""
    left = np.argsort(node, kind="stable")
    edges = []
    while len(left) > 1:
        queue, left = [int(left[0])], left[1:]
        while queue and len(left):
            i = queue.pop()
            differ = bits[left] ^ bits[i]
            agree = SLOTS - np.bitwise_count((differ | differ >> np.uint64(1)) & _LOW).sum(axis=1)
            near = (agree >= TWO_BITS) & _fits(n[left], n[i])
            found = left[near]
            left = left[~near]
            edges += [(int(node[i]), int(node[j])) for j in found]
            queue += found.tolist()
    return edges


_EDGES = pa.schema([("a", pa.int64()), ("b", pa.int64())])
PART = 128  # edges of one node that travel together


def _link_groups(rec: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Forest edges of every band group of a bucket."""
    rec = rec[np.argsort(rec["key"], kind="stable")]
    at = ts.group_bounds(rec["key"])
    rec = rec[np.repeat(np.diff(at) > 1, np.diff(at))]
    at = ts.group_bounds(rec["key"])
    edges: dict[tuple[int, int], int] = {}
    for i, j in zip(at[:-1].tolist(), at[1:].tolist()):
        g = rec[i:j]
        found = {(min(e), max(e)) for e in _forest(g["node"], g["n"], g["bits"]) if e[0] != e[1]}
        degree: dict[int, int] = {}
        for a, b in sorted(found):
            nth = degree[a] = degree.get(a, -1) + 1
            edges[a, b] = min(edges.get((a, b), nth // PART), nth // PART)
    if edges:
        a, b = zip(*edges)
        yield pa.RecordBatch.from_arrays(
            [pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(list(edges.values()), pa.int32())],
            schema=_EDGES.append(pa.field("part", pa.int32())),
        )


def element_set(h: np.ndarray) -> bytes:
    """A sorted multiset as distinct 48-bit elements: the i-th copy of a shingle is an element of its own."""
    at = ts.group_bounds(h)
    nth = np.arange(len(h)) - np.repeat(at[:-1], np.diff(at))
    x = np.unique(ts.mix64(h + nth.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) & np.uint64((1 << 48) - 1))
    return x.view(np.uint8).reshape(-1, 8)[:, :6].T.tobytes()


def elements(data: bytes) -> np.ndarray:
    cells = np.zeros((len(data) // 6, 8), np.uint8)
    cells[:, :6] = np.frombuffer(data, np.uint8).reshape(6, -1).T
    return cells.view(np.uint64).ravel()


def overlap(x: np.ndarray, y: np.ndarray) -> int:
    at = np.searchsorted(x, y)
    at[at == len(x)] = 0
    return int((x[at] == y).sum()) if len(x) else 0


def _sets(rows: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, elements) of the nodes asked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = ts.as_bytes(batch.column(1))
            for i, j in ts.pieces(buf, off):
                of, h = shingles(buf[off[i] : off[j]], off[i : j + 1] - off[i])
                at = np.searchsorted(of, np.arange(j - i + 1))
                data = [element_set(h[a:b]) for a, b in zip(at[:-1], at[1:])]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, j - i), pa.array(data, pa.binary())], names=["node", "elements"]
                )

    return rows.join(nodes, "node", "left_semi").select("node", "text").mapInArrow(run, "node long, elements binary")


BLOCK = 1024


def _verified(family: pa.Table) -> pa.Table:
    """Links of a family's block (or pair of blocks) that connect its known classes."""
    nodes, sides, known = family["node"].to_numpy(), family["side"].to_numpy(), family["known"].to_numpy()
    n = family["n"].to_numpy()
    sig = ts.as_bytes(family["sig"])[0].reshape(-1, SLOTS)
    sets = [elements(x.as_py()) for x in family["elements"]]
    _, root = np.unique(known, return_inverse=True)
    first = np.zeros(len(nodes), np.int64)
    first[root[::-1]] = np.arange(len(nodes))[::-1]
    root = first[root].tolist()  # members of a class that is known already

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    rows, cols, agree = [], [], []
    for i in range(len(nodes) - 1):  # a row of the agreement matrix at a time
        rest = np.arange(i + 1, len(nodes))
        if sides.any():
            rest = rest[sides[rest] != sides[i]]
        rest = rest[known[rest] != known[i]]
        rest = rest[_fits(n[rest], n[i])]
        same = (sig[rest] == sig[i]).sum(axis=1)
        ok = same >= EIGHT_BITS
        rows.append(np.full(int(ok.sum()), i))
        cols.append(rest[ok])
        agree.append(same[ok])
    links = []
    if rows:
        rows, cols, agree = (np.concatenate(x) for x in (rows, cols, agree))
        for k in np.argsort(-agree, kind="stable").tolist():
            i, j = int(rows[k]), int(cols[k])
            p, q = find(i), find(j)
            if p == q:
                continue
            both = overlap(sets[i], sets[j])
            if both >= SIMILARITY * (len(sets[i]) + len(sets[j]) - both) - 1e-9:
                root[q] = p
                links.append((int(known[i]), int(known[j])))
    a, b = zip(*links) if links else ((), ())
    return pa.Table.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], schema=_EDGES)


def _tried(edges: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b, alike): whether the ends of the forest's edges are alike in full.

    The edges of a common node lie in parts of bounded size, which is how often its set is sent on a side.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3)):
                x, y = elements(x.as_py()), elements(y.as_py())
                both = overlap(x, y)
                keep.append(both >= SIMILARITY * (len(x) + len(y) - both) - 1e-9)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(keep, pa.bool_())], names=["a", "b", "alike"])

    a = edges.select("a", "part").distinct().join(sets.select(F.col("node").alias("a"), F.col("elements").alias("ea")), "a")
    b = edges.join(sets.select(F.col("node").alias("b"), F.col("elements").alias("eb")), "b")
    return b.join(a, ["a", "part"]).select("a", "b", "ea", "eb").mapInArrow(run, "a long, b long, alike boolean")


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(node, doc_id, class_id, first): one row per document; the least id of its class and that one's node."""
    with ex.small_batches(docs.sparkSession):
        return _classes(docs, id_col, text_col)


def _classes(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    rows = docs.select(
        node_of(id_col, text_col).alias("node"),
        F.col(id_col).cast("long").alias("doc_id"),
        F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"),
    )
    buckets = ex.bucket_count(rows)
    signed = ex.cut(rows.mapInArrow(_sign, SIGNED))
    same = ["print1", "print2", "n"]
    low = F.struct(_number().alias("number"), F.col("node").alias("node"))
    reps = ex.cut(
        signed.filter("n > 0")
        .groupBy(*same)
        .agg(F.min(F.struct("node", "bands", "sig")).alias("r"), F.min(low).alias("low"))
        .select(*same, *[F.col(f"r.{c}").alias(c) for c in ("node", "bands", "sig")], "low")
    )
    edges = ex.per_bucket(_deal_bands(reps, buckets), MEMBER, _link_groups, "a long, b long, part int", buckets)
    edges = ex.cut(edges.groupBy("a", "b").agg(F.min("part").alias("part")))
    nodes = edges.select(F.col("a").alias("node")).unionByName(edges.select(F.col("b").alias("node"))).distinct()
    sets = ex.cut(_sets(rows, nodes).dropDuplicates(["node"]))
    tried = ex.cut(_tried(edges, sets))
    known = ex.cut(components(tried.filter("alike").select("a", "b")))
    roots = _with_rest(nodes, known, tried.filter("NOT alike"), sets, reps)
    of = reps.select(*same, F.col("node").alias("rep"), "low")
    roots = roots.withColumnRenamed("node", "rep")
    least = of.join(roots, "rep").groupBy("root").agg(F.min("low").alias("least"))
    out = signed.select("node", "doc_id", *same).join(of, same, "left")
    out = out.join(roots.join(least, "root").select("rep", "least"), "rep", "left")
    out = out.withColumn("of", F.coalesce("least", "low", low))
    return out.select("node", "doc_id", F.col("of.number").alias("class_id"), F.col("of.node").alias("first"))


def _with_rest(nodes: DataFrame, known: DataFrame, failed: DataFrame, sets: DataFrame, reps: DataFrame) -> DataFrame:
    """(node, root) of all classes: the known ones, joined by what else is alike in their families.

    Edges that failed tie known classes into families; in each, members outside the largest class
    meet all members, and links found join whole classes.
    """
    root = known.select(F.col("node").alias("x"), F.col("root").alias("r"))
    ties = failed
    for end in ("a", "b"):
        ties = ties.join(root.withColumnRenamed("x", end).withColumnRenamed("r", f"r{end}"), end, "left")
    ties = ties.select(F.coalesce("ra", "a").alias("a"), F.coalesce("rb", "b").alias("b")).filter("a <> b").distinct()
    families = components(ties).select(F.col("node").alias("known"), F.col("root").alias("family"))
    members = nodes.join(known, "node", "left").select("node", F.coalesce("root", "node").alias("known")).join(families, "known")
    size = members.groupBy("family", "known").agg(F.count(F.lit(1)).alias("c"))
    whole = size.groupBy("family").agg(F.max(F.struct("c", "known")).alias("top"), F.sum("c").alias("all"))
    parted = whole.select(
        "family", F.col("top.known").alias("bulk"), F.ceil(F.col("top.c") / BLOCK).cast("int").alias("nb"),
        F.ceil((F.col("all") - F.col("top.c")) / BLOCK).cast("int").alias("nr"),
    )
    placed = members.join(parted, "family").withColumn("inner", F.col("known") == F.col("bulk"))
    placed = placed.withColumn("mine", F.pmod(F.xxhash64("node"), F.when(F.col("inner"), F.col("nb")).otherwise(F.col("nr"))).cast("int"))
    # blocks of the rest (numbers from 0) meet each other and the blocks of the bulk (numbers from nr)
    rest = F.sequence(F.lit(0), F.col("nr") - 1)
    others = F.when(F.col("inner"), rest).otherwise(F.concat(rest, F.sequence(F.col("nr"), F.col("nr") + F.col("nb") - 1)))
    placed = placed.withColumn("mine", F.when(F.col("inner"), F.col("mine") + F.col("nr")).otherwise(F.col("mine")))
    full = placed.join(reps.select("node", "n", "sig"), "node").join(sets, "node")
    dealt = full.withColumn("other", F.explode(others)).select(
        "family", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"),
        F.when(F.col("mine") > F.col("other"), 1).otherwise(0).alias("side"), "node", "known", "n", "sig", "elements",
    )
    links = dealt.groupBy("family", "i", "j").applyInArrow(_verified, "a long, b long")
    joined = components(links).select(F.col("node").alias("known"), F.col("root").alias("top"))
    every = known.unionByName(joined.select(F.col("known").alias("node"), F.col("known").alias("root"))).distinct()
    return every.join(joined.withColumnRenamed("known", "root"), "root", "left").select("node", F.coalesce("top", "root").alias("root"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The document of least id of every class, with all its columns."""
    table = classes(docs, id_col, text_col).groupBy("node").agg(F.min("first").alias("first"), F.count(F.lit(1)).alias("c"))
    stay = table.filter("node = first").select(F.col("node").alias("kw_node"), F.col("c").alias("kw_c"))
    out = docs.withColumn("kw_node", node_of(id_col, text_col)).join(stay, "kw_node")
    once = out.filter("kw_c = 1").unionByName(out.filter("kw_c > 1").dropDuplicates(["kw_node"]))
    return once.select(*[F.col(f"`{c}`") for c in docs.columns])


def report(docs: DataFrame) -> DataFrame:
    """(doc_id, class_id)."""
    return classes(docs).select("doc_id", "class_id")


def brute_force(rows: list[tuple[int, str | None]]) -> dict[int, int]:
    """Classes by the similarity of all pairs that share a shingle."""
    import re
    from collections import Counter, defaultdict

    bags = {}
    for doc, text in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
        bags[doc] = Counter(tuple(w[i : i + WORDS]) for i in range(max(1, len(w) - WORDS + 1))) if w else Counter()
    root = {d: d for d in bags}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    holders = defaultdict(list)
    for d, bag in bags.items():
        for s in bag:
            holders[s].append(d)
    seen = set()
    for ds in holders.values():
        for i, a in enumerate(ds):
            for b in ds[i + 1 :]:
                if (a, b) not in seen:
                    seen.add((a, b))
                    both = sum((bags[a] & bags[b]).values())
                    if 10 * both >= 8 * (sum(bags[a].values()) + sum(bags[b].values()) - both):
                        x, y = sorted((find(a), find(b)))
                        root[y] = x
    return {d: find(d) for d in bags}
