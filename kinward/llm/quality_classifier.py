"""Quality classifier by co-training of two views, for quality and for toxicity.

One view is the text (hashed words, beginnings and endings of words, and a few densities), the other the page's
metadata (source, language, length). Both are logistic models fitted on a bounded sample of
labelled rows. For some rounds Spark scores every unlabelled document by each view and the ones a
view is surest of, with its verdict, go to the other view. In the end each view is calibrated on
labelled rows kept from the fit and the two are combined there; a last part of the labelled rows
measures the result (``held_out``), which scores every document in one pass.

Bounds (parameters): at most ``labelled`` labelled rows, and ``handed`` documents a round, view and
target, reach the driver; these are all that is fitted.
Cases: null text is empty, null metadata a value of its own; conflicting labels of one id count as
bad quality and as toxic; with fewer than ``least_labels`` rows, or labels of one kind only, the
score is the share known (or one half); repeated rows are scored each; other columns are ignored;
an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinward.llm import textscan as ts

#: (bits of the hash space, bytes of the word it sees: whole, beginnings, ending) of each family of text features.
FAMILIES = ((14, None), (13, 7), (12, 6), (12, 5), (10, -3))
DENSE = 8
TEXT_DIM = sum(1 << bits for bits, _ in FAMILIES) + DENSE
META_DIM = 256
LABELLED, HANDED, LEAST_LABELS = 5000, 200, 20
ROUNDS, SURE = 2, 0.97

_KIND = np.zeros(256, np.uint8)  # 1 symbol, 2 upper case, 3 digit
_KIND[[ord(c) for c in "#*$%&|<>{}[]=+~^_@!\\/"]] = 1
_KIND[ord("A") : ord("Z") + 1] = 2
_KIND[ord("0") : ord("9") + 1] = 3


@dataclass
class Rows:
    """Sparse rows: offsets, columns, values."""

    at: np.ndarray
    col: np.ndarray
    val: np.ndarray

    def take(self, rows: np.ndarray) -> Rows:
        n = np.diff(self.at)[rows]
        i = ts.ranges(self.at[rows], n)
        return Rows(np.append(0, np.cumsum(n)), self.col[i], self.val[i])

    def dot(self, w: np.ndarray) -> np.ndarray:
        return np.add.reduceat(np.append(self.val * w[self.col], 0.0), self.at[:-1]) * (np.diff(self.at) > 0)

    @staticmethod
    def stack(parts: list[Rows]) -> Rows:
        sizes = np.concatenate([np.diff(p.at) for p in parts])
        return Rows(np.append(0, np.cumsum(sizes)), np.concatenate([p.col for p in parts]), np.concatenate([p.val for p in parts]))


def text_rows(buf: np.ndarray, off: np.ndarray) -> Rows:
    """Features of texts: damped counts of hashed words and parts of words, and densities."""
    n = len(off) - 1
    sums = ts.prefix_sums(ts.byte_codes(buf))
    s, e, doc = ts.word_spans(buf, off)
    parts, base = [], 0
    for bits, reach in FAMILIES:
        if reach is None:
            a, b, use = s, e, slice(None)
        elif reach < 0:
            a, b, use = np.maximum(s, e + reach), e, slice(None)
        else:
            use = e - s > reach
            a, b = s[use], s[use] + reach
        parts.append(doc[use] * TEXT_DIM + base + (ts.span_hash(sums, a, b) & np.uint64((1 << bits) - 1)).astype(np.int64))
        base += 1 << bits
    keys, count = np.unique(np.concatenate(parts), return_counts=True)
    row, col = keys // TEXT_DIM, keys % TEXT_DIM
    val = np.log1p(count)
    kinds = [np.append(0, np.cumsum(_KIND[buf] == k))[off] for k in (1, 2, 3)]
    size = np.maximum(np.diff(off), 1)
    words = np.bincount(doc, minlength=n)
    distinct = np.bincount(row[col < (1 << FAMILIES[0][0])], minlength=n)
    dense = np.stack(
        [
            *[np.minimum(10 * np.diff(k) / size, 5) for k in kinds],
            2 * distinct / np.maximum(words, 1),
            np.minimum(size / np.maximum(words, 1) / 5, 4),
            np.log1p(words) / 4,
            (words == 0).astype(float),
            np.minimum(5 * np.diff(np.append(0, np.cumsum(buf == 10))[off]) / np.maximum(words, 1), 3),
        ],
        axis=1,
    )
    all_row = np.concatenate([row, np.repeat(np.arange(n), DENSE)])
    all_col = np.concatenate([col, np.tile(np.arange(TEXT_DIM - DENSE, TEXT_DIM), n)])
    order = np.argsort(all_row, kind="stable")
    return Rows(
        np.searchsorted(all_row[order], np.arange(n + 1)), all_col[order].astype(np.int32), np.concatenate([val, dense.ravel()])[order]
    )


def meta_rows(source: pa.Array, lang: pa.Array, n_chars: pa.Array) -> Rows:
    """Features of metadata: hashed source and language, length class, and a constant."""
    import pyarrow.compute as pc

    cols = []
    for values, base, width in ((source, 0, 128), (lang, 128, 64)):
        buf, off = ts.as_bytes(pc.fill_null(values.cast(pa.large_string()), "\x00none"))
        cols.append(base + (ts.text_hash(buf, off) % np.uint64(width)).astype(np.int64))
    chars = pc.fill_null(n_chars.cast(pa.int64()), 0).to_numpy(zero_copy_only=False)
    cols.append(192 + np.minimum(np.log2(np.maximum(chars, 0) + 1).astype(np.int64), 40))
    n = len(chars)
    col = np.stack(cols, axis=1).ravel()
    return Rows(np.arange(n + 1) * 3, col.astype(np.int32), np.ones(3 * n))


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def fit(rows: Rows, y: np.ndarray, dim: int, steps: int = 120, decay: float = 2e-3) -> np.ndarray:
    """Logistic weights (the last is the constant) by accelerated gradient steps."""
    n = len(y)
    w, v, moment = np.zeros(dim + 1), np.zeros(dim + 1), np.zeros(dim + 1)
    of = np.repeat(np.arange(n), np.diff(rows.at))
    for step in range(1, steps + 1):  # Adam
        miss = (_sigmoid(rows.dot(w[:-1]) + w[-1]) - y) / n
        grad = np.append(np.bincount(rows.col, weights=rows.val * miss[of], minlength=dim), miss.sum())
        grad[:-1] += decay * w[:-1]
        moment = 0.9 * moment + 0.1 * grad
        v = 0.99 * v + 0.01 * grad * grad
        w -= 0.08 * (moment / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return w


def fit_text(rows: Rows, y: np.ndarray) -> np.ndarray:
    """Weights of the text view, each feature scaled by how its presence differs between the classes."""
    sparse = rows.col < TEXT_DIM - DENSE
    of = np.repeat(np.arange(len(y)), np.diff(rows.at))[sparse]
    yes = np.bincount(rows.col[sparse], weights=y[of], minlength=TEXT_DIM) + 1
    no = np.bincount(rows.col[sparse], weights=1 - y[of], minlength=TEXT_DIM) + 1
    ratio = np.log(yes / (y.sum() + 2)) - np.log(no / (len(y) - y.sum() + 2))
    ratio[-DENSE:] = 1
    w = fit(Rows(rows.at, rows.col, rows.val * ratio[rows.col]), y, TEXT_DIM, steps=70)
    w[:-1] *= ratio
    return w


def logits(rows: Rows, w: np.ndarray) -> np.ndarray:
    return rows.dot(w[:-1]) + w[-1]


def _dense(columns: list[np.ndarray]) -> Rows:
    n, k = len(columns[0]), len(columns)
    return Rows(np.arange(n + 1) * k, np.tile(np.arange(k, dtype=np.int32), n), np.stack(columns, axis=1).ravel())


@dataclass
class CoTrained:
    text: np.ndarray
    meta: np.ndarray
    blend: np.ndarray  # of calibrated text and metadata logits, constant last
    calibration: tuple[np.ndarray, np.ndarray]
    held_out: float  # accuracy of the blend on rows that neither fit nor calibration has seen

    def views(self, text: Rows, meta: Rows) -> tuple[np.ndarray, np.ndarray]:
        """Calibrated logits of either view."""
        a, b = (logits(_dense([logits(r, w)]), c) for r, w, c in ((text, self.text, self.calibration[0]), (meta, self.meta, self.calibration[1])))
        return a, b

    def score(self, text: Rows, meta: Rows) -> np.ndarray:
        a, b = self.views(text, meta)
        return _sigmoid(self.blend[0] * a + self.blend[1] * b + self.blend[2])


#: Rows that a view was handed, with the verdict of the other.
Given = list[tuple[Rows, Rows, float]]


def fit_views(text: Rows, meta: Rows, y: np.ndarray, given: tuple[Given, Given] = ([], [])) -> CoTrained:
    """Both views on seven tenths of the labelled rows and what each was handed; two tenths calibrate and blend, one tests."""
    n = np.arange(len(y)) % 10
    train, fold, test = np.flatnonzero(~np.isin(n, (3, 4, 9))), np.flatnonzero(np.isin(n, (4, 9))), np.flatnonzero(n == 3)
    models = []
    for rows, extra, which, learn in ((text, given[0], 0, fit_text), (meta, given[1], 1, lambda x, z: fit(x, z, META_DIM))):
        x = Rows.stack([rows.take(train), *[g[which] for g in extra]])
        models.append(learn(x, np.concatenate([y[train], [g[2] for g in extra]])))
    a, b = (logits(rows.take(fold), w) for rows, w in ((text, models[0]), (meta, models[1])))
    cal = fit(_dense([a]), y[fold], 1), fit(_dense([b]), y[fold], 1)
    blend = fit(_dense([logits(_dense([a]), cal[0]), logits(_dense([b]), cal[1])]), y[fold], 2, steps=300)
    out = CoTrained(models[0], models[1], blend, cal, 0.0)
    out.held_out = float(((out.score(text.take(test), meta.take(test)) > 0.5) == (y[test] > 0.5)).mean()) if len(test) else float("nan")
    return out


def _columns(docs: DataFrame, id_col: str) -> DataFrame:
    have = set(docs.columns)
    pick = lambda c, kind: (F.col(c) if c in have else F.lit(None)).cast(kind).alias(c)
    return docs.select(
        F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
        pick("source", "string"), pick("lang", "string"), pick("n_chars", "long"),
    )


_PACKED = "doc_id long, y1 double, y2 double, cols binary, vals binary, meta binary"


def _features(rows: DataFrame) -> DataFrame:
    """Packed features of (doc_id, y1, y2, text, source, lang, n_chars) rows."""
    arrow = pa.schema(
        [("doc_id", pa.int64()), ("y1", pa.float64()), ("y2", pa.float64()), ("cols", pa.binary()), ("vals", pa.binary()), ("meta", pa.binary())]
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = ts.as_bytes(batch.column(3))
            meta = meta_rows(batch.column(4), batch.column(5), batch.column(6)).col.reshape(-1, 3)
            for i, j in ts.pieces(buf, off):
                r = text_rows(buf[off[i] : off[j]], off[i : j + 1] - off[i])
                cut = list(zip(r.at[:-1].tolist(), r.at[1:].tolist()))
                yield pa.RecordBatch.from_arrays(
                    [
                        *[batch.column(c).slice(i, j - i) for c in range(3)],
                        pa.array([r.col[a:b].tobytes() for a, b in cut], pa.binary()),
                        pa.array([r.val[a:b].astype(np.float32).tobytes() for a, b in cut], pa.binary()),
                        pa.array([m.tobytes() for m in meta[i:j]], pa.binary()),
                    ],
                    schema=arrow,
                )

    return rows.mapInArrow(run, _PACKED)


def _gather(rows: list) -> tuple[Rows, Rows]:
    cols = [np.frombuffer(r.cols, np.int32) for r in rows]
    text = Rows(
        np.append(0, np.cumsum([len(c) for c in cols])).astype(np.int64),
        np.concatenate(cols) if cols else np.zeros(0, np.int32),
        np.concatenate([np.frombuffer(r.vals, np.float32) for r in rows]).astype(float) if rows else np.zeros(0),
    )
    meta = np.concatenate([np.frombuffer(r.meta, np.int32) for r in rows]) if rows else np.zeros(0, np.int32)
    return text, Rows(np.arange(len(rows) + 1) * 3, meta, np.ones(len(meta)))


SALTS = 64


def _confident(rows: DataFrame, labelled: DataFrame, models: dict[str, CoTrained | float], most: dict[str, int]) -> DataFrame:
    """(slot, p, doc_id): of all rows without a label, those that a view is surest of, ``most[slot]`` a slot.

    A slot names target, view and verdict. The texts are scored where they are read; ids and logits only
    are shuffled, to leave labelled rows out and to rank, first within salts and then as a whole.
    """
    targets = [name for name, model in models.items() if isinstance(model, CoTrained)]
    arrow = pa.schema([("doc_id", pa.int64()), ("z", pa.list_(pa.float64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = ts.as_bytes(batch.column(1))
            whole = meta_rows(batch.column(2), batch.column(3), batch.column(4))
            for i, j in ts.pieces(buf, off):
                text, meta = text_rows(buf[off[i] : off[j]], off[i : j + 1] - off[i]), whole.take(np.arange(i, j))
                z = np.stack([x for name in targets for x in models[name].views(text, meta)], axis=1)
                at = pa.array(np.arange(0, z.size + 1, z.shape[1], dtype=np.int32))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.ListArray.from_arrays(at, pa.array(z.ravel()))], schema=arrow)

    scored = rows.mapInArrow(run, "doc_id long, z array<double>").join(labelled.select("doc_id").distinct(), "doc_id", "left_anti")
    views = F.array(*[F.lit(f"{name} {view}") for name in targets for view in ("text", "meta")])
    each = scored.select("doc_id", F.explode(F.arrays_zip(views.alias("slot"), F.col("z"))).alias("v")).select("doc_id", "v.slot", "v.z")
    p = F.lit(1.0) / (F.exp(-F.abs("z")) + 1)
    slot = F.concat("slot", F.when(F.col("z") > 0, F.lit(" yes")).otherwise(F.lit(" no")))
    found = each.select("doc_id", slot.alias("slot"), p.alias("p")).filter(F.col("p") >= SURE).dropDuplicates(["slot", "doc_id"])
    limit = F.create_map(*[F.lit(x) for pair in most.items() for x in pair])
    best = (F.desc("p"), F.xxhash64("doc_id"), F.col("doc_id"))
    for by in (("slot", "salt"), ("slot",)):
        rank = F.row_number().over(Window.partitionBy(*by).orderBy(*best))
        found = found.withColumn("salt", F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(SALTS)))
        found = found.withColumn("r", rank).filter(F.col("r") <= max(most.values())).filter(F.col("r") <= limit[F.col("slot")]).drop("r", "salt")
    return found


def train(
    docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", labelled: int = LABELLED, handed: int = HANDED, rounds: int = ROUNDS,
    least_labels: int = LEAST_LABELS,
) -> dict[str, CoTrained | float]:
    """A model for each of quality and toxic, or the known share where labels are few or of one kind."""
    lab = labels.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(
        F.min(F.col("quality").cast("double")).alias("y1"), F.max(F.col("toxic").cast("double")).alias("y2")
    ).filter("doc_id IS NOT NULL")
    lab = lab.filter(F.col("y1").isNotNull() | F.col("y2").isNotNull())
    rows = _columns(docs, id_col)
    fields = ("doc_id", "y1", "y2", "text", "source", "lang", "n_chars")

    def fetch(ids: DataFrame) -> list:
        """Features of a bounded number of rows, one of each id."""
        return _features(rows.join(F.broadcast(ids), "doc_id").select(*fields)).dropDuplicates(["doc_id"]).collect()

    # least hashes: a fixed sample of the labelled rows that have a document
    known = rows.select("doc_id").join(lab, "doc_id").dropDuplicates(["doc_id"])
    got = fetch(known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(labelled))
    got.sort(key=lambda r: (r.doc_id * 2654435761 % 4294967296, r.doc_id))
    target = {"quality": "y1", "toxic": "y2"}
    data, out = {}, {}
    for name, field in target.items():
        use = [r for r in got if getattr(r, field) is not None]
        y = np.array([float(getattr(r, field) > 0.5) for r in use])
        if len(y) < least_labels or y.min() == y.max():
            out[name] = float(y.mean()) if len(y) else 0.5
        else:
            data[name] = (*_gather(use), y)
            out[name] = fit_views(*data[name])
    if not data:
        return out
    free = rows.filter("doc_id IS NOT NULL").select("doc_id", "text", "source", "lang", "n_chars")
    given: dict[str, tuple[dict, dict]] = {name: ({}, {}) for name in data}
    spark = docs.sparkSession
    for _ in range(rounds):
        most = {}
        for name, (_, _, y) in data.items():
            for side, share in (("yes", y.mean()), ("no", 1 - y.mean())):
                most |= {f"{name} {view} {side}": int(handed * share) + 1 for view in ("text", "meta")}
        sure = _confident(free, lab, out, most).collect()
        if not sure:
            break
        asked = spark.createDataFrame([(d, None, None) for d in sorted({r.doc_id for r in sure})], "doc_id long, y1 double, y2 double")
        held = {r.doc_id: r for r in fetch(asked)}
        for r in sorted(sure, key=lambda r: (r.slot, -r.p, r.doc_id)):
            name, view, side = r.slot.split(" ")
            other = given[name][1 if view == "text" else 0]  # what one view is sure of teaches the other
            other.setdefault(r.doc_id, (*_gather([held[r.doc_id]]), 1.0 if side == "yes" else 0.0))
        for name in data:
            out[name] = fit_views(*data[name], tuple(list(g.values()) for g in given[name]))
    return out


def score(docs: DataFrame, models: dict[str, CoTrained | float], id_col: str = "doc_id") -> DataFrame:
    """(doc_id, quality, toxicity, kept): calibrated probabilities of every document."""
    arrow = pa.schema([("doc_id", pa.int64()), ("quality", pa.float64()), ("toxicity", pa.float64()), ("kept", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = ts.as_bytes(batch.column(1))
            whole = meta_rows(batch.column(2), batch.column(3), batch.column(4))
            for i, j in ts.pieces(buf, off):
                text = text_rows(buf[off[i] : off[j]], off[i : j + 1] - off[i])
                meta = whole.take(np.arange(i, j))
                p = [
                    m.score(text, meta) if isinstance(m, CoTrained) else np.full(j - i, m)
                    for m in (models["quality"], models["toxic"])
                ]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, j - i), pa.array(p[0]), pa.array(p[1]), pa.array((p[0] >= 0.5) & (p[1] < 0.5))],
                    schema=arrow,
                )

    return _columns(docs, id_col).mapInArrow(run, "doc_id long, quality double, toxicity double, kept boolean")


def classify(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", **bounds) -> DataFrame:
    return score(docs, train(docs, labels, id_col, **bounds), id_col)
