"""Line dedup by winnowing over line hashes, in Spark's own functions only.

Lines with ink form a sequence of hashes. Every window of ``min_run`` lines selects its least hash
(the leftmost among equals) as fingerprint, and a position selected by several windows is one row,
so two runs of at least that length share a fingerprint by guarantee. Fingerprints at one position
only drop out; the positions of the others are joined, and at each the match is extended line by
line both ways through the windows that chose it: equal windows choose at equal offsets, so a
window is a match if it is met at an earlier position of its fingerprint. Matched lines are deleted.

A common fingerprint is no hot task: its positions fold to the first and the last one before they
are shuffled, the positions to look up are dealt by a plain join that adaptive execution may split,
and windows meet under their content (two 64-bit hashes), not under the fingerprint.

Earlier: smaller doc_id (null first; rows of one id by a hash of their text), or the same document
and an earlier line. With ``min_run`` 1 every later copy of a line goes (``report_every``, the
pipeline); ``MIN_RUN`` is what the SQL of op5_line_dedup states, and leaves shorter runs however
long their lines are. Cases: null text is empty (one blank line); blank lines stay and are passed
over; runs shorter than ``min_run`` stay; rows that repeat a whole document (id and text) count as
one document; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinward.llm.exchange import cut
from kinward.llm.native import has_ink, let, lines_of

MIN_RUN = 3
LOWEST = -(2**63)


def _inked(text: Column) -> Column:
    """The two hashes (h, h2) of every line with ink."""
    inked = F.filter(lines_of(text), has_ink)
    return F.transform(inked, lambda line: F.struct(F.xxhash64(line).alias("h"), F.xxhash64(F.lit("second"), line).alias("h2")))


def _windows(lines: Column, width: int) -> Column:
    """(i, pos, fp, key, key2): every window of lines, what it selects, and its content."""

    def one(i: Column) -> Column:
        held = [F.get(lines, i + k) for k in range(width)]
        ranked = [F.struct(x["h"].alias("h"), F.lit(k).alias("k")) for k, x in enumerate(held)]
        least = F.least(*ranked) if width > 1 else ranked[0]
        return F.struct(
            i.alias("i"), (i + least["k"]).alias("pos"), least["h"].alias("fp"),
            F.xxhash64(*[x["h"] for x in held]).alias("key"), F.xxhash64(*[x["h2"] for x in held]).alias("key2"),
        )

    none = F.array().cast("array<struct<i:int,pos:int,fp:bigint,key:bigint,key2:bigint>>")
    return F.when(F.size(lines) >= width, F.transform(F.sequence(F.lit(0), F.size(lines) - width), one)).otherwise(none)


def _selected(text: Column, width: int) -> Column:
    """(fp, pos, windows): every position that some window selects, with the windows that do."""

    def of(wins: Column) -> Column:
        def place(w: Column, j: Column) -> Column:
            near = F.array(*[F.get(wins, j + k) for k in range(width)])  # selections never step back
            mine = F.filter(near, lambda x: x["pos"] == w["pos"])
            return F.struct(
                w["fp"].alias("fp"), w["pos"].alias("pos"), w["i"].alias("i"),
                F.transform(mine, lambda x: F.struct(x["i"].alias("i"), x["key"].alias("key"), x["key2"].alias("key2"))).alias("windows"),
            )

        begins = lambda p, j: (j == 0) | (F.get(wins, F.greatest(j - 1, F.lit(0)))["pos"] != p["pos"])
        heads = F.transform(wins, lambda w, j: F.struct(begins(w, j).alias("head"), place(w, j).alias("p")))
        return F.transform(F.filter(heads, lambda x: x["head"]), lambda x: x["p"])

    return let(let(_inked(text), lambda lines: _windows(lines, width)), of)


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.withColumn("kw_doc", F.coalesce(F.col(id_col).cast("long"), F.lit(LOWEST))).withColumn(
        "kw_tag", F.xxhash64(text)
    )


def positions(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_run: int = MIN_RUN) -> DataFrame:
    """(kw_doc, kw_tag, fp, pos, windows): one row per selected position."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = _keyed(docs, id_col, text_col).select("kw_doc", "kw_tag", F.explode(_selected(text, min_run)).alias("p"))
    return rows.select("kw_doc", "kw_tag", "p.fp", "p.pos", "p.windows")


def later_windows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_run: int = MIN_RUN) -> DataFrame:
    """(kw_doc, kw_tag, kw_starts): windows of lines whose content also starts earlier."""
    found = positions(docs, id_col, text_col, min_run)
    at = F.struct("kw_doc", "kw_tag", "pos")
    # a fingerprint's positions fold before the shuffle, however common it is
    shared = cut(found.groupBy("fp").agg(F.min(at).alias("a"), F.max(at).alias("b")).filter("a <> b").select("fp"))
    met = found.join(shared.hint("merge"), "fp", "left_semi").select("kw_doc", "kw_tag", F.explode("windows").alias("w"))
    met = cut(met.select("kw_doc", "kw_tag", "w.i", "w.key", "w.key2"))
    place = F.struct("kw_doc", "kw_tag", "i")
    span = met.groupBy("key", "key2").agg(F.min(place).alias("first"), F.max(place).alias("last"))
    first = cut(span.filter("first <> last").drop("last"))
    later = met.join(first, ["key", "key2"]).filter(place > F.col("first"))
    return later.groupBy("kw_doc", "kw_tag").agg(F.collect_set("i").alias("kw_starts"))


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_run: int = MIN_RUN) -> DataFrame:
    """All rows and columns of ``docs`` with the text reduced, plus kw_lines and kw_removed (lines with ink)."""
    rows = _keyed(docs, id_col, text_col).join(later_windows(docs, id_col, text_col, min_run), ["kw_doc", "kw_tag"], "left")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))

    def reduced(lines: Column) -> Column:
        def of(marked: Column) -> Column:
            seen = F.flatten(F.transform(F.col("kw_starts"), lambda s: F.sequence(s, s + (min_run - 1))))

            def kept(gone: Column) -> Column:
                inked = F.filter(marked, lambda x: x["ink"])
                stay = let(
                    inked,
                    lambda a: F.transform(
                        F.array_except(F.sequence(F.lit(0), F.size(a) - 1), gone), lambda k: F.get(a, k)["pos"]
                    ),
                )
                blank = F.transform(F.filter(marked, lambda x: ~x["ink"]), lambda x: x["pos"])
                return let(
                    F.sort_array(F.concat(stay, blank)),
                    lambda p: F.struct(
                        F.array_join(F.transform(p, lambda i: F.get(lines, i)), "\n").alias("text"),
                        F.size(gone).cast("long").alias("removed"),
                    ),
                )

            return let(F.array_distinct(seen), kept)

        return let(F.transform(lines, lambda x, i: F.struct(i.alias("pos"), has_ink(x).alias("ink"))), of)

    whole = F.struct(text.alias("text"), F.lit(0).cast("long").alias("removed"))
    rows = rows.withColumn("kw_out", F.when(F.col("kw_starts").isNull(), whole).otherwise(let(lines_of(text), reduced)))
    n_lines = F.size(F.filter(lines_of(text), has_ink)).cast("long")
    kept_text = F.when(F.col(text_col).isNull(), F.col(text_col)).otherwise(F.col("kw_out.text"))
    return rows.select(
        *[kept_text.alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns],
        n_lines.alias("kw_lines"),
        F.col("kw_out.removed").alias("kw_removed"),
    )


def report(docs: DataFrame, min_run: int = MIN_RUN) -> DataFrame:
    """(doc_id, n_lines, n_removed, kept_sha256)."""
    out = dedup_lines(docs.select("doc_id", "text"), min_run=min_run)
    return out.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("kw_lines").alias("n_lines"),
        F.col("kw_removed").alias("n_removed"),
        F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("kept_sha256"),
    )


def report_every(docs: DataFrame) -> DataFrame:
    """``report`` with every later copy of a line deleted."""
    return report(docs, min_run=1)


ORACLE = rf"""
WITH l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
    generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
k AS (SELECT *, regexp_matches(line, '[^\x20\x09-\x0D]') AS ink FROM l),
s AS (SELECT doc_id, pos, line, row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS i FROM k WHERE ink),
w AS (SELECT doc_id, i, line AS a, lead(line, 1) OVER o AS b, lead(line, 2) OVER o AS c FROM s WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
r AS (SELECT doc_id, i, row_number() OVER (PARTITION BY a, b, c ORDER BY doc_id, i) AS nth FROM w WHERE c IS NOT NULL),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 3)) AS i FROM r WHERE nth > 1),
kept AS (SELECT k.doc_id, k.pos, k.line, k.ink, gone.i IS NOT NULL AS gone
  FROM k LEFT JOIN s ON k.doc_id = s.doc_id AND k.pos = s.pos LEFT JOIN gone ON s.doc_id = gone.doc_id AND s.i = gone.i)
SELECT doc_id, count(*) FILTER (WHERE ink) AS n_lines, count(*) FILTER (WHERE gone) AS n_removed,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM kept GROUP BY doc_id
"""

ORACLE_EVERY = r"""
WITH l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
    generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
k AS (SELECT *, regexp_matches(line, '[^\x20\x09-\x0D]') AS ink FROM l),
r AS (SELECT *, ink AND row_number() OVER (PARTITION BY line ORDER BY doc_id, pos) > 1 AS gone FROM k)
SELECT doc_id, count(*) FILTER (WHERE ink) AS n_lines, count(*) FILTER (WHERE gone) AS n_removed,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM r GROUP BY doc_id
"""
