"""The ten operators against brute force, on small texts with planted cases and awkward rows."""

import hashlib
import random
import re

import pytest
from pyspark.sql import functions as F

from kinward.llm import (
    byte_bpe, chat_format, decontaminate, license_scan, line_dedup, near_dedup, quality_classifier, quality_rules, substring_dedup,
    suffix_dedup,
)
from kinward.llm.lyndon_suffixes import common_prefixes, suffix_order
from kinward.llm.queries import vocabulary_path

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def words(rng, n, kinds=400):
    return " ".join(f"w{rng.randrange(kinds)}" for _ in range(n))


@pytest.fixture(scope="module")
def rows():
    """Copies, near copies, shared passages, periodic and empty texts, ties and long texts."""
    rng = random.Random(5)
    passage, long_line = words(rng, 70), words(rng, 3000)
    base = words(rng, 200)
    near = base.split()
    near[50] = "changed"
    out = [base, base, " ".join(near), passage + " " + words(rng, 40), words(rng, 30) + "\n" + passage, long_line, long_line[5:]]
    out += ["a " * 90, "a b " * 60, "b a " * 60 + "c", "x" * 900, "xy" * 700, "", None, " \n\t ", "é" * 450, "one two", "one two"]
    out += ["l1 x\nl2 y\nl3 z\nl4 q", "k\nl1 x\nl2 y\nl3 z\nl4 q\nm", "l1 x\nl2 y", "\n\n", "same\nsame\nsame\nsame\nsame\nsame"]
    out += [words(rng, rng.randrange(1, 80), 30) for _ in range(30)]
    return list(enumerate(out))


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", None) for i, t in rows], DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    """Null ids, repeated rows, one id with two texts, and columns named like the operators' own."""
    data = [(None, "null id text here"), (None, None), (1, "twice told tale"), (1, "twice told tale"), (2, "first text"), (2, "second text"), (3, None)]
    schema = "doc_id long, text string, n_words long, kept string, node long, class_id long, starts string, blocks string, q string"
    return spark.createDataFrame([(*r, 7, "x", 1, 1, "s", "b", "q") for r in data], schema)


def test_bpe_matches_tiktoken(spark, rows, docs):
    import public_tokenizers
    import tiktoken

    path = vocabulary_path()
    vocab = byte_bpe.Vocabulary(path)
    known = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=vocab.ranks, special_tokens={})
    rng = random.Random(2)
    alphabet = list("ab'strevmldIL  \n\t1２é!? 　\x85ß😀") + ["'re", "'ll", " '", "\r\n"]
    extra = [(1000 + i, "".join(rng.choice(alphabet) for _ in range(rng.randrange(60)))) for i in range(800)]
    extra += [(5000, "a" * 3000), (5001, "'" * 700 + "s"), (5002, " " * 900 + "x"), (5003, "ab" * 2000)]
    frame = docs.select("doc_id", "text").unionByName(spark.createDataFrame(extra, "doc_id long, text string"))
    got = {r.doc_id: list(r.ids) for r in byte_bpe.encode_documents(frame, path).collect()}
    for i, t in rows + extra:
        assert got[i] == known.encode_ordinary(t or ""), i
    back = {r.doc_id: bytes(r.data) for r in byte_bpe.decode_documents(byte_bpe.encode_documents(frame, path), path).collect()}
    assert all(back[i] == (t or "").encode() for i, t in rows + extra)


def test_bpe_scan_agrees_with_one_state_at_a_time():
    import numpy as np

    rng = np.random.default_rng(1)
    sym = rng.integers(0, 16, 5000).astype(np.uint8)
    at, out = byte_bpe.S_CLOSED, []
    for i, c in enumerate(sym.tolist()):
        if byte_bpe.BEGINS[c, at]:
            out.append(i)
        at = byte_bpe.STEP[c, at]
    assert byte_bpe.token_starts(sym, 64).tolist() == out


def test_substring_dedup(rows, docs):
    want = substring_dedup.brute_force(rows)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.report(docs).collect()}
    assert got == want
    assert sum(v[1] for v in want.values()) > 500


def test_substring_dedup_random_periodic(spark):
    rng = random.Random(9)
    made = []
    for i in range(150):
        parts = [" ".join([rng.choice("abc") for _ in range(rng.randrange(1, 4))] * rng.randrange(1, 15)) for _ in range(rng.randrange(1, 6))]
        made.append((i, " ".join(parts)))
    frame = spark.createDataFrame(made, "doc_id long, text string")
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.report(frame).collect()}
    assert got == substring_dedup.brute_force(made)


def test_recompression_is_locally_consistent():
    import numpy as np

    rng = np.random.default_rng(3)
    middle = rng.integers(0, 50, 20).astype(np.uint64)
    cuts = []
    for _ in range(50):
        left, right = rng.integers(0, 50, 15).astype(np.uint64), rng.integers(0, 50, 15).astype(np.uint64)
        x = np.concatenate([left, middle, right])
        start, name = substring_dedup.compress(x, np.array([0, len(x)]))
        edge = substring_dedup.reach(substring_dedup.ROUNDS)
        inside = (start >= 15 + edge) & (start < 15 + 20 - edge - 4 + 1)
        cuts.append(tuple(zip((start[inside] - 15).tolist(), name[inside].tolist())))
    assert len(set(cuts)) == 1


def test_suffix_order_and_prefixes():
    rng = random.Random(4)
    for _ in range(800):
        s = [rng.randrange(1, rng.choice([2, 3, 5])) for _ in range(rng.randrange(0, 30))] + [0]
        order = suffix_order(s)
        assert order == sorted(range(len(s)), key=lambda i: s[i:])
        lcp = common_prefixes(s, order)
        for r in range(1, len(s)):
            a, b = s[order[r - 1] :], s[order[r] :]
            assert lcp[r] == next((k for k, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))


def test_suffix_dedup(rows, docs):
    want = suffix_dedup.brute_force(rows)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.report(docs).collect()}
    assert got == want
    assert sum(v[1] for v in want.values()) > 1000


def test_suffix_dedup_families(spark):
    rng = random.Random(8)
    base = words(rng, 400)
    made = []
    for i in range(40):  # every pair parts elsewhere
        b = bytearray(base.encode())
        for _ in range(rng.randrange(0, 6)):
            b[rng.randrange(len(b))] = ord("#")
        cut = rng.randrange(0, 900)
        made.append((i, b[cut : cut + rng.randrange(300, 1500)].decode()))
    frame = spark.createDataFrame(made, "doc_id long, text string")
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.report(frame).collect()}
    assert got == suffix_dedup.brute_force(made)


def test_line_dedup(rows, docs):
    seen, want = set(), {}
    for i, t in rows:
        lines = (t or "").split("\n")
        inked = [k for k, x in enumerate(lines) if re.search(r"[^\x20\x09-\x0D]", x)]
        gone = set()
        for j in range(len(inked) - 2):
            w = tuple(lines[k] for k in inked[j : j + 3])
            if w in seen:
                gone.update(inked[j : j + 3])
            seen.add(w)
        kept = "\n".join(x for k, x in enumerate(lines) if k not in gone)
        want[i] = (len(inked), len(gone), hashlib.sha256(kept.encode()).hexdigest())
    got = {r.doc_id: (r.n_lines, r.n_removed, r.kept_sha256) for r in line_dedup.report(docs).collect()}
    assert got == want
    assert want[19][1] == 4 and want[20][1] == 0


def test_every_line_dedup(spark, rows, docs):
    import corpus_pipeline

    seen, want, left = set(), {}, {}
    for i, t in rows:
        lines = (t or "").split("\n")
        gone = set()
        for k, x in enumerate(lines):
            if re.search(r"[^\x20\x09-\x0D]", x):
                gone |= {k} if x in seen else set()
                seen.add(x)
        kept = "\n".join(x for k, x in enumerate(lines) if k not in gone)
        want[i] = (len(gone), hashlib.sha256(kept.encode()).hexdigest())
        if kept.strip(" \t\n\x0b\x0c\r") or not gone:
            left[i] = t if t is None else kept
    got = {r.doc_id: (r.n_removed, r.kept_sha256) for r in line_dedup.report_every(docs).collect()}
    assert got == want and want[20][0] == 2
    assert {r.doc_id: r.text for r in corpus_pipeline.lines(spark, docs, "").collect()} == left


def test_quality_rules(spark, rows, docs):
    got = {r.doc_id: r for r in quality_rules.judge(docs).collect()}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        wins = [tuple(w[k : k + 8]) for k in range(len(w) - 7)]
        cover = {p for k, x in enumerate(wins) if wins.count(x) > 1 for p in range(k, k + 8)} if len(w) < 500 else None
        assert (got[i].n_words, got[i].word_chars) == (len(w), sum(map(len, w)))
        if cover is not None:
            assert got[i].n_repeat_words == len(cover)
            assert got[i].base_failed == (len(w) < 20 or 100 * len(cover) > 30 * len(w))
    kept = {r.doc_id for r in quality_rules.keep_passing(docs).collect()}
    assert kept == {i for i in got if got[i].kept}
    orders = [quality_rules.judge(docs, rules=rules).select("doc_id", "kept").collect() for rules in (quality_rules.RULES, quality_rules.RULES[::-1])]
    assert sorted(orders[0]) == sorted(orders[1])
    junk = spark.createDataFrame([(1, "Ab*** cd$$$ ef### " * 30), (2, "EVERY WORD IN HERE SHOUTS " + "LOUD " * 3 + words(random.Random(1), 30).upper())], "doc_id long, text string")
    assert not any(r.kept for r in quality_rules.judge(junk).collect())


def test_license_scan(spark):
    apache = "Licensed under the Apache License, Version 2.0 (the License). You may not use this file except in compliance with the License. You may obtain a copy of the License at"
    data = [(1, "Text.\nReleased under the MIT License.\nMore."), (2, apache), (3, "no licence"), (4, None), (5, "All rights reserved. Licensed under CC BY-NC 4.0.")]
    got = {r.doc_id: (r.n_known, list(r.licenses)) for r in license_scan.scan(spark.createDataFrame(data, "doc_id long, text string")).collect()}
    assert got[1] == (1, ["MIT"]) and got[2] == (3, ["Apache-2.0"]) and got[3] == (0, []) and got[4] == (0, [])
    assert got[5] == (2, ["CC-BY-NC-4.0", "proprietary"])


MIT = (
    'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), '
    "to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, "
    "and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:\n\n"
    "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\n\n"
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT."
)
BSD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n"
    "1. Redistributions of source code must retain the above copyright notice."
)
MPL = "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one."
GPL = (
    "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the "
    "Free Software Foundation, either version {} of the License, or (at your option) any later version.\n\nThis program is distributed in the hope."
)
APACHE = (
    'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. '
    "You may obtain a copy of the License at\n\n    http://www.apache.org/licenses/LICENSE-2.0"
)


def test_standard_licences_with_hard_wraps(spark):
    import textwrap

    whole = [(MIT, ["MIT"], 3), (BSD, ["BSD"], 1), (MPL, ["MPL-2.0"], 1), (GPL.format(3), ["GPL-3.0"], 1), (GPL.format(2), ["GPL-2.0"], 1), (APACHE, ["Apache-2.0"], 3)]
    names = [("MIT", "MIT"), ("Apache-2.0", "Apache-2.0"), ("GPL-3.0-only", "GPL-3.0"), ("GPL-2.0-or-later", "GPL-2.0"), ("BSD-3-Clause", "BSD"), ("MPL-2.0", "MPL-2.0")]
    data, want = [], {}
    for text, licences, n in whole:
        for width, sign in ((10**6, ""), (72, ""), (40, "# "), (30, " * ")):
            wrapped = "\n".join(sign + line for part in text.split("\n") for line in textwrap.wrap(part, width) or [""])
            want[len(data)] = (n, licences)
            data.append((len(data), f"Copyright 2020 Some One\n\n{wrapped}"))
    for name, licence in names:
        for form in ("SPDX-License-Identifier: {}", "/* SPDX-License-Identifier: {} */\nint x;", "<!-- SPDX-License-Identifier: {} -->"):
            want[len(data)] = (1, [licence])
            data.append((len(data), form.format(name)))
    for text in ("The permission to obtain a copy of this software was not granted.", MIT.replace("free of charge", "at a charge").split("\n")[0]):
        want[len(data)] = (0, [])
        data.append((len(data), text))
    got = {r.doc_id: (r.n_known, list(r.licenses)) for r in license_scan.scan(spark.createDataFrame(data, "doc_id long, text string")).collect()}
    assert got == want
    known = [*license_scan.SENTENCES.values(), *[x for bodies in license_scan.WHOLE.values() for x in bodies]]
    assert all(any(hint in x for hint in license_scan.HINTS) for x in known) and len(set(known)) == len(known)


def test_chat_format(spark):
    rng = random.Random(3)
    bits = ["<|turn|>", "<|end|>", "[INST]", "[\\INST]", "</s>", "<\\\\|end|>", "<<SYS>>", "\\", "<", "text é", "\n", "<|"]
    data = [(c, t, rng.choice(["user", "assistant", "sys\ntem\\"]), "".join(rng.choice(bits) for _ in range(rng.randrange(6)))) for c in range(60) for t in range(rng.randrange(1, 6))]
    data += [(70, 0, "assistant", None), (None, 0, None, "x"), (71, None, "user", "y")] + [(80, t, "assistant", f"t{t}") for t in range(9000)]
    frame = chat_format.with_probe(spark.createDataFrame(data, "conv_id long, turn long, role string, text string"))
    got = {r.conv_id: r for r in chat_format.digests(chat_format.format_conversations(frame)).collect()}
    said = "</s>[INST] ok [/INST]"
    data += [(-1, 0, "user", said), (-1, 1, "assistant", said)]
    for c in {r[0] for r in data}:
        turns = [(r[2] or "", r[3] or "") for r in sorted((r for r in data if r[0] == c), key=lambda r: (r[1] is not None, r[1] or 0))]
        learned = "".join(t for r, t in turns if r == "assistant")
        assert got[c].n_turns == len(turns)
        assert got[c].turns_sha256 == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
        assert (got[c].loss_chars, got[c].loss_sha256) == (len(learned), hashlib.sha256(learned.encode()).hexdigest())
    for text in ("".join(rng.choice(bits) for _ in range(8)) for _ in range(300)):
        safe = chat_format.escape(text)
        assert chat_format.unescape(safe) == text and not any(c in safe for c in chat_format.CONTROL)


def test_decontamination(spark):
    rng = random.Random(6)
    item = words(rng, 40)
    w = item.split()
    moved = " ".join(w[20:]) + " and " + " ".join(w[:20])
    bench = spark.createDataFrame([(1, item), (2, "tiny item"), (3, None), (4, words(rng, 30))], "item_id long, text string")
    data = [(1, "start " + item.upper() + " end"), (2, moved), (3, words(rng, 200, 5000)), (4, None), (5, " ".join(w[:12])), (6, "a tiny item here"), (7, item + " " + item)]
    got = {r.doc_id: (r.contaminated, list(r.item_ids), round(r.coverage, 3)) for r in decontaminate.judge(spark.createDataFrame(data, "doc_id long, text string"), bench).collect()}
    assert got[1] == (True, [1], 1.0) and got[2] == (True, [1], 1.0) and got[7] == (True, [1], 1.0)
    assert not got[3][0] and not got[4][0] and got[5] == (False, [], 0.3) and got[6] == (True, [2], 1.0)
    none = decontaminate.judge(spark.createDataFrame(data, "doc_id long, text string"), bench.limit(0)).collect()
    assert not any(r.contaminated for r in none)


def test_near_dedup(spark, rows, docs):
    rng = random.Random(12)
    base = words(rng, 150, 3000).split()
    more = []
    for i in range(60):
        x = list(base)
        for _ in range(rng.randrange(0, 5)):
            x[rng.randrange(len(x))] = f"n{rng.randrange(10**6)}"
        more.append((100 + i, " ".join(x)))
    frame = docs.select("doc_id", "text").unionByName(spark.createDataFrame(more, "doc_id long, text string"))
    got = {r.doc_id: r.class_id for r in near_dedup.report(frame).collect()}
    assert got == near_dedup.brute_force(rows + more)
    stay = sorted(r.doc_id for r in near_dedup.keep_one(frame).collect())
    assert stay == sorted(set(got.values()))


def test_near_dedup_of_ids_with_unlike_texts(spark):
    rng = random.Random(31)
    a, b, c = (words(rng, 60, 3000) for _ in range(3))
    data = [(5, b), (10, a), (10, b), (10, a), (12, c), (11, c + " end"), (7, "one text"), (7, "another text")]
    stay = sorted((r.doc_id, r.text) for r in near_dedup.keep_one(spark.createDataFrame(data, "doc_id long, text string")).collect())
    assert stay == sorted([(5, b), (10, a), (11, c + " end"), (7, "one text"), (7, "another text")])


def test_near_dedup_signature_is_unbiased():
    import numpy as np

    from kinward.llm import textscan as ts

    rng = np.random.default_rng(1)
    h = rng.integers(1, 2**63, 300).astype(np.uint64)
    a = rng.integers(0, 6, 300)
    b = np.where(rng.random(300) < 0.4, rng.integers(0, 6, 300), a)
    same = []
    for salt in range(40):
        x = ts.mix64(h + np.uint64(salt))
        sig = [near_dedup.signatures(np.zeros((w > 0).sum(), int), x[w > 0], w[w > 0], 1)[0] for w in (a, b)]
        same.append((sig[0] == sig[1]).mean())
    true = np.minimum(a, b).sum() / np.maximum(a, b).sum()
    assert abs(np.mean(same) - true) < 4 * (true * (1 - true) / (40 * 128)) ** 0.5


def test_classifier_held_out(spark):
    rng = random.Random(7)
    data, labels = [], []
    for i in range(600):
        bad, toxic = rng.random() < 0.3, rng.random() < 0.3
        text = words(rng, 60, 200) + (" ###*** $$$" * 8 if bad else "") + (" nasty vile nasty" if toxic else "")
        data.append((i, text, "en", f"s{int(bad)}", len(text)))
        if i % 2:
            labels.append((i, int(not bad), int(toxic)))
    d = spark.createDataFrame(data, DOCS)
    out = quality_classifier.classify(d, spark.createDataFrame(labels, "doc_id long, quality int, toxic int")).collect()
    right = sum(r.kept == ("###" not in data[r.doc_id][1] and "nasty" not in data[r.doc_id][1]) for r in out if r.doc_id % 2 == 0)
    assert right >= 0.95 * 300
    none = quality_classifier.classify(d, spark.createDataFrame([], "doc_id long, quality int, toxic int"))
    assert {r.quality for r in none.collect()} == {0.5}


def every_operator(spark, docs):
    bench = spark.createDataFrame([(1, "twice told tale of words")], "item_id long, text string")
    labels = spark.createDataFrame([(1, 1, 0), (1, 0, 1), (None, 1, 1), (2, None, None)], "doc_id long, quality int, toxic int")
    path = vocabulary_path()
    return {
        "bpe": byte_bpe.encode_and_digest(docs, path), "substring": substring_dedup.report(docs), "classifier": quality_classifier.classify(docs, labels),
        "bench": decontaminate.report(docs, bench), "clean": decontaminate.keep_clean(docs, bench), "lines": line_dedup.dedup_lines(docs),
        "rules": quality_rules.judge(docs), "passing": quality_rules.keep_passing(docs), "licences": license_scan.report(docs),
        "suffix": suffix_dedup.report(docs), "near": near_dedup.report(docs), "one": near_dedup.keep_one(docs),
    }


def test_awkward_rows(spark, odd):
    n = odd.count()
    for name, out in every_operator(spark, odd).items():
        got = out.collect()
        if name not in ("clean", "passing", "one"):
            assert len(got) == n, name
        else:
            assert out.columns == odd.columns, name
    assert near_dedup.keep_one(odd).filter("doc_id = 1").count() == 1
    assert near_dedup.keep_one(odd).filter("doc_id IS NULL").count() == 2


def test_empty_tables(spark, odd):
    for name, out in every_operator(spark, odd.limit(0)).items():
        assert out.collect() == [], name
    turns = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert chat_format.digests(chat_format.format_conversations(turns)).collect() == []


def test_native_plans_hold_no_python(docs):
    for out in (line_dedup.report(docs), quality_rules.judge(docs), license_scan.report(docs)):
        assert not re.search("Python|Pandas|Arrow", out._jdf.queryExecution().executedPlan().toString())


def test_pipeline_against_brute_force(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(21)
    clean = [". ".join(words(rng, 12, 900).capitalize() for _ in range(6)) for _ in range(12)]
    item = words(rng, 40, 5000)
    data = [(i, t) for i, t in enumerate(clean)] + [(20, clean[0]), (21, clean[1] + " extra"), (22, clean[2] + " " + item), (23, "Bad*** " * 60), (24, "short")]
    frame = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in data], DOCS)
    frame.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    got = {r.doc_id: r.n_tokens for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert sorted(got) == [i for i in range(12)]
    vocab = byte_bpe.vocabulary(vocabulary_path())
    import pyarrow as pa

    from kinward.llm import textscan as ts

    buf, off = ts.as_bytes(pa.array(clean))
    assert [got[i] for i in range(12)] == [int(x) for x in __import__("numpy").diff(vocab.encode(buf, off)[1])]
    assert frame.filter(F.col("doc_id") == 20).count() == 1


def pipeline_by_hand(data, items):
    """What every stage leaves of (doc_id, text) rows of different ids, stage by stage, in plain Python."""
    import unicodedata
    from collections import Counter

    import public_tokenizers
    import tiktoken

    ink = re.compile(r"[^\x20\x09-\x0D]+")

    def passes(t):
        w, lines = ink.findall(t), [x for x in t.split("\n") if ink.search(x)]
        wins = [tuple(w[k : k + 8]) for k in range(len(w) - 7)]
        times = Counter(wins)
        repeated = {p for k, x in enumerate(wins) if times[x] > 1 for p in range(k, k + 8)}
        chars, upper = sum(map(len, w)), sum(unicodedata.category(c) == "Lu" for c in t)
        bullets = sum(x.lstrip(" \t")[:1] in ("-", "•") and x.strip(" \t") != "" for x in t.split("\n"))
        return not (
            len(w) < 20 or 100 * len(repeated) > 30 * len(w) or 100 * len(re.findall(r"[#*$%&|<>]", t)) > 10 * len(w)
            or 100 * (len(lines) - len(set(lines))) > 30 * len(lines) or not 2 * len(w) <= chars <= 15 * len(w)
            or 100 * upper > 40 * chars or (len(lines) > 5 and 100 * bullets > 90 * len(lines)) or "lorem ipsum" in t.lower()
        )

    passed = [(i, t) for i, t in data if passes(t or "")]
    seen, lined = set(), []
    for i, t in sorted(passed):
        kept = []
        for x in t.split("\n"):
            if x not in seen or not ink.search(x):
                kept.append(x)
            seen.add(x)
        if ink.search("\n".join(kept)):
            lined.append((i, "\n".join(kept)))
    of = near_dedup.brute_force(lined)
    single = [(i, t) for i, t in lined if of[i] == i]
    dirty = {r[0] for r in decontaminate.brute_force(single, items) if r[1]}
    clean = [(i, t) for i, t in single if i not in dirty]
    ranks = byte_bpe.Vocabulary(vocabulary_path()).ranks
    known = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    digest = lambda b: hashlib.sha256(b).hexdigest()
    coded = [(i, known.encode_ordinary(t), t) for i, t in clean]
    return passed, lined, single, clean, [(i, len(x), digest(" ".join(map(str, x)).encode()), digest(t.encode())) for i, x, t in coded]


def test_pipeline_equals_stages_by_hand(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(33)
    fresh = lambda n=40: words(rng, n, 50_000)
    items = [(1, fresh(40)), (2, fresh(30)), (3, None), (4, "one")]
    moved = items[0][1].split()
    texts = [fresh(rng.randrange(20, 70)) for _ in range(25)]
    texts += [" ".join([*texts[k].split(), "more"][1:] if k % 2 else texts[k].split()[:-1]) for k in range(8)]  # near copies
    boiler = fresh(12)
    texts += [f"{fresh(25)}\n{boiler}\n\n{fresh(6)}" for _ in range(6)] + [texts[3], texts[4] + "\n" + boiler]
    texts += [f"{fresh(30)} {items[0][1]}", f"{fresh(9)} {' '.join(moved[20:])} and {' '.join(moved[:20])} {fresh(9)}", f"{fresh(30)} {' '.join(moved[:12])}"]
    texts += [f"{fresh(20)}\n{items[1][1].upper()[:60]}\n{fresh(20)}", "the one and only " + fresh(30)]
    # each fails one rule
    texts += ["short one", None, "", " \n\t ", " ".join([fresh(8)] * 4 + [fresh(2)]), " ".join(x + "##" for x in fresh(30).split())]
    texts += ["\n".join(x for k in range(6) for x in (fresh(3), f"same {k % 2}", fresh(4))), " ".join(f"{x}{'y' * 20}" for x in fresh(30).split())]
    texts += [" ".join(rng.choice("abcdefghijklm") for _ in range(40)), " ".join(f"LOUD{x}".upper() for x in fresh(30).split())]
    texts += ["\n".join("- " + fresh(4) for _ in range(7)), fresh(30) + " Lorem Ipsum " + fresh(5), fresh(30) + "\n- " + fresh(5)]
    data = [(7 * i % 101, t) for i, t in enumerate(texts)]
    frame = spark.createDataFrame([(i, t, None, "s", None) for i, t in data], DOCS).repartition(5)
    frame.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(items, "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    by_stage = pipeline_by_hand(data, items)
    sizes = [len(data), *map(len, by_stage)]
    assert sizes[0] > sizes[1] > sizes[2] > sizes[3] > sizes[4] == sizes[5] > 20  # every stage acts
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    for (name, stage), want in zip(corpus_pipeline.STAGES[:4], by_stage):
        out = stage(spark, docs, str(tmp_path))
        assert out.columns == docs.columns, name
        assert sorted((r.doc_id, r.text) for r in out.collect()) == sorted(want), name
        docs = spark.createDataFrame([(i, t, None, "s", None) for i, t in want], DOCS)
    got = corpus_pipeline.run(spark, str(tmp_path)).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256").collect()
    assert sorted(map(tuple, got)) == sorted(by_stage[4])


def test_pipeline_stages_on_awkward_rows(spark, odd, tmp_path):
    """Null ids and texts, repeated rows, one id with two texts, clashing columns; and empty tables."""
    import corpus_pipeline

    at = str(tmp_path)
    spark.createDataFrame([(1, "twice told tale"), (None, None)], "item_id long, text string").write.parquet(f"{at}/benchmark.parquet")
    left = {"quality_rules": 0, "line_dedup": 7, "near_dedup": 6, "decontamination": 5, "byte_bpe": 7}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, odd, at)
        assert out.count() == left[name], name
        assert name == "byte_bpe" or out.columns == odd.columns, name
        assert stage(spark, odd.limit(0), at).collect() == [], name
    odd.limit(0).write.parquet(f"{at}/documents.parquet")
    assert corpus_pipeline.run(spark, at).collect() == []


def test_texts_of_more_than_a_million_bytes(spark):
    rng = random.Random(52)
    one = words(rng, 160_000, 90_000).split()
    other = one[:100_000] + ["changed"] + one[100_000:159_000]
    data = [(1, " ".join(one)), (2, "start\n" + " ".join(other)), (3, words(rng, 40)), (4, "x" * 1_200_000)]
    assert len(data[0][1]) > 10**6
    frame = spark.createDataFrame(data, "doc_id long, text string")
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.report(frame).collect()}
    assert got == substring_dedup.brute_force(data)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.report(frame).collect()}
    assert got == suffix_dedup.brute_force(data)
    assert {r.doc_id: r.class_id for r in near_dedup.report(frame).collect()} == {1: 1, 2: 1, 3: 3, 4: 4}
    bench = spark.createDataFrame([(1, " ".join(one[5000:5030])), (2, "nowhere to be found")], "item_id long, text string")
    assert {r.doc_id for r in decontaminate.judge(frame, bench).filter("contaminated").collect()} == {1, 2}
    assert {r.doc_id: r.kw_removed for r in line_dedup.dedup_lines(frame, min_run=1).collect()} == dict.fromkeys((1, 2, 3, 4), 0)
    got = {r.doc_id: (r.n_words, r.n_repeat_words, r.kept) for r in quality_rules.judge(frame).collect()}
    assert got == {1: (160_000, 0, True), 2: (159_002, 0, True), 3: (40, 0, True), 4: (1, 0, False)}
    assert {r.doc_id for r in quality_rules.keep_passing(frame).collect()} == {1, 2, 3}
    assert {r.n_known for r in license_scan.scan(frame).collect()} == {0}
    coded = byte_bpe.encode_and_digest(frame, vocabulary_path()).collect()
    assert {r.doc_id: r.decoded_sha256 for r in coded} == {i: hashlib.sha256(t.encode()).hexdigest() for i, t in data}


def test_parity_words_do_not_collide(spark):
    """Two unlike words of 2048 letters whose polynomial hashes agree modulo any power of two."""
    odd = [bin(i).count("1") & 1 for i in range(2048)]
    one, two = "".join("ab"[k] for k in odd), "".join("ba"[k] for k in odd)
    lead = " ".join(f"w{i}" for i in range(10))
    data = [(1, f"{lead} {one} {lead}"), (2, f"{lead} {two} {lead}"), (3, one), (4, two)]
    frame = spark.createDataFrame(data, "doc_id long, text string")
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.report(frame).collect()}
    assert got == substring_dedup.brute_force(data) and got[2][1] == 0
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.report(frame).collect()}
    assert got == suffix_dedup.brute_force(data)
    assert {r.doc_id: r.class_id for r in near_dedup.report(frame).collect()} == {1: 1, 2: 2, 3: 3, 4: 4}
    bench = spark.createDataFrame([(1, one)], "item_id long, text string")
    assert {r.doc_id for r in decontaminate.judge(frame, bench, least_tokens=1).filter("contaminated").collect()} == {1, 3}


def test_winnowing_selects_minima_only(spark):
    rng = random.Random(17)
    text = "\n".join(f"line {rng.randrange(10**9)}" for _ in range(600))
    docs = spark.createDataFrame([(1, text), (2, "x\n" + text), (3, "a\nb")], "doc_id long, text string")
    got = line_dedup.positions(docs).collect()
    n = sum(r.kw_doc == 1 for r in got)
    assert 250 < n < 350  # 2 / (3 + 1) of the windows
    assert sum(len(r.windows) for r in got if r.kw_doc == 1) == 598
    assert all(r.windows[0].i <= r.pos < r.windows[0].i + 3 for r in got)
    assert not any(r.kw_doc == 3 for r in got)
    assert line_dedup.dedup_lines(docs).filter("doc_id = 2").first().kw_removed == 600


def test_near_dedup_of_a_large_family(spark, monkeypatch):
    """Families in several blocks, some held by the forest alone and some parted into classes."""
    monkeypatch.setattr(near_dedup, "BLOCK", 16)
    rng = random.Random(41)
    base, data = words(rng, 120, 9000).split(), []
    for i in range(150):  # drifts away, so that ends of the chain are unlike
        x = list(base)
        for k in range(i // 12):
            x[k * 9] = f"drift{k}"
        x[rng.randrange(len(x))] = f"n{i}"
        data.append((i, " ".join(x)))
    frame = spark.createDataFrame(data, "doc_id long, text string")
    assert {r.doc_id: r.class_id for r in near_dedup.report(frame).collect()} == near_dedup.brute_force(data)


def test_decontamination_by_blocks(spark):
    """A benchmark of many blocks gives what one block gives, and brute-force tiling gives the same verdicts."""
    rng = random.Random(16)
    items = [(i, words(rng, rng.randrange(1, 40), 60)) for i in range(40)] + [(3, None), (None, "some item of no id at all")]
    data = []
    for i in range(120):
        parts = [words(rng, rng.randrange(0, 20), 60)]
        for _ in range(rng.randrange(0, 3)):
            w = rng.choice(items)[1] or ""
            cut = rng.randrange(0, 5)
            parts += [" ".join(w.split()[cut:]), words(rng, rng.randrange(0, 4), 60)]
        rng.shuffle(parts)
        data.append((i, " ".join(parts)))
    data += [(5, data[5][1]), (None, "some item of no id at all"), (7, None)]
    docs, bench = spark.createDataFrame(data, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    key = lambda r: (r.doc_id is None, r.doc_id, r.contaminated, tuple(x or -1 for x in r.item_ids), round(r.coverage, 6))
    one = sorted(map(key, decontaminate.judge(docs, bench).collect()), key=str)
    many = sorted(map(key, decontaminate.judge(docs, bench, block_bytes=200).collect()), key=str)
    assert [r[:3] + r[4:] for r in one] == [r[:3] + r[4:] for r in many]
    assert [sorted(r[3]) for r in one] == [sorted(r[3]) for r in many]
    want = decontaminate.brute_force(data, items)
    assert sorted(((r[1], r[2], sorted(r[3]), r[4]) for r in one), key=str) == sorted(want, key=str)
    assert any(r[2] for r in one) and not all(r[2] for r in one)
    assert decontaminate.keep_clean(docs, bench, block_bytes=200).count() == sum(not r[2] for r in one)


def test_classifier_hands_over_and_scores(spark):
    """Pseudo-labels come from all unlabelled rows, and the Spark scores equal scores computed here."""
    import numpy as np
    import pyarrow as pa

    from kinward.llm import textscan as ts

    rng = random.Random(27)
    data = []
    for i in range(900):
        bad = rng.random() < 0.4
        data.append((i, words(rng, 50, 200) + (" ###*** $$$" * 8 if bad else ""), "en", f"s{int(bad)}", 300))
    labels = [(i, int("###" not in data[i][1]), int(i % 2)) for i in range(0, 900, 9)]
    docs = spark.createDataFrame(data, DOCS).repartition(7)
    models = quality_classifier.train(docs, spark.createDataFrame(labels, "doc_id long, quality int, toxic int"))
    got = {r.doc_id: (r.quality, r.toxicity) for r in quality_classifier.score(docs, models).collect()}
    text, meta = (pa.array([r[k] for r in data]) for k in (1, 3))
    rows = quality_classifier.text_rows(*ts.as_bytes(text))
    side = quality_classifier.meta_rows(meta, pa.array(["en"] * 900), pa.array([300] * 900, pa.int64()))
    for k, name in enumerate(("quality", "toxic")):
        want = models[name].score(rows, side) if isinstance(models[name], quality_classifier.CoTrained) else np.full(900, models[name])
        assert np.allclose([got[i][k] for i in range(900)], want)
    first = quality_classifier.train(docs, spark.createDataFrame(labels, "doc_id long, quality int, toxic int"), rounds=0)
    assert not np.array_equal(first["quality"].meta, models["quality"].meta)  # the exchange acts
    assert models["quality"].held_out >= 0.9
    most = {f"quality {v} {s}": 5 for v in ("text", "meta") for s in ("yes", "no")}
    marked = spark.createDataFrame([(i,) for i, _, _ in labels], "doc_id long")
    asked = docs.select("doc_id", "text", "source", "lang", "n_chars")
    sure = quality_classifier._confident(asked, marked, {"quality": models["quality"]}, most).collect()
    p = dict(zip(("text", "meta"), models["quality"].views(rows, side)))
    for slot in most:
        _, view, verdict = slot.split(" ")
        z = np.delete(p[view] if verdict == "yes" else -p[view], np.arange(0, 900, 9))
        best = np.sort(1 / (1 + np.exp(-z)))[::-1]
        mine = sorted((r.p for r in sure if r.slot == slot), reverse=True)
        assert np.allclose(mine, best[: len(mine)]) and len(mine) == min(5, int((best >= quality_classifier.SURE).sum()))


def test_folding_before_the_shuffle(spark, monkeypatch):
    """One passage in most documents, rows stored three times, folds of a few records: nothing changes, and little is sent."""
    import numpy as np

    from kinward.llm import repeats

    rng = random.Random(77)
    passage = words(rng, 60, 5000)
    data = [(i, f"{words(rng, rng.randrange(0, 30))} {passage} {words(rng, rng.randrange(0, 30))}") for i in range(60)]
    data += [(100 + i, passage) for i in range(20)] + [(200, words(rng, 50)), (201, "a b " * 80)]
    stored = data + data[::3] + data[::3]
    for fold in (50, repeats.FOLD):
        monkeypatch.setattr(repeats, "FOLD", fold)
        frame = spark.createDataFrame(stored, "doc_id long, text string").repartition(5)
        got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.report(frame).collect()}
        assert got == substring_dedup.brute_force(data)
        got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.report(frame).collect()}
        assert got == suffix_dedup.brute_force(data)
    rec = np.zeros(1000, repeats.PLACE)
    rec["doc"], rec["n"], rec["many"] = np.arange(1000), 1, 5
    for earlier, n in ((True, 1), (False, 2)):
        sent, settled = repeats.folded(rec, earlier)
        assert len(sent) == n and len(settled) == 1000 - n
