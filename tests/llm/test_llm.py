"""Operators on small fixtures: brute force, exact round trips, held-out accuracy, and odd rows."""

from __future__ import annotations

import hashlib
import math
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import Row

from compare import differs
from joinspace.llm import decontaminate, language, licenses, lm, mixing, neardup, queries, substrings, tokens, topk, warc
from joinspace.llm.common import Scratch

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size int, score double, copies string"
LONG = " ".join(f"w{i}" for i in range(160))


@pytest.fixture(scope="module")
def odd(spark):
    """Null and empty texts, nulls everywhere, repeated rows, a long text, columns whose names clash."""
    rows = [
        (1, LONG, "en", "a", 5, 1, 0.5, "x"),
        (2, "head " + LONG + " tail", "en", "a", 5, 1, 0.5, "x"),
        (2, "head " + LONG + " tail", "en", "a", 5, 1, 0.5, "x"),
        (3, None, None, None, None, None, None, None),
        (4, "", "de", "b", 0, 0, 0.0, ""),
        (None, "one two", "de", None, 7, 0, 0.0, ""),
        (5, "Solo", "de", "b", 4, 0, 0.0, ""),
        (6, "12 34 !!", None, "b", 8, 0, 0.0, ""),
        (7, "x" * 50_000 + " " + LONG, "en", "c", 9, 0, 0.0, ""),
    ]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_sql(spark, sf, name):
    assert differs(spark, queries.QUERIES[name], queries.ORACLE_SQL[name], sf) == ""


def test_decontaminate(spark, odd, none):
    bench = spark.createDataFrame([(1, "W5 w6, w7 w8 w9 w10 w11 w12 w13 w14"), (2, "solo"), (3, None), (4, "")], "item_id long, text string")
    got = {(r["doc_id"], r["n_hit"], tuple(r["items"])) for r in decontaminate.scan(odd, bench).collect()}
    assert {(1, 10, ("1",)), (2, 10, ("1",)), (5, 1, ("2",)), (4, 0, ()), (3, 0, ()), (None, 0, ())} <= got
    assert decontaminate.scan(odd, bench).count() == odd.count()
    shuffled = {(r["doc_id"], r["n_hit"], tuple(r["items"])) for r in decontaminate.scan(odd, bench, broadcast_windows=0).collect()}
    assert shuffled == got
    assert decontaminate.scan(none, bench).count() == 0
    assert decontaminate.scan(odd, bench.limit(0)).where("n_hit > 0").count() == 0
    kept = decontaminate.remove_documents(odd, bench)
    assert kept.columns == odd.columns and {r["doc_id"] for r in kept.collect()} == {3, 4, None, 6}
    cut = {r["doc_id"]: r["text"] for r in decontaminate.remove_spans(odd, bench).collect()}
    assert cut[5] == "" and "w5 " not in cut[1] and cut[6] == "12 34 !!"


def test_token_counts(spark, odd, none):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    t = Tokenizer.from_file(path)
    texts = [r["text"] for r in odd.collect()] + ["a<|endoftext|> b", "it's  'tis \n\n don't!!", "naïve çà  \t 12ab"]
    docs = spark.createDataFrame([(i, x) for i, x in enumerate(texts)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in tokens.token_counts(docs, path).collect()}
    for i, x in enumerate(texts):
        assert got[i]["n_tokens"] == len(t.encode(x or "", add_special_tokens=False).ids)
        assert got[i]["n_bytes"] == len((x or "").encode()) and got[i]["over_limit"] == (got[i]["n_tokens"] > 1024)
    for head in (0, 5):
        same = {r["doc_id"]: r for r in tokens.token_counts(docs.withColumn("row", docs["text"]).withColumn("n", docs["text"]), path, head=head).collect()}
        assert same == got
    assert tokens.token_counts(none, path).count() == 0
    assert tokens.token_counts(odd, path).where("doc_id = 2").count() == 2


def test_pieces_are_listed_once(spark):
    """Each distinct pre-token is one row, however many documents have it."""
    import public_tokenizers

    text = open(public_tokenizers.path("byte_bpe_50k.json"), encoding="utf-8").read()
    docs = spark.createDataFrame([("the cat, the cat",), ("the cat's 12",), (None,), ("naïve ³ the",)], "text string").repartition(3)
    rows = [r["piece"] for r in tokens.distinct_pieces(docs, spark.sparkContext.broadcast(text), most=2).collect()]
    assert sorted(rows) == sorted({"the", " cat", ",", " the", "'s", " 12", "naïve", " ³"})


def test_token_counts_on_documents(spark, sf):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for r in queries.op2_token_counts(spark, sf).collect():
        assert r["n_tokens"] == len(t.encode(docs[r["doc_id"]] or "", add_special_tokens=False).ids)


def test_license_scan(spark):
    rows = [
        ("r/LICENSE", "Hello.\nReleased under the MIT License."),
        ("r/a/x.py", "no notice here"),
        ("r/a/y.py", "Licensed under the Apache License, Version 2.0. More words."),
        ("r/b/LICENSE.txt", "This work is licensed under the GNU General Public License, version 3."),
        ("r/b/c/z.py", None),
        ("s/q.py", "the license of things that are mentioned in passing by"),
        (None, "Released under the MIT License."),
    ]
    files = spark.createDataFrame([Row(path=p, text=t, licence="clash") for p, t in rows])
    got = {r["path"]: (r["own_licence"], r["licence"], r["licence_from"], r["inherited"]) for r in licenses.scan(files).collect()}
    assert got["r/LICENSE"][:2] == ("MIT", "MIT")
    assert got["r/a/x.py"] == (None, "MIT", "r/LICENSE", True)
    assert got["r/a/y.py"][:2] == ("Apache-2.0", "Apache-2.0")
    assert got["r/b/c/z.py"] == (None, "GPL-3.0", "r/b/LICENSE.txt", True)
    assert got["s/q.py"] == (None, None, None, False)
    assert got[None][:2] == ("MIT", "MIT")
    assert licenses.scan(files.limit(0)).count() == 0
    again = files.unionByName(files).withColumn("score", files["text"]).withColumn("term", files["path"])
    both = [tuple(r) for r in licenses.scan(again).collect()]
    assert sorted(map(str, both)) == sorted(map(str, [tuple(r) for r in licenses.scan(files).collect()] * 2))
    long = spark.createDataFrame([Row(path="x/LICENSE", text=("word " * 20 + "\n") * 5000 + "Released under the MIT License."), Row(path="x/COPYING", text="Released under the MIT License."), Row(path="x/a", text="")])
    tie = {r["path"]: (r["licence"], r["licence_from"]) for r in licenses.scan(long).collect()}
    assert tie == {"x/LICENSE": ("MIT", "x/LICENSE"), "x/COPYING": ("MIT", "x/COPYING"), "x/a": ("MIT", "x/COPYING")}


def test_license_scan_brute_force(spark, sf):
    """Every passage of every text against every template, without the anchors."""
    import re

    known, other = licenses.idf(licenses.TEMPLATES)
    weights: dict[str, dict[str, float]] = {}
    for n, t, w in licenses.template_weights(licenses.TEMPLATES):
        weights.setdefault(n, {})[t] = w
    files = queries.file_tree(spark.read.parquet(f"{sf}/documents.parquet"))
    got = {r["path"]: r["own_licence"] for r in licenses.scan(files).collect()}
    for r in files.collect():
        best = []
        for line in re.sub(licenses.CUT, "\\1\n", (r["text"] or "").lower()).split("\n"):
            x = {t: n * known.get(t, other) for t, n in Counter(re.findall(licenses.TERM, line)).items()}
            size = math.sqrt(sum(v * v for v in x.values()))
            for n, w in weights.items():
                s = round(sum(v * w.get(t, 0) for t, v in x.items()) / size, 6) if size else 0
                if s >= 0.75:
                    best.append((-s, n))
        assert got[r["path"]] == (min(best)[1] if best else None)


def test_license_headers_and_texts(spark):
    """Headers wrapped as in source files, whole licence files with a holder, and titles; words alone are none."""
    import textwrap

    from joinspace.llm import licence_forms

    def comment(mark, *paragraphs):
        return f"\n{mark}\n".join("\n".join(f"{mark} {x}" for x in textwrap.wrap(p, 64)) for p in paragraphs) + "\nint f(int x) { return x + 1; }\n"

    gpl = "This program is free software: you can redistribute it and/or modify it under the terms of the GNU {} as published by the Free Software Foundation, either version {} of the License, or (at your option) any later version."
    apache = 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at'
    text = {p.stem: p.read_text() for p in licence_forms.TEXTS.glob("*.txt")}
    body = text["BSD-3-Clause"].replace("the copyright holder", "Example Widgets Ltd")
    cases = [
        ("gpl.c", "GPL-3.0", comment("//", "Copyright (C) 2019 Ann Example", gpl.format("General Public License", 3), "You should have received a copy along with it.")),
        ("gpl2.c", "GPL-2.0", comment(" *", "A small tool", gpl.format("General Public License", 2).replace("software:", "software;"))),
        ("lgpl.c", "LGPL-2.1", comment("#", gpl.format("Lesser General Public License", "2.1"))),
        ("agpl.py", "AGPL-3.0", comment("#", gpl.format("Affero General Public License", 3))),
        ("apache.py", "Apache-2.0", comment("#", "Copyright 2021 Ann Example. All rights reserved.", apache, "http://www.apache.org/licenses/LICENSE-2.0")),
        ("bsd.c", "BSD-3-Clause", "/*\n" + body + "*/\nint x;\n"),
        ("bsd2.c", "BSD-2-Clause", comment("#", *text["BSD-2-Clause"].split("\n\n"))),
        ("mit.js", "MIT", "/* " + text["MIT"].replace("\n", "\n   ") + "*/\nlet x;\n"),
        ("t1", "MIT", "MIT License\nand words"),
        ("t2", "MIT", "# The MIT License (MIT)"),
        ("t3", "MIT", "Licensed under the MIT license."),
        ("t4", "GPL-3.0", "                    GNU GENERAL PUBLIC LICENSE\n                       Version 3, 29 June 2007\n\nwords"),
        ("t5", "Apache-2.0", "// SPDX-License-Identifier: Apache-2.0\nint x;"),
        ("n1", None, "mit\nEr kommt mit. Ein Text mit Worten, die mit nichts zu tun haben."),
        ("n2", None, "The license was granted in 2007. The general public may redistribute version 3 of the work under the terms of it."),
        ("n3", None, "hereby\napache\ngnu\nspdx\nlesser"),
    ]
    cases += [(f"{n}/LICENSE", n, "Copyright (c) 2020 Ann Example and others\n\n" + t) for n, t in text.items()]
    got = {r["path"]: r["own_licence"] for r in licenses.scan(spark.createDataFrame([Row(path=p, text=t) for p, _, t in cases])).collect()}
    assert got == {p: want for p, want, _ in cases}


def test_lm_matches_tree(spark, sf, odd, none):
    from pyspark.sql import functions as F

    docs = odd.select("doc_id", "text").unionByName(spark.read.parquet(f"{sf}/documents.parquet").limit(40).select((F.col("doc_id") + 100).alias("doc_id"), "text"))
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    train = lambda i: i is None or zlib.crc32(str(i).encode()) % 7 != 2
    texts = [t for i, t in rows if train(i)]
    model = lm.ContextTree(texts, 5)
    count = Counter(w for t in texts for w in lm.tokens(t))
    n, v = sum(count.values()), len(count)
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 7 != 2, F.lit(True))
    got = {(r["doc_id"], r["n_tokens"]): r for r in lm.score(docs, held, block_bytes=20_000, part_bytes=5_000).collect()}
    for i, t in rows:
        own = lm.tokens(t)
        r = got[i, len(own)]
        assert r["held_out"] == (not train(i)) and r["train_tokens"] == n and r["n_known"] == sum(count[w] > 0 for w in own)
        assert r["base_score"] == pytest.approx(sum(math.log10((count[w] + 1) / (n + v + 1)) for w in own), rel=1e-9)
        assert r["score"] == pytest.approx(model.log10(t), rel=1e-6)
    assert lm.score(none, F.lit(True)).count() == 0


class PlainTree:
    """Context-tree weighting from its definition: dictionaries, one decision at a time, no code of the operator."""

    def __init__(self, streams, depth):
        self.depth, self.counts, self.below = depth, {}, {}
        for data in streams:
            padded = b"\n" * depth + data
            for i, byte in enumerate(data):
                for j in range(8):
                    prefix, bit = format(byte, "08b")[:j], byte >> (7 - j) & 1
                    for d in range(depth + 1):
                        context = padded[i + depth - d : i + depth]
                        self.counts.setdefault((context, prefix), [0, 0])[bit] += 1
                        if d:
                            self.below.setdefault((context[1:], prefix), set()).add(context)
        self.known = {}

    def kt(self, node):
        a, b = self.counts[node]
        return math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)

    def weighted(self, node):
        if node not in self.known:
            own = self.kt(node)
            if len(node[0]) < self.depth:
                deeper = sum(self.weighted((c, node[1])) for c in self.below[node])
                top = max(own, deeper)
                own = top + math.log(0.5 * math.exp(own - top) + 0.5 * math.exp(deeper - top))
            self.known[node] = own
        return self.known[node]

    def bit(self, context, prefix, bit, d=0):
        """Probability of the next bit, mixed over this depth and all deeper ones."""
        node = (context[len(context) - d :], prefix)
        if node not in self.counts:
            return 0.5
        a, b = self.counts[node]
        own = ((b if bit else a) + 0.5) / (a + b + 1)
        if d == self.depth:
            return own
        stop = 0.5 * math.exp(self.kt(node) - self.weighted(node))
        return stop * own + (1 - stop) * self.bit(context, prefix, bit, d + 1)

    def log10(self, data):
        padded, out = b"\n" * self.depth + data, 0.0
        for i, byte in enumerate(data):
            for j in range(8):
                out += math.log10(self.bit(padded[i : i + self.depth], format(byte, "08b")[:j], byte >> (7 - j) & 1))
        return out


def test_lm_brute_force(spark):
    """The distributed model, the one in memory, and one built from the definition agree, on training texts and on others."""
    from pyspark.sql import functions as F

    texts = ["abra cadabra abra", "Abracadabra  the abracus", "a", "", None, "the cat sat on the mat; the rat sat", "zebra \u00e9t\u00e9 crab", "the brat"]
    stream = lambda t: (" ".join([*(t or "").lower().split(), ""]).rstrip(" ") + " \n").lstrip(" ").encode() if (t or "").split() else b"\n"
    assert all(lm.stream(lm.tokens(t)) == stream(t) for t in texts)
    plain = PlainTree([stream(t) for t in texts[:6]], 4)
    flat = lm.ContextTree(texts[:6], 4)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in lm.score(docs, F.col("doc_id") < 6, depth=4, block_bytes=40, part_bytes=10).collect()}
    for i, t in enumerate(texts):
        want = plain.log10(stream(t))
        assert flat.log10(t) == pytest.approx(want, rel=1e-9)
        assert got[i]["score"] == pytest.approx(want, rel=1e-6) and got[i]["held_out"] == (i >= 6)
        assert got[i]["code_length"] == pytest.approx(-want / math.log10(2) / len(stream(t)), rel=1e-6)


def test_lm_is_a_distribution():
    """Probabilities of all bytes after a context sum to one, whether it was seen or not."""
    model = lm.ContextTree(["abra cadabra", "abracadabra abra"], 3)
    for context in (b"bra", b"xyz", b"zra"):
        grams = np.array([int.from_bytes(context + bytes([b]), "big") for b in range(256)], np.uint64)
        assert float((10 ** model.of_runs(grams)).sum()) == pytest.approx(1.0, abs=1e-9)


def test_ctw_against_sequential_updates():
    """The closed form equals the product of sequential KT predictions at one node."""
    bits = [0, 1, 1, 0, 1, 1, 1]
    a = b = 0
    p = 1.0
    for x in bits:
        p *= ((b if x else a) + 0.5) / (a + b + 1)
        a, b = a + (x == 0), b + (x == 1)
    assert math.exp(lm.log_kt(np.array([float(a)]), np.array([float(b)]))[0]) == pytest.approx(p)


def test_language(spark, odd, none):
    from pathlib import Path

    docs = spark.read.parquet(str(Path("/root/testdata/sf0.01/documents.parquet")))
    rows = [r for r in queries.op5_language_id(spark, "/root/testdata/sf0.01").collect()]
    real = {r["doc_id"]: r["lang"] for r in docs.collect()}
    held = [r for r in rows if r["held_out"] and r["lang_pred"] != "und"]
    assert np.mean([r["lang_pred"] == real[r["doc_id"]] for r in held]) > 0.97
    model = language.fit(odd.select("text", "lang"))
    got = language.predict(odd, model).collect()
    assert len(got) == 9 and set(got[0].asDict()) == {*odd.columns, "lang_pred"}
    by = {r["doc_id"]: r for r in got}
    assert by[3]["lang_pred"] == by[4]["lang_pred"] == by[6]["lang_pred"] == "und" and by[6]["score"] == 0
    assert language.predict(odd, language.fit(none)).where("lang_pred <> 'und'").count() == 0


def test_language_brute_force(spark, sf):
    """Exact n-gram sets of the same sample, built in plain Python; the filter adds only its false positives, whose number is corrected."""
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 120")
    some, languages = language.sampled(docs.select("text", "lang"), 4000)
    fold = lambda t: " " + " ".join("".join(c if c.isascii() and c.isalpha() or not c.isascii() else " " for c in t.lower()).split(" ")) + " "

    def grams(t):
        raw = b" ".join(fold(t).encode().split())
        raw = b" " + raw + b" "
        return [raw[i : i + 5] for i in range(len(raw) - 4)]

    sets: dict[int, set] = {b: set() for b in range(len(languages))}
    for r in some.collect():
        sets[r["bit"]].update(grams(r["text"]))
    model = language.fit(docs.select("text", "lang"))
    assert model.languages == languages
    for b, own in sets.items():  # all languages that contain an n-gram, and few others
        keys = np.array([int.from_bytes(g, "big") for g in sorted(own)], np.uint64)
        masks = model.masks(keys)
        assert ((masks >> np.uint64(b)) & np.uint64(1) == 1).all()
        for other, theirs in ((o, t) for o, t in sets.items() if o != b):
            strange = np.array([g not in theirs for g in sorted(own)])
            assert np.mean((masks[strange] >> np.uint64(other)) & np.uint64(1) == 1) < 0.08
    wrong = 0
    got = {r["doc_id"]: r for r in language.predict(docs, model).collect()}
    for r in docs.collect():
        count = [sum(g in s for g in grams(r["text"] or "")) for s in sets.values()]
        if not any(c.isalpha() for c in r["text"] or "") or not sum(count):
            assert got[r["doc_id"]]["lang_pred"] == "und"
        elif sorted(count)[-1] > 1.1 * sorted(count)[-2]:
            assert got[r["doc_id"]]["lang_pred"] == languages[int(np.argmax(count))]
            assert got[r["doc_id"]]["score"] == pytest.approx(max(count) / sum(count), abs=0.05)
        else:
            wrong += 1
    assert wrong < 12


def test_bloom_returns_all_languages():
    sets = [np.arange(0, 3000, dtype=np.uint64), np.arange(2000, 5000, dtype=np.uint64)]
    model = language.SlicedBloom.build(["a", "b"], sets, 16)
    masks = model.masks(np.arange(0, 5000, dtype=np.uint64))
    assert ((masks[:3000] & np.uint64(1)) == 1).all() and ((masks[2000:] & np.uint64(2)) == 2).all()
    assert np.mean((masks[3000:] & np.uint64(1)) == 1) < 0.05


def test_top_k(spark):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(300, 12)).astype(np.float32)
    base[50:120] = base[50]  # ties
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(base)] + [(900, None), (901, [1.0, None]), (902, [float("nan")] * 12), (903, [0.5] * 5), (7, [0.1] * 12)]
    t = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    v = topk.whole(t)
    got = topk.top_k(v, v.where("vec_id % 50 = 0"), 5, chunk_rows=64, block_rows=2, longest=16).collect()
    live = [(i, np.pad(np.floor(np.array(x, np.float32).astype(float) * 256), (0, 12 - len(x))).astype(int)) for i, x in rows if x is not None and all(y is not None and np.isfinite(y) for y in x)]
    want = set()
    for q, x in live:
        if q % 50 == 0:
            best = sorted((-int(x @ y), i) for i, y in live if i != q)[:5]
            want |= {(q, n + 1, i, -s) for n, (s, i) in enumerate(best)}
    assert {(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in got} == want
    assert topk.top_k(v.limit(0), v.limit(0)).count() == 0
    huge = spark.createDataFrame([(1, [1e30]), (2, [1.0]), (None, [1.0]), (50, [2.0])], "vec_id long, embedding array<double>")
    h = topk.whole(huge)
    assert [tuple(r) for r in topk.top_k(h, h.where("vec_id = 50")).collect()] == [(50, 1, 2, 131072)]


def test_top_k_skips_ranges(spark):
    """Long vectors first: blocks meet only the ranges that can still matter, and results stay exact."""
    rng = np.random.default_rng(8)
    base = rng.normal(size=(600, 6)) * np.exp(-np.arange(600) / 60)[:, None]
    t = spark.createDataFrame([(i, [float(x) for x in v]) for i, v in enumerate(base)], "vec_id long, embedding array<double>")
    v = topk.whole(t)
    got = topk.top_k(v, v.where("vec_id % 50 = 0"), 5, chunk_rows=50, block_rows=3, longest=40, bounds=8)
    whole = np.floor(base * 256).astype(int)
    want = set()
    for q in range(0, 600, 50):
        best = sorted((-int(whole[q] @ whole[i]), i) for i in range(600) if i != q)[:5]
        want |= {(q, n + 1, i, -s) for n, (s, i) in enumerate(best)}
    assert {(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in got.collect()} == want
    assert topk.bounds_of(v.select(topk.F.size("v").alias("x")), "x", 4).tolist() == [6.0]


def test_near_duplicates(spark, odd, none):
    found = neardup.NearDuplicates(odd, words=2).components().collect()
    by = {r["doc_id"]: r for r in found}
    assert len(found) == 9 and by[2]["component_id"] == 1 and by[7]["component_id"] == 1
    assert by[3]["n_shingles"] == by[4]["n_shingles"] == 0 and by[5]["n_shingles"] == 1 and by[None]["kept"]
    kept = neardup.keep_one(odd)
    assert kept.columns == odd.columns and 2 not in {r["doc_id"] for r in kept.collect()}
    assert neardup.NearDuplicates(none).components().count() == 0


@pytest.mark.parametrize("shape", [(64, 12, 2048), (4, 3, 8), (1, 100, 1)])
def test_near_duplicates_chain(spark, shape):
    """Copies with growing edits: each links with its neighbours only, and all with each other over them."""
    rng = np.random.default_rng(5)
    words = [f"v{i}" for i in range(3000)]
    base = [words[i] for i in rng.integers(0, 3000, 200)]
    rows = []
    for i in range(60):
        own = list(base)
        for j in rng.choice(200, 12, replace=False):
            own[j] = f"e{i}_{j}"
        rows.append((i, " ".join(own)))
        if i % 5 == 4:
            base = own
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sets = {i: set(zip(t.split(), t.split()[1:], strict=False)) for i, t in rows}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in sets:
        for j in range(i):
            both = len(sets[i] & sets[j])
            if 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    got = {r["doc_id"]: r["component_id"] for r in neardup.NearDuplicates(docs, words=2, block=shape[0], copies=shape[1], widest=shape[2]).components().collect()}
    assert got == {i: find(i) for i in sets}


def test_near_duplicates_of_repeated_ids(spark):
    """A doc_id on rows with different texts: the links of each of its texts count, and the rows are one component."""
    text = lambda a, n=40: " ".join(f"{a}{i}" for i in range(n))
    rows = [(5, text("x")), (5, text("y")), (5, text("z")), (2, text("y") + " more"), (9, text("z") + " end"), (7, text("q")), (9, text("q") + " q")]
    got = {(r["doc_id"], r["component_id"], r["kept"]) for r in neardup.NearDuplicates(spark.createDataFrame(rows, "doc_id long, text string"), words=2).components().collect()}
    assert got == {(5, 2, False), (2, 2, True), (9, 2, False), (7, 2, False)}


def test_components(spark):
    """A long chain, a loop, repeated and null edges."""
    from joinspace.llm.components import connected

    rows = [(i, i + 1) for i in range(300)] + [(500, 501), (501, 500), (700, 700), (None, 3), (4, None), (500, 501)]
    got = {r["node"]: r["label"] for r in connected(spark.createDataFrame(rows, "a long, b long"), Scratch(spark)).collect()}
    assert got == {**dict.fromkeys(range(301), 0), 500: 500, 501: 500}
    assert connected(spark.createDataFrame([], "a long, b long"), Scratch(spark)).count() == 0


def test_components_against_union_find(spark):
    """Random graphs with stars around the greatest, the least and a middle node, node numbers of either sign and chains numbered at random."""
    from joinspace.llm.components import connected

    rng = np.random.default_rng(8)
    chain = rng.permutation(np.arange(5000, 5200))
    rows = [*zip(chain, chain[1:], strict=False), *((i, 999) for i in range(900, 999)), *((-50, i) for i in range(300, 400)), *((2050, i) for i in range(2000, 2100))]
    rows += [tuple(x) for x in rng.integers(-40, 160, (150, 2))]
    rows = [(int(a), int(b)) for a, b in rows]
    root = {x: x for pair in rows if pair[0] != pair[1] for x in pair}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in rows:
        if a != b:
            p, q = find(a), find(b)
            root[max(p, q)] = min(p, q)
    scratch = Scratch(spark)
    got = [(r["node"], r["label"]) for r in connected(spark.createDataFrame(rows, "a long, b long"), scratch).collect()]
    assert sorted(got) == sorted((x, find(x)) for x in root)
    assert set(scratch.made) == {"cc-labels"}


def test_substrings(spark, odd, none):
    got = {r["doc_id"]: r for r in substrings.removals(odd, 50).collect()}
    assert got[1]["n_removed"] == 0 and got[2]["n_removed"] == 160 and got[7]["n_removed"] == 160
    assert got[2]["kept_sha256"] == hashlib.sha256(b"head tail").hexdigest() and got[3]["n_words"] == 0
    assert got[4]["kept_sha256"] == hashlib.sha256(b"").hexdigest()
    cut = {r["doc_id"]: r["text"] for r in substrings.remove_repeats(odd).collect()}
    assert cut[2] == "head tail" and cut[1] == LONG and cut[5] == "Solo"
    assert substrings.removals(none).count() == 0
    table = {r["level_words"]: r["windows"] for r in substrings.levels(odd, 50).collect()}
    assert table[50] >= 111 and table[100] >= 61 and 200 not in table


def test_substrings_brute_force(spark):
    """Documents cut from few passages, with shifted and partly equal pieces."""
    rng = np.random.default_rng(11)
    pool = [[f"p{k}_{i}" for i in range(90)] for k in range(4)]
    rows = []
    for d in range(40):
        own: list[str] = []
        for _ in range(3):
            p = pool[int(rng.integers(4))]
            a = int(rng.integers(0, 40))
            own += p[a : a + int(rng.integers(30, 60))] + [f"f{d}_{int(rng.integers(1000))}" for _ in range(int(rng.integers(0, 4)))]
        rows.append((d, " ".join(own)))
    first: dict = {}
    for d, t in rows:
        w = t.split()
        for i in range(len(w) - 49):
            first.setdefault(tuple(w[i : i + 50]), d)
    got = {r["doc_id"]: r for r in substrings.removals(spark.createDataFrame(rows, "doc_id long, text string"), 50).collect()}
    for d, t in rows:
        w = t.split()
        gone = [False] * len(w)
        for i in range(len(w) - 49):
            if first[tuple(w[i : i + 50])] < d:
                gone[i : i + 50] = [True] * 50
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        assert (got[d]["n_removed"], got[d]["kept_sha256"]) == (sum(gone), hashlib.sha256(kept.encode()).hexdigest())


def test_warc_round_trip(spark):
    big = "<p>" + "é" * 200 + "\r\n\r\n</p>"
    rows = [(1, "http://B.example.com/x?y=1", big), (2, "https://a.b.example.com:8443/", big), (3, None, None), (4, "http://b.example.com/x?y=1", "tiny"), (5, "u", "tiny"), (None, "http://c.example.com", big), (2, "https://a.b.example.com:8443/", big)]
    pages = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, digest string")
    archive = warc.Archive.create(pages, block_lines=2, directory_rows=2)
    got = archive.captures().collect()
    assert len(got) == 7
    assert sorted((r["page_id"] or 0, r["record_type"], r["refers_to"]) for r in got if r["payload_bytes"] > 100) == [(0, "revisit", 1), (1, "response", None), (2, "revisit", 1), (2, "revisit", 1)]
    hit = archive.lookup("http://b.example.com/x?y=1")
    assert {h["page_id"] for h in hit} == {1, 4}
    assert {archive.fetch(h) for h in hit} == {big.encode(), b"tiny"}
    again = archive.lookup("https://a.b.example.com:8443/")[0]
    assert again["record_type"] == "revisit" and archive.fetch(again) == big.encode()
    assert warc.surt("http://m.a.org:80/x?y#z") == "org,a,m)/x?y"
    assert archive.lookup("http://nowhere.example.org/") == []
    assert all(archive.fetch(x) for h in got if h["url"] for x in archive.lookup(h["url"]))
    assert warc.Archive.create(spark.createDataFrame([], "page_id long, url string, html string")).captures().count() == 0


def test_warc_repeated_smallest_row(spark):
    """Only one of several equal rows with the smallest page_id is the response; the others point to it."""
    big = "z" * 300
    rows = [(1, "u1", big), (1, "u1", big), (1, "u0", big), (4, "u4", big), (None, "n", "y" * 200), (None, "n", "y" * 200)]
    archive = warc.Archive.create(spark.createDataFrame(rows, "page_id long, url string, html string"))
    got = sorted((r["page_id"] or 0, r["record_type"], r["refers_to"] or 0) for r in archive.captures().collect())
    assert got == [(0, "response", 0), (0, "response", 0), (1, "response", 0), (1, "revisit", 1), (1, "revisit", 1), (4, "revisit", 1)]
    rows = [(7, "u", big), (7, "u", big), (8, "u", big)]
    archive = warc.Archive.create(spark.createDataFrame(rows, "page_id long, url string, html string"))
    assert sorted(r["record_type"] for r in archive.captures().collect()) == ["response", "revisit", "revisit"]
    assert {archive.fetch(x) for x in archive.lookup("u")} == {big.encode()}


def test_warc_files_are_bounded(spark, tmp_path):
    """Files hold about `file_bytes`, whatever the pages' sizes."""
    import random

    draw = random.Random(1)
    noise = lambda n: "".join(chr(draw.randrange(33, 126)) for _ in range(n))
    pages = spark.createDataFrame([(i, f"u{i}", noise(30_000 if i == 5 else 2000)) for i in range(60)], "page_id long, url string, html string").coalesce(1)
    scratch = Scratch(spark)
    warc.write(pages, str(tmp_path / "w"), scratch, run_bytes=10_000, file_bytes=60_000)
    sizes = [p.stat().st_size for p in (tmp_path / "w").glob("part-*")]
    assert len(sizes) > 2 and max(sizes) < 70_000
    assert warc.read(spark, str(tmp_path / "w")).count() == 60


def test_mixing(spark, odd, none):
    got = mixing.rates(odd.select("doc_id", "text", "source")).collect()
    assert len(got) == 9 and all(r["copies"] <= 3 for r in got)
    clash = mixing.rates(odd.withColumn("target", odd["text"]).withColumn("source_size", odd["text"]))
    pick = ["doc_id", "source", "size", "source_size", "target", "copies"]
    assert sorted(map(str, clash.select(pick).collect())) == sorted(map(str, mixing.rates(odd.select("doc_id", "text", "source")).select(pick).collect()))
    assert sorted(clash.columns) == sorted({*odd.columns, *mixing.ADDED})
    huge = spark.createDataFrame([(f"s{i:03}", 10**13) for i in range(100)], "source string, source_size long")
    assert sum(r["target"] for r in mixing.targets(huge).collect()) == pytest.approx(1e15)
    sources = spark.createDataFrame([("a", 10), ("b", 1000), ("c", 100), (None, 50)], "source string, source_size long")
    t = {r["source"]: r["target"] for r in mixing.targets(sources).collect()}
    assert t["a"] == 30 and sum(t.values()) == pytest.approx(1160) and t[None] == 150
    rest = 1160 - 30 - 150
    assert t["c"] == 300 and t["b"] == pytest.approx(rest - 300)
    mixed = mixing.mix(odd)
    assert mixed.columns == [*odd.columns, "copy_no"]
    assert mixing.mix(none).count() == 0
    assert sorted(map(str, mixing.mix(odd).collect())) == sorted(map(str, mixed.collect()))


def test_scratch_tables(spark):
    s = Scratch(spark)
    df = s.store(spark.range(5), "x")
    assert df.count() == 5
    s.drop("x")
    s.close()


def test_licence_terms_meet_one_set(spark):
    """Known terms are not put into a table anew for each passage."""
    files = spark.createDataFrame([("a", "Licensed under the Apache License, Version 2.0.")], "path string, text string")
    plan = licenses.own_licences(files)._jdf.queryExecution().optimizedPlan().toString()
    assert "array_except" not in plan


def test_licence_filters_work_out_words_once(spark):
    """A filter that names an expression once a form runs it as often: rare words were searched 48 times in each text and passage."""
    files = spark.createDataFrame([Row(path="a", text="Released under the MIT License.")])
    plan = licenses.own_licences(files)._jdf.queryExecution().optimizedPlan().toString()
    assert max(line.count("regexp_extract_all") for line in plan.split("\n")) <= 2
    assert any("Filter" in line and "exists(array(lower(text" in line for line in plan.split("\n"))  # texts are tested before passages are cut


def test_decontaminate_blocks_at_all_offsets(spark):
    """Windows of every width, at every offset, at the ends and next to each other; blocks are probed before any window is cut."""
    items = [" ".join(f"w{width}x{i}" for i in range(width + (width == 10) * 3)) for width in range(1, 11)]
    texts = [" ".join(["pad"] * before + items[n].split()[cut:] + ["End"] * after) for n in range(10) for before in (*range(8), 13) for after in (0, 3) for cut in (0, 1)] + [" ".join(items), None, ""]
    docs = spark.createDataFrame([Row(doc_id=i, text=t) for i, t in enumerate(texts)], "doc_id long, text string")
    bench = spark.createDataFrame([Row(item_id=i, text=t) for i, t in enumerate(items)], "item_id long, text string")
    want = {}
    for d, text in enumerate(texts):
        own, hit, seen = (text or "").lower().split(), set(), set()
        for i, item in enumerate(items):
            words = item.split()
            width = min(10, len(words))
            grams = {tuple(words[j : j + width]) for j in range(len(words) - width + 1)}
            for j in range(len(own) - width + 1):
                if tuple(own[j : j + width]) in grams:
                    hit |= set(range(j, j + width))
                    seen.add(str(i))
        want[d] = (len(own), len(hit), sorted(seen))
    for most in (1_000_000, 0):
        found = decontaminate.scan(docs, bench, broadcast_windows=most)
        assert {r["doc_id"]: (r["n_words"], r["n_hit"], r["items"]) for r in found.collect()} == want
        assert found._jdf.queryExecution().optimizedPlan().toString().count("LeftSemi") == 10


def test_sieve(spark):
    """All rows with a partner pass, few others; near duplicates sieve texts and bucket entries before they are shuffled."""
    from joinspace.llm.common import sieve

    rows = spark.range(0, 20_000).selectExpr("id as a", "string(id % 7) as b", "id as more")
    wanted = rows.where("a % 20 = 3").select("a", "b")
    kept = sieve(rows, wanted, "a", "b")
    assert kept.columns == rows.columns
    got = {r["a"] for r in kept.collect()}
    assert {a for a in range(20_000) if a % 20 == 3} <= got and len(got) < 4_000
    assert sieve(rows, wanted, "a", "b", most=1 << 15).where("a % 20 = 3").count() == 1_000
    assert sieve(rows, wanted.limit(0), "a", "b").count() == 0
    assert sieve(rows, wanted, "a", "b").join(wanted, ["a", "b"]).count() == 1_000
    docs = spark.createDataFrame([Row(doc_id=i, text=f"one two three {i // 2}") for i in range(8)])
    found = neardup.NearDuplicates(docs, words=2)
    wanted = found.scratch.store(found._profile().selectExpr("doc_id as node", "doc_id", "text_key"), "all")
    assert "bitmap_construct_agg" in found._sets(wanted)._jdf.queryExecution().optimizedPlan().toString()
