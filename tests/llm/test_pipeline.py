"""The corpus pipeline against a brute-force version of all its stages, and odd rows through each stage."""

from __future__ import annotations

import hashlib
import re
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from joinspace.llm import language

SPACE = " \t\n\v\f\r"
PASSAGE = " ".join(f"shared{i}" for i in range(70))


def words(text):
    return [w for w in re.split(f"[{SPACE}]+", text or "") if w]


def low(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text)


@pytest.fixture(scope="module")
def folder(spark, sf, tmp_path_factory):
    at = str(tmp_path_factory.mktemp("pipeline"))
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id % 2 = 0 and length(text) < 6000")
    one = docs.orderBy("doc_id").first()
    more = [
        (1001, one["text"], "en", "extra", 1), (1003, one["text"] + " more", "en", "extra", 1), (1005, None, None, None, None), (1007, "12 34 !!", "en", "extra", 8),
        (1009, "alone in front " + PASSAGE, "en", "extra", 9), (1011, PASSAGE + " and alone behind", "en", None, 9), (1013, "middle " + PASSAGE + "\nend", "de", "extra", 9), (1015, "", "en", "extra", 0),
    ]
    docs = docs.unionByName(spark.createDataFrame(more, docs.schema)).withColumn("copy_no", F.lit("clash")).withColumn("size", F.lit(1)).withColumn("score", F.lit(0.5))
    docs.write.parquet(f"{at}/documents.parquet")
    spark.read.parquet(f"{sf}/benchmark.parquet").write.parquet(f"{at}/benchmark.parquet")
    return at


def by_language(rows):
    """Exact n-gram sets of all labelled rows; a text without a letter or a known n-gram goes."""

    def grams(t):
        raw = " ".join("".join(c if not c.isascii() or c.isalpha() else " " for c in t.lower()).split(" ")).encode()
        raw = b" " + b" ".join(raw.split()) + b" "
        return {raw[i : i + language.NGRAM] for i in range(len(raw) - language.NGRAM + 1)}

    known = set().union(*(grams(r["text"]) for r in rows if r["lang"] is not None and r["text"] is not None))
    return [r for r in rows if any(c.isalpha() for c in r["text"] or "") and grams(r["text"]) & known]


def by_likeness(rows):
    sets = {}
    for r in rows:
        w = words(low(r["text"] or ""))
        n = min(5, len(w))
        sets[r["doc_id"]] = {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for j, b in enumerate(ids):
        for a in ids[:j]:
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return [r for r in rows if find(r["doc_id"]) == r["doc_id"]]


def by_passage(rows):
    first = {}
    for r in sorted(rows, key=lambda r: r["doc_id"]):
        w = words(r["text"])
        for i in range(len(w) - 49):
            first.setdefault(tuple(w[i : i + 50]), r["doc_id"])
    out = []
    for r in rows:
        w = words(r["text"])
        gone = set()
        for i in range(len(w) - 49):
            if first[tuple(w[i : i + 50])] < r["doc_id"]:
                gone |= set(range(i, i + 50))
        if gone:
            pieces = re.findall(f"[^{SPACE}]+[{SPACE}]*", r["text"])
            left = re.match(f"[{SPACE}]*", r["text"]).group() + "".join(p for i, p in enumerate(pieces) if i not in gone)
            if not words(left):
                continue
            r = {**r, "text": left, "n_chars": len(left)}
        elif r["text"] is not None:
            r = {**r, "n_chars": len(r["text"])}
        out.append(r)
    return out


def by_benchmark(rows, items):
    cut = lambda t: re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", low(t or ""))
    grams = set()
    for t in items:
        w = cut(t)
        n = min(10, len(w))
        grams |= {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if n else set()
    sizes = {len(g) for g in grams}
    return [r for r in rows if not any(tuple(w[i : i + n]) in grams for w in [cut(r["text"])] for n in sizes for i in range(len(w) - n + 1))]


def mixed(rows):
    size = defaultdict(int)
    for r in rows:
        size[r["source"]] += len(words(r["text"]))
    order = sorted(size, key=lambda s: (s is None, (s or "").encode("utf-32-be")))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    target, left, open_ = {}, sum(size.values()), set(order)
    while open_:
        share = left / sum(weight[s] for s in open_)
        full = {s for s in open_ if share * weight[s] >= 3 * size[s]}
        if not full:
            target |= {s: share * weight[s] for s in open_}
            break
        for s in full:
            target[s] = 3.0 * size[s]
            left -= 3 * size[s]
        open_ -= full
    out = []
    for r in rows:
        n = size[r["source"]]
        rate = min(3.0, target[r["source"]] / n) if n else 0.0
        draw = int(hashlib.md5(f"mix:{r['doc_id']}".encode()).hexdigest()[:13], 16) / 16**13
        copies = int(rate) + (draw < rate - int(rate))
        out += [{**r, "copy_no": i + 1} for i in range(copies)]
    return out


def test_run_brute_force(spark, folder):
    rows = [r.asDict() for r in spark.read.parquet(f"{folder}/documents.parquet").collect()]
    items = [r["text"] for r in spark.read.parquet(f"{folder}/benchmark.parquet").collect()]
    seen = [len(rows)]
    for step in (by_language, by_likeness, by_passage, lambda x: by_benchmark(x, items)):
        rows = step(rows)
        seen.append(len(rows))
    assert seen[0] > seen[1] > seen[2] and seen[3] > seen[4]  # every stage has something to decide
    got = corpus_pipeline.run(spark, folder)
    names = got.columns
    want = sorted(repr(tuple(r[c] for c in names)) for r in mixed(rows))
    assert sorted(repr(tuple(r)) for r in got.collect()) == want
    assert any("alone behind" in r["text"] and "shared3" not in r["text"] for r in rows)  # a passage was cut


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stage_on_odd_rows(spark, folder, name):
    """Null, empty and repeated rows and clashing columns: no crash, the same columns, and the stated decisions."""
    schema = "doc_id long, text string, lang string, source string, n_chars long, lang_pred string, score double, copy_no int, kept boolean, d long, k long"
    text = " ".join(f"a{i}" for i in range(60))
    rows = [(1, text, "en", "s", 1), (1, text, "en", "s", 1), (2, None, None, None, None), (None, "some words here", "en", None, 1), (3, "", "de", "s", 0), (4, "y" * 70_000 + " " + text, "en", "s", 1)]
    docs = spark.createDataFrame([(*r, "x", 0.1, 7, None, 1, 2) for r in rows], schema)
    stage = dict(corpus_pipeline.STAGES)[name]
    got = stage(spark, docs, folder)
    assert sorted(got.columns) == sorted(docs.columns)
    ids = [r["doc_id"] for r in got.collect()]
    assert stage(spark, docs.limit(0), folder).count() == 0
    if name == "language_id":
        assert sorted(ids, key=str) == [1, 1, 4, None]
    elif name == "near_dedup":
        assert sorted(ids, key=str) == [1, 1, 2, 3, None]  # 4 has all shingles of 1 and one more
    elif name == "decontamination":
        assert sorted(ids, key=str) == [1, 1, 2, 3, 4, None]
    elif name == "substring_dedup":
        assert {1, 4, None} <= set(ids)
