"""License scans: sparse TF-IDF cosine of header passages and licence files to templates, then inheritance by path.

Native. A passage is a line, cut again behind sentence ends, and is scored against one-line notices. Lines, paragraphs, the header (the
leading comment) and the whole text are also scored against the forms of `licence_forms`: titles, header paragraphs and whole licence texts, by
the cosine of distinct terms, as the words of running text all repeat in a long licence. Only passages with all key words of a form have it. For the notices, only passages
are scored whose terms hold enough of a template's length: by Cauchy-Schwarz the others cannot reach the threshold. That is tested first on the text, where a term may be part of a
word, and again on the terms. A file takes its best passage. A file without
a licence of its own takes that of the licence file in the nearest ancestor directory, found by joining its directory's
prefixes to the directories that have one.

Defined cases: a null text has no licence; very long texts are cut and scored whole; extra columns are ignored, whatever their names; a null path has no directory and inherits nothing; equal scores go to the
template first by name; several licence files in one directory: the highest score, then the smallest path; rows that
repeat a path and text get the same result each; empty tables give empty results.
"""

from __future__ import annotations

import json
import math
import re
from collections import Counter
from collections.abc import Callable
from functools import reduce
from operator import and_, or_

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import licence_forms
from .common import Scratch, text_key

#: Short notices by SPDX identifier.
TEMPLATES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "BSD-3-Clause": "Use of this source code is governed by a BSD-style license. Redistribution and use in source and binary forms are permitted.",
    "CC-BY-4.0": "Licensed under CC BY 4.0. This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "LGPL-3.0": "This library is licensed under the GNU Lesser General Public License, version 3.",
    "MIT": "Released under the MIT License.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
}
TERM = "[a-z0-9]+"
CUT = r"([.!?;])\s+"

#: A line of a comment, or one without terms.
COMMENT = r"^\s*(#|//|/\*|\*|--|;|%|<!--|dnl\b|rem\b)|^[^a-z0-9]*$"
#: A comment from the start of the text whose lines need no mark of their own, behind a line for the interpreter.
BLOCK = r"^(?:(?:#!|<\?)[^\n]*\n)?\s*(?:/\*[\s\S]*?\*/|<!--[\s\S]*?-->|\"\"\"[\s\S]*?\"\"\"|'''[\s\S]*?'''|\(\*[\s\S]*?\*\))"


def literal_rows(spark: SparkSession, rows: list[tuple], *names: str) -> DataFrame:
    """A small table out of one JSON literal: no Python task makes it."""
    kinds = {int: "int", float: "double", str: "string"}
    schema = ", ".join(f"{n} {kinds[type(v)]}" for n, v in zip(names, rows[0], strict=True))
    text = json.dumps([dict(zip(names, r, strict=True)) for r in rows])
    return spark.range(1).select(F.inline(F.from_json(F.lit(text), f"array<struct<{schema.replace(' ', ':')}>>".replace(",:", ","))))


def idf(templates: dict[str, str]) -> tuple[dict[str, float], float]:
    """Smoothed inverse document frequencies over the templates, and that of any other term."""
    df = Counter(t for text in templates.values() for t in set(re.findall(TERM, text.lower())))
    value = lambda n: round(math.log((1 + len(templates)) / (1 + n)) + 1, 12)
    return {t: value(n) for t, n in df.items()}, value(0)


def template_weights(templates: dict[str, str]) -> list[tuple[str, str, float]]:
    """(template, term, unit weight)"""
    known, _ = idf(templates)
    out = []
    for name, text in sorted(templates.items()):
        raw = {t: n * known[t] for t, n in Counter(re.findall(TERM, text.lower())).items()}
        size = math.sqrt(sum(w * w for w in raw.values()))
        out += [(name, t, w / size) for t, w in sorted(raw.items())]
    return out


def reachable(has: Callable[[str], Column], templates: dict[str, str], threshold: float) -> Column:
    """False only where the score must be below the threshold: it is at most the root of the squared weights of the
    template's terms that occur, by Cauchy-Schwarz. has: whether a term occurs; it may also say so of terms that do not."""
    any_of = F.lit(False)
    for name, few in needed(templates, threshold).items():
        mass = F.lit(0.0)
        for n, t, w in template_weights(templates):
            if n == name:
                mass = mass + F.when(has(t), w * w).otherwise(0.0)
        any_of = any_of | (reduce(or_, (has(t) for t in few), F.lit(False)) & (mass >= (threshold * 0.999) ** 2))  # most end at the few
    return any_of


def needed(templates: dict[str, str], threshold: float) -> dict[str, list[str]]:
    """Terms of each template of which every passage that can reach the threshold holds one: the heaviest, long ones before short ones, so many
    that the others hold too little of its length (see `reachable`)."""
    out: dict[str, list[str]] = {}
    for name in templates:
        mass, out[name] = 1.0, []
        for w, t in sorted(((w, t) for n, t, w in template_weights(templates) if n == name), key=lambda x: (len(x[1]) < 3, -x[0], x[1])):
            if mass < (threshold * 0.99) ** 2:
                break
            out[name].append(t)
            mass -= w * w
    return out


def once(value: Column, test: Callable[[Column], Column]) -> Column:
    """test(value), with the value worked out once a row: a filter that names an expression many times runs it as often."""
    return F.exists(F.array(value), test)


def own_licences(files: DataFrame, templates: dict[str, str] = TEMPLATES, threshold: float = 0.75, forms: list[tuple[str, list[str], str]] | None = None) -> DataFrame:
    """(path, text_key, licence, score) of files with a passage at or over the threshold; forms: those of `licence_forms` by default."""
    spark = files.sparkSession
    known, other = idf(templates)
    weights = F.broadcast(literal_rows(spark, template_weights(templates), "licence", "term", "w"))  # fixed size
    held = files.where(once(F.lower("text"), lambda low: reachable(lambda t: F.contains(low, F.lit(t)), templates, threshold)))  # a text holds what its passages hold
    passages = held.select("path", text_key(F.col("text")).alias("text_key"), F.posexplode(F.split(F.regexp_replace(F.lower("text"), CUT, "$1\n"), "\n")).alias("no", "passage"))
    passages = passages.where(reachable(lambda t: F.contains("passage", F.lit(t)), templates, threshold))  # if only as parts of words: no terms are cut yet
    passages = passages.withColumn("terms", F.regexp_extract_all("passage", F.lit(TERM), F.lit(0)))
    passages = passages.where(once(F.col("terms"), lambda terms: reachable(lambda t: F.array_contains(terms, t), templates, threshold)))  # terms are cut once, not once a template
    # rows that repeat a path and text count once
    terms = passages.groupBy("path", "text_key", "no").agg(F.first("terms").alias("terms")).select("path", "text_key", "no", F.explode("terms").alias("term"))
    counts = terms.groupBy("path", "text_key", "no", "term").agg(F.count("*").alias("n"))
    table = F.broadcast(literal_rows(spark, list(known.items()), "term", "idf"))
    weighed = counts.join(table, "term", "left").withColumn("x", F.col("n") * F.coalesce("idf", F.lit(other)))
    per = weighed.groupBy("path", "text_key", "no").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("size"), F.collect_list(F.struct("term", "x")).alias("terms"))
    dots = per.select("path", "text_key", "no", "size", F.explode("terms").alias("t")).select("path", "text_key", "no", "size", "t.*").join(weights, "term").groupBy("path", "text_key", "no", "size", "licence").agg(F.sum(F.col("x") * F.col("w")).alias("dot"))
    scored = dots.withColumn("score", F.round(F.col("dot") / F.col("size"), 6)).where(F.col("score") >= threshold)
    forms = licence_forms.forms() if forms is None else forms
    scored = scored.select("path", "text_key", "licence", "score")
    scored = scored.unionByName(with_forms(files, forms, threshold)) if forms else scored
    best = F.min(F.struct((-F.col("score")).alias("s"), "licence"))
    return scored.groupBy("path", "text_key").agg(best.alias("b")).select("path", "text_key", F.col("b.licence").alias("licence"), (-F.col("b.s")).alias("score"))


def form_weights(forms: list[tuple[str, list[str], str]]) -> tuple[list[tuple[int, str, float, int]], dict[str, float], float]:
    """(form, term, unit weight, 1 for key words) of each form's distinct terms; their idf, and that of any other term."""
    sets = [sorted({*re.findall(TERM, spelled(text)), *key}) for _, key, text in forms]
    known, other = idf({str(i): " ".join(x) for i, x in enumerate(sets)})
    sizes = [math.sqrt(sum(known[t] ** 2 for t in x)) for x in sets]
    return [(i, t, known[t] / sizes[i], int(t in forms[i][1])) for i, x in enumerate(sets) for t in x], known, other


def spelled(text: str) -> str:
    return text.lower().replace("licence", "license")


def form_passages(low: Column) -> Column:
    """Lines, paragraphs, the header and the whole of a lower-case text."""
    lines = F.split(low, "\n")
    marks = F.transform(lines, lambda x: x.rlike(COMMENT))
    ends = F.array_position(marks, False)
    header = F.when(ends > 1, F.array_join(F.slice(lines, 1, (ends - 1).cast("int")), "\n"))
    found = F.concat(lines, F.split(F.regexp_replace(low, CUT, "$1\n"), "\n"), F.split(low, r"\n[^a-z0-9]*\n"), F.array(header, F.regexp_extract(low, BLOCK, 0), low))
    return F.array_distinct(F.array_compact(found))


def with_forms(files: DataFrame, forms: list[tuple[str, list[str], str]], threshold: float) -> DataFrame:
    """(path, text_key, licence, score) of each file's passages and forms at or over the threshold."""
    spark = files.sparkSession
    rows, known, other = form_weights(forms)
    weights = F.broadcast(literal_rows(spark, rows, "form", "term", "w", "is_key"))  # fixed size
    names = F.broadcast(literal_rows(spark, [(i, name, len(set(key))) for i, (name, key, _) in enumerate(forms)], "form", "licence", "n_key"))
    table = F.broadcast(literal_rows(spark, list(known.items()), "term", "idf"))
    rarest = r"\b(" + "|".join(sorted({key[0] for _, key, _ in forms})) + r")\b"
    keys = sorted({tuple(key) for _, key, _ in forms})
    # all key words of some form must stand in the text, and in the passage, if only as parts of words: a cheap test before any terms are cut
    rare = lambda text: F.array_distinct(F.regexp_extract_all(text, F.lit(rarest), F.lit(0)))
    behind = {first: [key[1:] for key in keys if key[0] == first] for first, *_ in keys}
    with_rest = lambda text, is_there: reduce(or_, (is_there(first) & reduce(or_, (reduce(and_, (F.contains(text, F.lit(t)) for t in rest), F.lit(True)) for rest in rests)) for first, rests in behind.items()))
    spells = lambda text: with_rest(text, lambda t: F.contains(text, F.lit(t))) & once(rare(text), lambda found: with_rest(text, lambda t: F.array_contains(found, t)))
    lowered = F.replace(F.lower("text"), F.lit("licence"), F.lit("license"))
    low = files.where(once(lowered, spells)).select("path", text_key(F.col("text")).alias("text_key"), lowered.alias("low"))
    passages = low.select("path", "text_key", F.posexplode(form_passages(F.col("low"))).alias("no", "passage")).where(spells(F.col("passage")))
    passages = passages.select("path", "text_key", "no", F.array_distinct(F.regexp_extract_all("passage", F.lit(TERM), F.lit(0))).alias("terms"))
    has = lambda terms: reduce(or_, (reduce(and_, (F.array_contains(terms, t) for t in key)) for key in keys))
    # No term weighs more than an unknown one, so by Cauchy-Schwarz too many unknown ones for those known keep every score below the threshold.
    # One set of known terms serves all rows: array_except would fill a table of them for each row.
    strange = lambda terms: F.size(F.filter(terms, lambda t: ~t.isin(sorted(known))))
    near = lambda terms: once(strange(terms), lambda n: n * threshold**2 * 0.999 <= (1 - threshold**2) * (F.size(terms) - n))
    passages = passages.where(once(F.col("terms"), lambda terms: has(terms) & near(terms)))
    # rows that repeat a path and text count once
    passages = passages.groupBy("path", "text_key", "no").agg(F.first("terms").alias("terms"))
    terms = passages.select("path", "text_key", "no", F.explode("terms").alias("term")).join(table, "term", "left").withColumn("x", F.coalesce("idf", F.lit(other)))
    sizes = terms.groupBy("path", "text_key", "no").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("size"), F.collect_list(F.struct("term", "x")).alias("terms"))
    hits = sizes.select("path", "text_key", "no", "size", F.explode("terms").alias("t")).select("path", "text_key", "no", "size", "t.*").join(weights, "term")
    dots = hits.groupBy("path", "text_key", "no", "size", "form").agg(F.sum(F.col("x") * F.col("w")).alias("dot"), F.sum("is_key").alias("keys"))
    scored = dots.withColumn("score", F.round(F.col("dot") / F.col("size"), 6)).where(F.col("score") >= threshold).join(names, "form")
    return scored.where(F.col("keys") == F.col("n_key")).select("path", "text_key", "licence", "score")


def scan(files: DataFrame, templates: dict[str, str] = TEMPLATES, threshold: float = 0.75, licence_file: str = r"(^|/)(LICEN[CS]E|COPYING)(\.[a-z]+)?$", broadcast_rows: int = 100_000, forms: list[tuple[str, list[str], str]] | None = None) -> DataFrame:
    """files (path, text, ...) -> (path, text_key, own_licence, score, licence, licence_from, inherited)."""
    spark = files.sparkSession
    scratch = Scratch(spark)
    own = scratch.store(own_licences(files, templates, threshold, forms), "own")
    folder = F.regexp_replace("path", r"/?[^/]*$", "")
    given = own.where(F.col("path").rlike(licence_file)).withColumn("folder", folder)
    given = given.groupBy("folder").agg(F.min(F.struct((-F.col("score")).alias("s"), "path", "licence")).alias("b")).select(F.col("folder").alias("above"), F.col("b.licence").alias("given"), F.col("b.path").alias("given_by"))
    given = scratch.store(given, "given")
    small = given.count() <= broadcast_rows
    dirs = files.where(F.col("path").isNotNull()).select(folder.alias("folder")).distinct()
    parts = F.split("folder", "/")
    ups = dirs.select("folder", F.posexplode(F.transform(F.sequence(F.size(parts), F.lit(0), F.lit(-1)), lambda n: F.array_join(F.slice(parts, 1, n), "/"))).alias("up", "above"))
    near = ups.join(F.broadcast(given) if small else given, "above").groupBy("folder").agg(F.min(F.struct("up", "given", "given_by")).alias("g"))
    near = scratch.store(near.select(F.col("folder").alias("f"), "g.given", "g.given_by"), "near")
    rows = files.select("path", text_key(F.col("text")).alias("text_key"), folder.alias("folder"))
    mine = own.select(F.col("path").alias("p"), F.col("text_key").alias("k"), F.col("licence").alias("own_licence"), "score")
    out = rows.join(mine, F.col("path").eqNullSafe(F.col("p")) & (F.col("text_key") == F.col("k")), "left").join(near, F.col("folder") == F.col("f"), "left")
    has = F.col("own_licence").isNotNull()
    return out.select("path", "text_key", "own_licence", "score", F.coalesce("own_licence", "given").alias("licence"), F.when(has, F.col("path")).otherwise(F.col("given_by")).alias("licence_from"), (~has & F.col("given").isNotNull()).alias("inherited"))
