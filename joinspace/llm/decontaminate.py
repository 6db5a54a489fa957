"""Benchmark decontamination: a broadcast hash set of normalised test n-grams against all token windows.

Native: tokenisation, window hashes, the probe and the check of hits are SQL expressions inside one
generated stage. Windows are probed by a 64-bit hash; a hit counts only if the window's words are equal.
Beyond `broadcast_windows` distinct test windows the probe is a shuffled join instead of a broadcast one.

Defined cases: a null or word-free text has no words and no hits; a null benchmark text gives no window;
rows with a null doc_id are scanned like others; rows that repeat doc_id and text each get their result;
an empty benchmark leaves every document clean; extra columns are ignored by `scan` and kept by the removers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, lower_az, text_key

#: What stands between words (after lower-casing), and a word before lower-casing, as the ranges it has: most letters meet the first one.
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
RAW_WORD = r"[a-zA-Z0-9\x80-\x{10FFFF}]+"


def words(text: Column) -> Column:
    return F.coalesce(F.array_remove(F.split(lower_az(text), BETWEEN), ""), F.array().cast("array<string>"))


def count_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(RAW_WORD)), F.lit(0)).cast("long")


def _starts(tokens: Column, width: Column) -> Column:
    """1-based starts of windows of that width."""
    n = F.size(tokens) - width + 1
    return F.when(n > 0, F.sequence(F.lit(1), F.greatest(n, F.lit(1)))).otherwise(F.array().cast("array<int>"))


def test_windows(benchmark: DataFrame, width: int = 10) -> DataFrame:
    """Distinct windows (width, hash, gram) with the item_ids they come from."""
    own = benchmark.select(F.col("item_id").cast("string").alias("item"), words(F.col("text")).alias("t")).where(F.size("t") > 0)
    own = own.withColumn("width", F.least(F.size("t"), F.lit(width)))
    grams = own.select("item", "width", F.explode(F.transform(_starts(F.col("t"), F.col("width")), lambda i: F.concat_ws(" ", F.slice("t", i, F.col("width"))))).alias("gram"))
    return grams.groupBy("width", "gram").agg(F.array_sort(F.collect_set("item")).alias("items"))


def hits(documents: DataFrame, windows: DataFrame, widths: list[int], broadcast: bool) -> DataFrame:
    """(doc_id, text_key, start, width, items): every occurrence of a test window, checked word by word.

    Blocks of half a window are probed first, at every `step`-th word: of the starts that a window can have, each `step` in a row
    hold the same one of these blocks whole. So all windows around the blocks that occur in a test window are all that can hit."""
    docs = documents.select("doc_id", text_key(F.col("text")).alias("text_key"), words(F.col("text")).alias("t"))
    found = None
    for width in widths:
        size = (width + 1) // 2
        step = width - size + 1
        wide = windows.where(F.col("width") == width).select(F.split("gram", " ").alias("g"), "gram", "items")
        probe = wide.select(F.xxhash64("g").alias("h"), "gram", "items")
        blocks = wide.select(F.explode(F.transform(_starts(F.col("g"), F.lit(size)), lambda i: F.xxhash64(F.slice("g", i, size)))).alias("block")).distinct()
        n = F.size("t") - size + 1
        firsts = F.when(n > 0, F.sequence(F.lit(1), F.greatest(n, F.lit(1)), F.lit(step))).otherwise(F.array().cast("array<int>"))
        scanned = docs.select("doc_id", "text_key", "t", F.posexplode(F.transform(firsts, lambda i: F.xxhash64(F.slice("t", i, size)))).alias("no", "block"))
        first = F.greatest(F.col("no") * step + 2 - step, F.lit(1))  # of the windows around a block
        around = F.slice("t", first, F.col("no") * step + 1 + width - first)
        if broadcast:
            near = scanned.join(F.broadcast(blocks), "block", "left_semi").select("doc_id", "text_key", first.alias("first"), around.alias("t"))
        else:
            near = scanned.select("doc_id", "text_key", "block", first.alias("first"), around.alias("t")).join(blocks, "block", "left_semi")
        near = near.select("doc_id", "text_key", "first", "t", F.posexplode(F.transform(_starts(F.col("t"), F.lit(width)), lambda i: F.xxhash64(F.slice("t", i, width)))).alias("at", "h"))
        near = near.select("doc_id", "text_key", (F.col("first") - 1 + F.col("at")).alias("start"), "h", F.concat_ws(" ", F.slice("t", F.col("at") + 1, width)).alias("w"))
        one = near.join(F.broadcast(probe) if broadcast else probe, "h").where(F.col("w") == F.col("gram"))
        one = one.select("doc_id", "text_key", "start", F.lit(width).alias("width"), "items")
        found = one if found is None else found.unionByName(one)
    return found


def covered(spans: Column) -> Column:
    """Words in the union of sorted (start, width) spans."""
    step = lambda s, x: F.struct(
        (s["n"] + F.greatest(F.lit(0), x["start"] + x["width"] - F.greatest(s["end"], x["start"]))).alias("n"),
        F.greatest(s["end"], x["start"] + x["width"]).alias("end"),
    )
    return F.aggregate(spans, F.struct(F.lit(0).alias("n"), F.lit(0).alias("end")), step)["n"]


def scan(documents: DataFrame, benchmark: DataFrame, width: int = 10, broadcast_windows: int = 1_000_000) -> DataFrame:
    """Per document row: n_words, n_hit, the sorted item ids with occurring windows, and merged spans."""
    spark = documents.sparkSession
    windows = Scratch(spark).store(test_windows(benchmark, width), "windows")
    sizes = {r["width"]: r["n"] for r in windows.groupBy("width").agg(F.count("*").alias("n")).collect()}  # at most `width` rows
    base = documents.select("doc_id", text_key(F.col("text")).alias("text_key"), count_words(F.col("text")).alias("n_words"))
    none = F.array().cast("array<string>")
    if not sizes:
        return base.select("doc_id", "text_key", "n_words", F.lit(0).cast("long").alias("n_hit"), none.alias("items"), F.array().cast("array<struct<start:int,width:int>>").alias("spans"))
    found = hits(documents, windows, sorted(sizes), sum(sizes.values()) <= broadcast_windows)
    per = found.groupBy("doc_id", "text_key").agg(
        F.array_sort(F.collect_set(F.struct("start", "width"))).alias("spans"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"),
    )
    per = per.select(F.col("doc_id").alias("d"), F.col("text_key").alias("k"), "spans", "items")
    out = base.join(per, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("text_key") == F.col("k")), "left")
    spans = F.coalesce("spans", F.array().cast("array<struct<start:int,width:int>>"))
    return out.select("doc_id", "text_key", "n_words", covered(spans).cast("long").alias("n_hit"), F.coalesce("items", none).alias("items"), spans.alias("spans"))


def remove_documents(documents: DataFrame, benchmark: DataFrame, width: int = 10, min_hit: int = 1) -> DataFrame:
    """Documents with fewer than `min_hit` hit words, unchanged."""
    bad = scan(documents, benchmark, width).where(F.col("n_hit") >= min_hit).select(F.col("doc_id").alias("__js_d"), F.col("text_key").alias("__js_k")).distinct()
    return documents.join(bad, F.col("doc_id").eqNullSafe(F.col("__js_d")) & (text_key(documents["text"]) == F.col("__js_k")), "left_anti")


def remove_spans(documents: DataFrame, benchmark: DataFrame, width: int = 10) -> DataFrame:
    """All documents; where windows hit, text is its remaining normalised words joined by one space."""
    bad = scan(documents, benchmark, width).where(F.col("n_hit") > 0).select(F.col("doc_id").alias("__js_d"), F.col("text_key").alias("__js_k"), F.col("spans").alias("__js_s")).dropDuplicates(["__js_d", "__js_k"])
    joined = documents.join(bad, F.col("doc_id").eqNullSafe(F.col("__js_d")) & (text_key(documents["text"]) == F.col("__js_k")), "left")
    left = F.filter(words(F.col("text")), lambda w, i: ~F.exists("__js_s", lambda s: (i >= s["start"]) & (i < s["start"] + s["width"])))
    text = F.when(F.col("__js_s").isNull(), F.col("text")).otherwise(F.concat_ws(" ", left))
    return joined.select([text.alias("text") if c == "text" else F.col(c) for c in documents.columns])
