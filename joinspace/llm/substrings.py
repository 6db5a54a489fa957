"""Substring dedup by level-wise doubling of repeated word windows.

Level one is windows of half the length. Only anchors are kept: of the half-windows inside each full window, the one
with the least hash. Equal full windows have equal anchors, so a full window can repeat only if its anchor does.
Anchors seen in one document alone go. The survivors are extended to runs: all consecutive full windows that
share one anchor occurrence. Where every occurrence of an anchor has the same run, the smallest document keeps it and the
others lose it. Only anchors with several runs are extended once more, to their single full windows,
each compared by a 128-bit hash. `levels` goes on doubling until no candidate survives.

A document whose whole word sequence stands in a smaller doc_id is settled before any of this, so large groups of copies cost
one row each. Sums over anchors and windows are combined before the shuffle, and joined back from written tables, whose hot keys AQE splits.

Defined cases: a null text has no words; a null doc_id orders after all others; rows with the same doc_id are not
smaller than each other; texts shorter than the window lose nothing; empty tables give empty results; extra columns stay.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Rolling, Scratch, WordHashes, signed, text_key
from .common import mix as scramble

#: Multipliers of the two window hashes.
BASE_A, BASE_B = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F
LAST = 2**63 - 1


def anchor_runs(half: np.ndarray, width: int, n_words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Anchor positions with the first and last start of the full windows they anchor. `half`: hashes of half-windows."""
    n = n_words - width + 1
    inside = len(half) - n + 1  # half-windows in a full window
    key = scramble(half)
    best = np.empty(n, np.int64)
    for at in range(0, n, 1 << 16):
        part = key[at : min(n, at + (1 << 16)) + inside - 1]
        best[at : at + (1 << 16)] = np.lib.stride_tricks.sliding_window_view(part, inside).argmin(1) + np.arange(at, min(n, at + (1 << 16)))
    cut = np.flatnonzero(np.diff(best)) + 1
    first = np.concatenate([[0], cut])
    last = np.concatenate([cut - 1, [n - 1]])
    return best[first], first, last


class Sequence:
    """Hashes of one text's words and windows."""

    words = None
    one, two = Rolling(BASE_A), Rolling(BASE_B)

    def __init__(self, text: bytes | None):
        if Sequence.words is None:
            Sequence.words = WordHashes()
        self.tokens = (text or b"").split()
        self.hashes = Sequence.words.of(self.tokens)
        self.sums = self.one.sums(self.hashes)

    def anchors(self, width: int) -> tuple[np.ndarray, ...]:
        """(anchor hash, run hash, first, last) for each run."""
        n = len(self.tokens)
        if n < width:
            return tuple(np.empty(0, np.int64) for _ in range(4))
        half = self.one.windows(self.sums, width // 2)
        at, first, last = anchor_runs(half, width, n)
        place = ((at - first) * 65_536 + (last - at)).astype(np.uint64)
        run = scramble(self.one.spans(self.sums, first, last + width) + scramble(place))
        return signed(scramble(half[at])), signed(run), first, last

    def windows(self, width: int, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(start, hash, second hash) of the full windows in these runs."""
        starts = np.concatenate([np.arange(a, b + 1) for a, b in zip(first, last, strict=True)]) if len(first) else np.empty(0, np.int64)
        other = self.two.sums(self.hashes)
        return starts, signed(self.one.spans(self.sums, starts, starts + width)), signed(self.two.spans(other, starts, starts + width))


def _profile(documents: DataFrame, width: int) -> DataFrame:
    """One row a document: key, word count, hash of the whole sequence, digest of all words, packed anchors."""
    schema = "doc_id long, text_key long, n_words long, whole string, digest string, anchors array<long>, runs array<long>, firsts array<int>, lasts array<int>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, keys, texts = batch.columns
            for at in range(0, batch.num_rows, 200):
                cols: list[list] = [[] for _ in range(7)]
                for t in texts.slice(at, 200):
                    seq = Sequence(t.as_buffer().to_pybytes() if t.is_valid else None)
                    digest = hashlib.sha256(b" ".join(seq.tokens)).hexdigest()
                    a, r, f, l = seq.anchors(width)
                    for c, v in zip(cols, (len(seq.tokens), digest[:40], digest, a, r, f.astype(np.int32), l.astype(np.int32)), strict=True):
                        c.append(v)
                kinds = (pa.int64(), pa.string(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays([ids.slice(at, 200), keys.slice(at, 200), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names)

    names = [x.split()[0] for x in schema.split(", ")]
    return documents.select(F.col("doc_id").cast("long"), text_key(F.col("text")).alias("text_key"), "text").mapInArrow(run, schema)


def repeated_spans(documents: DataFrame, width: int, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """(profile with `copied`, spans (doc_id, text_key, first, last) of window starts that also start in a smaller document)."""
    order = F.coalesce("doc_id", F.lit(LAST))
    profile = scratch.store(_profile(documents, width), "profile")
    groups = profile.where(F.col("n_words") >= width).groupBy("whole").agg(F.min(order).alias("least"), F.count("*").alias("n"))
    groups = scratch.store(groups.where("n > 1").select(F.col("whole").alias("w"), "least"), "groups")
    marks = profile.where(F.col("n_words") >= width).select("doc_id", "text_key", "whole", order.alias("o")).join(groups, F.col("whole") == F.col("w")).where(F.col("least") < F.col("o"))
    marks = scratch.store(marks.select(F.col("doc_id").alias("d"), F.col("text_key").alias("k")).distinct(), "marks")
    same = F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("text_key") == F.col("k"))
    zipped = F.explode(F.arrays_zip("anchors", "runs", "firsts", "lasts"))
    runs = profile.where(F.size("anchors") > 0).join(marks, same, "left_anti").select("doc_id", "text_key", order.alias("o"), zipped.alias("x"))
    runs = runs.select("doc_id", "text_key", "o", F.col("x.anchors").alias("anchor"), F.col("x.runs").alias("run"), F.col("x.firsts").alias("first"), F.col("x.lasts").alias("last"))
    seen = runs.groupBy("anchor").agg(F.min("o").alias("lo"), F.max("o").alias("hi"), F.min("run").alias("r1"), F.max("run").alias("r2"))
    seen = scratch.store(seen.where("lo < hi").select(F.col("anchor").alias("a"), "lo", (F.col("r1") != F.col("r2")).alias("several")), "anchors")
    live = scratch.store(runs.join(seen, F.col("anchor") == F.col("a")).drop("a"), "runs")
    plain = live.where(~F.col("several") & (F.col("lo") < F.col("o"))).select("doc_id", "text_key", "first", "last")
    mixed = live.where("several")
    least = mixed.groupBy("anchor", "run").agg(F.min("o").alias("least"))
    least = scratch.store(least.select(F.col("anchor").alias("a"), F.col("run").alias("r"), "least"), "least")
    mixed = mixed.join(least, (F.col("anchor") == F.col("a")) & (F.col("run") == F.col("r"))).drop("a", "r")
    mixed = scratch.store(mixed.select("doc_id", "text_key", "o", "first", "last", (F.col("least") < F.col("o")).alias("gone")), "mixed")
    known = mixed.where("gone").select("doc_id", "text_key", "first", "last")
    # single full windows, only from the first document of each run that differs
    asked = mixed.where("not gone").groupBy("doc_id", "text_key", "o").agg(F.sort_array(F.collect_list(F.struct("first", "last"))).alias("spans"))
    asked = asked.select(F.col("doc_id").alias("d"), F.col("text_key").alias("k"), "o", "spans")
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(F.col("text")).alias("text_key"), "text")
    asked = texts.join(asked, same).select("doc_id", "text_key", "o", "text", "spans")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc, key, o, text, spans in zip(*batch.columns, strict=True):
                seq = Sequence(text.as_buffer().to_pybytes())
                flat = spans.values.flatten()
                start, h1, h2 = seq.windows(width, flat[0].to_numpy(), flat[1].to_numpy())
                many = lambda x: pa.array([x.as_py()] * len(start), pa.int64())
                yield pa.RecordBatch.from_arrays([many(doc), many(key), many(o), pa.array(start, pa.int64()), pa.array(h1), pa.array(h2)], ["doc_id", "text_key", "o", "start", "h1", "h2"])

    windows = scratch.store(asked.mapInArrow(run, "doc_id long, text_key long, o long, start long, h1 long, h2 long"), "windows")
    first = windows.groupBy("h1", "h2").agg(F.min("o").alias("lo"), F.max("o").alias("hi"))
    first = scratch.store(first.where("lo < hi").select(F.col("h1").alias("a"), F.col("h2").alias("b"), "lo"), "first")
    single = windows.join(first, (F.col("h1") == F.col("a")) & (F.col("h2") == F.col("b"))).where("lo < o")
    single = single.select("doc_id", "text_key", F.col("start").cast("int").alias("first"), F.col("start").cast("int").alias("last"))
    spans = scratch.store(plain.unionByName(known).unionByName(single), "spans")
    scratch.drop("groups", "anchors", "runs", "least", "mixed", "windows", "first")
    copied = profile.select("doc_id", "text_key", "n_words", "digest").join(marks.withColumn("copied", F.lit(True)), same, "left").drop("d", "k")
    return copied.withColumn("copied", F.coalesce("copied", F.lit(False))), spans


def _covered(n: int, spans: list, width: int) -> np.ndarray:
    step = np.zeros(n + 1, np.int32)
    for a, b in spans:
        step[a] += 1
        step[min(n, b + width)] -= 1
    return np.cumsum(step[:n]) > 0


def removals(documents: DataFrame, width: int = 50) -> DataFrame:
    """(doc_id, text_key, n_words, digest, n_removed, kept_sha256) per row; digest is that of all words."""
    scratch = Scratch(documents.sparkSession)
    profile, spans = repeated_spans(documents, width, scratch)
    per = spans.groupBy("doc_id", "text_key").agg(F.collect_list(F.struct("first", "last")).alias("spans"))
    per = per.select(F.col("doc_id").alias("d"), F.col("text_key").alias("k"), "spans")
    same = F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("text_key") == F.col("k"))
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(F.col("text")).alias("text_key"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[], []]
            for text, spans in zip(batch.column(2), batch.column(3), strict=True):
                tokens = text.as_buffer().to_pybytes().split()
                gone = _covered(len(tokens), [(s["first"], s["last"]) for s in spans.as_py()], width)
                out[0].append(int(gone.sum()))
                out[1].append(hashlib.sha256(b" ".join([t for t, g in zip(tokens, gone.tolist(), strict=True) if not g])).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out[0], pa.int64()), pa.array(out[1], pa.string())], ["doc_id", "text_key", "n_removed", "kept_sha256"])

    cut = texts.join(per, same).select("doc_id", "text_key", "text", "spans").mapInArrow(run, "doc_id long, text_key long, n_removed long, kept_sha256 string").dropDuplicates(["doc_id", "text_key"])
    cut = cut.select(F.col("doc_id").alias("d"), F.col("text_key").alias("k"), "n_removed", "kept_sha256")
    out = profile.join(cut, same, "left")
    gone = F.when(F.col("copied"), F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0)))
    kept = F.when(F.col("copied"), F.sha2(F.lit(""), 256)).otherwise(F.coalesce("kept_sha256", "digest"))
    return out.select("doc_id", "text_key", "n_words", "digest", gone.alias("n_removed"), kept.alias("kept_sha256"))


def cut_text(text: bytes, gone: np.ndarray) -> bytes:
    """The text without the words marked; the white space behind a removed word goes with it."""
    import re

    places = [m.span() for m in re.finditer(rb"[^\x20\x09-\x0D]+", text)]
    out, at = [], 0
    for i, (a, _) in enumerate(places):
        end = places[i + 1][0] if i + 1 < len(places) else len(text)
        if i == 0:
            out.append(text[:a])
        if not gone[i]:
            out.append(text[a:end])
        at = end
    return b"".join(out) if places else text[at:]


def remove_repeats(documents: DataFrame, width: int = 50, drop_empty: bool = True) -> DataFrame:
    """documents with repeated passages cut from text (n_chars follows); documents left without a word go, if asked."""
    scratch = Scratch(documents.sparkSession)
    profile, spans = repeated_spans(documents, width, scratch)
    copied = profile.where("copied").select("doc_id", "text_key", F.array(F.struct(F.lit(0).alias("first"), (F.col("n_words") - width).cast("int").alias("last"))).alias("spans"))
    per = spans.groupBy("doc_id", "text_key").agg(F.collect_list(F.struct("first", "last")).alias("spans")).unionByName(copied).dropDuplicates(["doc_id", "text_key"])
    per = per.select(F.col("doc_id").alias("__js_d"), F.col("text_key").alias("__js_k"), F.col("spans").alias("__js_s"))
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("__js_d")) & (text_key(documents["text"]) == F.col("__js_k"))
    names = documents.columns
    joined = documents.join(per, same, "left").select(*names, "__js_s")
    place = names.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, live = [], []
            for text, spans in zip(batch.column(place), batch.column(len(names)), strict=True):
                if not text.is_valid or not spans.is_valid:
                    texts.append(text.as_py())
                    live.append(True)
                    continue
                raw = text.as_buffer().to_pybytes()
                n = len(raw.split())
                left = cut_text(raw, _covered(n, [(s["first"], s["last"]) for s in spans.as_py()], width))
                texts.append(left.decode("utf-8", "replace"))
                live.append(bool(left.split()) or not drop_empty)
            cols = list(batch.columns[: len(names)])
            cols[place] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays(cols, names).filter(pa.array(live, pa.bool_()))

    out = joined.mapInArrow(run, documents.schema)
    if "n_chars" in names:
        out = out.withColumn("n_chars", F.length("text").cast(documents.schema["n_chars"].dataType))
    return out.select(*names)


def levels(documents: DataFrame, width: int = 50, most: int = 20) -> DataFrame:
    """(level_words, windows, documents): distinct windows of `width`, twice that, ... words that start in two documents or
    more, and the documents they start in. Each level looks only at documents that the level before left."""
    spark = documents.sparkSession
    scratch, out = Scratch(spark), []
    live = documents.select("doc_id", "text")
    for level in range(most):
        size = width << level

        def run(batches: Iterator[pa.RecordBatch], size: int = size) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for doc, text in zip(*batch.columns, strict=True):
                    seq = Sequence(text.as_buffer().to_pybytes() if text.is_valid else None)
                    n = len(seq.tokens) - size
                    if n < 0:
                        continue
                    _, h1, h2 = seq.windows(size, np.array([0]), np.array([n]))
                    yield pa.RecordBatch.from_arrays([pa.array([doc.as_py()] * len(h1), pa.int64()), pa.array(h1), pa.array(h2)], ["doc_id", "h1", "h2"])

        windows = scratch.store(live.mapInArrow(run, "doc_id long, h1 long, h2 long").distinct(), f"level{level}")
        again = scratch.store(windows.groupBy("h1", "h2").count().where("count > 1").select("h1", "h2"), f"again{level}")
        docs = scratch.store(windows.join(again, ["h1", "h2"]).select("doc_id").distinct(), f"docs{level}")
        n, d = again.count(), docs.count()
        scratch.drop(f"level{level}", f"again{level}")
        if not n:
            break
        out.append((size, n, d))
        live = documents.select("doc_id", "text").join(docs, "doc_id", "left_semi")
    return spark.createDataFrame(out, "level_words int, windows long, documents long")
