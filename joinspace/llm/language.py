"""Language ID with a bit-sliced Bloom filter: one lookup returns all languages that contain an n-gram.

Fitting takes every byte n-gram of lower-cased letters from a bounded, hash-chosen sample of labelled rows (`per_language`
documents each, a documented bound); each language's filter holds all of its n-grams, so the filter follows the sample:
`slots_per_gram` slots for each n-gram of the richest language, rounded up to a power of two. A slot is a word in which bit l belongs
to language l, and an n-gram's languages are the AND of its `PROBES` words. A text's n-grams are looked up once, all of them; the
per-language popcounts, corrected for the filter's false positives, decide. N-grams are made into slots on the executors; the
driver gets the slots that are set, at most one number for each slot.

Defined cases: a null text or one without a letter is 'und' with score 0; a text with letters whose n-grams no language
contains is 'und' with score 0 too; ties go to the smaller language name; with no labelled row every text is 'und'; at most 64
languages are learned (more raise an error); rows are independent, so repeated rows get equal answers, and in the fit they
count once, as sets do; very long texts are cut into overlapping pieces; extra columns stay, lang_pred and score replace columns of these names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, mix

#: Bytes after lower-casing: A-Z to a-z; letters and bytes over 0x7F stay; all else is a space.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
NGRAM, PROBES = 5, 2
NEXT = np.uint64(0x9E3779B97F4A7C15)


def folded(text: str) -> np.ndarray:
    """Lower-cased letters with single spaces between and around them."""
    return np.frombuffer(b" " + b" ".join(text.lower().encode("utf-8", "replace").translate(_FOLD).split()) + b" ", np.uint8)


def ngrams(data: np.ndarray, n: int = NGRAM) -> np.ndarray:
    if len(data) < n:
        return np.empty(0, np.uint64)
    out = np.zeros(len(data) - n + 1, np.uint64)
    for i in range(n):
        out = (out << np.uint64(8)) | data[i : len(data) - n + 1 + i]
    return out


def pieces(data: np.ndarray, block: int = 1 << 20) -> Iterator[np.ndarray]:
    """N-grams of overlapping pieces, each n-gram once, so that memory stays bounded on long texts."""
    for at in range(0, max(0, len(data) - NGRAM + 1), block):
        yield ngrams(data[at : at + block + NGRAM - 1])


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def places(grams: np.ndarray, log_slots: int) -> Iterator[np.ndarray]:
    """The slot of each n-gram, for each probe."""
    h = mix(grams)
    for _ in range(PROBES):
        yield (h >> np.uint64(64 - log_slots)).astype(np.int64)
        h = mix(h + NEXT)


@dataclass
class SlicedBloom:
    languages: list[str]
    slots: np.ndarray  # uint64, bit l: language l
    fill: np.ndarray  # share of slots with bit l

    def masks(self, grams: np.ndarray) -> np.ndarray:
        """For each n-gram the languages that contain it, as bits."""
        out = None
        for at in places(grams, len(self.slots).bit_length() - 1):
            out = self.slots[at] if out is None else out & self.slots[at]
        return out

    @staticmethod
    def of(languages: list[str], at: np.ndarray, bits: np.ndarray, log_slots: int) -> SlicedBloom:
        """From the set slots and their words."""
        slots = np.zeros(1 << log_slots, np.uint64)
        slots[at] = bits
        fill = np.array([float(np.mean((slots >> np.uint64(b)) & np.uint64(1))) for b in range(len(languages))])
        return SlicedBloom(languages, slots, fill)

    @staticmethod
    def build(languages: list[str], sets: list[np.ndarray], log_slots: int = 20) -> SlicedBloom:
        slots = np.zeros(1 << log_slots, np.uint64)
        for bit, grams in enumerate(sets):
            for at in places(grams, log_slots):
                slots[at] |= np.uint64(1 << bit)
        return SlicedBloom.of(languages, np.arange(1 << log_slots), slots, log_slots)

    def decide(self, text: str | None) -> tuple[str, float]:
        if not text or not self.languages or not has_letter(text):
            return "und", 0.0
        data = folded(text)
        counts, n = np.zeros(len(self.languages)), max(0, len(data) - NGRAM + 1)
        for grams in pieces(data):
            masks = self.masks(grams)
            for b in range(len(counts)):
                counts[b] += np.count_nonzero(masks & np.uint64(1 << b))
        wrong = self.fill**PROBES
        real = np.maximum(0.0, (counts - n * wrong) / np.maximum(1e-9, 1.0 - wrong))
        best = int(np.argmax(real))  # languages are sorted: ties go to the smaller name
        total = float(real.sum())
        return (self.languages[best], float(real[best]) / total) if total > 0 else ("und", 0.0)


def sampled(labelled: DataFrame, per_language: int) -> tuple[DataFrame, list[str]]:
    """(bit, text) of the rows to learn from, and the languages. A row's draw is a hash of its text."""
    own = labelled.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select(F.col("lang").cast("string").alias("lang"), "text")
    sizes = {r["lang"]: r["count"] for r in own.groupBy("lang").count().limit(65).collect()}
    if len(sizes) > 64:
        raise ValueError("a slot has 64 bits: at most 64 languages")
    languages = sorted(sizes)
    share, bit = F.lit(None).cast("double"), F.lit(None).cast("int")
    for b, lang in enumerate(languages):
        share = F.when(F.col("lang") == lang, min(1.0, per_language / sizes[lang])).otherwise(share)
        bit = F.when(F.col("lang") == lang, b).otherwise(bit)
    draw = F.pmod(F.xxhash64("text"), F.lit(1_000_003)) / F.lit(1_000_003.0)
    return own.where(draw < share).select(bit.alias("bit"), "text"), languages


def fit(labelled: DataFrame, per_language: int = 4000, slots_per_gram: int = 8, most: int = 1 << 20) -> SlicedBloom:
    """Learns from text and non-null lang: all n-grams of about `per_language` documents of each language."""
    some, languages = sampled(labelled, per_language)
    if not languages:
        return SlicedBloom([], np.zeros(2, np.uint64), np.zeros(0))
    scratch = Scratch(labelled.sparkSession)

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        have: dict[int, list[np.ndarray]] = {}
        held = 0

        def flush() -> Iterator[pa.RecordBatch]:
            for bit, parts in have.items():
                g = np.unique(np.concatenate(parts))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(g), bit, np.int32)), pa.array(g.view(np.int64))], ["bit", "gram"])
            have.clear()

        for batch in batches:
            for bit, text in zip(*batch.columns, strict=True):
                for grams in pieces(folded(text.as_py())):
                    own = np.unique(grams)
                    have.setdefault(bit.as_py(), []).append(own)
                    held += len(own)
                    if held > most:
                        yield from flush()
                        held = 0
        yield from flush()

    grams = scratch.store(some.mapInArrow(listed, "bit int, gram long").distinct(), "grams")
    richest = max([r["count"] for r in grams.groupBy("bit").count().collect()], default=0)  # one row a language
    log_slots = max(10, (richest * slots_per_gram).bit_length())

    def placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bit = np.left_shift(np.uint64(1), batch.column(0).to_numpy().astype(np.uint64))
            for at in places(batch.column(1).to_numpy().view(np.uint64), log_slots):
                yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(bit.view(np.int64))], ["at", "bits"])

    words = grams.mapInArrow(placed, "at long, bits long").groupBy("at").agg(F.bit_or("bits").alias("bits")).toArrow()  # at most one row a slot
    scratch.drop("grams")
    at, bits = (words.column(i).to_numpy() for i in (0, 1))
    return SlicedBloom.of(languages, at, bits.astype(np.int64).view(np.uint64), log_slots)


def predict(documents: DataFrame, model: SlicedBloom) -> DataFrame:
    """documents plus lang_pred and score (they replace columns of these names)."""
    spark = documents.sparkSession
    shared = spark.sparkContext.broadcast((model.languages, model.slots, model.fill))  # its size follows the fit's bounded sample
    keep = [c for c in documents.columns if c not in ("lang_pred", "score")]
    place = keep.index("text")
    schema = documents.select(keep).schema.add("lang_pred", "string").add("score", "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = SlicedBloom(*shared.value)
        for batch in batches:
            said = [own.decide(t.as_py()) for t in batch.column(place)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([x for x, _ in said], pa.string()), pa.array([y for _, y in said], pa.float64())], [*keep, "lang_pred", "score"])

    return documents.select(keep).mapInArrow(run, schema)
