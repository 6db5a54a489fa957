"""Token counts from pieces per distinct pre-token, without materialising ids.

A byte-level BPE never merges across pre-tokens, so a text has the sum over its pre-tokens of their piece counts.

1. Every task lists the distinct pre-tokens of its texts; one aggregation makes them distinct over the corpus.
2. Each distinct pre-token is encoded once; the table (piece, n_pieces) is written to the shared folder.
3. The table is joined to the pre-token frequencies of each document. Its `head`, the pre-tokens that most tasks list, goes to
   all tasks: at most `head` entries of at most `longest` characters, whatever the corpus. All others, the tail, are
   joined by a shuffle and summed by document. Both ways together cover every occurrence, so `head` moves work and not results.
   A pre-token that a large share of the documents holds is in the head, so no key of the shuffled join is hot.

Special strings inside a text are single tokens, as the library does by default; the pieces beside them are split alone.
Defined cases: a null or empty text has 0 tokens and 0 bytes; rows are counted one by one, so repeated rows, repeated or null
doc_ids and ties do not matter; extra columns are ignored, whatever their names; an empty table gives an empty result;
very long texts are split whole, one at a time.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch

#: Fixed value: the pre-token pattern of byte-level BPE vocabularies of this family.
PRE_TOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: For texts of these characters alone the classes above are plain ranges, which a simpler engine matches faster.
_LATIN = "A-Za-zÀ-ÖØ-öø-ÿ"
_PLAIN = re.compile(r"[\t\n\r -~À-ÖØ-öø-ÿ]*")
_PLAIN_TOKEN = re.compile(rf" ?[{_LATIN}]+|'(?:s|t|re|ve|m|ll|d)| ?[0-9]+| ?[^\s0-9{_LATIN}]+|\s+(?!\S)|\s+")


class Splitter:
    """Cuts texts into pre-tokens."""

    def __init__(self, vocabulary: str):
        import regex

        special = [t["content"] for t in json.loads(vocabulary).get("added_tokens", [])]
        self.special = regex.compile("|".join(map(regex.escape, special))) if special else None
        self.find = regex.compile(PRE_TOKEN).findall

    def cut(self, text: str) -> tuple[list[str], int]:
        """The pre-tokens, and the number of special strings between them."""
        marks = self.special.findall(text) if self.special else ()
        if marks:
            return [w for part in self.special.split(text) for w in self.find(part)], len(marks)
        return (_PLAIN_TOKEN.findall(text) if _PLAIN.fullmatch(text) else self.find(text)), 0


class Head(dict):
    """Piece counts of frequent pre-tokens. Others count 0 here and are noted in `tail`."""

    def __init__(self, known):
        super().__init__(known)
        self.tail: list[str] = []

    def __missing__(self, piece: str) -> int:
        self.tail.append(piece)
        return 0

    def count(self, pieces: list[str]) -> tuple[int, list[str]]:
        self.tail = []
        return sum(map(self.__getitem__, pieces)), self.tail


def distinct_pieces(documents: DataFrame, vocabulary, most: int = 200_000) -> DataFrame:
    """(piece, listed): the distinct pre-tokens of all texts, and how often a task listed them (`most` at a time)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut, own = Splitter(vocabulary.value).cut, set()
        for batch in batches:
            for text in batch.column(0):
                own.update(cut(text.as_py())[0])
                if len(own) > most:
                    yield pa.RecordBatch.from_arrays([pa.array(own, pa.string())], ["piece"])
                    own.clear()
        if own:
            yield pa.RecordBatch.from_arrays([pa.array(own, pa.string())], ["piece"])

    texts = documents.select("text").where(F.col("text").isNotNull())
    return texts.mapInArrow(run, "piece string").groupBy("piece").agg(F.count("*").alias("listed"))


def encoded(pieces: DataFrame, vocabulary) -> DataFrame:
    """pieces (piece, listed) with n_pieces from the library."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        own = Tokenizer.from_str(vocabulary.value)
        encode = getattr(own, "encode_batch_fast", own.encode_batch)
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                some = batch.slice(at, 4096)
                n = [len(e) for e in encode(some.column(0).to_pylist(), add_special_tokens=False)]
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(1), pa.array(n, pa.int64())], ["piece", "listed", "n_pieces"])

    return pieces.mapInArrow(run, "piece string, listed long, n_pieces long")


def token_counts(documents: DataFrame, vocabulary_path: str, limit: int = 1024, head: int = 300_000, longest: int = 64) -> DataFrame:
    """Per row: doc_id, n_bytes, n_tokens, over_limit. The vocabulary file is read once, on the driver."""
    spark = documents.sparkSession
    scratch = Scratch(spark)
    with open(vocabulary_path, encoding="utf-8") as f:
        vocabulary = spark.sparkContext.broadcast(f.read())  # bounded by the vocabulary, not by the data
    table = scratch.store(encoded(distinct_pieces(documents, vocabulary), vocabulary), "pieces")
    some = table.where(F.length("piece") <= longest).orderBy(F.desc("listed"), "piece").limit(head).select("piece", "n_pieces").toArrow()
    known = spark.sparkContext.broadcast((some.column(0).to_pylist(), some.column(1).to_pylist()))  # at most `head` short entries

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut, table = Splitter(vocabulary.value).cut, Head(zip(*known.value, strict=True))
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                n, tails = [], []
                for text in part.column(3):
                    pieces, marks = cut(text.as_py() or "")
                    own, tail = table.count(pieces)
                    n.append(own + marks)
                    tails.append(tail)
                yield pa.RecordBatch.from_arrays([*part.columns[:3], pa.array(n, pa.int64()), pa.array(tails, pa.list_(pa.string()))], ["row", "doc_id", "n_bytes", "n", "tail"])

    bytes_ = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes")
    doc_type = documents.schema["doc_id"].dataType.simpleString()
    own = documents.select(F.monotonically_increasing_id().alias("row"), "doc_id", bytes_, "text").mapInArrow(run, f"row long, doc_id {doc_type}, n_bytes long, n long, tail array<string>")
    own = scratch.store(own, "documents")  # row numbers hold from here on
    tail = own.select("row", F.explode("tail").alias("piece")).join(table.select("piece", "n_pieces"), "piece").groupBy("row").agg(F.sum("n_pieces").alias("more"))
    out = own.select("row", "doc_id", "n_bytes", "n").join(tail, "row", "left").withColumn("n_tokens", F.col("n") + F.coalesce("more", F.lit(0)))
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
