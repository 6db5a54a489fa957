"""Helpers shared by the training-data operators: scratch tables, row keys, text patterns."""

from __future__ import annotations

import atexit
import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, as bytes.split() and the contracts define it.
SPACE = r"\x20\x09-\x0D"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors see: spark.checkpoint.dir. Where that is unset a local master gets one of its own (tests); elsewhere
    a folder of this machine would not be seen by others, and an error says so."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found
    sc = spark.sparkContext
    if sc.master != "local" and not sc.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors see")
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="joinspace-"))
    return sc._jsc.sc().getCheckpointDir().get()


def remove_path(spark: SparkSession, path: str) -> None:
    jvm = spark._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


class Scratch:
    """Written tables in the shared folder. They cut lineage and survive lost executors.

    keep() tables live until the driver's process ends, drop() ones go at once. A table that a
    returned, still lazy DataFrame reads must not be dropped.
    """

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.root = f"{shared_folder(spark).rstrip('/')}/tables-{uuid.uuid4().hex}"
        self.made: dict[str, str] = {}
        atexit.register(self.close)

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def store(self, df: DataFrame, name: str) -> DataFrame:
        at = self.path(name)
        df.write.mode("overwrite").option("compression", "zstd").parquet(at)
        self.made[name] = at
        return self.spark.read.schema(df.schema).parquet(at)

    def drop(self, *names: str) -> None:
        for name in names:
            if at := self.made.pop(name, None):
                remove_path(self.spark, at)

    def close(self) -> None:
        try:
            if self.spark.sparkContext._jsc is not None:
                remove_path(self.spark, self.root)
        except Exception:  # the session is gone: nothing can be removed through it
            pass


def sieve(rows: DataFrame, wanted: DataFrame, *columns: str, most: int = 1 << 28) -> DataFrame:
    """rows without most of those that have no partner in the stored table `wanted` on these columns: a broadcast bitmap of 8 to 16 bits a wanted
    row, at most `most` bits, keeps all that have one. So a join behind it shuffles little else; it changes no result."""
    bits = min(most, max(1 << 15, 1 << (8 * wanted.count()).bit_length()))
    at = F.pmod(F.xxhash64(*columns), F.lit(bits))
    marks = wanted.select(at.alias("__js_at")).groupBy(F.floor(F.col("__js_at") / 32768).alias("__js_part")).agg(F.bitmap_construct_agg(F.col("__js_at") % 32768).alias("__js_bits"))
    held = rows.withColumn("__js_at", at).withColumn("__js_part", F.floor(F.col("__js_at") / 32768)).join(F.broadcast(marks), "__js_part")
    place = (F.col("__js_at") % 32768).cast("int")
    byte = F.conv(F.hex(F.substring("__js_bits", F.floor(place / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    return held.where(F.getbit(byte, place % 8) == 1).select(*(rows[c] for c in rows.columns))


def lower_az(text: Column) -> Column:
    """Lower-case A-Z only. lower() is that for pure ASCII texts, and much faster than translate()."""
    return F.when(text.rlike(r"[^\x00-\x7F]"), F.translate(text, UPPER, LOWER)).otherwise(F.lower(text))


def space_words(text: Column) -> Column:
    """Number of maximal runs of non-space characters; null counts 0."""
    return F.coalesce(F.regexp_count(text, F.lit(f"[^{SPACE}]+")), F.lit(0)).cast("long")


def text_key(text: Column) -> Column:
    """With doc_id, this tells rows apart that repeat a doc_id; equal rows have equal results anyway."""
    return F.xxhash64(text)


_LOW = bytes.maketrans(UPPER.encode(), LOWER.encode())


def low_bytes(text: bytes) -> bytes:
    return text.translate(_LOW)


class WordHashes(dict):
    """64-bit hashes of words, remembered up to a bound of entries."""

    def __init__(self, bound: int = 400_000):
        super().__init__()
        import xxhash

        self.digest, self.bound = xxhash.xxh3_64_intdigest, bound

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.bound:
            self.clear()
        out = self[word] = self.digest(word)
        return out

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Rolling:
    """Hashes of all word windows of one sequence, from prefix sums of a polynomial modulo 2**64."""

    def __init__(self, base: int):
        self.base = base | 1
        self.inverse = pow(self.base, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) < n:
            size = max(4096, 1 << (n - 1).bit_length())
            for name, by in (("up", self.base), ("down", self.inverse)):
                steps = np.full(size, np.uint64(by))
                steps[0] = 1
                setattr(self, name, np.multiply.accumulate(steps))

    def sums(self, words: np.ndarray) -> np.ndarray:
        self._powers(len(words) + 1)
        out = np.zeros(len(words) + 1, np.uint64)
        np.cumsum(words * self.up[: len(words)], out=out[1:])
        return out

    def spans(self, sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hashes of words [start, end)."""
        return (sums[end] - sums[start]) * self.down[start]

    def windows(self, sums: np.ndarray, width: int) -> np.ndarray:
        n = len(sums) - width
        if n <= 0:
            return np.empty(0, np.uint64)
        return (sums[width:] - sums[:-width]) * self.down[:n]


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
