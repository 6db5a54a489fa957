"""MinHash near-dedup as a multi-index Hamming join.

A document's signature has `chunks` x `per_chunk` symbols of 16 bits. Two signatures that differ in fewer than 2 * chunks
symbols agree, in some chunk, up to one symbol (pigeonhole). So each chunk is entered once for every symbol left out,
and all pairs under that distance meet in a bucket; beyond it most still do: a pair at similarity 0.8 is missed with
probability under 3e-5, one at 0.9 with under 1e-9. Links are confirmed on the full shingle sets.

Documents with equal sets are one node. Buckets never emit all their pairs: (A) every document is tested against one
partner, the least of its buckets' least members; (B) in buckets that still hold several components, one member of each is
tested; (C) where buckets are still mixed, all pairs across components under the signature distance are tested, block against
block, and only links that join components come out. Pairs inside a component cannot change it.

Defined cases: null texts and texts without a word have no shingles and link with nothing; fewer words than a shingle give
one shingle of all; rows with a null doc_id take no part (component null, kept); rows that share a doc_id are in one component, and
each text's own links count; doc_ids are whole numbers (text ids are cast, and an error says so if that fails); very long texts are shingled
whole; empty tables give empty results; extra columns stay, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Rolling, Scratch, WordHashes, low_bytes, sieve, signed, text_key
from .common import mix as scramble
from .components import connected

LANES = 4  # 16-bit symbols in a long


class Shingler:
    def __init__(self, words: int, chunks: int, per_chunk: int, seed: int = 42):
        self.words, self.chunks, self.per_chunk = words, chunks, per_chunk
        self.k = chunks * per_chunk
        self.roll, self.known = Rolling(0x9E3779B97F4A7C15), WordHashes()
        rng = np.random.default_rng(seed)
        self.mul = rng.integers(1, 2**63, self.k, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.add = rng.integers(0, 2**63, self.k, dtype=np.uint64)

    def shingles(self, text: bytes | None) -> np.ndarray:
        """Sorted distinct 64-bit fingerprints."""
        tokens = low_bytes(text or b"").split()
        if not tokens:
            return np.empty(0, np.uint64)
        sums = self.roll.sums(self.known.of(tokens))
        width = min(self.words, len(tokens))
        return np.unique(scramble(self.roll.windows(sums, width) + np.uint64(width)))

    def signature(self, own: np.ndarray) -> np.ndarray:
        least = np.full(self.k, np.uint64(2**64 - 1))
        for at in range(0, len(own), 2048):
            least = np.minimum(least, (own[at : at + 2048, None] * self.mul + self.add).min(0))
        return (scramble(least) >> np.uint64(48)).astype(np.uint16)

    def keys(self, signature: np.ndarray) -> np.ndarray:
        """chunks * per_chunk bucket keys: a chunk without one of its symbols."""
        part = signature.reshape(self.chunks, self.per_chunk).astype(np.uint64)
        out = np.empty((self.chunks, self.per_chunk), np.uint64)
        for gone in range(self.per_chunk):
            h = np.arange(self.chunks, dtype=np.uint64) * np.uint64(64) + np.uint64(gone)
            for i in range(self.per_chunk):
                if i != gone:
                    h = scramble(h * np.uint64(0x9E3779B97F4A7C15) + part[:, i])
            out[:, gone] = h
        return out.ravel()

    def lanes(self, signature: np.ndarray) -> np.ndarray:
        padded = np.zeros(-(-self.k // LANES) * LANES, np.uint16)
        padded[: self.k] = signature
        return padded.view(np.uint64)


def _pack(own: np.ndarray) -> bytes:
    """The upper 48 bits of each fingerprint; order is kept."""
    return (own >> np.uint64(16)).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6].tobytes()


def _unpack(data) -> np.ndarray:
    six = np.frombuffer(data, np.uint8).reshape(-1, 6)
    out = np.zeros((len(six), 8), np.uint8)
    out[:, :6] = six
    return out.view("<u8").ravel()


def joined_links(rows: pd.DataFrame, percent: int, distance: int, columns: int = 16_384) -> pd.DataFrame:
    """Links (a, b) between nodes of different labels, as far as they join labels not joined yet. Rows of two blocks are compared
    across the blocks only: pairs inside a block have a task of their own."""
    rows = rows.sort_values("mine", kind="stable")
    node, label, n, mine = (rows[c].to_numpy() for c in ("node", "label", "n", "mine"))
    sig = np.stack(rows["signature"].to_numpy()).astype(np.int64).view(np.uint16)
    maybe = np.zeros((len(node), len(node)), bool)
    second = int(np.searchsorted(mine, mine[0], side="right"))  # where the other block starts
    for i in range(len(node) if second == len(node) else second):
        to = i + 1 if second == len(node) else second
        far = (sig[i] != sig[to:]).sum(1)
        maybe[i, to:] = (far <= distance) & (label[i] != label[to:]) & (100 * np.minimum(n[i], n[to:]) >= percent * np.maximum(n[i], n[to:]))
    use = np.flatnonzero(maybe.any(0) | maybe.any(1))
    if not len(use):
        return pd.DataFrame({"a": np.empty(0, np.int64), "b": np.empty(0, np.int64)})
    items = [_unpack(rows["packed"].iloc[i]) for i in use]
    who = np.repeat(np.arange(len(use)), [len(x) for x in items])
    known, what = np.unique(np.concatenate(items), return_inverse=True)
    shared = np.zeros((len(use), len(use)), np.float32)
    order = np.argsort(what, kind="stable")
    who, what = who[order], what[order]
    for at in range(0, len(known), columns):
        lo, hi = np.searchsorted(what, [at, at + columns])
        part = np.zeros((len(use), min(columns, len(known) - at)), np.float32)
        part[who[lo:hi], what[lo:hi] - at] = 1
        shared += part @ part.T
    both = shared.astype(np.int64)
    either = n[use][:, None] + n[use][None, :] - both
    hit = maybe[np.ix_(use, use)] & (100 * both >= percent * either)
    root = {x: x for x in set(label.tolist())}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    a, b = [], []
    for i, j in zip(*np.nonzero(hit), strict=True):
        p, q = find(label[use[i]]), find(label[use[j]])
        if p != q:
            root[p] = q
            a.append(min(node[use[i]], node[use[j]]))
            b.append(max(node[use[i]], node[use[j]]))
    return pd.DataFrame({"a": np.array(a, np.int64), "b": np.array(b, np.int64)})


class NearDuplicates:
    def __init__(self, documents: DataFrame, words: int = 5, percent: int = 80, chunks: int = 10, per_chunk: int = 6, distance: int | None = None, block: int = 64, copies: int = 12, widest: int = 2048):
        self.block, self.copies, self.widest = block, copies, widest
        self.documents, self.words, self.percent = documents, words, percent
        self.chunks, self.per_chunk = chunks, per_chunk
        k = chunks * per_chunk
        miss = 1 - percent / 100
        # five standard deviations over the mean at the threshold, at least the distance the buckets guarantee
        self.distance = distance if distance is not None else max(2 * chunks - 1, int(np.ceil(k * miss + 5 * np.sqrt(k * miss * (1 - miss)))))
        self.scratch = Scratch(documents.sparkSession)

    def _profile(self) -> DataFrame:
        words, chunks, per_chunk = self.words, self.chunks, self.per_chunk
        names = ["doc_id", "text_key", "n_shingles", "set_id", "keys", "signature"]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = Shingler(words, chunks, per_chunk)
            for batch in batches:
                for at in range(0, batch.num_rows, 500):
                    cols: list[list] = [[], [], [], []]
                    for t in batch.column(2).slice(at, 500):
                        s = own.shingles(t.as_buffer().to_pybytes() if t.is_valid else None)
                        sig = own.signature(s) if len(s) else None
                        whole = own.known.digest(s.tobytes()).to_bytes(8, "big") + own.known.digest(s[::-1].tobytes()).to_bytes(8, "big") if len(s) else None
                        row = (len(s), whole, signed(own.keys(sig)) if len(s) else None, signed(own.lanes(sig)) if len(s) else None)
                        for c, v in zip(cols, row, strict=True):
                            c.append(v)
                    kinds = (pa.int64(), pa.binary(), pa.list_(pa.int64()), pa.list_(pa.int64()))
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 500), batch.column(1).slice(at, 500), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names)

        texts = self.documents.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(F.col("text")).alias("text_key"), "text")
        schema = "doc_id long, text_key long, n_shingles long, set_id binary, keys array<long>, signature array<long>"
        return texts.mapInArrow(run, schema)

    def _sets(self, wanted: DataFrame) -> DataFrame:
        """(node, n, packed) for (node, doc_id, text_key): their full shingle sets."""
        words, chunks, per_chunk = self.words, self.chunks, self.per_chunk

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = Shingler(words, chunks, per_chunk)
            for batch in batches:
                for at in range(0, batch.num_rows, 500):
                    sets = [own.shingles(t.as_buffer().to_pybytes()) for t in batch.column(1).slice(at, 500)]
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 500), pa.array([len(s) for s in sets], pa.int64()), pa.array([_pack(s) for s in sets], pa.binary())], ["node", "n", "packed"])

        texts = self.documents.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(F.col("text")).alias("text_key"), "text")
        return sieve(texts, wanted, "doc_id", "text_key").join(wanted, ["doc_id", "text_key"]).select("node", "text").mapInArrow(run, "node long, n long, packed binary").dropDuplicates(["node"])

    def _confirmed(self, pairs: DataFrame, sets: DataFrame) -> DataFrame:
        """Pairs (a, b) of set nodes whose sets are similar enough."""
        percent = self.percent

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                live = []
                for x, y, n, m in zip(*(batch.column(i) for i in (2, 3, 4, 5)), strict=True):
                    n, m = n.as_py(), m.as_py()
                    if 100 * min(n, m) < percent * max(n, m):
                        live.append(False)
                        continue
                    both = n + m - len(np.union1d(_unpack(x.as_buffer()), _unpack(y.as_buffer())))
                    live.append(100 * both >= percent * (n + m - both))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(live, pa.bool_()))

        left = sets.select(F.col("node").alias("a"), F.col("packed").alias("x"), F.col("n").alias("n1"))
        right = sets.select(F.col("node").alias("b"), F.col("packed").alias("y"), F.col("n").alias("n2"))
        # sizes alone rule out some pairs before the second join moves their sets
        joined = pairs.join(right, "b").join(left, "a").where((F.least("n1", "n2") * 100 >= F.greatest("n1", "n2") * percent))
        return joined.select("a", "b", "x", "y", "n1", "n2").mapInArrow(run, "a long, b long")

    def components(self) -> DataFrame:
        """(doc_id, text_key, n_shingles, component_id, kept) per row."""
        store, scratch = self.scratch.store, self.scratch
        profile = store(self._profile(), "profile")
        linked = profile.where(F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0))
        # one node for each distinct set: its least doc_id
        groups = linked.groupBy("set_id").agg(F.min(F.struct("doc_id", "text_key")).alias("m"), F.count("*").alias("c"))
        groups = store(groups.where("c > 1").select(F.col("set_id").alias("s"), F.col("m.doc_id").alias("least"), F.col("m.text_key").alias("least_key")), "groups")
        mapped = linked.join(groups, F.col("set_id") == F.col("s"), "left")
        mapped = mapped.withColumn("first", F.coalesce("least", "doc_id")).withColumn("first_key", F.coalesce("least_key", "text_key"))
        first_row = (F.col("doc_id") == F.col("first")) & (F.col("text_key") == F.col("first_key"))
        # a doc_id with several sets: all but one of them get a node number of their own
        several = store(mapped.where(first_row).groupBy("first").agg(F.min("first_key").alias("m"), F.max("first_key").alias("x")).where("m < x").select(F.col("first").alias("f"), "m"), "several")
        repeated = not several.isEmpty()
        node = F.col("first")
        if repeated:
            mapped = mapped.join(several, F.col("first") == F.col("f"), "left")
            node = F.when(F.col("first_key") > F.col("m"), -1 - F.shiftrightunsigned(F.xxhash64("first", "first_key"), 2)).otherwise(node)
        place = store(mapped.select("doc_id", "text_key", node.alias("node")), "place")
        own = mapped.where(first_row).select("doc_id", "text_key", node.alias("node"), "keys", "signature")
        entered = own.select("node", "doc_id", "text_key", F.explode("keys").alias("key"))
        buckets = entered.groupBy("key").agg(F.min("node").alias("lo"), F.max("node").alias("hi"))
        buckets = store(buckets.where("lo < hi").select(F.col("key").alias("k"), "lo"), "buckets")
        held = sieve(entered, buckets.select(F.col("k").alias("key")), "key")
        members = store(held.join(buckets, F.col("key") == F.col("k")).select("node", "doc_id", "text_key", "key", "lo"), "members")
        wanted = store(members.select("node", "doc_id", "text_key").distinct(), "wanted")
        sets = store(self._sets(wanted), "sets")
        # a doc_id on several rows ties their sets together
        tied = place.groupBy("doc_id").agg(F.min("node").alias("a"), F.max("node").alias("b"), F.collect_set("node").alias("all")).where("a < b").select("a", F.explode("all").alias("b")).where("a < b")
        first = members.where("lo < node").groupBy("node").agg(F.min("lo").alias("lo")).select(F.col("lo").alias("a"), F.col("node").alias("b"))
        links = store(self._confirmed(first, sets).unionByName(tied), "links-a")
        labels = connected(links, scratch, "cc-a")
        again = self._mixed(members, labels, "b")
        if again is not None:
            least = again.groupBy("key", "label").agg(F.min("node").alias("node"))
            least = store(least, "least")
            hubs = store(least.groupBy("key").agg(F.min("node").alias("a")), "hubs")
            pairs = least.join(hubs, "key").select("a", F.col("node").alias("b")).where("a < b").distinct()
            pairs = pairs.join(first, ["a", "b"], "left_anti")
            more = store(self._confirmed(store(pairs, "pairs-b"), sets), "links-b")
            links = links.unionByName(more)
            if not more.isEmpty():
                labels = connected(links, scratch, "cc-b")
            again = self._mixed(again.select("node", "key"), labels, "c")
        if again is not None:
            more = store(self._across(again, own, sets), "links-c")
            if not more.isEmpty():
                labels = connected(links.unionByName(more), scratch, "cc-c")
        labels = store(labels, "labels")
        scratch.drop(*[x for x in scratch.made if x not in ("profile", "place", "labels")])
        named = place.join(labels, "node", "left").select(F.col("doc_id").alias("d"), F.col("text_key").alias("t"), F.coalesce("label", "node").alias("c"))
        if repeated:  # labels may be node numbers that are no doc_id
            least = named.groupBy("c").agg(F.min("d").alias("least"))
            named = named.join(least, "c").select("d", "t", F.col("least").alias("c"))
        named = named.groupBy("d", "t").agg(F.min("c").alias("c"))
        out = profile.select("doc_id", "text_key", "n_shingles").join(named, (F.col("doc_id") == F.col("d")) & (F.col("text_key") == F.col("t")), "left")
        component = F.coalesce("c", "doc_id")
        return out.select("doc_id", "text_key", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))

    def _across(self, again: DataFrame, own: DataFrame, sets: DataFrame) -> DataFrame:
        """Links between components that share a bucket, without listing pairs.

        Nodes that buckets tie together are a family. A family is cut into blocks, and a task takes one block, or two against
        each other: signatures first, then the intersections of all sets of the nodes left, as products of a 0/1 matrix; only
        links come out, and of those only what joins components. A block has a `copies`-th of its family, but at least `block` and at
        most `widest` nodes: so a set travels about `copies` times, more only in families beyond copies * widest, and no task
        holds more than two blocks, however large the family.
        """
        scratch, store = self.scratch, self.scratch.store
        signatures = own.select("node", "signature").dropDuplicates(["node"])
        hubs = again.groupBy("key").agg(F.min("node").alias("a"))
        kin = connected(again.select("key", F.col("node").alias("b")).join(hubs, "key").select("a", "b").where("a < b"), scratch, "cc-k")
        sizes = kin.groupBy("label").agg(F.count("*").alias("size"))
        kin = store(kin.join(sizes, "label").select("node", F.col("label").alias("kin"), "size"), "kin")
        labelled = again.select("node", "label").distinct()
        full = labelled.join(kin, "node").join(sets, "node").join(signatures, "node")
        block = F.least(F.lit(self.widest), F.greatest(F.lit(self.block), F.ceil(F.col("size") / self.copies)))
        blocks = F.ceil(F.col("size") / block).cast("int")
        full = full.withColumn("mine", F.pmod(F.xxhash64("node"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
        full = full.select("kin", F.least("mine", "other").alias("x"), F.greatest("mine", "other").alias("y"), "mine", "node", "label", "n", "packed", "signature")
        percent, distance = self.percent, self.distance

        def run(rows: pd.DataFrame) -> pd.DataFrame:
            return joined_links(rows, percent, distance)

        return full.groupBy("kin", "x", "y").applyInPandas(run, "a long, b long")

    def _mixed(self, members: DataFrame, labels: DataFrame, name: str) -> DataFrame | None:
        """(node, key, label) of the buckets that hold several components; None if there is none."""
        named = members.select("node", "key").join(labels, "node", "left").select("node", "key", F.coalesce("label", "node").alias("label"))
        named = self.scratch.store(named, f"named-{name}")
        keys = named.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo < hi").select("key")
        keys = self.scratch.store(keys, f"keys-{name}")
        out = self.scratch.store(named.join(keys, "key"), f"mixed-{name}")
        self.scratch.drop(f"named-{name}", f"keys-{name}")
        return None if out.isEmpty() else out


def keep_one(documents: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """documents without those linked to a smaller doc_id, directly or over others."""
    found = NearDuplicates(documents, words, percent).components().where("not kept")
    gone = found.select(F.col("doc_id").alias("__js_d"), F.col("text_key").alias("__js_k")).distinct()
    return documents.join(gone, (F.col("doc_id") == F.col("__js_d")) & (text_key(documents["text"]) == F.col("__js_k")), "left_anti")
