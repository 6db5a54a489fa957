"""LM scoring by context-tree weighting over bytes.

A text is its lower-cased words, each closed by a space, and one end byte. A byte is eight binary decisions; each decision
node of each context of 0 to `depth` bytes holds a Krichevsky-Trofimov estimate from its counts, and a context's weighted
probability is half its own estimate and half the product over its one-byte-longer contexts. Frozen after training, this
gives each byte's probability as a mixture over all depths.

Everything is counted and looked up by block. Texts are dealt to blocks of about `block_bytes` by a hash; a block lists
its distinct byte runs (context and next byte) and words with their counts in training texts. Those are summed over the
corpus, the tree is weighted bottom-up, and each block gets back one number for each of its distinct runs and words. Subtrees below a
three-byte context are weighted in one part; the three levels above are sums over the cluster, and a part gets those nodes of them that
its contexts need. Items travel as sorted, packed lists, dealt to parts whose number follows the input. What is broadcast are the two uppermost levels,
at most 256 * 255 + 255 nodes. Prices of runs travel in single precision (a relative error of 1e-7).

Words are counted by 63-bit hashes, runs exactly: two words with one hash would be counted as one, in c, V and n_known alike. Among
a billion distinct words that has a probability of about 5 %, and it would move one word.

Defined cases: a null text is empty: one end token; a null doc_id hashes as the empty string; rows are scored one by one, so
repeats do not matter (and count each in training); with no training text the base has N = V = 0 and the tree is uniform; very long texts
and words are read in pieces of 2**20 bytes with their contexts; extra columns are ignored, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, WordHashes, low_bytes, signed, text_key
from .common import mix as scramble

#: What closes a word, what closes a text, and what stands before it. None can be in a word.
SPACE, END, BEFORE = b" ", b"\n", b"\n"
_HALF = math.log(0.5)
#: Depth from which a part holds whole subtrees; the levels above it are folded over the cluster.
TOP = 3


def tokens(text: str | bytes | None) -> list[bytes]:
    """Words, then the end."""
    raw = text.encode("utf-8", "replace") if isinstance(text, str) else (text or b"")
    return [*low_bytes(raw).split(), END]


def stream(words: list[bytes]) -> bytes:
    return SPACE.join(words) if len(words) > 1 else END


def runs(data: bytes, depth: int) -> np.ndarray:
    """For every byte: its `depth` predecessors and itself, as one integer, the byte lowest."""
    x = np.frombuffer(BEFORE * depth + data, np.uint8)
    n = len(data)
    out = np.zeros(n, np.uint64)
    for i in range(depth + 1):
        out = (out << np.uint64(8)) | x[i : i + n]
    return out


#: log gamma of i + 1/2 and of i + 1, by i.
_SMALL = 4096
_HALVES = np.array([math.lgamma(i + 0.5) for i in range(_SMALL)])
_WHOLES = np.array([math.lgamma(i + 1.0) for i in range(_SMALL)])


def log_kt(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Log probability that the KT estimator gives to any sequence of a zeros and b ones."""
    return _lgamma(a, _HALVES, 0.5) + _lgamma(b, _HALVES, 0.5) - math.log(math.pi) - _lgamma(a + b, _WHOLES, 1.0)


def _lgamma(n: np.ndarray, small: np.ndarray, more: float) -> np.ndarray:
    """log gamma of n + more: from a table, or by Stirling's series, whose error is below 1e-12 there."""
    out = small[np.minimum(n, _SMALL - 1).astype(np.int64)]
    big = np.flatnonzero(n >= _SMALL)
    if len(big):
        y = n[big] + more
        z = 1.0 / (y * y)
        out[big] = (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + (1 / 12 - z * (1 / 360 - z / 1260)) / y
    return out


#: Set in the items that are hashes of words.
WORD = np.uint64(1 << 63)


def part_of(items: np.ndarray, parts: int) -> np.ndarray:
    """Items are dealt to parts evenly, by a hash."""
    return (scramble(items) % np.uint64(parts)).astype(np.int32)


class Lookup:
    """Numbers by item: items in order of a hash, with the place where each hash prefix starts. All asked items are there."""

    def __init__(self, items: np.ndarray, x: np.ndarray):
        bits = max(4, int(len(items)).bit_length() + 1)
        self.shift = np.uint64(64 - bits)
        h = scramble(items) >> self.shift
        order = np.argsort(h, kind="stable")
        self.items, self.x = items[order], x[order]
        self.start = np.zeros(1 << bits, np.int32)
        np.cumsum(np.bincount(h.astype(np.int64), minlength=1 << bits)[:-1], out=self.start[1:])

    def of(self, wanted: np.ndarray) -> np.ndarray:
        place = self.start[(scramble(wanted) >> self.shift).astype(np.int64)]
        todo = np.flatnonzero(self.items[place] != wanted)
        while len(todo):
            place[todo] += 1
            todo = todo[self.items[place[todo]] != wanted[todo]]
        return self.x[place]


def pack_sorted(items: np.ndarray) -> bytes:
    return zlib.compress(np.diff(items, prepend=np.uint64(0)).astype("<u8").tobytes(), 1)


def unpack_sorted(data: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(zlib.decompress(data), "<u8"), dtype=np.uint64)


def decisions(grams: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each run its eight (context, prefix) keys and bits. A prefix is 1 followed by the bits so far."""
    byte, context = grams & np.uint64(255), grams >> np.uint64(8)
    keys, bits = [], []
    for j in range(8):
        prefix = (np.uint64(1) << np.uint64(j)) | (byte >> np.uint64(8 - j))
        keys.append((context << np.uint64(8)) | prefix)
        bits.append((byte >> np.uint64(7 - j)) & np.uint64(1))
    return np.stack(keys), np.stack(bits)


def shorten(keys: np.ndarray, to: int) -> np.ndarray:
    """Keys with only the last `to` bytes of their contexts."""
    return keys & np.uint64((1 << (8 * (to + 1))) - 1)


class Level:
    """Decision nodes of one depth by sorted key (context, prefix): counts, weighted log probability, and the weight of stopping here.

    After `descend`, zero and one are the probabilities that all depths down to this one give to a next bit of 0 and of 1, and left is
    the weight that is left for deeper ones."""

    def __init__(self, keys: np.ndarray, zeros: np.ndarray, ones: np.ndarray, children: np.ndarray | None):
        self.keys, self.zeros, self.ones = keys, zeros, ones
        own = log_kt(zeros, ones)
        if children is None:
            self.weighted, self.stop = own, np.ones(len(keys))
        else:
            self.weighted = np.logaddexp(_HALF + own, _HALF + children)
            self.stop = np.exp(_HALF + own - self.weighted)
        self.up: np.ndarray | None = None  # place of each node's parent in the level above

    def shorter(self, depth: int) -> Level:
        """The level above, at that depth."""
        u, self.up = np.unique(shorten(self.keys, depth), return_inverse=True)
        add = lambda x: np.bincount(self.up, x, len(u))
        return Level(u, add(self.zeros), add(self.ones), add(self.weighted))

    def descend(self, zero, one, left) -> None:
        """From what the parents of these nodes have; 0, 0, 1 at the root's depth."""
        share, total = left * self.stop, self.zeros + self.ones + 1.0
        self.zero, self.one, self.left = zero + share * (self.zeros + 0.5) / total, one + share * (self.ones + 0.5) / total, left * (1.0 - self.stop)

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place, whether it is there) of each key."""
        if not len(self.keys):
            return np.zeros(keys.shape, np.int64), np.zeros(keys.shape, bool)
        place = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return place, self.keys[place] == keys


def deepest(grams: np.ndarray, counts: np.ndarray) -> tuple[Level, np.ndarray]:
    """The level of the whole contexts of sorted distinct runs, and the place of each run's eight decisions in it. Runs in order
    have the keys of each decision in order, so nodes are found by comparing neighbours."""
    keys, bits = decisions(grams)
    places, parts = np.empty(keys.shape, np.int64), []
    at = 0
    for j in range(8):
        start = np.flatnonzero(np.concatenate([[True], keys[j, 1:] != keys[j, :-1]]))
        ones, both = (np.add.reduceat(x, start).astype(float) for x in (counts * bits[j].astype(np.int64), counts))
        places[j] = at + np.repeat(np.arange(len(start)), np.diff(np.append(start, len(grams))))
        parts.append((keys[j, start], both - ones, ones))
        at += len(start)
    flat, zeros, ones = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(flat, kind="stable")
    back = np.empty(len(order), np.int64)
    back[order] = np.arange(len(order))
    return Level(flat[order], zeros[order], ones[order], None), back[places]


def tree(grams: np.ndarray, counts: np.ndarray, deep: int, shallow: int) -> tuple[list[Level], np.ndarray]:
    """Levels `deep` down to `shallow`, deepest first, of sorted distinct runs; the places of their decisions in the deepest."""
    first, places = deepest(grams, counts)
    out = [first]
    for d in range(deep - 1, shallow - 1, -1):
        out.append(out[-1].shorter(d))
    return out, places


def prices(grams: np.ndarray, counts: np.ndarray, above: list[Level], depth: int) -> np.ndarray:
    """log10 probabilities of the last byte of sorted distinct runs. above: the levels 0, 1, ... already descended, with all parents of
    the runs that were counted. Runs that were not take, for each decision, what the deepest context seen gives, and half of what is left."""
    out, live = np.empty(len(grams)), counts > 0
    levels: list[Level] = []
    if live.any():
        levels, places = tree(grams[live], counts[live], depth, len(above))
        at, _ = above[-1].find(shorten(levels[-1].keys, len(above) - 1))
        levels[-1].descend(above[-1].zero[at], above[-1].one[at], above[-1].left[at])
        for low, high in zip(levels[-2::-1], levels[:0:-1], strict=True):
            low.descend(high.zero[low.up], high.one[low.up], high.left[low.up])
        _, bits = decisions(grams[live])
        out[live] = np.log10(np.where(bits == 1, levels[0].one[places], levels[0].zero[places])).sum(0)
    new = np.flatnonzero(~live)
    for start in range(0, len(new), 1 << 16):
        part = new[start : start + (1 << 16)]
        keys, bits = decisions(grams[part])
        made, left = np.zeros(keys.shape), np.ones(keys.shape)
        for d, level in enumerate([*above, *levels[::-1]]):
            at, seen = level.find(shorten(keys, d))
            if len(level.keys):
                made = np.where(seen, np.where(bits == 1, level.one[at], level.zero[at]), made)
                left = np.where(seen, level.left[at], left)
        out[part] = np.log10(made + 0.5 * left).sum(0)
    return out


class ContextTree:
    """The same model in memory, for small corpora."""

    def __init__(self, texts: list, depth: int = 5):
        self.depth = depth
        grams = np.concatenate([runs(stream(tokens(t)), depth) for t in texts]) if texts else np.empty(0, np.uint64)
        self.grams, self.counts = np.unique(grams, return_counts=True)
        self.root = Level(*(np.empty(0, t) for t in (np.uint64, float, float)), None)
        if texts:
            self.root = tree(self.grams, self.counts, depth, 0)[0][-1]
        self.root.descend(0.0, 0.0, 1.0)

    def of_runs(self, grams: np.ndarray) -> np.ndarray:
        both = np.union1d(self.grams, grams)
        counts = np.zeros(len(both), np.int64)
        counts[np.searchsorted(both, self.grams)] = self.counts
        return prices(both, counts, [self.root], self.depth)[np.searchsorted(both, grams)]

    def log10(self, text) -> float:
        return float(self.of_runs(runs(stream(tokens(text)), self.depth)).sum())

    def bits_per_byte(self, text) -> float:
        return -self.log10(text) / math.log10(2) / len(stream(tokens(text)))


def columns_of(nodes: pd.DataFrame) -> tuple[np.ndarray, ...]:
    """(keys, zeros, ones, stop) in order of the keys."""
    nodes = nodes.sort_values("node")  # contexts of up to two bytes: no key is negative
    return nodes["node"].to_numpy(np.int64).view(np.uint64), *(nodes[c].to_numpy(float) for c in ("zeros", "ones", "stop"))


def score(documents: DataFrame, training, depth: int = 5, block_bytes: int = 24 << 20, part_bytes: int = 8 << 20) -> DataFrame:
    """Per row: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, code_length (bits a byte).

    `training` is a Column over `documents`: true for the rows to learn from.
    """
    spark = documents.sparkSession
    scratch = Scratch(spark)
    size = documents.agg(F.sum(F.octet_length("text")).alias("n")).first()["n"] or 0
    if not TOP <= depth <= 6:
        raise ValueError("contexts of 3 to 6 bytes: runs and their byte must leave the top bit to words")
    blocks, parts = max(1, -(-size // block_bytes)), max(8, -(-size // part_bytes))
    own = documents.select(F.col("doc_id"), F.coalesce(training, F.lit(False)).alias("train"), F.coalesce("text", F.lit("")).cast("binary").alias("text"), text_key(F.col("text")).alias("k"))
    own = own.select(F.pmod(F.xxhash64("doc_id", "k"), F.lit(blocks)).cast("int").alias("block"), "doc_id", "train", "text")

    def listed(key: tuple, batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known = WordHashes()
        grams: list[np.ndarray] = []
        counts: list[np.ndarray] = []
        words: dict[bytes, int] = {}

        fresh: dict[bool, list[np.ndarray]] = {True: [], False: []}

        def fold() -> None:
            """Sorts what has come in, training texts and others apart, and counts runs of equal items."""
            for train, new in fresh.items():
                if new:
                    u, n = np.unique(np.concatenate(new), return_counts=True)
                    grams.append(u)
                    counts.append(n if train else np.zeros(len(u), np.int64))
                    new.clear()

        have = 0
        for batch in batches:
            for train, text in zip(batch["train"], batch["text"], strict=True):
                t = tokens(text)
                freq = Counter(t)
                for w, n in freq.items():
                    words[w] = words.get(w, 0) + (n if train else 0)
                data = stream(t)
                for at in range(0, len(data), 1 << 20):
                    before = data[max(0, at - depth) : at].rjust(depth, BEFORE)
                    g = runs(before + data[at : at + (1 << 20)], depth)[depth:] if at else runs(data[: 1 << 20], depth)
                    fresh[bool(train)].append(g)
                    have += len(g)
                    if have > 1 << 22:
                        fold()
                        have = 0
        fold()
        if grams:
            u, n = np.concatenate(grams), np.concatenate(counts)
            order = np.argsort(u, kind="stable")
            first = np.flatnonzero(np.diff(u[order], prepend=u[order[0]] ^ np.uint64(1)))
            grams[:], counts[:] = [u[order[first]]], [np.add.reduceat(n[order], first)]
            items = np.concatenate([grams[0], known.of(list(words)) | WORD])
            n = np.concatenate([counts[0], np.fromiter(words.values(), np.int64, len(words))])
            part = part_of(items, parts)
            rows = []
            order = np.lexsort((items, part))
            for p, at in zip(*np.unique(part[order], return_index=True), strict=True):
                to = np.searchsorted(part[order], p, side="right")
                mine = order[at:to]
                rows.append((int(p), int(key[0]), pack_sorted(items[mine]), zlib.compress(n[mine].astype("<u4" if n.max() < 2**32 else "<u8").tobytes(), 1), int(n.max() >= 2**32)))
            yield pd.DataFrame(rows, columns=["part", "block", "items", "n", "wide"])

    lists = scratch.store(own.groupBy("block").applyInPandas(listed, "part int, block int, items binary, n binary, wide int"), "lists")

    def summed(key: tuple, batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        items, n = np.empty(0, np.uint64), np.empty(0, np.int64)
        for b in batches:
            new = [unpack_sorted(x) for x in b["items"]]
            more = [np.frombuffer(zlib.decompress(x), "<u8" if wide else "<u4").astype(np.int64) for x, wide in zip(b["n"], b["wide"], strict=True)]
            u, back = np.unique(np.concatenate([items, *new]), return_inverse=True)
            items, n = u, np.rint(np.bincount(back, np.concatenate([n, *more]), len(u))).astype(np.int64)
        yield pd.DataFrame({"part": np.int32(key[0]), "kind": (items >= WORD).astype(np.int32), "item": signed(items), "n": n})

    sums = scratch.store(lists.groupBy("part").applyInPandas(summed, "part int, kind int, item long, n long"), "sums")
    facts = sums.where((F.col("kind") == 1) & (F.col("n") > 0)).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("N"), F.count("*").alias("V")).first()
    total, distinct = facts["N"], facts["V"]

    # subtrees below a three-byte context are whole in a part; a two-byte context with many runs is spread by its third byte
    pair, third = (F.shiftrightunsigned("item", 8).bitwiseAND(F.lit((1 << (8 * d)) - 1)) for d in (2, 3))
    low = sums.where("kind = 0").select("item", "n", pair.alias("pair"), third.alias("third"))
    sizes = scratch.store(low.groupBy("pair").agg(F.count("*").alias("size")), "sizes")  # at most 256**2 rows
    grams_in = sizes.agg(F.sum("size")).first()[0] or 0
    heavy = F.broadcast(sizes.where(F.col("size") > grams_in / parts).select("pair", F.lit(True).alias("heavy")))
    home = F.pmod(F.when(F.col("heavy"), F.xxhash64("third", F.lit(1))).otherwise(F.xxhash64("pair")), F.lit(parts)).cast("int")
    low = scratch.store(low.join(heavy, "pair", "left").select("item", "n", "pair", home.alias("home")), "low")

    def upper(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        live = rows[rows["n"] > 0].sort_values("item")
        if not len(live):
            return pd.DataFrame({"node": [], "zeros": [], "ones": [], "children": []})
        top = tree(live["item"].to_numpy(np.int64).view(np.uint64), live["n"].to_numpy(), depth, TOP)[0][-1]
        return pd.DataFrame({"node": signed(top.keys), "zeros": top.zeros, "ones": top.ones, "children": top.weighted})

    def folded(nodes: DataFrame, d: int) -> DataFrame:
        """The level of depth d from that of d + 1."""
        short = F.col("node").bitwiseAND(F.lit((1 << (8 * (d + 1))) - 1))

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                x = Level(b["node"].to_numpy(np.int64), b["zeros"].to_numpy(), b["ones"].to_numpy(), b["children"].to_numpy())
                yield pd.DataFrame({"node": x.keys, "zeros": x.zeros, "ones": x.ones, "children": x.weighted, "stop": x.stop})

        own = nodes.groupBy(short.alias("node")).agg(*[F.sum(c).alias(c) for c in ("zeros", "ones", "children")])
        return scratch.store(own.mapInPandas(run, "node long, zeros double, ones double, children double, stop double"), f"level{d}")

    nodes = scratch.store(low.groupBy("home").applyInPandas(upper, "node long, zeros double, ones double, children double"), "tops")
    for d in range(TOP - 1, -1, -1):
        nodes = folded(nodes, d)
    held: list[tuple] = []
    for d in range(TOP - 1):  # at most 255 and 256 * 255 nodes, whatever the corpus
        held.append(columns_of(spark.read.parquet(scratch.path(f"level{d}")).select("node", "zeros", "ones", "stop").toPandas()))
    shared = spark.sparkContext.broadcast(held)
    asked = low.select("home", "pair").distinct()
    second = spark.read.parquet(scratch.path(f"level{TOP - 1}")).select(F.shiftrightunsigned("node", 8).alias("pair"), "node", "zeros", "ones", "stop")
    second = scratch.store(asked.join(second, "pair").drop("pair"), "second")

    def priced(key: tuple, rows: pd.DataFrame, nodes: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("item")
        above: list[Level] = []
        for level in [*shared.value, columns_of(nodes)]:
            x = Level.__new__(Level)
            x.keys, x.zeros, x.ones, x.stop = level
            if above:
                at, _ = above[-1].find(shorten(x.keys, len(above) - 1))
                x.descend(*((above[-1].zero[at], above[-1].one[at], above[-1].left[at]) if len(x.keys) else (0.0, 0.0, 1.0)))
            else:
                x.descend(0.0, 0.0, 1.0)
            above.append(x)
        grams = rows["item"].to_numpy(np.int64).view(np.uint64)
        return pd.DataFrame({"part": part_of(grams, parts), "item": rows["item"], "x": prices(grams, rows["n"].to_numpy(), above, depth)})

    known = low.groupBy("home").cogroup(second.groupBy("home")).applyInPandas(priced, "part int, item long, x double")
    words = sums.where("kind = 1").select("part", "item", F.col("n").cast("double").alias("x"))
    known = scratch.store(known.unionByName(words), "prices")
    scratch.drop("low", "tops", "sums", "second")

    def answered(key: tuple, asked: pd.DataFrame, known: pd.DataFrame) -> pd.DataFrame:
        item = known["item"].to_numpy(np.int64).view(np.uint64)
        order = np.argsort(item)
        item, x = item[order], known["x"].to_numpy()[order]
        out = []
        for block, packed in zip(asked["block"], asked["items"], strict=True):
            mine = unpack_sorted(packed)
            got = x[np.searchsorted(item, mine)]
            cut = int(np.searchsorted(mine, WORD))  # grams, then words
            out.append((block, packed, got[:cut].astype("<f4").tobytes(), zlib.compress(got[cut:].astype("<f8").tobytes(), 1)))
        return pd.DataFrame(out, columns=["block", "items", "grams", "words"])

    back = lists.select("part", "block", "items").groupBy("part").cogroup(known.groupBy("part")).applyInPandas(answered, "block int, items binary, grams binary, words binary")
    doc_type = documents.schema["doc_id"].dataType.simpleString()

    def scored(key: tuple, docs: pd.DataFrame, known: pd.DataFrame) -> pd.DataFrame:
        item = [unpack_sorted(x) for x in known["items"]]
        x = [np.concatenate([np.frombuffer(g, "<f4").astype(float), np.frombuffer(zlib.decompress(w), "<f8")]) for g, w in zip(known["grams"], known["words"], strict=True)]
        item, x = np.concatenate(item), np.concatenate(x)
        find = Lookup(item, x)
        look = find.of
        hashes = WordHashes()
        out: list[tuple] = []
        bottom = math.log10(total + distinct + 1)
        for text in docs["text"]:
            t = tokens(text)
            c = look(hashes.of(t) | WORD)
            data, s = stream(t), 0.0
            for at in range(0, len(data), 1 << 20):
                before = data[max(0, at - depth) : at].rjust(depth, BEFORE)
                g = runs(before + data[at : at + (1 << 20)], depth)[depth:] if at else runs(data[: 1 << 20], depth)
                s += float(look(g).sum())
            out.append((len(t), int((c > 0).sum()), float(np.log10(c + 1).sum() - len(t) * bottom), s, -s / math.log10(2) / len(data)))
        cols = list(zip(*out, strict=True)) if out else [()] * 5
        return pd.DataFrame({"doc_id": docs["doc_id"], "held_out": ~docs["train"].astype(bool), "n_tokens": cols[0], "n_known": cols[1], "base_score": cols[2], "score": cols[3], "code_length": cols[4]})

    schema = f"doc_id {doc_type}, held_out boolean, n_tokens long, n_known long, base_score double, score double, code_length double"
    out = own.groupBy("block").cogroup(back.groupBy("block")).applyInPandas(scored, schema)
    return out.withColumn("train_tokens", F.lit(total).cast("long"))
