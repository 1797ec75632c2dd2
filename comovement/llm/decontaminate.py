"""Benchmark decontamination: SimHash of item-sized windows, multi-index Hamming search, exact check.

A window of a text has as many words as an item. It is fingerprinted where enough of its shingles occur
in items of that size at all (a window below that count cannot reach the threshold): 128 bits, the
majority of each bit over its shingles, each counted as often as it occurs. The fingerprints of items
of one size stand in an index of four blocks of 32 bits, each in two halves of 16: by the pigeonhole
(``shares``) a fingerprint within ``RADIUS`` = 38 differs in at most 9, 9, 9 or 8 bits in one of the
blocks, and so in at most 4 or 3 in one of its halves. Half values that near are enumerated, or
compared one by one where the index has fewer of them; that gives every item within the radius and
about 4 % of the others. Those are verified: the exact share of the item's shingles, each weighted by
how often it occurs, that the window holds. A text shorter than the item is one window. A pair at
exactly the threshold lies beyond the radius with probability 0.004, and a window is one of several.

Documents are scanned map-side against the benchmark, in blocks of at most ``BLOCK_BYTES`` of item
text (an index of about 40 bytes for each byte of short words, in flat arrays), so what is sent to
executors is bounded however large the benchmark grows; each block is a scan of the documents.

Defined results: texts or items that are null or without words match nothing; items under five words
count as one shingle; a doc_id on several rows, or an item_id, keeps its best row; columns of any
other name are ignored or, by ``clean``, kept.
"""

from __future__ import annotations

import functools
import itertools

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .licenses import WORD_BYTES
from .shared import WordHashes, map_texts, mix, pick, shingle_hashes

WIDTH, THRESHOLD, RADIUS = 5, 0.8, 38
BLOCK_BYTES = 8 << 20
BLOCKS, HALVES = 4, 8
"""A fingerprint of 128 bits is four blocks of 32 bits, or eight halves of 16."""


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(WORD_BYTES).split() if text else []


def _planes(hashes: np.ndarray) -> np.ndarray:
    """The 128 bits of each shingle hash, one row for each."""
    wide = np.stack([mix(hashes), mix(hashes ^ np.uint64(0x9E3779B97F4A7C15))], axis=1)
    return np.unpackbits(wide.view(np.uint8), axis=1)


def simhashes(hashes: np.ndarray, starts: np.ndarray, size: int) -> np.ndarray:
    """Fingerprints, as rows of eight 16-bit halves, of the ``size`` shingles from each start."""
    low, high = int(starts.min()), int(starts.max()) + size
    sums = np.zeros((high - low + 1, 128), np.int32)
    np.cumsum(_planes(hashes[low:high]), axis=0, dtype=np.int32, out=sums[1:])
    bits = 2 * (sums[starts - low + size] - sums[starts - low]) > size
    return np.packbits(bits, axis=1).view(np.uint16)


def simhash(hashes: np.ndarray) -> np.ndarray:
    return simhashes(hashes, np.zeros(1, np.int64), len(hashes))[0]


@functools.cache
def _flips(most: int) -> np.ndarray:
    """All 16-bit numbers with at most ``most`` bits set."""
    return np.array([sum(1 << b for b in bits) for n in range(most + 1) for bits in itertools.combinations(range(16), n)], np.uint16)


def shares(most: int, parts: int) -> list[int]:
    """Budgets of parts: a total of at most ``most`` keeps to the budget in some part."""
    return [(most + 1) // parts + (i < (most + 1) % parts) - 1 for i in range(parts)]


def distances(prints: np.ndarray, a: np.ndarray, others: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(prints[a] ^ others[b]).sum(axis=1, dtype=np.int64)


class HammingIndex:
    """Multi-index over fingerprints: for each half the different values, sorted, and who has them."""

    def __init__(self, prints: np.ndarray):
        self.prints = prints
        self.tables = []
        for h in range(HALVES):
            order = np.argsort(prints[:, h], kind="stable")
            values, first = np.unique(prints[order, h], return_index=True)
            self.tables.append((values, np.append(first, len(prints)), order))

    def candidates(self, prints: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
        """(fingerprint, item) pairs of which some block keeps to its share of the radius."""
        out = [np.empty((2, 0), np.int64)]
        for h, (values, first, order) in enumerate(self.tables):
            in_block = shares(radius, BLOCKS)[h // 2]
            in_half = shares(in_block, 2)[h % 2]
            if in_half < 0:
                continue
            codes, flips = prints[:, h], _flips(min(16, in_half))
            if len(values) <= len(flips):
                x, v = np.nonzero(np.bitwise_count(codes[:, None] ^ values[None]) <= in_half)
            else:
                near = codes[:, None] ^ flips[None]
                at = np.minimum(np.searchsorted(values, near), len(values) - 1)
                x, f = np.nonzero(values[at] == near)
                v = at[x, f]
            counts = first[v + 1] - first[v]
            x = np.repeat(x, counts)
            k = order[np.repeat(first[v] - np.cumsum(counts) + counts, counts) + np.arange(len(x))]
            block = slice(h // 2 * 2, h // 2 * 2 + 2)
            ok = np.bitwise_count(prints[x, block] ^ self.prints[k, block]).sum(axis=1) <= in_block
            out.append(np.stack([x[ok], k[ok]]))
        pairs = np.unique(np.concatenate(out, axis=1), axis=1)
        return pairs[0], pairs[1]

    def near(self, prints: np.ndarray, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(fingerprint, item, distance) of every pair within the radius."""
        x, k = self.candidates(prints, radius)
        apart = distances(prints, x, self.prints, k)
        return x[apart <= radius], k[apart <= radius], apart[apart <= radius]


class Index:
    """Items of the benchmark by size: shingles, fingerprints and their multi-index, in flat arrays."""

    def __init__(self, items: list[tuple[int, str]], width: int = WIDTH):
        words, by_size = WordHashes(), {}
        for item_id, text in items:
            w = words.of(words_of(text))
            if len(w):
                by_size.setdefault(len(w), []).append((item_id, shingle_hashes(w, width)))
        self.sizes = sorted(by_size)
        self.groups = [([i for i, _ in by_size[n]], [np.sort(sh) for _, sh in by_size[n]], HammingIndex(np.stack([simhash(sh) for _, sh in by_size[n]]))) for n in self.sizes]
        owned = [np.unique(np.concatenate(shingles)) for _, shingles, _ in self.groups]
        every = np.concatenate(owned) if owned else np.empty(0, np.uint64)
        group = np.repeat(np.arange(len(owned)), [len(x) for x in owned])
        order = np.argsort(every, kind="stable")
        self.known, first = np.unique(every[order], return_index=True)
        self.first, self.group = np.append(first, len(every)), group[order].astype(np.int32)  # groups that use a known shingle
        self.short = [n for n in self.sizes if n < width]

    def hits(self, sh: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place, group) of every shingle that items of the group use, by group and place."""
        at = np.minimum(np.searchsorted(self.known, sh), len(self.known) - 1)
        places = np.flatnonzero(self.known[at] == sh)
        at = at[places]
        counts = self.first[at + 1] - self.first[at]
        places = np.repeat(places, counts)
        groups = self.group[np.repeat(self.first[at] - np.cumsum(counts) + counts, counts) + np.arange(len(places))]
        order = np.argsort(groups, kind="stable")
        return places[order], groups[order]


def dense_starts(at: np.ndarray, need: int, size: int, last: int) -> np.ndarray:
    """Starts up to ``last`` of windows of ``size`` that hold at least ``need`` of the sorted places ``at``."""
    if last == 0:
        return np.zeros(int(len(at) >= need), np.int64)
    low, high = at[need - 1 :] - size + 1, at[: len(at) - need + 1]
    low, high = np.maximum(low, 0), np.minimum(high, last)
    ok = low <= high
    low, high = low[ok], high[ok]
    low = np.maximum(low, np.append(0, high[:-1] + 1))  # both rise, so cut each run where the one before ends
    counts = np.maximum(high - low + 1, 0)
    return np.repeat(low - np.cumsum(counts) + counts, counts) + np.arange(counts.sum())


def shared_counts(window: np.ndarray, item: np.ndarray) -> int:
    """How many of an item's sorted shingles, each as often as it occurs, the window's sorted shingles hold."""
    values, mine = np.unique(item, return_counts=True)
    theirs = np.searchsorted(window, values, "right") - np.searchsorted(window, values, "left")
    return int(np.minimum(mine, theirs).sum())


def matches(index: Index, words: np.ndarray, width: int, threshold: float, radius: int):
    """(item, similarity, first word, words, distance) of the best window of each item that meets the threshold."""
    found = {}
    for w in [*index.short, width]:
        if len(words) < w or not len(index.known):
            continue
        # a short item's shingle is its whole sequence, hashed with its length
        sh = shingle_hashes(words, w) if w == width else _short(words, w)
        places, groups = index.hits(sh)
        cuts = np.flatnonzero(np.append(True, groups[1:] != groups[:-1])) if len(groups) else []
        for a, b in zip(cuts, np.append(cuts[1:], len(groups)).astype(int)):
            g, at = int(groups[a]), places[a:b]
            n = index.sizes[g]
            if (n < width) != (w < width) or (w < width and n != w):
                continue
            size = max(1, n - width + 1)
            need = max(1, int(np.ceil((threshold - 1e-12) * size)))
            if len(at) < need:
                continue
            here = min(size, len(sh))
            starts = dense_starts(at, need, here, len(sh) - here)
            ids, shingles, hamming = index.groups[g]
            for k in range(0, len(starts), 4096):
                part = starts[k : k + 4096]
                x, item, apart = hamming.near(simhashes(sh, part, here), radius)
                windows = {s: np.sort(sh[s : s + here]) for s in set(part[x].tolist())}
                for s, i, distance in zip(part[x].tolist(), item.tolist(), apart.tolist()):
                    similarity = shared_counts(windows[s], shingles[i]) / size
                    if similarity >= threshold - 1e-12:
                        best = (similarity, -s, min(n, len(words)), distance)
                        found[ids[i]] = max(best, found.get(ids[i], best))
    return [(item_id, s, -start, size, distance) for item_id, (s, start, size, distance) in found.items()]


def _short(words: np.ndarray, w: int) -> np.ndarray:
    total = np.stack([words[i : len(words) - w + 1 + i] for i in range(w)], axis=1)
    return np.array([shingle_hashes(row, w + 1)[0] for row in total], np.uint64)


def _scan(shared, width: int, threshold: float, radius: int):
    def run(batches):
        index, words = cloudpickle.loads(shared.value), WordHashes()
        for pdf in batches:
            rows = []
            for doc_id, text in zip(pdf["doc_id"], pdf["text"]):
                rows += [(doc_id, *m) for m in matches(index, words.of(words_of(text)), width, threshold, radius)]
            yield pd.DataFrame(rows, columns=["doc_id", "item_id", "similarity", "first_word", "n_words", "distance"]).astype({"doc_id": "Int64", "item_id": "Int64"})

    return run


def leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, threshold: float = THRESHOLD, radius: int = RADIUS) -> DataFrame:
    """doc_id, item_id, similarity, first_word, n_words, distance: the best window of each pair that leaks."""
    spark = docs.sparkSession
    items = pick(benchmark, item_id="item_id", text="text").where("text is not null").dropDuplicates()
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = 1 + size // BLOCK_BYTES
    found = None
    for block in range(blocks):
        own = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == block)
        index = Index([(r["item_id"], r["text"]) for r in own.orderBy("item_id", "text").toLocalIterator()], width)
        part = map_texts(
            pick(docs, doc_id=id_col, text=text_col),
            _scan(spark.sparkContext.broadcast(cloudpickle.dumps(index)), width, threshold, radius),
            "doc_id long, item_id long, similarity double, first_word long, n_words long, distance long",
        )
        found = part if found is None else found.unionByName(part)
    best = F.struct("similarity", (-F.col("first_word")).alias("before"), "n_words", "distance")
    top = found.groupBy("doc_id", "item_id").agg(F.max(best).alias("m"))
    return top.select("doc_id", "item_id", "m.similarity", (-F.col("m.before")).alias("first_word"), "m.n_words", "m.distance")


def clean(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The rows of docs without any leak, all columns kept; rows with a null id go or stay together."""
    bad = leaks(docs, benchmark, id_col=id_col).select(F.col("doc_id").alias("leak")).distinct().alias("_leaks")
    return docs.alias("_docs").join(bad, F.col(f"_docs.{id_col}").eqNullSafe(F.col("_leaks.leak")), "left_anti")
