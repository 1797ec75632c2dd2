"""What several operators need: the shared folder, word and shingle hashing, connected components."""

from __future__ import annotations

import contextlib
import ctypes

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from ..sources.scratch import FOLDERS, remove, scratch, shared_folder  # noqa: F401

ASCII_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
"""bytes.translate table that lower-cases A-Z only."""


@contextlib.contextmanager
def small_batches(spark: SparkSession):
    """Arrow batches of at most ``BATCH_BYTES`` between JVM and Python while what is inside runs."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key, None)
    spark.conf.set(key, str(BATCH_BYTES))
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a table in the shared folder, read again: cuts the lineage and survives lost executors."""
    path = scratch(df.sparkSession, name)
    with small_batches(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextlib.contextmanager
def recorded():
    """Gives the list of tables written inside, filled at its end."""
    since, made = len(FOLDERS), []
    yield made
    made += FOLDERS[since:]


def drop(made: list[tuple[SparkSession, str]], docs: DataFrame) -> None:
    """Removes tables that docs does not read."""
    names = {path.rsplit("/", 1)[-1] for _, path in made}
    read = {n for f in docs.inputFiles() for n in f.split("/") if n in names} if made else set()
    for item in list(made):
        if item[1].rsplit("/", 1)[-1] not in read:
            remove(*item)
            made.remove(item)
            if item in FOLDERS:
                FOLDERS.remove(item)


def pick(df: DataFrame, **columns: str) -> DataFrame:
    """Only the named columns, under the operator's own names, whatever else df holds."""
    return df.select(*[F.col(f"`{old}`").alias(new) for new, old in columns.items()])


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


SLICE_BYTES, BATCH_BYTES = 1 << 20, 8 << 20


def _give_back() -> None:
    """Hands memory that a kernel no longer uses back to the system; its worker may wait long for the next task."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def frugal(run):
    """A kernel over batches that leaves its worker small."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            _give_back()

    return wrapped


def map_rows(df: DataFrame, run, schema) -> DataFrame:
    return df.mapInPandas(frugal(run), schema)


def map_texts(df: DataFrame, run, schema: str) -> DataFrame:
    """df.mapInPandas(run, schema) for rows that hold texts: run gets slices of about a megabyte of each
    Arrow batch, so a worker holds one batch as Arrow buffers and never all its texts as objects."""
    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def slices(batches):
        for batch in batches:
            step = max(1, min(batch.num_rows, int(batch.num_rows * SLICE_BYTES / max(1, batch.nbytes))))
            for at in range(0, batch.num_rows, step):
                yield batch.slice(at, step).to_pandas()

    def arrow_run(batches):
        for out in run(slices(batches)):
            if len(out):
                yield pa.RecordBatch.from_pandas(out, schema=arrow, preserve_index=False)

    return df.mapInArrow(frugal(arrow_run), schema)


class WordHashes(dict):
    """word (bytes) -> 64-bit hash; forgets all when it holds ``most`` words, so memory is bounded."""

    def __init__(self, most: int = 150_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


_POWERS = [np.uint64(pow(0x9E3779B97F4A7C15, i + 1, 2**64)) for i in range(64)]


def shingle_hashes(hashes: np.ndarray, width: int) -> np.ndarray:
    """A hash for each run of ``width`` words, in text order; the whole sequence when it is shorter."""
    n = len(hashes)
    if n == 0:
        return np.empty(0, np.uint64)
    width, short = min(width, n), n < width
    total = np.zeros(n - width + 1, np.uint64)
    for i in range(width):
        total += hashes[i : n - width + 1 + i] * _POWERS[i]
    return mix(total + np.uint64(n if short else 0))


def space_words(text: str | None) -> list[bytes]:
    """Words ``[^\\x20\\x09-\\x0D]+`` after lower-casing A-Z."""
    return text.encode("utf-8", "surrogatepass").translate(ASCII_LOWER).split() if text else []


def signed(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)


def _bitmap(ids: DataFrame, key: str, bits: int):
    """(one row for each word of a bitmap of 2^bits hashed ids, the word and the bit of a column)."""
    slot = lambda c: F.pmod(F.xxhash64(c), F.lit(1 << bits))
    word, bit = (lambda c: F.shiftright(slot(c), 6)), (lambda c: F.expr(f"shiftleft(1L, cast(pmod(xxhash64({c}), 64) as int))"))
    return ids.groupBy(word(key).alias("_word")).agg(F.bit_or(bit(key)).alias("_bits")), word, bit


def among(df: DataFrame, id_col: str, ids: DataFrame, key: str, bits: int = 22) -> DataFrame:
    """Rows of df whose id is in ids. A bitmap of 2^bits hashed ids (a broadcast of fixed size) drops
    most other rows before df is shuffled; where ids are so many that it fills up, it drops none."""
    bitmap, word, bit = _bitmap(ids, key, bits)
    kept = df.join(F.broadcast(bitmap), (word(id_col) == F.col("_word")) & (F.col("_bits").bitwiseAND(bit(id_col)) != 0), "left_semi")
    return kept.join(ids, F.col(id_col) == F.col(key), "left_semi")


def split_among(df: DataFrame, id_col: str, ids: DataFrame, key: str, bits: int = 22) -> tuple[DataFrame, DataFrame]:
    """(rows of df whose id is surely not in ids, the rest), by the same bitmap; rows with a null id are in the first."""
    bitmap, word, bit = _bitmap(ids, key, bits)
    marked = df.join(F.broadcast(bitmap), word(id_col) == F.col("_word"), "left")
    may = F.col(id_col).isNotNull() & F.coalesce(F.col("_bits").bitwiseAND(bit(id_col)) != 0, F.lit(False))
    return marked.where(~may).select(*df.columns), marked.where(may).select(*df.columns)


def contract(a: np.ndarray, b: np.ndarray, label: np.ndarray) -> np.ndarray:
    """Least label of each vertex's component once the edges (a, b) are added."""
    while len(a):
        x, y = label[a], label[b]
        open_ = x != y
        a, b, x, y = a[open_], b[open_], x[open_], y[open_]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
    return label


def _forest(batches):
    """Spanning forest of the edges of one partition: each node with the least node it reaches here."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while (up := parent.get(top, top)) != top:
            top = up
        while x != top:
            x, parent[x] = parent.get(x, x), top
        return top

    for pdf in batches:
        for u, v in zip(pdf["u"].tolist(), pdf["v"].tolist()):
            a, b = root(u), root(v)
            if a != b:
                parent[max(a, b)] = min(a, b)
            if len(parent) >= 2_000_000:
                yield pd.DataFrame([(x, root(x)) for x in list(parent)], columns=["u", "v"])
                parent.clear()
    yield pd.DataFrame([(x, root(x)) for x in list(parent)], columns=["u", "v"], dtype="int64")


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for every node of edges (u, v long); component is the least node reachable.

    Alternates large-star and small-star rounds until every tree has depth one. Each task first
    shrinks its edges to a spanning forest (memory bounded at two million nodes), so a hub arrives
    at most once per task. Rounds are written to the shared folder.
    """

    def shrunk(e: DataFrame) -> DataFrame:
        return map_rows(e.where("u <> v"), _forest, "u long, v long").where("u <> v")

    e = written(shrunk(edges.selectExpr("greatest(u, v) u", "least(u, v) v")).distinct(), "edges")
    while True:
        children = e.groupBy(F.col("u").alias("child")).agg(F.count("*").alias("n"))
        tops = e.select(F.col("v").alias("child"), F.lit(2).alias("n"))
        loose = children.select("child", "n").unionByName(tops.distinct().select("child", F.lit(1).cast("long").alias("n")))
        if not loose.groupBy("child").agg(F.sum("n").alias("n")).where("n > 1").limit(1).count():
            return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
                e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
            )
        both = e.unionByName(e.selectExpr("v u", "u v"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).selectExpr("u k", "least(u, m) m")
        large = both.where("v > u").join(least, F.col("u") == F.col("k")).selectExpr("v u", "m v").where("u <> v").distinct()
        small = large.groupBy("u").agg(F.min("v").alias("m")).selectExpr("u k", "m")
        joined = large.join(small, F.col("u") == F.col("k"))
        down = joined.selectExpr("v u", "m v").where("u <> v").unionByName(small.selectExpr("k u", "m v"))
        e = written(shrunk(down.distinct()).distinct(), "edges")

