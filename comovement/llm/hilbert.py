"""Sharding along a Hilbert curve, in DataFrame functions only.

Metadata dimensions (source, language, size class) are quantised to ``BITS`` bits each: source and language
by the rank of the value among the different ones, in equal shares where these are more than codes, so
that a code is a range of values and zones prune by value; a row's curve index orders it, and the order is cut into runs of equal row counts, so each shard covers a compact
box of the metadata space and files can be pruned on several columns at once (``zones`` gives the
boxes). The rank of a row comes from a histogram of (curve index, bucket of doc_id): sums over at
most 2^(3 BITS) cells times ``spread`` buckets, added up in two levels, and row numbers within a bucket only. A hot
cell is thus spread over ``spread`` buckets, which grow with the table.

Defined results: null source and language have code 0 and a null text size 1; a null doc_id sorts
first in its cell; repeated rows take neighbouring places; an empty table gives no rows; extra
columns are ignored. Law: rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import pick, written

BITS, SHARDS, ROWS_PER_BUCKET = 5, 16, 200_000


def curve_index(codes: list[Column], bits: int = BITS) -> Column:
    """Position on the Hilbert curve of a cell given by one code in [0, 2^bits) per dimension.

    Works on the array of codes bit plane by bit plane: planes below a set bit are mirrored, below a
    clear bit exchanged with the first axis; then the Gray code is undone across axes and the planes
    are interleaved."""
    n = len(codes)

    def turned(axes: Column, plane: Column) -> Column:
        below = plane - 1

        def one(state: Column, i: int) -> Column:
            x0, xi = state[0], state[i]
            swap = x0.bitwiseXOR(xi).bitwiseAND(below)
            is_set = xi.bitwiseAND(plane) != 0
            first = F.when(is_set, x0.bitwiseXOR(below)).otherwise(x0.bitwiseXOR(swap))
            other = F.when(is_set, xi).otherwise(xi.bitwiseXOR(swap))
            return F.array(*[first if j == 0 else other if j == i else state[j] for j in range(n)])

        def step(state: Column, i: Column) -> Column:
            choice = F.when(i == 0, one(state, 0))
            for j in range(1, n):
                choice = choice.when(i == j, one(state, j))
            return choice

        return F.aggregate(F.array(*[F.lit(i) for i in range(n)]), axes, step)

    planes = F.array(*[F.lit(1 << b) for b in range(bits - 1, 0, -1)])
    axes = F.aggregate(planes, F.array(*[c.cast("int") for c in codes]), turned)

    def gray(prefix: Column, x: Column) -> Column:
        return F.concat(prefix, F.array(x.bitwiseXOR(F.coalesce(F.try_element_at(prefix, F.lit(-1)), F.lit(0)))))

    axes = F.aggregate(axes, F.array().cast("array<int>"), gray)
    last = F.element_at(axes, -1)
    fix = F.aggregate(planes, F.lit(0), lambda t, plane: F.when(last.bitwiseAND(plane) != 0, t.bitwiseXOR(plane - 1)).otherwise(t))
    axes = F.transform(axes, lambda x: x.bitwiseXOR(fix))
    every = F.array(*[F.lit(b) for b in range(bits - 1, -1, -1)])
    plane_bits = F.transform(every, lambda b: F.aggregate(axes, F.lit(0), lambda word, x: word * 2 + F.call_function("shiftright", x, b).bitwiseAND(1)))
    return F.aggregate(plane_bits, F.lit(0).cast("long"), lambda h, word: h * (1 << n) + word)


def first_values(df: DataFrame, column: str, codes: int) -> list[str]:
    """First values, in order, of at most ``codes`` ranges that hold equal numbers of the different values.

    Ranks come from counts by the values' first two bytes and ranks within those, so no task sorts all values."""
    head = F.substring(F.hex(F.col(column).cast("binary")), 1, 4)
    values = df.where(F.col(column).isNotNull()).select(F.col(column).cast("string").alias("v"), head.alias("head")).distinct()
    heads = values.groupBy("head").agg(F.count("*").alias("n"))
    before = heads.select("head", F.coalesce(F.sum("n").over(Window.orderBy("head").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), F.sum("n").over(Window.partitionBy()).alias("total"))
    ranked = values.withColumn("nth", F.row_number().over(Window.partitionBy("head").orderBy("v")) - 1).join(before, "head")
    at = F.expr(f"(before + nth) * least(total, {codes}) div total")
    return sorted((r["v"] for r in ranked.groupBy(at.alias("at")).agg(F.min("v").alias("v")).collect()), key=lambda v: v.encode())


def shard(docs: DataFrame, shards: int = SHARDS, bits: int = BITS, id_col: str = "doc_id", text_col: str = "text", rows_per_bucket: int = ROWS_PER_BUCKET) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard, and the codes and curve index."""
    own = pick(docs, doc_id=id_col, text=text_col, source="source", lang="lang")
    text, cells = F.coalesce("text", F.lit("")), 1 << bits
    firsts = {c: first_values(own, c, cells - 1) for c in ("source", "lang")}
    # codes from 1: the number of code ranges that start at or before the value
    code = lambda c: F.when(F.col(c).isNull(), 0).otherwise(F.size(F.filter(F.array(*[F.lit(v) for v in firsts[c]]).cast("array<string>"), lambda v: v <= F.col(c)))).cast("int")
    size = F.octet_length(text).cast("long") + 1
    rows = own.select("doc_id", size.alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), "source", "lang", code("source").alias("source_code"), code("lang").alias("lang_code"), F.least(F.floor(F.log2(size.cast("double"))), F.lit(cells - 1)).cast("int").alias("size_code"))
    rows = rows.withColumn("curve", curve_index([F.col("source_code"), F.col("lang_code"), F.col("size_code")], bits))
    rows = written(rows, "curve")
    total = rows.count()
    spread = 64 * (1 + total // rows_per_bucket // 64)
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(spread)).cast("int"))
    coarse = F.shiftright("curve", max(0, 3 * bits - 9))
    counts = written(rows.groupBy("curve", "bucket").agg(F.count("*").alias("n")).withColumn("coarse", coarse), "cells")
    so_far = lambda *by: Window.partitionBy(*by).rowsBetween(Window.unboundedPreceding, -1)
    groups = counts.groupBy("coarse").agg(F.sum("n").alias("n"))  # 512 at most
    base = groups.select("coarse", F.coalesce(F.sum("n").over(so_far().orderBy("coarse")), F.lit(0)).alias("base"))
    fine = counts.groupBy("coarse", "curve").agg(F.sum("n").alias("n"))
    fine = fine.select("coarse", "curve", F.coalesce(F.sum("n").over(so_far("coarse").orderBy("curve")), F.lit(0)).alias("in_group"))
    within = counts.select("curve", "bucket", F.coalesce(F.sum("n").over(so_far("curve").orderBy("bucket")), F.lit(0)).alias("in_cell"))
    starts = within.join(fine.join(base, "coarse"), "curve").select("curve", "bucket", (F.col("base") + F.col("in_group") + F.col("in_cell")).alias("start"))
    numbered = rows.withColumn("nth", F.row_number().over(Window.partitionBy("curve", "bucket").orderBy("doc_id", "text_crc32")) - 1)
    placed = numbered.join(starts, ["curve", "bucket"]).withColumn("rank", F.col("start") + F.col("nth"))
    at = F.expr(f"rank * {shards}L div {max(1, total)}L")
    placed = placed.withColumn("shard", at.cast("int"))
    slot = F.col("rank") - F.expr(f"(shard * {total}L + {shards - 1}) div {shards}")
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", slot.cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "source", "lang", "source_code", "lang_code", "size_code", "curve")


def zones(sharded: DataFrame) -> DataFrame:
    """The box of each shard: least and greatest value and code of each dimension, for pruning (nulls have code 0)."""
    bounds = [f(c).alias(f"{name}_{c}") for c in ("source", "lang", "size", "source_code", "lang_code", "size_code") for name, f in (("min", F.min), ("max", F.max))]
    return sharded.groupBy("shard").agg(F.count("*").alias("n_rows"), F.sum("size").alias("bytes"), *bounds)
