"""Embedding near-duplicates by a subspace pigeonhole join.

Unit vectors are rotated (sign flips and Hadamard steps, so every bit of a rotated row depends on that
row alone) and split into blocks. Two vectors at cosine c lie at squared distance 2 - 2c, so in some
block they lie within that block's share of it. For each block, vectors are dealt into slabs as wide
as the block's radius along the block's first coordinate, each slab with a halo from the next one
(slabs with many vectors in tiles), and range-joined in the block's few dimensions. A pair belongs to
the first block that finds it and to one slab there, so it is counted once without being sent
anywhere; it is confirmed by its cosine in double precision on the vectors as given. Equal vectors
are one class with a count, and a tile returns sums and a spanning forest, never pairs.

In ``BLOCKS`` = 4 blocks a pair of unrelated vectors of 64 dimensions passes a block's budget with probability
2e-6 (with eight: 8e-4), so next to nothing is confirmed in vain. What remains is the scan: the radius
of a block is about that of the vectors' own spread along any coordinate, so slabs and the window on the
second coordinate leave about half of all pairs to one product in single precision. Work thus grows
with the square of the number of different vectors, by a small constant (see the README).

Defined results: vectors that are null, empty, zero or hold null or non-finite components, and rows
with a null vec_id, have no links and are kept; vectors of different lengths are not compared;
repeated rows are vectors of their own; rows that share a vec_id keep each vector's own links, and are one
vertex where components are concerned; empty input gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import components, contract, map_rows, pick, written

LEAST, BLOCKS, TILE = 0.9, 4, 16384


def rotated(x: np.ndarray) -> np.ndarray:
    """Rows of x (n, d) turned by a fixed orthogonal map in the next power-of-two dimension."""
    d = 1 << max(0, x.shape[1] - 1).bit_length()
    out = np.zeros((len(x), d))
    out[:, : x.shape[1]] = x
    rng = np.random.default_rng(20240202)
    for _ in range(2):
        out *= rng.choice([-1.0, 1.0], d)
        step = 1
        while step < d:
            pairs = out.reshape(len(out), -1, 2, step)
            out = np.stack([pairs[:, :, 0] + pairs[:, :, 1], pairs[:, :, 0] - pairs[:, :, 1]], axis=2).reshape(len(out), d)
            step *= 2
        out *= 1.0 / np.sqrt(d)
    return out


def _unit(vectors) -> np.ndarray:
    x = np.stack([np.asarray(v, np.float64) for v in vectors])
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _shares(d: int, blocks: int, least: float) -> tuple[int, np.ndarray]:
    """(dimensions of a block, squared distance that a pair may use up in each block)."""
    wide = max(1, d // blocks)
    return wide, np.full(d // wide, (2.0 - 2.0 * least + 1e-9) * wide / d)


def _deal(blocks: int, least: float, tile: int):
    def run(batches):
        for pdf in batches:
            for size, own in pdf.groupby("d"):
                turn = rotated(_unit(own["v"]))
                wide, share = _shares(turn.shape[1], blocks, least)
                for k, budget in enumerate(share):
                    slab = np.floor(turn[:, k * wide] / (np.sqrt(budget) * (1 + 1e-9))).astype(np.int64)
                    base = pd.DataFrame({"d": size, "block": k, "slab": slab, "halo": False, "rep": own["rep"].to_numpy(), "half": own["half"].to_numpy(), "m": own["m"].to_numpy(), "v": own["v"].to_numpy()})
                    yield base
                    yield base.assign(slab=slab - 1, halo=True)

    return run


def _join(blocks: int, least: float):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        k = int(pdf["block"].iloc[0])
        turn = rotated(_unit(pdf["v"]))
        wide, share = _shares(turn.shape[1], blocks, least)
        # own rows first, then the halo, each by the block's second coordinate: a row's partners are a range of it
        second = turn[:, k * wide + min(1, wide - 1)]
        order = np.lexsort((pdf["rep"].to_numpy(), second, pdf["halo"].to_numpy()))
        pdf, turn, second, n = pdf.iloc[order], turn[order], second[order], len(pdf)
        given = np.stack([np.asarray(v, np.float64) for v in pdf["v"]])
        length = np.sqrt((given * given).sum(axis=1))
        near = turn[:, k * wide : (k + 1) * wide]
        half = (near * near).sum(axis=1, keepdims=True) / 2
        ones = np.ones_like(half)
        # one product gives half the squared distance, in single precision with room for its rounding
        left, right = np.hstack([-near, half, ones]).astype(np.float32), np.ascontiguousarray(np.hstack([near, ones, half]).astype(np.float32).T)
        weight, side = pdf["m"].to_numpy(), pdf["side"].to_numpy()
        n_own, reach = int((~pdf["halo"].to_numpy()).sum()), np.sqrt(share[k]) * (1 + 1e-9) + 1e-9
        links, label = np.zeros(n, np.int64), np.arange(n)
        for at in range(0, n_own, 256):
            end = min(at + 256, n_own)
            low, high = second[at] - reach, second[end - 1] + reach
            ranges = ((at, int(np.searchsorted(second[:n_own], high, "right"))), tuple(n_own + np.searchsorted(second[n_own:], [low, high]) + [0, 1]))
            for first_col, last_col in ranges:
                apart = left[at:end] @ right[:, first_col : min(n, last_col)]
                x, y = np.divmod(np.flatnonzero(apart.ravel() <= np.float32(share[k] / 2 + 1e-5)), max(1, apart.shape[1]))
                x, y = x + at, y + first_col
                ok = (x < y) & (side[x] | side[y] == 3)
                x, y = x[ok], y[ok]
                for j in range(0, len(x), 65536):
                    p, q = x[j : j + 65536], y[j : j + 65536]
                    parts = ((turn[p] - turn[q]) ** 2).reshape(len(p), -1, wide).sum(axis=2)
                    first = ((parts <= share).argmax(axis=1) == k) & (parts[:, k] <= share[k])
                    p, q = p[first], q[first]
                    close = np.einsum("ij,ij->i", given[p], given[q]) >= least * length[p] * length[q]
                    p, q = p[close], q[close]
                    np.add.at(links, p, weight[q])
                    np.add.at(links, q, weight[p])
                    label = contract(p, q, label)
        rep = pdf["rep"].to_numpy()
        out = pd.DataFrame({"rep": rep, "half": pdf["half"].to_numpy(), "links": links, "root": rep[label]})
        return out[(links > 0) | (label != np.arange(n))]

    return run


def near_duplicates(table: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", least: float = LEAST, blocks: int = BLOCKS, tile: int = TILE) -> DataFrame:
    """vec_id, n_links, component_id, kept of each row of table."""
    own = pick(table, vec_id=id_col, v=vector_col)
    good = F.col("vec_id").isNotNull() & F.coalesce(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0), F.lit(False))
    keyed = own.withColumn("key", F.when(good, F.md5(F.col("v").cast("string").cast("binary"))))
    classes = keyed.where("key is not null").groupBy("key").agg(F.min("vec_id").alias("rep"), F.count("*").alias("m"), F.min("v").alias("v"))
    # rep and half a digest name a class, also where a vec_id has several vectors
    half = F.conv(F.substring("key", 1, 15), 16, 10).cast("long")
    classes = written(classes.withColumn("d", F.size("v")).withColumn("half", half), "vectors")
    dealt = map_rows(classes, _deal(blocks, least, tile), f"d int, block int, slab long, halo boolean, rep long, half long, m long, v {classes.schema['v'].dataType.simpleString()}")
    dealt = written(dealt, "blocks")
    sizes = dealt.groupBy("d", "block", "slab").agg(F.ceil(F.count("*") / tile).cast("int").alias("tiles"))
    tiles = F.col("tiles")
    dealt = dealt.join(sizes.select((F.col("d") + 0).alias("d"), F.col("block"), F.col("slab"), "tiles"), ["d", "block", "slab"])
    dealt = dealt.withColumn("t", F.pmod(F.xxhash64("rep"), tiles).cast("int"))
    pairs = F.transform(F.sequence(F.lit(0), tiles - 1), lambda o: F.struct(F.least("t", o).alias("i"), F.greatest("t", o).alias("j")))
    dealt = dealt.withColumn("p", F.explode(pairs)).select("d", "block", "slab", "p.i", "p.j", "halo", "rep", "half", "m", "v", F.when(F.col("p.i") == F.col("p.j"), 3).when(F.col("t") == F.col("p.i"), 1).otherwise(2).alias("side"))
    found = written(dealt.groupBy("d", "block", "slab", "i", "j").applyInPandas(_join(blocks, least), "rep long, half long, links long, root long"), "found")
    links = found.groupBy("rep", "half").agg(F.sum("links").alias("links"))
    comp = components(found.where("rep <> root").selectExpr("rep u", "root v"))
    state = classes.select("key", "rep", "half", "m").join(links, ["rep", "half"], "left").join(comp, F.col("rep") == F.col("node"), "left")
    state = state.select(F.concat("key", F.lit("")).alias("_k"), (F.col("m") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    rows = keyed.select("vec_id", F.coalesce("key", F.concat(F.lit("-"), F.coalesce(F.col("vec_id").cast("string"), F.lit("")))).alias("key"))
    joined = rows.join(state, F.concat("key", F.lit("")) == F.col("_k"), "left")
    component = F.coalesce("component_id", "vec_id")
    return joined.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


ORACLE = """
with recursive g as (select vec_id, e, sqrt(list_dot_product(e, e)) as n from (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings
  where vec_id is not null and len(embedding) > 0 and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0) where list_dot_product(e, e) > 0),
l as (select a.vec_id as a, b.vec_id as b from g a join g b on a.vec_id <> b.vec_id and len(a.e) = len(b.e) where list_dot_product(a.e, b.e) >= 0.9 * a.n * b.n),
r(a, b) as (select vec_id, vec_id from embeddings union select r.a, l.b from r join l on r.b = l.a),
c as (select a, min(b) as component_id from r group by 1), k as (select a, count(*) as n_links from l group by 1)
select e.vec_id, coalesce(k.n_links, 0) as n_links, c.component_id, e.vec_id = c.component_id as kept
from embeddings e join c on c.a = e.vec_id left join k on k.a = e.vec_id"""
