"""Packing by the length histogram, shortest pack first.

Documents are tokenised and cut into pieces of at most ``size`` tokens. Only the histogram of piece
lengths (``size`` numbers) goes to the driver. There, lengths are placed longest first, each into
the pack with the most room left (the shortest), and equal packs are kept as one pattern with a
count. The patterns are joined back to the pieces by the piece's rank within its length; ranks come
from per-file counts, so no length is gathered in one task.

Defined results: an added token of the vocabulary that stands in a text gets its own id, as the JSON form
gives it; a null text is empty and gives one piece (the end id alone); repeated rows are
packed one by one; empty input gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import base64
import json
import zlib
from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .shared import map_texts, pick, written

SIZE, END = 2048, 1


def encoder(ranks_path: str, pattern: str, json_path: str | None = None):
    """text -> ids of the byte-level vocabulary. With the JSON form of the same vocabulary its added tokens are
    matched in texts, as ``tokenizers`` does; the ids are the same (tested) at a fifth of the time."""
    import tiktoken

    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    added = {}
    if json_path is not None:
        with open(json_path, encoding="utf-8") as f:
            added = {t["content"]: t["id"] for t in json.load(f)["added_tokens"]}
    own = tiktoken.Encoding("public_bytes", pat_str=pattern, mergeable_ranks=ranks, special_tokens=added)
    return lambda text: own.encode(text, allowed_special="all") if any(t in text for t in added) else own.encode_ordinary(text)


def _pieces(ranks_path: str | None, pattern: str | None, json_path: str | None, size: int, end: int):
    def run(batches):
        if ranks_path is None:
            import public_tokenizers as tokens

            encode = encoder(tokens.path("byte_bpe_50k.tiktoken"), tokens.PATTERN, tokens.path("byte_bpe_50k.json"))
        else:
            encode = encoder(ranks_path, pattern, json_path)
        part, ranks = TaskContext.get().partitionId(), defaultdict(int)
        for pdf in batches:
            rows = []
            for doc_id, text in zip(pdf["doc_id"], pdf["text"]):
                ids = np.array([*encode(text or ""), end], "<u4")
                for start in range(0, len(ids), size):
                    piece = ids[start : start + size]
                    n = len(piece)
                    rows.append((doc_id, start, n, zlib.crc32(piece.tobytes()), len(ids), part, ranks[n]))
                    ranks[n] += 1
            yield pd.DataFrame(rows, columns=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "part", "rank_there"]).astype({"doc_id": "Int64"})

    return run


def plan(histogram: dict[int, int], size: int = SIZE) -> list[tuple[int, tuple[int, ...]]]:
    """(count, lengths) of each packing pattern; lengths longest first, shortest pack first."""
    by_room: dict[int, list[list]] = defaultdict(list)
    rooms = np.zeros(size + 1, bool)
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left:
            open_rooms = np.flatnonzero(rooms[length:])
            if len(open_rooms):
                room = int(open_rooms[-1]) + length
                count, lengths = by_room[room][-1]
                used = min(count, left)
                if used == count:
                    by_room[room].pop()
                    rooms[room] = bool(by_room[room])
                else:
                    by_room[room][-1][0] -= used
            else:
                room, used, lengths = size, left, ()
            by_room[room - length].append([used, (*lengths, length)])
            rooms[room - length] = True
            left -= used
    return [(count, lengths) for room in sorted(by_room) for count, lengths in by_room[room] if count]


def slots(patterns: list[tuple[int, tuple[int, ...]]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, rank after the last, first sequence, offset) of each place in each pattern."""
    taken: dict[int, int] = defaultdict(int)
    out, sequence = [], 0
    for count, lengths in patterns:
        offset = 0
        for length in lengths:
            out.append((length, taken[length], taken[length] + count, sequence, offset))
            taken[length] += count
            offset += length
        sequence += count
    return out


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE, end: int = END, ranks_path: str | None = None, pattern: str | None = None, json_path: str | None = None) -> DataFrame:
    """One row per piece with its sequence and offset; ``ranks_path`` names another vocabulary file (``json_path``
    the one that lists its added tokens)."""
    spark = docs.sparkSession
    pieces = written(map_texts(
        pick(docs, doc_id=id_col, text=text_col),
        _pieces(ranks_path, pattern, json_path, size, end),
        "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, part int, rank_there long",
    ), "pieces")
    by_part = pieces.groupBy("length", "part").agg(F.count("*").alias("n"))
    before = by_part.withColumn("before", F.sum("n").over(Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)))
    before = before.select("length", "part", F.coalesce("before", F.lit(0)).alias("before"))
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    places = slots(plan(histogram, size))
    table = spark.createDataFrame(pd.DataFrame(places or [(0, 0, 0, 0, 0)], columns=["length", "lo", "hi", "seq", "offset"]))
    ranked = pieces.join(before, ["length", "part"]).withColumn("rank", F.col("before") + F.col("rank_there"))
    # the table's size depends on ``size`` alone: each placing step makes at most one pattern
    placed = ranked.join(F.broadcast(table), (ranked["length"] == table["length"]) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    return placed.select("doc_id", "start", ranked["length"], "ids_crc32", "doc_tokens", (F.col("seq") + F.col("rank") - F.col("lo")).alias("sequence_id"), "offset")
