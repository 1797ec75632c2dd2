"""Exact removal of repeated byte strings: a distributed merge sort of suffixes that knows common prefixes.

A byte goes if a string of ``LENGTH`` bytes that covers it also starts earlier (by doc_id, then start).
Sorting every suffix would move each byte a hundred times, so suffixes are sorted only at anchors:
each window of LENGTH bytes has one, the leftmost least-hashed gram of ``GRAM`` bytes in it, which
depends on the window's content alone. Equal windows hence have equal anchors at equal offsets, and
the windows of one anchor form a range.

1. Each task reduces its texts to ranges (anchor gram, hash of the whole range, place). Of ranges that
   repeat within a batch of the task the first stands for all, so a hot passage leaves a batch once; the
   rest go by gram to a partition, where grams that stand alone are dropped.
2. All other ranges are decided by sorted suffixes. Each, from its anchor to its end with the bytes
   before the anchor attached, is sorted among those of its task, front-coded, and sent in runs by gram.
   Runs are merged by a loser tree in which each head carries the length of its common prefix with the
   last suffix out: only heads with equal such lengths are compared, from there on. Of equal suffixes
   with equal bytes before them all but the first go; for the others neighbours' common prefixes tell,
   for each split of a window into bytes before and from the anchor, which suffixes can agree, and the
   bytes before the anchor decide.

Step 1 settles repeats inside a batch by 96-bit hash equality of ranges that also share their gram (64
bits more); what is decided between batches is decided by bytes. Partitions follow the bytes of text,
``PART_BYTES`` each, so what a task gathers does not grow with the table: of one range it gathers as many
copies as there are batches at most.

Defined results: a null text is empty; texts under LENGTH bytes lose nothing and remove nothing; a
null doc_id comes before all others; rows that repeat doc_id and text are one document and get one
result each; a doc_id with several texts has them ordered by their MD5; empty input gives no rows;
extra columns are ignored. Removal is by bytes, so ``kept`` (the text) leaves out characters of which
a part was removed, while ``kept_sha256`` covers the remaining bytes themselves.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import among, map_rows, map_texts, mix, pick, split_among, written

LENGTH, GRAM = 100, 32
SEGMENT, BATCH_BYTES, PART_BYTES = 1 << 20, 16 << 20, 16 << 20
NO_ID = -(2**63)

_RANGE = np.dtype([("gram", "<u8"), ("whole", "<u8"), ("more", "<u4"), ("d", "<i8"), ("j", "<i4"), ("lo", "<u4"), ("before", "u1"), ("span", "u1")])
_SENT = np.dtype([(f, _RANGE[f].str) for f in ("gram", "d", "j", "lo", "before", "span")])
"""A range as it leaves its batch: the hashes of the whole range have done their work there."""


class Anchors:
    """Anchor ranges of byte strings. Prefix sums of bytes times powers give any substring's hash."""

    def __init__(self, length: int = LENGTH, gram: int = GRAM):
        self.length, self.gram = length, gram
        rng = np.random.default_rng(20240303)
        self.tables = rng.integers(0, 2**63, (2, 256), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        n = SEGMENT + 2 * length
        base, back = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 2**64)
        self.powers = np.cumprod(np.full(n, base, np.uint64))
        self.backs = np.cumprod(np.full(n, back, np.uint64))

    def of(self, data: bytes):
        """Arrays (gram hash, range hash, its second half, anchor, first window, last window)."""
        parts = [self._segment(data[at : at + SEGMENT + self.length - 1], at) for at in range(0, max(1, len(data) - self.length + 1), SEGMENT) if len(data) - at >= self.length]
        return [np.concatenate(x) for x in zip(*parts)] if parts else None

    def _segment(self, data: bytes, at: int):
        b = np.frombuffer(data, np.uint8)
        n, k, length = len(b), self.gram, self.length
        sums = np.zeros((2, n + 1), np.uint64)
        for i in range(2):
            np.cumsum(self.tables[i][b] * self.powers[:n], out=sums[i, 1:])
        grams = mix((sums[0, k:] - sums[0, :-k]) * self.backs[: n - k + 1])
        low = (grams & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(grams), dtype=np.uint64)
        wide, width = 1, length - k + 1
        while 2 * wide <= width:
            low = np.minimum(low[:-wide], low[wide:])
            wide *= 2
        if width > wide:
            low = np.minimum(low[: len(low) - (width - wide)], low[width - wide :])
        anchor = (low & np.uint64(0xFFFFFFFF)).astype(np.int64)
        first = np.flatnonzero(np.append(True, anchor[1:] != anchor[:-1]))
        last = np.append(first[1:], len(anchor)) - 1
        anchor = anchor[first]
        end = last + length
        whole = [mix((s[end] - s[first]) * self.backs[first] + (end - first).astype(np.uint64)) for s in sums]
        return grams[anchor], whole[0], whole[1].astype(np.uint32), anchor + at, first + at, last + at


def _firsts(r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ranges sorted by content then place, whether each is the first of its content)."""
    r = r[np.lexsort((r["lo"], r["j"], r["d"], r["more"], r["whole"], r["gram"]))]
    same = (r["gram"][1:] == r["gram"][:-1]) & (r["whole"][1:] == r["whole"][:-1]) & (r["more"][1:] == r["more"][:-1])
    return r, np.append(True, ~same)


def _spans(d, j, lo, hi) -> np.ndarray:
    """The union of intervals [lo, hi) of documents (d, j), as rows (d, j, lo, hi) in order."""
    order = np.lexsort((hi, lo, j, d))
    d, j, lo, hi = d[order], j[order], lo[order].astype(np.int64), hi[order].astype(np.int64)
    new = np.append(True, (d[1:] != d[:-1]) | (j[1:] != j[:-1]))
    doc = np.cumsum(new)
    far = int(hi.max(initial=0)) + 1
    reach = np.maximum.accumulate(hi + doc * far)  # running end within each document
    starts = np.flatnonzero(new | (lo + doc * far > np.append(0, reach[:-1])))
    ends = np.append(starts[1:], len(lo)) - 1
    return np.stack([d[starts], j[starts], lo[starts], reach[ends] - doc[ends] * far], axis=1) if len(lo) else np.empty((0, 4), np.int64)


def _reduce_texts(parts: int, length: int, gram: int):
    """Texts to rows (part, settled, ranges): binary blobs of ranges or of settled spans."""

    def out(pieces):
        if not pieces:
            return pd.DataFrame({"part": [], "settled": [], "blob": []})
        r, first = _firsts(np.concatenate(pieces))
        gone, r = r[~first], r[first]
        part = (r["gram"] >> np.uint64(20)).astype(np.int64) % parts
        order = np.lexsort((r["lo"], r["d"], part))
        r, part = r[order], part[order]
        cuts = np.flatnonzero(np.append(True, part[1:] != part[:-1]))
        rows = [(int(part[a]), False, b"".join(r[f][a:b].tobytes() for f in _SENT.names)) for a, b in zip(cuts, np.append(cuts[1:], len(r)))]
        s = _spans(gone["d"], gone["j"], gone["lo"], gone["lo"] + gone["span"] + np.uint32(length))
        place = (mix(s[:, 0].view(np.uint64)) % np.uint64(parts)).astype(np.int64) if len(s) else np.empty(0, np.int64)
        order = np.argsort(place, kind="stable")
        s, place = s[order], place[order]
        cuts = np.flatnonzero(np.append(True, place[1:] != place[:-1])) if len(s) else []
        rows += [(int(place[a]), True, s[a:b].tobytes()) for a, b in zip(cuts, np.append(cuts[1:], len(s)).astype(int))]
        return pd.DataFrame(rows, columns=["part", "settled", "blob"])

    def run(batches):
        anchors, pieces, size = Anchors(length, gram), [], 0
        for pdf in batches:
            for d, j, text in zip(pdf["d"].tolist(), pdf["j"].tolist(), pdf["text"]):
                data = text.encode("utf-8", "surrogatepass") if text else b""
                found = anchors.of(data)
                if found is None:
                    continue
                g, whole, more, anchor, lo, hi = found
                r = np.empty(len(g), _RANGE)
                r["gram"], r["whole"], r["more"], r["d"], r["j"], r["lo"], r["before"], r["span"] = g, whole, more, d, j, lo, anchor - lo, hi - lo
                pieces.append(r)
                size += len(data)
                if size >= BATCH_BYTES:
                    yield out(pieces)
                    pieces, size = [], 0
        yield out(pieces)

    return run


def _unpacked(blob: bytes) -> np.ndarray:
    n = len(blob) // _SENT.itemsize
    r, at = np.empty(n, _SENT), 0
    for f in _SENT.names:
        r[f] = np.frombuffer(blob, _SENT[f], n, at)
        at += n * _SENT[f].itemsize
    return r


def _settle(length: int):
    """Blobs of one partition to rows (d, j, lo, hi, before): settled spans (before null), and ranges left open,
    which are those whose gram stands in some other range too."""

    def run(batches):
        held, spans = [], []
        for pdf in batches:
            for settled, blob in zip(pdf["settled"], pdf["blob"]):
                (spans if settled else held).append(blob)
        done = np.concatenate([np.frombuffer(b, np.int64).reshape(-1, 4) for b in spans]) if spans else np.empty((0, 4), np.int64)
        r = np.concatenate([_unpacked(b) for b in held]) if held else np.empty(0, _SENT)
        if len(r):
            order = np.argsort(r["gram"], kind="stable")
            gram = r["gram"][order]
            same = gram[1:] == gram[:-1]
            r = r[order[np.append(False, same) | np.append(same, False)]]
        s = _spans(*done.T)
        yield pd.DataFrame({"d": s[:, 0], "j": s[:, 1], "lo": s[:, 2], "hi": s[:, 3], "before": pd.array([None] * len(s), "Int64")})
        lo = r["lo"].astype(np.int64)
        yield pd.DataFrame({"d": r["d"], "j": r["j"], "lo": lo, "hi": lo + r["span"] + length, "before": pd.array(r["before"].astype(np.int64), "Int64")})

    return run


def common_prefix(a: bytes, b: bytes, known: int = 0) -> int:
    """Length of the common prefix of a and b, which agree in the first ``known`` bytes."""
    n = min(len(a), len(b))
    if a[known:n] == b[known:n]:
        return n
    x = int.from_bytes(a[known:n], "big") ^ int.from_bytes(b[known:n], "big")
    return n - (x.bit_length() + 7) // 8


def front_coded(suffixes: list[bytes]) -> tuple[bytes, bytes, bytes]:
    """(common prefix with the one before, length of the rest, the rests) of sorted suffixes."""
    shared, rest, last = bytearray(), [], b""
    for s in suffixes:
        k = common_prefix(last, s)
        shared.append(k)
        rest.append(s[k:])
        last = s
    return bytes(shared), bytes(map(len, rest)), b"".join(rest)


def decoded(shared: bytes, sizes: bytes, rests: bytes):
    """(suffix, common prefix with the one before) of a front-coded run, one at a time."""
    last, at = b"", 0
    for k, n in zip(shared, sizes):
        last = last[:k] + rests[at : at + n]
        at += n
        yield last, k


def merged(runs: list):
    """(run, suffix, common prefix with the suffix before) of all sorted runs, by a loser tree.

    runs: iterators of (suffix, common prefix with the one before it in its run)."""
    k = len(runs)
    heads: list[bytes | None] = [None] * k
    known = [0] * k  # common prefix of each head with the last suffix out

    def advance(i: int) -> None:
        heads[i], known[i] = next(runs[i], (None, 0))

    def wins(i: int, j: int) -> bool:
        a, b = heads[i], heads[j]
        if a is None or b is None:
            return b is None and (a is not None or i < j)
        if known[i] != known[j]:
            return known[i] > known[j]
        n = common_prefix(a, b, known[i])
        first = i < j if n == len(a) == len(b) else n == len(a) or (n < len(b) and a[n] < b[n])
        known[j if first else i] = n
        return first

    for i in range(k):
        advance(i)
    losers = [0] * k

    def play(node: int) -> int:
        if node >= k:
            return node - k
        i, j = play(2 * node), play(2 * node + 1)
        if wins(i, j):
            losers[node] = j
            return i
        losers[node] = i
        return j

    top = play(1) if k > 1 else 0
    while k and heads[top] is not None:
        yield top, heads[top], known[top]
        advance(top)
        node = (top + k) // 2
        while node:
            if not wins(top, losers[node]):
                top, losers[node] = losers[node], top
            node //= 2


def _runs(parts: int, length: int, gram: int):
    """Texts with open ranges to rows (part, run columns): front-coded sorted suffixes by gram."""

    def out(left):
        by_part: dict[int, list] = {}
        for item in left:
            by_part.setdefault(xxhash.xxh3_64_intdigest(item[0][:gram]) % parts, []).append(item)
        rows = []
        for part, items in by_part.items():
            items.sort(key=lambda x: x[0])
            rows.append((part, *front_coded([x[0] for x in items]), bytes(len(x[1]) for x in items), b"".join(x[1] for x in items), np.array([x[2:] for x in items], np.int64).tobytes()))
        return pd.DataFrame(rows, columns=["part", "shared", "sizes", "rests", "left_sizes", "lefts", "places"])

    def run(batches):
        left, size = [], 0
        for pdf in batches:
            for d, j, text, ranges in zip(pdf["d"].tolist(), pdf["j"].tolist(), pdf["text"], pdf["ranges"]):
                data = text.encode("utf-8", "surrogatepass")
                for r in ranges:
                    a = r["lo"] + r["before"]
                    left.append((data[a : r["hi"]], data[r["lo"] : a], d, j, a))
                if len(left) >= 200_000:
                    yield out(left)
                    left = []
        yield out(left)

    return run


def singled(block: list, near: list[int]) -> tuple[list, list[int], list[tuple]]:
    """The block with the first of equal suffixes that also have equal bytes before them, its common prefixes, and
    the spans (d, j, start, end) of the others."""
    kept, apart, spans = [], [], []
    seen: dict[bytes, int] = {}
    low, size = 1 << 30, -1  # least common prefix since the last kept entry; length of the suffix before
    for entry, k in zip(block, near):
        suffix, left, *place = entry
        if not k == len(suffix) == size:
            seen = {}
        low, size = min(low, k), len(suffix)
        at = seen.get(left)
        if at is None:
            seen[left] = len(kept)
            kept.append(entry)
            apart.append(low)
            low = 1 << 30
            continue
        if tuple(place) < tuple(kept[at][2:]):
            kept[at], place = entry, kept[at][2:]
        d, j, a = place
        spans.append((d, j, a - len(left), a + len(suffix)))
    return kept, apart, spans


def resolved(block: list, near: list[int], length: int, gram: int):
    """(d, j, start, end) covered by earlier equal windows, of sorted suffixes that share their gram.

    block: (suffix, bytes before it, d, j, place); near: common prefix of each with the one before."""
    block, near, spans = singled(block, near)
    m = len(block)
    if m < 2:
        return spans
    lows, highs = [length] * m, [-1] * m
    most = max(near[1:])
    for before in range(max(0, length - most), length - gram + 1):
        need, at = length - before, 0
        while at < m:
            end = at + 1
            while end < m and near[end] >= need:
                end += 1
            if end - at > 1:
                first: dict[bytes, tuple] = {}
                for i in range(at, end):
                    s, left, *place = block[i]
                    if len(left) >= before and len(s) >= need:
                        context = left[len(left) - before :]
                        here = (*place[:2], place[2] - before, i)
                        seen = first.get(context)
                        if seen is None or here < seen:
                            first[context] = here
                            here, seen = seen, here
                        if here is not None:
                            i = here[3]
                            lows[i], highs[i] = min(lows[i], before), max(highs[i], before)
            at = end
    return spans + [(block[i][2], block[i][3], block[i][4] - highs[i], block[i][4] - lows[i] + length) for i in range(m) if highs[i] >= 0]


def _merge(length: int, gram: int):
    """Front-coded runs of one partition to covered spans (d, j, lo, hi)."""

    def run(batches):
        runs, tails = [], []
        for pdf in batches:
            for row in pdf.itertuples(index=False):
                runs.append(decoded(row.shared, row.sizes, row.rests))
                ends = np.cumsum(np.frombuffer(row.left_sizes, np.uint8).astype(np.int64)).tolist()
                lefts = [row.lefts[a:b] for a, b in zip([0, *ends], ends)]
                tails.append(zip(lefts, np.frombuffer(row.places, np.int64).reshape(-1, 3).tolist()))
        block, near, rows = [], [], []
        for i, suffix, shared in merged(runs):
            if shared < gram and block:
                rows += resolved(block, near, length, gram) if len(block) > 1 else []
                block, near = [], []
                if len(rows) >= 100_000:
                    yield pd.DataFrame(rows, columns=["d", "j", "lo", "hi"])
                    rows = []
            left, place = next(tails[i])
            block.append((suffix, left, *place))
            near.append(shared)
        rows += resolved(block, near, length, gram) if len(block) > 1 else []
        yield pd.DataFrame(rows, columns=["d", "j", "lo", "hi"])

    return run


def _cut(carried: list[str], with_text: bool):
    def run(batches):
        for pdf in batches:
            rows = []
            for d, j, text, spans in zip(pdf["d"], pdf["j"], pdf["text"], pdf["spans"]):
                data = text.encode("utf-8", "surrogatepass") if text else b""
                n, gone, at, kept = 0, 0, 0, []
                if spans is not None and len(spans):
                    for _, _, lo, hi in _spans(np.zeros(len(spans), np.int64), np.zeros(len(spans), np.int64), np.array([s["lo"] for s in spans]), np.array([s["hi"] for s in spans])).tolist():
                        kept.append(data[at:lo])
                        n, gone, at = n + 1, gone + hi - lo, hi
                kept = b"".join([*kept, data[at:]])
                rows.append((d, j, len(data), gone, n, hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "ignore") if with_text else None))
            out = pd.DataFrame(rows, columns=["d", "j", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])
            yield out.assign(**{c: pdf[c] for c in carried})

    return run


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, gram: int = GRAM, with_text: bool = False, carried: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of each row (and kept, the remaining text, and carried columns)."""
    own = pick(docs, doc_id=id_col, text=text_col, **{c: c for c in carried}).withColumn("d", F.coalesce("doc_id", F.lit(NO_ID)))
    repeats, size = own.groupBy("d").agg(F.count("*").alias("n"), F.sum(F.octet_length("text")).alias("bytes")).agg(F.max("n"), F.sum("bytes")).first()
    parts = max(8, -(-(size or 0) // PART_BYTES))
    if (repeats or 0) > 1:
        texts = own.select("d", F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("md5")).distinct()
        order = texts.groupBy("d").agg(F.array_sort(F.collect_list("md5")).alias("all"))
        numbered = order.select("d", F.posexplode("all").alias("j", "md5"))
        own = own.withColumn("md5", F.md5(F.coalesce("text", F.lit("")).cast("binary"))).join(numbered, ["d", "md5"]).select("doc_id", "text", "d", "j", *carried)
        single = own.dropDuplicates(["d", "j"])
    else:
        own = single = own.withColumn("j", F.lit(0))
    source = single.select("d", "j", "text")
    blobs = map_texts(source, _reduce_texts(parts, length, gram), "part int, settled boolean, blob binary")
    marks = written(map_rows(blobs.repartitionById(parts, "part"), _settle(length), "d long, j int, lo long, hi long, before long"), "ranges")
    left = marks.where("before is not null").groupBy("d", "j").agg(F.collect_list(F.struct("lo", "hi", "before")).alias("ranges"))
    few = written(left, "open")
    runs = map_texts(among(source, "d", few.select(F.col("d").alias("_d")).distinct(), "_d").join(few, ["d", "j"]), _runs(parts, length, gram), "part int, shared binary, sizes binary, rests binary, left_sizes binary, lefts binary, places binary")
    more = map_rows(runs.repartitionById(parts, "part"), _merge(length, gram), "d long, j int, lo long, hi long")
    spans = marks.where("before is null").select("d", "j", "lo", "hi").unionByName(more)
    spans = written(spans.groupBy("d", "j").agg(F.collect_list(F.struct("lo", "hi")).alias("spans")), "spans")
    more = "".join(f", {c} {own.schema[c].dataType.simpleString()}" for c in carried)
    schema = "d long, j int, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept string" + more
    # texts that a bitmap of cut documents leaves out are not shuffled
    whole, some = split_among(own, "d", spans.select(F.col("d").alias("_d")), "_d")
    whole = whole.select("d", "j", "text", F.lit(None).cast(spans.schema["spans"].dataType).alias("spans"), *carried)
    some = some.join(spans, ["d", "j"], "left").select("d", "j", "text", "spans", *carried)
    out = map_texts(whole, _cut(list(carried), with_text), schema).unionByName(map_texts(some, _cut(list(carried), with_text), schema))
    columns = [F.when(F.col("d") != NO_ID, F.col("d")).alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256", *["kept"] * with_text, *carried]
    return out.select(*columns)


ORACLE = """
with d as (select doc_id, hex(encode(coalesce(text, ''))) as h, strlen(coalesce(text, '')) as n from documents),
w as (select doc_id, i, hash(substr(h, 2 * i + 1, 200)) as k from (select doc_id, h, unnest(range(0, n - 99)) as i from d where n >= 100)),
f as (select doc_id, i from (select doc_id, i, row_number() over (partition by k order by doc_id, i) as r from w) where r > 1),
g as (select doc_id, i, sum(new) over (partition by doc_id order by i) as g from (select doc_id, i, case when i <= lag(i) over (partition by doc_id order by i) + 100 then 0 else 1 end as new from f)),
s as (select doc_id, min(i) as lo, max(i) + 100 as hi from g group by doc_id, g),
b as (select *, coalesce(lag(hi) over (partition by doc_id order by lo), 0) as since from s),
x as (select b.doc_id, sum(hi - lo) as gone, count(*) as spans, string_agg(substr(h, 2 * since + 1, 2 * (lo - since)), '' order by lo) || substr(any_value(h), 2 * max(hi) + 1) as kept
  from b join d using (doc_id) group by b.doc_id)
select d.doc_id, d.n as n_bytes, coalesce(x.gone, 0)::bigint as n_removed, coalesce(x.spans, 0) as n_spans, sha256(unhex(coalesce(x.kept, d.h))) as kept_sha256 from d left join x using (doc_id)"""
