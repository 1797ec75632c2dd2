"""MinHash near-duplicates by an inverted join on signature coordinates.

Documents are reduced to the set of their word shingles; equal sets are one class. A signature has
``coordinates`` minima. A pair whose signatures agree in at least ``matches`` coordinates must agree
in one of the first ``coordinates - matches + 1`` (prefix), so only those are posted. Lists are
keyed by (coordinate, value, size class): sets with similarity >= s differ in size by at most 1/s,
hence by at most one class, and other lists are skipped. Every list is first joined with its least
member only, links found so join components, and only lists that still hold several components are
compared pair by pair, in tiles, among members of different components. All links are confirmed on
the full shingle sets, so none is false; one at exactly the threshold is missed with probability
at most ``MISS`` (binomial tail below ``matches``, which is chosen by the threshold: 7.3e-8 for 26 at
0.85, 3.4e-8 for 22 at 0.80). A tile first names the members that have a pair to
confirm, gets their sets, and then confirms its pairs itself and returns a spanning forest, so what
is written grows with the members of a list and not with their pairs.

Defined results: a null text and a text without words have an empty set and no links; a null doc_id
is a document of its own (component null); rows that repeat a doc_id keep their own row, their links
are those of any of the doc_id's texts; empty input gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import WordHashes, among, components, contract, map_rows, map_texts, mix, pick, shingle_hashes, signed, space_words, written

COORDINATES, MATCHES, WIDTH, PERCENT = 48, 26, 5, 85
TILE, TILE_SHINGLES, MISS = 512, 1 << 20, 1e-7
"""Most rows of a tile and, as the members of a list are of like size, most shingles in their sets together."""


def miss_rate(percent: int, coordinates: int, matches: int) -> float:
    """Probability that a pair at exactly the threshold agrees in fewer than ``matches`` coordinates."""
    p = percent / 100
    return sum(math.comb(coordinates, k) * p**k * (1 - p) ** (coordinates - k) for k in range(matches))


def matches_for(percent: int, coordinates: int = COORDINATES) -> int:
    """The most agreements to ask for while the miss rate is at most ``MISS``; one at least."""
    return max([1, *(m for m in range(1, coordinates + 1) if miss_rate(percent, coordinates, m) <= MISS)])


def _coefficients(n: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20240101)
    return (rng.integers(0, 2**63, n, dtype=np.uint64) << np.uint64(1)) | np.uint64(1), rng.integers(0, 2**63, n, dtype=np.uint64)


def _fingerprint(h: np.ndarray) -> tuple[int, int]:
    """128 bits of a set of hashes, in halves."""
    return tuple(np.array([h.sum(dtype=np.uint64), mix(h ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64)]).view(np.int64).tolist())


def sketcher(coordinates: int = COORDINATES, matches: int = MATCHES, width: int = WIDTH):
    """mapInPandas body: (doc_id, text) -> shingle count, 128-bit set fingerprint, the coordinates to
    post, and every coordinate to count agreements by."""
    prefix = coordinates - matches + 1

    def run(batches):
        words, (a, b) = WordHashes(), _coefficients(coordinates)
        for pdf in batches:
            rows = []
            for doc_id, text in zip(pdf["doc_id"], pdf["text"]):
                h = np.unique(shingle_hashes(words.of(space_words(text)), width))
                if not len(h):
                    rows.append((doc_id, 0, None, None, None, None))
                    continue
                low = np.full(coordinates, np.uint64(2**64 - 1))
                for k in range(0, len(h), 2048):  # whole sets, in pieces that stay in cache
                    part = h[k : k + 2048]
                    np.minimum(low, (part[None, :] * a[:, None] + b[:, None]).min(axis=1), out=low)
                sig = (low >> np.uint64(32)).astype(np.uint32)
                rows.append((doc_id, len(h), *_fingerprint(h), sig[:prefix].view(np.int32), sig.astype("<u4").tobytes()))
            yield pd.DataFrame(rows, columns=["doc_id", "n_shingles", "fp1", "fp2", "posted", "sig"]).astype({"doc_id": "Int64", "fp1": "Int64", "fp2": "Int64"})

    return run


def _sets(width: int):
    def run(batches):
        words = WordHashes()
        for pdf in batches:
            sets = [np.unique(shingle_hashes(words.of(space_words(t)), width)) for t in pdf["text"]]
            yield pd.DataFrame({"id": pdf["doc_id"], "fp": [_fingerprint(h)[0] for h in sets], "items": list(map(signed, sets))})

    return run


def _tiles(batches):
    """Whole tile pairs (rows of equal key, i, j, which come sorted), several in one frame; ``g`` numbers them."""
    rest = None
    for pdf in batches:
        t = pdf if rest is None else pd.concat([rest, pdf], ignore_index=True)
        key = t[["key", "i", "j"]].to_numpy()
        new = np.append(True, (key[1:] != key[:-1]).any(axis=1))
        cut = int(np.flatnonzero(new)[-1])
        if cut:
            yield t.iloc[:cut].assign(g=np.cumsum(new[:cut])).reset_index(drop=True)
        rest = t.iloc[cut:]
    if rest is not None and len(rest):
        yield rest.assign(g=0).reset_index(drop=True)


def _pairs(t: pd.DataFrame, matches: int, percent: int):
    """Row numbers (a, b), in blocks, of pairs of one tile pair in different components whose sizes fit,
    whose first common coordinate is this list's, and whose signatures agree often enough.

    Rows are sorted by size within a tile pair, so a row is compared with the next ones while sizes fit."""
    group, n = t["g"].to_numpy(), t["n"].to_numpy()
    sig = np.stack([np.frombuffer(x, "<u4") for x in t["sig"]])
    comp, coord, guest, side = (t[c].to_numpy() for c in ("comp", "coord", "guest", "side"))
    alive, step = np.arange(len(t)), 1
    while len(alive):
        alive = alive[alive + step < len(t)]
        a, b = alive, alive + step
        ok = (group[a] == group[b]) & (n[a] * 100 >= n[b] * percent)
        alive = a = alive[ok]
        b = alive + step
        ok = (comp[a] != comp[b]) & ~(guest[a] & guest[b]) & (side[a] | side[b] == 3)
        a, b = a[ok], b[ok]
        for k in range(0, len(a), 65536):
            x, y = a[k : k + 65536], b[k : k + 65536]
            same = sig[x] == sig[y]
            ok = (same.argmax(axis=1) == coord[x]) & (same.sum(axis=1) >= matches)
            if ok.any():
                yield x[ok], y[ok]
        step += 1


def _involved(matches: int, percent: int):
    """mapInPandas body: the rows of each tile pair that have a pair to confirm."""

    def run(batches):
        for t in _tiles(batches):
            hit = np.zeros(len(t), bool)
            for a, b in _pairs(t, matches, percent):
                hit[a] = hit[b] = True
            yield t.loc[hit].drop(columns="g")

    return run


def _linked(matches: int, percent: int):
    """mapInPandas body: rows of tile pairs with their sets to the forest (u, v) of confirmed links."""

    def run(batches):
        for t in _tiles(batches):
            n, label = t["n"].to_numpy(), np.arange(len(t))
            sets = t["items"].to_numpy()
            for a, b in _pairs(t, matches, percent):
                open_ = label[a] != label[b]
                a, b = a[open_], b[open_]
                common = np.array([len(np.intersect1d(sets[x], sets[y], assume_unique=True)) for x, y in zip(a, b)], np.int64)
                ok = 100 * common >= percent * (n[a] + n[b] - common)
                label = contract(a[ok], b[ok], label)
            rep = t["rep"].to_numpy()
            moved = label != np.arange(len(t))
            yield pd.DataFrame({"u": rep[moved], "v": rep[label[moved]]})

    return run


def _sets_of(ids: DataFrame, docs: DataFrame, width: int) -> DataFrame:
    """(id, fp, items): the different shingle sets of each document named in ids (_id)."""
    return map_texts(among(docs, "doc_id", ids, "_id"), _sets(width), "id long, fp long, items array<long>").dropDuplicates(["id", "fp"])


def _agreeing(matches: int):
    def run(batches):
        for pdf in batches:
            same = np.stack([np.frombuffer(x, "<u4") for x in pdf["sa"]]) == np.stack([np.frombuffer(x, "<u4") for x in pdf["sb"]]) if len(pdf) else np.zeros((0, 1), bool)
            yield pdf.loc[same.sum(axis=1) >= matches, ["a", "b"]]

    return run


def _confirmed(pairs: DataFrame, docs: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) of document ids that are linked on their full shingle sets."""
    ids = pairs.select(F.explode(F.array("a", "b")).alias("_id")).distinct()
    sets = written(_sets_of(ids, docs, width), "sets")
    left, right = sets.selectExpr("id a", "items x"), sets.selectExpr("id b", "items y")  # a pair of ids holds if any two of their sets do
    common = F.size(F.array_intersect("x", "y"))
    return pairs.join(left, "a").join(right, "b").where(100 * common >= percent * (F.size("x") + F.size("y") - common)).select("a", "b")


def links(docs: DataFrame, classes: DataFrame, matches: int, width: int, percent: int) -> DataFrame:
    """Edges (u, v) between class representatives, enough to connect all that similarity links connect.

    classes: rep, n, posted, sig, fp of each distinct shingle set."""
    reps = classes.withColumn("cls", F.floor(F.log(F.col("n").cast("double")) / F.lit(math.log(100 / percent)) + F.lit(1e-9)).cast("int"))
    posts = reps.select("rep", "n", "cls", F.posexplode("posted").alias("coord", "value"))
    posts = posts.select("rep", "n", "coord", F.explode(F.array(F.struct(F.col("cls").alias("c"), F.lit(False).alias("guest")), F.struct((F.col("cls") + 1).alias("c"), F.lit(True).alias("guest")))).alias("at"), "value")
    posts = posts.select(F.xxhash64("coord", "value", "at.c").alias("key"), "rep", "n", "coord", "at.guest")
    lists = posts.groupBy("key").agg(F.min(F.when(~F.col("guest"), F.col("rep"))).alias("hub"), F.count("*").alias("size"), F.max("guest").alias("guests"), F.max("rep").alias("most"), F.min("rep").alias("least"), F.max("n").alias("widest"))
    rows_of_tile = F.greatest(F.lit(1), F.least(F.lit(TILE), F.expr(f"{TILE_SHINGLES} div widest")))
    lists = written(lists.where("hub is not null and most <> least").select((F.col("key") + F.lit(0)).alias("_k"), "hub", F.ceil(F.col("size") / rows_of_tile).cast("int").alias("tiles")), "lists")
    members = written(posts.join(lists, F.col("key") + F.lit(0) == F.col("_k")).select("key", "rep", "coord", "guest", "hub", "tiles"), "members")

    signature = reps.select("rep", "n", "sig")

    def agreeing(p: DataFrame) -> DataFrame:
        x, y = signature.selectExpr("rep a", "n na", "sig sa"), signature.selectExpr("rep b", "n nb", "sig sb")
        sized = p.join(x, "a").join(y, "b").where(F.least("na", "nb") * 100 >= F.greatest("na", "nb") * percent)
        return map_rows(sized.select("a", "b", "sa", "sb"), _agreeing(matches), "a long, b long")

    hubs = members.where("rep <> hub").select(F.least("rep", "hub").alias("a"), F.greatest("rep", "hub").alias("b")).distinct()
    found = written(_confirmed(written(agreeing(hubs), "pairs"), docs, width, percent).selectExpr("a u", "b v"), "links")

    comp = components(found)
    known = members.join(comp, F.col("rep") == F.col("node"), "left").select("key", "rep", "coord", "guest", "tiles", F.coalesce("component", "rep").alias("comp"))
    open_lists = known.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select((F.col("key") + F.lit(0)).alias("_k"))
    left = known.join(open_lists, F.col("key") + F.lit(0) == F.col("_k"), "left_semi")
    tiles = F.col("tiles")
    left = left.withColumn("t", F.pmod(F.xxhash64("rep"), tiles).cast("int"))
    pairs_of_tiles = F.transform(F.sequence(F.lit(0), tiles - 1), lambda o: F.struct(F.least("t", o).alias("i"), F.greatest("t", o).alias("j")))
    left = left.withColumn("p", F.explode(pairs_of_tiles)).select("key", F.col("p.i").alias("i"), F.col("p.j").alias("j"), "rep", "coord", "guest", "comp", F.when(F.col("p.i") == F.col("p.j"), 3).when(F.col("t") == F.col("p.i"), 1).otherwise(2).alias("side"))
    # a doc_id with several sets has several signatures: its own is the one that was posted under the key
    own = F.xxhash64("coord", F.element_at("posted", F.col("coord") + 1), F.col("cls") + F.col("guest").cast("int")) == F.col("key")
    left = left.join(reps.select("rep", "n", "sig", "fp", "posted", "cls"), "rep").where(own).select("key", "i", "j", "rep", "coord", "guest", "comp", "side", "n", "sig", "fp")
    together = lambda df: df.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "n", "rep")
    involved = written(map_rows(together(left), _involved(matches, percent), left.schema), "involved")
    sets = _sets_of(involved.select(F.col("rep").alias("_id")).distinct(), docs, width)
    sets = sets.withColumnRenamed("fp", "_fp")
    whole = together(involved.join(sets, (F.col("rep") == F.col("id")) & (F.col("fp") == F.col("_fp"))).drop("id", "_fp"))
    return found.unionByName(written(map_rows(whole, _linked(matches, percent), "u long, v long"), "more"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT, width: int = WIDTH, coordinates: int = COORDINATES, matches: int | None = None) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of each row of docs; ``matches`` follows from percent if not given."""
    matches = matches_for(percent, coordinates) if matches is None else matches
    own = pick(docs, doc_id=id_col, text=text_col)
    sketches = written(map_texts(own, sketcher(coordinates, matches, width), "doc_id long, n_shingles long, fp1 long, fp2 long, posted array<int>, sig binary"), "sketches")
    full = sketches.where("fp1 is not null and doc_id is not null")
    classes = written(full.groupBy("fp1", "fp2").agg(F.min("doc_id").alias("rep"), F.min("n_shingles").alias("n"), F.min("posted").alias("posted"), F.min("sig").alias("sig")), "classes")
    same = full.select(F.concat_ws(":", "fp1", "fp2").alias("k"), "doc_id")
    dealt = classes.select(F.concat_ws(":", "fp1", "fp2").alias("k"), "rep")
    equal = same.join(dealt, "k").where("doc_id <> rep").selectExpr("doc_id u", "rep v")
    between = links(own, classes.select("rep", "n", "posted", "sig", F.col("fp1").alias("fp")), matches, width, percent)
    comp = components(equal.unionByName(between))
    joined = sketches.join(comp, F.col("doc_id") == F.col("node"), "left")
    component = F.coalesce("component", "doc_id")
    return joined.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


ORACLE = r"""
with recursive w as (select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents),
s as (select distinct doc_id, hash(sh) as sh from (select doc_id, unnest(case when len(w) >= 5 then list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))
  when len(w) > 0 then [array_to_string(w, ' ')] else [] end) as sh from w)),
n as (select doc_id, count(*) as n from s group by 1),
p as (select a.doc_id as a, b.doc_id as b, count(*) as k from s a join s b on a.sh = b.sh and a.doc_id < b.doc_id group by 1, 2),
l as (select a, b from p join n x on x.doc_id = a join n y on y.doc_id = b where 100 * k >= 85 * (x.n + y.n - k)),
e as (select a, b from l union all select b, a from l),
r(a, b) as (select doc_id, doc_id from documents union select r.a, e.b from r join e on r.b = e.a),
c as (select a, min(b) as component_id from r group by 1)
select d.doc_id, coalesce(n.n, 0) as n_shingles, c.component_id, d.doc_id = c.component_id as kept
from documents d join c on c.a = d.doc_id left join n on n.doc_id = d.doc_id"""
