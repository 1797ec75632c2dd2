"""Every operator on awkward rows, against plain versions of its contract."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from comovement.llm import decontaminate, hilbert, langid, licenses, minhash, packing, preference, suffixes, vectors, warc
from comovement.llm.shared import components

DOCS = "doc_id long, text string, lang string, source string, n_chars long, d long, part string, `rank` int, `key` string, kept string"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


def prose(seed: int, n: int) -> str:
    rng = np.random.default_rng(seed)
    return " ".join(f"{WORDS[i]}{j}" for i, j in zip(rng.integers(0, 20, n), rng.integers(0, 50, n)))


def awkward():
    base = prose(1, 120)
    near = base.split()
    near[60] = "changed"
    far = base.split()
    far[::9] = ["other"] * len(far[::9])
    passage = prose(9, 60)
    texts = [
        base, base, base.upper(), " ".join(near), " ".join(far), None, "", "   \n\t", "one", "one two three", "one two three", "Ünïcode — ünï \U0001f600 words of all kinds here",
        "x" * 200_000, prose(2, 20_000), f"{prose(3, 40)}\n{passage}\n{prose(4, 40)}", f"{prose(5, 30)}\n{passage}\n{prose(6, 30)}", "aa" * 300, passage, "12345 67890 !!! ???", "é" * 150, "ab" * 80,
        "SPDX-License-Identifier: (MIT OR GPL-2.0-only WITH Classpath-exception-2.0) AND BSD-3-Clause\nLicensed under the Apache License; CC BY 4.0, cc-by. MIT License mit license",
    ]
    rows = [(i, t, ["en", "fr", None][i % 3], [f"s{i % 2}", None][i % 5 == 4], len(t or "")) for i, t in enumerate(texts)]
    rows += [(3, rows[3][1], "en", "s", 1), (None, base, "en", "s", 2), (None, None, None, None, None)]
    return [(*r, 1, "p", 2, "k", "x") for r in rows]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(awkward(), DOCS).repartition(3).cache()


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], DOCS)


def lower(b: bytes) -> bytes:
    return bytes(x + 32 if 65 <= x <= 90 else x for x in b)


def test_minhash_against_brute_force(docs, nothing):
    got = minhash.near_duplicates(docs).collect()
    assert len(got) == docs.count() and minhash.near_duplicates(nothing).count() == 0
    sets = {}
    for r in awkward():
        w = lower((r[1] or "").encode()).split()
        if r[0] is not None:
            sets[r[0]] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())
    top = {i: i for i in sets}
    changed = True
    while changed:
        changed = False
        for i, a in sets.items():
            for j, b in sets.items():
                if a and b and 100 * len(a & b) >= 85 * len(a | b) and top[i] < top[j]:
                    top[j], changed = top[i], True
    for r in got:
        if r.doc_id is not None:
            assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), top[r.doc_id], top[r.doc_id] == r.doc_id), r
        else:
            assert r.component_id is None and r.kept


def test_minhash_large_group_of_near_copies(spark):
    base = prose(11, 150).split()
    rng = np.random.default_rng(3)
    rows = []
    for i in range(700):
        w = list(base)
        for k in rng.integers(0, 150, int(rng.integers(0, 5))):
            w[k] = f"edit{i}x{k}"
        rows.append((i, " ".join(w)))
    got = {r.doc_id: r.component_id for r in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in (t.split() for _, t in rows)]
    label = list(range(700))
    for i in range(700):
        for j in range(i):
            if label[i] != label[j] and 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j]):
                lo, hi = sorted((label[i], label[j]))
                label = [lo if x == hi else x for x in label]
    assert [got[i] for i in range(700)] == label


def test_minhash_asks_for_agreements_by_the_threshold():
    assert minhash.matches_for(85) == minhash.MATCHES == 26 and minhash.matches_for(80) == 22
    assert minhash.miss_rate(80, 48, 22) < minhash.MISS < minhash.miss_rate(80, 48, 26)


def test_minhash_first_common_coordinate_is_that_of_whole_values():
    import pandas as pd

    a = np.arange(48, dtype="<u4") + 70_000
    b = a.copy()
    b[0] ^= np.uint32(1 << 20)  # differs, but not in its low 16 bits
    rows = [(0, 100, x.tobytes(), k, 1, False, 3) for k, x in enumerate((a, b))]
    t = pd.DataFrame(rows, columns=["g", "n", "sig", "comp", "coord", "guest", "side"])
    assert [(x.tolist(), y.tolist()) for x, y in minhash._pairs(t, 26, 85)] == [([0], [1])]


def removed(texts: list[bytes], length: int = 100):
    seen, out = set(), []
    for b in texts:
        mask = bytearray(len(b))
        for p in range(len(b) - length + 1):
            w = b[p : p + length]
            if w in seen:
                mask[p : p + length] = b"\1" * length
            seen.add(w)
        out.append((sum(mask), sum(mask[k] and not (k and mask[k - 1]) for k in range(len(mask))), hashlib.sha256(bytes(x for x, m in zip(b, mask) if not m)).hexdigest()))
    return out


def test_suffixes_against_brute_force(docs, nothing):
    assert suffixes.remove_repeats(nothing).count() == 0
    own = sorted({(r[0], r[1]) for r in awkward()}, key=lambda x: (x[0] is not None, x[0] or 0, hashlib.md5((x[1] or "").encode()).hexdigest()))
    expected = {(i, hashlib.sha256((t or "").encode()).hexdigest()): x for (i, t), x in zip(own, removed([(t or "").encode() for _, t in own]))}
    got = suffixes.remove_repeats(docs).collect()
    assert Counter((r.doc_id, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == Counter((r[0], *expected[r[0], hashlib.sha256((r[1] or "").encode()).hexdigest()]) for r in awkward())


def test_suffixes_random_repeats(spark):
    rng = np.random.default_rng(5)
    parts = ["".join(rng.choice(list("abcdé "), int(n))) for n in rng.integers(20, 260, 30)]
    texts = ["".join(parts[k] for k in rng.integers(0, 30, int(m))) for m in rng.integers(1, 12, 120)]
    got = suffixes.remove_repeats(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)).collect()
    assert [(r.n_removed, r.n_spans, r.kept_sha256) for r in sorted(got)] == removed([t.encode() for t in texts])


def test_loser_tree_merges_and_knows_prefixes():
    rng = np.random.default_rng(7)
    for k in (1, 2, 3, 7, 16):
        runs = [sorted(bytes(rng.choice(list(b"ab"), int(n))) for n in rng.integers(0, 12, int(m))) for m in rng.integers(0, 30, k)]
        out = list(suffixes.merged([suffixes.decoded(*suffixes.front_coded(r)) for r in runs]))
        assert [s for _, s, _ in out] == sorted(s for r in runs for s in r)
        for (_, a, _), (_, b, n) in zip(out, out[1:]):
            assert n == suffixes.common_prefix(a, b)


def test_licenses_against_brute_force(docs, nothing):
    assert licenses.scan(nothing).count() == 0
    pattern = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    for r in licenses.scan(docs).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score").join(docs.select("doc_id", "text").distinct(), "doc_id").collect():
        words = pattern.findall(lower((r.text or "").encode()).decode())
        at = [(k, label) for k in range(len(words)) for phrase, label in licenses.BASE_PHRASES.items() if words[k : k + len(phrase.split())] == phrase.split()]
        assert (r.n_words, r.n_base) == (len(words), len(at))
        assert (r.first_word, r.last_word) == (min((k for k, _ in at), default=None), max((k for k, _ in at), default=None))
        assert r.base_labels == ",".join(sorted({label for _, label in at})) and set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1


def test_licence_labels_against_a_plain_version(spark):
    tags = ["SPDX-License-Identifier: GPL-3.0-only\nx\nspdx-license-identifier: MIT", "SPDX-License-Identifier: MIT\n# SPDX-License-Identifier: Apache-2.0 OR GPL-2.0+", "SPDX-License-Identifier: (MIT", "SPDX-License-Identifier: 0BSD\nSPDX-License-Identifier: (oops", "no tag: MIT"]
    phrases = [*licenses.BASE_PHRASES, *licenses.NOTICES]
    texts = tags + [f"{prose(i, 5)} {phrases[i % len(phrases)].title()}, {phrases[3 * i % len(phrases)]} {prose(i, 3)}" for i in range(40)]
    names = [["gpl-3.0-only", "mit"], ["mit", "apache-2.0", "gpl-2.0+"], ["mit"], ["0bsd", "oops"], []]
    rows = {r.doc_id: r for r in licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [rows[i].expressions for i in range(5)] == [["gpl-3.0-only", "mit"], ["mit", "apache-2.0 gpl-2.0+ or"], [], ["0bsd"], None]
    assert [rows[i].permissive for i in range(5)] == [False, True, False, False, None]
    for i, text in enumerate(texts):
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text.lower())
        at = sorted((k, label, len(p.split())) for p, label in (licenses.BASE_PHRASES | licenses.NOTICES).items() for k in range(len(words)) if words[k : k + len(p.split())] == p.split())
        own = names[i] if i < 5 else []
        assert rows[i].labels == ",".join(sorted({label for _, label, _ in at} | set(own)))
        assert sorted((s.first_word, s.label, s.n_words) for s in rows[i].spans) == at
        assert rows[i].score == 1 - 0.5 ** min(50, len(at) + 2 * len(own))


def test_licence_expressions():
    names, postfix = licenses.parse_expression("(MIT OR GPL-2.0-only WITH Classpath-exception-2.0) AND BSD-3-Clause")
    assert names == ["mit", "gpl-2.0-only", "bsd-3-clause"] and licenses.permits(postfix)
    assert not licenses.permits(licenses.parse_expression("MIT AND GPL-3.0-only")[1])
    assert licenses.permits(licenses.parse_expression("GPL-3.0-only OR MIT AND ISC")[1])
    assert licenses.parse_expression("MIT OR")[1] is None and licenses.parse_expression("(MIT")[1] is None and licenses.parse_expression("")[1] is None


def test_language_by_held_out_accuracy_and_spans(spark, docs, nothing, sf_dir):
    table = spark.read.parquet(f"{sf_dir}/documents.parquet")
    held = langid.identify(table, table).where("held_out").join(table.select("doc_id", "lang"), "doc_id")
    assert held.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.97
    model = langid.fit(table)
    mixed = " ".join(r.text for r in table.where("lang = 'en' and n_chars > 400").orderBy("doc_id").limit(1).collect() + table.where("lang = 'de' and n_chars > 400").orderBy("doc_id").limit(1).collect())
    spans = langid.predict(spark.createDataFrame([(1, mixed)], "doc_id long, text string"), model).first().spans
    assert [s.lang for s in spans] == ["en", "de"]
    rows = {r.doc_id: r for r in langid.predict(docs, model).collect() if r.doc_id is not None}
    assert len(rows) == len({r[0] for r in awkward() if r[0] is not None})
    assert all(rows[i].lang_pred == "und" and rows[i].score == 0 for i in (5, 6, 7, 18)) and all(0 <= r.score <= 1 for r in rows.values())
    assert langid.identify(nothing, nothing).count() == 0 and langid.identify(docs, nothing).where("lang_pred <> 'und'").count() == 0


def test_language_against_a_plain_version(spark, sf_dir):
    """Counts, scores and the full lattice in plain Python, on every document."""
    table = spark.read.parquet(f"{sf_dir}/documents.parquet")
    docs = [(r.doc_id, r.text, r.lang) for r in table.collect()] + [(10**7 + i, t, None) for i, t in enumerate(["και το είναι", "ab" * 20, "1 2 3", "Straße — naïve façade", ""])]
    got = {r.doc_id: r for r in langid.identify(spark.createDataFrame(docs, "doc_id long, text string, lang string"), table).collect()}

    def words(text):
        out, word = [], ""
        for c in (text or "").lower() + " ":
            if c.isalpha():
                word += c
            elif word:
                out.append(f" {word} ")
                word = ""
        return out

    def slots(word):
        for a, b, c in zip(word, word[1:], word[2:]):
            h = (ord(a) * 0x85EBCA6B + ord(b) * 0xC2B2AE35 + ord(c) * 0x27D4EB2F) % 2**32
            yield ((h ^ h >> 15) * 0x2C1B3C6D % 2**32) >> 32 - langid.BITS

    def script(word):
        return [name for start, name in langid.SCRIPTS.items() if start <= ord(word[1])][-1]

    grams, scripts = defaultdict(Counter), defaultdict(Counter)
    for doc_id, text, lang in docs:
        if lang is not None and text is not None and zlib.crc32(str(doc_id).encode()) % 3 != 1:
            for w in words(text):
                grams[lang].update(slots(w))
                scripts[lang][script(w)] += 1
    langs = sorted(grams)
    total = {k: sum(grams[k].values()) for k in langs}
    uses = {k: {s for s, n in scripts[k].items() if n >= max(1, 0.01 * sum(scripts[k].values()))} for k in langs}
    for doc_id, text, _ in docs:
        rows, known = [], []
        for w in words(text):
            may = [k for k in langs if script(w) in uses[k]]
            known.append(bool(may))
            s = {k: sum(np.log((grams[k][x] + 0.1) / (total[k] + 0.1 * 2**langid.BITS)) for x in slots(w)) for k in may}
            top = max(s.values(), default=0)
            rows.append([max(-6.0, s[k] - top) if k in s else -6.0 for k in langs] if may else [0.0] * len(langs))
        r = got[doc_id]
        assert r.held_out == (zlib.crc32(str(doc_id).encode()) % 3 == 1)
        if not rows:
            assert (r.lang_pred, r.score) == ("und", 0.0)
            continue
        if not any(known):
            assert r.score == 0.05
            continue
        best, back = rows[0], []
        for row in rows[1:]:
            top = max(best)
            back.append([k if v >= top - 6.0 else best.index(top) for k, v in enumerate(best)])
            best = [max(v, top - 6.0) + x for v, x in zip(best, row)]
        labels = [best.index(max(best))]
        for step in reversed(back):
            labels.append(step[labels[-1]])
        labels.reverse()
        letters = Counter()
        for k, w in zip(labels, words(text)):
            letters[k] += len(w) - 2
        k = max(letters, key=lambda x: (letters[x], -x))
        mine = [row for row, x in zip(rows, labels) if x == k]
        rival = max(sum(row[j] for row in mine) for j in range(len(langs)) if j != k)
        sure = 1 - np.exp(min(0.0, rival - sum(row[k] for row in mine)))
        assert r.lang_pred == langs[k] and r.score == pytest.approx(letters[k] / sum(letters.values()) * (0.05 + 0.95 * sure), abs=1e-3)


def test_language_with_one_language_and_private_code_points(spark):
    docs = spark.createDataFrame([(i, prose(i, 8), "en") for i in range(9)], "doc_id long, text string, lang string")
    asked = spark.createDataFrame([(1, prose(50, 8)), (2, "\U000f0000\U000f0001"), (3, "\U00020000\U00020001"), (4, "\U0001e900\U0001e901")], "doc_id long, text string")
    found = {r.doc_id: (r.lang_pred, r.score) for r in langid.predict(asked, langid.fit(docs)).collect()}
    assert found[1] == ("en", 1.0) and found[2] == ("und", 0.0) and found[3] == found[4] == ("en", 0.05)
    assert langid.bits_for(4) == langid.BITS and langid.bits_for(2000) < langid.BITS


def test_language_sample_has_every_language(spark):
    greek = "και το είναι που δεν θα για με τον στην από"
    rows = [(i, prose(i, 8), "en") for i in range(3000)] + [(5000 + i, greek, "el") for i in range(5)]
    model = langid.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"), sample=30, bits=10)
    found = langid.predict(spark.createDataFrame([(1, greek), (2, prose(9999, 8))], "doc_id long, text string"), model).collect()
    assert {r.doc_id: r.lang_pred for r in found} == {1: "el", 2: "en"} and all(r.score > 0.9 for r in found)
    # rows of one doc_id share a hash, and so stand or fall together
    trained = next(i for i in range(7000, 7100) if zlib.crc32(str(i).encode()) % 3 != 1)
    one = langid.fit(spark.createDataFrame([(i, prose(i, 8), "en") for i in range(20)] + [(trained, greek, "el")] * 500, "doc_id long, text string, lang string"), sample=1, bits=10)
    assert one["languages"] == ["el", "en"] and one["uses"].any(axis=1).all()


def test_language_learns_more_than_a_thousand(spark):
    rows = [(3 * k + i, f"{WORDS[k % 20]}", f"l{k:04}") for k in range(1100) for i in range(3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    labelled = {r.lang for r in docs.where(langid.training_part()).select("lang").distinct().collect()}
    model = langid.fit(docs, bits=8)
    assert len(labelled) > 1000 and set(model["languages"]) == labelled and model["uses"].any(axis=1).all()


def test_language_knows_letters_of_the_second_plane(spark):
    gothic, bold = "\U00010330\U00010331 \U00010332\U00010333\U00010334 " * 5, "\U0001d400\U0001d401 \U0001d402"
    rows = [(i, gothic, "got") for i in range(9)] + [(20 + i, prose(i, 8), "en") for i in range(9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    found = {r.doc_id: r for r in langid.predict(spark.createDataFrame([(1, gothic), (2, bold), (3, "\U0001f600 \U0001f600")], "doc_id long, text string"), langid.fit(docs, bits=10)).collect()}
    assert found[1].lang_pred == "got" and found[1].score > 0.9
    assert found[2].lang_pred != "und" and found[2].score > 0 and (found[3].lang_pred, found[3].score) == ("und", 0.0)


def test_viterbi_equals_plain_lattice():
    rng = np.random.default_rng(2)
    texts = [np.minimum(0, rng.normal(-2, 3, (int(rng.integers(1, 60)), 3))) for _ in range(300)]
    for s in texts:
        labels, total = langid.viterbi(s, 4.0), [list(s[0])]
        for row in s[1:]:
            total.append([max(total[-1][k], max(total[-1]) - 4.0) + row[k] for k in range(3)])
        value = s[np.arange(len(s)), labels].sum() - 4.0 * (labels[1:] != labels[:-1]).sum()
        assert value == pytest.approx(max(total[-1]))


def test_decontamination_finds_planted_items(spark, docs, nothing):
    items = [(1, prose(20, 30)), (2, prose(21, 12)), (3, "two words"), (4, None), (5, ""), (6, prose(22, 60))]
    bench = spark.createDataFrame(items, "item_id long, text string")
    edited = prose(20, 30).split()
    edited[15] = "edited"
    texts = [f"{prose(30, 50)} {prose(20, 30).upper()}! {prose(31, 50)}", f"{prose(32, 9)} {' '.join(edited)}", f"{prose(33, 4)} two words", prose(21, 12), prose(34, 500), f"{prose(22, 60)[:150]} {prose(35, 40)}"]
    got = decontaminate.leaks(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), bench).collect()
    assert {(r.doc_id, r.item_id) for r in got} == {(0, 1), (1, 1), (2, 3), (3, 2)}
    assert decontaminate.leaks(docs, bench).count() == 0 and decontaminate.leaks(nothing, bench).count() == 0
    assert decontaminate.leaks(docs, bench.where("false")).count() == 0
    assert decontaminate.clean(docs, bench).count() == docs.count()


def hashed(text: str) -> np.ndarray:
    return decontaminate.WordHashes().of(decontaminate.words_of(text))


def shares(item: str, text: str) -> list[float]:
    """Share of an item in its window at each start, by plain counting."""
    w, t = hashed(item), hashed(text)
    shingles = Counter(decontaminate.shingle_hashes(w, 5).tolist())
    rows = [Counter(decontaminate.shingle_hashes(t[a : a + len(w)], 5).tolist()) for a in range(max(1, len(t) - len(w) + 1))] if len(t) >= min(5, len(w)) else []
    return [sum((shingles & r).values()) / sum(shingles.values()) for r in rows]


def found(index, text: str) -> dict:
    return {m[0]: m[1:4] for m in decontaminate.matches(index, hashed(text), 5, 0.8, decontaminate.RADIUS)}


def test_decontamination_looks_at_every_start():
    item = prose(40, 40).split()
    index = decontaminate.Index([(1, " ".join(item))])
    assert found(index, f"{prose(41, 50)} {' '.join(item[20:] + item[:20])} {prose(42, 50)}") == {1: (32 / 36, 50, 40)}


def test_decontamination_against_brute_force():
    """Recall and precision over all windows and items; texts of few words too, so that shingles repeat and count."""
    rng = np.random.default_rng(12)
    caught = due = 0
    for few in (3, 400):
        items = [" ".join(f"w{x}" for x in rng.integers(0, few, int(n))) for n in rng.integers(5, 45, 60)]
        index = decontaminate.Index(list(enumerate(items)))
        for _ in range(60):
            text = []
            for k in rng.permutation(60)[:3]:
                copy = items[k].split()
                for at in rng.integers(0, len(copy), int(rng.integers(0, 3))):
                    copy[at] = f"w{rng.integers(0, few)}"
                text += [*(f"w{x}" for x in rng.integers(0, few, 6)), *np.roll(copy, int(rng.integers(0, 2)) * int(rng.integers(0, 9))).tolist()]
            got = found(index, " ".join(text))
            best = {k: s for k, item in enumerate(items) for s in [shares(item, " ".join(text))] if s}
            expected = {k: (max(s), s.index(max(s))) for k, s in best.items() if max(s) >= 0.8}
            assert set(got) <= set(expected)
            caught += sum(got.get(k, (0, 0))[:2] == v for k, v in expected.items())
            due += len(expected)
    assert due > 150 and caught / due > 0.97


def test_decontamination_compares_few_items_of_a_random_window():
    rng = np.random.default_rng(3)
    index = decontaminate.HammingIndex(np.stack([decontaminate.simhash(rng.integers(0, 2**63, 40, dtype=np.uint64)) for _ in range(6000)]))
    asked = np.stack([decontaminate.simhash(rng.integers(0, 2**63, 40, dtype=np.uint64)) for _ in range(50)])
    assert len(index.candidates(asked, decontaminate.RADIUS)[0]) < 0.05 * 50 * 6000


def test_hamming_index_is_complete():
    rng = np.random.default_rng(4)
    for n in (30, 6000):  # few values are compared one by one, of many the near ones are enumerated
        prints = rng.integers(0, 2**16, (n, 8)).astype(np.uint16)
        asked = prints[rng.integers(0, n, 60)].copy()
        for row, flips in zip(asked, rng.integers(0, 45, 60)):
            for bit in rng.permutation(128)[:flips]:
                row[bit // 16] ^= np.uint16(1 << bit % 16)
        apart = np.bitwise_count(asked[:, None] ^ prints[None]).sum(axis=2)
        for radius in (0, 3, 20, 37):
            x, k, distance = decontaminate.HammingIndex(prints).near(asked, radius)
            assert set(zip(x.tolist(), k.tolist())) == set(zip(*map(np.ndarray.tolist, np.nonzero(apart <= radius)))) and (distance == apart[x, k]).all()


def test_decontamination_of_texts_shorter_than_the_item():
    item = prose(43, 30).split()
    index = decontaminate.Index([(1, " ".join(item))])
    got = {n: found(index, " ".join(item[:n])) for n in (30, 27, 25, 24, 4, 0)}
    assert got[30] == {1: (1.0, 0, 30)} and got[27] == {1: (23 / 26, 0, 27)} and got[25] == {1: (21 / 26, 0, 25)}
    assert not got[24] and not got[4] and not got[0]
    assert found(index, " ".join(item[2:28])) == {1: (22 / 26, 0, 26)}


def test_decontamination_keeps_clashing_columns(spark):
    docs = spark.createDataFrame([(1, prose(20, 30), 7, "a", 1), (2, prose(30, 30), 7, "b", 2), (None, prose(20, 30), 7, "c", 3), (None, None, 7, "d", 4)], "doc_id long, text string, _leak int, leak string, item_id long")
    bench = spark.createDataFrame([(1, prose(20, 30), "x", 5), (1, prose(20, 30), "x", 5), (None, prose(23, 30), "y", 5)], "item_id long, text string, similarity string, doc_id long")
    assert [r.doc_id for r in decontaminate.clean(docs, bench).collect()] == [2] and decontaminate.clean(docs, bench).columns == docs.columns


def test_packing_is_whole_and_tight(docs, nothing):
    import public_tokenizers as tokens
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokens.path("byte_bpe_50k.json"))
    assert packing.pack(nothing).count() == 0
    got = packing.pack(docs).collect()
    expected = Counter()
    for r in awkward():
        ids = np.array([*t.encode(r[1] or "", add_special_tokens=False).ids, 1], "<u4")
        for at in range(0, len(ids), 2048):
            expected[r[0], at, len(ids[at : at + 2048]), zlib.crc32(ids[at : at + 2048].tobytes()), len(ids)] += 1
    assert Counter((r.doc_id, r.start, r.length, r.ids_crc32, r.doc_tokens) for r in got) == expected
    rows = defaultdict(list)
    for r in got:
        rows[r.sequence_id].append((r.offset, r.length))
    for pieces in rows.values():
        end = 0
        for offset, length in sorted(pieces):
            assert offset == end
            end += length
        assert end <= 2048


def test_packing_gives_the_ids_of_the_json_form(spark):
    import public_tokenizers as tokens
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokens.path("byte_bpe_50k.json"))
    texts = ["a<|endoftext|>b", "<|endoftext|>", " <|endoftext|><|endoftext|> end", "hello <|endoftext|> world", "x  \n <|endoftext|>\n\n  y", "<|endoftext|", "plain  text 123's", "é\u00a0ü \U0001f600"]
    ids = {i: np.array([*t.encode(x, add_special_tokens=False).ids, 1], "<u4") for i, x in enumerate(texts)}
    assert 50256 in ids[0]
    got = packing.pack(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    assert {r.doc_id: (r.doc_tokens, r.ids_crc32) for r in got} == {i: (len(x), zlib.crc32(x.tobytes())) for i, x in ids.items()}
    plain = packing.encoder(tokens.path("byte_bpe_50k.tiktoken"), tokens.PATTERN)
    assert 50256 not in plain(texts[0])


def test_packing_plan_uses_every_length():
    rng = np.random.default_rng(6)
    for _ in range(20):
        histogram = {int(k): int(v) for k, v in zip(rng.integers(1, 65, 30), rng.integers(1, 1000, 30))}
        plan = packing.plan(histogram, 64)
        used = Counter()
        for count, lengths in plan:
            assert sum(lengths) <= 64 and list(lengths) == sorted(lengths, reverse=True)
            for x in lengths:
                used[x] += count
        assert used == histogram


def test_hilbert_shards(spark, docs, nothing):
    assert hilbert.shard(nothing).count() == 0
    rows = hilbert.shard(docs).collect()
    sizes = Counter(r.shard for r in rows)
    assert sum(sizes.values()) == docs.count() and max(sizes.values()) - min(sizes[k] for k in range(16)) <= 1
    for k, n in sizes.items():
        assert sorted(r.slot for r in rows if r.shard == k) == list(range(n))
    texts = Counter((r[0], len((r[1] or "").encode()) + 1, zlib.crc32((r[1] or "").encode())) for r in awkward())
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in rows) == texts
    assert hilbert.zones(hilbert.shard(docs)).count() == len(sizes)


def plain_curve(axes: list[int], bits: int) -> int:
    """Position on the curve by the usual transposition, one axis at a time in plain integers."""
    x, m = list(axes), 1 << bits - 1
    q = m
    while q > 1:
        p = q - 1
        for i in range(len(x)):
            if x[i] & q:
                x[0] ^= p
            else:
                t = (x[0] ^ x[i]) & p
                x[0] ^= t
                x[i] ^= t
        q >>= 1
    for i in range(1, len(x)):
        x[i] ^= x[i - 1]
    t, q = 0, m
    while q > 1:
        if x[-1] & q:
            t ^= q - 1
        q >>= 1
    x = [v ^ t for v in x]
    return int("".join(str(v >> b & 1) for b in range(bits - 1, -1, -1) for v in x), 2)


def test_hilbert_placement_against_a_plain_version(spark, sf_dir):
    """Codes by rank, curve positions in plain integers, and shards as equal runs of the sorted positions."""
    rng = np.random.default_rng(7)
    many = [(i, "x" * int(2 ** rng.integers(0, 14)), f"l{rng.integers(0, 5)}", [f"site{rng.integers(0, 90):02}", None][i % 11 == 0]) for i in range(700)]
    for table in (spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.createDataFrame(many, "doc_id long, text string, lang string, source string")):
        docs = {r.doc_id: r for r in table.select("doc_id", "text", "lang", "source").collect()}
        codes = {}
        for c in ("source", "lang"):
            values = sorted({r[c] for r in docs.values() if r[c] is not None})
            k = min(31, len(values))
            codes[c] = {v: 1 + i * k // len(values) for i, v in enumerate(values)} | {None: 0}
        sharded = hilbert.shard(table)
        rows = sorted(sharded.collect(), key=lambda r: (r.shard, r.slot))
        assert len(rows) == len(docs)
        for r in rows:
            d = docs[r.doc_id]
            axes = [codes["source"][d.source], codes["lang"][d.lang], min(31, (len((d.text or "").encode()) + 1).bit_length() - 1)]
            assert [r.source_code, r.lang_code, r.size_code, r.curve] == [*axes, plain_curve(axes, 5)]
        assert [r.curve for r in rows] == sorted(r.curve for r in rows)
        assert [r.shard for r in rows] == [k * 16 // len(rows) for k in range(len(rows))]
        # a zone that the box of a shard leaves out holds no row of a value
        boxes = hilbert.zones(sharded).collect()
        probe = rows[len(rows) // 3].source
        may = {b.shard for b in boxes if probe is not None and b.min_source is not None and b.min_source <= probe <= b.max_source}
        assert {r.shard for r in rows if r.source == probe and probe is not None} <= may and (len(may) < 16 or probe is None)


@pytest.mark.parametrize("bits", [1, 2, 3])
def test_hilbert_curve_steps_by_one(spark, bits):
    n = 1 << bits
    cells = spark.range(n**3).selectExpr(f"id div {n * n} a", f"id div {n} % {n} b", f"id % {n} c")
    path = cells.select("a", "b", "c", hilbert.curve_index([F.col("a"), F.col("b"), F.col("c")], bits).alias("h")).orderBy("h").collect()
    assert [r.h for r in path] == list(range(n**3))
    assert all(abs(x.a - y.a) + abs(x.b - y.b) + abs(x.c - y.c) == 1 for x, y in zip(path, path[1:]))


def test_vectors_against_brute_force(spark):
    rng = np.random.default_rng(8)
    centres = rng.normal(size=(40, 24))
    x = np.concatenate([centres[rng.integers(0, 40, 500)] + rng.normal(size=(500, 24)) * rng.choice([0.05, 0.25, 0.45], (500, 1)), centres[:5], centres[:5] * 3]).astype(np.float32)
    rows = [(i, v.tolist(), "a", 1) for i, v in enumerate(x)] + [(600, None, "a", 1), (601, [0.0] * 24, "a", 1), (602, [float("nan")] * 24, "a", 1), (603, [1.0] * 3, "a", 1), (604, [], "a", 1), (None, x[0].tolist(), "a", 1), (605, [None] * 24, "a", 1), (606, [float("inf")] * 24, "a", 1)]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>, rep string, d int")
    for tile in (16384, 60):
        got = {r.vec_id: r for r in vectors.near_duplicates(table, tile=tile).collect()}
        assert len(got) == len(rows)
        y = x.astype(float)
        length = np.sqrt((y * y).sum(axis=1))
        near = y @ y.T >= 0.9 * length[:, None] * length[None]
        np.fill_diagonal(near, False)
        label = np.arange(len(x))
        while True:
            new = np.array([min(label[i], label[near[i]].min(initial=label[i])) for i in range(len(x))])
            if (new == label).all():
                break
            label = new
        for i in range(len(x)):
            assert (got[i].n_links, got[i].component_id, got[i].kept) == (near[i].sum(), label[i], label[i] == i)
        assert all(got[i].n_links == 0 and got[i].kept for i in (600, 601, 602, 603, 604, 605, 606, None))
    assert vectors.near_duplicates(table.where("false")).count() == 0


def test_vectors_of_one_id_have_links_of_their_own(spark):
    rows = [(1, [1.0, 0.0, 0.0, 0.0]), (1, [0.0, 1.0, 0.0, 0.0]), (2, [1.0, 0.01, 0.0, 0.0]), (3, [1.0, 0.0, 0.01, 0.0]), (4, [0.0, 0.0, 0.0, 1.0])]
    got = vectors.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    assert sorted((r.vec_id, r.n_links, r.component_id, r.kept) for r in got) == [(1, 0, 1, True), (1, 2, 1, True), (2, 2, 1, False), (3, 2, 1, False), (4, 0, 4, True)]


def test_warc_reads_in_tasks_of_a_size(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(warc, "BIN_BYTES", 2000)
    pages = spark.createDataFrame([(i, f"u{i}", prose(i, 40 + i % 7 * 30)) for i in range(120)], "page_id long, url string, html string")
    index = warc.write(pages.repartition(3), str(tmp_path / "w"))
    back = warc.read(index, str(tmp_path / "w"))
    n = index.agg({"length": "sum"}).first()[0]
    assert back.rdd.getNumPartitions() == -(-n // 2000) and back.count() == 120


def test_warc_round_trip(spark, tmp_path):
    big, rows = "<p>" + "é" * 700, [(1, "u1", "short"), (2, "u2", "short")]
    rows += [(3, "u\r\n3", big), (4, None, big), (5, "u5", None), (6, "u6", "x" * 3_000_000), (5, "u5", big), (5, "u5", big), (None, "n", big), (7, "u7", "")]
    pages = spark.createDataFrame([(*r, "c", 1) for r in rows], "page_id long, url string, html string, digest string, first int")
    folder = str(tmp_path / "w")
    index = warc.write(pages.repartition(2), folder)
    back = warc.read(index, folder, with_payload=True).collect()
    first = {hashlib.sha1(big.encode()).hexdigest(): 5}
    expected = Counter()
    for page_id, _, html in rows:
        b = (html or "").encode()
        f = first.get(hashlib.sha1(b).hexdigest())
        revisit = f is not None and f != page_id
        expected[page_id, len(b), hashlib.sha1(b).hexdigest(), "revisit" if revisit else "response", f if revisit else None, None if revisit else b] += 1
    assert Counter((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to, None if r.payload is None else bytes(r.payload)) for r in back) == expected
    assert {r.url for r in back} == {u or "" for _, u, _ in rows}
    one = warc.read(index.where("page_id = 6"), folder).collect()
    assert [r.page_id for r in one] == [6] and warc.round_trip(pages.where("false")).count() == 0


def test_preference_prefix_and_masks(spark):
    turns = [(0, 0, "user", "hi"), (0, 1, "assistant", "a"), (0, 2, "user", "q"), (1, 0, "user", "hi"), (1, 1, "assistant", "a"), (1, 2, "user", "z"), (1, 3, "assistant", None), (2, 0, "user", "x"), (4, 0, None, "same"), (5, 0, None, "same"), (None, 0, "user", "lost"), (6, None, "user", "lost")]
    table = spark.createDataFrame([(*t, 9) for t in turns], "conv_id long, turn long, role string, text string, pair_id int")
    got = {r.pair_id: r for r in preference.by_neighbours(table).collect()}
    assert set(got) == {0, 1, 2}
    assert got[0].n_prefix == 2 and got[0].prompt == "<|user|>\nhi<|end|>\n<|assistant|>\na<|end|>\n" and got[0].chosen == "<|user|>\nq<|end|>\n"
    assert got[0].rejected_runs == "-9,-9,-14,8"
    assert (got[1].n_prefix, got[1].rejected, got[1].chosen) == (0, None, "<|user|>\nx<|end|>\n")
    assert (got[2].n_prefix, got[2].chosen, got[2].rejected) == (1, "", "")
    assert preference.by_neighbours(table.where("false")).count() == 0


def test_components(spark):
    rng = np.random.default_rng(9)
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 100)] + [tuple(map(int, e)) for e in rng.integers(2000, 2400, (300, 2))] + [(5, 5)]
    label = {x: x for e in edges for x in e}
    changed = True
    while changed:
        changed = False
        for u, v in edges:
            lo = min(label[u], label[v])
            if label[u] != lo or label[v] != lo:
                label[u] = label[v] = lo
                changed = True
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "u long, v long").repartition(7)).collect()}
    assert got == {k: v for k, v in label.items() if k in got} and set(got) == {x for u, v in edges if u != v for x in (u, v)}


def test_minhash_links_every_text_of_a_repeated_id(spark):
    first, second, far = prose(50, 80), prose(51, 80).split(), prose(52, 300)
    near = " ".join([*second[:-2], "tail"])
    rows = [(1, first), (1, " ".join(second)), (3, near), (4, first + " end"), (5, far), (2, far), (2, None)]
    got = minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {(r.doc_id, r.component_id) for r in got} == {(1, 1), (3, 1), (4, 1), (5, 2), (2, 2)} and len(got) == len(rows)
    # the tile join alone, as when a list's least member links nothing
    pairs = [(k, t) for k, t in enumerate([prose(60, 400), *(prose(61, 60) + f" x{i}" for i in range(4))])] + [(2, prose(62, 50))]
    for tile in (512, 1):
        minhash.TILE, kept = tile, minhash.TILE
        try:
            got = minhash.near_duplicates(spark.createDataFrame(pairs, "doc_id long, text string")).collect()
        finally:
            minhash.TILE = kept
        assert {(r.doc_id, r.component_id) for r in got} == {(0, 0), (1, 1), (2, 1), (3, 1), (4, 1)}
