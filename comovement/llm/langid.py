"""Language identification by spans: script ranges, word scores, Viterbi with a switching penalty.

The model holds log-probabilities of hashed letter trigrams (word borders included) by language, and
which scripts each language uses. It is fitted on at most about ``SAMPLE`` labelled documents of each
language (a stated bound, chosen by a hash of doc_id; whole texts; one document at least), which are
held to the training part of the split. All languages are learned; the model takes 2^bits numbers for
each, with bits = BITS or fewer so that all languages together take at most ``MODEL_NUMBERS``. A word (run of letters) is scored only for languages of its script; Viterbi over a text's
words then labels spans. Where no run of words favours other languages by more than the penalty, one
span is optimal, which a maximum-subarray test shows without running the lattice.

Defined results: ``und`` with score 0 and no spans for a null text or one without letters; a text
in scripts that no language uses gets the commonest learned language at a low score; without any labelled document
all texts are ``und``; repeated rows are treated alike; extra columns are ignored.
"""

from __future__ import annotations

import functools

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import map_texts, pick

SAMPLE, BITS, PENALTY, FLOOR = 6000, 18, 6.0, -6.0
MODEL_NUMBERS = 1 << 26
"""Numbers in the model, 4 bytes each: what is broadcast stays under 256 MB however many languages there are."""
CHUNK = 400_000
"""Characters scored at a time."""
HELD = 64
"""Languages whose counts a task holds at a time."""

# First code points of script ranges (letters below the first are Latin).
SCRIPTS = {
    0x0000: "latin",
    0x0370: "greek",
    0x0400: "cyrillic",
    0x0530: "armenian",
    0x0590: "hebrew",
    0x0600: "arabic",
    0x0900: "devanagari",
    0x0980: "indic",
    0x0E00: "thai",
    0x0E80: "other",
    0x10A0: "georgian",
    0x1100: "hangul",
    0x1200: "other",
    0x1E00: "latin",
    0x1F00: "greek",
    0x2000: "other",
    0x3040: "kana",
    0x3100: "other",
    0x3400: "han",
    0xA000: "other",
    0xAC00: "hangul",
    0xD7B0: "other",
    0xF900: "han",
    0xFB00: "latin",
    0xFB1D: "hebrew",
    0xFB50: "arabic",
    0xFF00: "other",
    0x20000: "han",
}
_STARTS = np.array(list(SCRIPTS), np.uint32)
_NAMES = sorted(set(SCRIPTS.values()))
_KIND = np.array([_NAMES.index(s) for s in SCRIPTS.values()])


@functools.cache
def _letters() -> np.ndarray:
    """For every code point whether it is a letter."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


def bits_for(languages: int, most: int = BITS) -> int:
    return max(8, min(most, (MODEL_NUMBERS // max(1, languages)).bit_length() - 1))


class Words:
    """Letter trigrams and words of several texts at once."""

    def __init__(self):
        self.is_letter = _letters()

    def of(self, texts: list[str], bits: int = BITS):
        """(hash of each letter's trigram, first letter of each word, script of each word, text of each word)."""
        low = [t.lower() for t in texts]
        codes = np.frombuffer(("\n" + "\n".join(low) + "\n").encode("utf-32-le", "surrogatepass"), np.uint32)
        ends = np.cumsum([len(t) + 1 for t in low])  # position of the newline after each text
        letter = self.is_letter[codes]
        plain = np.where(letter, codes, np.uint32(32))
        at = np.flatnonzero(letter)
        h = plain[at - 1] * np.uint32(0x85EBCA6B) + plain[at] * np.uint32(0xC2B2AE35) + plain[at + 1] * np.uint32(0x27D4EB2F)
        h = (h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D) >> np.uint32(32 - bits)
        first = np.flatnonzero(~letter[at - 1]) if len(at) else np.empty(0, np.int64)
        script = _KIND[np.searchsorted(_STARTS, codes[at[first]], "right") - 1] if len(first) else np.empty(0, np.int64)
        return h, first, script, np.searchsorted(ends, at[first], "left")


def _chunks(ids, texts):
    part, size = ([], []), 0
    for i, t in zip(ids, texts):
        part[0].append(i)
        part[1].append(t or "")
        size += len(t or "")
        if size >= CHUNK:
            yield part
            part, size = ([], []), 0
    if part[0]:
        yield part


def _count(languages: list[str], bits: int):
    number = {lang: k for k, lang in enumerate(languages)}

    def counted(grams, scripts):
        for kind, tables in (("gram", grams), ("script", scripts)):
            for k, table in tables.items():
                slot = np.flatnonzero(table)
                yield pd.DataFrame({"kind": kind, "k": k, "slot": slot, "n": table[slot]})
            tables.clear()

    def run(batches):
        words, grams, scripts = Words(), {}, {}
        for pdf in batches:
            for lang, own in pdf.groupby("lang")["text"]:
                k = number[lang]
                if k not in grams:
                    if len(grams) >= HELD:
                        yield from counted(grams, scripts)
                    grams[k], scripts[k] = np.zeros(1 << bits, np.int64), np.zeros(len(_NAMES), np.int64)
                for _, texts in _chunks(own, own):
                    h, _, script, _ = words.of(texts, bits)
                    grams[k] += np.bincount(h, minlength=1 << bits)
                    scripts[k] += np.bincount(script, minlength=len(_NAMES))
        yield from counted(grams, scripts)

    return run


def training_part(id_col: str = "doc_id"):
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(3)) != 1


def fit(docs: DataFrame, sample: int = SAMPLE, bits: int | None = None) -> dict:
    """Model from documents (doc_id, text, lang); rows of the held-out part are never read into it."""
    labelled = docs.where("text is not null and lang is not null and doc_id is not null").where(training_part())
    slot = F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(1_000_000))
    found = labelled.groupBy("lang").agg(F.count("*").alias("n"), F.min(slot).alias("least")).collect()
    per_lang = {r["lang"]: r["n"] for r in found}
    languages = sorted(per_lang)
    bits = bits_for(len(languages)) if bits is None else bits
    # documents of a language below its cut are taken; the one of the least hash always is
    cuts = [(r["lang"], max(int(np.ceil(min(1.0, sample / r["n"]) * 1_000_000)), r["least"] + 1)) for r in found]
    chosen = labelled.join(F.broadcast(docs.sparkSession.createDataFrame(cuts, "lang string, cut long")), "lang").where(slot < F.col("cut"))
    counts = map_texts(chosen.select("lang", "text"), _count(languages, bits), "kind string, k long, slot long, n long").groupBy("kind", "k", "slot").agg(F.sum("n").alias("n")).toPandas()
    logs, scripts, smooth = np.zeros((len(languages), 1 << bits), np.float32), np.zeros((len(languages), len(_NAMES))), 0.1
    for kind, table in (("gram", logs), ("script", scripts)):
        own = counts[counts["kind"] == kind]
        table[own["k"].to_numpy(int), own["slot"].to_numpy(int)] = own["n"].to_numpy()
    for row in logs:
        total = row.sum(dtype=np.float64)
        row[:] = np.log((row + smooth) / (total + smooth * (1 << bits)))
    uses = scripts >= np.maximum(1, 0.01 * scripts.sum(axis=1, keepdims=True))
    return {"languages": languages, "logs": logs, "uses": uses, "commonest": max(per_lang, key=lambda k: (per_lang[k], k), default=None), "bits": bits}


def viterbi(s: np.ndarray, penalty: float = PENALTY) -> np.ndarray:
    """Best label of each word (rows of s: scores by language) when each change costs ``penalty``.

    The lattice runs over plain lists, which are faster than arrays for a few languages; the way back
    looks at the totals again instead of keeping a pointer for each label."""
    best = s.sum(axis=0).argmax()
    gain = s - s[:, [best]]
    gain[:, best] = -np.inf
    run = np.concatenate([[0.0], np.cumsum(gain.max(axis=1))]) if s.shape[1] > 1 else np.zeros(1)
    if (run - np.minimum.accumulate(run)).max() <= penalty:
        return np.full(len(s), best)
    rows = s.tolist()
    total, totals = rows[0], []
    for row in rows[1:]:
        totals.append(total)
        changed = max(total) - penalty
        total = [(v if v >= changed else changed) + x for v, x in zip(total, row)]
    label = total.index(max(total))
    labels = [label]
    for total in reversed(totals):
        top = max(total)
        if total[label] < top - penalty:
            label = total.index(top)
        labels.append(label)
    return np.array(labels[::-1])


def _predict(shared, penalty: float, returned: list[str]):
    def run(batches):
        model = shared.value
        words, languages = Words(), model["languages"]
        for pdf in batches:
            rows = []
            for ids, texts in _chunks(pdf["doc_id"], pdf["text"]):
                h, first, script, owner = words.of(texts, model["bits"])
                if len(first) and languages:
                    scores = np.stack([np.add.reduceat(logs[h], first) for logs in model["logs"]], axis=1)
                    may = model["uses"][:, script].T
                    known = may.any(axis=1)
                    scores = np.where(may | ~known[:, None], scores, -np.inf)
                    scores -= scores.max(axis=1, keepdims=True)
                    scores = np.maximum(scores, FLOOR).astype(np.float64)
                    scores[~known] = 0.0
                    sizes = np.diff(np.append(first, len(h)))
                bounds = np.searchsorted(owner, np.arange(len(texts) + 1))
                for i, doc_id in enumerate(ids):
                    lo, hi = bounds[i], bounds[i + 1]
                    if lo == hi or not languages:
                        rows.append((doc_id, "und", 0.0, []))
                        continue
                    s, size = scores[lo:hi], sizes[lo:hi]
                    if not known[lo:hi].any():
                        rows.append((doc_id, model["commonest"], 0.05, []))
                        continue
                    labels = viterbi(s, penalty)
                    share = np.bincount(labels, weights=size, minlength=len(languages))
                    top = int(share.argmax())
                    mine = s[labels == top]
                    rival = np.delete(mine.sum(axis=0), top).max() if len(languages) > 1 else -50.0
                    sure = 1.0 - np.exp(min(0.0, rival - mine[:, top].sum()))
                    starts = np.flatnonzero(np.append(True, labels[1:] != labels[:-1]))
                    spans = [{"lang": languages[labels[a]], "first_word": int(a), "n_words": int(b - a)} for a, b in zip(starts, np.append(starts[1:], len(labels)))]
                    rows.append((doc_id, languages[top], float(min(1.0, max(0.0, share[top] / share.sum() * (0.05 + 0.95 * sure)))), spans))
            out = pd.DataFrame(rows, columns=["doc_id", "lang_pred", "score", "spans"]).astype({"doc_id": "Int64"})
            yield out.assign(**{c: pdf[c] for c in returned})

    return run


def predict(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text", penalty: float = PENALTY, carried: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, lang_pred, score, spans; only the text is looked at. With ``carried``, also text and those columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # of fixed size: languages x 2^bits
    own = pick(docs, doc_id=id_col, text=text_col, **{c: c for c in carried})
    back = own.schema.fields[1:] if carried else []
    more = "".join(f", {f.name} {f.dataType.simpleString()}" for f in back)
    return map_texts(own, _predict(shared, penalty, [f.name for f in back]), "doc_id long, lang_pred string, score double, spans array<struct<lang:string,first_word:long,n_words:long>>" + more)


def identify(docs: DataFrame, labelled: DataFrame, carried: tuple[str, ...] = ()) -> DataFrame:
    """Fit on the training part of ``labelled`` and predict every row of docs."""
    out = predict(docs, fit(pick(labelled, doc_id="doc_id", text="text", lang="lang")), carried=carried)
    return out.select("doc_id", F.coalesce(~training_part(), F.lit(False)).alias("held_out"), "lang_pred", "score", "spans", *(("text", *carried) if carried else ()))
