"""Language identification with a blended-spectrum string kernel.

A text is the set of its n-grams of one to three characters over a reduced alphabet (the letters most frequent in training,
one symbol for other letters, one for all else). The kernel of two texts is the size of their sets' intersection over the
root of the product of their sizes. A few hundred training texts are landmarks; their kernel matrix gives Nyström features,
on which one ridge regression for each language is solved. A batch is scored by two matrix products.

Learns from at most ``sample`` texts of at most ``text_chars`` characters, drawn evenly over languages by a hash of doc_id; a
language that has longer texts only is learnt from its shortest. Texts that are null or have no letter are ``und`` with score 0,
and so is every text if there is nothing to learn from. Very long texts are classified whole. Of rows that share an id one is
learnt from; equal texts get equal results, and equal scores the language that sorts first. Empty tables give empty results.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import small, small_batches, tidy

SIGNS = 64  # the reduced alphabet with space and other letters
LANDMARKS = 320


class Spectrum:
    """Presence of 1- to 3-grams: numbers into SIGNS + SIGNS**2 + SIGNS**3 places."""

    def __init__(self, letters: str):
        self.table = np.full(0x110000, 1, np.uint8)
        letter = np.array([chr(c).isalpha() for c in range(0x3000)])
        self.table[:0x3000][~letter] = 0
        for k, c in enumerate(letters[: SIGNS - 2]):
            self.table[ord(c)] = k + 2
            if len(c.upper()) == 1:
                self.table[ord(c.upper())] = k + 2
        self.flags = np.zeros(SIGNS + SIGNS**2 + SIGNS**3, bool)

    def __call__(self, text: str) -> np.ndarray:
        s = self.table[np.frombuffer(text.encode("utf-32-le", "replace"), "<u4")].astype(np.int32)
        if len(s) > 1:
            s = s[np.concatenate(([True], (s[1:] != 0) | (s[:-1] != 0)))]  # one space for a run of other signs
        flags = self.flags
        two = s[:-1] * SIGNS + s[1:]
        three = two[:-1] * SIGNS + s[2:] if len(two) else two
        flags[s] = True
        flags[SIGNS + two] = True
        flags[SIGNS + SIGNS**2 + three] = True
        found = np.flatnonzero(flags)
        flags[found] = False
        return found


class Classifier:
    def __init__(self, letters: str, grams: np.ndarray, landmark: np.ndarray, weights: np.ndarray, languages: list[str]):
        self.letters, self.grams, self.landmark, self.weights, self.languages = letters, grams, landmark, weights, languages

    def __call__(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        if not hasattr(self, "spectrum"):
            self.spectrum = Spectrum(self.letters)
            self.place = np.full(len(self.spectrum.flags), -1, np.int32)
            self.place[self.grams] = np.arange(len(self.grams))
        names, scores = ["und"] * len(texts), np.zeros(len(texts))
        for at in range(0, len(texts), 64):
            rows = [k for k in range(at, min(at + 64, len(texts))) if self.languages and texts[k] and _has_letter(texts[k])]
            if not rows:
                continue
            x = np.zeros((len(rows), len(self.grams)), np.float32)
            for r, k in enumerate(rows):
                found = self.spectrum(texts[k])
                own = self.place[found]
                x[r, own[own >= 0]] = 1 / np.sqrt(len(found))
            f = (x @ self.landmark) @ self.weights
            best = f.argmax(1)
            # One-versus-rest targets are 0 and 1; the share of the best among the clipped outputs is the score.
            clipped = np.clip(f, 1e-6, 1)
            share = clipped[np.arange(len(rows)), best] / clipped.sum(1)
            for r, k in enumerate(rows):
                names[k], scores[k] = self.languages[best[r]], float(share[r])
        return names, scores


def _has_letter(text: str) -> bool:
    return any(map(str.isalpha, text[:200])) or any(map(str.isalpha, text))


def fit(docs: DataFrame, sample: int = 2000, text_chars: int = 20_000) -> Classifier:
    """Learns from documents whose crc32(doc_id as text) mod 3 is not 1, and that have a lang."""
    known = docs.select("doc_id", "text", "lang").filter("lang is not null and text is not null").filter(F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3, F.lit(1)) != 1)
    known = known.withColumn("size", F.length("text"))
    sizes = known.groupBy("lang").agg(F.count_if(F.col("size") <= text_chars).alias("short"), F.min("size").alias("least"))
    known = known.join(small(sizes), "lang").filter((F.col("size") <= text_chars) | ((F.col("short") == 0) & (F.col("size") == F.col("least"))))
    # The order statistics of a hash, stretched by a language's size, draw evenly over languages. Doubles, since longs overflow.
    unit = (F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)) + 1).cast("double") * F.greatest("short", F.lit(1)).cast("double")
    ids = known.select("doc_id", unit.alias("unit")).orderBy("unit", "doc_id").limit(sample).select("doc_id").distinct().collect()
    chosen = docs.sparkSession.createDataFrame([(r[0],) for r in ids], "doc_id long")
    rows = sorted(known.join(F.broadcast(chosen), "doc_id").dropDuplicates(["doc_id"]).collect(), key=lambda r: r.doc_id)
    if not rows:
        return Classifier("", np.zeros(0, int), np.zeros((0, 0)), np.zeros((0, 0)), [])
    letters: dict[str, int] = {}
    for r in rows:
        for c in set(r.text.lower()):
            if c.isalpha() and len(c) == 1:
                letters[c] = letters.get(c, 0) + 1
    letters = "".join(sorted(letters, key=lambda c: (-letters[c], c))[: SIGNS - 2])
    spectrum = Spectrum(letters)
    sets = [spectrum(r.text) for r in rows]
    languages = sorted({r.lang for r in rows})
    marks, by = [], {}
    for k, r in enumerate(rows):
        by.setdefault(r.lang, []).append(k)
    for turn in range(LANDMARKS):
        marks += [own[turn] for own in by.values() if turn < len(own)]
        if len(marks) >= LANDMARKS:
            break
    grams = np.unique(np.concatenate([sets[k] for k in marks]))
    place = np.full(len(spectrum.flags), -1, np.int64)
    place[grams] = np.arange(len(grams))
    x = np.zeros((len(rows), len(grams)), np.float32)
    for k, s in enumerate(sets):
        own = place[s]
        x[k, own[own >= 0]] = 1 / np.sqrt(max(1, len(s)))
    z = x[marks].astype(np.float64)
    value, vector = np.linalg.eigh(z @ z.T)
    keep = value > 1e-6 * value.max()
    root = vector[:, keep] / np.sqrt(value[keep])  # Nyström: features are kernels to the landmarks, times this
    feats = (x @ z.T) @ root
    y = np.array([[float(r.lang == q) for q in languages] for r in rows])
    ridge = 1e-3 * len(rows)
    solved = np.linalg.solve(feats.T @ feats + ridge * np.eye(feats.shape[1]), feats.T @ y)
    return Classifier(letters, grams, np.ascontiguousarray(x[marks].T), (root @ solved).astype(np.float32), languages)


def predict(docs: DataFrame, model: Classifier) -> DataFrame:
    """(doc_id, lang_pred, score) of each row of docs (doc_id, text)."""
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for b in batches:
            names, scores = model(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(names, pa.string()), pa.array(scores, pa.float64())], ["doc_id", "lang_pred", "score"])

    small_batches(docs.sparkSession)
    return docs.select("doc_id", "text").mapInArrow(tidy(run), f"doc_id {id_type}, lang_pred string, score double")
