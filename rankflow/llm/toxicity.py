"""Toxicity by gradient-boosted trees over dense features, calibrated by isotonic regression.

Features of a whole text: density, count and variety of lexicon words, their nearness to second-person words, share of
capitals, punctuation and of words with obfuscating marks, and length. The lexicon is a short fixed list of insults and the
words whose share among toxic training documents most exceeds that among the others. Trees and lexicon are fitted on at most
``sample`` labelled documents of at most ``text_chars`` characters, taken by a hash of their ids; the calibration on a third of
these that trees and lexicon don't see.

Null and empty texts score as a text with no words. Rows of labels with null ids or labels, or that contradict each other,
are not learnt from; repeated ones count once, and of rows that share an id one is learnt from. With nothing to learn from,
every score is 0. Very long texts are scored whole; equal texts score equal. An empty table gives an empty result. Other columns
pass through; ``_score`` and ``_toxic`` are replaced in ``scored``, and ``clean`` adds no column at all.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .boosting import Boosted, Isotonic
from .common import small_batches, tidy

#: Insults and second-person words.
INSULTS = "idiot idiots moron morons stupid loser losers scum worthless pathetic trash garbage dumb imbecile fool disgusting shut hate kill vermin".split()
SECOND = "you your yours yourself u ur du dich dir dein deine sie ihr euch tu te toi ton ta vous votre tú ti tus usted vosotros".split()
UNMASK = str.maketrans({"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i"})
NAMES = ["density", "hits", "kinds", "weight", "near_second", "second", "capitals", "shouted", "exclaims", "marks", "masked", "masked_hits", "log_words"]
_WORD, _MASKED = re.compile(r"[^\W\d_]+"), re.compile(r"\b[^\W\d_][\w]*[0-9@$*!][\w@$!*]*[^\W\d_]")
_CAPITAL, _SHOUTED, _MARK = re.compile(r"[A-ZÀ-ÖØ-Þ]"), re.compile(r"\b[A-Z]{3,}\b"), re.compile(r"[^\w\s]")
_SECOND = frozenset(SECOND)


def features(text: str | None, lexicon: dict[str, float]) -> list[float]:
    text = text or ""
    low = text.lower()
    words = _WORD.findall(low)
    n = max(1, len(words))
    found = lexicon.keys() & set(words)
    hits = weight = near = 0
    if found:
        at = [k for k, w in enumerate(words) if w in found]
        hits, weight = len(at), sum(lexicon[words[k]] for k in at)
        near = sum(any(w in _SECOND for w in words[max(0, k - 3) : k + 4]) for k in at)
    second = sum(map(words.count, ("you", "your", "du", "tu", "vous")))
    masked = _MASKED.findall(low)
    unmasked = sum(w.rstrip("!").translate(UNMASK) in lexicon for w in masked)
    chars = max(1, len(text))
    capitals, shouted = len(_CAPITAL.findall(text)), len(_SHOUTED.findall(text))
    return [1000 * hits / n, float(hits), float(len(found)), weight, float(near), 1000 * second / n, 100 * capitals / chars, 1000 * shouted / n, 1000 * text.count("!") / chars, 100 * len(_MARK.findall(text)) / chars, 1000 * len(masked) / n, float(unmasked), float(np.log1p(len(words)))]


class Scorer:
    def __init__(self, lexicon: dict[str, float], trees: Boosted, calibrate: Isotonic | None):
        self.lexicon, self.trees, self.calibrate = lexicon, trees, calibrate

    def __call__(self, texts: list[str | None]) -> np.ndarray:
        if self.calibrate is None or not texts:
            return np.zeros(len(texts))
        return self.calibrate(self.trees.score(np.array([features(t, self.lexicon) for t in texts])))


def lexicon_of(texts: list[str], y: np.ndarray, most: int = 60) -> dict[str, float]:
    """word -> smoothed log of its odds among toxic texts against the others."""
    counts = (Counter(), Counter())
    for t, v in zip(texts, y, strict=True):
        counts[int(v)].update(set(_WORD.findall(t.lower())))
    n1, n0 = max(1, int(y.sum())), max(1, int(len(y) - y.sum()))
    scored = {w: float(np.log((c + 0.5) / (n1 + 1)) - np.log((counts[0][w] + 0.5) / (n0 + 1))) for w, c in counts[1].items() if c >= max(3, 0.02 * n1)}
    top = sorted(((v, w) for w, v in scored.items() if v > 1.2), reverse=True)[:most]
    return {w: 1.0 for w in INSULTS} | {w: v for v, w in top}


def fit(docs: DataFrame, labels: DataFrame, sample: int = 9_000, text_chars: int = 20_000) -> Scorer:
    """Learns from documents whose crc32(doc_id as text) mod 4 is not 2. Longer texts are scored like any other, but not learnt from."""
    known = labels.filter("doc_id is not null and toxic in (0, 1)").filter(F.crc32(F.col("doc_id").cast("string")) % 4 != 2)
    ids = [r[0] for r in known.select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample).collect()]
    spark = docs.sparkSession
    chosen = spark.createDataFrame([(i,) for i in ids], "doc_id long")
    toxic = known.join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.min("toxic").alias("lo"), F.max("toxic").alias("toxic")).filter("lo = toxic").select("doc_id", "toxic")
    rows = docs.select("doc_id", "text").filter(F.length(F.coalesce("text", F.lit(""))) <= text_chars).join(F.broadcast(toxic), "doc_id").dropDuplicates(["doc_id"]).collect()  # at most sample rows of text_chars
    rows.sort(key=lambda r: r.doc_id)
    if not rows:
        return Scorer({}, Boosted(), None)
    y = np.array([r.toxic for r in rows], float)
    texts = [r.text or "" for r in rows]
    apart = np.arange(len(y)) % 3 == 0
    apart = apart if 0 < y[apart].sum() < apart.sum() else np.zeros(len(y), bool)
    lexicon = lexicon_of([t for t, out in zip(texts, apart, strict=True) if not out], y[~apart])
    x = np.array([features(t, lexicon) for t in texts])
    trees = Boosted(rounds=60, depth=3, rate=0.15).fit(x[~apart], y[~apart])
    rest = apart if apart.any() else ~apart
    return Scorer(lexicon, trees, Isotonic().fit(trees.score(x[rest]), y[rest]))


def _mapped(docs: DataFrame, names: list[str], types: str, run) -> DataFrame:
    """docs through run under names by position, so that no column's name matters; back under ``names``."""
    small_batches(docs.sparkSession)
    kinds = ", ".join(f"`c{k}` {f.dataType.simpleString()}" for k, f in enumerate(docs.schema))
    out = docs.toDF(*[f"c{k}" for k in range(len(docs.columns))]).mapInArrow(tidy(run), kinds + types)
    return out.toDF(*names)


def scored(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, **how) -> DataFrame:
    """docs with _score and _toxic (0 or 1)."""
    scorer = fit(docs, labels, **how)
    docs = docs.drop("_score", "_toxic")
    at = docs.columns.index("text")

    def run(batches):
        for b in batches:
            s = scorer(b.column(at).to_pylist())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32))], [*b.schema.names, "s", "t"])

    return _mapped(docs, [*docs.columns, "_score", "_toxic"], ", s double, t int", run)


def clean(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, **how) -> DataFrame:
    """The rows of docs that score under the threshold."""
    scorer = fit(docs, labels, **how)
    at = docs.columns.index("text")

    def run(batches):
        for b in batches:
            yield b.filter(pa.array(scorer(b.column(at).to_pylist()) < threshold))

    return _mapped(docs, docs.columns, "", run)
