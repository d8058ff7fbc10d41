"""Toxicity: gradient-boosted trees over dense features, calibrated by isotonic regression.

Features are densities of a fixed lexicon and of word beginnings learned from labelled rows (the only
lexicon for languages without a fixed one), second-person proximity, capitals, punctuation, and rates
of obfuscated words. The labelled sample is dealt in three by a hash of the text: one part picks the
learned beginnings, one fits the trees, one the calibration.

Null and empty texts have zero features and a score all the same; repeated texts score alike.
"""

from __future__ import annotations

import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from packflow.llm import classify
from packflow.llm.gbdt import Isotonic, Trees, fit, fit_isotonic

PARTS, HELD, CUT = 5, 0, 0.5
# Insults, second-person words, and look-alike characters with the letters they stand for.
INSULTS = frozenset("idiot idiots moron morons stupid dumb fool loser losers scum trash garbage pathetic worthless disgusting clown ugly hate vermin filth filthy jerk imbecile cretin dumbass bastard".split())
SECOND_PERSON = frozenset("you your yours yourself u ur tu te toi vous votre du dich dir dein ihr euch usted tú ti".split())
LOOK_ALIKE = str.maketrans("013457@$!", "oieastasi")
STRIP = "".join(map(chr, range(33, 48))) + ":;<=>?@[\\]^_`{|}~«»„“”…¡¿"
PREFIXES = range(4, 9)
LEARNED, WEIGHTS = 400, 15
MEMORY = 300_000


def clean(word: str) -> str:
    return word.lower().strip(STRIP)


class Words(dict):
    """Codes of words: bit 0 insult, bit 1 second person, bit 2 obfuscated insult, bit 3 letters mixed
    with digits or signs, then the learned weight. Forgets all when it is full."""

    def __init__(self, learned: dict[str, int]):
        self.learned = learned

    def __missing__(self, raw: str) -> int:
        if len(self) >= MEMORY:
            self.clear()
        word = clean(raw)
        plain = word.translate(LOOK_ALIKE)
        squeezed = "".join(c for c in plain if c.isalpha())
        code = (word in INSULTS) | (word in SECOND_PERSON) << 1
        code |= (not code & 1 and (plain in INSULTS or squeezed in INSULTS)) << 2
        code |= (word != squeezed and any(c.isalpha() for c in word) and any(not c.isalpha() for c in word)) << 3
        weight = max((self.learned.get(word[:k], 0) for k in PREFIXES if k <= len(word)), default=0)
        self[raw] = code = code | weight << 4
        return code


def learn(texts: list[str], y: list[int], least: int = 4) -> dict[str, int]:
    """Word beginnings and their weights, 1 to 15: scaled log odds of toxic against other documents."""
    seen: tuple[Counter, Counter] = (Counter(), Counter())
    for text, label in zip(texts, y, strict=True):
        words = {clean(w) for w in text.split()}
        seen[label].update({w[:k] for w in words for k in PREFIXES if k <= len(w)})
    toxic, rest = sum(y) + 1, len(y) - sum(y) + 1
    odds = {p: np.log((n + 0.5) / toxic) - np.log((seen[0][p] + 0.5) / rest) for p, n in seen[1].items() if n >= least}
    top = sorted(((o * np.sqrt(seen[1][p]), p) for p, o in odds.items() if o > 1), reverse=True)[:LEARNED]
    return {p: int(np.clip(round(2 * odds[p]), 1, WEIGHTS)) for _, p in top}


def features(texts: list[str], words: Words) -> np.ndarray:
    rows = np.zeros((len(texts), 18))
    for i, text in enumerate(texts):
        split = text.split()
        if not split:
            continue
        code = np.fromiter(map(words.__getitem__, split), np.int64, len(split))
        n, b = len(split), np.frombuffer(text.encode(), np.uint8)
        h = np.bincount(b, minlength=256)
        insult, you, weight = np.flatnonzero(code & 5), np.flatnonzero(code & 2), code >> 4
        near = 0
        if len(insult) and len(you):
            at = np.searchsorted(you, insult)
            gap = np.minimum(np.abs(you[np.minimum(at, len(you) - 1)] - insult), np.abs(insult - you[np.maximum(at - 1, 0)]))
            near = int((gap <= 4).sum())
        hit = weight[weight > 0]
        upper, lower = h[65:91].sum(), h[97:123].sum()
        rows[i] = (
            len(insult), len(insult) / n, near / n, len(you) / n, (code & 4 > 0).sum() / n, (code & 8 > 0).sum() / n,
            len(hit), len(hit) / n, hit.sum() / n, hit.max(initial=0), (weight >= 5).sum(), (weight >= 7).sum(), (weight >= 7).sum() / n,
            upper / max(1, upper + lower), h[33] / len(b), (h[33:48].sum() + h[58:65].sum()) / len(b), h[48:58].sum() / len(b), np.log1p(n),
        )
    return rows


@dataclass
class Toxicity:
    learned: dict[str, int]
    trees: Trees
    calibration: Isotonic

    def __post_init__(self):
        self.words = Words(self.learned)

    def __getstate__(self):
        return (self.learned, self.trees, self.calibration)

    def __setstate__(self, state):
        self.__init__(*state)

    def __call__(self, texts: list[str]) -> np.ndarray:
        return np.clip(self.calibration(self.trees.probability(features(texts, self.words))), 0, 1)


def fit_texts(texts: list[str], y: list[int]) -> Toxicity:
    part = np.array([zlib.crc32(t.encode()) % 10 for t in texts], int)
    label = np.array(y, int)
    pick = lambda low, high: [k for k in np.flatnonzero((part >= low) & (part < high)).tolist()]
    a, b, c = pick(0, 4), pick(4, 8), pick(8, 10)
    learned = learn([texts[k] for k in a], [y[k] for k in a])
    words = Words(learned)
    trees = fit(features([texts[k] for k in b], words), label[b].astype(float), trees=100, depth=3)
    score = trees.probability(features([texts[k] for k in c], words))
    return Toxicity(learned, trees, fit_isotonic(score, label[c].astype(float)))


def train(docs: DataFrame, labels: DataFrame, rows: int = classify.SAMPLE_ROWS, id_col: str = "doc_id", text_col: str = "text") -> Toxicity:
    """Fit on at most ``rows`` labelled documents outside the held-out fold."""
    got = classify.labelled_sample(docs, labels, "toxic", PARTS, HELD, rows, id_col, text_col).toPandas()
    return fit_texts([t or "" for t in got["text"]], got["y"].tolist())


def toxicity_scores(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, held_out, score, predicted) for every row."""
    return classify.score_rows(docs, train(docs, labels, id_col=id_col, text_col=text_col), PARTS, HELD, CUT, id_col, text_col)
