"""Quality classifier: histogram gradient-boosted trees over document statistics.

Null and empty texts score like any other from their (zero) statistics; repeated texts score alike.
"""

from __future__ import annotations

from operator import eq

import numpy as np
from pyspark.sql import DataFrame

from packflow.llm import classify
from packflow.llm.gbdt import Trees, fit

PARTS, HELD, CUT = 4, 2, 0.7
#: Fixed value: bytes whose shares are features of their own.
SIGNS = b".,!?;:*#$%&|@+-_=/\\\"'()[]{}<>~^"


def statistics(texts: list[str]) -> np.ndarray:
    """One row of statistics per text, from its byte histogram, words and lines."""
    sign, rows = np.frombuffer(SIGNS, np.uint8), np.zeros((len(texts), 16 + len(SIGNS)))
    for i, text in enumerate(texts):
        b = text.encode()
        n = len(b)
        if not n:
            continue
        h = np.bincount(np.frombuffer(b, np.uint8), minlength=256)
        words, lines = b.split(), b.split(b"\n")
        p = h[h > 0] / n
        w = max(1, len(words))
        upper, lower, digit = h[65:91].sum(), h[97:123].sum(), h[48:58].sum()
        rows[i, :16] = (
            np.log1p(n), np.log1p(len(words)), sum(map(len, words)) / w, len(set(words)) / w,
            sum(map(eq, words, words[1:])) / w, len(set(map(bytes.lower, words))) / w,
            len(lines), n / len(lines), len(set(lines)) / len(lines), upper / n, lower / n, digit / n,
            h[128:].sum() / n, h[32] / n, -(p * np.log2(p)).sum(), upper / max(1, upper + lower),
        )
        rows[i, 16:] = h[sign] / n
    return rows


def train(docs: DataFrame, labels: DataFrame, rows: int = classify.SAMPLE_ROWS, id_col: str = "doc_id", text_col: str = "text") -> Trees:
    """Fit on at most ``rows`` labelled documents outside the held-out fold."""
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            x = statistics([t or "" for t in batch.column(0).to_pylist()])
            yield pa.RecordBatch.from_arrays([pa.array(list(x), pa.list_(pa.float64())), batch.column(1)], names=["x", "y"])

    sample = classify.labelled_sample(docs, labels, "quality", PARTS, HELD, rows, id_col, text_col)
    got = sample.mapInArrow(run, "x array<double>, y int").toPandas()
    x = np.array(got["x"].tolist()) if len(got) else np.zeros((0, 16 + len(SIGNS)))
    return fit(x, got["y"].to_numpy(float))


def scorer(model: Trees):
    return lambda texts: model.probability(statistics(texts))


def quality_scores(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, held_out, score, predicted) for every row."""
    return classify.score_rows(docs, scorer(train(docs, labels, id_col=id_col, text_col=text_col)), PARTS, HELD, CUT, id_col, text_col)


def keep_good(docs: DataFrame, labels: DataFrame, cut: float = CUT) -> DataFrame:
    """The rows that the classifier does not reject, with all their columns."""
    return classify.keep_rows(docs, scorer(train(docs, labels)), cut)
