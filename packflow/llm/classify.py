"""What the quality and the toxicity classifier share: a bounded labelled sample, and scoring all rows.

The sample has at most ``SAMPLE_ROWS`` labelled documents outside the held-out fold, those with the
least hash of their id, whatever the tables' sizes, and of them, in that order, as many as ``SAMPLE_BYTES``
of text allow; its ids are broadcast (so that their size is bounded). Of rows of one id the least text
counts. The sample is the same in every run. Labels, ids, languages and sources are no
features. Scoring reads every whole text.
"""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from packflow.llm.common import materialize, sliced

#: Bounds of the sample: documents, and bytes of their texts together.
SAMPLE_ROWS, SAMPLE_BYTES = 12_000, 96 << 20


def fold(id_col: str, parts: int) -> Column:
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % parts


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, parts: int, held: int, rows: int = SAMPLE_ROWS, id_col: str = "doc_id", text_col: str = "text", most_bytes: int = SAMPLE_BYTES) -> DataFrame:
    """(text, y) of the sample. Contradicting labels of one id count as their maximum."""
    chosen = (
        labels.where(F.col(label).isNotNull() & F.col(id_col).isNotNull() & (fold(id_col, parts) != held))
        .groupBy(F.col(id_col).alias("__id"))
        .agg(F.max(F.col(label)).cast("int").alias("y"))
        .orderBy(F.xxhash64("__id"), "__id")
        .limit(rows)
    )
    texts = docs.select(F.col(id_col).alias("__id"), F.col(text_col).cast("string").alias("text"))
    found = texts.join(F.broadcast(chosen), "__id").groupBy("__id").agg(F.min("text").alias("text"), F.max("y").alias("y"))
    found = materialize(found, "sample")
    so_far = F.sum(F.coalesce(F.octet_length("text"), F.lit(0))).over(Window.orderBy(F.xxhash64("__id"), "__id"))
    kept = found.select("__id", so_far.alias("bytes")).where(F.col("bytes") <= most_bytes).select("__id")  # of ``rows`` rows at most
    return found.join(F.broadcast(kept), "__id", "left_semi").orderBy(F.xxhash64("__id"), "__id").select("text", "y")


def score_rows(docs: DataFrame, scores: Callable[[list[str]], object], parts: int, held: int, cut: float, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, held_out, score, predicted) for every row; a null id is not held out."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        for batch in sliced(batches, "__text", 8 << 20):
            s = scores([t or "" for t in batch.column(2).to_pylist()])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s, pa.float64()), pa.array(s >= cut, pa.bool_()).cast(pa.int32())], names=[id_col, "held_out", "score", "predicted"])

    narrow = docs.select(F.col(id_col), F.coalesce(fold(id_col, parts) == held, F.lit(False)).alias("__held"), F.col(text_col).cast("string").alias("__text"))
    return narrow.mapInArrow(run, f"`{id_col}` {kind}, held_out boolean, score double, predicted int")


def keep_rows(docs: DataFrame, scores: Callable[[list[str]], object], cut: float, text_col: str = "text") -> DataFrame:
    """The rows, all columns, whose score is ``cut`` or more."""

    def run(batches):
        for batch in sliced(batches, text_col, 8 << 20):
            s = scores([t or "" for t in batch.column(text_col).to_pylist()])
            yield batch.filter(pa.array(s >= cut))

    return docs.mapInArrow(run, docs.schema)
