"""Runs of several strategies over one corpus, summarized from their ledgers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packflow.config import EncoderProfile, PackPolicy
from packflow.operators import encode, packing
from packflow.operators.sizes import lane_of, partition_sizes


def summary(ledger: DataFrame, strategy: str) -> DataFrame:
    """One row: calls, texts, largest call, bytes resident at most, seconds by stage."""
    return ledger.agg(
        F.count(F.lit(1)).alias("calls"), F.coalesce(F.sum("n_texts"), F.lit(0)).alias("texts"), F.max("n_texts").alias("largest"), F.max("data_bytes").alias("data_bytes"),
        F.sum("t_encode").alias("encode_s"), F.sum("t_serialize").alias("serialize_s"), F.sum("t_stall").alias("stall_s"), F.min("t_start").alias("first_start"),
    ).select(F.lit(strategy).alias("strategy"), "*")


def compare_strategies(corpus: DataFrame, configs: dict[str, dict], profile: EncoderProfile) -> DataFrame:
    """Union of the summaries of named runs.

    A configuration has ``kind``: ``packed`` (with ``policy``, ``lanes``), ``per_partition``, ``fixed``
    (with ``size``; calls are counted per task) or ``ffd`` (with ``size``).
    """
    out = None
    for name, c in configs.items():
        if c["kind"] == "packed":
            led = encode.stream_pack_encode(corpus, c["policy"], profile, c.get("lanes", 1), "ledger")
        elif c["kind"] == "per_partition":
            led = encode.per_partition_encode(corpus, profile, "ledger")
        elif c["kind"] == "fixed":
            led = encode.fixed_batch_encode(corpus, c["size"], profile, "ledger")
        elif c["kind"] == "ffd":
            led = encode.planned_encode(corpus, packing.ffd_pack(partition_sizes(corpus), c["size"]), profile, "ledger")
        else:
            raise ValueError(c["kind"])
        one = summary(led, name)
        out = one if out is None else out.unionByName(one)
    return out


def first_partitions(corpus: DataFrame, policy: PackPolicy, profile: EncoderProfile, lanes: int, lane: int = 0) -> DataFrame:
    """A preview: one lane's vectors only. A limit would not stop the other lanes' encoders; this does."""
    return encode.stream_pack_encode(corpus.where(lane_of(F.col("part_key").cast("string"), lanes) == lane), policy, profile, lanes)
