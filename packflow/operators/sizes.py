"""Partition sizes and what is derived from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def partition_sizes(corpus: DataFrame) -> DataFrame:
    """(part_key, n_texts, n_bytes): one partial and one final aggregate."""
    return corpus.groupBy("part_key").agg(F.count(F.lit(1)).alias("n_texts"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).cast("long").alias("n_bytes"))


def size_stats(sizes: DataFrame) -> DataFrame:
    """One row: P, N, extremes, mean, deviation, and both variation measures (by mean and by median)."""
    n = F.col("n_texts")
    return sizes.agg(
        F.count(F.lit(1)).alias("parts"), F.coalesce(F.sum(n), F.lit(0)).alias("texts"), F.min(n).alias("n_min"), F.max(n).alias("n_max"),
        F.avg(n).alias("mean"), F.stddev_pop(n).alias("sd"), F.expr("percentile(n_texts, 0.5)").alias("median"),
    ).select("*", (F.col("sd") / F.col("mean")).alias("cv"), (F.col("sd") / F.col("median")).alias("std_over_median"))


def size_histogram(sizes: DataFrame) -> DataFrame:
    """Partitions and texts by the power of two of the size."""
    return sizes.groupBy(F.floor(F.log2(F.col("n_texts")) + 1e-9).cast("long").alias("bucket")).agg(F.count(F.lit(1)).alias("parts"), F.sum("n_texts").alias("texts"))


def md5_number(column: Column) -> Column:
    """The first eight hex digits of the MD5 as a number; equal on every engine."""
    return F.conv(F.substring(F.md5(column.cast("binary")), 1, 8), 16, 10).cast("long")


def lane_of(column: Column, lanes: int) -> Column:
    """Hash lane of a key, equal on every engine; a null key has lane 0."""
    return F.coalesce(md5_number(column) % lanes, F.lit(0)).cast("int")


def own_lane_of(column: Column, lanes: int) -> Column:
    """Hash lane of a key by Spark's own hash, which costs little for each row; a null key has lane 0."""
    return F.when(column.isNull(), 0).otherwise(F.pmod(F.xxhash64(column), F.lit(lanes))).cast("int")


ORDERS = ("key", "md5", "size_asc", "size_desc", "largest_last", "near_full_then_largest")


def arrival_order(sizes: DataFrame, how: str = "key", b_min: int = 1) -> DataFrame:
    """Adds ``arrival``, the partitions' order of arrival.

    ``near_full_then_largest`` is the adversary: small ones up to nearly ``b_min``, then the largest.
    """
    n = F.col("n_texts")
    largest = F.row_number().over(Window.orderBy(n.desc(), "part_key")) == 1
    orders: dict[str, list[Column]] = {
        "key": [F.col("part_key")],
        "md5": [F.md5(F.col("part_key").cast("binary")), F.col("part_key")],
        "size_asc": [n, F.col("part_key")],
        "size_desc": [n.desc(), F.col("part_key")],
        "largest_last": [F.col("__largest"), F.col("part_key")],
        "near_full_then_largest": [F.when(F.col("__largest"), 1).when(F.col("__run") < b_min, 0).otherwise(2), n, F.col("part_key")],
    }
    marked = sizes
    if how in ("largest_last", "near_full_then_largest"):
        marked = sizes.withColumn("__largest", largest)
        if how == "near_full_then_largest":
            marked = marked.withColumn("__run", F.sum("n_texts").over(Window.orderBy(n, "part_key")))
    return marked.withColumn("arrival", F.row_number().over(Window.orderBy(*orders[how])).cast("long")).select(*sizes.columns, "arrival")


def assign_lanes(sizes: DataFrame, lanes: int, how: str = "hash") -> DataFrame:
    """Adds ``lane``: by hash, by ranges of the key order with even texts, or longest first to the
    least loaded lane (``lpt``; a plan over sizes in one task)."""
    if how == "hash":
        return sizes.withColumn("lane", lane_of(F.col("part_key"), lanes))
    if how == "range":
        before = F.sum("n_texts").over(Window.orderBy("part_key")) - F.col("n_texts")
        total = F.sum("n_texts").over(Window.partitionBy())
        return sizes.withColumn("lane", F.least(F.lit(lanes - 1), F.floor(before * lanes / total)).cast("int"))
    if how != "lpt":
        raise ValueError(how)

    def plan(table):
        import heapq

        import pyarrow as pa

        rows = sorted(table.to_pylist(), key=lambda r: (-r["n_texts"], r["part_key"] or ""))
        heap = [(0, k) for k in range(lanes)]
        for r in rows:
            load, k = heapq.heappop(heap)
            r["lane"] = k
            heapq.heappush(heap, (load + r["n_texts"], k))
        return pa.Table.from_pylist(rows, schema=table.schema.append(pa.field("lane", pa.int32())))

    return sizes.withColumn("__one", F.lit(0)).groupBy("__one").applyInArrow(lambda t: plan(t.drop_columns(["__one"])), ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in sizes.schema) + ", lane int")
