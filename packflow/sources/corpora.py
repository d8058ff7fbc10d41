"""Keyed corpora ``(part_key, seq, text)`` over the given tables, and synthetic partition sizes."""

from __future__ import annotations

import math
from collections.abc import Callable
from statistics import NormalDist

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Joins the parts of a composite key.
SEPARATOR = "\x1f"


def load_table(spark: SparkSession, sf_dir: str, name: str, fmt: str = "parquet") -> DataFrame:
    return spark.read.format(fmt).load(f"{sf_dir}/{name}.{fmt}")


def composite(*columns: str) -> Column:
    """One string key of several columns; null if any of them is."""
    parts = [F.col(c).cast("string") for c in columns]
    joined = parts[:1]
    for p in parts[1:]:
        joined += [F.lit(SEPARATOR), p]
    return F.concat(*joined)


LINE_KEYS = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def catalog_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The order lines that have a part, by their keys alone."""
    part = load_table(spark, sf_dir, "part").select("p_partkey")
    lines = load_table(spark, sf_dir, "lineitem").select(*LINE_KEYS)
    return lines.join(part, lines.l_partkey == part.p_partkey, "left_semi")


def with_titles(lines: DataFrame, sf_dir: str) -> DataFrame:
    """Adds their part's attributes as short titles (``text``) and its brand. The part table is far smaller."""
    part = load_table(lines.sparkSession, sf_dir, "part").select("p_partkey", "p_name", "p_brand", "p_type", "p_size")
    text = F.concat_ws(" ", "p_name", "p_brand", "p_type", F.col("p_size").cast("string"), F.col("l_orderkey").cast("string"), F.col("l_linenumber").cast("string"))
    return lines.join(part, lines.l_partkey == part.p_partkey).select(*lines.columns, "p_brand", text.alias("text"))


def catalog_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with their part's attributes as short titles."""
    return with_titles(load_table(spark, sf_dir, "lineitem").select(*LINE_KEYS), sf_dir)


def numbered(df: DataFrame, *order: str) -> DataFrame:
    """``seq`` counts a partition's texts in the given order."""
    return df.withColumn("seq", F.row_number().over(Window.partitionBy("part_key").orderBy(*order)).cast("long")).select("part_key", "seq", "text")


def _by_column(column: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: catalog_lines(spark, sf_dir).select(composite(column).alias("part_key"), "text", *LINE_KEYS)


def _brand_nation(spark, sf_dir):
    supplier = load_table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    df = catalog_lines(spark, sf_dir).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    return df.select(composite("p_brand", "s_nationkey").alias("part_key"), "text", *LINE_KEYS)


#: Corpora whose texts have no number yet, with the columns that order them.
UNNUMBERED: dict[str, Callable[[SparkSession, str], DataFrame]] = {"brand_nation": _brand_nation, "supplier": _by_column("l_suppkey"), "part": _by_column("l_partkey")}


def _catalog(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: numbered(UNNUMBERED[name](spark, sf_dir), *LINE_KEYS)


def _documents(*key: str):
    return lambda spark, sf_dir: load_table(spark, sf_dir, "documents").select(composite(*key).alias("part_key"), F.col("doc_id").alias("seq"), "text")


def _web(spark, sf_dir):
    host = F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1)
    return load_table(spark, sf_dir, "pages").select(host.alias("part_key"), F.col("page_id").alias("seq"), F.regexp_replace("html", "<[^>]*>", " ").alias("text"))


def _chat(spark, sf_dir):
    return load_table(spark, sf_dir, "conversations").select(composite("conv_id").alias("part_key"), F.col("turn").cast("long").alias("seq"), F.concat_ws(": ", "role", "text").alias("text"))


def _activity(key: Callable[[], Column]):
    text = lambda: F.concat_ws(" ", "event_type", F.col("user_id").cast("string"), "props")
    return lambda spark, sf_dir: load_table(spark, sf_dir, "events").select(key().alias("part_key"), F.col("event_id").alias("seq"), text().alias("text"))


def _orders(spark, sf_dir):
    text = F.concat_ws(" ", "o_orderpriority", "o_orderstatus", F.col("o_orderkey").cast("string"))
    return load_table(spark, sf_dir, "orders").select(composite("o_custkey").alias("part_key"), F.col("o_orderkey").alias("seq"), text.alias("text"))


CORPORA: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "brand_nation": _catalog("brand_nation"),
    "supplier": _catalog("supplier"),
    "part": _catalog("part"),
    "lang_source": _documents("lang", "source"),
    "lang": _documents("lang"),
    "source": _documents("source"),
    "host": _web,
    "conversation": _chat,
    "user_day": _activity(lambda: F.concat(F.col("user_id").cast("string"), F.lit(SEPARATOR), F.to_date("ts").cast("string"))),
    "user": _activity(lambda: F.col("user_id").cast("string")),
    "event_type": _activity(lambda: F.col("event_type")),
    "customer": _orders,
}


def load_corpus(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A corpus by name. Key and text are pruned to what it needs before any Python stage."""
    return CORPORA[name](spark, sf_dir)


def load_unnumbered(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, tuple[str, ...]]:
    """(texts, order): a corpus whose texts are still to be numbered by the order's columns in each
    partition, so that whoever shuffles by partition anyway can number them on the way."""
    return (UNNUMBERED[name](spark, sf_dir), LINE_KEYS) if name in UNNUMBERED else (load_corpus(spark, sf_dir, name), ("seq",))


def lognormal_shares(parts: int, sigma: float) -> list[float]:
    """Shares of log-normal quantiles, ascending."""
    inverse = NormalDist().inv_cdf
    weights = [math.exp(sigma * inverse((k - 0.5) / parts)) for k in range(1, parts + 1)]
    total = math.fsum(weights)
    return [w / total for w in weights]


def lognormal_sizes(parts: int, texts: int, sigma: float) -> list[int]:
    """Sizes of at least 1 in log-normal proportions that sum to ``texts``: floors, then the largest
    remainders, ties in order."""
    if texts < parts:
        raise ValueError("fewer texts than partitions")
    raw = [s * (texts - parts) for s in lognormal_shares(parts, sigma)]
    sizes = [1 + math.floor(x) for x in raw]
    for k in sorted(range(parts), key=lambda k: (math.floor(raw[k]) - raw[k], k))[: texts - sum(sizes)]:
        sizes[k] += 1
    return sizes


def synthetic_sizes(spark: SparkSession, parts: int, texts: int, sigma: float, text_bytes: int = 51) -> DataFrame:
    """A size table of synthetic keys ``k00001`` ...; only metadata, one row per partition."""
    rows = [(f"k{k:05d}", n, n * text_bytes) for k, n in enumerate(lognormal_sizes(parts, texts, sigma), 1)]
    return spark.createDataFrame(rows, "part_key string, n_texts long, n_bytes long")


def assign_synthetic(df: DataFrame, sizes: DataFrame, order: list[str]) -> DataFrame:
    """Give rows the synthetic keys (``part_key``, ``seq``): global row numbers, from counts per range
    partition and running offsets, range-joined with the cumulated sizes. Both small tables, a row per task
    and a row per partition, are metadata; ``order`` must order rows fully but for equal ones. All of ``df``
    is sorted: give it narrow rows, and add texts after."""
    from packflow.operators.resume import checkpointed

    spark = df.sparkSession
    ranged = df.repartitionByRange(max(2, spark.sparkContext.defaultParallelism), *order).sortWithinPartitions(*order)
    ranged = ranged.withColumn("__task", F.spark_partition_id()).withColumn("__at", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))
    ranged = checkpointed(ranged)  # read twice, and sampled bounds must not differ
    counts = ranged.groupBy("__task").agg(F.count(F.lit(1)).alias("n"))
    offsets = counts.select("__task", (F.sum("n").over(Window.orderBy("__task")) - F.col("n")).alias("base"))
    rows = ranged.join(F.broadcast(offsets), "__task").withColumn("__id", F.col("base") + F.col("__at"))
    edges = sizes.select("part_key", (F.sum("n_texts").over(Window.orderBy("part_key")) - F.col("n_texts")).alias("low"), F.sum("n_texts").over(Window.orderBy("part_key")).alias("high"))
    return rows.join(F.broadcast(edges), (F.col("__id") >= F.col("low")) & (F.col("__id") < F.col("high"))).select("part_key", (F.col("__id") - F.col("low") + 1).alias("seq"), *df.columns)


def synthetic_corpus(spark: SparkSession, sf_dir: str, parts: int, sigma: float) -> tuple[DataFrame, int]:
    """(corpus, texts): the catalog under log-normal keys. Only keys are sorted; texts are made after."""
    keys = catalog_keys(spark, sf_dir)
    n = keys.count()
    made = assign_synthetic(keys, synthetic_sizes(spark, parts, n, sigma), list(LINE_KEYS))
    return with_titles(made, sf_dir).select("part_key", "seq", "text"), n
