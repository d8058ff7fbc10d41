"""Queries through the user-facing surface: data sources, table functions, column functions."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import functions as F

from packflow.functions import tables
from packflow.operators import packing
from packflow.operators.encode import encode_udf, stream_pack_encode
from packflow.operators.resume import shared_root
from packflow.plans import sql
from packflow.plans.packing_queries import ENCODER, TIGHT, PackPolicy, plan_of, size_table
from packflow.plans.registry import query
from packflow.sources import datasource
from packflow.sources.corpora import catalog_lines, load_corpus, synthetic_corpus


@query("split_oversized_udtf", f"select part_key, u.chunk::int as chunk, least(1000, n_texts - u.chunk * 1000)::bigint as n from ({sql.sizes('event_type')}) s, unnest(range(0, ceil(n_texts / 1000.0)::bigint)) u(chunk)")
def split_oversized_udtf(spark, sf_dir):
    tables.register(spark)
    size_table(spark, sf_dir, "event_type").createOrReplaceTempView("packflow_sizes")
    return spark.sql("select u.* from packflow_sizes s, lateral split_oversized(s.part_key, s.n_texts, 1000) u")


@query("pack_report_udtf", f"select lane::int as lane, count(*)::bigint as packs, sum(n)::bigint as texts, max(n)::bigint as largest, count(*) filter (reason in ('ceiling', 'oversize'))::bigint as by_ceiling from ({sql.totals(sql.policy(sql.arrival(sql.sizes('event_type')), TIGHT['before', 'split']))}) group by lane")
def pack_report_udtf(spark, sf_dir):
    tables.register(spark)
    packing.pack_totals(plan_of(spark, sf_dir, "event_type", TIGHT["before", "split"])).createOrReplaceTempView("packflow_packs")
    return spark.sql("select * from pack_report(table(packflow_packs) partition by lane)")


@query("lognormal_source", f"select part_key, n_texts from ({sql.synthetic(100, 1.72)})")
def lognormal_source(spark, sf_dir):
    """The texts of all order lines under log-normal keys, counted by key."""
    texts, _ = synthetic_corpus(spark, sf_dir, 100, 1.72)
    return texts.groupBy("part_key").agg(F.count("text").alias("n_texts"))


@query("packed_vectors_sink", f"select part_key, count(*)::bigint as n_texts from ({sql.CORPORA['conversation']}) group by part_key")
def packed_vectors_sink(spark, sf_dir):
    """Vectors in one file per task, found again through the boundary index."""
    datasource.register(spark)
    root = f"{shared_root(spark)}/packed-{uuid.uuid4().hex}"
    stream_pack_encode(load_corpus(spark, sf_dir, "conversation"), PackPolicy(50, 250), ENCODER, lanes=4).write.format("packed_vectors").mode("append").option("path", root).save()
    index = spark.read.option("pathGlobFilter", "*.index.parquet").parquet(root)
    return index.groupBy("part_key").agg(F.sum(F.col("end") - F.col("start")).alias("n_texts"))


@query("encode_column", "select doc_id, 64::bigint as dim, 1.0::double as norm from documents")
def encode_column(spark, sf_dir):
    """The plain vectorised function: one-off use without packs."""
    encode = encode_udf(ENCODER)
    d = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", encode("text").alias("e"))
    norm = F.sqrt(F.aggregate("e", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    return d.select("doc_id", F.size("e").cast("long").alias("dim"), F.round(norm, 4).alias("norm"))


RUNS = sql.CORPORA["conversation"]
PACKED = sql.totals(sql.policy(sql.arrival(sql.sizes("conversation")), PackPolicy(50, 250)))


@query("compare_strategies", f"""select 'per_partition' as strategy, count(*)::bigint as calls, sum(n_texts)::bigint as texts, max(n_texts)::bigint as largest from ({sql.sizes('conversation')})
    union all select 'packed', count(*)::bigint, sum(n)::bigint, max(n)::bigint from ({PACKED})
    union all select 'fixed', ceil(count(*) / 50.0)::bigint, count(*)::bigint, 50 from ({RUNS})""")
def compare_strategies(spark, sf_dir):
    """Live runs of the strategies on one corpus: calls and largest calls from their ledgers."""
    from packflow.operators.compare import compare_strategies as compare

    corpus = load_corpus(spark, sf_dir, "conversation").coalesce(1)
    runs = {"per_partition": {"kind": "per_partition"}, "packed": {"kind": "packed", "policy": PackPolicy(50, 250)}, "fixed": {"kind": "fixed", "size": 50}}
    return compare(corpus, runs, ENCODER).select("strategy", "calls", "texts", "largest")


@query("preview_lane", f"select part_key, count(*)::bigint as n_texts from ({RUNS}) where ('0x' || substr(md5(part_key), 1, 8))::bigint % 8 = 3 group by part_key")
def preview_lane(spark, sf_dir):
    from packflow.operators.compare import first_partitions

    return first_partitions(load_corpus(spark, sf_dir, "conversation"), PackPolicy(50, 250), ENCODER, 8, 3).groupBy("part_key").agg(F.count(F.lit(1)).alias("n_texts"))


@query("call_size_percentiles", f"select reason, round(quantile_cont(n, 0.95), 6) as p95, round(quantile_cont(n, 0.5), 6) as median from ({PACKED}) group by reason")
def call_size_percentiles(spark, sf_dir):
    """A grouped-aggregate vectorised function over a live ledger: percentiles of call sizes by reason."""

    @F.pandas_udf("double")
    def p95(n: pd.Series) -> float:
        return float(n.quantile(0.95))

    @F.pandas_udf("double")
    def median(n: pd.Series) -> float:
        return float(n.median())

    led = stream_pack_encode(load_corpus(spark, sf_dir, "conversation"), PackPolicy(50, 250), ENCODER, lanes=1, what="ledger")
    return led.groupBy("reason").agg(F.round(p95("n_texts"), 6).alias("p95"), F.round(median("n_texts"), 6).alias("median"))


SNIPPET = 8
SNIPPETS = f"select ceil(len(string_split(text, ' ')) / {SNIPPET}.0) as texts, len(string_split(text, ' ')) as words, strlen(text) as bytes from documents"


@query("synthetic_vs_natural", f"""select 'titles' as source, count(*)::bigint as texts, round(sum(len(string_split(text, ' ')))::double / count(*), 6) as words, round(sum(strlen(text))::double / count(*), 6) as bytes from ({sql.CATALOG})
    union all select 'snippets', sum(texts)::bigint, round(sum(words)::double / sum(texts), 6), round((sum(bytes) - sum(texts) + count(*))::double / sum(texts), 6) from ({SNIPPETS})""")
def synthetic_vs_natural(spark, sf_dir):
    """Made-up titles against whole documents cut into snippets of about their length: texts, words and bytes
    of each, which are what a call's time depends on."""
    words = lambda: F.size(F.split("text", " ")).cast("long")
    titles = catalog_lines(spark, sf_dir).agg(F.count(F.lit(1)).alias("texts"), F.sum(words()).alias("words"), F.sum(F.octet_length("text")).alias("bytes"))
    parts = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.explode(snippets(F.col("text"))).alias("text"))
    cut = parts.agg(F.count(F.lit(1)).alias("texts"), F.sum(words()).alias("words"), F.sum(F.octet_length("text")).alias("bytes"))
    out = titles.select(F.lit("titles").alias("source"), "*").unionByName(cut.select(F.lit("snippets").alias("source"), "*"))
    return out.select("source", "texts", *(F.round(F.col(c) / F.col("texts").cast("double"), 6).alias(c) for c in ("words", "bytes")))


def snippets(text, words: int = SNIPPET):
    """All of a text in pieces of so many words."""
    split = F.split(text, " ")
    return F.transform(F.sequence(F.lit(0), F.size(split) - 1, F.lit(words)), lambda at: F.array_join(F.slice(split, at + 1, F.lit(words)), " "))
