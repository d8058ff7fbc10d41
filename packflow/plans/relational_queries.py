"""Relational operators that users need around packing: scans, joins, windows, sets, vectors, resume, sinks."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from packflow.operators import packing
from packflow.operators.resume import pending_partitions
from packflow.operators.sizes import md5_number
from packflow.plans import sql
from packflow.plans.packing_queries import BY_PART, ENCODER, PackPolicy, arrived, plan_of, size_table
from packflow.plans.registry import query
from packflow.sources.corpora import catalog_lines, load_corpus, load_table

# -- scans, filters, strings -------------------------------------------------------------------------------


@query("corpus_scan", "select corpus, count(*)::bigint as texts, sum(strlen(text))::bigint as bytes from (" + " union all ".join(f"select '{c}' as corpus, text from ({q})" for c, q in sql.CORPORA.items()) + ") group by corpus")
def corpus_scan(spark, sf_dir):
    out = None
    for c in sql.CORPORA:
        one = load_corpus(spark, sf_dir, c).agg(F.count(F.lit(1)).alias("texts"), F.sum(F.octet_length("text")).alias("bytes")).select(F.lit(c).alias("corpus"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("filter_project", "select doc_id, lang || chr(31) || source as part_key, strlen(text)::bigint as n_bytes from documents where lang in ('fr', 'de') and length(text) between 500 and 5000")
def filter_project(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents").where(F.col("lang").isin("fr", "de") & F.length("text").between(500, 5000))
    return d.select("doc_id", F.concat("lang", F.lit("\x1f"), "source").alias("part_key"), F.octet_length("text").cast("long").alias("n_bytes"))


@query("catalog_texts", f"select l_orderkey, l_linenumber, l_partkey, l_suppkey, text from ({sql.CATALOG})")
def catalog_texts(spark, sf_dir):
    return catalog_lines(spark, sf_dir).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "text")


@query("order_line_texts", "select l_orderkey, l_linenumber, l_partkey, concat_ws(' ', o_orderpriority, o_orderstatus, l_returnflag, l_linestatus) as text from lineitem join orders on l_orderkey = o_orderkey")
def order_line_texts(spark, sf_dir):
    """Two large sides: left to a sort-merge join."""
    lines = load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_returnflag", "l_linestatus")
    orders = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority", "o_orderstatus")
    joined = lines.hint("merge").join(orders.hint("merge"), lines.l_orderkey == orders.o_orderkey)
    return joined.select("l_orderkey", "l_linenumber", "l_partkey", F.concat_ws(" ", "o_orderpriority", "o_orderstatus", "l_returnflag", "l_linestatus").alias("text"))


@query("labelled_docs", "select doc_id, lang from documents where doc_id in (select doc_id from labels where quality = 1)")
def labelled_docs(spark, sf_dir):
    good = load_table(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    return load_table(spark, sf_dir, "documents").select("doc_id", "lang").join(good, "doc_id", "left_semi")


@query("page_hosts", "select regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) as host, count(*)::bigint as pages, sum(length(regexp_replace(html, '<[^>]*>', ' ', 'g')))::bigint as chars from pages group by 1")
def page_hosts(spark, sf_dir):
    p = load_table(spark, sf_dir, "pages")
    return p.groupBy(F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host")).agg(F.count(F.lit(1)).alias("pages"), F.sum(F.length(F.regexp_replace("html", "<[^>]*>", " "))).cast("long").alias("chars"))


@query("token_counts", "select doc_id, len(string_split(text, ' '))::bigint as tokens, list_unique(string_split(lower(translate(text, '.,!?', '    ')), ' '))::bigint as distinct_tokens from documents")
def token_counts(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents")
    return d.select("doc_id", F.size(F.split("text", " ")).cast("long").alias("tokens"), F.size(F.array_distinct(F.split(F.lower(F.translate("text", ".,!?", "    ")), " "))).cast("long").alias("distinct_tokens"))


@query("user_day_sizes", "select user_id, strftime(ts, '%Y-%m-%d') as day, count(*)::bigint as n_texts, date_sub('second', min(ts), max(ts))::bigint as span_s from events group by 1, 2")
def user_day_sizes(spark, sf_dir):
    e = load_table(spark, sf_dir, "events").select("user_id", "ts", F.to_date("ts").cast("string").alias("day"))
    return e.groupBy("user_id", "day").agg(F.count(F.lit(1)).alias("n_texts"), F.timestamp_diff("second", F.min("ts"), F.max("ts")).alias("span_s"))


@query("event_props", "select json_extract_string(props, '$.k') as k, event_type, count(*)::bigint as n from events group by 1, 2")
def event_props(spark, sf_dir):
    return load_table(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").alias("k"), "event_type").agg(F.count(F.lit(1)).alias("n"))


# -- hierarchies -------------------------------------------------------------------------------------------------

HIERARCHY = "select r_name, n_name, s_suppkey, count(*)::bigint as n_texts from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by all"


def hierarchy(spark, sf_dir):
    s = load_table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    n = load_table(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey")
    r = load_table(spark, sf_dir, "region").select("r_regionkey", "r_name")
    lines = load_table(spark, sf_dir, "lineitem").select("l_suppkey")
    return lines.join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(n, F.col("s_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))


@query("size_rollup", f"select r_name, n_name, s_suppkey, sum(n_texts)::bigint as n_texts, grouping(r_name, n_name, s_suppkey)::bigint as level from ({HIERARCHY}) group by rollup (r_name, n_name, s_suppkey)")
def size_rollup(spark, sf_dir):
    return hierarchy(spark, sf_dir).rollup("r_name", "n_name", "s_suppkey").agg(F.count(F.lit(1)).alias("n_texts"), F.grouping_id().alias("level"))


@query("size_cube", "select lang, source, count(*)::bigint as n_texts, grouping(lang, source)::bigint as level from documents group by cube (lang, source)")
def size_cube(spark, sf_dir):
    return load_table(spark, sf_dir, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n_texts"), F.grouping_id().alias("level"))


@query("size_grouping_sets", "select lang, source, count(*)::bigint as n_texts from documents group by grouping sets ((lang), (source), ())")
def size_grouping_sets(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents").select("lang", "source")
    return d.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count(F.lit(1)).alias("n_texts"))


# -- windows, ranks, samples, sets ------------------------------------------------------------------------------

BRANDS = sql.sizes("brand_nation")


@query("size_rank", f"select part_key, n_texts, rank() over (order by n_texts desc)::bigint as r, ntile(4) over (order by n_texts desc, part_key)::bigint as quarter, first_value(part_key) over (order by n_texts desc, part_key) as largest, sum(n_texts) over (order by n_texts desc, part_key rows between 2 preceding and current row)::bigint as moving from ({BRANDS})")
def size_rank(spark, sf_dir):
    w = Window.orderBy(F.col("n_texts").desc(), "part_key")
    return size_table(spark, sf_dir, "brand_nation").select(
        "part_key", "n_texts", F.rank().over(Window.orderBy(F.col("n_texts").desc())).cast("long").alias("r"), F.ntile(4).over(w).cast("long").alias("quarter"),
        F.first("part_key").over(w).alias("largest"), F.sum("n_texts").over(w.rowsBetween(-2, 0)).alias("moving"),
    )


@query("top_partitions", f"select part_key, n_texts from ({BRANDS}) order by n_texts desc, part_key limit 20")
def top_partitions(spark, sf_dir):
    """A top-k report."""
    return size_table(spark, sf_dir, "brand_nation").select("part_key", "n_texts").orderBy(F.col("n_texts").desc(), "part_key").limit(20)


@query("size_sample", f"select part_key, n_texts from ({sql.sizes('part')}) where ('0x' || substr(md5(part_key), 1, 8))::bigint % 10 = 0")
def size_sample(spark, sf_dir):
    """A portable tenth of the keys, for predicting sizes."""
    return size_table(spark, sf_dir, "part").where(md5_number(F.col("part_key")) % 10 == 0).select("part_key", "n_texts")


TWO_RUNS = f"a as (select part_key from ({BRANDS}) where n_texts % 3 <> 0), b as (select part_key from ({BRANDS}) where n_texts % 3 <> 1)"


def two_runs(spark, sf_dir):
    t = size_table(spark, sf_dir, "brand_nation")
    return t.where("n_texts % 3 <> 0").select("part_key"), t.where("n_texts % 3 <> 1").select("part_key")


@query("keys_in_both", f"with {TWO_RUNS} select part_key from a intersect select part_key from b")
def keys_in_both(spark, sf_dir):
    a, b = two_runs(spark, sf_dir)
    return a.intersect(b)


@query("lost_rows", f"with {TWO_RUNS} select part_key from a except all select part_key from b")
def lost_rows(spark, sf_dir):
    a, b = two_runs(spark, sf_dir)
    return a.exceptAll(b)


@query("resume_pending", f"with done as (select part_key from ({BRANDS}) where ('0x' || substr(md5(part_key), 1, 8))::bigint % 3 = 0) select part_key, n_texts from ({BRANDS}) where part_key not in (select part_key from done)")
def resume_pending(spark, sf_dir):
    t = size_table(spark, sf_dir, "brand_nation").select("part_key", "n_texts")
    return pending_partitions(t, t.where(md5_number(F.col("part_key")) % 3 == 0))


@query("offset_to_partition", f"""with c as (select part_key, sum(n_texts) over (order by part_key) - n_texts as low, sum(n_texts) over (order by part_key) as high from ({BRANDS}))
    select unnest(range(low::bigint, high::bigint)) as row_id, part_key, unnest(range(0, (high - low)::bigint)) as inside from c""")
def offset_to_partition(spark, sf_dir):
    """Every row number up to the total of sizes to its partition."""
    return locate(spark, size_table(spark, sf_dir, "brand_nation"))


#: Row numbers of one bucket of ``locate``.
ROW_BUCKET = 1 << 16


def locate(spark, sizes, bucket: int = ROW_BUCKET):
    """(row_id, part_key, inside): a range join within equal buckets of row numbers; a partition is in
    each bucket that it reaches into."""
    w = Window.orderBy("part_key")
    edges = sizes.select("part_key", F.sum("n_texts").over(w).alias("high"), (F.sum("n_texts").over(w) - F.col("n_texts")).alias("low")).where("low < high")
    cut = edges.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("low") / bucket), F.floor((F.col("high") - 1) / bucket))))
    total = sizes.agg(F.sum("n_texts")).first()[0] or 0
    rows = spark.range(total).select(F.col("id").alias("row_id"), F.floor(F.col("id") / bucket).alias("bucket"))
    both = rows.join(cut, (rows.bucket == cut.bucket) & (F.col("row_id") >= F.col("low")) & (F.col("row_id") < F.col("high")))
    return both.select("row_id", "part_key", (F.col("row_id") - F.col("low")).alias("inside"))


@query("asof_ledger", """select event_id, (select max(f.event_id) from events f where f.event_type = 'purchase' and f.user_id = e.user_id and f.ts <= e.ts) as last_purchase from events e where event_type <> 'purchase'""")
def asof_ledger(spark, sf_dir):
    """Each event with its user's latest earlier purchase: an as-of join as one window over the union."""
    e = load_table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return e.withColumn("last_purchase", F.max(F.when(F.col("event_type") == "purchase", F.col("event_id"))).over(w)).where("event_type <> 'purchase'").select("event_id", "last_purchase")


@query("approx_measures", "select corpus, true as parts_close, true as median_close from (values " + ", ".join(f"('{c}')" for c in sql.CORPORA) + ") v(corpus)")
def approx_measures(spark, sf_dir):
    """Sketched against exact: distinct keys within five percent, and the sketched median between the exact
    quartiles."""
    out = None
    for c in sql.CORPORA:
        keys = load_corpus(spark, sf_dir, c).agg(F.approx_count_distinct("part_key", 0.02).alias("near"), F.countDistinct("part_key").alias("exact"))
        quantile = lambda f, q: F.expr(f"{f}(n_texts, {q})")
        n = size_table(spark, sf_dir, c).agg(quantile("percentile_approx", 0.5).alias("median"), quantile("percentile", 0.25).alias("low"), quantile("percentile", 0.75).alias("high"))
        one = keys.crossJoin(n).select(F.lit(c).alias("corpus"), (F.abs(F.col("near") - F.col("exact")) <= F.greatest(F.lit(1.0), 0.05 * F.col("exact"))).alias("parts_close"), F.col("median").between(F.floor("low"), F.ceil("high")).alias("median_close"))
        out = one if out is None else out.unionByName(one)
    return out


# -- vectors --------------------------------------------------------------------------------------------------


@query("vector_norms", "select vec_id, round(sqrt(list_sum([x::double * x::double for x in embedding])), 5) as norm, len(embedding)::bigint as dim from embeddings")
def vector_norms(spark, sf_dir):
    square = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return load_table(spark, sf_dir, "embeddings").select("vec_id", F.round(F.sqrt(square), 5).alias("norm"), F.size("embedding").cast("long").alias("dim"))


#: Query vectors of one broadcast block.
QUERY_BLOCK = 1024


def dot_products(e, queries, block: int = QUERY_BLOCK):
    """(query_id, vec_id, dot) of every vector with every query vector, in broadcast blocks of ``block`` queries."""
    dot = F.aggregate(F.zip_with("embedding", "q", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, x: a + x)
    queries = queries.select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("q"))
    blocks, out = max(1, -(-queries.count() // block)), None
    for b in range(blocks):
        part = queries.where(F.pmod(F.xxhash64("query_id"), F.lit(blocks)) == b)
        one = e.crossJoin(F.broadcast(part)).select("query_id", "vec_id", F.round(dot, 5).alias("dot"))
        out = one if out is None else out.union(one)
    return out


@query("vector_dot", "select b.vec_id as query_id, a.vec_id, round(list_dot_product(a.embedding::double[], b.embedding::double[]), 5) as dot from embeddings a, embeddings b where b.vec_id % 100 = 0")
def vector_dot(spark, sf_dir):
    """Every vector against every query vector, those whose id is divisible by 100."""
    e = load_table(spark, sf_dir, "embeddings")
    return dot_products(e.select("vec_id", "embedding"), e.where("vec_id % 100 = 0"))


@query("label_centroids", "select label, i::bigint as i, round(avg(x), 5) as x, count(*)::bigint as n from (select label, unnest(embedding)::double as x, unnest(range(0, len(embedding))) as i from embeddings) group by label, i")
def label_centroids(spark, sf_dir):
    e = load_table(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("i", "x"))
    return e.groupBy("label", F.col("i").cast("long").alias("i")).agg(F.round(F.avg(F.col("x").cast("double")), 5).alias("x"), F.count(F.lit(1)).alias("n"))


# -- sinks -----------------------------------------------------------------------------------------------------


@query("sink_roundtrip", sql.checksums("conversation", 64))
def sink_roundtrip(spark, sf_dir):
    """Packs are written as one file per partition by the workers, read back, and compared by checksums of
    the vectors' signed counts, which the norm lets one recover."""
    from packflow.operators.encode import PartitionFiles, stream_pack_encode
    from packflow.plans.recovery_queries import fresh_root, read_back, recovered_sums

    root, corpus = fresh_root(spark, "vectors"), load_corpus(spark, sf_dir, "conversation")
    done = stream_pack_encode(corpus, PackPolicy(50, 250), ENCODER, lanes=4, what="manifest", sink=PartitionFiles(root, "r1"))
    done.write.mode("append").parquet(f"{root}/manifest")
    return recovered_sums(read_back(spark, root, "r1"), corpus)


@query("packed_sink_roundtrip", sql.checksums("conversation", 64))
def packed_sink_roundtrip(spark, sf_dir):
    """The same through one file per task and its boundary index: rows find their key by their place."""
    from packflow.operators.encode import stream_pack_encode
    from packflow.plans.recovery_queries import fresh_root, recovered_sums
    from packflow.sources import datasource

    datasource.register(spark)
    root, corpus = fresh_root(spark, "packed"), load_corpus(spark, sf_dir, "conversation")
    stream_pack_encode(corpus, PackPolicy(50, 250), ENCODER, lanes=4).write.format("packed_vectors").mode("append").option("path", root).save()
    return recovered_sums(datasource.read_packed(spark, root), corpus)


@query("ledger_calls", f"select reason, count(*)::bigint as calls, sum(n)::bigint as texts, max(n)::bigint as largest from ({sql.totals(sql.greedy(sql.arrival(sql.sizes('brand_nation')), '600', '3000', by='coalesce((' + chr(39) + '0x' + chr(39) + ' || substr(md5(part_key), 1, 8))::bigint % 8, 0)::integer'))}) group by reason")
def ledger_calls(spark, sf_dir):
    """Calls of the online form, from its ledger, against the plan made from sizes."""
    from packflow.operators.encode import stream_pack_encode

    led = stream_pack_encode(load_corpus(spark, sf_dir, "brand_nation"), PackPolicy(600, 3000), ENCODER, lanes=8, what="ledger")
    return led.groupBy("reason").agg(F.count(F.lit(1)).alias("calls"), F.sum("n_texts").alias("texts"), F.max("n_texts").alias("largest"))


@query("online_equals_planned", f"select count(*)::bigint as packs, 0::bigint as differing from ({sql.totals(sql.policy(sql.arrival(sql.sizes('part')), BY_PART))})")
def online_equals_planned(spark, sf_dir):
    """Packs of the online form, in one lane, against those planned from sizes."""
    from packflow.operators.encode import stream_pack_encode

    led = stream_pack_encode(load_corpus(spark, sf_dir, "part"), BY_PART, ENCODER, lanes=1, what="ledger").select("pack_id", F.col("n_texts").alias("a"), F.col("reason").alias("ra"))
    plan = packing.pack_totals(plan_of(spark, sf_dir, "part", BY_PART)).select("pack_id", F.col("n").alias("b"), F.col("reason").alias("rb"))
    both = led.join(plan, "pack_id", "full")
    return both.agg(F.count(F.lit(1)).alias("packs"), F.sum((~(F.col("a").eqNullSafe(F.col("b")) & F.col("ra").eqNullSafe(F.col("rb")))).cast("long")).alias("differing"))


@query("sql_functions", "select corpus, round((1 + a) / (1 + a * 100 / parts), 6) as speedup, case when parts > 1000 then 'strong' else 'optional' end as advice from (select 'part' as corpus, count(*) as parts, count(*) * 0.087 / (sum(n_texts) * 0.149 / 1000 / 4) as a from (" + sql.sizes("part") + "))")
def sql_functions(spark, sf_dir):
    """The models called by name from SQL."""
    from packflow.functions.register import register

    register(spark)
    size_table(spark, sf_dir, "part").agg(F.count(F.lit(1)).alias("parts"), (F.count(F.lit(1)) * 0.087 / (F.sum("n_texts") * 0.149 / 1000 / 4)).alias("a")).createOrReplaceTempView("packflow_stats")
    return spark.sql("select 'part' as corpus, round(predicted_speedup(a, 100, parts), 6) as speedup, recommend(if(parts > 1000, 0.9, 0.1), if(parts > 1000, 2, 0)) as advice from packflow_stats")


__all__ = ["arrived"]
