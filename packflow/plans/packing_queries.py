"""Queries about sizes, pack plans and encode strategies."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from packflow.config import EncoderProfile, PackPolicy
from packflow.functions.hashing import hash_embed
from packflow.operators import encode, packing, sizes
from packflow.plans import sql
from packflow.plans.registry import query
from packflow.sources.corpora import CORPORA, load_corpus, load_unnumbered, synthetic_corpus, synthetic_sizes

DIM = 64
ENCODER = EncoderProfile("hash64", DIM)
SMALL_CORPORA = [c for c in CORPORA if c not in ("part", "user_day", "customer")]


def size_table(spark, sf_dir, corpus: str) -> DataFrame:
    return sizes.partition_sizes(load_corpus(spark, sf_dir, corpus))


def arrived(spark, sf_dir, corpus: str, how: str = "key") -> DataFrame:
    return sizes.arrival_order(size_table(spark, sf_dir, corpus), how)


def all_sizes(spark, sf_dir, corpora=tuple(CORPORA)) -> DataFrame:
    out = None
    for c in corpora:
        one = size_table(spark, sf_dir, c).select(F.lit(c).alias("corpus"), "part_key", "n_texts", "n_bytes")
        out = one if out is None else out.unionByName(one)
    return out


def all_sizes_sql(corpora=tuple(CORPORA)) -> str:
    return " union all ".join(f"select '{c}' as corpus, part_key, n_texts, n_bytes from ({sql.sizes(c)})" for c in corpora)


@query("partition_sizes", all_sizes_sql())
def partition_sizes(spark, sf_dir):
    return all_sizes(spark, sf_dir)


STATS = "parts, texts, n_min, n_max, round(mean, 6) as mean, round(sd, 6) as sd, median, round(cv, 6) as cv, round(std_over_median, 6) as std_over_median"


@query("size_stats", " union all ".join(f"select '{c}' as corpus, {STATS} from ({sql.stats(sql.sizes(c))})" for c in CORPORA))
def size_stats(spark, sf_dir):
    out = None
    for c in CORPORA:
        one = sizes.size_stats(size_table(spark, sf_dir, c)).selectExpr(f"'{c}' as corpus", "parts", "texts", "n_min", "n_max", "round(mean, 6) as mean", "round(sd, 6) as sd", "median", "round(cv, 6) as cv", "round(std_over_median, 6) as std_over_median")
        out = one if out is None else out.unionByName(one)
    return out


@query("size_histogram", f"select corpus, floor(log2(n_texts) + 1e-9)::bigint as bucket, count(*)::bigint as parts, sum(n_texts)::bigint as texts from ({all_sizes_sql()}) group by 1, 2")
def size_histogram(spark, sf_dir):
    table = all_sizes(spark, sf_dir)
    return table.groupBy("corpus", F.floor(F.log2("n_texts") + 1e-9).cast("long").alias("bucket")).agg(F.count(F.lit(1)).alias("parts"), F.sum("n_texts").alias("texts"))


# -- plans ---------------------------------------------------------------------------------------------

COLUMNS = "lane, pack_id, part_key, chunk, n, reason"
BY_PART = PackPolicy(2000, 10_000)
TIGHT = {(c, o): PackPolicy(500, 1000, c, o) for c in ("before", "after") for o in ("own", "split")}


def plan_sql(corpus: str, policy: PackPolicy, columns: str = COLUMNS) -> str:
    return f"select {columns} from {sql.policy(sql.arrival(sql.sizes(corpus)), policy)} p"


def plan_of(spark, sf_dir, corpus: str, policy: PackPolicy) -> DataFrame:
    return packing.greedy_pack(arrived(spark, sf_dir, corpus), policy)


@query("greedy_pack_plan", plan_sql("part", BY_PART))
def greedy_pack_plan(spark, sf_dir):
    return plan_of(spark, sf_dir, "part", BY_PART).select(*COLUMNS.split(", "))


def _register_policy(name: str, corpus: str, policy: PackPolicy) -> None:
    @query(name, plan_sql(corpus, policy))
    def run(spark, sf_dir):
        return plan_of(spark, sf_dir, corpus, policy).select(*COLUMNS.split(", "))


_register_policy("pack_after_ceiling", "brand_nation", TIGHT["after", "own"])
_register_policy("pack_before_ceiling", "brand_nation", TIGHT["before", "own"])
_register_policy("pack_oversize_own", "event_type", TIGHT["before", "own"])
_register_policy("pack_oversize_split", "event_type", TIGHT["before", "split"])
_register_policy("pack_after_split", "event_type", TIGHT["after", "split"])


@query("reassemble_split", f"select part_key, count(*)::bigint as pieces, sum(n)::bigint as n_texts, (max(chunk) + 1)::bigint as last_piece, count(distinct pack_id)::bigint as packs from {sql.policy(sql.arrival(sql.sizes('event_type')), TIGHT['before', 'split'])} p group by part_key")
def reassemble_split(spark, sf_dir):
    return packing.reassembled(plan_of(spark, sf_dir, "event_type", TIGHT["before", "split"]))


@query("pack_bounds", plan_sql("part", BY_PART, "lane, pack_id, part_key, chunk, n, start_off, end_off"))
def pack_bounds(spark, sf_dir):
    return packing.pack_bounds(plan_of(spark, sf_dir, "part", BY_PART))


@query("pack_members", f"select pack_id, count(*)::bigint as parts, string_agg(part_key, ',' order by arrival) as members from {sql.policy(sql.arrival(sql.sizes('part')), BY_PART)} p group by pack_id")
def pack_members(spark, sf_dir):
    members = F.array_sort(F.collect_list(F.struct("arrival", "part_key")))
    return plan_of(spark, sf_dir, "part", BY_PART).groupBy("pack_id").agg(F.count(F.lit(1)).alias("parts"), F.array_join(F.transform(members, lambda m: m["part_key"]), ",").alias("members"))


@query("flush_summary", f"select reason, count(*)::bigint as packs, sum(parts)::bigint as parts, sum(n)::bigint as texts, max(n)::bigint as largest, round(avg(parts), 6) as parts_per_pack from ({sql.totals(sql.policy(sql.arrival(sql.sizes('part')), BY_PART))}) group by reason")
def flush_summary(spark, sf_dir):
    totals = packing.pack_totals(plan_of(spark, sf_dir, "part", BY_PART))
    return totals.groupBy("reason").agg(F.count(F.lit(1)).alias("packs"), F.sum("parts").alias("parts"), F.sum("n").alias("texts"), F.max("n").alias("largest"), F.round(F.avg("parts"), 6).alias("parts_per_pack"))


PREFIX = f"select 0 as lane, floor((sum(n_texts) over (order by arrival) - n_texts) / 2000)::bigint as pack_id, part_key, n_texts as n from ({sql.arrival(sql.sizes('part'))})"


@query("prefix_pack_plan", PREFIX)
def prefix_pack_plan(spark, sf_dir):
    return packing.prefix_pack(arrived(spark, sf_dir, "part"), 2000).select("lane", "pack_id", "part_key", "n")


LPT = f"""with recursive s as (select *, row_number() over (order by n_texts desc, part_key) as pos from ({sql.sizes('brand_nation')})), walk as (
    select pos, part_key, n_texts, 1::bigint as lane, [n_texts, 0, 0, 0, 0, 0, 0, 0]::bigint[] as loads from s where pos = 1
    union all
    select pos, part_key, n_texts, lane, list_concat(list_append(loads[1:lane - 1], loads[lane] + n_texts), loads[lane + 1:])
    from (select s.pos, s.part_key, s.n_texts, w.loads, list_position(w.loads, list_min(w.loads))::bigint as lane from walk w join s on s.pos = w.pos + 1))
select part_key, n_texts, (lane - 1)::integer as lane from walk"""


@query("lane_assignment_lpt", LPT)
def lane_assignment_lpt(spark, sf_dir):
    """Longest partition first, each to the least loaded lane."""
    return sizes.assign_lanes(size_table(spark, sf_dir, "brand_nation"), 8, "lpt").select("part_key", "n_texts", "lane")


@query("greedy_jump_equals_scan", f"select pack_id, part_key, n from {sql.policy(sql.arrival(sql.sizes('part')), PackPolicy(2000, 10**9, 'after', 'own'))} p")
def greedy_jump_plan(spark, sf_dir):
    return packing.greedy_jump(arrived(spark, sf_dir, "part"), 2000).select("pack_id", "part_key", "n")


NEXT_FIT = f"""with recursive s as ({sql.arrival(sql.sizes('part'))}), walk as (
    select arrival, part_key, n_texts as n, 0::bigint as pack_id, n_texts as held from s where arrival = 1
    union all
    select s.arrival, s.part_key, s.n_texts, w.pack_id + (w.held + s.n_texts > 2000)::bigint, case when w.held + s.n_texts > 2000 then s.n_texts else w.held + s.n_texts end
    from walk w join s on s.arrival = w.arrival + 1)
select pack_id, part_key, n from walk"""


@query("next_fit_pack", NEXT_FIT)
def next_fit_pack(spark, sf_dir):
    return packing.next_fit_pack(arrived(spark, sf_dir, "part"), 2000).select("pack_id", "part_key", "n")


#: First fit as a walk with the bins' loads in a list.
FFD = f"""with recursive s as (select *, row_number() over (order by n_texts desc, part_key) as pos from ({sql.sizes('lang_source')})), walk as (
    select pos, part_key, n_texts as n, 1::bigint as bin, [n_texts] as loads from s where pos = 1
    union all
    select pos, part_key, n, bin, case when bin > len(loads) then list_append(loads, n) else list_concat(list_append(loads[1:bin - 1], loads[bin] + n), loads[bin + 1:]) end
    from (select s.pos, s.part_key, s.n_texts as n, w.loads,
            coalesce((select min(i) from unnest(range(1, len(w.loads) + 1)) r(i) where w.loads[i] + s.n_texts <= 100), len(w.loads) + 1)::bigint as bin
          from walk w join s on s.pos = w.pos + 1))
select bin - 1 as pack_id, part_key, n from walk"""


@query("ffd_pack", FFD)
def ffd_pack(spark, sf_dir):
    return packing.ffd_pack(size_table(spark, sf_dir, "lang_source"), 100).select("pack_id", "part_key", "n")


LANE = "coalesce(('0x' || substr(md5(part_key), 1, 8))::bigint % 8, 0)::integer"


@query("lane_assignment_hash", f"select part_key, n_texts, {LANE} as lane from ({sql.sizes('brand_nation')})")
def lane_assignment_hash(spark, sf_dir):
    return sizes.assign_lanes(size_table(spark, sf_dir, "brand_nation"), 8).select("part_key", "n_texts", "lane")


@query("lane_balance", f"""select how, lane, count(*)::bigint as parts, sum(n_texts)::bigint as texts from (
    select 'hash' as how, {LANE} as lane, n_texts from ({sql.sizes('brand_nation')})
    union all select 'range', least(7, floor((sum(n_texts) over (order by part_key) - n_texts) * 8.0::double / sum(n_texts) over ()))::integer, n_texts from ({sql.sizes('brand_nation')})) group by how, lane""")
def lane_balance(spark, sf_dir):
    table, out = size_table(spark, sf_dir, "brand_nation"), None
    for how in ("hash", "range"):
        one = sizes.assign_lanes(table, 8, how).groupBy(F.lit(how).alias("how"), "lane").agg(F.count(F.lit(1)).alias("parts"), F.sum("n_texts").alias("texts"))
        out = one if out is None else out.union(one)
    return out


@query("lane_plan", f"select lane, pack_id, part_key, chunk, n, reason from {sql.greedy(sql.arrival(sql.sizes('brand_nation')), '500', '2500', by=LANE)} p")
def lane_plan(spark, sf_dir):
    return packing.greedy_pack(arrived(spark, sf_dir, "brand_nation"), PackPolicy(500, 2500), lanes=8).select(*COLUMNS.split(", "))


# -- encode strategies -------------------------------------------------------------------------------------

ENCODE = PackPolicy(600, 3000)
ENCODE_DOCS = PackPolicy(20, 100)
CATALOG_SUMS = sql.checksums("brand_nation", DIM)
DOC_SUMS = sql.checksums("lang_source", DIM)


@query("stream_pack_encode", CATALOG_SUMS)
def stream_pack_encode(spark, sf_dir):
    """Lanes number the texts themselves: one exchange of texts, no window before it."""
    corpus, order = load_unnumbered(spark, sf_dir, "brand_nation")
    lanes = 4 * max(8, spark.sparkContext.defaultParallelism)
    return encode.stream_pack_encode(corpus, ENCODE, ENCODER, lanes, "checksums", order=order, lane=sizes.own_lane_of)


@query("stream_pack_docs", DOC_SUMS)
def stream_pack_docs(spark, sf_dir):
    return encode.stream_pack_encode(load_corpus(spark, sf_dir, "lang_source"), ENCODE_DOCS, ENCODER, lanes=4, what="checksums")


@query("per_partition_encode", CATALOG_SUMS)
def per_partition_encode(spark, sf_dir):
    return encode.per_partition_encode(load_corpus(spark, sf_dir, "brand_nation"), ENCODER, "checksums")


@query("fixed_batch_encode", CATALOG_SUMS)
def fixed_batch_encode(spark, sf_dir):
    return encode.fixed_batch_encode(load_corpus(spark, sf_dir, "brand_nation"), 600, ENCODER, "checksums")


@query("planned_ffd_encode", DOC_SUMS)
def planned_ffd_encode(spark, sf_dir):
    corpus = load_corpus(spark, sf_dir, "lang_source")
    return encode.planned_encode(corpus, packing.ffd_pack(sizes.partition_sizes(corpus), 100), ENCODER, "checksums")


@query("hash_embed_columns", DOC_SUMS)
def hash_embed_columns(spark, sf_dir):
    return hash_embed(load_corpus(spark, sf_dir, "lang_source"), DIM, "part_key", "seq")


SYNC = "select count(*)::bigint as texts, count(distinct part_key)::bigint as parts, 0::bigint as differing from (" + sql.CORPORA["conversation"] + ")"


@query("serialize_paths_agree", SYNC)
def serialize_paths_agree(spark, sf_dir):
    corpus, out = load_corpus(spark, sf_dir, "conversation"), []
    for how in ("zero_copy", "naive"):
        v = encode.stream_pack_encode(corpus, PackPolicy(50, 250), ENCODER, lanes=4, serialize=how)
        out.append(v.select("part_key", "seq", F.xxhash64("embedding").alias(f"h_{how}")))
    return out[0].join(out[1], ["part_key", "seq"], "full").agg(F.count(F.lit(1)).alias("texts"), F.countDistinct("part_key").alias("parts"), F.coalesce(F.sum((~F.col("h_zero_copy").eqNullSafe(F.col("h_naive"))).cast("long")), F.lit(0)).alias("differing"))


@query("strategies_agree", f"select count(*)::bigint as texts, 5::bigint as strategies, 0::bigint as differing from ({sql.CORPORA['conversation']})")
def strategies_agree(spark, sf_dir):
    """Every strategy gives the same checksum for every text."""
    corpus = load_corpus(spark, sf_dir, "conversation")
    plan = packing.ffd_pack(sizes.partition_sizes(corpus), 60)
    made = [
        encode.stream_pack_encode(corpus, PackPolicy(50, 250), ENCODER, 4, "checksums"),
        encode.stream_pack_encode(corpus, PackPolicy(50, 60, "after", "own", strict=False), ENCODER, 3, "checksums"),
        encode.per_partition_encode(corpus, ENCODER, "checksums"),
        encode.fixed_batch_encode(corpus, 64, ENCODER, "checksums"),
        encode.planned_encode(corpus, plan, ENCODER, "checksums"),
    ]
    rows = None
    for k, m in enumerate(made):
        one = m.withColumn("strategy", F.lit(k))
        rows = one if rows is None else rows.unionByName(one)
    each = rows.groupBy("part_key", "seq").agg(F.countDistinct("weighted", "squares", "touched").alias("values"), F.count(F.lit(1)).alias("times"))
    return each.agg(F.count(F.lit(1)).alias("texts"), F.max("times").alias("strategies"), F.sum(((F.col("values") != 1) | (F.col("times") != 5)).cast("long")).alias("differing"))


@query("boundary_marks", f"""select part_key, seq, starts, run from (select part_key, seq, (lag(part_key) over w is distinct from part_key)::int as starts,
    sum(st) over (order by part_key, seq)::bigint as run from (select *, (lag(part_key) over (order by part_key, seq) is distinct from part_key)::int as st from ({sql.CORPORA['conversation']})) window w as (order by part_key, seq))""")
def boundary_marks(spark, sf_dir):
    """Key changes by a window: the SQL twin of the worker's run detection (one lane)."""
    w = Window.orderBy("part_key", "seq")
    marked = load_corpus(spark, sf_dir, "conversation").withColumn("starts", (~F.lag("part_key").over(w).eqNullSafe(F.col("part_key"))).cast("int"))
    return marked.select("part_key", "seq", "starts", F.sum("starts").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("run"))


# -- workloads: counts, bounds, sweeps ------------------------------------------------------------------------

SHARES = (0.001, 0.005, 0.01, 0.02, 0.05)


@query("threshold_sweep", " union all ".join(
    f"select {s}::double as share, count(*)::bigint as packs, max(n)::bigint as largest, round(avg(n), 6) as mean_pack, round(avg(parts), 6) as parts_per_pack, round(count(*) * 0.087 + sum(n) * 0.149 / 1000 / 4, 6) as wall from "
    f"({sql.totals(sql.greedy(f'select *, ceil((sum(n_texts) over ()) * {int(s * 1000)} / 1000)::bigint as bm from ({sql.arrival(sql.sizes("user_day"))})', 'bm', '(5 * bm)'))})" for s in SHARES))
def threshold_sweep(spark, sf_dir):
    """Flushes, parts per pack and predicted time over b_min; b_max is five times that."""
    table = arrived(spark, sf_dir, "user_day").cache()
    n, out = table.agg(F.sum("n_texts")).first()[0], None
    for s in SHARES:
        totals = packing.pack_totals(packing.greedy_pack(table, PackPolicy(b := -(-n * int(s * 1000) // 1000), 5 * b)))
        one = totals.agg(F.count(F.lit(1)).alias("packs"), F.max("n").alias("largest"), F.round(F.avg("n"), 6).alias("mean_pack"), F.round(F.avg("parts"), 6).alias("parts_per_pack"), F.round(F.count(F.lit(1)) * 0.087 + F.sum("n") * 0.149 / 1000 / 4, 6).alias("wall")).select(F.lit(s).alias("share"), "*")
        out = one if out is None else out.unionByName(one)
    return out


SIGMAS, PARTS = (1.0, 1.72, 2.5), 400


def _sigma_sql(s: float) -> str:
    source = f"select *, ceil((sum(n_texts) over ()) / 100)::bigint as bm from ({sql.arrival(sql.synthetic(PARTS, s), 'md5(part_key)')})"
    return f"select {s}::double as sigma, count(*)::bigint as packs, sum(parts)::bigint as units, max(n)::bigint as largest, count(*) filter (reason in ('ceiling', 'oversize'))::bigint as by_ceiling from ({sql.totals(sql.greedy(source, 'bm', '(5 * bm)'))})"


@query("sigma_sweep_packs", " union all ".join(map(_sigma_sql, SIGMAS)))
def sigma_sweep_packs(spark, sf_dir):
    """Packs over the spread of sizes: the ceiling only acts for the widest."""
    n, out = spark.read.parquet(f"{sf_dir}/lineitem.parquet").count(), None
    for s in SIGMAS:
        table = sizes.arrival_order(synthetic_sizes(spark, PARTS, n, s), "md5")
        totals = packing.pack_totals(packing.greedy_pack(table, PackPolicy(b := -(-n // 100), 5 * b)))
        one = totals.agg(F.count(F.lit(1)).alias("packs"), F.sum("parts").alias("units"), F.max("n").alias("largest"), F.sum(F.col("reason").isin("ceiling", "oversize").cast("long")).alias("by_ceiling")).select(F.lit(s).alias("sigma"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("sigma_sizes", " union all ".join(f"select {s}::double as sigma, part_key, n_texts from ({sql.synthetic(PARTS, s)})" for s in SIGMAS))
def sigma_sizes(spark, sf_dir):
    n, out = spark.read.parquet(f"{sf_dir}/lineitem.parquet").count(), None
    for s in SIGMAS:
        one = synthetic_sizes(spark, PARTS, n, s).select(F.lit(s).alias("sigma"), "part_key", "n_texts")
        out = one if out is None else out.union(one)
    return out


ORDER_SQL = {
    "key": "part_key", "md5": "md5(part_key), part_key", "size_asc": "n_texts, part_key", "size_desc": "n_texts desc, part_key",
    "largest_last": "(part_key = (select part_key from s order by n_texts desc, part_key limit 1)), part_key",
    "near_full_then_largest": "case when part_key = (select part_key from s order by n_texts desc, part_key limit 1) then 1 when run < 600 then 0 else 2 end, n_texts, part_key",
}
BOUNDS = [(c, o) for c in ("before", "after") for o in ("own", "split")]
ADVERSE = {(c, o): PackPolicy(600, 1200, c, o) for c, o in BOUNDS}


def _order_sql(how: str, c: str, o: str) -> str:
    source = f"select *, row_number() over (order by {ORDER_SQL[how]})::bigint as arrival from s"
    return f"select '{how}' as arrival_order, '{c}' as ceiling, '{o}' as oversize, count(*)::bigint as packs, max(n)::bigint as largest from ({sql.totals(sql.policy(source, ADVERSE[c, o]))})"


@query("arrival_order_bounds", "with s0 as (" + sql.synthetic(100, 1.72, "20000") + "), s as (select *, sum(n_texts) over (order by n_texts, part_key) as run from s0), b as (" + " union all ".join(_order_sql(h, c, o) for h in ORDER_SQL for c, o in BOUNDS) + ") select *, true as within from b")
def arrival_order_bounds(spark, sf_dir):
    """Largest packs under adverse orders against the policy's bound."""
    table, out = synthetic_sizes(spark, 100, 20_000, 1.72).cache(), None
    n_max = table.agg(F.max("n_texts")).first()[0]
    for how in ORDER_SQL:
        ordered = sizes.arrival_order(table, how, 600)
        for c, o in BOUNDS:
            one = packing.pack_totals(packing.greedy_pack(ordered, ADVERSE[c, o])).agg(F.count(F.lit(1)).alias("packs"), F.max("n").alias("largest"))
            one = one.select(F.lit(how).alias("arrival_order"), F.lit(c).alias("ceiling"), F.lit(o).alias("oversize"), "*", (F.col("largest") <= ADVERSE[c, o].bound(n_max)).alias("within"))
            out = one if out is None else out.unionByName(one)
    return out


@query("memory_bound_holds", " union all ".join(
    f"select '{c}' as ceiling, '{o}' as oversize, count(*)::bigint as packs, max(n)::bigint as largest, (select {expr} from s)::bigint as bound, (max(n) <= (select {expr} from s)) as holds from ({sql.totals(sql.policy(sql.arrival(sql.sizes('event_type')), TIGHT[c, o]))})"
    for c, o, expr in (("before", "own", "greatest(1000, max(n_texts))"), ("before", "split", "1000 + 0 * max(n_texts)"), ("after", "own", "499 + max(n_texts)"), ("after", "split", "499 + least(1000, max(n_texts))"))
).replace("from s)", f"from ({sql.sizes('event_type')}))"))
def memory_bound_holds(spark, sf_dir):
    table, out = arrived(spark, sf_dir, "event_type"), None
    n_max = table.agg(F.max("n_texts")).first()[0]
    for (c, o), policy in TIGHT.items():
        one = packing.pack_totals(packing.greedy_pack(table, policy)).agg(F.count(F.lit(1)).alias("packs"), F.max("n").alias("largest"))
        one = one.select(F.lit(c).alias("ceiling"), F.lit(o).alias("oversize"), "*", F.lit(policy.bound(n_max)).cast("long").alias("bound"), (F.col("largest") <= policy.bound(n_max)).alias("holds"))
        out = one if out is None else out.unionByName(one)
    return out


@query("synthetic_catalog", f"select part_key, n_texts, n_texts as last_seq from ({sql.synthetic(PARTS, 1.72)})")
def synthetic_catalog(spark, sf_dir):
    """The catalog's rows under log-normal keys: the main workload's corpus, counted."""
    rows, _ = synthetic_corpus(spark, sf_dir, PARTS, 1.72)
    return rows.groupBy("part_key").agg(F.count(F.lit(1)).alias("n_texts"), F.max("seq").alias("last_seq"))


@query("synthetic_encode", f"""with lines as (select *, row_number() over (order by l_orderkey, l_linenumber, l_partkey, l_suppkey) - 1 as id from ({sql.CATALOG})), edges as (
    select part_key, sum(n_texts) over (order by part_key) - n_texts as low, sum(n_texts) over (order by part_key) as high from ({sql.synthetic(PARTS, 1.72)}))
    select part_key, count(*)::bigint as n_texts, sum(weighted)::bigint as weighted, sum(squares)::bigint as squares from (
        {sql.checksums('select part_key, id as seq, text from lines join edges on id >= low and id < high', DIM)}) group by part_key""")
def synthetic_encode(spark, sf_dir):
    """The main workload end to end: log-normal partitions, packed, encoded, summed by partition."""
    corpus, n = synthetic_corpus(spark, sf_dir, PARTS, 1.72)
    made = encode.stream_pack_encode(corpus, PackPolicy.for_texts(n), ENCODER, lanes=8, what="checksums", lane=sizes.own_lane_of)
    return made.groupBy("part_key").agg(F.count(F.lit(1)).alias("n_texts"), F.sum("weighted").alias("weighted"), F.sum("squares").alias("squares"))
