"""The paper's main workload: every strategy's calls over log-normal partitions, and what ledgers of them tell.

A run is a method's calls over one corpus: (sigma, method, pack_id, parts, n). Runs come from the planners
over the sizes of the given tables' lines; a clock ledger gives each call its seconds, with a spread of five
percent either way by a hash of the call where constants are to be recovered from it. All measures are
aggregates over such ledgers.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from packflow.config import DOLLARS_PER_HOUR, SMALL, SWEEP, PackPolicy
from packflow.functions import models
from packflow.operators import packing
from packflow.operators.sizes import md5_number
from packflow.plans import sql
from packflow.plans.model_queries import CORPUS_STATS, PIPE, PROFILE_SQL, corpus_stats, ledger_sql, literal, profiles, synthetic_arrived, values
from packflow.plans.packing_queries import SIGMAS
from packflow.plans.registry import query

PARTS, SIGMA = 400, 1.72
#: Name and the number of batches or bins that the texts would fill.
FIXED, FITTED = (("fixed_0.1%", 1000), ("fixed_0.5%", 200), ("fixed_1%", 100)), (("ffd_1%", 100), ("ffd_2%", 50))
#: Bytes of a text and its vector in a pack, and uploads of one pack at a time.
TEXT_BYTES, DIM, SLOTS = 51, 384, 16


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def up(a: int, b: int) -> int:
    return -(-a // b)


# -- runs --------------------------------------------------------------------------------------------------


def arrived_sql(sigma: float) -> str:
    return f"select *, (sum(n_texts) over ())::bigint as total from ({sql.arrival(sql.synthetic(PARTS, sigma), 'md5(part_key)')})"


def packed_sql(sigma: float) -> str:
    return sql.totals(sql.greedy(f"select *, ceil(total / 100)::bigint as bm from ({arrived_sql(sigma)})", "bm", "(5 * bm)"))


def runs_sql(sigma: float = SIGMA, fixed=FIXED, fitted=FITTED) -> str:
    t = f"({arrived_sql(sigma)})"
    made = [f"select 'per_partition' as method, arrival - 1 as pack_id, 1::bigint as parts, n_texts as n from {t}"]
    for name, k in fixed:
        batch = f"ceil(total / {k})::bigint"
        made.append(f"select '{name}', i, 0::bigint, least(b, total - i * b)::bigint from (select max(total) as total, max({batch}) as b from {t}), unnest(range(0, ceil(total / b)::bigint)) u(i)")
    for name, k in fitted:
        bins = sql.fit_decreasing(f"select * from {t}", f"ceil(total / {k})::bigint")
        made.append(f"select '{name}', pack_id, count(*)::bigint, sum(n)::bigint from {bins} f group by pack_id")
    made.append(f"select 'packed', pack_id, parts, n from ({packed_sql(sigma)})")
    return " union all ".join(made)


def runs(spark, sf_dir, sigma: float = SIGMA, fixed=FIXED, fitted=FITTED) -> DataFrame:
    """(method, pack_id, parts, n): the calls of every method on the log-normal corpus."""
    n, table = synthetic_arrived(spark, sf_dir, sigma, PARTS)
    row = lambda name, df: df.select(F.lit(name).alias("method"), F.col("pack_id").cast("long"), F.col("parts").cast("long"), F.col("n").cast("long"))
    made = [row("per_partition", table.select((F.col("arrival") - 1).alias("pack_id"), F.lit(1).alias("parts"), F.col("n_texts").alias("n")))]
    for name, k in fixed:
        b = up(n, k)
        made.append(row(name, spark.range(up(n, b)).select(F.col("id").alias("pack_id"), F.lit(0).alias("parts"), F.least(F.lit(b), n - F.col("id") * b).alias("n"))))
    for name, k in fitted:
        plan = packing.ffd_pack(table, up(n, k)).groupBy("pack_id").agg(F.count(F.lit(1)).alias("parts"), F.sum("n").alias("n"))
        made.append(row(name, plan))
    b = up(n, 100)
    made.append(row("packed", packing.pack_totals(packing.greedy_pack(table, PackPolicy(b, 5 * b)))))
    return union(made)


# -- plans against each other -------------------------------------------------------------------------------

BEST_FIT = f"select pack_id, part_key, n from {sql.fit_decreasing(arrived_sql(SIGMA), 'ceil(total / 100)::bigint', best=True)} f"
FIRST_FIT = f"select pack_id, part_key, n from {sql.fit_decreasing(arrived_sql(SIGMA), 'ceil(total / 100)::bigint')} f"


@query("bfd_pack", BEST_FIT)
def bfd_pack(spark, sf_dir):
    """Best-fit decreasing on the main workload."""
    n, table = synthetic_arrived(spark, sf_dir, SIGMA, PARTS)
    return packing.bfd_pack(table, up(n, 100)).select("pack_id", "part_key", "n")


@query("ffd_pack_lognormal", FIRST_FIT)
def ffd_pack_lognormal(spark, sf_dir):
    """First-fit decreasing on the main workload."""
    n, table = synthetic_arrived(spark, sf_dir, SIGMA, PARTS)
    return packing.ffd_pack(table, up(n, 100)).select("pack_id", "part_key", "n")


#: Spread of sizes and how many packs the texts would fill; at ten, a pack has forty partitions or so.
FILLS = ((1.0, 100), (1.72, 100), (2.5, 100), (1.0, 10), (1.72, 10))


def _next_fit_sql(t: str, capacity: str) -> str:
    return f"""(with recursive s as (select *, {capacity} as cap from ({t})), walk as (
        select arrival, n_texts as n, 0::bigint as pack_id, n_texts as held from s where arrival = 1
        union all
        select s.arrival, s.n_texts, w.pack_id + (w.held + s.n_texts > cap)::bigint, case when w.held + s.n_texts > cap then s.n_texts else w.held + s.n_texts end from walk w join s on s.arrival = w.arrival + 1)
        select pack_id, n from walk)"""


def _tightness_sql(sigma: float, k: int) -> str:
    t, b = arrived_sql(sigma), f"ceil(total / {k})::bigint"
    greedy = sql.totals(sql.greedy(f"select *, {b} as bm from ({t})", "bm", "(5 * bm)"))
    made = {
        "packed": f"select n from ({greedy})",
        "prefix": f"select sum(n_texts) as n from (select n_texts, floor((sum(n_texts) over (order by arrival) - n_texts) / ceil(total / {k})) as p from ({t})) group by p",
        "next_fit": f"select sum(n) as n from {_next_fit_sql(t, b)} f group by pack_id",
        "ffd": f"select sum(n) as n from {sql.fit_decreasing(t, b)} f group by pack_id",
        "bfd": f"select sum(n) as n from {sql.fit_decreasing(t, b, best=True)} f group by pack_id",
    }
    total = f"(select max(total) from ({t}))"
    return " union all ".join(
        f"select {sigma}::double as sigma, {k}::bigint as fills, '{m}' as method, count(*)::bigint as packs, max(n)::bigint as largest, round({total}::double / ceil({total} / {k}) / count(*), 6) as tightness from ({q})" for m, q in made.items()
    )


@query("packing_efficiency", " union all ".join(_tightness_sql(*x) for x in FILLS))
def packing_efficiency(spark, sf_dir):
    """Texts over threshold and packs, streaming against offline fits, over the spread of sizes. Over one, packs
    pass the threshold on the mean; the fits never do but for partitions that are larger than it."""
    out = []
    for sigma, k in FILLS:
        n, table = synthetic_arrived(spark, sf_dir, sigma, PARTS)
        b = up(n, k)
        plans = {"packed": packing.greedy_pack(table, PackPolicy(b, 5 * b)), "prefix": packing.prefix_pack(table, b), "next_fit": packing.next_fit_pack(table, b), "ffd": packing.ffd_pack(table, b), "bfd": packing.bfd_pack(table, b)}
        for name, plan in plans.items():
            packs = plan.groupBy("lane", "pack_id").agg(F.sum("n").alias("n")).agg(F.count(F.lit(1)).alias("packs"), F.max("n").alias("largest"))
            row = (F.lit(sigma).alias("sigma"), F.lit(k).cast("long").alias("fills"), F.lit(name).alias("method"))
            out.append(packs.select(*row, "packs", "largest", F.round(F.lit(n / b) / F.col("packs"), 6).alias("tightness")))
    return union(out)


def _stronger_sql(sigma: float) -> str:
    wall = f"(calls * {SWEEP.c_ipc} + texts * {SWEEP.c_enc_ms} / 1000 / {SWEEP.workers})"
    rate = lambda m: f"max(case when method = '{m}' then texts / {wall} end) over ()"
    return f"""select {sigma}::double as sigma, method, calls, largest, round({wall}, 6) as wall,
        round((texts / {wall} - {rate('per_partition')}) / ({rate('packed')} - {rate('per_partition')}), 6) as gap_closed, round({rate('packed')} / (texts / {wall}) - 1, 6) as packed_edge,
        largest <= 5 * ceil(texts / 100) as within_bound
        from (select method, count(*)::bigint as calls, max(n)::bigint as largest, sum(n)::double as texts from ({runs_sql(sigma, ())}) group by method)"""


@query("ffd_vs_packed", " union all ".join(map(_stronger_sql, SIGMAS)))
def ffd_vs_packed(spark, sf_dir):
    """The size-sorted baseline at two capacities against streaming packs, over the spread of sizes: calls,
    largest pack, modelled time, how much of the gap it closes, and whether its packs keep the bound."""
    out = []
    for sigma in SIGMAS:
        made = runs(spark, sf_dir, sigma, ()).groupBy("method").agg(F.count(F.lit(1)).alias("calls"), F.max("n").alias("largest"), F.sum("n").cast("double").alias("texts"))
        made = made.withColumn("w", models.wall_seconds(F.col("calls"), F.col("texts"), SWEEP.c_ipc, SWEEP.c_enc_ms, SWEEP.workers)).withColumn("rate", F.col("texts") / F.col("w"))
        of = lambda m: F.max(F.when(F.col("method") == m, F.col("rate"))).over(Window.partitionBy())
        closed = (F.col("rate") - of("per_partition")) / (of("packed") - of("per_partition"))
        out.append(made.select(F.lit(sigma).alias("sigma"), "method", "calls", "largest", F.round("w", 6).alias("wall"), F.round(closed, 6).alias("gap_closed"), F.round(of("packed") / F.col("rate") - 1, 6).alias("packed_edge"), (F.col("largest") <= 5 * F.ceil(F.col("texts") / 100)).alias("within_bound")))
    return union(out)


# -- end to end ----------------------------------------------------------------------------------------------

PACK_BYTES = TEXT_BYTES + 4 * DIM
TAIL = f"ceil({PARTS} / {SLOTS}.0) * 0.01"
END_TO_END = f"""with a as (
        select method, count(*)::bigint as calls, max(n)::bigint as largest, sum(n)::double as texts, sum(t_encode) as encode_s, sum(io) as io_s, max(io_end) as piped,
            max(case when pack_id = 0 then t_encode + io end) as first_s
        from ({PIPE.format(by='method', ledger=ledger_sql(totals=runs_sql()))}) group by method
    ), w as (
        select *, 'sync' as io, encode_s + io_s as wall, first_s as first_output, (largest * {PACK_BYTES})::bigint as held_bytes from a where method not like 'fixed%'
        union all select *, 'async', piped, first_s, (2 * largest * {PACK_BYTES})::bigint from a where method not like 'fixed%'
        union all select *, 'end', encode_s + io_s + {TAIL}, encode_s + io_s + {TAIL}, (texts * {PACK_BYTES})::bigint from a where method like 'fixed%'
    )
    select method, io, calls, largest, held_bytes, round(wall, 6) as wall, round(texts / wall, 6) as texts_per_second, round(encode_s / wall, 6) as duty, round(case when io = 'end' then 0 else 1 - (wall - encode_s) / io_s end, 6) as hidden,
        round(first_output, 6) as first_output, round(wall * {DOLLARS_PER_HOUR} / 3600 * 1e6 / texts, 6) as dollars,
        round(max(case when method = 'per_partition' and io = 'sync' then wall end) over () / wall, 6) as speedup from w"""


@query("e2e_modelled", END_TO_END)
def e2e_modelled(spark, sf_dir):
    """The end-to-end comparison, packed with and without background uploads as rows of their own: calls,
    time, rate, duty, share of I/O hidden, first output, bytes held, cost, and gain over a call a partition."""
    io = F.col("t_serialize") + F.col("t_upload")
    timed = models.pipeline(models.clock_ledger(runs(spark, sf_dir), SMALL, 10.0, 200.0), "method").withColumn("io", io)
    a = timed.groupBy("method").agg(
        F.count(F.lit(1)).alias("calls"), F.max("n").alias("largest"), F.sum("n").cast("double").alias("texts"), F.sum("t_encode").alias("encode_s"), F.sum("io").alias("io_s"),
        F.max("io_end").alias("piped"), F.max(F.when(F.col("pack_id") == 0, F.col("t_encode") + F.col("io"))).alias("first_s"),
    )
    late = F.col("encode_s") + F.col("io_s") + up(PARTS, SLOTS) * 0.01
    batched = F.col("method").startswith("fixed")
    kinds = [(~batched, "sync", F.col("encode_s") + F.col("io_s"), F.col("first_s"), F.col("largest")), (~batched, "async", F.col("piped"), F.col("first_s"), 2 * F.col("largest")), (batched, "end", late, late, F.col("texts"))]
    w = union([a.where(which).select("*", F.lit(kind).alias("io"), wall.alias("wall"), first.alias("first_output"), (held * PACK_BYTES).cast("long").alias("held_bytes")) for which, kind, wall, first, held in kinds])
    r = lambda c, name: F.round(c, 6).alias(name)
    base = F.max(F.when((F.col("method") == "per_partition") & (F.col("io") == "sync"), F.col("wall"))).over(Window.partitionBy())
    return w.select(
        "method", "io", "calls", "largest", "held_bytes", r(F.col("wall"), "wall"), r(F.col("texts") / F.col("wall"), "texts_per_second"), r(models.duty_cycle(F.col("encode_s"), F.col("wall")), "duty"),
        r(F.when(F.col("io") == "end", 0.0).otherwise(models.overlap_ratio_observed(F.col("wall") - F.col("encode_s"), F.col("io_s"))), "hidden"), r(F.col("first_output"), "first_output"),
        r(models.cost_per_million(F.col("wall"), F.col("texts"), DOLLARS_PER_HOUR), "dollars"), r(base / F.col("wall"), "speedup"),
    )


# -- constants and errors from ledgers with a spread -----------------------------------------------------------

RUNS = 3


def spread_sql() -> str:
    h = "('0x' || substr(md5(method || ':' || pack_id || ':' || run), 1, 8))::bigint"
    return f"select *, (0.087::double + n * 0.149::double / 1000 / 4) * (1 + ({h} % 1000 - 500) / 10000.0::double) as t_encode from ({runs_sql()}), unnest(range(0, {RUNS})) u(run)"


def spread(spark, sf_dir) -> DataFrame:
    """Ledgers of ``RUNS`` runs of each method, each call up to five percent off the model."""
    each = runs(spark, sf_dir).withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(RUNS - 1))))
    h = md5_number(F.concat_ws(":", "method", F.col("pack_id").cast("string"), F.col("run").cast("string")))
    return each.withColumn("t_encode", models.call_seconds(F.col("n"), SMALL.c_ipc, SMALL.c_enc_ms, SMALL.workers) * (1 + (h % 1000 - 500) / 10000.0))


WALLS = f"select method, run, count(*)::bigint as calls, sum(n)::double as texts, sum(t_encode) as wall from ({spread_sql()}) group by method, run"


def walls(spark, sf_dir) -> DataFrame:
    return spread(spark, sf_dir).groupBy("method", "run").agg(F.count(F.lit(1)).alias("calls"), F.sum("n").cast("double").alias("texts"), F.sum("t_encode").alias("wall"))


def basic() -> Column:
    return models.wall_seconds(F.col("calls"), F.col("texts"), SMALL.c_ipc, SMALL.c_enc_ms, SMALL.workers)


BASIC = "(calls * 0.087 + texts * 0.149 / 1000 / 4)"


@query("repeat_stats", f"select method, count(*)::bigint as runs, round(avg(wall), 6) as mean, round(stddev_samp(wall), 6) as sd, round(stddev_samp(wall) / avg(wall) * 100, 4) as sd_percent from ({WALLS}) group by method")
def repeat_stats(spark, sf_dir):
    t = models.repeat_stats(walls(spark, sf_dir), "method", "wall")
    return t.select("method", "runs", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd"), F.round("sd_percent", 4).alias("sd_percent"))


@query("prediction_error", f"select method, round(avg({BASIC}), 6) as predicted, round(avg(wall), 6) as measured, round(avg(abs({BASIC} - wall) / wall), 6) as error from ({WALLS}) group by method")
def prediction_error(spark, sf_dir):
    """The model with the profile's constants against the ledgers' times."""
    return walls(spark, sf_dir).groupBy("method").agg(F.round(F.avg(basic()), 6).alias("predicted"), F.round(F.avg("wall"), 6).alias("measured"), F.round(F.avg(models.prediction_error(basic(), F.col("wall"))), 6).alias("error"))


@query("calibrate_two_point", f"""with p as (select * from ({WALLS}) where run = 0)
    select a.method as a, b.method as b, round((a.wall - b.wall) / (a.calls - b.calls), 5) as c_ipc, round((a.wall - a.calls * (a.wall - b.wall) / (a.calls - b.calls)) * 4 / a.texts * 1000, 5) as c_enc_ms from p a join p b on a.calls > b.calls + 20""")
def calibrate_two_point(spark, sf_dir):
    """Both constants from the times of any two methods whose numbers of calls lie apart."""
    p = walls(spark, sf_dir).where("run = 0")
    a = p.select(F.col("method").alias("a"), F.col("wall").alias("t1"), F.col("calls").alias("f1"), "texts")
    b = p.select(F.col("method").alias("b"), F.col("wall").alias("t2"), F.col("calls").alias("f2"))
    c_ipc, c_enc = models.calibrate_two_point(F.col("t1"), F.col("f1"), F.col("t2"), F.col("f2"), F.col("texts"), 4)
    return a.join(b, F.col("f1") > F.col("f2") + 20).select("a", "b", F.round(c_ipc, 5).alias("c_ipc"), F.round(c_enc, 5).alias("c_enc_ms"))


@query("calibrate_regression", f"select method, round(regr_intercept(t_encode, n), 5) as c_ipc, round(regr_slope(t_encode, n) * 4000, 5) as c_enc_ms, round(regr_r2(t_encode, n), 5) as r2 from ({spread_sql()}) where method not like 'fixed%' group by method")
def calibrate_regression(spark, sf_dir):
    """Both constants by regression over a method's calls; batches of one size can give none."""
    t = spread(spark, sf_dir).where(~F.col("method").startswith("fixed"))
    fit = lambda f: F.expr(f"{f}(t_encode, cast(n as double))")
    return t.groupBy("method").agg(F.round(fit("regr_intercept"), 5).alias("c_ipc"), F.round(fit("regr_slope") * 4000, 5).alias("c_enc_ms"), F.round(fit("regr_r2"), 5).alias("r2"))


@query("held_out_error", f"""with p as (select * from ({WALLS})), fit as (select a.run, (a.wall - b.wall) / (a.calls - b.calls) as c_ipc, a.wall, a.calls from p a join p b using (run) where a.method = 'per_partition' and b.method = 'fixed_0.5%')
    select method, p.run::bigint as run, round(abs(p.calls * c_ipc + (fit.wall - fit.calls * c_ipc) - p.wall) / p.wall, 6) as error from p join fit on p.run = fit.run where method not in ('per_partition', 'fixed_0.5%')""")
def held_out_error(spark, sf_dir):
    """Constants from two methods of a run, tested on the others of that run."""
    p = walls(spark, sf_dir)
    a = p.where("method = 'per_partition'").select("run", F.col("wall").alias("t1"), F.col("calls").alias("f1"), F.col("texts").alias("all"))
    b = p.where("method = 'fixed_0.5%'").select("run", F.col("wall").alias("t2"), F.col("calls").alias("f2"))
    c_ipc, c_enc = models.calibrate_two_point(F.col("t1"), F.col("f1"), F.col("t2"), F.col("f2"), F.col("all"), 4)
    fit = a.join(b, "run").select("run", c_ipc.alias("c_ipc"), c_enc.alias("c_enc_ms"))
    wall = models.wall_seconds(F.col("calls"), F.col("texts"), F.col("c_ipc"), F.col("c_enc_ms"), 4)
    tested = p.where(~F.col("method").isin("per_partition", "fixed_0.5%")).join(fit, "run")
    return tested.select("method", F.col("run").cast("long").alias("run"), F.round(models.prediction_error(wall, F.col("wall")), 6).alias("error"))


@query("cost_per_million", f"select method, round(avg(wall) * {DOLLARS_PER_HOUR} / 3600 * 1e6 / max(texts), 6) as dollars from ({WALLS}) group by method")
def cost_per_million(spark, sf_dir):
    return walls(spark, sf_dir).groupBy("method").agg(F.round(models.cost_per_million(F.avg("wall"), F.max("texts"), DOLLARS_PER_HOUR), 6).alias("dollars"))


@query("gap_closed", f"""with r as (select run, method, texts / wall as rate from ({WALLS})), p as (pivot r on method in ('per_partition', 'ffd_1%', 'packed') using max(rate) group by run)
    select run::bigint as run, round(("ffd_1%" - per_partition) / (packed - per_partition), 6) as closed, round(packed / "ffd_1%" - 1, 6) as edge from p""")
def gap_closed(spark, sf_dir):
    """How much of the gap between a call a partition and packing the size-sorted baseline closes, run by run."""
    p = walls(spark, sf_dir).withColumn("rate", F.col("texts") / F.col("wall")).groupBy("run").pivot("method", ["per_partition", "ffd_1%", "packed"]).agg(F.max("rate"))
    closed, edge = models.gap_closed(F.col("per_partition"), F.col("ffd_1%"), F.col("packed"))
    return p.select(F.col("run").cast("long").alias("run"), F.round(closed, 6).alias("closed"), F.round(edge, 6).alias("edge"))


# -- by encoder, by corpus ---------------------------------------------------------------------------------------

BY_PROFILE = f"""select profile, method, texts / (calls * c_ipc + texts * c_enc_ms / 1000 / workers) as rate,
        case when method like 'fixed%' then texts else 2 * largest end * ({TEXT_BYTES} + 4 * dim) as held,
        case when method like 'fixed%' then calls * c_ipc + texts * c_enc_ms / 1000 / workers else c_ipc + first_n * c_enc_ms / 1000 / workers end as first_output
    from (select method, count(*)::double as calls, sum(n)::double as texts, max(n) as largest, max(case when pack_id = 0 then n end) as first_n from ({runs_sql()}) group by method), {PROFILE_SQL}"""


def by_profile(spark, sf_dir) -> DataFrame:
    a = runs(spark, sf_dir).groupBy("method").agg(F.count(F.lit(1)).cast("double").alias("calls"), F.sum("n").cast("double").alias("texts"), F.max("n").alias("largest"), F.max(F.when(F.col("pack_id") == 0, F.col("n"))).alias("first_n"))
    a = a.crossJoin(F.broadcast(profiles(spark)))
    price = (F.col("c_ipc"), F.col("c_enc_ms"), F.col("workers"))
    wall, batched = models.wall_seconds(F.col("calls"), F.col("texts"), *price), F.col("method").startswith("fixed")
    held = models.pack_bytes(F.when(batched, F.col("texts")).otherwise(2 * F.col("largest")), TEXT_BYTES, F.col("dim"))
    first = F.when(batched, wall).otherwise(models.call_seconds(F.col("first_n"), *price))
    return a.select("profile", "method", (F.col("texts") / wall).alias("rate"), held.alias("held"), first.alias("first_output"))


@query("strategy_ratios", f"""select profile, method, round(rate / max(case when method = 'per_partition' then rate end) over (partition by profile), 6) as speedup,
    round(held / max(case when method = 'packed' then held end) over (partition by profile), 6) as memory_ratio, round(first_output / max(case when method = 'packed' then first_output end) over (partition by profile), 6) as first_ratio from ({BY_PROFILE})""")
def strategy_ratios(spark, sf_dir):
    """By encoder: gain over a call a partition, memory and first output as multiples of packing's."""
    w = Window.partitionBy("profile")
    of = lambda method, c: F.max(F.when(F.col("method") == method, F.col(c))).over(w)
    ratio = lambda c, method, name: F.round(F.col(c) / of(method, c), 6).alias(name)
    return by_profile(spark, sf_dir).select("profile", "method", ratio("rate", "per_partition", "speedup"), ratio("held", "packed", "memory_ratio"), ratio("first_output", "packed", "first_ratio"))


@query("strategy_pivot", f"""select profile, round(max(case when method = 'per_partition' then rate end), 6) as per_partition, round(max(case when method = 'fixed_1%' then rate end), 6) as fixed,
    round(max(case when method = 'ffd_1%' then rate end), 6) as ffd, round(max(case when method = 'packed' then rate end), 6) as packed from ({BY_PROFILE}) group by profile""")
def strategy_pivot(spark, sf_dir):
    names = {"per_partition": "per_partition", "fixed_1%": "fixed", "ffd_1%": "ffd", "packed": "packed"}
    wide = by_profile(spark, sf_dir).groupBy("profile").pivot("method", list(names)).agg(F.max("rate"))
    return wide.select("profile", *(F.round(F.col(f"`{old}`"), 6).alias(new) for old, new in names.items()))


#: Seconds to tokenize a byte, to move a byte to a device, and the share of a text's price that is its kernel.
TOKENIZE_S, MOVE_S, KERNEL = 40e-9, 1 / 12e9, 0.9
STAGES = f"""select corpus, profile, n_bytes * {TOKENIZE_S}::double / workers as tokenize, calls * c_ipc + texts * 4 * dim * {MOVE_S!r}::double as transfer, texts * c_enc_ms * {KERNEL} / 1000 / workers as kernel,
    calls * c_ipc + texts * c_enc_ms / 1000 / workers as encode, texts * dim * 32e-9::double + parts / {SLOTS}.0 * 0.01 as io from (select *, ceil(texts / 1000.0)::double as calls from ({CORPUS_STATS})) s, {PROFILE_SQL}"""


def stages(spark, sf_dir) -> DataFrame:
    s = corpus_stats(spark, sf_dir).withColumn("calls", F.ceil(F.col("texts") / 1000.0).cast("double")).crossJoin(F.broadcast(profiles(spark)))
    c = F.col
    encode = models.wall_seconds(c("calls"), c("texts"), c("c_ipc"), c("c_enc_ms"), c("workers"))
    return s.select(
        "corpus", "profile", (c("n_bytes") * TOKENIZE_S / c("workers")).alias("tokenize"), (c("calls") * c("c_ipc") + c("texts") * 4 * c("dim") * MOVE_S).alias("transfer"),
        (c("texts") * c("c_enc_ms") * KERNEL / 1000 / c("workers")).alias("kernel"), encode.alias("encode"), (c("texts") * c("dim") * 32e-9 + c("parts") / float(SLOTS) * 0.01).alias("io"),
    )


@query("intensity_and_duty", f"select corpus, profile, round(kernel / (tokenize + transfer + kernel), 6) as intensity, round(encode / (encode + io), 6) as duty, round(kernel / (tokenize + transfer + kernel) * encode / (encode + io), 6) as bound from ({STAGES})")
def intensity_and_duty(spark, sf_dir):
    """Share of kernels in a call's stages, share of calls in the time, and the bound on use that both give,
    by corpus and encoder: bytes, calls and vectors of each corpus make the stages."""
    intensity, duty = models.compute_intensity(F.col("tokenize"), F.col("transfer"), F.col("kernel")), models.duty_cycle(F.col("encode"), F.col("encode") + F.col("io"))
    return stages(spark, sf_dir).select("corpus", "profile", F.round(intensity, 6).alias("intensity"), F.round(duty, 6).alias("duty"), F.round(models.utilization_bound(duty, intensity), 6).alias("bound"))


BUDGETS = [(m, d) for m in (8.0e9, 24.0e9, 192.0e9) for d in (384, 768, 1024)]
BUDGETED = f"(select corpus, n_max, n_bytes / texts::double as text_bytes from ({CORPUS_STATS})) s, {values(BUDGETS, 'memory, dim')}"


def budgeted(spark, sf_dir) -> DataFrame:
    s = corpus_stats(spark, sf_dir).select("corpus", "n_max", (F.col("n_bytes") / F.col("texts").cast("double")).alias("text_bytes"))
    return s.crossJoin(F.broadcast(literal(spark, BUDGETS, "memory double, dim long")))


@query("pack_memory", f"select corpus, memory, dim, round((999 + n_max) * (text_bytes + 4 * dim), 3) as bytes, round(2 * (999 + n_max) * (text_bytes + 4 * dim), 3) as with_inflight, 2 * (999 + n_max) * (text_bytes + 4 * dim) <= memory as fits from {BUDGETED}")
def pack_memory(spark, sf_dir):
    """The largest pack at a threshold of 1,000 under the loosest policy, alone and with one in flight."""
    b = models.pack_bytes(999 + F.col("n_max"), F.col("text_bytes"), F.col("dim"))
    return budgeted(spark, sf_dir).select("corpus", "memory", "dim", F.round(b, 3).alias("bytes"), F.round(2 * b, 3).alias("with_inflight"), (2 * b <= F.col("memory")).alias("fits"))


@query("feasible_n", f"select corpus, memory, dim, floor(memory / ((text_bytes + 4 * dim) * 2.0))::bigint as texts from {BUDGETED}")
def feasible_n(spark, sf_dir):
    """Texts that the boundary-blind baseline can hold, by each corpus's bytes a text."""
    return budgeted(spark, sf_dir).select("corpus", "memory", "dim", F.floor(models.max_feasible_n(F.col("memory"), F.col("text_bytes"), F.col("dim"), 2.0)).alias("texts"))


@query("bmax_for_budget", f"select corpus, memory, dim, floor(memory / (2 * (text_bytes + 4 * dim)))::bigint as b_max from {BUDGETED}")
def bmax_for_budget(spark, sf_dir):
    return budgeted(spark, sf_dir).select("corpus", "memory", "dim", models.b_max_for_budget(F.col("memory"), F.col("text_bytes"), F.col("dim")).alias("b_max"))


@query("model_call_time", f"select method, profile, max(n)::bigint as n, round(max(c_ipc + n * c_enc_ms / 1000 / workers), 6) as slowest, round(avg(n / (c_ipc + n * c_enc_ms / 1000 / workers)), 4) as texts_per_second from ({runs_sql()}), {PROFILE_SQL} group by method, profile")
def model_call_time(spark, sf_dir):
    """The slowest call of each method by encoder, and the mean rate of its calls."""
    seconds = models.call_seconds(F.col("n"), F.col("c_ipc"), F.col("c_enc_ms"), F.col("workers"))
    t = runs(spark, sf_dir).crossJoin(F.broadcast(profiles(spark)))
    return t.groupBy("method", "profile").agg(F.max("n").alias("n"), F.round(F.max(seconds), 6).alias("slowest"), F.round(F.avg(F.col("n") / seconds), 4).alias("texts_per_second"))


@query("predicted_wall_ext", f"select method, round({BASIC} + {PARTS} * 0.002 + texts * {DIM} * 2e-9 + 0.5, 6) as predicted from (select method, count(*)::double as calls, sum(n)::double as texts from ({runs_sql()}) group by method)")
def predicted_wall_ext(spark, sf_dir):
    """The model with prices for partitions, vectors and exposed I/O, for each method's calls."""
    a = runs(spark, sf_dir).groupBy("method").agg(F.count(F.lit(1)).alias("calls"), F.sum("n").cast("double").alias("texts"))
    ext = models.wall_seconds_ext(F.col("calls"), PARTS, F.col("texts"), DIM, SMALL.c_ipc, SMALL.c_enc_ms, SMALL.workers, 0.002, 2.0, 0.5)
    return a.select("method", F.round(ext, 6).alias("predicted"))


SCALES = (1, 2, 5)


def _scale_sql(k: int) -> str:
    texts = f"({k} * (select count(*) from lineitem))"
    base = f"select *, ceil((select count(*) from lineitem) / 100)::bigint as bm, (sum(n_texts) over ())::bigint as total from ({sql.arrival(sql.synthetic(PARTS * k, SIGMA, texts), 'md5(part_key)')})"
    packs = sql.totals(sql.greedy(base, "bm", "(5 * bm)"))
    return f"""select {k}::bigint as factor, count(*)::bigint as packs, max(n)::bigint as largest, sum(n)::bigint as texts, round(count(*) * 0.087 + sum(n) * 0.149 / 1000 / 4, 6) as packed_s,
        round(0.087 + max(case when pack_id = 0 then n end) * 0.149 / 1000 / 4, 6) as packed_first, round(0.087 + sum(n) * 0.149 / 1000 / 4, 6) as fixed_first, (2 * max(n) * {PACK_BYTES})::bigint as packed_bytes, (sum(n) * {PACK_BYTES})::bigint as fixed_bytes from ({packs})"""


@query("scaling_modelled", " union all ".join(map(_scale_sql, SCALES)))
def scaling_modelled(spark, sf_dir):
    """Texts and partitions grow together under one policy: packs planned, time, first output, bytes held.
    Flat for packing, in proportion for the batch that holds everything."""
    n, out = spark.read.parquet(f"{sf_dir}/lineitem.parquet").count(), []
    for k in SCALES:
        _, table = synthetic_arrived(spark, sf_dir, SIGMA, PARTS * k, k)
        b = up(n, 100)
        packs = packing.pack_totals(packing.greedy_pack(table, PackPolicy(b, 5 * b)))
        a = packs.agg(F.count(F.lit(1)).alias("packs"), F.max("n").alias("largest"), F.sum("n").alias("texts"), F.max(F.when(F.col("pack_id") == 0, F.col("n"))).alias("first"))
        price = (SMALL.c_ipc, SMALL.c_enc_ms, SMALL.workers)
        out.append(a.select(
            F.lit(k).cast("long").alias("factor"), "packs", "largest", "texts", F.round(models.wall_seconds(F.col("packs"), F.col("texts"), *price), 6).alias("packed_s"),
            F.round(models.call_seconds(F.col("first"), *price), 6).alias("packed_first"), F.round(models.call_seconds(F.col("texts"), *price), 6).alias("fixed_first"),
            (2 * F.col("largest") * PACK_BYTES).cast("long").alias("packed_bytes"), (F.col("texts") * PACK_BYTES).cast("long").alias("fixed_bytes"),
        ))
    return union(out)


DEVICES = [("l4", 1024), ("a100", 2048), ("l4-mid", 512)]


@query("device_batches", f"select device, method, sum(ceil(n / batch::double))::bigint as batches, round(sum(n) / sum(ceil(n / batch::double) * batch), 6) as filled from ({runs_sql()}), {values(DEVICES, 'device, batch')} group by device, method")
def device_batches(spark, sf_dir):
    """Batches that calls become on each kind of device, and how full they are: small calls leave them empty."""
    from packflow.config import DEVICE_BATCH

    table = F.broadcast(literal(spark, sorted(DEVICE_BATCH.items()), "device string, batch long"))
    per_call = F.ceil(F.col("n") / F.col("batch").cast("double"))
    t = runs(spark, sf_dir).crossJoin(table)
    return t.groupBy("device", "method").agg(F.sum(per_call).cast("long").alias("batches"), F.round(F.sum("n") / F.sum(per_call * F.col("batch")), 6).alias("filled"))


