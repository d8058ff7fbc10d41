import pytest

from packflow.config import LARGE, MID, SMALL, SWEEP, PackPolicy
from packflow.functions import models as m
from packflow.functions.register import register

N, P = 10_000_000, 4000
near = lambda x, rel=1e-3: pytest.approx(x, rel=rel)


def alpha(p, parts=P, workers=None):
    return m.ipc_to_compute(parts, N, p.c_ipc, p.c_enc_ms, workers or p.workers)


def test_worked_numbers():
    assert m.break_even_size(SMALL.c_ipc, SMALL.c_enc_ms, 4) == near(2336)
    assert P * SMALL.c_ipc == near(348)
    assert N * SMALL.c_enc_ms / 1000 / 4 == near(372.5)
    assert alpha(SMALL) == near(0.934)
    assert m.predicted_speedup(alpha(SMALL), 100, P) == near(1.8901, 1e-4)
    assert m.predicted_speedup(alpha(SMALL), 89, P) == near(1.8948, 1e-4)
    assert m.predicted_speedup(1e12, 100, P) == near(40)
    assert m.predicted_speedup(alpha(MID), 100, P) == near(1.2917, 1e-4)
    assert m.predicted_speedup(alpha(MID, workers=4), 100, P) == near(1.5790, 1e-4)
    assert m.predicted_speedup(alpha(SWEEP), 100, P) == near(1.4694, 1e-3)
    assert m.predicted_speedup(0.34, 100, P) == near(1.3287, 1e-3)
    assert alpha(LARGE) == near(0.34, 0.01)
    assert m.ipc_time_share(alpha(SMALL)) == near(0.483, 5e-3)
    assert m.pack_bytes(500_000, 47, 384) == 791_500_000
    assert m.expected_fill(8412, 17_660, 100_000, "printed") == near(1.185, 1e-3)
    assert m.expected_fill(8412, 17_660, 100_000) == near(1.227, 1e-3)
    assert m.cost_per_million(726.4, N, 7.30) == near(0.147, 5e-3)
    assert m.cost_per_million(378.6, N, 7.30) == near(0.077, 5e-3)
    assert 0.106 / 0.57 == near(0.186, 1e-2) and 0.62 / 0.85 == near(0.73, 1e-2)
    assert m.gap_closed(12190, 16718, 17909) == (near(0.792), near(0.0712, 1e-2))
    assert m.worker_efficiency(949.1, 385.7, 4)[1] == near(0.615, 1e-2)


def test_calibration_recovers_constants_and_predicts_held_out():
    t1, t2 = m.wall_seconds(4000, N, 0.087, 0.149, 4), m.wall_seconds(100, N, 0.087, 0.149, 4)
    assert m.calibrate_two_point(t1, 4000, t2, 100, N, 4) == (near(0.087), near(0.149))
    c_ipc, c_enc = m.calibrate_two_point(726.4, 4000, 383.6, 200, N, 4)
    errors = {f: m.prediction_error(m.wall_seconds(f, N, c_ipc, c_enc, 4), t) for f, t in ((89, 384.2), (160, 414.5), (48, 367.4))}
    assert errors[89] < 0.03 and errors[48] < 0.01 and errors[160] > 0.05


def test_overlap_regimes_and_advice():
    assert m.overlap_ratio_model(3, 1, 1) == 1 and m.overlap_ratio_model(1, 1, 1) == 0.5 and m.overlap_ratio_model(1, 0, 0) == 1
    assert m.overlap_ratio_observed(0, 0) == 1 and m.overlap_ratio_observed(1, 4) == 0.75
    assert [m.regime(a) for a in (100, 1, 0.01)] == ["boundary", "mixed", "compute"]
    assert [m.recommend(*x) for x in ((0.6, 2), (0.6, 1), (0.5, 2), (0.5, 1))] == ["strong", "beneficial", "moderate", "optional"]


def test_memory_bounds():
    assert [PackPolicy(10, 20, c, o).bound(47) for c, o in (("after", "own"), ("after", "split"), ("before", "own"), ("before", "split"))] == [56, 29, 47, 20]
    assert m.memory_bound(PackPolicy(100_000, 500_000), 10**9, 47, 384, 1) == 2 * 791_500_000
    assert m.b_max_for_budget(2 * 791_500_000, 47, 384) == 500_000
    assert m.max_feasible_n(192e9, 47, 384, 2.0) == near(60.6e6, 1e-2)
    assert m.rss_estimate(500_000, 47, 384) > 791_500_000


def test_time_to_first_output_orders_as_reported():
    t = {s: m.ttfo_model(s, n, N, 100, 0.087, 0.149, 4, 0.01, size_pass=1.0) for s, n in (("per_partition", 2500), ("fixed_batch", 0), ("ffd", 179_814), ("packed", 112_000))}
    assert t["per_partition"] < t["packed"] < t["ffd"] < t["fixed_batch"]


def test_sql_functions(spark):
    register(spark)
    r = spark.sql("select break_even_size(0.087, 0.149, 4) a, overlap_ratio(1, 1, 1) b, recommend(0.6, 2) c, predicted_speedup(1e12, 100, 4000) d").first()
    assert (round(r.a), r.b, r.c, round(r.d)) == (2336, 0.5, "strong", 40)


def test_pipeline_adds_in_the_order_of_the_oracle(spark):
    """Times of packs to the last bit as DuckDB's windows have them, over several levels of its tree."""
    import duckdb
    import random

    r = random.Random(5)
    rows = [(0, k, r.random(), r.random() / 3, r.random()) for k in range(5000)]
    t = spark.createDataFrame(rows, "lane int, pack_id long, t_encode double, t_serialize double, t_upload double").repartition(3)
    got = [tuple(x) for x in m.pipeline(t, "lane").orderBy("pack_id").select("ready", "io_total", "io_end").collect()]
    from packflow.plans.model_queries import PIPE

    con = duckdb.connect()
    con.sql("create table t (lane int, pack_id bigint, t_encode double, t_serialize double, t_upload double)")
    con.executemany("insert into t values (?, ?, ?, ?, ?)", rows)
    want = con.sql(f"select ready, io_total, io_end from ({PIPE.format(by='lane', ledger='from t')}) order by pack_id").fetchall()
    assert got == want
