import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from packflow.config import EncoderProfile, PackPolicy, RetryPolicy
from packflow.functions.hashing import HashEncoder
from packflow.operators import encode, packing, sizes
from packflow.operators.resume import pending_partitions, redo_bound, run_with_resume
from packflow.operators.serialize import vectors_to_arrow, vectors_to_arrow_naive
from packflow.operators.sink import AsyncUploader, UploadError, output_path, output_path_expr, with_retry

PROFILE = EncoderProfile("t", 16)
KEYS = [None, "a", "a/b", "x=1", "50%", "é ü", "", "z"]


def corpus(spark):
    rows = [(k, s, f"word{s} {k} text" if s % 3 else None) for i, k in enumerate(KEYS) for s in range(1, 4 + 7 * i)]
    return spark.createDataFrame(rows, "part_key string, seq long, text string").repartition(5)


def values(df):
    return sorted(((r.part_key, r.seq, tuple(np.round(r.embedding, 5))) for r in df.collect()), key=str)


@pytest.fixture(scope="module")
def expected(spark):
    e = HashEncoder(16)
    return sorted(((r.part_key, r.seq, tuple(np.round(e.encode([r.text or ""])[0].astype(float), 5))) for r in corpus(spark).collect()), key=str)


@pytest.mark.parametrize("records", [1, 7, 10_000])
@pytest.mark.parametrize("policy", [PackPolicy(10, 20), PackPolicy(10, 20, "after", "own"), PackPolicy(1, 2), PackPolicy(10**6, 10**7)])
def test_packed_vectors_for_any_arrow_batches(spark, expected, records, policy):
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", records)
    try:
        assert values(encode.stream_pack_encode(corpus(spark), policy, PROFILE, lanes=3)) == expected
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_other_strategies(spark, expected):
    c = corpus(spark)
    plan = packing.ffd_pack(sizes.partition_sizes(c), 25)
    assert values(encode.per_partition_encode(c, PROFILE)) == expected
    assert values(encode.fixed_batch_encode(c, 13, PROFILE)) == expected
    assert values(encode.planned_encode(c, plan, PROFILE)) == expected
    assert values(encode.stream_pack_encode(c, PackPolicy(10, 20), PROFILE, lanes=1, serialize="naive")) == expected


def test_one_shuffle_below_the_encoder(spark):
    plan = encode.stream_pack_encode(spark.range(9).selectExpr("string(id) as part_key", "id as seq", "'x' as text"), PackPolicy(10, 20), PROFILE, lanes=2)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and plan.index("MapInArrow") < plan.index("Exchange")


def test_main_workloads_move_texts_once_and_use_every_lane(spark):
    """One exchange below the encoder that is no broadcast, no window, and a task for each lane."""
    from packflow.plans.queries import QUERIES

    made = QUERIES["stream_pack_encode"](spark, "/root/testdata/sf0.001")
    plan = made._jdf.queryExecution().executedPlan().toString()
    below = plan[plan.index("MapInArrow") :]
    assert below.count("Exchange") - below.count("BroadcastExchange") == 1 and "Window" not in below and "REPARTITION_BY" in below.upper()
    texts = corpus(spark)
    for lanes in (4, 8, 16):
        own = encode.route(texts, lanes).select("lane", F.spark_partition_id().alias("task")).distinct().collect()
        assert all(r.lane == r.task for r in own)


def test_lanes_number_texts_as_a_window_does(spark):
    from packflow.sources.corpora import load_corpus, load_unnumbered

    dir_ = "/root/testdata/sf0.001"
    df, order = load_unnumbered(spark, dir_, "brand_nation")
    got = encode.stream_pack_encode(df, PackPolicy(50, 250), PROFILE, 5, "checksums", order=order)
    want = encode.per_partition_encode(load_corpus(spark, dir_, "brand_nation"), PROFILE, "checksums")
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_ledger_of_the_online_form_equals_the_plan(spark):
    policy = PackPolicy(10, 20)
    led = encode.stream_pack_encode(corpus(spark), policy, PROFILE, lanes=1, what="ledger").collect()
    plan = packing.pack_totals(packing.greedy_pack(sizes.arrival_order(sizes.partition_sizes(corpus(spark))), policy)).orderBy("pack_id").collect()
    assert [(r.n_texts, r.n_parts, r.reason) for r in sorted(led, key=lambda r: r.pack_id)] == [(r.n, r.parts, r.reason) for r in plan]


def test_a_returning_key_is_an_error():
    emitter = encode.Emitter(PROFILE, "checksums")
    batch = pa.record_batch({"lane": pa.array([0, 0, 0], pa.int32()), "part_key": ["a", "b", "a"], "seq": pa.array([1, 2, 3], pa.int64()), "text": ["x", "y", "z"]})
    with pytest.raises(encode.UnsortedInputError):
        list(encode.run_lane(PackPolicy(10, 20), emitter)(iter([batch])))


def test_empty_corpus(spark):
    empty = spark.createDataFrame([], "part_key string, seq long, text string")
    assert encode.stream_pack_encode(empty, PackPolicy(10, 20), PROFILE).count() == 0
    assert encode.per_partition_encode(empty, PROFILE).count() == 0


def test_files_resume_and_manifest(spark, tmp_path):
    root, c = f"file://{tmp_path}", corpus(spark)
    sink = encode.PartitionFiles(root, "r")
    first = c.where("part_key in ('a', 'z')")
    done = encode.stream_pack_encode(first, PackPolicy(10, 20), PROFILE, lanes=2, what="manifest", sink=sink)
    done = spark.createDataFrame(done.collect(), done.schema)
    rest = pending_partitions(c, done)
    assert {r.part_key for r in rest.select("part_key").distinct().collect()} == set(KEYS) - {"a", "z"}
    rows = encode.stream_pack_encode(rest, PackPolicy(10, 20), PROFILE, lanes=2, what="manifest", sink=sink).collect()
    assert {(r.part_key, r.n_texts) for r in rows} | {(r.part_key, r.n_texts) for r in done.collect()} >= {("a", 10)}
    files = [p for p in tmp_path.rglob("*") if p.is_file()]
    assert files and not [p for p in files if p.suffix == ".tmp"]
    paths = spark.createDataFrame([(k,) for k in KEYS if k is not None], "k string").select("k", output_path_expr("r", "i", F.col("k"), F.lit(2)).alias("p")).collect()
    assert all(r.p == output_path("r", "i", r.k, 2) for r in paths)


def test_retry_and_upload():
    waits, tries = [], []

    def flaky():
        tries.append(1)
        if len(tries) < 3:
            raise OSError
        return "ok"

    assert with_retry(flaky, RetryPolicy(), waits.append) == ("ok", 2) and waits == [1, 2]
    with pytest.raises(UploadError):
        with_retry(lambda: 1 / 0, RetryPolicy(), waits.append)
    up, done = AsyncUploader(4, 2), []
    for k in range(10):
        up.submit([lambda k=k: done.append(k)] * 3)
        assert len(up.packs) <= 2
    up.close()
    assert sorted(done) == sorted(k for k in range(10) for _ in range(3)) and up.most <= 2
    up = AsyncUploader(1, 1, RetryPolicy(2, 0.0))
    up.submit([lambda: 1 / 0])
    with pytest.raises(UploadError):
        up.close()


def test_serialization_agrees_and_shares_memory():
    m = HashEncoder(8).encode(["a b", "c", ""])
    assert vectors_to_arrow(m).to_pylist() == vectors_to_arrow_naive(m).to_pylist() == vectors_to_arrow(m, "fixed").to_pylist()
    assert vectors_to_arrow(m, "binary")[1].as_py() == m[1].tobytes()
    assert vectors_to_arrow(m, "fixed").values.buffers()[1].address == m.ctypes.data
    assert len(vectors_to_arrow(m[:0])) == 0


def test_run_with_resume_and_redo_bound():
    def job(attempt):
        if attempt < 2:
            raise OSError
        return attempt

    assert run_with_resume(job) == 2
    assert redo_bound(PackPolicy(10, 20), 1000, 1) == 40


def test_memory_guard():
    emitter = encode.Emitter(PROFILE, "ledger", bound=1)
    emitter.start()
    u = encode.Unit("a", 0, 2)
    u.take(pa.array([1, 2]), pa.array(["x", "y"]))
    with pytest.raises(MemoryError):
        emitter.pack(0, 0, [u], "final")


def test_scans_are_pruned_and_filters_pushed(spark):
    from packflow.plans.queries import QUERIES

    plan = lambda name: QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "n_chars" not in plan("stream_pack_docs") and "ReadSchema: struct<doc_id:bigint,text:string,lang:string,source:string>" in plan("stream_pack_docs")
    assert "In(lang, [de,fr])" in plan("filter_project") or "In(lang, [fr,de])" in plan("filter_project")
    sizes_plan = plan("partition_sizes")
    assert "Window" not in sizes_plan and "partial_count" in sizes_plan


class FakeState:
    """A lane's state in a test: what Spark would hand over."""

    def __init__(self, value=None, timed_out=False):
        self.value, self.hasTimedOut, self.timeout = value, timed_out, None

    @property
    def exists(self):
        return self.value is not None

    @property
    def get(self):
        return self.value

    def update(self, value):
        self.value = value

    def setTimeoutDuration(self, ms):
        self.timeout = ms


def test_a_waiting_pack_is_flushed_by_its_time_out():
    import pandas as pd

    from packflow.streaming.packers import packing_step

    step, state = packing_step(PackPolicy(10, 20), 500), FakeState()
    sizes = pd.DataFrame({"part_key": ["a", "b", "c"], "n_texts": [4, 7, 3]})
    assert [tuple(r) for out in step((2,), iter([sizes]), state) for r in out.itertuples(index=False)] == [(2, 0, 2, 11, "efficiency")]
    assert state.value == (3, 1, 1) and state.timeout == 500
    late = FakeState(state.value, timed_out=True)
    assert [tuple(r) for out in step((2,), iter([]), late) for r in out.itertuples(index=False)] == [(2, 1, 1, 3, "timeout")]
    assert late.value == (0, 0, 2)


def test_carried_tails_time_out_and_a_batch_run_again_changes_nothing(spark, tmp_path):
    from packflow.streaming.packers import CarryingPacker

    packer = CarryingPacker(PackPolicy(10, 30, oversize="own"), PROFILE, f"file://{tmp_path}", lanes=1, max_wait=2)
    batch = lambda rows: spark.createDataFrame([(k, s, "t") for k, n in rows for s in range(n)], "part_key string, seq long, text string")
    packs = lambda b: sorted(tuple(r) for r in spark.read.parquet(packer.at("packs", b)).select("parts", "n", "reason").collect())
    arrivals = [[("a", 6), ("b", 6), ("c", 3)], [("d", 2)], [("e", 1)], [("f", 2)]]
    for b, rows in enumerate(arrivals):
        for _ in range(2):
            packer(batch(rows), b)
    packer.finish(spark, 4)
    assert [packs(b) for b in range(5)] == [[(2, 12, "efficiency")], [], [(3, 6, "timeout")], [], [(1, 2, "final")]]
    stored = spark.read.parquet(f"{tmp_path}/manifest").groupBy("part_key").agg(F.sum("n_texts").alias("n")).collect()
    assert {r.part_key: r.n for r in stored} == dict(x for rows in arrivals for x in rows)


def test_live_ledgers_give_measures_in_range(spark):
    from packflow.plans.queries import QUERIES

    rows = {r.run: r for r in QUERIES["ledger_measures"](spark, "/root/testdata/sf0.001").collect()}
    assert set(rows) == {"packed_sync", "packed_async", "packed_null"}
    assert all(0 <= r.hidden <= 1 and 0 < r.duty <= 1 and r.dollars > 0 for r in rows.values())
    assert len({(r.calls, r.texts) for r in rows.values()}) == 1
    assert rows["packed_async"].stall_s < rows["packed_sync"].stall_s


def test_texts_whose_signs_cancel_have_unit_vectors():
    e = HashEncoder(64)
    texts = ["In. The.", "a b", "", "In. The. In. The."]
    assert not e.counts(texts)[[0, 3]].any()
    assert np.allclose((e.encode(texts).astype(float) ** 2).sum(1), 1)
    assert e.checksums(texts)[1].tolist()[::3] == [0, 0]
