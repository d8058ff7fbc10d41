import itertools

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from packflow.config import PackPolicy
from packflow.operators import packing
from packflow.operators.packing import best_fit_decreasing, first_fit_decreasing, next_fit, pack_units
from packflow.operators.sizes import arrival_order
from packflow.sources.corpora import lognormal_sizes

HAND = list(zip("ABCDEFGHIJ", [4, 5, 3, 9, 18, 2, 47, 1, 10, 6], strict=True))
EXPECTED = {
    ("after", "own"): [("ABC", 12, "efficiency"), ("DE", 27, "ceiling"), ("FG", 49, "oversize"), ("HI", 11, "efficiency"), ("J", 6, "final")],
    ("after", "split"): [("ABC", 12, "efficiency"), ("DE", 27, "ceiling"), ("FG", 22, "oversize"), ("G", 20, "oversize"), ("GHI", 18, "efficiency"), ("J", 6, "final")],
    ("before", "own"): [("ABC", 12, "efficiency"), ("D", 9, "ceiling"), ("E", 18, "efficiency"), ("F", 2, "ceiling"), ("G", 47, "oversize"), ("HI", 11, "efficiency"), ("J", 6, "final")],
    ("before", "split"): [("ABC", 12, "efficiency"), ("D", 9, "ceiling"), ("E", 18, "efficiency"), ("F", 2, "ceiling"), ("G", 20, "oversize"), ("G", 20, "oversize"), ("GHI", 18, "efficiency"), ("J", 6, "final")],
}


def cut(sizes, policy):
    for k, n in sizes:
        if policy.oversize == "own":
            yield (k, 0, n, n)
        else:
            for c in range(-(-n // policy.b_max)):
                yield (k, c, min(policy.b_max, n - c * policy.b_max), n)


@pytest.mark.parametrize(("ceiling", "oversize"), EXPECTED)
def test_hand_example(ceiling, oversize):
    policy = PackPolicy(10, 20, ceiling, oversize)
    got = [("".join(u[0] for u in units), sum(u[2] for u in units), reason) for units, reason in pack_units(cut(HAND, policy), policy)]
    assert got == EXPECTED[ceiling, oversize]


@pytest.mark.parametrize(("ceiling", "oversize"), EXPECTED)
def test_plan_on_spark_equals_plain(spark, ceiling, oversize):
    policy = PackPolicy(10, 20, ceiling, oversize)
    sizes = arrival_order(spark.createDataFrame([(k, n, n) for k, n in HAND], "part_key string, n_texts long, n_bytes long"))
    rows = packing.greedy_pack(sizes, policy).orderBy("pack_id", "arrival", "chunk").collect()
    packs = [list(g) for _, g in itertools.groupby(rows, key=lambda r: r.pack_id)]
    assert [("".join(r.part_key for r in p), sum(r.n for r in p), p[0].reason) for p in packs] == EXPECTED[ceiling, oversize]
    for p in packs:
        assert [r.start_off for r in p] == [sum(x.n for x in p[:i]) for i in range(len(p))]


def test_other_planners_on_the_hand_example(spark):
    def named(bins):
        out = {}
        for (k, _), b in zip(HAND, bins, strict=True):
            out.setdefault(b, []).append(k)
        return sorted("".join(sorted(v)) for v in out.values())

    assert named(first_fit_decreasing(HAND, 20)) == named(best_fit_decreasing(HAND, 20)) == sorted(["G", "EF", "DHI", "ABCJ"])
    assert named(list(next_fit([n for _, n in HAND], 20))) == sorted(["ABC", "D", "EF", "G", "HIJ"])
    sizes = arrival_order(spark.createDataFrame(HAND, "part_key string, n_texts long"))
    got = {r.part_key: r.pack_id for r in packing.prefix_pack(sizes, 10).collect()}
    assert [got[k] for k, _ in HAND] == [0, 0, 0, 1, 2, 3, 4, 8, 8, 9]


sizes_lists = st.lists(st.integers(1, 60), min_size=1, max_size=40)


@settings(max_examples=300, deadline=None)
@given(sizes_lists, st.integers(1, 25), st.sampled_from(["before", "after"]), st.sampled_from(["own", "split"]))
def test_bounds_hold_for_any_order(sizes, b_min, ceiling, oversize):
    policy = PackPolicy(b_min, 2 * b_min + 3, ceiling, oversize)
    packs = pack_units(cut(list(enumerate(sizes)), policy), policy)
    totals = [sum(u[2] for u in units) for units, _ in packs]
    assert sum(totals) == sum(sizes)
    assert [u[:2] for units, _ in packs for u in units] == [u[:2] for u in cut(list(enumerate(sizes)), policy)]
    assert max(totals) <= policy.bound(max(sizes))
    assert len(packs) <= -(-sum(sizes) // b_min)
    if ceiling == "after":
        assert all(t >= b_min for t in totals[:-1])


@settings(max_examples=200, deadline=None)
@given(sizes_lists, st.integers(5, 70))
def test_fits_against_brute_force(sizes, capacity):
    rows = [(f"k{k:03d}", n) for k, n in enumerate(sizes)]
    for method, best in ((first_fit_decreasing, False), (best_fit_decreasing, True)):
        loads, want = [], {}
        for key, n in sorted(rows, key=lambda r: (-r[1], r[0])):
            fits = [b for b, load in enumerate(loads) if n <= capacity and load + n <= capacity]
            b = (max(fits, key=lambda b: (loads[b], -b)) if best else fits[0]) if fits else len(loads)
            if b == len(loads):
                loads.append(0)
            loads[b] += n
            want[key] = b
        assert {k: b for (k, _), b in zip(rows, method(rows, capacity), strict=True)} == want


def test_lognormal_sizes_sum_exactly():
    for parts, texts, sigma in ((400, 60_000, 1.72), (40, 6000, 2.5), (7, 7, 1.0)):
        s = lognormal_sizes(parts, texts, sigma)
        assert sum(s) == texts and min(s) >= 1 and s == sorted(s)
    assert max(lognormal_sizes(400, 60_000, 1.72)) == 6390


def test_policy_is_checked():
    for bad in ((0, 5), (6, 5), (5, 9)):
        with pytest.raises(ValueError, match="b_m"):
            PackPolicy(*bad)
    assert PackPolicy.for_texts(60_000) == PackPolicy(600, 3000)


def test_lanes_are_balanced_and_whole(spark):
    from packflow.operators.sizes import assign_lanes

    sizes = spark.createDataFrame([(f"k{k}", n) for k, n in enumerate(lognormal_sizes(60, 6000, 1.5))], "part_key string, n_texts long")
    loads = {}
    for how in ("hash", "range", "lpt"):
        rows = assign_lanes(sizes, 4, how).collect()
        assert len(rows) == 60 and all(0 <= r.lane < 4 for r in rows)
        loads[how] = max(sum(r.n_texts for r in rows if r.lane == lane) for lane in range(4))
    assert loads["lpt"] <= loads["hash"] and loads["lpt"] <= max(2000, 1.1 * 6000 / 4)


@pytest.mark.parametrize("how", ["key", "md5", "size_asc", "size_desc", "largest_last", "near_full_then_largest"])
def test_arrival_orders_are_permutations(spark, how):
    sizes = spark.createDataFrame([(None, 3), ("a", 50), ("b", 3), ("c", 9)], "part_key string, n_texts long")
    rows = sorted(arrival_order(sizes, how, 5).collect(), key=lambda r: r.arrival)
    assert [r.arrival for r in rows] == [1, 2, 3, 4]
    if how == "largest_last":
        assert rows[-1].n_texts == 50
    if how == "near_full_then_largest":
        assert [r.n_texts for r in rows][:2] == [3, 50]


def test_jump_equals_scan_for_small_inputs(spark):
    for values in ([1], [5, 5, 5], [1, 2, 3, 4, 5, 6, 7], [10, 1, 1, 1]):
        sizes = arrival_order(spark.createDataFrame([(f"k{k}", n) for k, n in enumerate(values)], "part_key string, n_texts long"))
        jump = {r.part_key: r.pack_id for r in packing.greedy_jump(sizes, 6).collect()}
        scan = {r.part_key: r.pack_id for r in packing.greedy_pack(sizes.withColumn("n_bytes", sizes.n_texts), PackPolicy(6, 10**6, "after", "own")).collect()}
        assert jump == scan
