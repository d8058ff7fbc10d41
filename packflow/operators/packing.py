"""Pack plans from partition sizes alone.

A plan has a row per unit: ``lane, pack_id, part_key, chunk, n, reason`` in arrival order, where a unit is
a partition or, split, a piece of one. Lanes are independent. Only sizes, one row per partition, go
through here; texts follow a plan later.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from packflow.config import PackPolicy
from packflow.operators.sizes import lane_of

PLAN = "lane int, pack_id long, part_key string, chunk int, n long, start_off long, end_off long, reason string, arrival long"


class Packer:
    """The state of one lane: a running total and what made the last pack close."""

    def __init__(self, policy: PackPolicy):
        self.policy, self.total, self.pack = policy, 0, 0

    def add(self, n: int, whole: int) -> tuple[str | None, str | None]:
        """Take a unit of ``n`` from a partition of ``whole``. (reason of the pack closed before it,
        reason of the pack closed with it)."""
        p, before, after = self.policy, None, None
        if p.ceiling == "before" and self.total and self.total + n > p.b_max:
            before, self.total = "ceiling", 0
        self.total += n
        if self.total >= p.b_min:
            after = "oversize" if whole > p.b_max else "ceiling" if self.total >= p.b_max else "efficiency"
            self.total = 0
        return before, after


def pack_units(units: Iterable[tuple], policy: PackPolicy) -> list[tuple[list[tuple], str]]:
    """Packs of (key, chunk, n, whole, ...) units, with the reason each closed. Plain Python, for one lane."""
    packs, held, state = [], [], Packer(policy)
    for unit in units:
        before, after = state.add(unit[2], unit[3])
        if before:
            packs.append((held, before))
            held = []
        held.append(unit)
        if after:
            packs.append((held, after))
            held = []
    return packs + ([(held, "final")] if held else [])


def units(sizes: DataFrame, policy: PackPolicy) -> DataFrame:
    """Sizes as units ``(part_key, chunk, n, whole)``; pieces of at most ``b_max`` if split."""
    size = F.col("n_texts" if policy.unit == "texts" else "n_bytes")
    if policy.oversize == "own":
        return sizes.withColumn("chunk", F.lit(0)).withColumn("n", size).withColumn("whole", size)
    top = F.lit(policy.b_max).cast("long")
    last = F.greatest(F.lit(0), F.ceil(size / top) - 1).cast("int")
    return sizes.withColumn("chunk", F.explode(F.sequence(F.lit(0), last))).withColumn("whole", size).withColumn("n", F.least(top, size - F.col("chunk") * top))


def greedy_pack(sizes: DataFrame, policy: PackPolicy, lanes: int = 1) -> DataFrame:
    """The two-threshold plan: a scan over each lane's units in arrival order with O(1) state.

    ``sizes`` needs ``arrival``; a ``lane`` column is taken if there is one, else keys are hashed to lanes.
    """
    if "lane" not in sizes.columns:
        sizes = sizes.withColumn("lane", lane_of(F.col("part_key"), lanes))
    ordered = units(sizes, policy).select("lane", "arrival", "part_key", "chunk", "n", "whole").repartitionById(lanes, "lane").sortWithinPartitions("lane", "arrival", "part_key", "chunk")

    def scan(batches):
        lane, state, held, offset, pack = object(), None, [], 0, 0
        for batch in batches:
            out = []

            def close(reason, out=out):
                nonlocal held, offset, pack
                out.extend((*row, reason) for row in held)
                held, offset, pack = [], 0, pack + 1

            for own, arrival, key, chunk, n, whole in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if own != lane:
                    if held:
                        close("final")
                    lane, state, pack = own, Packer(policy), 0
                before, after = state.add(n, whole)
                if before:
                    close(before)
                held.append((lane, pack, arrival, key, chunk, n, offset, offset + n))
                offset += n
                if after:
                    close(after)
            yield rows(out)
        if held:
            yield rows([(*row, "final") for row in held])

    def rows(out):
        names = ["lane", "pack_id", "arrival", "part_key", "chunk", "n", "start_off", "end_off", "reason"]
        types = [pa.int32(), pa.int64(), pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.string()]
        made = dict(zip(names, (pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [[]] * 9, types, strict=True)), strict=True))
        return pa.RecordBatch.from_pydict({f.split()[0]: made[f.split()[0]] for f in PLAN.split(", ")})

    return ordered.mapInArrow(scan, PLAN)


def pack_totals(plan: DataFrame) -> DataFrame:
    """(lane, pack_id, parts, n, reason): one row per pack."""
    return plan.groupBy("lane", "pack_id").agg(F.count(F.lit(1)).alias("parts"), F.sum("n").alias("n"), F.max("reason").alias("reason"))


def pack_bounds(plan: DataFrame) -> DataFrame:
    """Start and end of each unit in its pack's matrix, by a window over the plan."""
    w = Window.partitionBy("lane", "pack_id").orderBy("arrival", "part_key", "chunk").rowsBetween(Window.unboundedPreceding, 0)
    return plan.select("lane", "pack_id", "part_key", "chunk", "n", (F.sum("n").over(w) - F.col("n")).alias("start_off"), F.sum("n").over(w).alias("end_off"))


def prefix_pack(sizes: DataFrame, b_min: int) -> DataFrame:
    """Cuts where the running total passes multiples of ``b_min``: no sequential state, the same size bound."""
    w = Window.partitionBy("lane").orderBy("arrival", "part_key")
    if "lane" not in sizes.columns:
        sizes = sizes.withColumn("lane", F.lit(0))
    before = F.sum("n_texts").over(w.rowsBetween(Window.unboundedPreceding, 0)) - F.col("n_texts")
    return sizes.select("lane", F.floor(before / b_min).cast("long").alias("pack_id"), "part_key", F.lit(0).alias("chunk"), F.col("n_texts").alias("n"), "arrival")


def greedy_jump(sizes: DataFrame, b_min: int, tasks: int | None = None) -> DataFrame:
    """The greedy plan without a ceiling, for very many partitions: each partition points to the first one
    whose preceding total is ``b_min`` more, and doubling the pointers from the first partition marks where
    packs begin. ``arrival`` must count from 1.

    Nothing is in one task but a row for each range of arrivals: totals are running sums within a range and
    the ranges' offsets. A pointer's target is found by a merge within equal stretches of the running total,
    of ``b_min`` or more each, to which a probe and the first partition of a stretch go. Inside a range,
    pointers are followed to where they leave it; log2(ranges) rounds of equality joins between ranges and
    one more pass within them mark the rest.
    """
    from packflow.operators.resume import checkpointed

    spark = sizes.sparkSession
    tasks = tasks or max(2, spark.sparkContext.defaultParallelism)
    last = sizes.agg(F.max("arrival")).first()[0]
    if last is None:
        return sizes.select(F.lit(0).alias("lane"), F.lit(0).cast("long").alias("pack_id"), "part_key", F.lit(0).alias("chunk"), F.col("n_texts").alias("n"), "arrival")
    stretch = -(-last // tasks)
    ranged = sizes.select("part_key", "arrival", F.col("n_texts").alias("n"), (F.col("arrival") - 1).alias("i"), F.floor((F.col("arrival") - 1) / stretch).cast("int").alias("range"))
    within = Window.partitionBy("range").orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    ranged = checkpointed(ranged.repartitionById(tasks, "range").withColumn("c", F.sum("n").over(within) - F.col("n")))
    totals = ranged.groupBy("range").agg(F.sum("n").alias("total"))
    base = totals.select("range", (F.sum("total").over(Window.orderBy("range")) - F.col("total")).alias("before"))
    rows = checkpointed(ranged.join(F.broadcast(base), "range").withColumn("c", F.col("c") + F.col("before")).drop("before"))
    grand = rows.agg(F.max(F.col("c") + F.col("n"))).first()[0]
    wide = max(b_min, -(-grand // tasks), 1)
    # the first partition of each stretch of totals, and of the next one that has any: a row a stretch
    cell = lambda c: F.floor(c / wide).cast("long")
    heads = rows.groupBy(cell(F.col("c")).alias("cell")).agg(F.min("i").alias("head"))
    after = heads.select((F.col("cell")).alias("have"), "head").withColumn("previous", F.lag("have").over(Window.orderBy("have")))
    following = after.select(F.explode(F.sequence(F.coalesce(F.col("previous"), F.lit(-1)).cast("long"), F.col("have") - 1)).alias("cell"), F.col("head").alias("next"))
    target = rows.select(cell(F.col("c")).alias("cell"), F.col("c").alias("v"), F.lit(0).alias("kind"), "i")
    probe = rows.select(cell(F.col("c") + b_min).alias("cell"), (F.col("c") + b_min).alias("v"), F.lit(1).alias("kind"), "i")
    # from the greatest value down; targets stand before probes of the same value, which they serve
    later = Window.partitionBy("cell").orderBy(F.col("v").desc(), F.col("kind").asc(), F.col("i").desc()).rowsBetween(Window.unboundedPreceding, 0)
    merged = probe.union(target).withColumn("to", F.min(F.when(F.col("kind") == 0, F.col("i"))).over(later)).where("kind = 1")
    jump = merged.join(F.broadcast(following), "cell", "left").select("i", F.coalesce("to", "next").alias("to"))
    jump = checkpointed(jump.where("to is not null"))
    region = lambda c: F.floor(c / stretch).cast("int")

    def leave(batches):
        """Within a range: each place with where its pointers lead out of it."""
        table = {"i": [], "to": []}
        for batch in batches:
            table["i"] += batch.column(1).to_pylist()
            table["to"] += batch.column(2).to_pylist()
        out: dict[int, int] = {}
        for i, to in sorted(zip(table["i"], table["to"], strict=True), reverse=True):
            out[i] = out.get(to, to) if to // stretch == i // stretch else to
        rows = sorted(out.items())
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64())], names=["i", "to"])

    sent = jump.select(region(F.col("i")).alias("range"), "i", "to").repartitionById(tasks, "range")
    exits = checkpointed(sent.mapInArrow(leave, "i long, to long"))
    entered = rows.where("i = 0").select("i")
    hop = exits.where(region(F.col("to")) != region(F.col("i")))
    for _ in range(max(1, tasks.bit_length())):
        entered = checkpointed(entered.union(entered.join(hop, "i").select(F.col("to").alias("i"))).distinct())
        a, b = hop.alias("a"), hop.alias("b")
        hop = checkpointed(a.join(b, F.col("a.to") == F.col("b.i")).select("a.i", "b.to"))

    def mark(batches):
        """Within a range: the places where packs begin, followed from where the range is entered."""
        step, begin = {}, []
        for batch in batches:
            for i, to, entry in zip(*(c.to_pylist() for c in batch.columns[1:]), strict=True):
                if entry:
                    begin.append(i)
                else:
                    step[i] = to
        found = set()
        for i in begin:
            own = i // stretch
            while i is not None and i // stretch == own and i not in found:
                found.add(i)
                i = step.get(i)
        yield pa.RecordBatch.from_arrays([pa.array(sorted(found), pa.int64())], names=["i"])

    both = jump.select("i", "to", F.lit(False).alias("entry")).union(entered.select("i", F.lit(None).cast("long").alias("to"), F.lit(True).alias("entry")))
    starts = both.select(region(F.col("i")).alias("range"), "i", "to", "entry").repartitionById(tasks, "range").mapInArrow(mark, "i long")
    flagged = rows.join(starts.withColumn("start", F.lit(1)), "i", "left").withColumn("start", F.coalesce("start", F.lit(0)))
    flagged = checkpointed(flagged.repartitionById(tasks, "range").withColumn("pack", F.sum("start").over(within)))
    packs = flagged.groupBy("range").agg(F.sum("start").alias("packs"))
    ahead = packs.select("range", (F.sum("packs").over(Window.orderBy("range")) - F.col("packs")).alias("ahead"))
    number = F.col("ahead") + F.col("pack") - 1
    return flagged.join(F.broadcast(ahead), "range").select(F.lit(0).alias("lane"), number.cast("long").alias("pack_id"), "part_key", F.lit(0).alias("chunk"), "n", "arrival")


def first_fit_decreasing(rows: list[tuple], capacity: int) -> list[int]:
    """Bin of each (key, n), taken by size descending, ties by key: the first bin with room. A tree over
    the bins' free room finds it in O(log P). What is over the capacity gets a bin of its own."""
    width = 1
    while width < max(1, len(rows)):
        width *= 2
    free, used, out = [capacity] * (2 * width), 0, [0] * len(rows)
    for k in sorted(range(len(rows)), key=lambda k: (-rows[k][1], rows[k][0] is None, rows[k][0])):
        n = rows[k][1]
        if n > capacity:
            at, left = width + used, -1
        else:
            node = 1
            while node < width:
                node = 2 * node if free[2 * node] >= n else 2 * node + 1
            at, left = node, free[node] - n
        used = max(used, at - width + 1)
        out[k] = at - width
        free[at] = left
        at //= 2
        while at:
            free[at] = max(free[2 * at], free[2 * at + 1])
            at //= 2
    return out


def best_fit_decreasing(rows: list[tuple], capacity: int) -> list[int]:
    """As first fit, but the fullest bin with room, the earliest of equals."""
    room: list[tuple[int, int]] = []
    out, used = [0] * len(rows), 0
    for k in sorted(range(len(rows)), key=lambda k: (-rows[k][1], rows[k][0] is None, rows[k][0])):
        n = rows[k][1]
        at = bisect.bisect_left(room, (n, -1))
        if n <= capacity and at < len(room):
            left, b = room.pop(at)
            bisect.insort(room, (left - n, b))
        else:
            b, used = used, used + 1
            if n <= capacity:
                bisect.insort(room, (capacity - n, b))
        out[k] = b
    return out


def _in_one_group(sizes: DataFrame, assign) -> DataFrame:
    """A plan that needs all sizes together: one row per partition in one task, as the method asks."""

    def plan(table: pa.Table) -> pa.Table:
        keys, n = table.column("part_key").to_pylist(), table.column("n_texts").to_pylist()
        return pa.table({"lane": pa.array([0] * len(keys), pa.int32()), "pack_id": pa.array(assign(list(zip(keys, n, strict=True))), pa.int64()), "part_key": pa.array(keys, pa.string()), "chunk": pa.array([0] * len(keys), pa.int32()), "n": pa.array(n, pa.int64())})

    return sizes.select("part_key", "n_texts", F.lit(0).alias("one")).groupBy("one").applyInArrow(plan, "lane int, pack_id long, part_key string, chunk int, n long")


def ffd_pack(sizes: DataFrame, capacity: int) -> DataFrame:
    return _in_one_group(sizes, lambda rows: first_fit_decreasing(rows, capacity))


def bfd_pack(sizes: DataFrame, capacity: int) -> DataFrame:
    return _in_one_group(sizes, lambda rows: best_fit_decreasing(rows, capacity))


def next_fit(values: Iterable[int], capacity: int) -> Iterator[int]:
    """Bin numbers: a bin closes when the next item does not fit."""
    held = pack = 0
    for n in values:
        if held and held + n > capacity:
            held, pack = 0, pack + 1
        held += n
        yield pack


def next_fit_pack(sizes: DataFrame, capacity: int) -> DataFrame:
    """Classic Next-Fit in arrival order."""
    ordered = sizes.select("arrival", "part_key", "n_texts").repartition(1).sortWithinPartitions("arrival", "part_key")

    def scan(batches):
        held = pack = 0
        for batch in batches:
            n, ids = batch.column(2).to_pylist(), []
            for x in n:
                if held and held + x > capacity:
                    held, pack = 0, pack + 1
                held += x
                ids.append(pack)
            yield pa.RecordBatch.from_arrays([pa.array([0] * len(n), pa.int32()), pa.array(ids, pa.int64()), batch.column(1), pa.array([0] * len(n), pa.int32()), batch.column(2), batch.column(0)], names=["lane", "pack_id", "part_key", "chunk", "n", "arrival"])

    return ordered.mapInArrow(scan, "lane int, pack_id long, part_key string, chunk int, n long, arrival long")


def fixed_batches(sizes: DataFrame, size: int) -> DataFrame:
    """Calls of the boundary-blind baseline: (calls, texts, largest call)."""
    return sizes.agg(F.sum("n_texts").alias("texts")).select("texts", F.ceil(F.col("texts") / size).cast("long").alias("calls"), F.least(F.lit(size).cast("long"), "texts").alias("largest"))


def reassembled(plan: DataFrame) -> DataFrame:
    """Split partitions put together again: pieces counted, texts summed, and whether pieces are contiguous."""
    return plan.groupBy("part_key").agg(
        F.count(F.lit(1)).alias("pieces"), F.sum("n").alias("n_texts"), (F.max("chunk") + 1).cast("long").alias("last_piece"), F.countDistinct("pack_id").alias("packs")
    )
