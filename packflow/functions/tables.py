"""Table functions."""

from __future__ import annotations

from pyspark.sql.functions import udtf


@udtf(returnType="part_key: string, chunk: int, n: bigint")
class SplitOversized:
    """``split_oversized(key, n, b_max)``: the pieces of a partition, of at most ``b_max`` each."""

    def eval(self, key: str, n: int, b_max: int):
        for chunk in range(max(1, -(-n // b_max))):
            yield key, chunk, min(b_max, n - chunk * b_max)


@udtf(returnType="lane: int, packs: bigint, texts: bigint, largest: bigint, by_ceiling: bigint")
class PackReport:
    """``pack_report(TABLE(plan totals) PARTITION BY lane)``: a line per lane."""

    def __init__(self):
        self.lane, self.packs, self.texts, self.largest, self.ceiling = None, 0, 0, 0, 0

    def eval(self, row):
        self.lane, self.packs, self.texts = row["lane"], self.packs + 1, self.texts + row["n"]
        self.largest, self.ceiling = max(self.largest, row["n"]), self.ceiling + (row["reason"] in ("ceiling", "oversize"))

    def terminate(self):
        if self.packs:
            yield self.lane, self.packs, self.texts, self.largest, self.ceiling


def register(spark) -> None:
    spark.udtf.register("split_oversized", SplitOversized)
    spark.udtf.register("pack_report", PackReport)
