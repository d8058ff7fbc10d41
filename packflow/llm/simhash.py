"""SimHash near-duplicates by deletion-variant signatures.

A fingerprint's 64 bits are cut into two halves, fewer than the classic bits+1 segments, so of two
fingerprints that differ in at most three bits one half differs in at most one bit. Each half is
indexed under its 32 variants with one bit wildcarded; fingerprints that are equal in a variant are
the candidates of an equality join and are verified. Documents with equal fingerprints count once, so
copies cost nothing. Variants are counted by a grouped count that keeps the least, the greatest and the
combination of all: two or three fingerprints of a variant are known from these. Where more than ``PAIR_GROUP`` fingerprints share a variant, they
are not paired but linked to the least of every small ball around the bits that the variant leaves open,
which loses no link: two fingerprints that differ in few enough bits have a common centre.

Null ids sort last and come back null; null and empty texts have fingerprint zero and are linked like
any other; repeated rows each get a row.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from packflow.llm.common import NULL_ID, id_or_last, in_few_tasks, materialize, sliced, small_batches, text_bytes

#: Up to so many fingerprints of one variant are compared pair by pair.
PAIR_GROUP = 64
#: Cells of variants, by hash, that tell which variants may be crowded.
CELLS = 1 << 18


def fingerprint(text: bytes, words: int = 3, seed: int = 42) -> int:
    """Majority of the bits of the shingles' XXH64, as a signed 64-bit number; ASCII case folds."""
    import xxhash

    split = text.lower().split()
    if not split:
        return 0
    shingles = [b" ".join(split[i : i + words]) for i in range(max(1, len(split) - words + 1))]
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(s, seed) for s in shingles), np.uint64, len(shingles))
    total = np.zeros(64, np.int64)
    for start in range(0, len(h), 1 << 16):
        total += np.unpackbits(h[start : start + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * total > len(h), bitorder="little").view(np.int64)[0])


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, kind: str = "long") -> DataFrame:
    """(key, fp): the id, null as NULL_ID, or a name of kind string, and the fingerprint of each whole text."""
    key = id_or_last(id_col) if kind == "long" else F.col(id_col)

    def run(batches):
        for batch in sliced(batches, "__text", 8 << 20):
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([fingerprint(t, words) for t in text_bytes(batch.column(1))], pa.int64())], names=["key", "fp"])

    return df.select(key.alias("key"), F.col(text_col).cast("string").alias("__text")).mapInArrow(run, f"key {kind}, fp long")


def variants(nodes: DataFrame) -> DataFrame:
    """(variant, fp): the 64 one-wildcard variants of each fingerprint; half and wildcard are in the variant."""
    half = lambda s: F.shiftrightunsigned("fp", 32 * s).bitwiseAND(F.lit(0xFFFFFFFF))
    made = [
        F.lit((32 * s + w) << 32).bitwiseOR(half(s).bitwiseAND(F.lit(0xFFFFFFFF ^ (1 << w))))
        for s in (0, 1)
        for w in range(32)
    ]
    return nodes.select("fp", F.explode(F.array(*made)).alias("variant"))


def rest(variant: str = "variant", fp: str = "fp"):
    """What a variant leaves open, as 33 bits: the wildcard bit, and the other half."""
    return F.expr(f"""case when {variant} < {32 << 32}L
        then shiftleft(shiftrightunsigned({fp}, cast(shiftright({variant}, 32) as int)) & 1L, 32) | shiftrightunsigned({fp}, 32)
        else shiftleft(shiftrightunsigned({fp}, cast(shiftright({variant}, 32) as int)) & 1L, 32) | ({fp} & {0xFFFFFFFF}L) end""")


def within(bits: int) -> list[int]:
    """Numbers of 33 bits of which at most so many are set."""
    return [sum(1 << b for b in chosen) for n in range(bits + 1) for chosen in combinations(range(33), n)]


def links(nodes: DataFrame, max_bits: int = 2) -> DataFrame:
    """(a, b), a < b: enough links between fingerprints of ``max_bits`` or fewer differing bits to
    join whatever a chain of such links joins. ``nodes`` is a table, or cheap to make again."""
    if not 0 <= max_bits <= 3:
        raise ValueError("two halves cover at most three differing bits")
    every = variants(nodes)
    counts = every.groupBy("variant").agg(F.count(F.lit(1)).alias("n"), F.min("fp").alias("a"), F.max("fp").alias("b"), F.bit_xor("fp").alias("all")).where("n > 1")
    counts = materialize(in_few_tasks(counts, 64 * nodes.count()), "variants")
    # of three, the one that is neither least nor greatest is what all and these two leave when combined by bits
    middle = F.col("all").bitwiseXOR(F.col("a")).bitwiseXOR(F.col("b"))
    pair = lambda a, b: F.struct(a.alias("a"), b.alias("b"))
    ends = F.array(pair(F.col("a"), F.col("b")))
    pairs = F.when(F.col("n") == 2, ends).otherwise(F.concat(ends, F.array(pair(F.col("a"), middle), pair(middle, F.col("b")))))
    two = counts.where("n <= 3").select(F.explode(pairs).alias("p")).select("p.a", "p.b").where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= max_bits)
    crowd = counts.where("n > 3").select("variant", "n")
    # at most CELLS numbers are broadcast: variants that are in no crowd's cell need not move to be joined
    cell = F.pmod(F.xxhash64("variant"), F.lit(CELLS)).alias("cell")
    maybe = every.withColumn("cell", cell).join(F.broadcast(crowd.select(cell).distinct()), "cell", "left_semi").drop("cell")
    shared = materialize(maybe.join(crowd, "variant"), "shared")
    few = (
        shared.where(F.col("n") <= PAIR_GROUP)
        .groupBy("variant")
        .agg(F.sort_array(F.collect_list("fp")).alias("fps"))
        .select(F.explode("fps").alias("a"), "fps")
        .select("a", F.explode(F.filter("fps", lambda b: (b > F.col("a")) & (F.bit_count(b.bitwiseXOR(F.col("a"))) <= max_bits))).alias("b"))
    )
    # the centre is within max_bits // 2 of the one and the rest of max_bits of the other; so small balls have few members
    inner, outer = within(max_bits // 2), within(max_bits - max_bits // 2)
    centre = F.explode(F.array(*(F.struct(F.lit(m).cast("long").alias("mask"), F.lit(m in inner).alias("inner")) for m in outer))).alias("c")
    least = F.min(F.when(F.col("inner"), F.col("fp"))).over(Window.partitionBy("variant", "centre"))
    many = (
        shared.where(F.col("n") > PAIR_GROUP)
        .select("variant", "fp", rest().alias("rest"), centre)
        .select("variant", "fp", F.col("rest").bitwiseXOR(F.col("c.mask")).alias("centre"), "c.inner")
        .withColumn("a", least)
        .where("a is not null and fp != a")
        .select(F.least("fp", "a").alias("a"), F.greatest("fp", "a").alias("b"))
    )
    return two.union(few).union(many).distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b", rows: int | None = None) -> DataFrame:
    """(node, root) for every node with an edge; root is the component's least node.

    Alternates large-star and small-star steps, each a grouped minimum and an equality join, until
    the edges are stars. Every step is checkpointed in the cluster's shared folder. ``rows``: how many
    edges there are, if that is known.
    """

    def large_star(e: DataFrame) -> DataFrame:
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()

    def small_star(e: DataFrame) -> DataFrame:
        least = e.groupBy("u").agg(F.min("v").alias("m"))
        return e.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").union(least.select("u", F.col("m").alias("v"))).distinct()

    current = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u != v").distinct()
    current = materialize(current if rows is None else in_few_tasks(current, rows), "edges")
    measure = lambda e: tuple(e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
    before = measure(current)
    while before[0]:
        current = materialize(in_few_tasks(small_star(large_star(current)), 2 * before[0]), "edges")
        now = measure(current)
        if now == before:
            break
        before = now
    roots = current.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return in_few_tasks(roots.union(current.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()), 2 * before[0])


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, max_bits: int = 2) -> DataFrame:
    """(id, fingerprint, component_id): component_id is the least id that links lead to."""
    from packflow.llm.common import shared_dir

    shared_dir(df.sparkSession, "probe")  # sets a checkpoint folder where there is none
    docs = materialize(fingerprints(df, id_col, text_col, words), "fingerprints")
    nodes = materialize(docs.groupBy("fp").agg(F.min("key").alias("least")), "nodes")
    roots = components(links(nodes.select("fp"), max_bits))
    member = nodes.join(roots, nodes.fp == roots.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    least = member.groupBy("root").agg(F.min("least").alias("component"))
    of_fp = member.join(least, "root").select("fp", "component")
    back = lambda c: F.when(F.col(c) == NULL_ID, None).otherwise(F.col(c))
    return docs.join(of_fp, "fp").select(back("key").alias(id_col), F.col("fp").alias("fingerprint"), back("component").alias("component_id"))


def keep_least(df: DataFrame, roots_of: Callable[[DataFrame], DataFrame], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The row with the least id, nulls last, of each group of texts, with all its columns; any one of rows
    that are equal in id and text.

    ``roots_of`` gives (node, root) for the texts (node, text) that are in a group with others. Rows are
    told apart by id and text, so rows of one id, or of none, with unlike texts all stay.
    """
    from packflow.llm.common import shared_dir

    shared_dir(df.sparkSession, "probe")  # sets a checkpoint folder where there is none
    text = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    row = F.struct(*(F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(df.columns)))
    named = df.select(F.md5(text(f"`{text_col}`").cast("binary")).alias("node"), id_or_last(id_col).alias("key"), row.alias("row"))
    with small_batches(df.sparkSession):
        one = materialize(named.groupBy("node").agg(F.min("key").alias("key"), F.min_by("row", "key").alias("row")), "distinct")
        roots = materialize(roots_of(one.select("node", text(f"row.c{df.columns.index(text_col)}").alias("text"))), "roots")
    best = roots.join(one.select("node", "key"), "node").groupBy("root").agg(F.min(F.struct("key", "node")).alias("best")).select("best.node")
    dropped = roots.select("node").join(best, "node", "left_anti")
    return one.join(dropped, "node", "left_anti").select(*(F.col(f"row.c{i}").alias(c) for i, c in enumerate(df.columns)))


def print_pairs(texts: DataFrame, words: int = 3, max_bits: int = 2) -> DataFrame:
    """(a, b), a < b: pairs of (node, text) with near fingerprints, enough to join all that those link. Texts
    of one fingerprint are paired with the least of them, which stands for it towards other fingerprints."""
    named = materialize(fingerprints(texts, "node", "text", words, "string"), "fingerprints")
    least = materialize(in_few_tasks(named.groupBy("fp").agg(F.min("key").alias("least")), named.count()), "least")
    within = named.join(least, "fp").where("key != least").select(F.col("least").alias("x"), F.col("key").alias("y"))
    side = lambda c, name: least.select(F.col("fp").alias(c), F.col("least").alias(name))
    across = links(least.select("fp"), max_bits).join(side("a", "x"), "a").join(side("b", "y"), "b").select("x", "y")
    return within.union(across).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, max_bits: int = 2) -> DataFrame:
    """The row with the least id of each group, nulls last, with all its columns."""

    def roots_of(texts: DataFrame) -> DataFrame:
        named = materialize(fingerprints(texts, "node", "text", words, "string"), "fingerprints")
        alike = named.groupBy("fp").agg(F.min("key").alias("least"), F.count(F.lit(1)).alias("n"))
        roots = components(links(named.select("fp").distinct(), max_bits))
        grouped = alike.join(roots, alike.fp == roots.node, "left").where("n > 1 or root is not null")
        grouped = grouped.select("fp", F.coalesce("root", "fp").cast("string").alias("root"))
        return named.join(grouped, "fp").select(F.col("key").alias("node"), "root")

    return keep_least(df, roots_of, id_col, text_col)
