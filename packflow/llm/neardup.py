"""Near-duplicates by SimHash and the Jaccard similarity of five-word shingles, exactly, for the corpus pipeline.

First come the pairs whose SimHash fingerprints differ in at most two bits. They are verified on the words,
and what holds is one group from then on. An exact join then adds the links that fingerprints do not show.

Two sets of similarity ``t`` or more share a member among the first ``n - ceil(t n) + 1`` of each, in any
order that all sets have in common (the prefix filter). The order taken is by the number of texts that
hold a shingle, rarest first; shingles of one text alone can match nothing and are passed over. So texts
that merely share common passages never meet, and each true pair does:

1. Tasks send each batch's distinct shingle hashes with their counts to buckets of the hash range, as
   packed blobs; the buckets reply how many texts hold each (a byte, exact up to 127).
2. Batches turn the replies into a row for each shared shingle of a prefix.
3. In each shingle's group a node is paired with its neighbour and with the text that has the least share
   of shingles of its own. A group of very many is cut into salted parts for that. What the words verify is
   linked; a large group of near copies becomes one component at a cost in proportion to its size.
4. Groups that still hold several components are paired up, only across components, and only where places
   in the prefixes and sizes leave room for the similarity. These are verified, too.

Every link is verified on the words themselves, and by 4 none is lost, so the groups are those of all
pairs of ``t`` or more. Sketched counts and hash collisions change the order or add candidates, no more.

Equal texts are one node, named by their digest. ASCII case folds and words are cut at white space, as in
``simhash``. Texts without words are alike. Rows of one id, or of none, with unlike texts are told apart.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from packflow.llm.common import grid, in_few_tasks, materialize, sliced, text_bytes
from packflow.llm.simhash import components, keep_least, print_pairs

WORDS, SIMILARITY = 5, 0.8
HASH_BITS = 48
#: Nodes of one shingle that are ordered together; more are cut by salt.
SALTED = 4096
#: Pairs of texts that a task verifies, at least.
PAIRS_A_TASK = 256
#: Texts that a pair names and a task writes, a few MB of them.
TEXTS_A_TASK = 1 << 12
#: Bytes of text that are hashed together; each takes some 50 bytes meanwhile.
CHUNK = 1 << 18

#: ASCII letters to lower case, white space to blanks.
FOLD = bytes(32 if c in b"\t\n\v\f\r" else c + 32 if 65 <= c <= 90 else c for c in range(256))
BASE = 0x9E3779B97F4A7C15
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the odd base and of its inverse, modulo 2**64."""
    if len(_powers[0]) < n:
        for k, b in enumerate((BASE, pow(BASE, -1, 1 << 64))):
            _powers[k] = np.cumprod(np.append(np.uint64(1), np.full(n - 1, b, np.uint64)), dtype=np.uint64)
    return _powers[0], _powers[1]


def mixed(h: np.ndarray) -> np.ndarray:
    h = h ^ h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    return h ^ h >> np.uint64(29)


def word_hashes(buf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(start, hash) of the words of folded bytes."""
    blank = np.concatenate(([True], buf == 32, [True]))
    edge = np.flatnonzero(blank[1:] != blank[:-1])
    start, end = edge[::2], edge[1::2]
    out, at = [], 0
    while at < len(start):
        stop = max(at + 1, int(np.searchsorted(end, start[at] + CHUNK, side="right")))
        low, high = int(start[at]), int(end[stop - 1])
        up, down = powers(high - low + 1)
        total = np.zeros(high - low + 1, np.uint64)
        np.cumsum((buf[low:high].astype(np.uint64) + np.uint64(1)) * up[: high - low], out=total[1:])
        s, e = start[at:stop] - low, end[at:stop] - low
        out.append(mixed((total[e] - total[s]) * down[s]))
        at = stop
    return start, np.concatenate(out) if out else np.empty(0, np.uint64)


def shingle_hashes(texts: list[bytes], words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(text, hash), sorted and distinct: each text's shingles as 48-bit numbers. A text of fewer words has
    the whole sequence for its shingle, one without words a number that stands for that."""
    raw = b" ".join(texts).translate(FOLD)
    ends = np.cumsum([len(t) + 1 for t in texts])
    start, h = word_hashes(np.frombuffer(raw, np.uint8))
    text = np.searchsorted(ends, start, side="right")
    count = np.bincount(text, minlength=len(texts))
    first = np.cumsum(count) - count
    of, hashes = [np.flatnonzero(count == 0)], [np.zeros(int((count == 0).sum()), np.uint64)]
    for k in range(1, words + 1):
        at = first[count == k] if k < words else np.flatnonzero(text[: len(text) - words + 1] == text[words - 1 :])
        if len(at):
            whole = np.full(len(at), k, np.uint64)
            for i in range(k):
                whole = whole * np.uint64(BASE) + h[at + i]
            of.append(text[at])
            hashes.append(mixed(whole) >> np.uint64(64 - HASH_BITS))
    of, hashes = np.concatenate(of), np.concatenate(hashes)
    del raw, start, h, text
    order = np.lexsort((hashes, of))
    of, hashes = of[order], hashes[order]
    new = np.append(True, (of[1:] != of[:-1]) | (hashes[1:] != hashes[:-1]))[: len(of)]
    return of[new], hashes[new]


def shingles(text: bytes, words: int = WORDS) -> set[bytes]:
    """Shingles of a text; of fewer words, the whole sequence."""
    split = text.lower().split()
    return {b" ".join(split[i : i + words]) for i in range(max(1, len(split) - words + 1))} if split else set()


def similarity(a: set[bytes], b: set[bytes]) -> float:
    return len(a & b) / len(a | b) if a or b else 1.0


def cuts_of(hashes: np.ndarray, buckets: int) -> np.ndarray:
    """Where each bucket's hashes begin in a sorted array."""
    return np.searchsorted(hashes, np.array([-(-(b << HASH_BITS) // buckets) for b in range(buckets + 1)], np.uint64))


def pack_counts(hashes: np.ndarray, counts: np.ndarray) -> bytes:
    """Sorted hashes as steps, and their counts."""
    import zstandard

    step = np.diff(hashes, prepend=np.uint64(0))[1:]
    wide = len(step) and int(step.max()) >> 32
    head = np.array([len(hashes), int(hashes[0]), 8 if wide else 4], np.int64)
    return zstandard.compress(head.tobytes() + step.astype("<u8" if wide else "<u4").tobytes() + counts.astype(np.uint32).tobytes(), 1)


def unpack_counts(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    import zstandard

    data = zstandard.decompress(blob)
    n, low, width = np.frombuffer(data, np.int64, 3).tolist()
    step = np.frombuffer(data, f"<u{width}", n - 1, 24).astype(np.uint64)
    return np.cumsum(np.append(np.uint64(low), step), dtype=np.uint64), np.frombuffer(data, np.uint32, n, 24 + width * (n - 1))


def count_class(total: np.ndarray) -> np.ndarray:
    """A byte that grows with the count: the count up to 127, then three steps for each doubling."""
    return np.where(total < 128, total, np.minimum(255, 127 + 3 * np.log2(np.maximum(total, 128) / 127))).astype(np.uint8)


def counted(table: pa.Table) -> pa.Table:
    """Of one bucket: for each batch, the count class over all texts of each of its hashes."""
    import zstandard

    parts = [unpack_counts(b) for b in table.column("blob").to_pylist()]
    sizes = [len(h) for h, _ in parts]
    h, n = np.concatenate([h for h, _ in parts]), np.concatenate([c for _, c in parts])
    order = np.argsort(h, kind="stable")
    group = np.cumsum(np.append(True, h[order][1:] != h[order][:-1])) - 1
    out = np.empty(len(h), np.uint8)
    out[order] = count_class(np.bincount(group, n[order]))[group]
    blobs = [zstandard.compress(x.tobytes(), 1) for x in np.split(out, np.cumsum(sizes)[:-1])]
    return pa.table({"batch": table.column("batch"), "bucket": table.column("bucket"), "classes": pa.array(blobs, pa.binary())})


def prefix_rows(nodes: list[str], texts: list[bytes], replies: pa.Table, threshold: float) -> pa.Table:
    """(shingle, node, place, n, own): the shared shingles of each text's prefix."""
    import zstandard

    of, h = shingle_hashes(texts)
    u = np.unique(h)
    parts = sorted(zip(replies.column("bucket").to_pylist(), replies.column("classes").to_pylist(), strict=True))
    rank = np.frombuffer(b"".join(zstandard.decompress(c) for _, c in parts), np.uint8)
    if len(rank) != len(u):
        raise RuntimeError("the input gave other rows when it was read again; materialize it first")
    rank = rank[np.searchsorted(u, h)]
    order = np.lexsort((h, rank, of))
    of, h, rank = of[order], h[order], rank[order]
    n = np.bincount(of, minlength=len(texts))
    place = np.arange(len(of)) - (np.cumsum(n) - n)[of]
    own = np.bincount(of, rank == 1, len(texts)).astype(np.int64)
    least = np.ceil(threshold * n - 1e-9).astype(np.int64)
    keep = (place <= (n - least)[of]) & (rank > 1)
    of = of[keep]
    names = pa.array(nodes, pa.string()).take(pa.array(of, pa.int64()))
    return pa.table({"shingle": pa.array(h[keep].astype(np.int64)), "node": names, "place": pa.array(place[keep], pa.int64()), "n": pa.array(n[of], pa.int64()), "own": pa.array(own[of], pa.int64())})


def gathered(batches, batch_bytes: int):
    """(number, nodes, texts) of about ``batch_bytes`` each; the number is the task's and a count."""
    from pyspark import TaskContext

    number, nodes, texts, held = TaskContext.get().partitionId() << 32, [], [], 0
    for part in sliced(batches, "text", batch_bytes // 4):
        new = text_bytes(part.column(1))
        nodes += part.column(0).to_pylist()
        texts += new
        held += sum(map(len, new))
        if held >= batch_bytes:
            yield number, nodes, texts
            number, nodes, texts, held = number + 1, [], [], 0
    if nodes:
        yield number, nodes, texts


def prefixes(texts: DataFrame, threshold: float) -> DataFrame:
    """The prefix rows of (node, text). The input must be stable, as a table scan is."""
    size = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    batch_bytes, buckets = grid(size)

    def pack(batches):
        import pickle

        import zstandard

        for number, nodes, found in gathered(batches, batch_bytes):
            yield pa.RecordBatch.from_arrays([pa.array([number], pa.int64()), pa.array([zstandard.compress(pickle.dumps((nodes, found)), 3)], pa.binary())], names=["batch", "blob"])

    def send(batches):
        for number, _, found in gathered(batches, batch_bytes):
            u, n = np.unique(shingle_hashes(found)[1], return_counts=True)
            cuts = cuts_of(u, buckets)
            full = np.flatnonzero(np.diff(cuts)).tolist()
            blobs = [pack_counts(u[cuts[k] : cuts[k + 1]], n[cuts[k] : cuts[k + 1]]) for k in full]
            yield pa.RecordBatch.from_arrays([pa.array(full, pa.int64()), pa.array([number] * len(full), pa.int64()), pa.array(blobs, pa.binary())], names=["bucket", "batch", "blob"])

    def resolve(left, right):
        import pickle

        import zstandard

        made = [prefix_rows(*pickle.loads(zstandard.decompress(b)), right, threshold) for b in left.column("blob").to_pylist()]
        return pa.concat_tables(made) if made else pa.table({c: pa.array([], t) for c, t in (("shingle", pa.int64()), ("node", pa.string()), ("place", pa.int64()), ("n", pa.int64()), ("own", pa.int64()))})

    batches = texts.select("node", "text").mapInArrow(pack, "batch long, blob binary")
    sent = texts.select("node", "text").mapInArrow(send, "bucket long, batch long, blob binary")
    replies = sent.groupBy("bucket").applyInArrow(counted, "batch long, bucket long, classes binary")
    made = batches.groupBy("batch").cogroup(replies.groupBy("batch")).applyInArrow(resolve, "shingle long, node string, place long, n long, own long")
    return in_few_tasks(made, size, 4 * batch_bytes)


def verified(pairs: DataFrame, texts: DataFrame, threshold: float) -> DataFrame:
    """The pairs (a, b), a table, whose texts reach the threshold. Only texts that a pair names are moved."""
    named = pairs.select(F.col("a").alias("node")).union(pairs.select(F.col("b").alias("node"))).distinct()
    n_pairs = pairs.count()
    # moved once more, as a scan of all texts must keep its tasks
    few = materialize(texts.join(named, "node", "left_semi").repartition(max(1, -(-2 * n_pairs // TEXTS_A_TASK))), "near-texts")
    side = lambda c: few.select(F.col("node").alias(c), F.col("text").alias(f"text_{c}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "text_a", "text_b")

    def run(batches):
        for batch in sliced(batches, "text_a", 8 << 20):
            a, b = (map(shingles, text_bytes(batch.column(k))) for k in (2, 3))
            good = [similarity(x, y) >= threshold for x, y in zip(a, b, strict=True)]
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    return in_few_tasks(both, n_pairs, PAIRS_A_TASK).mapInArrow(run, "a string, b string")


def linked(texts: DataFrame, threshold: float = SIMILARITY) -> DataFrame:
    """(node, root) for every node of (node, text) with a near-duplicate."""
    prints = materialize(print_pairs(texts), "prints")
    sure = materialize(verified(prints, texts, threshold), "links")
    share = threshold / (1 + threshold)
    rows = materialize(prefixes(texts, threshold).withColumn("left", F.col("n") - F.col("place")), "prefixes")
    least_of = lambda n, m: F.ceil(share * (n + m) - 1e-9)
    centre = F.min(F.struct((F.col("own") / F.col("n")).alias("share"), "node", "n", "left"))
    groups = rows.groupBy("shingle").agg(F.count(F.lit(1)).alias("members"), F.min("n").alias("smallest"), centre.alias("centre")).where("members > 1")
    # a member stays if any other of the group could reach the threshold with it
    partner = F.greatest(F.ceil(threshold * F.col("n") - 1e-9), F.col("smallest"))
    able = rows.join(groups, "shingle").where(F.col("left") >= least_of(F.col("n"), partner))
    able = able.withColumn("salt", F.pmod(F.xxhash64("node"), F.ceil(F.col("members") / SALTED)))
    able = materialize(in_few_tasks(able, rows.count()), "able")
    n_able = able.count()

    def near(a: str, b: str) -> Column:
        """Whether sizes and places leave room for the similarity."""
        n, m = F.col(f"{a}.n"), F.col(f"{b}.n")
        fits = F.least(n, m) >= threshold * F.greatest(n, m) - 1e-9
        return fits & (F.least(F.col(f"{a}.left"), F.col(f"{b}.left")) >= least_of(n, m))

    def ordered(pairs: DataFrame) -> DataFrame:
        return pairs.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()

    me = F.struct("node", "n", "left")
    next_one = F.lead(me).over(Window.partitionBy("shingle", "salt").orderBy("node"))
    two = able.select(me.alias("x"), next_one.alias("next"), F.struct("centre.node", "centre.n", "centre.left").alias("centre"))
    two = two.select("x", F.explode(F.array("next", "centre")).alias("y"))
    tried = ordered(two.where(F.col("y.node").isNotNull() & (F.col("x.node") != F.col("y.node")) & near("x", "y")))
    tried = materialize(in_few_tasks(tried, 2 * n_able), "tried")
    tried = materialize(in_few_tasks(tried.join(prints, ["a", "b"], "left_anti"), tried.count()), "untried")
    first = sure.union(materialize(verified(tried, texts, threshold), "links"))
    roots = materialize(components(first, rows=first.count()), "roots")

    placed = able.select("shingle", "node", "n", "left").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    mixed_ones = placed.groupBy("shingle").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low < high").select("shingle")
    placed = materialize(in_few_tasks(placed.join(mixed_ones, "shingle", "left_semi"), n_able), "mixed")
    parts = placed.groupBy("shingle", "root").agg(F.max("left").alias("left"), F.min("n").alias("n"))
    part = lambda c: parts.select("shingle", F.col("root").alias(f"root_{c}"), F.struct("n", "left").alias(c))
    room = F.least("a.left", "b.left") >= least_of(F.col("a.n"), F.col("b.n"))
    facing = part("a").join(part("b"), "shingle").where(F.col("root_a") < F.col("root_b")).where(room).select("shingle", "root_a", "root_b")
    side = lambda c: placed.select("shingle", F.col("root").alias(f"root_{c}"), F.struct("node", "n", "left").alias("x" if c == "a" else "y"))
    crossing = facing.join(side("a"), ["shingle", "root_a"]).join(side("b"), ["shingle", "root_b"]).where(near("x", "y"))
    most = placed.groupBy("shingle").count().agg(F.sum(F.expr("count * (count - 1) div 2").cast("decimal(38,0)"))).first()[0]
    rest = materialize(in_few_tasks(ordered(crossing).join(tried.union(prints), ["a", "b"], "left_anti"), int(most or 0)), "crossing")
    second = materialize(verified(rest, texts, threshold), "links")
    linking = first.union(second)
    return components(linking, rows=linking.count())


def keep_one_similar(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = SIMILARITY) -> DataFrame:
    """The row with the least id of each group, nulls last, with all its columns."""
    return keep_least(df, lambda texts: linked(texts, threshold), id_col, text_col)
