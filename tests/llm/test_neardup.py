"""The pipeline's near-duplicate stage against all pairs."""

import itertools
import random

import pytest

import corpus_pipeline
from packflow.llm import common, neardup, simhash

STAGE = dict(corpus_pipeline.STAGES)["simhash_dedup"]


def test_hashes_tell_shingles_apart():
    """Vectorised hashes against shingles of words: equal counts, and equal overlaps of any two texts."""
    r = random.Random(3)
    texts = [b"", b" \t\n", b"One", b"one ", b"one two", b"a\x0bb\x0cC d", b"a b c d e", b"A B  c\nd e", b"\xc3\x89 \xc3\xa9 x y z"]
    texts += [" ".join(r.choices(["x", "Y", "yy", "zz\n"], k=r.randint(0, 40))).encode() for _ in range(60)]
    of, h = neardup.shingle_hashes(texts)
    sets = [set(h[of == k].tolist()) for k in range(len(texts))]
    for a, x in zip(texts, sets, strict=True):
        assert len(x) == max(1, len(neardup.shingles(a)))
        for b, y in zip(texts, sets, strict=True):
            if neardup.shingles(a) and neardup.shingles(b):
                assert len(x & y) == len(neardup.shingles(a) & neardup.shingles(b))
    small = neardup.CHUNK
    neardup.CHUNK = 16
    try:
        again = neardup.shingle_hashes(texts)
    finally:
        neardup.CHUNK = small
    assert (again[0] == of).all() and (again[1] == h).all()


def test_counts_survive_packing():
    import numpy as np

    h = np.sort(np.random.default_rng(0).integers(0, 1 << 48, 1000, np.uint64))
    for part in (h, h[:1], np.arange(5, dtype=np.uint64)):
        n = np.arange(1, len(part) + 1)
        got = neardup.unpack_counts(neardup.pack_counts(part, n))
        assert (got[0] == part).all() and (got[1] == n).all()
    classes = neardup.count_class(np.array([1, 2, 127, 128, 10**6, 10**14]))
    assert (np.diff(classes.astype(int)) >= 0).all() and classes[0] == 1


def test_stage_keeps_one_of_each_group(spark):
    """Groups of all pairs by brute force, chains and a large group of near copies among them."""
    r = random.Random(7)
    words = [f"w{k}" for k in range(2000)]
    rows = []
    for k in range(60):
        text = r.choices(words, k=r.randint(1, 250))
        for copy in range(r.choice((1, 1, 2, 4, 30))):
            rows.append((1000 * copy + k, " ".join(text)))
            text = [*text]
            text[r.randrange(len(text))] = "edited"
    rows += [(9000, None), (9001, ""), (9002, " \n ")]
    sets = [neardup.shingles((t or "").encode()) for _, t in rows]
    root = list(range(len(rows)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, j in itertools.combinations(range(len(rows)), 2):
        if neardup.similarity(sets[i], sets[j]) >= 0.8:
            root[top(j)] = top(i)
    groups = {}
    for i, (key, _) in enumerate(rows):
        groups.setdefault(top(i), []).append(key)
    kept = STAGE(spark, spark.createDataFrame(rows, "doc_id long, text string").repartition(4), "").collect()
    assert sorted(r.doc_id for r in kept) == sorted(map(min, groups.values()))


@pytest.mark.parametrize("stage", [STAGE, lambda spark, docs, _: simhash.keep_one(docs)])
def test_rows_without_an_id_or_of_one_id_are_not_lost(spark, stage):
    texts = [" ".join(f"{w}{k}" for w in "the quick brown fox jumps over a lazy dog".split()) for k in range(4)]
    rows = [(None, texts[0]), (None, texts[1]), (None, texts[1]), (5, texts[2]), (5, texts[3]), (6, texts[3]), (None, texts[2])]
    kept = stage(spark, spark.createDataFrame(rows, "doc_id long, text string").repartition(3), "").collect()
    assert sorted(((r.doc_id, r.text) for r in kept), key=str) == sorted([(None, texts[0]), (None, texts[1]), (5, texts[2]), (5, texts[3])], key=str)


def test_fingerprints_link_without_the_join(spark, monkeypatch):
    """SimHash pairs are grouped where the join's prefixes give nothing; those that the words refute are not."""
    body = [f"w{k}" for k in range(400)]
    edited = [*body[:200], "edited", *body[201:]]
    texts = [" ".join(body), " ".join(edited), "x y z " * 300 + " ".join(f"a{k}" for k in range(60)), "x y z " * 300 + " ".join(f"b{k}" for k in range(60)), "another text"]
    texts += [" ".join(body).upper(), "x y z " * 3 + " ".join(f"a{k}" for k in range(60))]
    prints = [simhash.fingerprint(t.encode()) & (2**64 - 1) for t in texts]
    near = {(i, j) for i, j in itertools.combinations(range(7), 2) if (prints[i] ^ prints[j]).bit_count() <= 2}
    assert {(0, 5), (2, 3)} <= near and (2, 6) not in near
    nodes = spark.createDataFrame([(str(k), t) for k, t in enumerate(texts)], "node string, text string")
    got = {(int(r.a), int(r.b)) for r in simhash.print_pairs(nodes).collect()}
    assert got <= near and {j for _, j in got} == {j for _, j in near}
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r.doc_id for r in STAGE(spark, docs, "").collect()} == {0, 2, 3, 4}
    found = neardup.prefixes
    monkeypatch.setattr(neardup, "prefixes", lambda *a: found(*a).where("false"))
    assert {5, 6} & {r.doc_id for r in STAGE(spark, docs, "").collect()} == {6}


def test_small_steps_write_few_files(spark, monkeypatch):
    """Steps of few rows write few files, however many parts their shuffles have and though none are put together."""
    r, files = random.Random(5), {}
    rows = []
    for k in range(40):
        text = r.choices([f"w{i}" for i in range(500)], k=60)
        rows += [(3 * k, " ".join(text)), (3 * k + 1, " ".join([*text, "more"])), (3 * k + 2, " ".join(text[1:]))]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)

    def noted(df, name):
        out = found(df, name)
        files[name] = max(files.get(name, 0), len(out.inputFiles()))
        return out

    found = neardup.materialize
    monkeypatch.setattr(neardup, "materialize", noted)
    monkeypatch.setattr(simhash, "materialize", noted)
    settings = {"spark.sql.shuffle.partitions": "24", "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    before = {k: spark.conf.get(k) for k in settings}
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        assert sorted(r.doc_id for r in STAGE(spark, docs, "").collect()) == list(range(0, 120, 3))
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    small = {"least", "variants", "edges", "able", "tried", "untried", "links", "roots", "mixed", "crossing"}
    assert small <= set(files) and all(files[k] == 1 for k in small), files


def test_hashing_takes_memory_in_proportion_to_the_text(monkeypatch):
    """Batches of texts are hashed in pieces: whole-batch arrays of powers and sums took 32 bytes a byte of text."""
    import tracemalloc

    import numpy as np

    r = random.Random(11)
    words = [f"w{k}" for k in range(30_000)]
    texts = [" ".join(r.choices(words, k=600)).encode() for _ in range(1200)]
    monkeypatch.setattr(neardup, "_powers", [np.ones(1, np.uint64), np.ones(1, np.uint64)])
    tracemalloc.start()
    try:
        neardup.shingle_hashes(texts)
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert peak < 18 * sum(map(len, texts)), peak


def test_texts_that_pairs_name_are_written_by_few_tasks(spark):
    """The scan keeps its tasks, and what it finds is put together: a file, without checksum file or mark beside it."""
    from pathlib import Path

    texts = common.materialize(spark.range(40).selectExpr("cast(id as string) node", "concat('a b c d e ', id % 2) text").repartition(12), "texts")
    pairs = common.materialize(spark.createDataFrame([(str(k), str(k + 1 + k % 4 // 2)) for k in range(0, 38, 2)], "a string, b string"), "pairs")
    made, old = [], neardup.materialize
    try:
        neardup.materialize = lambda df, name: made.append(old(df, name)) or made[-1]
        got = neardup.verified(pairs, texts, 0.8).collect()
    finally:
        neardup.materialize = old
    assert {(r.a, r.b) for r in got} == {(str(k), str(k + 2)) for k in range(2, 38, 4)}
    (file,) = made[0].inputFiles()
    assert [p.name for p in Path(file.removeprefix("file://")).parent.iterdir()] == [Path(file).name]


def test_arrow_batches_of_the_stage_are_bounded(spark):
    """Both sides of a Python step hold a batch; inside the stage one is of some MB, afterwards Spark's bound is back."""
    import pyarrow as pa

    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.nbytes])], names=["n"])

    rows, before = spark.range(0, 6000, 1, 1).selectExpr("id", "repeat('abcd', 1000) text"), spark.conf.get(common.ARROW_CONF)
    with common.small_batches(spark):
        inside = [r.n for r in rows.mapInArrow(sizes, "n long").collect()]
    assert max(inside) < 1.1 * common.ARROW_BYTES and sum(inside) > 6000 * 4000
    seen = []
    simhash.keep_least(rows, lambda t: seen.append(spark.conf.get(common.ARROW_CONF)) or t.selectExpr("node", "node root"), "id").count()
    assert seen == [str(common.ARROW_BYTES)] and spark.conf.get(common.ARROW_CONF) == before
