import hashlib

import pytest
from pyspark.sql import functions as F

from packflow.llm import warc
from packflow.llm.common import shared_dir

SCHEMA = "page_id long, url string, html string, extra int"
FAKE = warc.build_record(999, "http://fake", b"inside", "0" * 64, None, False).decode()


def rows():
    long = "x" * 150
    made = [(i, f"http://h/{i}", f"<p>page {i}</p>" + "é" * (i % 97) + (FAKE if i % 5 == 0 else ""), 0) for i in range(10, 120)]
    return [*made, (3, "u", long, 0), (1, "u v\r\n", long, 0), (2, None, long, 0), (4, "u", "short", 0), (5, "u", "short", 0), (6, "u", None, 0), (7, "u", "", 0), (None, "u", long, 0), (8, "u", "WARC/1.1\r\n" * 40, 0), (9, "big", "y" * 50_000, 0), (121, "u", "z" * 200, 1), (121, "u", "z" * 200, 1)]


@pytest.mark.parametrize("gzip", [False, True])
@pytest.mark.parametrize("block", [1000, 8 << 20])
def test_round_trip(spark, gzip, block):
    pages = spark.createDataFrame(rows(), SCHEMA).repartition(3)
    got = sorted((tuple(r) for r in warc.page_records(pages, gzip, block).collect()), key=str)
    first = {}
    for k, _, h, _ in rows():
        if k is not None:
            first[h or ""] = min(first.get(h or "", k), k)
    want = []
    for k, _, h, _ in rows():
        h = (h or "").encode()
        revisit = len(h) >= 100 and k != first[h.decode()]
        want.append((k, len(h), hashlib.sha256(h).hexdigest(), "revisit" if revisit else "response", first[h.decode()] if revisit else None))
    assert got == sorted(want, key=str)


def test_magic_inside_payloads_is_a_candidate_but_not_reached(spark):
    pages = spark.createDataFrame([(i, "u", FAKE * 3, 0) for i in range(4)], SCHEMA).where("page_id < 1").coalesce(1)
    files = warc.write_archives(pages, shared_dir(spark, "t"), gzip=False)
    path, size = files.first()
    assert len(list(warc.candidates(warc.Reader(path, 0, 100), 0, size, False))) == 4
    assert warc.read_archives(files, False).count() == 1


def test_broken_chain_is_an_error(spark):
    folder = shared_dir(spark, "t")
    good = warc.build_record(1, "u", b"abc", "0" * 64, None, False)
    warc.write_atomically(f"{folder}/a.warc", [good, b"rubbish"])
    files = spark.createDataFrame([(f"{folder}/a.warc", len(good) + 7)], "path string, bytes long")
    with pytest.raises(Exception, match="breaks"):
        warc.read_archives(files, False).collect()


def test_empty_table(spark):
    assert warc.page_records(spark.createDataFrame([], SCHEMA)).select(F.count("*")).first()[0] == 0


def test_hot_payloads_are_spread_and_refer_to_the_first(spark, monkeypatch):
    """Pages of one payload by the thousand, and of a few others, give the same records either way."""
    made = [(k, "u", ("error page " * 20) if k % 3 else f"page {k % 50} " * 20, 0) for k in range(1, 3001)]
    pages = spark.createDataFrame(made, SCHEMA).repartition(4)
    got = {r.page_id: (r.record_type, r.refers_to) for r in warc.page_records(pages).collect()}
    first = {}
    for k, _, h, _ in made:
        first.setdefault(h, k)
    assert got == {k: ("response", None) if first[h] == k else ("revisit", first[h]) for k, _, h, _ in made}


def test_small_files_go_through_candidates(spark, monkeypatch):
    """One block or many: entries come from verified candidates."""
    pages = spark.createDataFrame(rows(), SCHEMA).coalesce(1)
    files = warc.write_archives(pages, shared_dir(spark, "t"))
    seen = []
    original = warc.materialize
    monkeypatch.setattr(warc, "materialize", lambda df, name: seen.append(name) or original(df, name))
    assert warc.read_archives(files).count() == len(rows())
    assert seen == ["warc-edges", "warc-jump", "warc-reached"]
