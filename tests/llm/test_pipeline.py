import hashlib

import duckdb
import pytest

import corpus_pipeline
from packflow.llm.oracles import ORACLES
from packflow.llm.queries import queries
from packflow.llm.simhash import fingerprint

DIR = "/root/testdata/sf0.01"


def test_stages_keep_columns_and_act(spark):
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    start = {r.doc_id: r.text for r in docs.collect()}
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, DIR)
        assert out.columns == docs.columns
        rows = out.collect()
        kept[name] = {r.doc_id: r.text for r in rows}
        docs = spark.createDataFrame(rows, out.schema)
    assert set(kept["pii"]) == set(kept["decontamination"]) < set(kept["simhash_dedup"]) < set(kept["quality"]) < set(start)
    labels = duckdb.sql(f"select doc_id, quality from '{DIR}/labels.parquet'").fetchall()
    good = [k for k, q in labels if q]
    assert sum(k in kept["quality"] for k in good) > 0.98 * len(good)
    assert sum(k in kept["quality"] for k, q in labels if not q) < 0.1 * (len(labels) - len(good))
    items = [t for (t,) in duckdb.sql(f"select text from '{DIR}/benchmark.parquet'").fetchall()]
    leaking = {k for k, t in kept["simhash_dedup"].items() if any(i in t for i in items)}
    assert leaking and not leaking & set(kept["decontamination"])
    prints = [fingerprint(t.encode()) & (2**64 - 1) for t in kept["simhash_dedup"].values()]
    assert all((a ^ b).bit_count() > 2 for i, a in enumerate(prints) for b in prints[:i])
    changed = [k for k, t in kept["pii"].items() if t != kept["decontamination"][k]]
    assert changed and all("[" in kept["pii"][k] for k in changed)
    tokens = corpus_pipeline.STAGES[-1][1](spark, docs, DIR)
    assert tokens.count() == len(kept["pii"])


def test_empty_tables(spark, tmp_path):
    for t in ("documents", "labels", "benchmark", "pages"):
        spark.read.parquet(f"{DIR}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
    for name, q in queries().items():
        assert q(spark, str(tmp_path)).count() == 0, name


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracles(spark, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "benchmark", "labels"):
        con.sql(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    want = con.sql(ORACLES[name])
    df = queries()[name](spark, DIR)
    assert sorted(df.columns) == sorted(want.columns)
    digest = lambda rows: hashlib.sha256(str(sorted(tuple(map(str, r)) for r in rows)).encode()).hexdigest()
    assert digest(df.select(*want.columns).collect()) == digest(want.fetchall())


def test_stages_on_odd_rows(spark):
    """Nulls, empty and long texts, repeated rows, and columns whose names clash with the operators' own."""
    from tests.llm.test_operators import odd_rows

    schema = "doc_id long, text string, score double, batch long"
    docs = spark.createDataFrame(odd_rows(), schema).repartition(3)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, DIR)
        assert out.schema.names == docs.schema.names
        rows = out.collect()
        assert len(rows) <= len(odd_rows())
    assert corpus_pipeline.STAGES[-1][1](spark, docs, DIR).count() == len(odd_rows())


def test_long_runs_of_one_text(spark):
    """A third of all rows is one text; every query still gives a row each."""
    from packflow.llm import simhash, suffix

    rows = [(k, "the same long text that stands in very many documents of this table, again and again") for k in range(400)] + [(1000 + k, f"other {k} text {k * 7919 % 997} here") for k in range(600)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(6)
    groups = {r.component_id for r in simhash.near_duplicates(docs).where("doc_id < 400").collect()}
    assert groups == {0}
    got = suffix.remove_repeats(docs).where("doc_id < 400").collect()
    assert sum(r.n_removed == r.n_bytes for r in got) == 399
