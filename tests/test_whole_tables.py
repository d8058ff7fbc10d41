"""Queries over whole tables: no row is left out by a filter that is no part of the operator."""

import duckdb
import pytest

from packflow.plans.queries import QUERIES
from packflow.plans.relational_queries import dot_products, locate

DIR = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["token_counts", "encode_column"])
def test_every_document_is_there(spark, name):
    ids = [r.doc_id for r in QUERIES[name](spark, DIR).select("doc_id").collect()]
    assert sorted(ids) == [k for (k,) in duckdb.sql(f"select doc_id from '{DIR}/documents.parquet' order by 1").fetchall()]


def test_blocks_of_queries_give_all_products(spark):
    e = spark.createDataFrame([(k, [float(k), 1.0]) for k in range(30)], "vec_id long, embedding array<float>")
    got = {(r.query_id, r.vec_id): r.dot for r in dot_products(e, e.where("vec_id % 3 = 0"), block=4).collect()}
    assert got == {(q, v): q * v + 1.0 for q in range(0, 30, 3) for v in range(30)}


def test_every_row_number_finds_its_partition(spark):
    sizes = [("a", 3), ("b", 0), ("c", 1), ("d", 25), ("e", 7)]
    got = [tuple(r) for r in locate(spark, spark.createDataFrame(sizes, "part_key string, n_texts long"), bucket=4).orderBy("row_id").collect()]
    assert got == [(at, key, inside) for at, (key, inside) in enumerate((k, i) for k, n in sizes for i in range(n))]


def test_small_partitions_of_all_corpora_are_listed(spark):
    rows = QUERIES["ipc_dominated_partitions"](spark, DIR).collect()
    assert len({r.corpus for r in rows}) == 12 and min(r.n_texts for r in rows) == 1


def test_lognormal_texts_are_those_of_the_order_lines(spark):
    rows = QUERIES["lognormal_source"](spark, DIR).collect()
    assert len(rows) == 100 and sum(r.n_texts for r in rows) == duckdb.sql(f"select count(*) from '{DIR}/lineitem.parquet'").fetchall()[0][0]


def test_data_source_gives_its_sizes(spark):
    from packflow.sources import datasource
    from packflow.sources.corpora import lognormal_sizes

    datasource.register(spark)
    texts = spark.read.format("lognormal_texts").options(parts=100, texts=20_000, sigma=1.72).load()
    got = [r["count"] for r in texts.groupBy("part_key").count().orderBy("part_key").collect()]
    assert got == lognormal_sizes(100, 20_000, 1.72)
