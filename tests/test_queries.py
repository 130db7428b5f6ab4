"""Every engine query that has SQL equals it on the smallest tables."""

import pytest

from blockrecover import queries

from .twins import assert_equal

SLOW = {"frg_gap", "frg_ltr", "hyb_workflow", "frg_ooo", "frg_omit", "frg_zero", "fmt_mixed", "fmt_mixed_zero", "fmt_mixed_random"}


@pytest.mark.parametrize("name", sorted(set(queries.ORACLE_SQL) - SLOW))
def test_twin(spark, data, name):
    assert_equal(spark, data, queries.QUERIES[name], queries.ORACLE_SQL[name])


def test_gap_scenario_is_recovered_whole(spark, data):
    assert_equal(spark, data, queries.QUERIES["frg_gap"], queries.ORACLE_SQL["frg_gap"])


def test_displaced_scenario_mostly_recovered(spark, data):
    from pyspark.sql import functions as F

    got = queries.QUERIES["frg_ooo"](spark, data)
    docs = spark.read.parquet(f"{data}/documents.parquet").select("doc_id", F.sha2("text", 256).alias("s"))
    right = got.join(docs, "doc_id").where("s = text_sha256").count()
    assert right >= 0.98 * docs.count()
    assert got.join(docs, "doc_id").where("s <> text_sha256").count() == 0  # what validates is right
