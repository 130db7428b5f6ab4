"""Images: repeated ids, nulls, long numbers, and plans that hold at scale."""

import re

import pytest
from pyspark.sql import functions as F

from blockrecover import layout as L
from blockrecover.operators import recover as R
from blockrecover.plans import next_on_axis


def plan_nodes(df):
    """(depth, text) of each operator of a physical plan."""
    df._jdf.queryExecution().assertAnalyzed()
    text = df._jdf.queryExecution().sparkPlan().toString() + "\n" + df._jdf.queryExecution().executedPlan().toString()
    return [line.strip(" :+-*") for line in text.splitlines()]


@pytest.mark.parametrize("name", sorted(L.SCENARIOS))
def test_repeated_ids_and_nulls_give_whole_files(spark, name):
    rows = [(1, "a" * 3000), (1, "b" * 3000), (2, "short"), (3, None), (3, None), (4, ""), (None, "lost"), (5, "é" * 900)]
    image, truth = L.build_image(spark.createDataFrame(rows, "doc_id long, text string"), L.SCENARIOS[name])
    files = [f for f in L.framed_files(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    assert len(files) == 7
    blocks = sum(-(-f.file_len // L.BLOCK) for f in files)
    assert truth.count() >= blocks - 7 and (name == "omit" or truth.count() == blocks)
    assert image.select("pos").distinct().count() == image.count()
    if name in ("cont", "gap"):
        got = sorted(r.text_sha256 for r in R.recovered_texts(R.recover(image).written).collect())
        import hashlib

        assert got == sorted(hashlib.sha256((t or "").encode()).hexdigest() for i, t in rows if i is not None)


def test_numbers_beyond_their_field_are_errors(spark):
    with pytest.raises(Exception, match="beyond its field"):
        L.framed_files(spark.createDataFrame([(10**11, "x")], "doc_id long, text string")).collect()


def test_lengths_by_arithmetic(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    both = L.framed_files(docs).select("file_id", "file_len").join(L.lengths(docs).select("file_id", F.col("file_len").alias("n")), "file_id")
    assert both.where("file_len <> n").count() == 0 and both.count() == docs.count()


def test_next_on_axis_brute_force(spark):
    import random

    rng = random.Random(1)
    left, right = [rng.randrange(500) for _ in range(200)], [rng.randrange(60, 400) for _ in range(12)]
    a = spark.createDataFrame([(i, x) for i, x in enumerate(left)], "id long, at long")
    b = spark.createDataFrame([(x,) for x in right], "at long")
    for chunk in (1, 7, 64, 1000):
        got = {r.id: r.n for r in next_on_axis(a, b, "at", "n", chunk=chunk).collect()}
        assert got == {i: min((y for y in right if y >= x), default=None) for i, x in enumerate(left)}
    assert next_on_axis(a, b.where("false"), "at", "n").where("n is not null").count() == 0


def test_axis_windows_are_parted(spark):
    """A window over one axis without a key would run in one task: no window of the plan stands on a single partition."""
    a = spark.range(5000).select(F.col("id").alias("at"))
    nodes = plan_nodes(next_on_axis(a, a.where("at % 7 = 0"), "at", "n"))
    windows = [n for n in nodes if re.match(r"(\(\d+\) )?Window", n)]
    assert windows and all("na_chunk" in w for w in windows)
    assert not any("SinglePartition" in n for n in nodes)


def test_queries_over_directives_and_runs_read_given_tables(spark, data):
    from blockrecover.queries import QUERIES

    for name, table in (("lay_parse", "documents"), ("lay_directed", "documents"), ("prog_speedup", "events")):
        assert any(f"/{table}.parquet" in x for x in QUERIES[name](spark, data).inputFiles())
