"""Odd input of the wider operators: nulls, empty tables, repeats and limits."""

import zlib

import pytest
from pyspark.sql import functions as F

from blockrecover import sources
from blockrecover.operators import classify, hybrid, ledger, score, solve, validate


def test_block_scores(spark):
    rows = spark.createDataFrame([(None,), ("",), ("0000",), ("~H1:x",), ("a b",), ("abcd",)], "payload string")
    assert [r[0] for r in rows.select(validate.framed_score(F.col("payload"))).collect()] == [0, 0, 1, 100, 0, 8]


def test_block_state_is_held_once_per_content(spark):
    image = spark.createDataFrame([(0, "00"), (1, "ab"), (2, "00"), (3, "ab"), (4, "cd")], "pos long, payload string")
    states = validate.block_state(image, F.crc32("payload"), zero="00")
    assert states.count() == 3
    got = dict(map(tuple, validate.with_state(image, states, zero="00").select("pos", "state").collect()))
    assert got == {p: zlib.crc32(x) for p, x in enumerate([b"00", b"ab", b"00", b"ab", b"cd"])}
    none = image.limit(0)
    assert validate.with_state(none, validate.block_state(none, F.crc32("payload"), zero="00"), zero="00").count() == 0


def test_segments_round_trip_and_ignore_other_files(spark, tmp_path):
    blocks = [(i, bytes([i % 256]) * (4 if i < 20 else 2)) for i in range(21)]
    image = spark.createDataFrame(blocks, "pos long, payload binary")
    folder = str(tmp_path / "raw")
    assert {tuple(r) for r in sources.write_segments(image, folder, per_segment=8).collect()} == {(0, 8), (1, 8), (2, 5)}
    (tmp_path / "raw" / "notes.txt").write_text("x")
    spark.dataSource.register(sources.ImageSource)
    got = spark.read.format("block_image").option("block", "4").option("per_segment", "8").option("piece", "3").load(folder)
    assert sorted((r["pos"], bytes(r["payload"])) for r in got.collect()) == blocks
    assert sources.read_image(spark, str(tmp_path / "nothing")).count() == 0


def test_pairs_by_brute_force(spark):
    import random

    r = random.Random(5)
    texts = ["".join(r.choice("abcdef0123") for _ in range(256)) for _ in range(12)]
    blocks = spark.createDataFrame(list(enumerate(texts)), "live long, payload string")
    whole = texts[0] + texts[3] + texts[4] + texts[7] + "tail"
    need = [(1, 0, zlib.crc32(whole.encode()), zlib.crc32(texts[0].encode()), texts[4], "tail"), (2, 0, 5, None, None, "")]
    needs = spark.createDataFrame(need, "cand_id long, at long, target long, before_crc long, between string, after string")
    want = {(1, a, b) for a in range(1, 12) for b in range(1, 12) if a != b and zlib.crc32((texts[0] + texts[a] + texts[4] + texts[b] + "tail").encode()) == zlib.crc32(whole.encode())}
    assert {tuple(x) for x in solve.solve_pairs(needs, blocks).collect()} == want == {(1, 3, 7)}
    with pytest.raises(ValueError):
        solve.solve_pairs(needs, blocks, most_work=10)


def test_classifier_orders_but_never_excludes(spark):
    assert not classify.statistics(None).any() and not classify.statistics(b"").any()
    rows = [("text", b"plain words here " * 8)] * 20 + [("dense", bytes(range(256)))] * 20
    labelled = spark.createDataFrame(rows, "type string, payload binary")
    model = classify.train(labelled, ["dense", "text"])
    asked = labelled.unionByName(spark.createDataFrame([(None, None)], "type string, payload binary"))
    got = classify.score(asked, model, ["dense", "text"]).collect()
    assert all(min(x["confidence"].values()) >= 1 for x in got)
    assert all(x["guess"] == x["type"] for x in got if x["type"])
    off = classify.score(labelled, None, ["dense", "text"]).collect()
    assert len(off) == 40 and all(x["confidence"] == {"dense": 100, "text": 100} for x in off)


def test_log_lines_become_coverage(spark):
    files = spark.createDataFrame([(3, 5), (9, 9)], "a long, b long")
    lines = files.select(hybrid.log_of("a", "b").alias("value")).unionByName(spark.createDataFrame([("started",)], "value string"))
    assert {tuple(x) for x in ledger.ingest_log(lines).collect()} == {(3, 5, True), (9, 9, True)}


def test_differences_count_repeats(spark):
    a, b = spark.createDataFrame([(1,), (1,), (2,)], "x int"), spark.createDataFrame([(1,), (3,)], "x int")
    assert tuple(score.differences(a, b).first()) == (2, 1, 3)
    assert tuple(score.differences(a.limit(0), b.limit(0)).first()) == (0, 0, 0)


def test_fallback_proposes_for_files_that_lack_their_footer_only(spark):
    from blockrecover.formats import framed
    from blockrecover.layout import framed_files

    docs = spark.createDataFrame([(1, "x" * 700), (2, "y" * 1500)], "doc_id long, text string")
    whole = framed_files(docs).select(F.col("file_id").alias("header_pos"), F.expr("left(content, length(content) - 20)").alias("content"))
    rows = whole.withColumn("v", framed.verdict(F.col("content"))).withColumn("positions", F.expr("transform(sequence(1L, length(content) div 256), i -> 100 * header_pos + i)"))
    view = rows.select(F.explode("positions").alias("pos")).withColumn("live", F.col("pos"))
    got = solve.neighbours_of(rows, view, window=2).groupBy("header_pos").agg(F.max("j").alias("j")).join(rows, "header_pos").select("j", F.size("positions").alias("n")).collect()
    assert len(got) == 2 and all(x["j"] == x["n"] for x in got)


def test_floats_are_scaled_as_floats(spark, tmp_path):
    """A float that rounds up to a whole number when scaled; nulls are left out, and a vector without numbers has no sum."""
    from blockrecover.queries import QUERIES

    rows = [(1, [0.029, -0.001]), (2, [0.5, None]), (3, []), (4, None), (5, [0.057, 0.289])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    from .twins import rows as cells

    got = QUERIES["op_arr"](spark, str(tmp_path))
    import duckdb

    from blockrecover.queries import ORACLE_SQL

    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{tmp_path}/embeddings.parquet/*.parquet')")
    out = con.execute(ORACLE_SQL["op_arr"])
    assert cells(got.columns, [tuple(r) for r in got.collect()]) == cells([d[0] for d in out.description], out.fetchall())


def test_shared_work_covers_no_block_of_the_next_file(spark, tmp_path):
    """A file whose footer begins in one block and ends in the next, and a fragmented one behind it: the copy up to the next
    footer validates, and its log must not cover blocks of the fragmented file."""
    from blockrecover.layout import SCENARIOS, framed_files, lengths, placed_files
    from blockrecover.queries import QUERIES

    docs = spark.range(60).selectExpr("id as doc_id", "substring(repeat(sha2(cast(id as string), 256), 40), 1, cast(1192 + id * 7 as int)) as text")
    plan = placed_files(lengths(docs), SCENARIOS["gap"]).orderBy("key").collect()
    # the footer's first four bytes lie over a border of blocks
    split_ = [253 <= (r.file_len - 37) % 256 for r in plan]
    assert any(a and not p.has_gap and b.has_gap for a, p, b in zip(split_, plan, plan[1:]))
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r.text_sha256 for r in QUERIES["hyb_workflow"](spark, str(tmp_path)).collect()}
    assert got == {r.doc_id: r.s for r in docs.selectExpr("doc_id", "sha2(text, 256) as s").collect()}
