import pytest
from pyspark.sql import functions as F

from blockrecover.operators import ledger as L
from blockrecover.operators import pool, score, search, view
from blockrecover.operators.contiguous import fixpoint, resolve_claims


def image(spark, payloads):
    return spark.createDataFrame(list(enumerate(payloads)), "pos long, payload string")


def test_example_with_two_fillers(spark):
    """Fourteen blocks with one filler twice: exemplar, counts and ranks after covering."""
    blocks = [f"u{i}" for i in range(14)]
    blocks[8] = blocks[12] = "filler"
    ledger = L.build(image(spark, blocks), size=4)
    got = {r.pos: r for r in ledger.collect()}
    assert got[8].exemplar and got[8].dup and got[8].refcount == 2
    assert got[12].dup and not got[12].exemplar and got[12].exemplar_pos == 8
    after = L.merge(ledger, spark.createDataFrame([(3, True), (4, True)], "pos long, covered boolean"))
    ranks = {r.pos: r.live for r in view.live(after, chunk=4).collect()}
    assert ranks == {0: 0, 1: 1, 2: 2, 5: 3, 6: 4, 7: 5, 8: 6, 9: 7, 10: 8, 11: 9, 12: 10, 13: 11}
    assert 12 not in {r.pos for r in view.live(after, phase="F", chunk=4).collect()}


def test_flag_states(spark):
    rows = [(c, d, e) for c in (False, True) for d in (False, True) for e in (False, True)]
    for c, d, e in rows:
        df = spark.createDataFrame([(c, d, e)], "covered boolean, dup boolean, exemplar boolean").select(L.state().alias("s"))
        if e and not d:
            with pytest.raises(Exception, match="exemplar without duplicates"):
                df.collect()
        else:
            assert df.first().s == ("covered " if c else "free ") + ("exemplar" if e else "duplicate" if d else "unique")


def test_edit_merge_and_empty_image(spark):
    ledger = L.build(image(spark, ["a", "b", "a", "0000"]), size=4)
    edited = L.edit(ledger, spark.createDataFrame([(0, 1, True), (1, 1, False)], "lo long, hi long, cover boolean"))
    assert {r.pos for r in edited.where("covered").collect()} == {0, 1}
    assert {r.pos: r.refcount for r in edited.collect()}[2] == 1
    assert L.merge(edited, edited.where("covered").select("pos", "covered")).exceptAll(edited).count() == 0
    none = L.build(spark.createDataFrame([], "pos long, payload string"), size=4)
    assert none.count() == 0 and view.live(none).count() == 0
    assert [r.zero for r in ledger.orderBy("pos").collect()] == [False, False, False, True]


def test_straddling_and_literals(spark):
    blocks = image(spark, ["~H1:aa~E", "1:bb~E1:", "xx~H1:yy"])
    got = {(r.kind, r.pos, r.off) for r in search.literals(blocks, [search.FRAMED]).collect()}
    assert got == {("header", 0, 0), ("footer", 1, 4)}
    assert {(r.pos, r.off) for r in search.straddling(blocks, "~E1:", chunk=2).collect()} == {(0, 6)}


def test_claims_are_all_or_nothing(spark):
    claims = spark.createDataFrame([(1, [1, 2]), (2, [2, 3]), (5, [3, 4]), (9, [9])], "header_pos long, positions array<long>")
    assert {r.header_pos for r in resolve_claims(claims).collect()} == {1, 9}


def test_priorities_are_conserved(spark):
    rows = spark.createDataFrame([(i, "t", 0, i) for i in range(6)], "cand_id long, type string, priority long, created long")
    served = spark.createDataFrame([(0, 5), (0, 7), (3, 1)], "cand_id long, service long")
    after = pool.requeue(rows, served)
    assert after.agg(F.sum("priority")).first()[0] == -13
    assert [r.cand_id for r in pool.dispatch(after, 3).collect()] == [1, 2, 4]


def test_outcome_classes(spark):
    truth = spark.createDataFrame([(1, "t", "whole", ["a", "b", "c"], "S", 2)], "file_id long, type string, layout string, blocks array<string>, sha256 string, first_break int")
    cases = {"complete": (["a", "b", "c"], "S"), "partial longer": (["a", "b", "c", "x"], "x"), "partial prefix": (["a"], "x"), "partial terminal": (["a", "b", "x"], "x"), "incorrect": (["a", "x", "c"], "x"), "incorrect first": (["x"], "x"), "partial bytes": (["a", "b", "c"], "x")}
    for name, (blocks, sha) in cases.items():
        out = spark.createDataFrame([(1, 1, blocks, sha)], "file_id long, out_id int, blocks array<string>, sha256 string")
        assert score.classify(out, truth).first()["class"] == name.split()[0], name
    none = spark.createDataFrame([], "file_id long, out_id int, blocks array<string>, sha256 string")
    assert score.best(score.classify(none, truth), truth).first()["class"] == "not recovered"


def test_fixpoint_without_headers(spark):
    blocks = image(spark, ["x" * 256, "y" * 256])
    written, queued, covered = fixpoint(blocks, search.literals(blocks, [search.FRAMED]))
    assert written.count() == queued.count() == covered.count() == 0
