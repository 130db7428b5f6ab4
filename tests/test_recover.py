import hashlib
import os
import zlib
from urllib.parse import urlparse

from pyspark.sql import functions as F

from blockrecover import layout
from blockrecover.formats import framed
from blockrecover.operators import contiguous, solve
from blockrecover.operators.recover import Options, recover, recovered_texts
from blockrecover.session import partitions_for, settings, snapshot

DOCS = "doc_id long, text string"


def image_of(spark, texts, orders, piece=8):
    """The files of ``texts`` in pieces of ``piece`` blocks; orders: (file, piece) as they lie, a filler behind each."""
    files = layout.framed_files(spark.createDataFrame(list(texts.items()), DOCS))
    blocks = {}
    for r in layout.split(files).collect():
        blocks.setdefault(r.file_id, {})[r.logical_block] = r.payload
    out = []
    for f, k in orders:
        own = [blocks[f][i] for i in sorted(blocks[f])]
        out += own[k * piece : (k + 1) * piece] + [hashlib.sha256(f"{f}:{k}".encode()).hexdigest() * (layout.BLOCK // 64)]
    return spark.createDataFrame(list(enumerate(out)), "pos long, payload string")


def test_a_file_of_six_scattered_pieces_is_recovered(spark):
    text = " ".join(hashlib.md5(str(i).encode()).hexdigest() for i in range(260))
    image = image_of(spark, {7: text}, [(7, k) for k in (0, 3, 1, 5, 2, 4)])
    out = recover(image)
    assert [r.text_sha256 for r in recovered_texts(out.written).collect()] == [hashlib.sha256(text.encode()).hexdigest()]


def test_layouts_are_carried_into_later_epochs(spark):
    texts = {k: " ".join(hashlib.md5(f"{k}:{i}".encode()).hexdigest() for i in range(n)) for k, n in ((1, 260), (2, 70))}
    # one piece a round: the small file is won early, the large one needs what it has gained before
    image = image_of(spark, texts, [(1, 0), (2, 0), (1, 3), (1, 1), (1, 5), (2, 1), (1, 2), (1, 4)])
    out = recover(image, Options(rounds=1))
    assert out.written.select("header_pos").distinct().count() == out.written.count() == 2
    assert {r.text_sha256 for r in recovered_texts(out.written).collect()} == {hashlib.sha256(t.encode()).hexdigest() for t in texts.values()}


def test_filler_and_a_displaced_block_in_one_frame(spark):
    text = " ".join(hashlib.md5(str(i).encode()).hexdigest() for i in range(90))
    blocks = {r.logical_block: r.payload for r in layout.split(layout.framed_files(spark.createDataFrame([(5, text)], DOCS))).collect()}
    fill = [hashlib.sha256(f"fill{k}".encode()).hexdigest() * (layout.BLOCK // 64) for k in range(3)]
    # the second frame lies in blocks 3 to 7: filler before block 5, block 6 stored behind the file
    own = [blocks[i] for i in sorted(blocks)]
    image = spark.createDataFrame(list(enumerate(own[:5] + fill[:2] + own[5:6] + own[7:] + fill[2:] + own[6:7])), "pos long, payload string")
    out = recover(image)
    assert [r.text_sha256 for r in recovered_texts(out.written).collect()] == [hashlib.sha256(text.encode()).hexdigest()]


def test_filler_that_ends_a_checksum_by_chance(spark):
    """The last digit of a frame's checksum begins a block; the filler before that block begins with the same digit."""
    text = " ".join(hashlib.md5(str(i).encode()).hexdigest() for i in range(150))
    blocks = [r.payload for r in sorted(layout.split(layout.framed_files(spark.createDataFrame([(5, text)], DOCS))).collect(), key=lambda r: r.logical_block)]
    assert blocks[18][1:3] == "~D"
    fill = next(x for x in (hashlib.sha256(str(k).encode()).hexdigest() * (layout.BLOCK // 64) for k in range(10_000)) if x[0] == blocks[18][0])
    image = spark.createDataFrame(list(enumerate(blocks[:18] + [fill] + blocks[18:])), "pos long, payload string")
    out = recover(image)
    assert [r.text_sha256 for r in recovered_texts(out.written).collect()] == [hashlib.sha256(text.encode()).hexdigest()]
    assert sorted(out.written.first().positions) == [*range(18), *range(19, len(blocks) + 1)]


def test_a_content_is_made_once_and_not_for_each_of_its_pieces(spark):
    """frg_*: the optimizer put the whole encoding of a file into each of its blocks."""
    docs = spark.createDataFrame([(1, "a"), (2, "b")], DOCS)
    plan = layout.split(layout.framed_files(docs))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("crc32(") == 1


def test_frames_that_check_over_text_that_is_no_base64(spark):
    body = "*" * 31
    text = f"~H1:0000000001:{len(body):08d}~~D{len(body):06d}:{body}{zlib.crc32(body.encode()):08x}~E1:{'0' * 32}~"
    v = spark.createDataFrame([(text,)], "content string").select(framed.verdict(F.col("content")).alias("v")).first().v
    assert (v.promising, v.good, v.validates, v.validates_to) == (True, 1, False, len(text) - framed.FOOTER - 1)


def test_only_proposals_that_close_the_open_frame_are_gathered_whole(spark):
    text = " ".join(hashlib.md5(str(i).encode()).hexdigest() for i in range(90))
    own = [r.payload for r in sorted(layout.split(layout.framed_files(spark.createDataFrame([(5, text)], DOCS))).collect(), key=lambda r: r.logical_block)]
    fill = [hashlib.sha256(f"fill{k}".encode()).hexdigest() * (layout.BLOCK // 64) for k in range(3)]
    blocks = spark.createDataFrame([(i, i, p) for i, p in enumerate(own[:6] + fill + own[6:])], "pos long, live long, payload string")
    rows = spark.createDataFrame([(0, "".join((own[:6] + fill + own[6:])[: len(own)]), list(range(len(own))))], "header_pos long, content string, positions array<long>").withColumn("v", framed.verdict(F.col("content")))
    tries = spark.createDataFrame([(0, j, start) for j in (3, 4, 5, 6, 7) for start in range(1, len(own) + 3)], "header_pos long, j int, start long")
    assert [tuple(r) for r in solve.plausible(rows, tries, blocks).collect()] == [(0, 6, 9)]
    assert [r.v.validates for r in solve.extend(rows, tries, blocks).collect()] == [True]


def test_ranks_are_taken_from_positions_only_where_these_have_no_holes(spark):
    at = lambda *xs: contiguous.start_of(spark.createDataFrame([(x,) for x in xs], "pos long"))
    assert (at(3, 4, 5), at(3, 5), at(3, 3, 5), at()) == (3, None, None, None)


def test_ranges_are_put_together_where_their_bins_lie(spark):
    """frg_omit: the blocks of an image were dealt out once to meet their files and once more to be put together."""
    blocks = spark.range(40).selectExpr("id + 100 as pos", "id as live", "concat('<', id, '>') as payload")
    wanted = spark.createDataFrame([(1, 0, 3), (2, 3, 8), (3, 8, 21), (4, 30, 30), (5, 22, 24), (6, 38, 44)], "header_pos long, lo long, hi long")
    rows = lambda df: sorted(map(tuple, df.select("header_pos", "content", "positions").collect()))
    got = rows(contiguous.gather_once(blocks, wanted, ["header_pos"], width=8))
    assert got == rows(contiguous.gather(blocks, wanted, ["header_pos"])) and [r[0] for r in got] == [1, 2, 3, 5, 6]


def joined_schemas(df):
    """The schemas of the inputs of all joins of a plan."""
    todo, out = [df._jdf.queryExecution().optimizedPlan()], []
    while todo:
        node = todo.pop()
        kids = [node.children().apply(i) for i in range(node.children().size())]
        if node.nodeName() == "Join":
            out += [k.schema() for k in kids]
        todo += kids
    return out


def test_blocks_that_start_no_file_do_not_meet_the_headers(spark):
    image = spark.createDataFrame([(0, f"~H1:0000000001:{0:08d}~"), (1, "x"), (2, "~H1:damaged")], "pos long, payload string")
    boundary = spark.createDataFrame([("header", 0), ("header", 2)], "kind string, pos long")
    found = contiguous.spans(image, boundary, image.selectExpr("pos", "pos as live"))
    assert [tuple(r) for r in found.collect()] == [(0, 0, 1)]
    # what meets the headers is a length, not a payload
    assert len(joined_schemas(found)) >= 4 and all(set(s.fieldNames()) <= {"pos", "n", "live"} for s in joined_schemas(found))


def test_searches_carry_a_window_and_cuts_are_made_whole_on_demand(spark):
    text = " ".join(hashlib.md5(str(i).encode()).hexdigest() for i in range(200))
    own = [r.payload for r in sorted(layout.split(layout.framed_files(spark.createDataFrame([(5, text)], DOCS))).collect(), key=lambda r: r.logical_block)]
    fill = [hashlib.sha256(f"fill{k}".encode()).hexdigest() * (layout.BLOCK // 64) for k in range(2)]
    # frame 4 lies in blocks 14 to 17: two blocks of filler before block 16
    blocks = own[:16] + fill + own[16:]
    rows = spark.createDataFrame([(3, "".join(blocks[: len(own)]), list(range(len(own))))], "header_pos long, content string, positions array<long>").withColumn("v", framed.verdict(F.col("content")))
    cuts = solve.without_filler(rows)
    assert "content" not in cuts.columns and max(len(r.win) for r in cuts.collect()) <= (solve.WINDOW + solve.MOST_GAP) * layout.BLOCK
    whole = {r.header_pos: r for r in solve.cut_contents(rows, cuts).collect()}
    assert len(whole) == cuts.count() and any(r.content == "".join(own[:-2]) and r.positions == [*range(16), *range(18, len(own))] for r in whole.values())
    assert all(k // 64 == 3 for k in whole)


def test_little_data_has_few_partitions(spark):
    key = "spark.sql.shuffle.partitions"
    before = spark.conf.get(key)
    try:
        spark.conf.set(key, "200")
        with partitions_for(spark, 1 << 20) as n:
            assert n == int(spark.conf.get(key)) == spark.sparkContext.defaultParallelism
        with partitions_for(spark, 1 << 40) as n:
            assert n == 200
        assert spark.conf.get(key) == "200"
    finally:
        spark.conf.set(key, before)


def test_columns_of_a_search_are_made_once(spark, monkeypatch):
    """frg_both: each round made the some thousand parts of the same columns anew, each part by calls to the JVM."""
    rows = spark.createDataFrame([(0, "x", [0])], "header_pos long, content string, positions array<long>").withColumn("v", framed.verdict(F.col("content")))
    blocks = spark.createDataFrame([(0, 0, "x")], "pos long, live long, payload string")
    tries = spark.createDataFrame([(0, 1, 0)], "header_pos long, j int, start long")
    calls, client = [], type(spark.sparkContext._gateway._gateway_client)
    send = client.send_command
    monkeypatch.setattr(client, "send_command", lambda self, *a, **b: calls.append(1) or send(self, *a, **b))

    def planned():
        calls.clear()
        solve.extend(rows, tries, blocks)
        return len(calls)

    planned()
    again = planned()
    framed.verdict(F.col("content"))  # one of its columns alone
    assert again < 2 * (len(calls) - again)


def test_settings_hold_inside_only(spark):
    key = "spark.sql.maxPlanStringLength"
    before = spark.conf.get(key)
    with settings(spark, maxPlanStringLength="100"):
        assert spark.conf.get(key) == "100"
    assert spark.conf.get(key) == before


def test_a_content_that_is_no_file_has_no_text(spark):
    """frg_*: a caller's filter on the texts met contents that did not validate, whose bytes are no UTF-8, and failed."""
    docs = spark.createDataFrame([(1, "ä" * 40), (2, "")], DOCS)
    good = layout.framed_files(docs).select("content")
    body = "//79" * 5
    bad = f"~H1:0000000003:{len(body):08d}~~D{len(body):06d}:{body}{zlib.crc32(body.encode()):08x}~E1:{'0' * 32}~"
    rows = good.unionByName(spark.createDataFrame([(bad,), (bad.replace("//79", "*-,;"),)], "content string"))
    got = recovered_texts(rows).collect()
    assert sorted((r.doc_id, r.text_sha256) for r in got if r.doc_id < 3) == [(i, hashlib.sha256(t.encode()).hexdigest()) for i, t in ((1, "ä" * 40), (2, ""))]
    assert [r.text_sha256 for r in got if r.doc_id == 3] == [None, None]


def test_the_whole_image_goes_when_what_is_left_of_it_is_kept(spark, monkeypatch):
    """frg_both: a copy of the whole image stayed on disk through all epochs."""
    made = []
    monkeypatch.setattr("blockrecover.operators.recover.snapshot", lambda df, name, **kw: made.append((name, snapshot(df, name, **kw))) or made[-1][1])
    text = " ".join(hashlib.md5(str(i).encode()).hexdigest() for i in range(90))
    out = recover(image_of(spark, {7: text}, [(7, 0), (7, 1), (7, 2)]))
    assert [r.text_sha256 for r in recovered_texts(out.written).collect()] == [hashlib.sha256(text.encode()).hexdigest()]
    stays = {name: os.path.exists(urlparse(t.inputFiles()[0]).path) for name, t in made if name in ("image", "live")}
    assert stays == {"image": False, "live": True}
