"""Checksum-constrained reassembly: the next piece of a broken file by equi-joins on checksums.

A broken candidate is consistent up to some frame. For every block boundary inside the open frame at which the break may
lie, the frame's known part fixes a value that the missing part must have; the missing part covers k full blocks and x
bytes of one more. The end-block index holds, for every plausible end of a frame in the image, that value for k = 0..K
preceding live blocks. Joining on (k, x, value) finds the place at once, over the whole image; hits are verified by the
file's own validator, so that chance agreements of 32 bits cannot pass.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..formats import framed
from ..functions.crc import crc_hex, shift, shift_by
from ..layout import BLOCK, BODY, FRAME, HEADER
from ..plans import held, once, range_join
from ..session import snapshot
from .contiguous import gather
from .search import hits

#: Filler blocks that may stand before an anchored tail. A frame with a displaced run whose tail stands behind more of
#: them has no anchored proposal, and is found only if its whole missing part lies in one run.
MOST_GAP = 4
#: Blocks in which a frame that opens in the first of them ends: 255 + 917 bytes at most.
SPAN = 5
#: Blocks of a candidate that a search reads: from the one that holds the end of the last good frame's checksum to the end of
#: the open frame; filler that may stand in it comes on top.
WINDOW = -(-(BLOCK + 8 + FRAME) // BLOCK)
#: Candidates whose searches' keys (some hundred of about 40 bytes for each) may be sent to all tasks.
FEW = 500
RUNS = 4  # full blocks of a frame's missing part: 900 bytes in blocks of 256


def with_neighbours(blocks: DataFrame, *, chunk: int = 32_768) -> DataFrame:
    """blocks (pos, live, payload) with crc, next (first ten bytes of the live successor) and the checksums of the runs
    of 1..RUNS - 1 live predecessors: run1.. Windows run inside live chunks that see a halo of their neighbours."""
    rows = blocks.withColumn("crc", F.crc32("payload")).withColumn("chunk", F.expr(f"live div {chunk}"))
    slim = rows.select("live", "crc", F.substring("payload", 1, 10).alias("head"), "chunk")
    inside = F.col("live") % chunk
    before = slim.where(inside >= chunk - RUNS).withColumn("chunk", F.col("chunk") + 1)
    after = slim.where((inside == 0) & (F.col("chunk") > 0)).withColumn("chunk", F.col("chunk") - 1)
    w = W.partitionBy("chunk").orderBy("live")
    out = slim.withColumn("own", F.lit(True)).unionByName(before.unionByName(after).withColumn("own", F.lit(False)))
    out = out.withColumn("next", F.lead("head").over(w)).withColumn("run1", F.lag("crc", 1).over(w))
    for k in range(2, RUNS):
        out = out.withColumn(f"run{k}", shift_by(F.lag("crc", k).over(w), BLOCK * (k - 1)).bitwiseXOR(F.col(f"run{k - 1}")))
    return rows.select("pos", "live", "payload", "crc").join(out.where("own").select("live", "next", *[f"run{k}" for k in range(1, RUNS)]), "live")


def end_index(blocks: DataFrame, own: DataFrame | None = None) -> DataFrame:
    """live, x, stored, prefix_crc, k, value: for each plausible frame end in a block, and each number k of full blocks
    before it, what the known part of the frame must shift to. ``own``: ``with_neighbours`` of the blocks, if made before."""
    text = F.concat("payload", F.coalesce("next", F.lit("")))
    marks = F.filter(hits(F.col("text"), "~"), lambda o: (o >= 8) & (o < BLOCK + 8))
    rows = (with_neighbours(blocks) if own is None else own).withColumn("text", text).withColumn("m", F.explode(marks))
    rows = rows.withColumn("x", F.col("m") - 8).withColumn("word", F.substring("text", F.col("x") + 1, F.lit(8))).where(F.col("word").rlike("^[0-9a-f]{8}$") & F.substring("text", F.col("m") + 2, F.lit(1)).isin("D", "E"))
    rows = rows.withColumn("stored", F.conv("word", 16, 10).cast("long")).withColumn("prefix_crc", F.crc32(F.substring("payload", F.lit(1), F.col("x"))))
    runs = F.array(*[F.struct(F.lit(k).alias("k"), (F.lit(0).cast("long") if k == 0 else F.col(f"run{k}")).alias("run")) for k in range(RUNS)])
    rows = rows.withColumn("r", F.explode(F.filter(runs, lambda r: r.run.isNotNull())))
    value = F.col("stored").bitwiseXOR(shift(F.col("r.run"), F.col("x"), most=BLOCK)).bitwiseXOR(F.col("prefix_crc"))
    return rows.select("live", "x", "stored", "prefix_crc", "r.k", value.alias("value"))


def run_index(own: DataFrame) -> DataFrame:
    """start, r, value: the checksum of each run of r live blocks; own: ``with_neighbours``."""
    ends = [F.col("crc")] + [shift_by(F.col(f"run{k}"), BLOCK).bitwiseXOR(F.col("crc")) for k in range(1, RUNS - 1)]
    runs = own.select("live", F.explode(F.array(*[F.struct(F.lit(k + 1).alias("r"), e.alias("value")) for k, e in enumerate(ends)])).alias("e")).where("e.value is not null")
    return runs.select((F.col("live") - F.col("e.r") + 1).alias("start"), "e.r", "e.value")


def fronts(candidates: DataFrame, *, filler: int = MOST_GAP) -> DataFrame:
    """What searches need of candidates (header_pos, content, positions, v): header_pos, n (body length), good, fs (where the
    open frame starts), size (its characters, null where all frames check), win (WINDOW + filler blocks of the content from
    block ``base`` on), held_blocks, foot (the footer, where all frames check). A search then costs the window, not the whole file, for
    each place that it tries. Rows that are such already stay as they are."""
    if "win" in candidates.columns:
        return candidates
    n, ends, fs, base, *out = front_columns(filler)
    rows = candidates.withColumns({"n": n, "good": F.col("v.good")}).where("n is not null").withColumn("ends", ends).withColumn("fs", fs).withColumn("base", base)
    return held(rows.select(*out), "win", "foot")


@once
def front_columns(filler: int) -> tuple[Column, ...]:
    """n, ends, fs, base, and then what ``fronts`` returns."""
    n, ends = framed.body_length(F.col("content")), F.col("good") == framed.frames(F.col("n"))
    # where all frames check, the last one is shorter than a full one and the footer stands that much earlier
    short = framed.frames(F.col("n")) * BODY - F.col("n")
    fs, base = HEADER + F.col("good") * FRAME - F.when(F.col("ends"), short).otherwise(0), F.expr(f"(fs - 8) div {BLOCK}")
    win = F.substring("content", (F.col("base") * BLOCK + 1).cast("int"), F.lit((WINDOW + filler) * BLOCK))
    size = F.when(~F.col("ends"), F.least(F.lit(BODY).cast("long"), F.col("n") - F.col("good") * BODY))
    foot = F.when(F.col("ends"), framed.footer_of(F.col("content")))
    return n, ends, fs, base, *[F.col(c) for c in ("header_pos", "n", "good", "fs")], size.alias("size"), F.col("base"), win.alias("win"), F.size("positions").alias("held_blocks"), foot.alias("foot")


def of_window(start: Column, length: Column) -> Column:
    """A piece of the content, named by its place in the whole (from 0)."""
    return F.substring("win", (start - F.col("base") * BLOCK + 1).cast("int"), length.cast("int"))


def boundaries(rows: DataFrame) -> DataFrame:
    """fronts with j: one row per block boundary inside the open frame's body at which the break may lie."""
    first, last = F.expr(f"(fs + 9 + {BLOCK - 1}) div {BLOCK}"), F.expr(f"(fs + 9 + size) div {BLOCK}")
    return rows.where("size > 0").where(last >= first).withColumn("j", F.explode(F.sequence(first, last))).where("j >= 1 and j <= held_blocks")


def open_frames(candidates: DataFrame) -> DataFrame:
    """For candidates (or their ``fronts``): one row per block boundary at which the break may lie: header_pos, j (blocks
    kept), rem (bytes of the frame still missing), k, x, value."""
    known, rem, *out = open_columns()
    return boundaries(fronts(candidates)).select("header_pos", "j", "size", known.alias("known")).withColumn("rem", rem).select("header_pos", "j", "rem", *out)


@once
def open_columns() -> tuple[Column, ...]:
    known, rem = of_window(F.col("fs") + 9, F.col("j") * BLOCK - F.col("fs") - 9), F.col("size") - F.length("known")
    return known, rem, F.expr(f"cast(rem div {BLOCK} as int)").alias("k"), F.expr(f"cast(rem % {BLOCK} as int)").alias("x"), behind_zeros(F.col("known"), F.col("rem")).alias("value")


def sent(rows: DataFrame, few: bool) -> DataFrame:
    return F.broadcast(rows) if few else rows


def behind_zeros(text: Column, n: Column) -> Column:
    """shift(crc32(text), n) of a text that is at hand: the checksum of the text with n zero bytes behind it, less theirs."""
    zeros = F.repeat(F.lit("\0"), n.cast("int"))
    return F.crc32(F.concat(text, zeros)).bitwiseXOR(F.crc32(zeros))


def solve(candidates: DataFrame, index: DataFrame, *, few: bool = False) -> DataFrame:
    """header_pos, j, start (live block at which the missing part begins) of all checksum matches. ``few``, here and below: there
    are at most FEW candidates, whose few numbers are sent to the index, which then stays where it is."""
    need = sent(open_frames(candidates), few)
    found = need.join(index, ["k", "x", "value"])
    return found.select("header_pos", "j", (F.col("live") - F.col("k")).alias("start")).distinct()


def expected_words(candidates: DataFrame) -> DataFrame:
    """For breaks outside a frame's body, the bytes that the next block must start with: header_pos, j, expect. They
    are the rest of a frame header, of a checksum and the mark behind it, or of the footer. A frame that checks may end in a
    wrong block whose first characters are by chance the last digits of its checksum: a boundary inside the checksum of
    the last good frame is a possible break too."""
    count, j, word = word_columns()
    rows = fronts(candidates).withColumn("count", count).withColumn("j", j).where("j >= 1 and j <= held_blocks")
    return rows.select("header_pos", "j", word.alias("expect")).where("length(expect) > 0")


@once
def word_columns() -> tuple[Column, ...]:
    """count, j, and the word that is expected behind boundary j."""
    count = framed.frames(F.col("n"))
    j = F.explode(F.expr(f"sequence((fs - if(good > 0, 7, 0) + {BLOCK - 1}) div {BLOCK}, (fs + coalesce(size, 0) + 37) div {BLOCK})"))
    at = F.col("j") * BLOCK - F.col("fs")
    head = F.concat(F.lit("~D"), F.lpad(F.col("size").cast("string"), 6, "0"), F.lit(":"))
    body = of_window(F.col("fs") + 9, F.col("size"))
    last = F.col("good") + 1 == F.col("count")
    foot = F.col("foot")
    # what follows a checksum is known as well, and keeps its last digits from meeting every block that starts with them
    later = F.concat(F.lit("~D"), F.lpad(F.least(F.lit(BODY).cast("long"), F.col("n") - (F.col("good") + 1) * BODY).cast("string"), 6, "0"), F.lit(":"))
    tail = F.concat(crc_hex(body), F.when(last, foot).otherwise(later))
    rest = lambda text, used: F.substring(text, (used + 1).cast("int"), F.lit(64))
    digits = of_window(F.col("j") * BLOCK, F.col("fs") - F.col("j") * BLOCK)  # of the last good frame
    word = F.when(at < 0, F.concat(digits, F.when(F.col("size").isNull(), foot).otherwise(head)))
    word = word.when(F.col("size").isNull(), F.when(at < 37, rest(foot, at))).when(at < 9, rest(head, at)).when((at > 9 + F.col("size")) & (at < 17 + F.col("size")), rest(tail, at - 9 - F.col("size")))
    return count, j, word


def solve_words(candidates: DataFrame, blocks: DataFrame, *, few: bool = False) -> DataFrame:
    """header_pos, j, start of live blocks that begin as a candidate expects: an equi-join on up to eight characters,
    for which blocks send no more than the characters that are compared."""
    want = expected_words(candidates).withColumn("t", F.least(F.lit(8), F.length("expect"))).withColumn("key", F.substring("expect", F.lit(1), F.col("t")))
    starts = F.transform(F.sequence(F.lit(1), F.lit(8)), lambda t: F.substring(F.col("start_of"), F.lit(1), t))
    # blocks of plain body text start no frame, checksum or footer that can be told from others
    keyed = blocks.select("live", F.substring("payload", 1, 64).alias("start_of")).select("live", "start_of", F.explode(starts).alias("key"))
    return sent(want, few).join(keyed, "key").where(F.col("start_of").startswith(F.col("expect"))).select("header_pos", "j", F.col("live").alias("start")).distinct()


def neighbours_of(candidates: DataFrame, view: DataFrame, *, window: int) -> DataFrame:
    """The fallback's proposals: every live block within ``window`` after each possible break of the open frame."""
    n = framed.body_length(F.col("content"))
    short = framed.frames(n) * BODY - n  # by which the last frame is shorter: the footer stands that much earlier
    at = HEADER + F.col("v.good") * FRAME - F.when(F.col("v.good") == framed.frames(n), short).otherwise(0)
    rows = candidates.withColumn("fs", at).withColumn("j0", F.expr(f"greatest(1, fs div {BLOCK})")).where("j0 <= size(positions)")
    rows = rows.withColumn("j", F.explode(F.expr("sequence(j0, least(j0 + 5, size(positions)))")))
    last = F.element_at("positions", F.col("j").cast("int"))
    at = rows.select("header_pos", "j", last.alias("pos")).join(view, "pos")
    return at.select("header_pos", "j", F.explode(F.expr(f"sequence(live + 2, live + 1 + {window})")).alias("start"))


def solve_anchor(candidates: DataFrame, blocks: DataFrame, *, most_gap: int = MOST_GAP, runs: DataFrame | None = None, few: bool = False) -> DataFrame:
    """header_pos, j, start, r, g: runs of r live blocks that fit between the kept part of the open frame and its tail,
    the tail being what physically follows the kept part, or what follows g filler blocks behind it. Target, prefix
    and tail are known, so the run's checksum is too; every (split point j, run length r, gap g) is a row, and the search one
    equi-join on (r, checksum). ``runs``: the blocks' ``run_index``, if made before."""
    r, g, known, rest, tail, word, fits, value = anchor_columns(most_gap)
    rows = boundaries(fronts(candidates, filler=max(MOST_GAP, most_gap))).withColumn("r", r).withColumn("g", g).withColumn("known", known).withColumn("rest", rest).where("rest >= 0")
    rows = rows.withColumns({"tail": tail, "word": word}).where(fits).select("header_pos", "j", "r", "g", "known", "rest", "tail", "word")
    need = rows.select("header_pos", "j", "r", "g", value.alias("value"))
    found = sent(need, few).join(run_index(with_neighbours(blocks)) if runs is None else runs, ["r", "value"])
    return found.select("header_pos", "j", "start", "r", "g").distinct()


@once
def anchor_columns(most_gap: int) -> tuple[Column, ...]:
    """r, g, known, rest, tail, word, whether tail and word fit, and the checksum that the run must have."""
    r, g = F.explode(F.sequence(F.lit(1), F.lit(RUNS - 1))), F.explode(F.sequence(F.lit(0), F.lit(most_gap)))
    known = of_window(F.col("fs") + 9, F.col("j") * BLOCK - F.col("fs") - 9)
    rest = (F.col("size") - F.length("known") - F.col("r") * BLOCK).cast("int")
    after = (F.col("j") + F.col("g")) * BLOCK
    tail, word = of_window(after, F.col("rest")), of_window(after + F.col("rest"), F.lit(8))
    fits = F.col("word").rlike("^[0-9a-f]{8}$") & (F.length("tail") == F.col("rest"))
    target = F.conv("word", 16, 10).cast("long")
    left = target.bitwiseXOR(behind_zeros(F.col("known"), F.col("r") * BLOCK + F.col("rest"))).bitwiseXOR(F.crc32("tail"))
    return r, g, known, rest, tail, word, fits, shift(left, F.col("rest"), most=1024, inverse=True)


def without_filler(candidates: DataFrame) -> DataFrame:
    """The ``fronts`` of each candidate with 1..MOST_GAP blocks left out at each boundary inside its open frame, so that a second
    break of the frame can be solved as if it were the only one. header_pos is a number of its own; ``header_of``
    leads back, and ``cut_contents`` makes the whole contents of those that are needed."""
    rows = fronts(candidates).where("size > 0")
    rows = rows.withColumn("first", F.expr(f"(fs + 9 + {BLOCK - 1}) div {BLOCK}")).withColumn("last", F.expr(f"(fs + 9 + size) div {BLOCK}")).where("last >= first")
    rows = rows.withColumn("d", F.explode(F.sequence("first", "last"))).withColumn("g", F.explode(F.sequence(F.lit(1), F.lit(MOST_GAP)))).where("d >= 1 and d + g < held_blocks")
    win = F.expr(f"concat(substring(win, 1, cast((d - base) * {BLOCK} as int)), substring(win, cast((d - base + g) * {BLOCK} + 1 as int)))")
    return rows.select((F.col("header_pos") * 64 + (F.col("d") - F.col("first")) * 8 + F.col("g")).alias("header_pos"), "n", "good", "fs", "size", "base", win.alias("win"), (F.col("held_blocks") - F.col("g")).alias("held_blocks"), "foot")


def cut_contents(candidates: DataFrame, names: DataFrame) -> DataFrame:
    """header_pos (as ``without_filler`` names it), content, positions, v of the named cuts."""
    rows = names.select(F.col("header_pos").alias("name"), header_of(F.col("header_pos")).alias("header_pos")).join(candidates, "header_pos")
    rows = rows.withColumn("fs", HEADER + F.col("v.good") * FRAME).withColumn("d", F.expr(f"(fs + 9 + {BLOCK - 1}) div {BLOCK} + name % 64 div 8")).withColumn("g", F.expr("name % 8"))
    content = F.expr(f"concat(substring(content, 1, cast(d * {BLOCK} as int)), substring(content, cast((d + g) * {BLOCK} + 1 as int)))")
    positions = F.expr("concat(slice(positions, 1, cast(d as int)), slice(positions, cast(d + g + 1 as int), size(positions)))")
    return rows.select(F.col("name").alias("header_pos"), content.alias("content"), positions.alias("positions"), "v")


def header_of(name: Column) -> Column:
    return F.floor(name / 64)


def solve_two_breaks(candidates: DataFrame, blocks: DataFrame, index: DataFrame, runs: DataFrame | None = None, *, few: bool = False) -> DataFrame:
    """Candidates (header_pos, content, positions, v) whose open frame has filler at one place and a missing piece at
    another, taken further; of several ways the one that validates furthest, ties to the first boundary and the least filler."""
    cut = without_filler(fronts(candidates) if few else snapshot(fronts(candidates), "fronts"))
    whole = solve(cut, index, few=few).withColumn("r", F.lit(None).cast("int")).withColumn("g", F.lit(0))
    found = snapshot(whole.unionByName(solve_anchor(cut, blocks, most_gap=0, runs=runs, few=few)), "proposals")
    if found.isEmpty():
        return candidates.limit(0)
    tails = plausible(cut.join(found.select("header_pos").distinct(), "header_pos", "left_semi"), found.where("r is null"), blocks)
    found = snapshot(tails.select("header_pos", "j", "start", F.lit(None).cast("int").alias("r"), F.lit(0).alias("g")).unionByName(found.where("r is not null")), "proposals")
    got = extend(cut_contents(candidates, found.select("header_pos").distinct()), found, blocks, checked=True)
    best = got.groupBy(header_of(F.col("header_pos")).alias("h")).agg(F.max_by(F.struct("content", "positions", "v"), F.struct("v.validates", "v.validates_to", -F.col("header_pos"))).alias("b"))
    return best.select(F.col("h").alias("header_pos"), "b.*")


def plausible(candidates: DataFrame, proposals: DataFrame, blocks: DataFrame) -> DataFrame:
    """The proposals (header_pos, j, start) by which the first bad frame checks, or the footer where all frames do. No other can
    take a candidate further, and this needs no more than SPAN blocks from ``start``, gathered once for starts near each other."""
    front, ends, hits_ = plausible_columns()
    rows = fronts(candidates).select("header_pos", "fs", "size", front.alias("front"), "foot", ends.alias("ends"))
    tries = proposals.groupBy("header_pos", F.expr("start div 16").alias("near")).agg(F.min("start").alias("lo"), (F.max("start") + SPAN).alias("hi"), F.collect_set(F.struct("j", "start")).alias("tries"))
    got = gather(blocks, tries.select("header_pos", "near", "lo", "hi"), ["header_pos", "near"], width=16).drop("positions")
    got = got.join(tries, ["header_pos", "near"]).join(rows, "header_pos")
    return got.select("header_pos", hits_.alias("t")).select("header_pos", "t.j", "t.start")


@once
def plausible_columns() -> tuple[Column, ...]:
    def fits(t):
        kept = F.greatest(F.lit(0).cast("long"), t.j * BLOCK - F.col("fs"))
        skip = (t.start - F.col("lo")) * BLOCK + F.greatest(F.lit(0).cast("long"), F.col("fs") - t.j * BLOCK)
        frame = F.concat(F.substring("front", F.lit(1), kept.cast("int")), F.substring("content", (skip + 1).cast("int"), F.lit(FRAME)))
        return F.when(F.col("ends"), frame.startswith(F.col("foot"))).otherwise(framed.frame_checks(frame, F.col("size")))

    return of_window(F.col("fs"), F.lit(FRAME)), F.col("size").isNull(), F.explode(F.filter("tries", fits))


def extend(candidates: DataFrame, proposals: DataFrame, blocks: DataFrame, *, checked: bool = False, of: DataFrame | None = None) -> DataFrame:
    """Each candidate with the proposal (header_pos, j, start, r, g) that validates furthest: kept blocks, then r live
    blocks from ``start`` and what followed the kept blocks before, but for its first g blocks; with r null, live blocks up to the file's length.
    Ties: the start physically nearest to the last kept block. ``checked``: the proposals are ``plausible``; ``of``: the candidates'
    ``fronts``, if made before."""
    if "r" not in proposals.columns:
        proposals = proposals.withColumn("r", F.lit(None).cast("int")).withColumn("g", F.lit(0))
    blocks_of, missing, content, positions, far, whole, best_of = extend_columns()
    base = candidates.select("header_pos", F.col("content").alias("c0"), F.col("positions").alias("p0"), blocks_of.alias("blocks"), F.col("v.validates_to").alias("before"))
    if not checked:
        tails = plausible(candidates if of is None else of, proposals.where("r is null"), blocks).select("header_pos", "j", "start", F.lit(None).cast("int").alias("r"), F.lit(0).alias("g"))
        proposals = tails.unionByName(proposals.where("r is not null"))
    wanted = proposals.join(base.select("header_pos", "blocks"), "header_pos").select("header_pos", "j", "start", "r", "g", F.col("start").alias("lo"), missing.alias("hi"))
    got = gather(blocks, wanted.withColumn("r", F.coalesce("r", F.lit(-1))), ["header_pos", "j", "start", "r", "g"]).join(base, "header_pos")
    tried = got.select("header_pos", "j", "start", "r", "g", content.alias("content"), positions.alias("positions"), "before", far.alias("far"))
    tried = held(held(tried, "content").withColumn("v", framed.verdict_of("content")), "v").where("v.validates_to > before").where(whole)
    return tried.groupBy("header_pos").agg(best_of.alias("b")).select("header_pos", "b.*")


@once
def extend_columns() -> tuple[Column, ...]:
    """blocks, hi, content, positions, far, whether a layout may stand, the best of a candidate's layouts."""
    n = framed.block_count(framed.body_length(F.col("content")), BLOCK)
    missing = F.col("start") + F.coalesce(F.col("r"), F.col("blocks") - F.col("j"))
    later = F.when(F.col("r") > 0, F.greatest(F.lit(0), F.least(F.col("blocks") - F.col("j") - F.col("r"), F.size("p0") - F.col("j") - F.col("g")))).otherwise(0).cast("int")
    after = F.substring("c0", ((F.col("j") + F.col("g")) * BLOCK + 1).cast("int"), later * BLOCK)
    content = F.concat(F.substring("c0", F.lit(1), (F.col("j") * BLOCK).cast("int")), F.col("content"), after)
    positions = F.concat(F.slice("p0", F.lit(1), F.col("j").cast("int")), F.col("positions"), F.slice("p0", (F.col("j") + F.col("g")).cast("int") + 1, later))
    far = F.abs(F.get("positions", F.lit(0)) - F.get("p0", F.col("j").cast("int") - 1))
    # behind a file's end its last block holds dots: of equal ends this one is the file's own
    own_end = F.expr("length(trim(TRAILING '.' FROM content)) <= v.file_len")
    # a complete layout uses a block once; behind the break of an open one anything may stand
    whole = ~F.col("v.validates") | (F.size(F.array_distinct("positions")) == F.size("positions"))
    best = F.max_by(F.struct("content", "positions", "v"), F.struct(F.col("v.validates"), F.col("v.validates_to"), F.col("v.validates") & own_end, -F.col("far"), -F.col("start"), -F.col("r"), -F.col("g")))
    return n, missing, content, positions, far, whole, best


def solve_pairs(needs: DataFrame, blocks: DataFrame, *, window: int = 64, most_work: int = 1 << 34) -> DataFrame:
    """cand_id, a, b: live blocks that fill two single slots on either side of known content, so that the whole has its
    checksum. needs: cand_id, at (live place before the first slot), target, before_crc, between (text), after (text).

    Meet in the middle: each block near ``at`` as the first slot fixes the checksum of the second, so both halves are lists of
    ``window`` blocks that meet in an equi-join. Work beyond ``most_work`` rows is an error, nothing is cut off. Candidates
    with null parts get no row; of several pairs all are returned, to be verified by the file's own validator."""
    if needs.count() * window > most_work:
        raise ValueError("more work than allowed: raise most_work or narrow the window")
    mid, rest = F.octet_length("between"), F.octet_length("after")
    fixed = F.col("target").bitwiseXOR(shift(F.col("before_crc"), 2 * BLOCK + mid + rest, most=4096)).bitwiseXOR(shift(F.crc32("between"), rest + BLOCK, most=2048)).bitwiseXOR(F.crc32("after"))
    want = needs.select("cand_id", (F.col("at") + 1).alias("lo"), (F.col("at") + 1 + window).alias("hi"), mid.alias("mid"), shift(fixed, rest, most=1024, inverse=True).alias("left"))
    near = range_join(blocks.select("live", F.crc32("payload").alias("crc")), want, "live", "lo", "hi", width=max(64, window))
    first = near.select("cand_id", F.col("live").alias("a"), F.col("left").bitwiseXOR(shift(F.col("crc"), BLOCK + F.col("mid"), most=2048)).alias("crc"))
    second = near.select("cand_id", F.col("live").alias("b"), "crc")
    return first.join(second, ["cand_id", "crc"]).where("a <> b").select("cand_id", "a", "b")
