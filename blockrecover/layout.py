"""Images with a ground-truth key: framed text files, fragmentation scenarios and directive texts.

A file of the text lane is a header ``~H1:<id, 10 digits>:<body length, 8 digits>~``, frames
``~D<length, 6 digits>:<up to 900 characters><CRC-32 of them, 8 hex digits>`` over the base64 form of the text, and a
footer ``~E1:<md5 of the text>~``; the last block is padded by dots. Characters are bytes. Where a block goes is a sort
key, so a whole scenario is one projection and one two-level rank.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .functions.crc import crc_hex
from .plans import held, ranked
from .session import snapshot

BLOCK, BODY, FRAME, HEADER, FOOTER = 256, 900, 917, 24, 37
SEED = 42
#: Zero or random blocks added per 100 file blocks in the padded scenarios.
PADDING_PERCENT = 148


@dataclass(frozen=True)
class Scenario:
    """Which files are fragmented, how, and what is added between blocks."""

    name: str
    gap: tuple[int, int] | None = None  # (modulus, remainder) of files with filler before one block
    displaced: tuple[int, int] | None = None
    omitted: tuple[int, int] | None = None
    most_gap: int = 4
    padding: str | None = None  # zero or random


SCENARIOS = {
    "cont": Scenario("cont"),
    "gap": Scenario("gap", gap=(5, 0)),
    "ooo": Scenario("ooo", displaced=(10, 1)),
    "both": Scenario("both", gap=(10, 2), displaced=(10, 2), most_gap=2),
    "omit": Scenario("omit", omitted=(50, 3)),
    "zero": Scenario("zero", padding="zero"),
    "rand": Scenario("rand", padding="random"),
}


def encoded(text: Column) -> Column:
    """base64 without the line breaks that Spark may put in; found as a whole, as a walk over single characters costs more than the encoding."""
    return F.replace(F.base64(F.encode(text, "UTF-8")), F.lit("\r\n"), F.lit(""))


def slices(content: Column, size: int) -> Column:
    """The pieces of ``size`` characters of an ASCII text; cut from its bytes, so that a piece costs its own length only."""
    data = content.cast("binary")
    return F.transform(F.sequence(F.lit(0), F.floor((F.octet_length(content) - 1) / size).cast("int")), lambda i: F.substring(data, i * size + 1, F.lit(size)).cast("string"))


def digits(number: Column, width: int) -> Column:
    """A number with leading zeros; one of more digits is an error, as it would not fit its field."""
    text = number.cast("string")
    return F.when(F.length(text) <= width, F.lpad(text, width, "0")).otherwise(F.raise_error(F.concat(F.lit("number beyond its field: "), text)))


def framed_files(docs: DataFrame) -> DataFrame:
    """file_id, content, file_len of the framed file of every document. Rows without a doc_id make no file; null
    texts count as empty; a doc_id that comes again gives a file for each row, which ``tag`` (a hash of the text) keeps apart."""
    body = encoded(F.coalesce("text", F.lit("")))
    rows = docs.where("doc_id is not null").select(F.col("doc_id").alias("file_id"), F.coalesce("text", F.lit("")).alias("text"), body.alias("body"))
    frames = F.transform(slices(F.col("body"), BODY), lambda p: F.concat(F.lit("~D"), F.lpad(F.octet_length(p).cast("string"), 6, "0"), F.lit(":"), p, crc_hex(p)))
    frames = F.when(F.octet_length("body") > 0, F.array_join(frames, "")).otherwise("")
    head = F.concat(F.lit("~H1:"), digits(F.col("file_id"), 10), F.lit(":"), digits(F.octet_length("body"), 8), F.lit("~"))
    content = F.concat(head, frames, F.lit("~E1:"), F.md5(F.encode("text", "UTF-8")), F.lit("~"))
    return rows.select("file_id", F.xxhash64("text").alias("tag"), content.alias("content")).withColumn("file_len", F.octet_length("content").cast("long"))


def split(files: DataFrame, size: int = BLOCK, pad: str | None = ".") -> DataFrame:
    """file_id, logical_block, payload and the other columns of files: fixed blocks, the last one padded (or left short).
    Contents of characters beyond ASCII are cut by characters."""
    files = held(files, "content")  # or a content would be made anew for each of its pieces
    ascii_ = F.octet_length("content") == F.length("content")
    pieces = F.when(ascii_, slices(F.col("content"), size)).otherwise(F.transform(F.expr(f"sequence(0, (length(content) - 1) div {size})"), lambda i: F.substring(F.col("content"), i * size + 1, F.lit(size))))
    others = [c for c in files.columns if c not in ("file_id", "content")]
    rows = files.where(F.length("content") > 0).select("file_id", *others, F.posexplode(pieces).alias("logical_block", "payload"))
    return rows.withColumn("payload", F.rpad("payload", size, pad)) if pad else rows


def choice(file_id: Column, seed: int = SEED) -> Column:
    """The number that decides a file's fragmentation."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), file_id.cast("string"))), 1, 8), 16, 10).cast("long")


def order_key(file_id: Column, seed: int = SEED) -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:order:"), file_id.cast("string")))


def noise(*parts: Column) -> Column:
    """A filler block of hashed text."""
    name = F.concat_ws(":", *parts)
    return F.concat(*[F.sha2(F.concat(name, F.lit(f":{k}")), 256) for k in range(BLOCK // 64)])


def placed_files(files: DataFrame, scenario: Scenario) -> DataFrame:
    """files (file_id, file_len) with what the scenario does to each."""
    plan = files.withColumn("m", F.expr(f"(file_len + {BLOCK - 1}) div {BLOCK}")).withColumn("h", choice(F.col("file_id"))).withColumn("key", order_key(F.col("file_id")))
    hit = lambda x: (F.col("h") % x[0] == x[1]) & (F.col("m") >= 4) if x else F.lit(False)
    plan = plan.withColumn("has_gap", hit(scenario.gap)).withColumn("has_run", hit(scenario.displaced)).withColumn("has_hole", hit(scenario.omitted))
    plan = plan.withColumn("gap_at", F.when(F.col("has_gap"), 1 + F.col("h") % (F.col("m") - 1))).withColumn("gap_n", F.when(F.col("has_gap"), 1 + F.expr("h div 7") % scenario.most_gap))
    length = 1 + F.col("h") % F.greatest(F.lit(1), F.expr("m div 2 - 1"))
    plan = plan.withColumn("run_n", F.when(F.col("has_run"), length)).withColumn("run_at", F.when(F.col("has_run"), 1 + F.expr("h div 10") % (F.col("m") - F.col("run_n"))))
    return plan.withColumn("hole_at", F.when(F.col("has_hole"), 1 + F.expr("h div 10") % (F.col("m") - 1)))


def key_digits(rows: int, *, a_chunk: int = 1_000_000) -> int:
    """Leading hex digits of keys that part so many rows into chunks of about ``a_chunk``."""
    n = 2
    while rows > a_chunk * 16**n:
        n += 1
    return n


def lengths(docs: DataFrame) -> DataFrame:
    """file_id, file_len of the framed files, by arithmetic alone."""
    body = F.expr("4 * ((octet_length(coalesce(text, '')) + 2) div 3)")
    size = body + F.expr(f"({{}} + {BODY - 1}) div {BODY}".format("4 * ((octet_length(coalesce(text, '')) + 2) div 3)")) * (FRAME - BODY) + HEADER + FOOTER
    return docs.where("doc_id is not null").select(F.col("doc_id").alias("file_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("tag"), size.cast("long").alias("file_len"))


def build_image(docs: DataFrame, scenario: Scenario) -> tuple[DataFrame, DataFrame]:
    """(image, truth). image: pos, payload. truth: file_id, logical_block, pos, file_len, fragmented. Files are encoded and
    cut in one pass; what becomes of a block follows from its own file, but for the hosts of displaced runs."""
    plan = placed_files(lengths(docs), scenario)
    rows = split(placed_files(framed_files(docs), scenario))
    if scenario.displaced:
        # a displaced run goes behind the fourth fragmented file after its own; few rows: one per fragmented file
        moved = snapshot(plan.where("has_run").select(F.col("file_id").alias("f"), F.col("key").alias("k")).distinct(), "moved")
        moved = ranked(moved, F.substring("k", 1, key_digits(moved.count())), ["k"], "place")
        later = moved.select(F.col("place").alias("p"), F.col("k").alias("host"))
        # a table of known size: where it is small, blocks are not dealt out to meet it
        hosts = snapshot(moved.join(later, moved["place"] + 4 == later["p"], "left").select("f", F.coalesce("host", F.lit("~")).alias("host")), "hosts")
        rows = rows.join(hosts, rows["file_id"] == hosts["f"], "left").drop("f")
    else:
        rows = rows.withColumn("host", F.lit(None).cast("string"))
    moved = F.coalesce((F.col("logical_block") >= F.col("run_at")) & (F.col("logical_block") < F.col("run_at") + F.col("run_n")), F.lit(False))
    kept = rows.where(~F.coalesce(F.col("logical_block") == F.col("hole_at"), F.lit(False)))
    own = kept.select(
        F.when(moved, F.col("host")).otherwise(F.col("key")).alias("k1"), F.when(moved, 1).otherwise(0).alias("k2"), F.when(moved, F.col("key")).otherwise("").alias("k3"), "tag", (F.col("logical_block") * 2 + 1).alias("k4"), F.lit(0).alias("k5"),
        "payload", "file_id", "logical_block", "file_len", (F.col("has_gap") | F.col("has_run") | F.col("has_hole")).alias("fragmented"),
    )
    none = [F.lit(None).cast("long").alias("file_id"), F.lit(None).cast("int").alias("logical_block"), F.lit(None).cast("long").alias("file_len"), F.lit(None).cast("boolean").alias("fragmented")]
    parts = [own]
    if scenario.gap:
        filler = plan.where("has_gap").withColumn("j", F.explode(F.sequence(F.lit(1), F.col("gap_n").cast("int"))))
        parts.append(filler.select(F.col("key").alias("k1"), F.lit(0).alias("k2"), F.lit("").alias("k3"), "tag", (F.col("gap_at") * 2).cast("int").alias("k4"), F.col("j").alias("k5"), noise(F.lit("gap"), F.col("file_id"), F.col("j")).alias("payload"), *none))
    if scenario.padding:
        # as many as the share asks for, each behind the block that its own hash picks
        pads = kept.select("key", "file_id", "logical_block", F.explode(F.sequence(F.lit(1), F.lit(3))).alias("j")).withColumn("u", F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("pad"), "file_id", "logical_block", "j")), 1, 8), 16, 10).cast("long") % 300).where(F.col("u") < PADDING_PERCENT)
        body = F.lit("0" * BLOCK) if scenario.padding == "zero" else noise(F.lit("rand"), F.col("file_id"), F.col("logical_block"), F.col("j"))
        spot = F.md5(F.concat_ws(":", F.lit("spot"), "file_id", "logical_block", "j"))
        parts.append(pads.select(spot.alias("k1"), F.lit(0).alias("k2"), F.lit("").alias("k3"), F.lit(0).cast("long").alias("tag"), F.lit(-1).alias("k4"), F.col("j").alias("k5"), body.alias("payload"), *none))
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    every = snapshot(every, "blocks", compression="zstd")
    placed = ranked(every, F.substring("k1", 1, key_digits(every.count())), ["k1", "k2", "k3", "tag", "k4", "k5"], "pos")
    image = placed.select("pos", "payload")
    truth = placed.where("file_id is not null").select("file_id", "logical_block", "pos", "file_len", "fragmented")
    return image, truth


# ---------------------------------------------------------------- directives


def parse_directives(lines: DataFrame) -> DataFrame:
    """lines: one column ``value``. Returns line-wise file, op, lo, hi; globals have file null.

    ``key = value`` sets a global; ``[name]`` is written as ``name: op ranges`` per line, ranges being numbers or
    ``a-b``, separated by commas; ``#`` starts a comment."""
    rows = lines.select(F.trim(F.regexp_replace("value", "#.*$", "")).alias("v")).where("v <> ''")
    glob = rows.where(F.col("v").rlike(r"^\w+\s*=")).select(F.lit(None).cast("string").alias("file"), F.regexp_extract("v", r"^(\w+)", 1).alias("op"), F.regexp_extract("v", r"=\s*(.*)$", 1).alias("arg"), F.lit(None).cast("int").alias("lo"), F.lit(None).cast("int").alias("hi"))
    per = rows.where(F.col("v").rlike(r"^\S+:\s")).select(F.regexp_extract("v", r"^(\S+):", 1).alias("file"), F.regexp_extract("v", r":\s+(\w+)", 1).alias("op"), F.regexp_extract("v", r":\s+\w+\s*(.*)$", 1).alias("args"))
    per = per.withColumn("arg", F.explode_outer(F.when(F.col("args") != "", F.split("args", r"\s*,\s*"))))
    lo = F.regexp_extract("arg", r"^(\d+)", 1)
    hi = F.regexp_extract("arg", r"-(\d+)$", 1)
    per = per.select("file", "op", "arg", F.when(lo != "", lo.cast("int")).alias("lo"), F.when(hi != "", hi.cast("int")).when(lo != "", lo.cast("int")).alias("hi"))
    return glob.unionByName(per)


def directed_truth(files: DataFrame, directives: DataFrame) -> DataFrame:
    """files: file, blocks, place. Applies omit, displace, gap and scatter: file, logical_block, pos (null: omitted).

    ``gap a-b`` puts b - a + 1 filler blocks before logical block a; ``displace`` moves blocks behind the last file;
    ``scatter`` sends all blocks after the first to hashed places behind the last file."""
    d = directives.where("file is not null").select(F.col("file").alias("d_file"), "op", "lo", "hi")
    blocks = files.withColumn("logical_block", F.explode(F.expr("sequence(0, blocks - 1)")))
    said = blocks.join(d.where("op in ('omit', 'displace', 'scatter')"), (blocks["file"] == F.col("d_file")) & (F.col("op").isin("scatter") & (F.col("logical_block") > 0) | (F.col("logical_block") >= F.col("lo")) & (F.col("logical_block") <= F.col("hi"))), "left")
    said = said.groupBy("file", "place", "logical_block").agg(F.max(F.col("op") == "omit").alias("omit"), F.max(F.col("op") == "displace").alias("moved"), F.max(F.col("op") == "scatter").alias("scattered"))
    far = F.coalesce(F.col("moved") | F.col("scattered"), F.lit(False))
    keyed = said.where(~F.coalesce("omit", F.lit(False))).select(
        "file", "logical_block", far.cast("int").alias("k1"), F.when(far, 0).otherwise(F.col("place")).alias("k2"), F.when(F.coalesce("scattered", F.lit(False)), F.md5(F.concat_ws(":", "file", "logical_block"))).otherwise("").alias("k3"), "place", (F.col("logical_block") * 2 + 1).alias("k4")
    )
    gaps = d.where("op = 'gap'").join(files, F.col("d_file") == F.col("file")).withColumn("j", F.explode(F.sequence("lo", "hi")))
    filler = gaps.select(F.lit(None).cast("string").alias("file"), F.lit(None).cast("int").alias("logical_block"), F.lit(0).alias("k1"), F.col("place").alias("k2"), F.lit("").alias("k3"), "place", (F.col("lo") * 2).alias("k4"))
    placed = keyed.unionByName(filler)
    # chunks of 1,024 places, or of one hash prefix
    at = lambda c: F.lpad(F.expr(f"{c} div 1024").cast("string"), 16, "0")
    k0 = F.concat_ws(":", F.col("k1").cast("string"), at("k2"), F.rpad(F.substring("k3", 1, 2), 2, " "), F.when(F.col("k3") == "", at("place")).otherwise(""))
    placed = ranked(placed, k0, ["k1", "k2", "k3", "place", "k4"], "pos").where("file is not null").select("file", "logical_block", "pos")
    lost = said.where("omit").select("file", "logical_block", F.lit(None).cast("long").alias("pos"))
    return placed.unionByName(lost)
