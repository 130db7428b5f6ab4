"""Contiguous recovery of binary formats: signatures at block starts, extents that grow while a file stays consistent.

A candidate first reads up to the next signature. Where its validator says that more bytes may follow, as when a signature
stands inside a file, its extent doubles; a candidate that is whole, or broken before its extent ends, is done. So a
file of m blocks is read at most about 2 m blocks in log m rounds, and no candidate reads to a configured maximum.

Image: pos, payload (binary, one size). Defined results: an empty image gives no rows; positions that are missing end an
extent's consistent part; a file that begins inside another is left to ``outermost``; null payloads are no blocks.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..formats.binary import FORMATS, unwrap
from ..layout import key_digits, order_key
from ..plans import next_on_axis, offsets, range_join
from ..session import snapshot

#: Files or spans whose places every executor may hold, some 100 bytes each; beyond that the image is dealt out to meet them.
MOST_HELD = 1 << 20
#: Rows that Python holds as objects at a time.
PIECE = 256

CARVED = "header_pos long, type string, label string, whole boolean, more boolean, good long, lo long, hi long, last long, content binary"


def _held(rows: DataFrame, many: int) -> DataFrame:
    return F.broadcast(rows) if many <= MOST_HELD else rows


def _pieces(batches):
    """The batches in parts of at most ``PIECE`` rows."""
    for b in batches:
        for at in range(0, b.num_rows, PIECE):
            yield b.slice(at, PIECE)


def encoded_files(docs: DataFrame, kind: str) -> DataFrame:
    """file_id, type, content of every document (doc_id not null; a null text is empty) as a file. kind: a format, or mixed."""
    names = sorted(FORMATS)

    def run(batches):
        for b in _pieces(batches):
            ids, texts = b.column("doc_id").to_pylist(), b.column("text").to_pylist()
            types = [kind if kind != "mixed" else names[i % len(names)] for i in ids]
            files = [FORMATS[t].encode(i, (x or "").encode()) for i, t, x in zip(ids, types, texts)]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(types), pa.array(files, pa.binary())], names=["file_id", "type", "content"])

    rows = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(run, "file_id long, type string, content binary")


def binary_image(files: DataFrame, *, size: int = 512, padding: str | None = None) -> DataFrame:
    """pos, payload: the files in a hashed order, last blocks filled with zeros; padding: zero or random blocks between files,
    as many as the file's own hash says (none to seven)."""
    # files are kept once and places found by their lengths alone: blocks are cut where they are read
    pads = F.pmod(F.xxhash64("file_id"), F.lit(8)).cast("int") if padding else F.lit(0)
    kept = files.select("file_id", "content", F.expr(f"cast((octet_length(content) + {size - 1}) div {size} as int)").alias("n"), pads.alias("pads"), F.monotonically_increasing_id().alias("row"))
    kept = snapshot(kept, "binary", compression="zstd")
    many = kept.count()
    sizes = kept.select("row", order_key(F.col("file_id")).alias("key"), (F.col("n") + F.col("pads")).alias("size"))
    starts = snapshot(offsets(sizes, F.substring("key", 1, key_digits(many)), ["key", "row"], "size", "start").select("row", "start"), "starts")
    rows = kept.join(_held(starts, many), "row")
    pieces = F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda i: F.rpad(F.substring("content", i * size + 1, F.lit(size)), size, F.unhex(F.lit("00"))))
    image = rows.where("n > 0").select("start", F.posexplode(pieces).alias("i", "payload")).select((F.col("start") + F.col("i")).alias("pos"), "payload")
    if padding:
        key, i = order_key(F.col("file_id")), (1 << 30) + F.col("j")
        fill = F.unhex(F.lit("00" * size)) if padding == "zero" else F.unhex(F.concat(*[F.sha2(F.concat_ws(":", key, i, F.lit(k)), 256) for k in range(size // 32)]))
        more = rows.where("pads > 0").select("file_id", "start", "n", F.explode(F.sequence(F.lit(1), F.col("pads"))).alias("j"))
        image = image.unionByName(more.select((F.col("start") + F.col("n") + F.col("j") - 1).alias("pos"), fill.alias("payload")))
    return image


def signatures(image: DataFrame) -> DataFrame:
    """pos, type: blocks that begin as a file of a format does."""
    kinds = {f.signature: f.name for f in FORMATS.values() if f.name != "docx"}
    named = [F.when(F.substring("payload", 1, len(s)) == F.lit(s), F.lit(n)) for s, n in kinds.items()]
    return image.select("pos", F.coalesce(*named).alias("type")).where("type is not null")


def judged(image: DataFrame, spans: DataFrame, width: int) -> DataFrame:
    """The verdict of every span (header_pos, type, lo, hi)."""
    def run(batches):
        for b in _pieces(batches):
            out = []
            for head, kind, lo, hi, last, blocks in zip(*(b.column(c).to_pylist() for c in ("header_pos", "type", "lo", "hi", "last", "blocks"))):
                blocks.sort(key=lambda x: x["pos"])
                run_ = [x["payload"] for k, x in enumerate(blocks) if x["pos"] == lo + k]
                data = b"".join(run_)
                v = FORMATS[kind].check(data)
                cut = len(run_) < hi - lo  # the image ends here
                out.append((head, kind, v.label or kind, v.whole, v.more and not cut, v.good, lo, hi, last, data[: v.good] if v.whole else None))
            rows = list(zip(*out)) or [()] * 10
            kinds = [pa.int64(), pa.string(), pa.string(), pa.bool_(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(list(x), k) for x, k in zip(rows, kinds)], names=[x.split()[0] for x in CARVED.split(", ")])

    met = range_join(image, spans, "pos", "lo", "hi", width=width)
    held = met.groupBy("header_pos", "type", "lo", "hi", "last").agg(F.collect_list(F.struct("pos", "payload")).alias("blocks"))
    return held.mapInArrow(run, CARVED)


def carve(image: DataFrame, *, width: int = 64) -> tuple[DataFrame, DataFrame]:
    """(written, left). written: header_pos, label, content of complete files; left: header_pos, type, good of candidates that
    are consistent up to byte ``good`` only."""
    heads = snapshot(signatures(image), "signatures")
    top = image.agg(F.coalesce(F.max("pos"), F.lit(-1))).first()[0] + 1
    follow = next_on_axis(heads.select((F.col("pos") + 1).alias("at"), "pos", "type"), heads.select(F.col("pos").alias("at")), "at", "next_at")
    spans = follow.select(F.col("pos").alias("header_pos"), "type", F.col("pos").alias("lo"), F.coalesce("next_at", F.lit(top)).alias("hi"), F.lit(top).cast("long").alias("last"))
    done, many = None, heads.count()
    while True:  # each round doubles what is open, so rounds end with the image
        got = snapshot(judged(image, _held(spans, many), width), "judged", compression="zstd")
        again = got.where("more and not whole and hi < last")
        closed = got.where("whole or not more or hi >= last")
        done = closed if done is None else done.unionByName(closed)
        if again.isEmpty():
            break
        # few as a rule: kept by themselves, so that the planner knows their size and need not deal out the image again
        spans = snapshot(again.select("header_pos", "type", "lo", F.expr("least(last, lo + 2 * (hi - lo))").alias("hi"), "last"), "spans")
    return done.where("whole").select("header_pos", "label", "content"), done.where("not whole and good > 0").select("header_pos", "type", "good")


def outermost(written: DataFrame, *, size: int = 512, width: int = 256) -> DataFrame:
    """Written files that do not begin inside another one."""
    ends = written.select(F.col("header_pos").alias("o_pos"), (F.col("header_pos") + 1).alias("lo"), (F.col("header_pos") + F.expr(f"(octet_length(content) - 1) div {size}") + 1).alias("hi"))
    inner = range_join(written.select("header_pos"), ends, "header_pos", "lo", "hi", width=width).select("header_pos").distinct()
    return written.join(inner, "header_pos", "left_anti")


def texts(written: DataFrame) -> DataFrame:
    """doc_id, label, text_sha256 decoded from recovered files."""
    def run(batches):
        import hashlib

        for b in _pieces(batches):
            labels = b.column("label").to_pylist()
            both = [unwrap(FORMATS[k].decode(x)) for k, x in zip(labels, b.column("content").to_pylist())]
            yield pa.RecordBatch.from_arrays([pa.array([n for n, _ in both], pa.int64()), pa.array(labels, pa.string()), pa.array([hashlib.sha256(x).hexdigest() for _, x in both], pa.string())], names=["doc_id", "label", "text_sha256"])

    return written.select("label", "content").mapInArrow(run, "doc_id long, label string, text_sha256 string")


def copied(image: DataFrame, *, width: int = 64) -> DataFrame:
    """The baseline without validation: from each signature to the next, whatever stands there. header_pos, content."""
    heads = signatures(image)
    follow = next_on_axis(heads.select((F.col("pos") + 1).alias("at"), "pos"), heads.select(F.col("pos").alias("at")), "at", "next_at")
    spans = follow.where("next_at is not null").select(F.col("pos").alias("header_pos"), F.col("pos").alias("lo"), F.col("next_at").alias("hi"))
    met = range_join(image, spans, "pos", "lo", "hi", width=width)
    held = met.groupBy("header_pos").agg(F.array_sort(F.collect_list(F.struct("pos", "payload"))).alias("b"))
    return held.select("header_pos", F.unhex(F.array_join(F.transform("b", lambda x: F.hex(x.payload)), "")).alias("content"))
