"""Queries over block validation, the classifier, image files, shared work, paired slots and measures of the engine's output."""

from __future__ import annotations

import uuid

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import functions as F

from .. import sources
from ..formats import framed
from ..formats.binary import FORMATS, zip_entries
from ..layout import BLOCK, choice
from ..operators import baseline, carve, classify, contiguous, hybrid, score, search, solve, validate
from ..operators.recover import Options, recover, recovered_texts
from ..session import shared_dir, snapshot
from .lanes import lane, sql_crc, sql_lane, table

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}

TEXTS = "SELECT doc_id, sha256(coalesce(text, '')) AS text_sha256 FROM documents WHERE doc_id IS NOT NULL"


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


@query(f"""WITH {sql_lane('rand')}, k AS (SELECT pos, payload, CAST(len(list_distinct(string_split(payload, ''))) AS INTEGER) AS kinds FROM image)
    SELECT pos, CAST(CASE WHEN NOT regexp_full_match(payload, '[A-Za-z0-9+/=~:.]+') THEN 0 WHEN starts_with(payload, '~H1:') THEN 100 WHEN kinds = 1 THEN 1 ELSE least(99, 2 + kinds * 97 // 64) END AS INTEGER) AS score FROM k""")
def val_block_rule(spark, sf_dir):
    return lane(spark, sf_dir, "rand")[0].select("pos", validate.framed_score(F.col("payload")).alias("score"))


@query(f"WITH {sql_lane('zero')} SELECT pos, CAST({sql_crc('payload')} AS BIGINT) AS crc FROM image, crc_t")
def val_block_state(spark, sf_dir):
    """Checksums by content, computed once for each and found again by every block that has it."""
    image, zero = lane(spark, sf_dir, "zero")[0], "0" * BLOCK
    states = snapshot(validate.block_state(image, F.crc32("payload"), zero=zero), "states")
    return validate.with_state(image, states, zero=zero).select("pos", F.col("state").alias("crc"))


def labelled_blocks(spark, sf_dir, size: int = 512):
    """file_id, type, payload of all blocks of the documents as files of mixed formats."""
    files = carve.encoded_files(table(spark, sf_dir, "documents"), "mixed")
    pieces = F.transform(F.sequence(F.lit(0), F.floor((F.octet_length("content") - 1) / size).cast("int")), lambda i: F.substring("content", i * size + 1, F.lit(size)))
    return files.select("file_id", "type", F.explode(pieces).alias("payload"))


@query()
def clf_confusion(spark, sf_dir):
    """truth, guess, n over blocks of files that took no part in training (one in four, by hash)."""
    rows, types = snapshot(labelled_blocks(spark, sf_dir), "labelled"), sorted(FORMATS)
    held = choice(F.col("file_id")) % 4 == 0
    model = classify.train(rows.where(~held), types)
    return classify.confusion(classify.score(rows.where(held), model, types))


@query(f"WITH {sql_lane('gap')} SELECT pos, sha256(payload) AS h FROM image")
def src_image(spark, sf_dir):
    """An image written as raw segment files and read back by the data source."""
    folder = f"{shared_dir(spark)}/raw-{uuid.uuid4().hex}"
    folder = folder.removeprefix("file:")
    image = lane(spark, sf_dir, "gap")[0].select("pos", F.col("payload").cast("binary").alias("payload"))
    sources.write_segments(image, folder, per_segment=4096).write.format("noop").mode("overwrite").save()
    return sources.read_image(spark, folder, per_segment=4096).select("pos", F.sha2("payload", 256).alias("h"))


@query(f"""WITH {sql_lane('cont')}, n AS (SELECT file_id, min(pos) AS p, count(*) AS n FROM image GROUP BY file_id)
    SELECT file_id AS cand_id, p + 1 AS a, p + 3 AS b FROM n WHERE n >= 5""")
def crc_mitm2(spark, sf_dir):
    """The second and fourth block of every file of five blocks or more, from its first, third and fifth and the checksum
    of the five; of several pairs the first in order."""
    image, truth = lane(spark, sf_dir, "cont")
    image = snapshot(image, "image")
    at = truth.where("logical_block < 5").join(image, "pos").groupBy("file_id").agg(F.array_sort(F.collect_list(F.struct("logical_block", "pos", "payload"))).alias("b")).where("size(b) = 5")
    text = lambda i: F.get("b", F.lit(i)).payload
    needs = at.select(F.col("file_id").alias("cand_id"), F.get("b", F.lit(0)).pos.alias("at"), F.crc32(F.concat(*[text(i) for i in range(5)])).alias("target"), F.crc32(text(0)).alias("before_crc"), text(2).alias("between"), text(4).alias("after"))
    pairs = solve.solve_pairs(snapshot(needs, "needs"), image.withColumn("live", F.col("pos")))
    return pairs.groupBy("cand_id").agg(F.min(F.struct("a", "b")).alias("p")).select("cand_id", "p.a", "p.b")


@query(TEXTS)
def hyb_workflow(spark, sf_dir):
    """Texts of the gap scenario: files that header-to-footer copies get right, by their log, then the engine on the rest."""
    image = snapshot(lane(spark, sf_dir, "gap")[0], "image")
    copies = baseline.header_footer(image, search.literals(image, [search.FRAMED]))
    first = snapshot(copies.withColumn("v", framed.verdict(F.col("content"))).where("v.validates"), "first")
    # a file ends where its header says: where its footer begins in one block and ends in the next, the copy runs into the next file
    blocks = framed.block_count(framed.body_length(F.col("content")), BLOCK)
    log = first.select(F.col("header_pos").alias("a"), (F.col("header_pos") + blocks - 1).alias("b")).select(hybrid.log_of("a", "b").alias("value"))
    out, _ = hybrid.hybrid(image, log, size=BLOCK)
    return recovered_texts(first.select("content").unionByName(out.written.select("content")))


@query(TEXTS)
def frg_ltr(spark, sf_dir):
    """The gap scenario by the generic left-to-right strategy alone: checksums verify, they do not solve."""
    return recovered_texts(recover(lane(spark, sf_dir, "gap")[0], Options(use_checksums=False, use_fallback=True)).written)


@query(f"""WITH {sql_lane('gap')}, s AS (SELECT 'framed' AS type, CASE WHEN has_gap THEN 'split' ELSE 'whole' END AS layout, has_gap FROM plan)
    SELECT type, layout, count(*) AS files, count(*) FILTER (NOT has_gap) AS complete, CAST(0 AS BIGINT) AS partial, CAST(0 AS BIGINT) AS incorrect, count(*) FILTER (has_gap) AS not_recovered FROM s GROUP BY GROUPING SETS ((type, layout), ())""")
def scr_contiguous(spark, sf_dir):
    """Classes of what contiguous recovery alone writes of the gap scenario, against the key."""
    image, truth = lane(spark, sf_dir, "gap")
    image = snapshot(image, "image")
    written = contiguous.fixpoint(image, search.literals(image, [search.FRAMED]))[0]
    key = snapshot(score.key_of(image, truth), "key")
    return score.breakdown(score.best(score.classify(score.outputs_of(written), key), key))


@query("SELECT 0 AS only_first, 0 AS only_second, count(*) AS first FROM documents WHERE doc_id IS NOT NULL")
def run_identity(spark, sf_dir):
    """Two runs over two builds of one image, compared row by row."""
    runs = []
    for _ in range(2):
        image = snapshot(lane(spark, sf_dir, "gap")[0], "image")
        written, queued, _ = contiguous.fixpoint(image, search.literals(image, [search.FRAMED]))
        runs.append(written.select("header_pos", F.md5("content").alias("h"), "positions").unionByName(queued.select("header_pos", F.md5("content").alias("h"), "positions")))
    return score.differences(*runs)


@query(f"""WITH {sql_lane('gap')}, h AS (SELECT CAST(sum((length(payload) - length(replace(payload, '~D', ''))) // 2) AS BIGINT) AS hits FROM image)
    SELECT method, hits FROM h, unnest(['arrow', 'native', 'row']) AS u(method)""")
def scan_ablation(spark, sf_dir):
    """Frame marks found by a native expression, an Arrow function and a row-wise function: the same counts; bench.py times them."""
    image = snapshot(lane(spark, sf_dir, "gap")[0], "image")

    @F.arrow_udf("int")
    def arrow(x: pa.Array) -> pa.Array:
        return pc.count_substring(x, "~D").cast(pa.int32())

    row = F.udf(lambda x: x.count("~D"), "int")
    ways = {"native": F.size(search.hits(F.col("payload"), "~D")), "arrow": arrow("payload"), "row": row("payload")}
    parts = [image.select(F.lit(k).alias("method"), c.cast("long").alias("n")) for k, c in ways.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).groupBy("method").agg(F.sum("n").alias("hits"))


@F.udtf(returnType="name string, size int")
class ArchiveEntries:
    """name, size of the entries of a ZIP archive; none if it is null or damaged."""

    def eval(self, data):
        end = -1 if data is None else bytes(data).rfind(b"PK\x05\x06")
        for name, body in (zip_entries(bytes(data), end) or []) if end >= 0 else []:
            yield name, len(body)


@query("""WITH d AS (SELECT doc_id AS file_id, octet_length(encode(coalesce(text, ''))) AS n FROM documents WHERE doc_id IS NOT NULL)
    SELECT file_id, 'body.bin' AS name, CAST(12 + n AS INTEGER) AS size FROM d UNION ALL SELECT file_id, 'name.txt', CAST(length(CAST(file_id AS VARCHAR)) AS INTEGER) FROM d UNION ALL SELECT file_id, 'sum.txt', 8 FROM d""")
def op_udtf_zip(spark, sf_dir):
    files = carve.encoded_files(table(spark, sf_dir, "documents"), "zip")
    return files.lateralJoin(ArchiveEntries(F.col("content").outer())).select("file_id", "name", "size")
