"""Queries over contiguous recovery, reassembly, the pool, scoring, progress, control and baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..formats import framed
from ..layout import BLOCK, SCENARIOS, build_image, framed_files, order_key, split
from ..operators import baseline, contiguous, persist, pool, score, search, solve
from ..operators.recover import Options, recover, recovered_texts
from ..plans import ranked
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


def _start(spark, sf_dir, name):
    image = snapshot(lane(spark, sf_dir, name)[0], "image")
    return image, search.literals(image, [search.FRAMED]), image.select("pos", F.col("pos").alias("live"))


# ---------------------------------------------------------------- contiguous


@query(f"WITH {sql_lane('cont')} SELECT pos AS header_pos, pos AS lo, pos + m AS hi FROM image JOIN plan0 USING (file_id) WHERE logical_block = 0")
def ctg_span_metadata(spark, sf_dir):
    image, boundary, view = _start(spark, sf_dir, "cont")
    return contiguous.spans(image, boundary, view)


@query(f"""WITH {sql_lane('cont')}, h AS (SELECT pos FROM image WHERE starts_with(payload, '~H1:')), f AS (SELECT pos AS f_pos FROM image WHERE contains(payload, '~E1:'))
    SELECT h.pos AS header_pos, h.pos AS lo, f.f_pos + 1 AS hi FROM h ASOF JOIN f ON h.pos <= f.f_pos""")
def ctg_span_footer(spark, sf_dir):
    _, boundary, view = _start(spark, sf_dir, "cont")
    return contiguous.footer_spans(boundary, view)


@query(f"WITH {sql_lane('cont')}, h AS (SELECT pos FROM image WHERE starts_with(payload, '~H1:')) SELECT pos AS header_pos, pos AS lo, least(coalesce(lead(pos) OVER (ORDER BY pos), 4611686018427387904), pos + 16) AS hi FROM h")
def ctg_span_limit(spark, sf_dir):
    _, boundary, _ = _start(spark, sf_dir, "cont")
    return search.span_limits(boundary, search.FormatSpec("framed", "~H1:", max_len=16 * BLOCK), BLOCK)


@query(f"WITH {sql_lane('gap')} SELECT file_id, CASE WHEN has_gap THEN 'queued' ELSE 'written' END AS route FROM plan")
def ctg_pass1(spark, sf_dir):
    image, boundary, view = _start(spark, sf_dir, "gap")
    got = contiguous.route(contiguous.run_pass(image.join(view, "pos"), contiguous.spans(image, boundary, view)))
    return got.select(framed.file_number(F.col("content")).alias("file_id"), "route")


@query(TEXTS)
def ctg_fixpoint(spark, sf_dir):
    image, boundary, _ = _start(spark, sf_dir, "cont")
    return recovered_texts(contiguous.fixpoint(image, boundary)[0])


def nested_image(docs):
    """Files of at least two blocks in threes: the third inside the second inside the first, each cut behind its first
    block. pos, payload."""
    files = framed_files(docs).where(F.col("file_len") > BLOCK).withColumn("key", order_key(F.col("file_id")))
    placed = ranked(files, F.substring("key", 1, 2), ["key"], "place").select("file_id", "content", F.expr("place div 3").alias("trio"), F.expr("place % 3").alias("depth"))
    blocks = split(placed.select("file_id", "content")).join(placed.drop("content"), "file_id")
    late = (F.col("logical_block") > 0) & (F.col("depth") < 2)
    spot = F.when(late, 10 - F.col("depth")).otherwise(F.col("depth"))
    trios = ranked(blocks.withColumn("spot", spot).withColumn("chunk", F.expr("trio div 16")), F.col("chunk"), ["trio", "spot", "logical_block"], "pos")
    return trios.select("pos", "payload")


@query(f"""WITH {sql_lane('cont')}, n AS (SELECT file_id, row_number() OVER (ORDER BY key) - 1 AS place, count(*) OVER () AS total FROM plan0 WHERE file_len > 256)
    SELECT file_id, CAST(least(3 - place % 3, total - place) AS INTEGER) AS pass_no FROM n""")
def ctg_nested(spark, sf_dir):
    image = snapshot(nested_image(table(spark, sf_dir, "documents")), "image")
    written = contiguous.fixpoint(image, search.literals(image, [search.FRAMED]))[0]
    return written.select(framed.file_number(F.col("content")).alias("file_id"), "pass_no")


@query("""SELECT DISTINCT c_custkey AS header_pos FROM (SELECT c_custkey, c_custkey * 5 AS lo, c_custkey * 5 + 7 AS hi FROM customer) c JOIN (SELECT s_suppkey * 31 AS pos FROM supplier) s ON pos BETWEEN lo AND hi""")
def ctg_affected_headers(spark, sf_dir):
    ext = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("header_pos"), (F.col("c_custkey") * 5).alias("first_pos"), (F.col("c_custkey") * 5 + 7).alias("last_pos"))
    return contiguous.affected(ext, table(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 31).alias("pos")), width=64)


@query("""WITH c AS (SELECT o_orderkey AS header_pos, o_custkey * 40 + o_orderkey % 37 + k AS pos FROM orders, unnest(range(3)) AS u(k)),
    f AS (SELECT pos, min(header_pos) AS owner FROM c GROUP BY pos) SELECT DISTINCT header_pos FROM c WHERE header_pos NOT IN (SELECT header_pos FROM c JOIN f USING (pos) WHERE owner <> header_pos)""")
def claims_resolve(spark, sf_dir):
    at = F.col("o_custkey") * 40 + F.col("o_orderkey") % 37
    claims = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("header_pos"), F.array(at, at + 1, at + 2).alias("positions"))
    return contiguous.resolve_claims(claims).select("header_pos")


# ---------------------------------------------------------------- reassembly


@query(f"""WITH {sql_lane('gap')}, t AS (SELECT pos, payload, payload || coalesce(left(lead(payload) OVER (ORDER BY pos), 10), '') AS text FROM image),
    m AS (SELECT pos, payload, text, x FROM t, unnest(range(256)) AS u(x) WHERE substr(text, x + 9, 1) = '~' AND substr(text, x + 10, 1) IN ('D', 'E') AND regexp_full_match(substr(text, x + 1, 8), '[0-9a-f]{{8}}'))
    SELECT pos, CAST(x AS INTEGER) AS x, CAST('0x' || substr(text, x + 1, 8) AS BIGINT) AS stored, CASE WHEN x = 0 THEN 0 ELSE CAST({sql_crc('left(payload, x)')} AS BIGINT) END AS prefix_crc FROM m, crc_t""")
def crc_end_index(spark, sf_dir):
    image, _, view = _start(spark, sf_dir, "gap")
    return solve.end_index(image.join(view, "pos")).where("k = 0").select(F.col("live").alias("pos"), "x", "stored", "prefix_crc")


@query(f"""WITH {sql_lane('gap')}, c AS (SELECT pos, CAST({sql_crc('payload || lead2')} AS BIGINT) AS crc FROM (SELECT pos, payload, lead(payload) OVER (ORDER BY pos) AS lead2 FROM image), crc_t WHERE lead2 IS NOT NULL) SELECT * FROM c""")
def crc_run(spark, sf_dir):
    """Checksums of runs of two blocks from those of single blocks, by window prefix algebra."""
    image, _, view = _start(spark, sf_dir, "gap")
    own = solve.with_neighbours(image.join(view, "pos"), chunk=512)
    return own.where("run2 is not null").select((F.col("pos") - 2).alias("pos"), F.col("run2").alias("crc")).unionByName(
        own.join(own.agg(F.max("pos").alias("top")), F.col("pos") == F.col("top")).select((F.col("pos") - 1).alias("pos"), solve.shift_by(F.col("run1"), BLOCK).bitwiseXOR(F.col("crc")).alias("crc"))
    )


def _fragments(name: str):
    def run(spark, sf_dir):
        return recovered_texts(recover(lane(spark, sf_dir, name)[0]).written)

    return run


@query(TEXTS)
def frg_gap(spark, sf_dir):
    """Texts of all files of the gap scenario, decoded from recovered blocks."""
    return _fragments("gap")(spark, sf_dir)


@query(TEXTS)
def frg_ooo(spark, sf_dir):
    return _fragments("ooo")(spark, sf_dir)


@query()
def frg_both(spark, sf_dir):
    return _fragments("both")(spark, sf_dir)


@query(f"WITH {sql_lane('omit')} SELECT file_id, CASE WHEN has_hole THEN 'promising' ELSE 'written' END AS status FROM plan")
def frg_omit(spark, sf_dir):
    out = recover(lane(spark, sf_dir, "omit")[0], Options())
    name = framed.file_number(F.col("content")).alias("file_id")
    return out.written.select(name, F.lit("written").alias("status")).unionByName(out.promising.select(name, F.lit("promising").alias("status")))


@query(TEXTS)
def frg_zero(spark, sf_dir):
    """Zero padding at random places: the recovered set is that of the unpadded image."""
    image = lane(spark, sf_dir, "zero")[0].where(F.col("payload") != "0" * BLOCK)
    image = snapshot(ranked(image, F.expr("pos div 4096"), ["pos"], "live").select(F.col("live").alias("pos"), "payload"), "image")
    return recovered_texts(contiguous.fixpoint(image, search.literals(image, [search.FRAMED]))[0])


# ---------------------------------------------------------------- pool


def _pool(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("cand_id"), F.col("c_mktsegment").alias("type"), (-F.floor("c_acctbal")).cast("long").alias("priority"), (F.col("c_custkey") % 10).alias("created"))


SQL_POOL = "p AS (SELECT c_custkey AS cand_id, c_mktsegment AS type, -CAST(floor(c_acctbal) AS BIGINT) AS priority, c_custkey % 10 AS created FROM customer)"


@query(f"WITH {SQL_POOL} SELECT cand_id, priority FROM p ORDER BY priority DESC, created, cand_id LIMIT 32")
def pool_dispatch(spark, sf_dir):
    return pool.dispatch(_pool(spark, sf_dir), 32).select("cand_id", "priority")


@query(f"WITH {SQL_POOL} SELECT cand_id, priority + CASE WHEN type = 'BUILDING' THEN 5000 ELSE 0 END AS priority FROM p ORDER BY 2 DESC, created, cand_id LIMIT 32")
def pool_bias(spark, sf_dir):
    return pool.dispatch(_pool(spark, sf_dir), 32, bias=spark.createDataFrame([("BUILDING", 5000)], "type string, bias long")).select("cand_id", "priority")


@query(f"WITH {SQL_POOL}, s AS (SELECT user_id AS cand_id, sum(event_id % 1000 + 64 * (event_id % 3)) AS s FROM events GROUP BY 1) SELECT cand_id, CAST(priority - coalesce(s, 0) AS BIGINT) AS priority FROM p LEFT JOIN s USING (cand_id)")
def pool_requeue(spark, sf_dir):
    served = table(spark, sf_dir, "events").select(F.col("user_id").alias("cand_id"), pool.service_of(F.col("event_id") % 1000, F.col("event_id") % 3).alias("service"))
    return pool.requeue(_pool(spark, sf_dir), served).select("cand_id", "priority")


@query(f"""WITH {SQL_POOL}, l AS (SELECT cand_id, (cand_id * 3) % 101 AS a, (cand_id * 3) % 101 + 1 AS b FROM p),
    k AS (SELECT p.*, a FROM p JOIN l USING (cand_id) WHERE a % 10 <> 4 AND b % 10 <> 4 AND cand_id % 17 <> 0)
    SELECT cand_id FROM k QUALIFY row_number() OVER (PARTITION BY a ORDER BY created, cand_id) = 1""")
def pool_maintain(spark, sf_dir):
    rows = _pool(spark, sf_dir)
    a = (F.col("cand_id") * 3) % 101
    layouts = rows.select("cand_id", F.array(a, a + 1).alias("positions"))
    ledger = spark.range(103).select(F.col("id").alias("pos"), F.when(F.col("id") % 10 == 4, 0).otherwise(1).alias("refcount"))
    return pool.maintain(rows, layouts, ledger, rows.where("cand_id % 17 = 0")).select("cand_id")


@query(f"WITH {sql_lane('cont')} SELECT 'header' AS kind, pos, 1 AS priority FROM image WHERE starts_with(payload, '~H1:') AND pos % 4 <> 0 UNION ALL SELECT 'footer', pos, 0 FROM image WHERE contains(payload, '~E1:') AND pos % 4 <> 0")
def f2_unused(spark, sf_dir):
    image, boundary, _ = _start(spark, sf_dir, "cont")
    return pool.seed(boundary, image.where("pos % 4 = 0")).select("kind", "pos", "priority")


@query("""SELECT l_orderkey AS cand_id, l_linenumber AS slot, l_partkey AS pos, CAST(row_number() OVER (PARTITION BY l_orderkey ORDER BY l_quantity > 40 DESC, CAST(l_quantity AS BIGINT) DESC, l_suppkey % 3, l_partkey % 50, l_partkey, l_linenumber) AS INTEGER) AS rank FROM lineitem""")
def ltr_choice_order(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("cand_id"), F.lit(0).alias("slot"), F.struct("l_partkey", "l_linenumber").alias("pos"), (F.col("l_quantity") > 40).alias("adjacent"), F.col("l_quantity").cast("long").alias("confidence"), (F.col("l_suppkey") % 3).alias("holds"), (F.col("l_partkey") % 50).alias("distance"))
    return pool.choices(li).select("cand_id", F.col("pos.l_linenumber").alias("slot"), F.col("pos.l_partkey").alias("pos"), "rank")


@query("SELECT o_orderkey AS cand_id, CAST(o_custkey % 40 AS BIGINT) AS single, CASE WHEN o_custkey % 40 > 0 THEN CAST(ceil(log2(o_custkey % 40 + 1)) AS BIGINT) ELSE 0 END AS gallop FROM orders")
def ltr_gallop_runs(spark, sf_dir):
    return pool.gallop_calls(table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("cand_id"), (F.col("o_custkey") % 40).alias("n")))


# ---------------------------------------------------------------- scoring


def _scored(spark, sf_dir):
    """Outputs made by damaging the key of the displaced scenario: one of six damages per file."""
    image, truth = lane(spark, sf_dir, "ooo")
    t = truth.join(image, "pos").groupBy("file_id").agg(F.array_sort(F.collect_list(F.struct("logical_block", "pos", F.md5("payload").alias("h")))).alias("b"), F.max("fragmented").alias("fragmented"))
    pos = F.transform("b", lambda x: x.pos)
    breaks = F.filter(F.sequence(F.lit(1), F.size("b") - 1), lambda i: F.get(pos, i) != F.get(pos, i - 1) + 1)
    t = t.withColumn("blocks", F.transform("b", lambda x: x.h)).withColumn("first_break", F.when(F.size("b") > 1, F.get(breaks, 0)))
    sha = F.sha2(F.array_join("blocks", ""), 256)
    t = t.select("file_id", F.lit("framed").alias("type"), F.when(F.col("fragmented"), "split").otherwise("whole").alias("layout"), "blocks", "first_break", sha.alias("sha256"))
    n, kind = F.size("blocks"), F.col("file_id") % 6
    bad = F.lit("x")
    damaged = (
        F.when(kind == 0, F.col("blocks")).when(kind == 1, F.slice("blocks", F.lit(1), F.greatest(F.lit(1), n - 1))).when(kind == 2, F.concat(F.slice("blocks", F.lit(1), n - 1), F.array(bad)))
        .when(kind == 3, F.concat(F.array(bad), F.slice("blocks", F.lit(2), n))).when(kind == 4, F.concat("blocks", F.array(bad)))
    )
    out = t.where(kind < 5).select("file_id", F.lit(1).alias("out_id"), damaged.alias("blocks"))
    return out.withColumn("sha256", F.sha2(F.array_join("blocks", ""), 256)), t


SQL_SCORED = f"""{sql_lane('ooo')},
    t AS (SELECT file_id, count(*) AS n, max(fragmented) AS fragmented FROM image WHERE file_id IS NOT NULL GROUP BY 1),
    br AS (SELECT file_id, min(logical_block) AS first_break FROM (SELECT file_id, logical_block, pos - lag(pos) OVER (PARTITION BY file_id ORDER BY logical_block) AS d FROM image WHERE file_id IS NOT NULL) WHERE d <> 1 GROUP BY 1),
    sc AS (SELECT file_id, 'framed' AS type, CASE WHEN fragmented THEN 'split' ELSE 'whole' END AS layout,
             CASE file_id % 6 WHEN 0 THEN 'complete' WHEN 1 THEN CASE WHEN n = 1 THEN 'complete' ELSE 'partial' END WHEN 2 THEN 'partial' WHEN 3 THEN CASE WHEN n = 1 THEN 'partial' ELSE 'incorrect' END WHEN 4 THEN 'partial' ELSE 'not recovered' END AS class,
             CAST(CASE file_id % 6 WHEN 0 THEN n WHEN 1 THEN greatest(1, n - 1) WHEN 2 THEN n - 1 WHEN 3 THEN 0 WHEN 4 THEN n ELSE 0 END AS BIGINT) AS prefix, first_break
           FROM t LEFT JOIN br USING (file_id))"""


@query(f"WITH {SQL_SCORED} SELECT file_id, type, layout, class, prefix, coalesce(prefix > first_break, false) AS crossed FROM sc")
def scr_best(spark, sf_dir):
    out, truth = _scored(spark, sf_dir)
    return score.best(score.classify(out, truth), truth)


@query(f"""WITH {SQL_SCORED} SELECT type, layout, count(*) AS files, count(*) FILTER (class = 'complete') AS complete, count(*) FILTER (class = 'partial') AS partial, count(*) FILTER (class = 'incorrect') AS incorrect,
    count(*) FILTER (class = 'not recovered') AS not_recovered FROM sc GROUP BY GROUPING SETS ((type, layout), ())""")
def scr_breakdown(spark, sf_dir):
    out, truth = _scored(spark, sf_dir)
    return score.breakdown(score.best(score.classify(out, truth), truth))


@query(f"WITH {SQL_SCORED} SELECT layout, count(*) FILTER (class = 'partial' AND prefix > first_break) AS crossed, count(*) FILTER (class = 'complete') * 1000 // count(*) AS exact_per_mille FROM sc GROUP BY 1")
def scr_first_boundary(spark, sf_dir):
    out, truth = _scored(spark, sf_dir)
    best = score.best(score.classify(out, truth), truth)
    return best.groupBy("layout").agg(F.count_if((F.col("class") == "partial") & F.col("crossed")).alias("crossed"), F.expr("count_if(class = 'complete') * 1000 div count(1)").alias("exact_per_mille"))


# ---------------------------------------------------------------- progress


def _log(spark, sf_dir):
    """Two runs' status samples from purchases: every 50th, with the running count."""
    from pyspark.sql import Window as W

    e = table(spark, sf_dir, "events").where("event_type = 'purchase'").select((F.col("user_id") % 2).alias("run"), (F.unix_timestamp("ts") - F.unix_timestamp(F.lit("2024-01-01 00:00:00"))).alias("t"), "event_id")
    e = e.withColumn("validated", F.row_number().over(W.partitionBy("run").orderBy("t", "event_id")))
    return e.where("validated % 50 = 0").groupBy("run", "t").agg(F.max("validated").alias("validated"))


SQL_LOG = """e AS (SELECT user_id % 2 AS run, CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01')) AS BIGINT) AS t, event_id FROM events WHERE event_type = 'purchase'),
    n AS (SELECT run, t, row_number() OVER (PARTITION BY run ORDER BY t, event_id) AS validated FROM e), log AS (SELECT run, t, max(validated) AS validated FROM n WHERE validated % 50 = 0 GROUP BY 1, 2)"""


@query(f"""WITH {SQL_LOG}, g AS (SELECT run, t FROM (SELECT DISTINCT run FROM log), (SELECT CAST(k * 86400 AS BIGINT) AS t FROM unnest(range(31)) AS u(k))),
    a AS (SELECT g.run, g.t, l.t AS t0, l.validated AS y0 FROM g ASOF LEFT JOIN log l ON g.run = l.run AND g.t >= l.t),
    b AS (SELECT a.*, l.t AS t1, l.validated AS y1 FROM a ASOF LEFT JOIN log l ON a.run = l.run AND a.t <= l.t)
    SELECT CAST(t AS DOUBLE) AS t, round(avg(CASE WHEN t0 IS NULL THEN 0.0 WHEN t1 IS NULL OR t1 = t0 THEN y0 ELSE y0 + (y1 - y0) * (t - t0) / (t1 - t0) END), 6) AS validated FROM b GROUP BY 1""")
def prog_curve(spark, sf_dir):
    grid = spark.range(31).select((F.col("id") * 86400).alias("t"))
    return score.curve(_log(spark, sf_dir), grid).withColumn("validated", F.round("validated", 6))


@query(f"""WITH {SQL_LOG}, p AS (SELECT *, lag(t) OVER w AS t0, lag(validated) OVER w AS y0 FROM log WINDOW w AS (PARTITION BY run ORDER BY t))
    SELECT run, round(min(CASE WHEN y0 IS NULL THEN t ELSE t0 + (120.0 - y0) * (t - t0) / (validated - y0) END), 6) AS t FROM p WHERE validated >= 120 AND (y0 < 120 OR y0 IS NULL) GROUP BY run""")
def prog_time_to_n(spark, sf_dir):
    return score.time_to(_log(spark, sf_dir), 120.0).select("run", F.round("t", 6).alias("t"))


@query("""WITH r AS (SELECT CAST(1 << CAST(user_id % 8 AS INTEGER) AS INTEGER) AS workers, CAST(floor(value * 100) AS BIGINT) + 1000 AS cents FROM events WHERE user_id IS NOT NULL AND value IS NOT NULL),
    m AS (SELECT workers, CAST(sum(cents) AS DOUBLE) / count(*) / 100 AS seconds FROM r GROUP BY 1)
    SELECT workers, round(seconds, 6) AS seconds, round((SELECT seconds FROM m WHERE workers = 1) / seconds, 2) AS speedup FROM m""")
def prog_speedup(spark, sf_dir):
    """Events as repeated runs on 1 to 128 workers that take ten seconds more than their value in cents says."""
    runs = table(spark, sf_dir, "events").where("user_id is not null and value is not null")
    runs = runs.select(F.expr("cast(shiftleft(1, cast(user_id % 8 as int)) as int)").alias("workers"), (F.floor(F.col("value") * 100).cast("long") + 1000).alias("cents"))
    mean = runs.groupBy("workers").agg((F.sum("cents").cast("double") / F.count(F.lit(1)) / 100).alias("seconds"))
    return score.speedup(mean).withColumn("seconds", F.round("seconds", 6))


# ---------------------------------------------------------------- control, output, restart, baselines


@query("SELECT c_custkey AS cand_id, CASE WHEN c_custkey % 9 = 0 OR c_custkey > (SELECT max(c_custkey) FROM customer) - 3 THEN 'done' ELSE 'unknown' END AS status FROM customer WHERE c_custkey % 9 IN (0, 1) AND c_custkey <= (SELECT max(c_custkey) FROM customer) - 3")
def ctl_status(spark, sf_dir):
    rows = _pool(spark, sf_dir)
    top = rows.agg(F.max("cand_id").alias("top"))
    ask = rows.join(F.broadcast(top), F.lit(True)).where("cand_id % 9 in (0, 1) and cand_id <= top - 3")
    control = ask.select(F.lit(0).alias("ts"), F.lit("cancel").alias("cmd"), F.col("cand_id"))
    return persist.poll(rows.where("cand_id % 9 <> 1"), control)[1].select("cand_id", "status")


@query("SELECT doc_id AS file_id, 'validated/text/' || left(sha256('text:' || doc_id), 12) || '-00_' || sha256(text) AS path, sha256(text) AS sha256 FROM documents WHERE text IS NOT NULL")
def out_names(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").where("text is not null")
    return persist.output_names(docs.select(F.lit("text").alias("type"), F.lit("validated").alias("status"), F.lit(0).alias("clone"), F.col("doc_id").alias("file_id"), F.col("text").alias("content")))


@query(TEXTS)
def chk_resume_equal(spark, sf_dir):
    """A run stopped after its first pass, saved, loaded and finished gives what an uninterrupted run gives."""
    image, boundary, _ = _start(spark, sf_dir, "cont")
    first, _, covered = contiguous.fixpoint(image, boundary.where("pos % 2 = 0"))
    folder = f"{shared_dir(spark)}/restart-{spark.sparkContext.applicationId}-{id(image)}"
    persist.save(spark, folder, {"written": first, "covered": covered, "boundary": boundary, "image": image}, {"pass": 1})
    state, _ = persist.load(spark, folder)
    rest = state["boundary"].join(state["written"].select(F.col("header_pos").alias("pos")), "pos", "left_anti")
    more = contiguous.fixpoint(state["image"], rest, state["covered"])[0]
    return recovered_texts(state["written"].unionByName(more))


@query(f"""WITH {sql_lane('gap')}, h AS (SELECT pos, file_id FROM image WHERE starts_with(payload, '~H1:')), f AS (SELECT pos AS f_pos FROM image WHERE contains(payload, '~E1:')),
    s AS (SELECT h.pos, h.file_id, f.f_pos FROM h ASOF JOIN f ON h.pos <= f.f_pos),
    c AS (SELECT s.pos AS header_pos, any_value(s.file_id) AS file_id, string_agg(i.payload, '' ORDER BY i.pos) AS content FROM s JOIN image i ON i.pos BETWEEN s.pos AND s.f_pos GROUP BY 1)
    SELECT c.file_id, left(c.content, length(p.content)) = p.content AS exact FROM c JOIN plan0 p USING (file_id)""")
def base_header_footer(spark, sf_dir):
    """Exactness of header-to-footer copies on the gap scenario: fragmented files fail."""
    image, boundary, _ = _start(spark, sf_dir, "gap")
    got = baseline.header_footer(image, boundary).select(framed.file_number(F.col("content")).alias("file_id"), F.col("content").alias("got"))
    files = framed_files(table(spark, sf_dir, "documents"))
    return got.join(files, "file_id").select("file_id", (F.expr("left(got, length(content))") == F.col("content")).alias("exact"))
