"""The relational operators that the engine is made of, each as a query on the star schema with its SQL twin."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans import asof_join, range_join, ranked
from .lanes import table

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


# ---------------------------------------------------------------- joins


@query("SELECT n_name, count(*) AS n, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def op_join_inner(spark, sf_dir):
    o, c, n = (table(spark, sf_dir, x) for x in ("orders", "customer", "nation"))
    return o.join(c, o["o_custkey"] == c["c_custkey"]).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("o_totalprice") * 100).cast("long")).alias("cents"))


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def op_join_left(spark, sf_dir):
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("orders"))
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left").select("c_custkey", F.coalesce("orders", F.lit(0)).alias("orders"))


@query("SELECT coalesce(s_suppkey, c_custkey) AS key, s_suppkey IS NULL AS no_supplier, c_custkey IS NULL AS no_customer FROM (SELECT s_suppkey * 2 AS s_suppkey FROM supplier) FULL JOIN (SELECT c_custkey * 3 AS c_custkey FROM customer) ON s_suppkey = c_custkey")
def op_join_full(spark, sf_dir):
    s = table(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 2).alias("s"))
    c = table(spark, sf_dir, "customer").select((F.col("c_custkey") * 3).alias("c"))
    return s.join(c, F.col("s") == F.col("c"), "full").select(F.coalesce("s", "c").alias("key"), F.col("s").isNull().alias("no_supplier"), F.col("c").isNull().alias("no_customer"))


@query("SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity >= 49)")
def op_join_semi(spark, sf_dir):
    p, li = table(spark, sf_dir, "part"), table(spark, sf_dir, "lineitem").where("l_quantity >= 49").select("l_partkey")
    return p.join(li, p["p_partkey"] == li["l_partkey"], "left_semi").select("p_partkey")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey IS NOT NULL)")
def op_join_anti(spark, sf_dir):
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_anti").select("c_custkey")


@query("SELECT event_id, s_suppkey FROM (SELECT event_id, event_id * 7 % 1000 AS spot FROM events) JOIN (SELECT s_suppkey, s_suppkey * 13 % 950 AS lo, s_suppkey * 13 % 950 + 1 + s_nationkey AS hi FROM supplier) ON spot >= lo AND spot < hi")
def op_join_range(spark, sf_dir):
    points = table(spark, sf_dir, "events").select("event_id", (F.col("event_id") * 7 % 1000).alias("at"))
    lo = F.col("s_suppkey") * 13 % 950
    ranges = table(spark, sf_dir, "supplier").select("s_suppkey", lo.alias("lo"), (lo + 1 + F.col("s_nationkey")).alias("hi"))
    return range_join(points, ranges, "at", "lo", "hi", width=32).select("event_id", "s_suppkey")


@query("""WITH p AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY 1, 2)
    SELECT e.event_id, p.ts AS at, p.value FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN p ON e.user_id = p.user_id AND e.ts >= p.ts""")
def op_join_asof(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    left = e.where("event_type = 'error'").select("user_id", "ts", "event_id")
    return asof_join(left, e.where("event_type = 'purchase'").select("user_id", "ts", "value"), ["user_id"], "ts", ["value"]).select("event_id", F.col("r_ts").alias("at"), F.col("r_value").alias("value"))


@query("SELECT a.event_id AS error_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOUR")
def op_join_interval(spark, sf_dir):
    """Pairs within six hours: an equi-join on user and six-hour bin, neighbours included."""
    e = table(spark, sf_dir, "events").withColumn("bin", F.floor(F.unix_timestamp("ts") / 21_600))
    a = e.where("event_type = 'error'").select("user_id", F.col("ts").alias("t0"), F.col("event_id").alias("error_id"), F.explode(F.array(F.col("bin"), F.col("bin") + 1)).alias("bin"))
    b = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase_id"), "bin")
    return a.join(b, ["user_id", "bin"]).where((F.col("ts") >= F.col("t0")) & (F.col("ts") <= F.col("t0") + F.expr("INTERVAL 6 HOURS"))).select("error_id", "purchase_id")


@query("SELECT n_name, r_name FROM nation, region WHERE n_regionkey <> r_regionkey")
def op_join_cross(spark, sf_dir):
    n, r = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    return n.join(F.broadcast(r), n["n_regionkey"] != r["r_regionkey"]).select("n_name", "r_name")


@query("SELECT c.c_custkey, o.o_orderkey, CAST(o.k AS INTEGER) AS k FROM customer c JOIN (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) o ON o.o_custkey = c.c_custkey AND k <= 2")
def op_join_lateral(spark, sf_dir):
    """The two largest orders of each customer."""
    o = table(spark, sf_dir, "orders").withColumn("k", F.row_number().over(W.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey"))).where("k <= 2")
    return table(spark, sf_dir, "customer").join(o, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey", "k")


# ---------------------------------------------------------------- aggregation


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity, min(l_shipdate) AS first, max(l_shipdate) AS last FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2")
def op_agg_hash(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").where("l_shipdate <= timestamp'1998-09-02'")
    return li.groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"), F.min("l_shipdate").alias("first"), F.max("l_shipdate").alias("last"))


@query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1")
def op_agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_orderkey").alias("orders"))


@query("SELECT c_mktsegment, coalesce(c_nationkey, -1) AS c_nationkey, count(*) AS n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)")
def op_agg_rollup(spark, sf_dir):
    return table(spark, sf_dir, "customer").rollup("c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n")).withColumn("c_nationkey", F.coalesce("c_nationkey", F.lit(-1)))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n, GROUPING(o_orderstatus) * 2 + GROUPING(o_orderpriority) AS level FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def op_agg_cube(spark, sf_dir):
    return table(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


@query("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1")
def op_agg_pivot(spark, sf_dir):
    got = table(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return got.select("o_orderpriority", *[F.coalesce(x, F.lit(0)).alias(x.lower()) for x in "FOP"])


@query("SELECT p_partkey, 'size' AS measure, CAST(p_size AS BIGINT) AS v FROM part UNION ALL SELECT p_partkey, 'price', CAST(floor(p_retailprice) AS BIGINT) FROM part")
def op_agg_unpivot(spark, sf_dir):
    p = table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("long").alias("size"), F.floor("p_retailprice").cast("long").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "measure", "v")


@query("SELECT event_type, arg_max(event_id, (value, event_id)) AS top, arg_min(event_id, (value, event_id)) AS low, bit_xor(event_id) AS x FROM events GROUP BY 1")
def op_agg_by(spark, sf_dir):
    key = F.struct("value", "event_id")
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.max_by("event_id", key).alias("top"), F.min_by("event_id", key).alias("low"), F.bit_xor("event_id").alias("x"))


@query("SELECT l_returnflag, quantile_cont(CAST(l_quantity AS DOUBLE), 0.5) AS p50, quantile_cont(CAST(l_quantity AS DOUBLE), 0.9) AS p90 FROM lineitem GROUP BY 1")
def op_agg_percentile(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("p50"), F.percentile("l_quantity", 0.9).alias("p90"))


@query("SELECT source, string_agg(lang, ',' ORDER BY lang) AS langs FROM (SELECT DISTINCT source, lang FROM documents) GROUP BY 1")
def op_agg_list(spark, sf_dir):
    return table(spark, sf_dir, "documents").groupBy("source").agg(F.array_join(F.array_sort(F.collect_set("lang")), ",").alias("langs"))


@query("SELECT count(DISTINCT l_partkey) AS exact, true AS close FROM lineitem")
def op_agg_sketch(spark, sf_dir):
    got = table(spark, sf_dir, "lineitem").agg(F.count_distinct("l_partkey").alias("exact"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("about"))
    return got.select("exact", (F.abs(F.col("about") - F.col("exact")) <= F.col("exact") * 0.05).alias("close"))


# ---------------------------------------------------------------- windows


@query("""SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER v AS INTEGER) AS rk, CAST(dense_rank() OVER v AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS nt FROM orders
    WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)""")
def op_win_rank(spark, sf_dir):
    w, v = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"), W.partitionBy("o_custkey").orderBy("o_orderpriority")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"))


@query("SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id, 2) OVER w, -1) AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_win_lag(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select("event_id", F.lag("event_id", 1, -1).over(w).alias("before"), F.lead("event_id", 2, -1).over(w).alias("after"))


@query("SELECT o_orderkey, sum(o_orderkey % 10) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS s FROM orders")
def op_win_rows(spark, sf_dir):
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return table(spark, sf_dir, "orders").select("o_orderkey", F.sum(F.col("o_orderkey") % 10).over(w).alias("s"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(epoch_us(ts) // 1000000 AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
def op_win_range(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("sec").rangeBetween(-86_400, 0)
    return table(spark, sf_dir, "events").withColumn("sec", F.unix_timestamp("ts")).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@query("""WITH g AS (SELECT user_id, event_type, ts, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS island FROM events)
    SELECT user_id, event_type, min(event_id) AS first_id, count(*) AS n FROM g GROUP BY user_id, event_type, island""")
def op_win_islands(spark, sf_dir):
    """Runs of equal event types of a user."""
    a, b = W.partitionBy("user_id").orderBy("ts", "event_id"), W.partitionBy("user_id", "event_type").orderBy("ts", "event_id")
    g = table(spark, sf_dir, "events").withColumn("island", F.row_number().over(a) - F.row_number().over(b))
    return g.groupBy("user_id", "event_type", "island").agg(F.min("event_id").alias("first_id"), F.count(F.lit(1)).alias("n")).drop("island")


@query("SELECT event_id, coalesce(last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS purchase FROM events")
def op_win_last(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return table(spark, sf_dir, "events").select("event_id", F.coalesce(F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w), F.lit(-1)).alias("purchase"))


@query("SELECT event_id, row_number() OVER (ORDER BY ts, event_id) - 1 AS place FROM events")
def op_rank_global(spark, sf_dir):
    """A global rank without one window over everything."""
    return ranked(table(spark, sf_dir, "events"), F.date_trunc("hour", "ts"), ["ts", "event_id"], "place").select("event_id", "place")


# ---------------------------------------------------------------- sets, order, functions


@query("SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45 INTERSECT SELECT l_partkey FROM lineitem WHERE l_quantity < 5")
def op_set_intersect(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem")
    return li.where("l_quantity > 45").select(F.col("l_partkey").alias("k")).intersect(li.where("l_quantity < 5").select("l_partkey"))


@query("SELECT l_suppkey AS k FROM lineitem WHERE l_linenumber = 1 EXCEPT ALL SELECT l_suppkey FROM lineitem WHERE l_linenumber = 2")
def op_set_except(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem")
    return li.where("l_linenumber = 1").select(F.col("l_suppkey").alias("k")).exceptAll(li.where("l_linenumber = 2").select("l_suppkey"))


@query("SELECT user_id AS k FROM events UNION SELECT c_custkey FROM customer")
def op_set_union(spark, sf_dir):
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("k")).union(table(spark, sf_dir, "customer").select("c_custkey")).distinct()


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def op_topk(spark, sf_dir):
    return table(spark, sf_dir, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("SELECT p_partkey, upper(p_name) AS up, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded, replace(p_brand, '#', '-') AS brand, strpos(p_type, ' ') AS gap, md5(p_name) AS md5 FROM part")
def op_str(spark, sf_dir):
    return table(spark, sf_dir, "part").select("p_partkey", F.upper("p_name").alias("up"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"), F.replace("p_brand", F.lit("#"), F.lit("-")).alias("brand"), F.instr("p_type", " ").cast("long").alias("gap"), F.md5("p_name").alias("md5"))


@query("SELECT doc_id, lower(hex(encode(substr(text, 1, 8)))) AS hex, octet_length(encode(text)) AS bytes, sha256(text) AS sha FROM documents WHERE text IS NOT NULL")
def op_bin(spark, sf_dir):
    d = table(spark, sf_dir, "documents").where("text is not null")
    return d.select("doc_id", F.lower(F.hex(F.encode(F.substring("text", 1, 8), "UTF-8"))).alias("hex"), F.octet_length("text").cast("long").alias("bytes"), F.sha2("text", 256).alias("sha"))


@query("SELECT date_trunc('week', ts) AS week, extract('hour' FROM ts) AS hour, count(*) AS n FROM events GROUP BY 1, 2")
def op_date(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.date_trunc("week", "ts").alias("week"), F.hour("ts").cast("long").alias("hour")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT vec_id, CAST(list_sum(list_transform(embedding, lambda x: CAST(floor(x * 1000) AS BIGINT))) AS BIGINT) AS s, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive FROM embeddings")
def op_arr(spark, sf_dir):
    # a float times an integer is a double under ANSI rules, which floors another way where a float rounds up to a whole number
    thousand = F.lit(1000).cast("float")
    v = F.transform(F.filter("embedding", lambda x: x.isNotNull()), lambda x: F.floor(x * thousand).cast("long"))
    s = F.when(F.size(v) > 0, F.aggregate(v, F.lit(0).cast("long"), lambda a, x: a + x))
    return table(spark, sf_dir, "embeddings").select("vec_id", s.alias("s"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@query("SELECT conv_id, string_agg(role || ':' || length(text), ',' ORDER BY turn, role) AS turns FROM conversations WHERE text IS NOT NULL GROUP BY 1")
def op_map(spark, sf_dir):
    c = table(spark, sf_dir, "conversations").where("text is not null").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", F.length("text").alias("n")))).alias("t"))
    return c.select("conv_id", F.array_join(F.transform("t", lambda x: F.concat(x.role, F.lit(":"), x.n.cast("string"))), ",").alias("turns"))


@query("SELECT event_id, json_extract_string(props, '$.page') AS page, json_extract_string(props, '$.ref') AS ref FROM events")
def op_json(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.page").alias("page"), F.get_json_object("props", "$.ref").alias("ref"))


@query("SELECT event_id, CAST(len(json_keys(props)) AS BIGINT) AS keys FROM events")
def op_variant(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.coalesce(F.size(F.json_object_keys("props")), F.lit(0)).cast("long").alias("keys"))


@query("SELECT doc_id, len(regexp_extract_all(lower(text), '[a-z]+')) AS words FROM documents WHERE text IS NOT NULL")
def op_sql_udf(spark, sf_dir):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION br_word_count(t STRING) RETURNS BIGINT RETURN CAST(regexp_count(lower(t), '[a-z]+') AS BIGINT)")
    table(spark, sf_dir, "documents").where("text is not null").createOrReplaceTempView("br_docs")
    return spark.sql("SELECT doc_id, br_word_count(text) AS words FROM br_docs")
