"""The text lane's images in Spark and, independently, in DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..layout import SCENARIOS, build_image, key_digits, order_key, split
from ..plans import ranked
from ..session import snapshot


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lane(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    return build_image(table(spark, sf_dir, "documents"), SCENARIOS[name])


def raw_blocks(docs: DataFrame, size: int = 256) -> DataFrame:
    """doc_id, i, payload: unframed blocks of texts, the last one short."""
    rows = split(docs.select(F.col("doc_id").alias("file_id"), F.coalesce("text", F.lit("")).alias("content")), size, None)
    return rows.select(F.col("file_id").alias("doc_id"), F.col("logical_block").alias("i"), "payload")


def raw_image(spark: SparkSession, sf_dir: str) -> DataFrame:
    """pos, payload over all documents, files in the order of their keys."""
    rows = snapshot(raw_blocks(table(spark, sf_dir, "documents")).withColumn("key", order_key(F.col("doc_id"))), "blocks")
    return ranked(rows, F.substring("key", 1, key_digits(rows.count())), ["key", "i"], "pos").select("pos", "payload", "doc_id", "i")


def covers(image: DataFrame) -> DataFrame:
    """The blocks that ledger examples take as covered."""
    return image.where("pos % 7 = 3").select("pos")


#: Raw image and its ledger facts.
SQL_RAW = """
    r0 AS (SELECT doc_id, CAST(i AS INTEGER) AS i, substr(text, CAST(i * 256 + 1 AS BIGINT), 256) AS payload, md5('42:order:' || doc_id) AS key
           FROM documents, unnest(range(CAST(ceil(length(text) / 256.0) AS BIGINT))) AS u(i)),
    raw AS (SELECT row_number() OVER (ORDER BY key, i) - 1 AS pos, payload, doc_id, i FROM r0),
    raw_ledger AS (SELECT pos, payload, pos % 7 = 3 AS covered, count(*) OVER w > 1 AS dup, count(*) OVER w > 1 AND min(pos) OVER w = pos AS exemplar,
                          payload = repeat('0', 256) AS zero, min(pos) OVER w AS exemplar_pos, count(*) OVER w AS members,
                          CAST(sum(CASE WHEN pos % 7 = 3 THEN 0 ELSE 1 END) OVER w AS BIGINT) AS refcount
                   FROM raw WINDOW w AS (PARTITION BY payload))"""

#: The table of byte steps of CRC-32 by rule, and the checksum of an ASCII text with it.
SQL_CRC_TABLE = "crc_t AS (SELECT list_transform(range(256), lambda n: list_reduce(range(8), lambda c, k: CASE WHEN c & 1 = 1 THEN xor(c >> 1, CAST(3988292384 AS BIGINT)) ELSE c >> 1 END, CAST(n AS BIGINT))) AS t)"


def sql_crc(text: str) -> str:
    chars = f"list_transform(range(1, length({text}) + 1), lambda i: CAST(ascii(substr({text}, i, 1)) AS BIGINT))"
    return f"xor(list_reduce({chars}, lambda c, b: xor(c >> 8, crc_t.t[(xor(c, b) & 255) + 1]), CAST(4294967295 AS BIGINT)), CAST(4294967295 AS BIGINT))"


def sql_noise(*parts: str) -> str:
    name = " || ':' || ".join(parts)
    return " || ".join(f"sha256({name} || ':{k}')" for k in range(4))


def sql_lane(name: str) -> str:
    """CTEs ending in ``image`` (pos, payload, file_id, logical_block, file_len, fragmented) of a scenario."""
    s = SCENARIOS[name]
    hit = lambda x: f"(h % {x[0]} = {x[1]} AND m >= 4)" if x else "false"
    unions = [
        """SELECT CASE WHEN moved THEN host ELSE key END AS k1, CASE WHEN moved THEN 1 ELSE 0 END AS k2, CASE WHEN moved THEN key ELSE '' END AS k3, lb * 2 + 1 AS k4, 0 AS k5,
                  payload, file_id, lb AS logical_block, file_len, has_gap OR has_run OR has_hole AS fragmented FROM kept"""
    ]
    none = "CAST(NULL AS BIGINT), CAST(NULL AS INTEGER), CAST(NULL AS BIGINT), CAST(NULL AS BOOLEAN)"
    if s.gap:
        unions.append(f"SELECT key, 0, '', gap_at * 2, j, {sql_noise(repr('gap'), 'file_id', 'j')}, {none} FROM plan, unnest(range(1, gap_n + 1)) AS u(j) WHERE has_gap")
    if s.padding:
        body = "repeat('0', 256)" if s.padding == "zero" else sql_noise("'rand'", "file_id", "lb", "j")
        unions.append(f"SELECT md5('spot:' || file_id || ':' || lb || ':' || j), 0, '', -1, j, {body}, {none} FROM kept, unnest(range(1, 4)) AS u(j) WHERE CAST('0x' || substr(md5('pad:' || file_id || ':' || lb || ':' || j), 1, 8) AS BIGINT) % 300 < 148")
    return f"""
    {SQL_CRC_TABLE},
    enc AS (SELECT doc_id AS file_id, coalesce(text, '') AS text, base64(encode(coalesce(text, ''))) AS body FROM documents WHERE doc_id IS NOT NULL),
    pieces AS (SELECT file_id, k, substr(body, CAST(k * 900 + 1 AS BIGINT), 900) AS p FROM enc, unnest(range(CAST(ceil(length(body) / 900.0) AS BIGINT))) AS u(k)),
    frames AS (SELECT file_id, k, '~D' || lpad(CAST(length(p) AS VARCHAR), 6, '0') || ':' || p || lpad(lower(to_hex({sql_crc('p')})), 8, '0') AS f FROM pieces, crc_t),
    joined AS (SELECT file_id, string_agg(f, '' ORDER BY k) AS f FROM frames GROUP BY 1),
    files AS (SELECT file_id, '~H1:' || lpad(CAST(file_id AS VARCHAR), 10, '0') || ':' || lpad(CAST(length(body) AS VARCHAR), 8, '0') || '~' || coalesce(f, '') || '~E1:' || md5(text) || '~' AS content
              FROM enc LEFT JOIN joined USING (file_id)),
    plan0 AS (SELECT file_id, content, CAST(length(content) AS BIGINT) AS file_len, CAST(ceil(length(content) / 256.0) AS BIGINT) AS m,
                     CAST('0x' || substr(md5('42:' || file_id), 1, 8) AS BIGINT) AS h, md5('42:order:' || file_id) AS key FROM files),
    plan1 AS (SELECT *, {hit(s.gap)} AS has_gap, {hit(s.displaced)} AS has_run, {hit(s.omitted)} AS has_hole FROM plan0),
    plan2 AS (SELECT *, 1 + h % greatest(1, m - 1) AS gap_at, 1 + (h // 7) % {s.most_gap} AS gap_n, 1 + h % greatest(1, m // 2 - 1) AS run_n, 1 + (h // 10) % greatest(1, m - 1) AS hole_at FROM plan1),
    hosts AS (SELECT file_id, coalesce(lead(key, 4) OVER (ORDER BY key), '~') AS host FROM plan2 WHERE has_run),
    plan AS (SELECT plan2.*, hosts.host, 1 + (h // 10) % greatest(1, m - run_n) AS run_at FROM plan2 LEFT JOIN hosts USING (file_id)),
    kept AS (SELECT plan.*, CAST(lb AS INTEGER) AS lb, rpad(substr(content, CAST(lb * 256 + 1 AS BIGINT), 256), 256, '.') AS payload, has_run AND lb >= run_at AND lb < run_at + run_n AS moved
             FROM plan, unnest(range(m)) AS u(lb) WHERE NOT (has_hole AND lb = hole_at)),
    every AS ({' UNION ALL '.join(unions)}),
    image AS (SELECT row_number() OVER (ORDER BY k1, k2, k3, k4, k5) - 1 AS pos, payload, file_id, logical_block, file_len, fragmented FROM every)"""
