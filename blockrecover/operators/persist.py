"""Restart snapshots, operator control and outputs."""

from __future__ import annotations

import json
import uuid

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


POINTER = "number long, version string, facts string, names array<string>"


def versions(spark: SparkSession, folder: str) -> DataFrame:
    """The complete versions of a folder: number, version, facts, names; none where nothing has been saved."""
    try:
        return spark.read.schema(POINTER).parquet(f"{folder}/pointers")
    except AnalysisException as error:
        if error.getCondition() != "PATH_NOT_FOUND":
            raise
        return spark.createDataFrame([], POINTER)


def save(spark: SparkSession, folder: str, tables: dict[str, DataFrame], facts: dict) -> str:
    """Writes a version of the state. Its tables come first, then one appended row that names them: until that row is
    committed, and whatever a lost driver leaves behind, readers see the version before. Nothing is overwritten. One
    writer at a time."""
    version = uuid.uuid4().hex
    number = (versions(spark, folder).agg(F.max("number")).first()[0] or 0) + 1
    for name, df in tables.items():
        df.write.parquet(f"{folder}/{version}/{name}")
    pointer = spark.createDataFrame([(number, version, json.dumps(facts), sorted(tables))], POINTER)
    pointer.coalesce(1).write.mode("append").parquet(f"{folder}/pointers")
    return version


def load(spark: SparkSession, folder: str) -> tuple[dict[str, DataFrame], dict]:
    """The tables and facts of the newest complete version."""
    row = versions(spark, folder).orderBy(F.col("number").desc()).first()
    if row is None:
        raise FileNotFoundError(f"no complete version in {folder}")
    return {n: spark.read.parquet(f"{folder}/{row['version']}/{n}") for n in row["names"]}, json.loads(row["facts"])


def poll(pool: DataFrame, control: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Applies operator commands (ts, cmd, cand_id) at a barrier: the pool without cancelled candidates, and a status
    row per command: done, or unknown for ids that the pool does not hold."""
    cancelled = control.where("cmd = 'cancel'").select("cand_id").distinct()
    known = pool.select(F.col("cand_id").alias("p_id"))
    status = control.join(known, control["cand_id"] == known["p_id"], "left").select("ts", "cmd", "cand_id", F.when(F.col("cmd") != "cancel", "done").when(F.col("p_id").isNotNull(), "done").otherwise("unknown").alias("status"))
    return pool.join(cancelled, "cand_id", "left_anti"), status


def output_names(outputs: DataFrame) -> DataFrame:
    """path of each output (type, status, clone, file_id, content): status and type folders, the id pair and the hash."""
    sha = F.sha2("content", 256)
    ids = F.concat_ws("-", F.substring(F.sha2(F.concat_ws(":", "type", "file_id"), 256), 1, 12), F.lpad(F.col("clone").cast("string"), 2, "0"))
    return outputs.select("file_id", F.concat_ws("/", "status", "type", F.concat(ids, F.lit("_"), sha)).alias("path"), sha.alias("sha256"))


def write_outputs(outputs: DataFrame, folder: str, *, validated_only: bool = True) -> None:
    """Outputs as Parquet in status and type folders."""
    rows = outputs.where("status = 'validated'") if validated_only else outputs
    rows.write.mode("append").partitionBy("status", "type").parquet(folder)
