"""Queries over binary formats: documents as files, an image of them, and what contiguous recovery gets back."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..formats.binary import FORMATS
from ..operators import carve
from .lanes import table

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}

_TEXTS = "SELECT doc_id, {label} AS label, sha256(coalesce(text, '')) AS text_sha256 FROM documents WHERE doc_id IS NOT NULL"
_MIXED = "CASE " + " ".join(f"WHEN doc_id % {len(FORMATS)} = {i} THEN '{n}'" for i, n in enumerate(sorted(FORMATS))) + " END"


def recovered(spark, sf_dir, kind: str, padding: str | None = None):
    """doc_id, label, text_sha256 of all files of one image, decoded from recovered blocks."""
    image = carve.binary_image(carve.encoded_files(table(spark, sf_dir, "documents"), kind), padding=padding)
    return carve.texts(carve.outermost(carve.carve(image)[0]))


def _register(name: str, kind: str, padding: str | None, label: str) -> None:
    QUERIES[name] = lambda spark, sf_dir: recovered(spark, sf_dir, kind, padding)
    ORACLE_SQL[name] = _TEXTS.format(label=label)


for _name in sorted(FORMATS):
    _register(f"fmt_{_name}", _name, None, f"'{_name}'")
_register("fmt_mixed", "mixed", None, _MIXED)
_register("fmt_mixed_zero", "mixed", "zero", _MIXED)
_register("fmt_mixed_random", "mixed", "random", _MIXED)


def fmt_exact_by_type(spark, sf_dir):
    """Files recovered exactly, byte for byte, by type: own recovery against copies from signature to signature."""
    files = carve.encoded_files(table(spark, sf_dir, "documents"), "mixed")
    image = carve.binary_image(files, padding="random")
    truth = files.select("type", F.md5("content").alias("h"))
    own = carve.outermost(carve.carve(image)[0]).select(F.md5("content").alias("h")).distinct().withColumn("own", F.lit(1))
    copies = carve.copied(image).select(F.md5("content").alias("h")).distinct().withColumn("copied", F.lit(1))
    rows = truth.join(own, "h", "left").join(copies, "h", "left")
    return rows.groupBy("type").agg(F.count(F.lit(1)).alias("files"), F.count("own").alias("exact"), F.count("copied").alias("exact_copies"))


QUERIES["fmt_exact_by_type"] = fmt_exact_by_type
