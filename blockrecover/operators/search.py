"""Signature search over blocks and the header and footer table (type, kind, pos, off)."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans import next_on_axis


@dataclass(frozen=True)
class FormatSpec:
    """A format's registration. Signatures are literals; ``|`` separates alternatives; a pattern in ``regex`` is used
    where literals cannot say it. ``aligned`` headers start blocks. ``direction`` says which footer ends a file."""

    name: str
    headers: str
    footers: str = ""
    regex: str | None = None
    aligned: bool = True
    direction: str = "forward"
    min_len: int = 0
    max_len: int = 1 << 30
    priority: int = 0
    fragmentable: bool = True
    notes: dict = field(default_factory=dict)

    def literals(self, kind: str) -> list[str]:
        """Alternatives of a signature that reduce to literals."""
        text = self.headers if kind == "header" else self.footers
        return [x for x in text.split("|") if x]


FRAMED = FormatSpec("framed", "~H1:", "~E1:", min_len=61, max_len=1 << 26)


def registry_table(spark, specs: list[FormatSpec]) -> DataFrame:
    return spark.createDataFrame([(s.name, s.min_len, s.max_len, s.literals("header"), s.literals("footer"), s.direction, s.priority, not s.fragmentable) for s in specs], "type string, min_len long, max_len long, headers array<string>, footers array<string>, direction string, priority int, no_fragment boolean")


def hits(payload: Column, literal: str) -> Column:
    """Offsets (from 0) of a literal, found by native search: the pieces between its occurrences give them."""
    pieces = F.split(payload, "(?s)" + _quote(literal))
    step = len(literal)
    # running sum of piece lengths
    ends = F.aggregate(F.slice(pieces, 1, F.greatest(F.size(pieces) - 1, F.lit(0))), F.array().cast("array<int>"), lambda acc, p: F.concat(acc, F.array(F.coalesce(F.get(acc, F.size(acc) - 1) + step, F.lit(0)) + F.length(p))))
    return F.when(payload.contains(literal), ends).otherwise(F.array().cast("array<int>"))


def regex_hits(payload: Column, pattern: str) -> Column:
    """Offsets (from 0) of a pattern's matches: the pieces between matches and the matches themselves give them. The pattern
    must not match the empty text."""
    pieces, found = F.split(payload, pattern, -1), F.regexp_extract_all(payload, F.lit(f"({pattern})"), 1)
    steps = F.zip_with(F.slice(pieces, F.lit(1), F.size(found)), found, lambda p, m: F.struct(F.length(p).alias("p"), F.length(m).alias("m")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out"))
    walked = F.aggregate(steps, start, lambda acc, x: F.struct((acc.at + x.p + x.m).alias("at"), F.concat(acc.out, F.array(acc.at + x.p)).alias("out")))
    return F.when(payload.rlike(pattern), walked.out).otherwise(F.array().cast("array<int>"))


def _quote(literal: str) -> str:
    return "\\Q" + literal + "\\E"


def _marked(offsets: Column, name: str, kind: str) -> Column:
    return F.transform(offsets, lambda o: F.struct(F.lit(name).alias("type"), F.lit(kind).alias("kind"), o.alias("off")))


def literals(image: DataFrame, specs: list[FormatSpec], *, skip: DataFrame | None = None) -> DataFrame:
    """boundary rows (type, kind, pos, off): one pass over the blocks. ``skip`` (pos): blocks known to be zero."""
    rows = image if skip is None else image.join(skip.select("pos"), "pos", "left_anti")
    found = []
    for s in specs:
        for kind in ("header", "footer"):
            for text in s.literals(kind):
                if kind == "header" and s.aligned:
                    found.append(F.when(F.col("payload").startswith(text), F.array(F.struct(F.lit(s.name).alias("type"), F.lit(kind).alias("kind"), F.lit(0).alias("off")))))
                else:
                    found.append(_marked(hits(F.col("payload"), text), s.name, kind))
        if s.regex:  # what literals cannot say
            found.append(_marked(regex_hits(F.col("payload"), s.regex), s.name, "header"))
    every = F.flatten(F.filter(F.array(*found), lambda x: x.isNotNull()))
    return rows.select("pos", F.explode(every).alias("b")).select("b.type", "b.kind", "pos", "b.off")


def straddling(image: DataFrame, literal: str, *, chunk: int = 32_768, size: int = 256) -> DataFrame:
    """pos, off of a literal that starts in one block and ends in the next. Chunks see one halo row of the next."""
    n = len(literal) - 1
    rows = image.select("pos", F.substring("payload", -n, n).alias("tail"), F.substring("payload", 1, n).alias("head"), F.length("payload").alias("size"))
    own = rows.withColumn("chunk", F.expr(f"pos div {chunk}"))
    halo = rows.where(F.col("pos") % chunk == 0).withColumn("chunk", F.expr(f"pos div {chunk} - 1"))
    w = W.partitionBy("chunk").orderBy("pos")
    paired = own.unionByName(halo).withColumn("next", F.lead("head").over(w)).withColumn("next_pos", F.lead("pos").over(w)).where(F.col("next_pos") == F.col("pos") + 1)
    joined = F.concat("tail", "next")
    return paired.where(joined.contains(literal)).select("pos", (F.col("size") - n + F.locate(literal, joined) - 1).alias("off"))


def span_limits(boundary: DataFrame, spec: FormatSpec, block: int) -> DataFrame:
    """header_pos, lo, hi by the configured largest size, ended early by the next header of the type."""
    heads = boundary.where((F.col("type") == spec.name) & (F.col("kind") == "header")).select("pos").distinct()
    most = -(-spec.max_len // block)
    later = next_on_axis(heads.select((F.col("pos") + 1).alias("at"), "pos"), heads.select(F.col("pos").alias("at")), "at", "next_at")
    return later.select(F.col("pos").alias("header_pos"), F.col("pos").alias("lo"), F.least(F.coalesce("next_at", F.lit(1 << 62)), F.col("pos") + most).alias("hi"))
