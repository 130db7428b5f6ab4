"""The live view: ranks of blocks that are not covered, both ways."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import ranked

CHUNK = 32_768


def live(ledger: DataFrame, *, phase: str = "C", chunk: int = CHUNK) -> DataFrame:
    """pos, live: phase C ranks all uncovered blocks, phase F one block per content with a free member."""
    rows = ledger.where("not covered")
    if phase == "F":
        rows = rows.where("refcount > 0 and (not dup or exemplar)")
    return ranked(rows.select("pos"), F.expr(f"pos div {chunk}"), ["pos"], "live")


def live_of(positions: DataFrame, covered: DataFrame, *, chunk: int = CHUNK) -> DataFrame:
    """pos, live of positions that are not among ``covered`` (pos)."""
    return ranked(positions.select("pos").join(covered.select("pos"), "pos", "left_anti"), F.expr(f"pos div {chunk}"), ["pos"], "live")
