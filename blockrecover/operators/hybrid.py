"""Work shared with another tool: its log becomes coverage, the engine recovers from what is left, the rest is handed on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import ledger as L
from .recover import Options, Outcome, recover


def log_of(first_pos: str, last_pos: str):
    """The log line of a file that lies from first to last."""
    return F.concat(F.lit("recovered blocks "), F.col(first_pos).cast("string"), F.lit("-"), F.col(last_pos).cast("string"))


def hybrid(image: DataFrame, log: DataFrame, *, size: int, options: Options | None = None) -> tuple[Outcome, DataFrame]:
    """(the engine's outcome on what the log (value) leaves, the residual image for the next tool). Lines that name no
    blocks are ignored; an empty log leaves the whole image."""
    ledger = L.edit(L.build(image, size=size, dedup=False), L.ingest_log(log))
    left = L.residual(image, ledger)
    out = recover(left, options)
    return out, left.join(out.covered.select("pos").distinct(), "pos", "left_anti")
