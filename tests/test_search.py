"""Signatures by patterns."""

import re

from pyspark.sql import functions as F

from blockrecover.operators import search


def test_regex_offsets(spark):
    texts = ["", "ab", "xxab12ab", "ab1b22", "no", None, "1ab1", "a" * 50 + "b9"]
    rows = spark.createDataFrame(list(enumerate(texts)), "pos long, payload string")
    spec = search.FormatSpec("p", "", regex="ab?[0-9]*|b[0-9]+")
    got = {(r.pos, r.off) for r in search.literals(rows, [spec]).collect()}
    assert got == {(i, m.start()) for i, t in enumerate(texts) for m in re.finditer(spec.regex, t or "")}
    assert search.literals(rows.where(F.lit(False)), [spec]).count() == 0
