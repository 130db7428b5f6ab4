import zlib

from hypothesis import given, settings
from hypothesis import strategies as st

from blockrecover.functions import crc


@given(st.binary(max_size=300), st.binary(max_size=300))
@settings(max_examples=60, deadline=None)
def test_combination(a, b):
    assert crc.check(a, b)


@given(st.integers(0, 2**32 - 1), st.integers(0, 5000))
@settings(max_examples=40, deadline=None)
def test_inverse_undoes_shift(value, n):
    assert crc.apply_map(crc.inverse_map(n), crc.apply_map(crc.shift_map(n), value)) == value


@given(st.binary(max_size=50), st.binary(min_size=1, max_size=64), st.binary(max_size=50))
@settings(max_examples=40, deadline=None)
def test_required_is_the_missing_blocks_own(p, b, s):
    assert crc.required(zlib.crc32(p + b + s), zlib.crc32(p), len(b), zlib.crc32(s), len(s)) == zlib.crc32(b)


def test_native_shift_by_column(spark):
    from pyspark.sql import functions as F

    rows = [(bytes([i] * (i + 1)).decode("latin-1").encode(), i * 37) for i in range(1, 60)]
    got = spark.createDataFrame(rows, "b binary, n int").select("b", "n", crc.shift(F.crc32("b"), F.col("n"), most=4096).alias("v"), crc.shift(crc.shift(F.crc32("b"), F.col("n"), most=4096), F.col("n"), most=4096, inverse=True).alias("w")).collect()
    for r in got:
        assert r.v == crc.apply_map(crc.shift_map(r.n), zlib.crc32(bytes(r.b)))
        assert r.w == zlib.crc32(bytes(r.b))


def test_long_files_checksums(spark, tmp_path):
    """A file beyond 131,072 bytes: the checksum of its second block and that of the whole, against zlib."""
    from blockrecover.layout import framed_files
    from blockrecover.queries import QUERIES

    docs = spark.createDataFrame([(1, "abcdefgh" * 14_000), (2, "x" * 900)], "doc_id long, text string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    content = {r.file_id: r.content.encode() for r in framed_files(docs).collect()}
    assert len(content[1]) > 1 << 17
    assert {r.file_id: r.crc for r in QUERIES["crc_required"](spark, str(tmp_path)).collect()} == {k: zlib.crc32(x[256:512]) for k, x in content.items()}
    assert {r.file_id: r.crc for r in QUERIES["crc_combine"](spark, str(tmp_path)).collect()} == {k: zlib.crc32(x) for k, x in content.items()}


def test_shift_beyond_its_bound_is_an_error(spark):
    import pytest
    from pyspark.sql import functions as F

    row = spark.range(1).select(F.lit(1).cast("long").alias("v"), F.lit(300).alias("n"))
    assert row.select(crc.shift(F.col("v"), F.col("n"), most=512)).first()[0] == crc.apply_map(crc.shift_map(300), 1)
    with pytest.raises(Exception, match="shift by 256"):
        row.select(crc.shift(F.col("v"), F.col("n"), most=256)).collect()
