"""Validator of the framed text format, wholly in native expressions.

A verdict says whether the start is promising, up to which byte (inclusive) the content is consistent, and whether a
complete file has been seen. Lengths come from the header, so the number of blocks is known from the first one.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.crc import crc_hex
from ..layout import BODY, FOOTER, FRAME, HEADER
from ..plans import once


def body_length(content: Column) -> Column:
    """Length of the body by the header, null without one."""
    return F.when(F.substring(content, 1, HEADER).rlike(r"^~H1:\d{10}:\d{8}~$"), F.substring(content, 16, 8).cast("long"))


def file_number(content: Column) -> Column:
    return F.substring(content, 5, 10).cast("long")


def frames(body_len: Column) -> Column:
    return F.floor((body_len + BODY - 1) / BODY)


def file_length(body_len: Column) -> Column:
    return (body_len + frames(body_len) * (FRAME - BODY) + HEADER + FOOTER).cast("long")


def block_count(body_len: Column, size: int) -> Column:
    return F.floor((file_length(body_len) + size - 1) / size).cast("long")


def let(value: Column, f) -> Column:
    """f of a value that is made once and stands in the plan once, however often f uses it."""
    return F.get(F.transform(F.array(value), f), 0)


def pieces(content: Column, n: Column) -> Column:
    """The frames' places in a content with a body of n characters, 917 each: bytes where these are its characters, so that a
    frame costs no walk over the whole content. Empty without frames."""
    every = F.sequence(F.lit(0).cast("long"), frames(n) - 1)
    at = lambda i: (F.lit(HEADER) + i * FRAME + 1).cast("int")
    data = content.cast("binary")
    cut = F.when(F.octet_length(content) == F.length(content), F.transform(every, lambda i: F.substring(data, at(i), F.lit(FRAME)).cast("string"))).otherwise(F.transform(every, lambda i: F.substring(content, at(i), F.lit(FRAME))))
    return F.when(frames(n) > 0, cut).when(n.isNotNull(), F.array().cast("array<string>"))


def footer(cut: Column, n: Column) -> Column:
    """The footer that frames ask for; null where their text is no base64."""
    body = F.array_join(F.transform(cut, lambda p, i: F.substring(p, F.lit(10), F.least(F.lit(BODY).cast("long"), n - i * BODY).cast("int"))), "")
    return F.concat(F.lit("~E1:"), F.md5(F.try_to_binary(body, F.lit("base64"))), F.lit("~"))


def footer_of(content: Column) -> Column:
    return let(body_length(content), lambda n: footer(pieces(content, n), n))


def frame_checks(frame: Column, size: Column) -> Column:
    """Whether a text starts with a frame of ``size`` characters that agrees with its checksum."""
    text = F.substring(frame, F.lit(10), size.cast("int"))
    head = F.concat(F.lit("~D"), F.lpad(size.cast("string"), 6, "0"), F.lit(":"))
    return (F.substring(frame, 1, 9) == head) & (F.length(text) == size) & (crc_hex(text) == F.substring(frame, (size + 10).cast("int"), F.lit(8)))


def verdict(content: Column) -> Column:
    """struct(promising, good (leading frames that check), validates_to, validates, file_len)."""

    def judged(x, bad):
        n, count = x.n, frames(x.n)
        foot = n + count * (FRAME - BODY) + HEADER

        def said(good):
            end = F.substring(content, (foot + 1).cast("int"), F.lit(FOOTER)) == footer(x.cut, n)
            whole = F.when(good == count, F.coalesce(end, F.lit(False))).otherwise(False)
            reach = lambda w: F.when(w, foot + FOOTER - 1).when(good == count, foot - 1).otherwise(F.lit(HEADER) + good * FRAME - 1)
            return let(whole, lambda w: F.struct(
                n.isNotNull().alias("promising"), F.coalesce(good, F.lit(0)).cast("long").alias("good"), F.coalesce(reach(w), F.lit(-1)).cast("long").alias("validates_to"), w.alias("validates"), file_length(n).alias("file_len")
            ))

        return let(F.when(bad > 0, bad - 1).otherwise(count), said)

    def checked(x):
        checks = F.transform(x.cut, lambda p, i: frame_checks(p, F.least(F.lit(BODY).cast("long"), x.n - i * BODY)))
        return let(F.array_position(checks, False), lambda bad: judged(x, bad))

    return let(body_length(content), lambda n: let(F.struct(n.alias("n"), pieces(content, n).alias("cut")), checked))


@once
def verdict_of(name: str) -> Column:
    """The verdict on a column by its name."""
    return verdict(F.col(name))


def text_of(content: Column) -> Column:
    """The original text of a valid file, null of any other: the optimizer may ask for texts before it leaves out what
    does not validate, so what is no text of a file must not be decoded."""
    n = body_length(content)
    every = F.sequence(F.lit(0).cast("long"), frames(n) - 1)
    body = F.array_join(F.transform(every, lambda i: F.substring(content, (F.lit(HEADER) + i * FRAME + 10).cast("int"), F.least(F.lit(BODY).cast("long"), n - i * BODY).cast("int"))), "")
    said = F.substring(content, (n + frames(n) * (FRAME - BODY) + HEADER + 5).cast("int"), F.lit(32))
    text = let(F.try_to_binary(body, F.lit("base64")), lambda data: F.when(F.md5(data) == said, F.decode(data, "UTF-8")))
    return F.when(n > 0, text).otherwise("")
