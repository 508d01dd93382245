"""Tiles and windows: n-grams at stride n (build) and at stride 1 (query), over characters or tokens.

Character grams cut a text into blocks of n with one linear regular expression; windows glue each block
to the next and take n offsets of that, because ``substring`` is linear in its position. Arrays are exploded
by outer generators, then filtered: an inner one is given a filter on its size, which computes the array twice.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SEPARATOR = "\x1f"
WORDS = re.compile(r"[^ \t\n\r\f]+")


def tokens(text: Column, pattern: str = r"[^ \t\n\r\f]+") -> Column:
    """Tokens of a text; any Column -> array function can take its place."""
    return F.regexp_extract_all(text, F.lit(f"({pattern})"), 1)


def char_blocks(text: Column, n: int, whole: bool = True) -> Column:
    return F.regexp_extract_all(text, F.lit(f"(?s)(.{{{'' if whole else '1,'}{n}}})"), 1)


def tile_grams(df: DataFrame, *, text: str = "text", key: str = "doc_id", n: int = 50, stride: int | None = None, unit: str = "char", where: Column | None = None) -> DataFrame:
    """(key, tile_no, gram): complete n-grams at offsets 0, stride, 2 stride, ... of each text.

    The incomplete tail is no tile; a null text or one shorter than n has none.
    """
    stride = stride or n
    rows = df.where(where) if where is not None else df
    if unit == "char":
        rows = rows.where(F.length(text) >= n)
        if stride == n:
            return rows.select(key, F.posexplode_outer(char_blocks(F.col(text), n)).alias("tile_no", "gram")).where("tile_no is not null")
        return slide_grams(rows, text=text, key=key, n=n).where(F.col("pos") % stride == 0).select(key, (F.col("pos") / stride).cast("int").alias("tile_no"), "gram")
    if unit != "token":
        raise ValueError("unit must be char or token")
    rows = rows.select(key, F.col(text).alias("_w")) if dict(df.dtypes)[text].startswith("array") else rows.select(key, tokens(F.col(text)).alias("_w"))
    rows = rows.where(F.size("_w") >= n)
    starts = F.sequence(F.lit(1), F.size("_w") - n + 1, F.lit(stride))
    return rows.select(key, F.posexplode_outer(F.transform(starts, lambda i: F.array_join(F.slice("_w", i, n), SEPARATOR))).alias("tile_no", "gram")).where("tile_no is not null")


def slide_grams(df: DataFrame, *, text: str = "text", key: str = "doc_id", n: int = 50, unit: str = "char") -> DataFrame:
    """(key, pos, gram): all n-grams at stride 1, positions from 0."""
    if unit == "token":
        out = tile_grams(df, text=text, key=key, n=n, stride=1, unit="token")
        return out.withColumnRenamed("tile_no", "pos")
    blocks = char_blocks(F.col(text), n, whole=False)
    cut = df.where(F.length(text) >= n).select(key, F.length(text).alias("_len"), blocks.alias("_b"))
    glued = cut.select(key, "_len", F.posexplode_outer(F.transform("_b", lambda x, i: F.concat(x, F.coalesce(F.get("_b", i + 1), F.lit(""))))).alias("_j", "_g"))
    span = F.least(F.lit(n - 1), F.col("_len") - n - F.col("_j") * n)
    cells = glued.where(F.col("_len") - n - F.col("_j") * n >= 0).select(key, "_j", "_g", F.explode_outer(F.sequence(F.lit(0), span)).alias("_o"))
    return cells.select(key, (F.col("_j") * n + F.col("_o")).cast("int").alias("pos"), F.substring("_g", F.col("_o") + 1, F.lit(n)).alias("gram"))


def local_grams(text: str | list[str], n: int, stride: int = 1, unit: str = "char") -> list[bytes]:
    """The same grams of one text, or of its tokens, as UTF-8, in a worker."""
    if unit == "token":
        cells = WORDS.findall(text) if isinstance(text, str) else text
        return [SEPARATOR.join(cells[i : i + n]).encode() for i in range(0, len(cells) - n + 1, stride)]
    data = text.encode()
    if len(data) == len(text):
        return [data[i : i + n] for i in range(0, len(data) - n + 1, stride)]
    at = [*np.flatnonzero((np.frombuffer(data, np.uint8) & 0xC0) != 0x80).tolist(), len(data)]
    return [data[at[i] : at[i + n]] for i in range(0, len(at) - n, stride)]


def min_query_length(n: int) -> int:
    """A stored text of this length holds a whole tile wherever the tiles begin."""
    return 2 * n - 1


def guaranteed_hits(length: Column, n: int) -> Column:
    return F.greatest(F.lit(0), F.floor((length - n + 1) / n)).cast("bigint")
