"""Uniform sharding with exact shard sizes, by a hypergeometric communication matrix.

Rows lie in logical blocks (a hash of the row, so a retried task deals the same). How many rows of
each block go to each shard is drawn from the multivariate hypergeometric law that a uniform shuffle
of all rows would give; block rows are then permuted by a seeded hash, cut by those counts, exchanged
by shard and permuted again. Only block counts (one for each ``BLOCK_ROWS`` rows) reach the driver.
Everything on rows is DataFrame code.
"""

from __future__ import annotations

import math
import random

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilesieve.llm.common import stored

BLOCK_ROWS = 200_000
LEAST_BLOCKS = 64


def hypergeometric(draws: int, good: int, total: int, rng: random.Random) -> int:
    """How many of ``good`` among ``total`` rows are in ``draws`` drawn ones: inversion outwards from the mode."""
    low, high = max(0, draws + good - total), min(draws, good)
    if low == high:
        return low
    mode = min(max((draws + 1) * (good + 1) // (total + 2), low), high)
    lg = lambda n, k: math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)
    peak = math.exp(lg(good, mode) + lg(total - good, draws - mode) - lg(total, draws))
    left = rng.random() - peak
    up, down, p_up, p_down = mode, mode, peak, peak
    while left > 0 and (up < high or down > low):
        if up < high:
            p_up *= (good - up) * (draws - up) / ((up + 1) * (total - good - draws + up + 1))
            up += 1
            left -= p_up
            if left <= 0:
                return up
        if down > low:
            p_down *= down * (total - good - draws + down) / ((good - down + 1) * (draws - down + 1))
            down -= 1
            left -= p_down
            if left <= 0:
                return down
        if p_up + p_down < 1e-300:
            break
    return mode


def communication_matrix(counts: list[int], sizes: list[int], seed: int) -> list[list[int]]:
    """Rows from each block (``counts``) to each shard (``sizes``); both sums hold exactly."""
    rng, left, out = random.Random(seed), list(sizes), []
    for n in counts:
        row, need, total = [], n, sum(left)
        for k, room in enumerate(left):
            got = need if k == len(left) - 1 else hypergeometric(need, room, total, rng)
            row.append(got)
            need, total = need - got, total - room
        left = [a - b for a, b in zip(left, row, strict=True)]
        out.append(row)
    return out


def shard_rows(df: DataFrame, shards: int = 8, *, seed: int = 20, key: str = "doc_id", text: str = "text", keep_text: bool = False) -> DataFrame:
    """Deal all rows to ``shards`` shards whose row counts differ by one at most (law ``rows``).

    Returns ``key``, ``size`` (UTF-8 bytes plus 1; a null text has none), ``text_crc32``, ``law``,
    ``shard``, ``slot`` (0, 1, ... within a shard, in a uniformly random order) and ``grown_shard``
    (null: only the law ``key`` has one); ``keep_text`` adds the text. Null keys, repeated rows and
    equal texts are rows like others, spread as the uniform shuffle spreads them; an empty table
    gives an empty result. Columns that the operator doesn't name are left out, whatever their names.
    """
    spark = df.sparkSession
    rows = df.select(F.col(key).alias(key), (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("bigint").alias("size"), F.crc32(F.coalesce(F.col(text), F.lit(""))).alias("text_crc32"), *([F.col(text)] if keep_text else []))
    total = df.count()
    blocks = max(LEAST_BLOCKS, -(-total // BLOCK_ROWS))
    mixed = lambda salt: F.xxhash64(F.lit(seed + salt), F.col(key), "text_crc32", "size")
    dealt = rows.withColumn("block", F.pmod(mixed(0), F.lit(blocks)).cast("int"))
    counts = {r["block"]: r["n"] for r in dealt.groupBy("block").agg(F.count("*").alias("n")).collect()}
    sizes = [total // shards + (k < total % shards) for k in range(shards)]
    random.Random(seed).shuffle(sizes)
    matrix = communication_matrix([counts.get(b, 0) for b in range(blocks)], sizes, seed)
    cuts = [(b, [sum(row[: k + 1]) for k in range(shards)]) for b, row in enumerate(matrix)]
    plan = F.broadcast(spark.createDataFrame(cuts, "block int, cuts array<bigint>"))
    order = Window.partitionBy("block").orderBy(mixed(1), F.col(key), "text_crc32", "size")
    local = dealt.withColumn("at", F.row_number().over(order)).join(plan, "block")
    shard = F.size(F.filter("cuts", lambda c: c < F.col("at"))).cast("int")
    lanes = max(8, -(-total // (shards * BLOCK_ROWS)))
    sent = local.select(key, "size", "text_crc32", *([text] if keep_text else []), shard.alias("shard"), mixed(2).alias("spin"))
    sent = stored(sent.withColumn("lane", F.floor((F.shiftrightunsigned("spin", 1) / F.lit(float(1 << 63))) * lanes).cast("int")), "sharded")
    per = sent.groupBy("shard", "lane").agg(F.count("*").alias("n"))
    before = per.select("shard", "lane", F.coalesce(F.sum("n").over(Window.partitionBy("shard").orderBy("lane").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    within = Window.partitionBy("shard", "lane").orderBy(F.shiftrightunsigned("spin", 1), F.col(key), "text_crc32", "size")
    slot = (F.col("base") + F.row_number().over(within) - 1).cast("bigint")
    return sent.join(F.broadcast(before), ["shard", "lane"]).select(key, "size", "text_crc32", *([text] if keep_text else []), F.lit("rows").alias("law"), "shard", slot.alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def write_shards(df: DataFrame, path: str, shards: int = 8, *, seed: int = 20) -> None:
    """Write the texts in slot order, a folder for each shard."""
    dealt = shard_rows(df, shards, seed=seed, keep_text=True)
    dealt.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
