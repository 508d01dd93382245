"""Connected components of a table of edges, by large-star and small-star rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesieve.llm.common import discard, stored


def components(edges: DataFrame, *, most_rounds: int = 60) -> DataFrame:
    """(id, root) of every id in ``edges`` (a, b); root is the smallest id reachable.

    Each round hangs the larger neighbours of every node from its smallest one, then the same for the
    smaller neighbours; chains halve, so rounds grow with the logarithm of the longest path. Rounds
    pass a table in the shared folder, so no plan grows and a lost executor costs one round's tasks.
    Stops when no edge changes; ``most_rounds`` is an error, not a cut.
    """
    now = stored(edges.where("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    state = None
    for _ in range(most_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # large star: neighbours above u go to the least of u's neighbourhood
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        # small star: u and its neighbours below go to the least of them
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        after = stored(small, "edges")
        mark = after.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        discard(now)
        now = after
        if state == (mark["n"], mark["h"]):
            break
        state = mark["n"], mark["h"]
    else:
        raise RuntimeError("components did not settle")
    roots = now.select(F.col("v").alias("id"), F.col("v").alias("root")).distinct()
    return now.select(F.col("u").alias("id"), F.col("v").alias("root")).unionByName(roots)
