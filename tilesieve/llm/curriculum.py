"""Mixing sources to target weights under a curriculum that changes over training.

Each source has a weight and a schedule: its share of demand as a function of training time in
[0, 1]. The integral of the schedule, scaled to the source's target, is its cumulative token demand;
a document that begins after ``c`` tokens of its source is due where that demand reaches ``c``, so
inverting it gives the training position. Sorting by position (range partitions, no single task)
gives the training order. All steps are DataFrame code; the only whole-source figure is a prefix sum,
taken over hash lanes of each source, so a source with a third of all rows is still many tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tilesieve.llm.common import stored, word_count

#: Weights of sources in code-point order, null last, repeating.
WEIGHTS = (1.0, 2.0, 3.0)
#: A source gives at most so many times its own size.
MOST_REPEATS = 3
#: Relative demand at the beginning and end of training, in the order of WEIGHTS; linear between.
SCHEDULES = ((1.0, 1.0), (1.5, 0.5), (0.5, 1.5))
LANES = 256
#: Stretches of training time that are sorted each for itself.
STRETCHES = 1 << 14


def source_targets(sized: DataFrame, *, weights: tuple[float, ...] = WEIGHTS, most_repeats: int = MOST_REPEATS) -> DataFrame:
    """Target of each source: a weighted share of all sizes, stopped at ``most_repeats`` times its size.

    What a stopped source leaves is shared again by weight until none is above: the level at which
    that ends is found from running sums over sources ordered by when they stop. A source without
    words gets 0.
    """
    per = sized.groupBy("source").agg(F.sum("size").cast("bigint").alias("source_size"))
    named = per.withColumn("place", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("place") % len(weights) + 1).cast("int"))
    cap = F.col("source_size") * float(most_repeats)
    base = named.withColumn("weight", weight).withColumn("cap", cap).withColumn("stop", F.col("cap") / F.col("weight"))
    ordered = Window.orderBy("stop", "place")
    every = Window.partitionBy()
    upto = ordered.rowsBetween(Window.unboundedPreceding, -1)
    level = (F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(upto), F.lit(0.0))) / (F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(upto), F.lit(0.0)))
    held = base.withColumn("level", level).withColumn("final", F.min(F.when(F.col("level") <= F.col("stop"), F.struct("stop", "place", "level"))).over(every)["level"])
    target = F.when(F.col("source_size") == 0, F.lit(0.0)).otherwise(F.least("cap", F.coalesce(F.col("final"), F.col("stop")) * F.col("weight")))
    return held.select("source", "place", "weight", "source_size", target.alias("target"))


def training_time(share: Column, start: Column, end: Column) -> Column:
    """Where a linear schedule has met ``share`` (0 to 1) of its demand: the inverse of its integral."""
    # a t + (b - a) t^2 / 2 = share (a + b) / 2
    need = share * (start + end)
    root = F.sqrt(F.greatest(start * start + (end - start) * need, F.lit(0.0)))
    return F.least(F.lit(1.0), F.greatest(F.lit(0.0), need / F.greatest(start + root, F.lit(1e-12))))


def plan_mix(docs: DataFrame, *, weights: tuple[float, ...] = WEIGHTS, schedules: tuple[tuple[float, float], ...] = SCHEDULES, most_repeats: int = MOST_REPEATS, seed: int = 11, payload: bool = False) -> DataFrame:
    """What the mix takes of each document, and when.

    Returns ``doc_id``, ``size`` (words), ``source_size``, ``target``,
    ``copies`` (0 to ``most_repeats``), ``taken`` (words, repeats counted) and ``positions`` (the
    training time of each copy), ``spin`` (a hash of id and text, which breaks ties); ``payload`` adds ``row``, a
    struct of all columns of ``docs``, so none can clash. Copy r of a document is taken when the source's words before it, in
    a seeded hash order, plus r times the source's size fall short of the target; so a source's taken
    words end within one document of its target. Null texts and texts without words have size 0 and
    are taken while their source still has demand; a null source is a source of its own; null and
    repeated ids are told apart by their texts, so reruns take the same; an empty table gives no rows.
    """
    row = [F.struct("*").alias("row")] if payload else []
    sized = docs.select(*row, F.col("source").alias("source"), F.col("doc_id").alias("_id"), F.col("text").alias("text"), word_count(F.col("text")).alias("size"))
    spin = F.xxhash64(F.lit(seed), F.col("_id"), F.col("text"))
    sized = sized.withColumn("spin", F.shiftrightunsigned(spin, 1)).drop("text").withColumn("lane", (F.shiftrightunsigned("spin", 55)).cast("int"))
    targets = source_targets(sized, weights=weights, most_repeats=most_repeats)
    lanes = sized.groupBy("source", "lane").agg(F.sum("size").alias("n"))
    before = lanes.select("source", "lane", F.coalesce(F.sum("n").over(Window.partitionBy("source").orderBy("lane").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    table = before.alias("b").join(targets.alias("t"), F.col("b.source").eqNullSafe(F.col("t.source"))).select(F.col("b.source").alias("s"), F.col("b.lane").alias("l"), "base", "place", "source_size", "target")
    within = Window.partitionBy("source", "lane").orderBy("spin", "_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = sized.withColumn("inner", F.coalesce(F.sum("size").over(within), F.lit(0)))
    both = placed.join(table, F.col("source").eqNullSafe(F.col("s")) & (F.col("lane") == F.col("l")))
    at = (F.col("base") + F.col("inner")).cast("double")
    # copies r = 0, 1, ... with at + r * source_size < target
    copies = F.when(F.col("source_size") == 0, F.lit(0)).otherwise(F.greatest(F.lit(0), F.least(F.lit(most_repeats), F.ceil((F.col("target") - at) / F.col("source_size"))))).cast("int")
    pick = lambda side: F.element_at(F.array(*[F.lit(float(s[side])) for s in schedules]), (F.col("place") % len(schedules) + 1).cast("int"))
    out = both.withColumn("at", at).withColumn("copies", copies).withColumn("_a", pick(0)).withColumn("_b", pick(1))
    positions = F.transform(F.sequence(F.lit(0), F.lit(most_repeats - 1)), lambda r: training_time((F.col("at") + r * F.col("source_size")) / F.col("target"), F.col("_a"), F.col("_b")))
    chosen = F.when(F.col("copies") > 0, F.slice(positions, 1, F.col("copies"))).otherwise(F.array().cast("array<double>"))
    return out.select(F.col("_id").alias("doc_id"), "size", "source_size", "target", "copies", (F.col("size") * F.col("copies")).cast("bigint").alias("taken"), chosen.alias("positions"), "spin", *(["row"] if payload else []))


def mixed_documents(docs: DataFrame, *, position: str | None = "position", **how) -> DataFrame:
    """The training stream: a row of ``docs`` for each copy taken, range-sorted by its training time.

    ``position`` names a column for that time; none is added if it is None. Written to files, their names and the
    rows in them keep the order. Nulls, ties, repeated rows and empty tables are as in ``plan_mix``; all columns of
    ``docs`` are kept, whatever their names but ``position``.
    """
    plan = plan_mix(docs, payload=True, **how)
    copies = plan.select("row", "doc_id", "spin", F.explode("positions").alias("at"))
    return copies.repartitionByRange("at", "spin", "doc_id").sortWithinPartitions("at", "spin", "doc_id").select("row.*", *([F.col("at").alias(position)] if position else []))


def ranked_mix(docs: DataFrame, **how) -> DataFrame:
    """``plan_mix`` with ``ranks``: the place (from 0) of each copy in the training order of all copies.

    Copies are range-sorted by training time: STRETCHES of it are sorted each for itself and counted, and what lies
    before a stretch is a running sum of their counts. The plan holds no texts, so only numbers are sorted.
    """
    plan = stored(plan_mix(docs, **how).withColumn("_row", F.monotonically_increasing_id()), "mix")
    copies = plan.select("_row", "doc_id", "spin", F.posexplode("positions").alias("_copy", "at")).withColumn("_stretch", F.least(F.lit(STRETCHES - 1), F.floor(F.col("at") * STRETCHES)).cast("int"))
    sizes = copies.groupBy("_stretch").agg(F.count("*").alias("n"))  # at most STRETCHES rows
    begins = sizes.select("_stretch", F.coalesce(F.sum("n").over(Window.orderBy("_stretch").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("begin"))
    inner = F.row_number().over(Window.partitionBy("_stretch").orderBy("at", "spin", "doc_id", "_row", "_copy"))
    placed = copies.withColumn("inner", inner).join(F.broadcast(begins), "_stretch")
    ranks = placed.groupBy("_row").agg(F.array_sort(F.collect_list(F.struct("_copy", (F.col("begin") + F.col("inner") - 1).alias("rank")))).alias("_r"))
    out = plan.join(ranks, "_row", "left").withColumn("ranks", F.coalesce(F.col("_r.rank"), F.array().cast("array<bigint>")))
    return out.drop("_row", "_r", "spin")
