"""Chains of hits, longest overlaps, spans and the measures on them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilesieve.functions.measures import expected_hits


def joined(left: DataFrame, right: DataFrame, key: str, how: str = "left") -> DataFrame:
    """A join by ``key`` in which a null key meets a null key."""
    other = right.withColumnRenamed(key, "_key")
    return left.join(other, left[key].eqNullSafe(other["_key"]), how).drop("_key")


def islands(df: DataFrame, *, key: list[str], pos: str, step: int) -> DataFrame:
    """Maximal runs of positions exactly ``step`` apart: (key..., start, n_tiles)."""
    lane = Window.partitionBy(*key, F.col(pos) % step).orderBy(pos)
    ranked = df.select(*key, F.col(pos).alias("_p"), (F.col(pos) - step * F.row_number().over(lane)).alias("_island"), (F.col(pos) % step).alias("_lane"))
    return ranked.groupBy(*key, "_lane", "_island").agg(F.min("_p").alias("start"), F.count("*").alias("n_tiles")).select(*key, "start", "n_tiles")


def chain_hits(hits: DataFrame, *, key: str = "doc_id", n: int = 50, stride: int | None = None, texts: DataFrame | None = None) -> DataFrame:
    """(key, start, n_tiles, n_chars): hits one stride apart joined; ``texts`` adds the inferred string."""
    stride = stride or n
    rows = hits.where("hit") if "hit" in hits.columns else hits
    out = islands(rows, key=[key], pos="pos", step=stride).withColumn("n_chars", F.col("n_tiles") * stride + (n - stride))
    if texts is not None:
        out = joined(out, texts.select(key, F.col("text").alias("_t")), key, "inner").withColumn("chain", F.substring("_t", F.col("start") + 1, F.col("n_chars").cast("int"))).drop("_t")
    return out


def longest_chain(chains: DataFrame, docs: DataFrame, *, key: str = "doc_id") -> DataFrame:
    """(key, max_tiles, lcs_chars, start) of every document; none has 0, and ties go to the smaller start."""
    best = chains.groupBy(key).agg(F.max(F.struct("n_tiles", (-F.col("start")).alias("s"), "n_chars")).alias("b"))
    return joined(docs.select(key), best, key).select(key, F.coalesce("b.n_tiles", F.lit(0)).cast("bigint").alias("max_tiles"), F.coalesce("b.n_chars", F.lit(0)).cast("bigint").alias("lcs_chars"), (-F.col("b.s")).cast("bigint").alias("start"))


def top_chains(chains: DataFrame, k: int = 10, *, key: str = "doc_id", per: str = "all", overlapping: bool = True) -> DataFrame:
    """The ``k`` longest chains of all documents or of each; ties by key, then start.

    ``overlapping=False`` keeps longest first and drops those that intersect a kept one.
    """
    if not overlapping:
        chains = disjoint_chains(chains, key=key)
    if per == "doc":
        w = Window.partitionBy(key).orderBy(F.desc("n_tiles"), "start")
        return chains.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)
    return chains.orderBy(F.desc("n_tiles"), key, "start").limit(k)


def disjoint_chains(chains: DataFrame, *, key: str = "doc_id") -> DataFrame:
    """Longest first, then leftmost, each kept if it meets none kept before: one fold over a document's chains."""
    order = F.array_sort(F.collect_list(F.struct((-F.col("n_tiles")).alias("t"), "start", "n_chars")))
    meets = lambda kept, c: F.exists(kept, lambda x: (x["start"] < c["start"] + c["n_chars"]) & (c["start"] < x["start"] + x["n_chars"]))
    per = chains.groupBy(key).agg(order.alias("cs"))
    kept = F.aggregate("cs", F.slice("cs", 1, 0), lambda kept, c: F.when(meets(kept, c), kept).otherwise(F.array_append(kept, c)))
    return per.select(key, F.inline(kept)).select(key, F.col("start"), (-F.col("t")).alias("n_tiles"), "n_chars")


def merged_spans(hits: DataFrame, *, key: str = "doc_id", n: int = 50) -> DataFrame:
    """(key, begin, end): the union of all hit windows, as disjoint ranges."""
    rows = hits.where("hit") if "hit" in hits.columns else hits
    w = Window.partitionBy(key).orderBy("pos")
    before = F.max(F.col("pos") + n).over(w.rowsBetween(Window.unboundedPreceding, -1))
    marked = rows.withColumn("_new", (before.isNull() | (F.col("pos") > before)).cast("int"))
    grouped = marked.withColumn("_g", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return grouped.groupBy(key, "_g").agg(F.min("pos").alias("begin"), (F.max("pos") + n).alias("end")).drop("_g")


def highlight(docs: DataFrame, hits: DataFrame, *, key: str = "doc_id", n: int = 50, mark: tuple[str, str] = ("[[", "]]")) -> DataFrame:
    """(key, spans, marked): every document's hit ranges and its text with them marked."""
    spans = merged_spans(hits, key=key, n=n).groupBy(key).agg(F.array_sort(F.collect_list(F.struct(F.col("begin").cast("int").alias("begin"), F.col("end").cast("int").alias("end")))).alias("spans"))
    shown = joined(docs.select(key, "text"), spans, key).withColumn("spans", F.coalesce("spans", F.array().cast("array<struct<begin:int,end:int>>")))
    state = F.struct(F.lit("").alias("s"), F.lit(0).alias("at"))
    piece = lambda a, x: F.struct(F.concat(a["s"], F.substring("text", a["at"] + 1, x["begin"] - a["at"]), F.lit(mark[0]), F.substring("text", x["begin"] + 1, x["end"] - x["begin"]), F.lit(mark[1])).alias("s"), x["end"].alias("at"))
    done = F.aggregate("spans", state, piece)
    return shown.withColumn("_d", done).select(key, "spans", F.concat("_d.s", F.substring("text", F.col("_d.at") + 1, F.length("text"))).alias("marked"))


def hanging(docs: DataFrame, best: DataFrame, *, key: str = "doc_id") -> DataFrame:
    """(key, head, tail): units before and after a document's longest chain that nothing confirms."""
    return joined(docs.select(key, F.length("text").alias("len")), best.where("max_tiles > 0"), key, "inner").select(key, F.col("start").alias("head"), (F.col("len") - F.col("start") - F.col("lcs_chars")).cast("bigint").alias("tail"))


def expected_overlap(docs: DataFrame, best: DataFrame, *, width: int, group: list[str], key: str = "doc_id", alignment: str = "uniform", min_tiles: int = 1) -> DataFrame:
    """Longest chains of all documents of a group over the hits expected had each been stored: a ratio of sums.

    Documents without hits stay in the denominator; a group that expects nothing has a null ratio. A
    row with all ``group`` columns null is the total.
    """
    rows = joined(docs.select(key, *group, F.length("text").alias("_len")), best.select(key, "max_tiles"), key)
    tiles = F.when(F.col("max_tiles") >= min_tiles, F.col("max_tiles")).otherwise(0)
    per = rows.rollup(*group) if group else rows.groupBy()
    out = per.agg(F.count("*").alias("instances"), F.sum(tiles).cast("bigint").alias("sum_max"), F.sum(expected_hits(F.coalesce("_len", F.lit(0)), width, alignment)).alias("_e"))
    return out.select(*group, "instances", "sum_max", F.round("_e", 4).alias("sum_expected"), F.round(100.0 * F.col("sum_max") / F.nullif(F.col("_e"), F.lit(0.0)), 4).alias("eo_pct"))


def coverage(docs: DataFrame, hits: DataFrame, *, key: str = "doc_id", n: int = 50) -> DataFrame:
    """(key, windows, hit_count, covered_chars) of every document."""
    counts = hits.groupBy(key).agg(F.count("*").alias("windows"), F.count_if("hit").alias("hit_count"))
    covered = merged_spans(hits, key=key, n=n).groupBy(key).agg(F.sum(F.col("end") - F.col("begin")).alias("covered_chars"))
    out = joined(joined(docs.select(key), counts, key), covered, key)
    return out.select(key, *[F.coalesce(c, F.lit(0)).cast("bigint").alias(c) for c in ("windows", "hit_count", "covered_chars")])
