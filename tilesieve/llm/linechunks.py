"""Line dedup by content-defined line chunks; DataFrame functions only.

Each line is hashed, and a rolling hash over the hashes of adjacent lines closes a chunk where it meets
a fixed residue. Boundaries so depend on nearby lines alone: a line put in or taken out moves those next
to it, and the rest fall where they did. A chunk of several lines that occurs again anywhere in the
corpus, byte for byte, is removed from all places but the first; on request with the lines around it
that are repeated too, since a repeated passage seldom begins and ends where chunks do. A passage too
short to hold a whole chunk may still hold the lines whose hash makes a boundary, which do not depend
on what stands before it; these are then looked up as well.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tilesieve.llm.common import discard, stored

#: A chunk closes after one line pair in so many, and never holds more than MOST lines.
MODULUS = 2
MOST = 32
#: Lines that the rolling hash sees.
ROLL = 2
#: Fewest lines of a chunk that is ever removed.
LEAST_LINES = 2
#: A table of at most so many bytes, summed over its rows, is sent to all tasks.
BROADCAST_BYTES = 48 << 20
#: A chunk of more occurrences is looked up apart from the others; there are few of those, whatever the corpus.
HOT_ROWS = 1_000_000
#: Occurrences of one chunk that a task compares.
SALT_ROWS = 500


def line_hashes(text: Column) -> Column:
    return F.transform(F.split(text, "\n", -1), lambda x: F.xxhash64(x))


def _meets(a: Column, b: Column, modulus: int) -> Column:
    return (F.pmod(F.xxhash64(a, b), F.lit(modulus)) == 0) | (a == b)


def _meeting(hashes: Column, modulus: int) -> Column:
    """For each line but the first, whether it and the line before meet the residue."""
    pairs = F.zip_with(F.slice(hashes, F.lit(1), F.size(hashes) - 1), F.slice(hashes, F.lit(2), F.size(hashes) - 1), lambda a, b: _meets(a, b, modulus))
    return F.when(F.size(hashes) > 1, pairs).otherwise(F.array().cast("array<boolean>"))


def closing_lines(hashes: Column, *, modulus: int = MODULUS) -> Column:
    """Positions (from 1) of all lines after which a boundary may follow by content, side by side or not."""
    return F.filter(F.transform(_meeting(hashes, modulus), lambda hit, i: F.when(hit, i + 2)), lambda x: x.isNotNull())


def chunk_ends(hashes: Column, *, modulus: int = MODULUS, most: int = MOST) -> Column:
    """Positions (from 1) of the lines that close a chunk, given all lines' hashes; the last line always does.

    A boundary may follow line i where the hash of lines i-1 and i meets the residue or both are equal; of
    such positions side by side every other one is a boundary, so a chunk has two lines at least. Only what
    a boundary by length or the last content boundary leaves before the next or the end may be one. Where
    there is none for more than ``most`` lines, every ``most`` lines counted from the boundary before close
    a chunk; so no boundary depends on where in the document a passage stands.
    """
    misses = F.filter(F.transform(_meeting(hashes, modulus), lambda hit, i: F.when(~hit, i + 2)), lambda x: x.isNotNull())
    low, high = F.concat(F.array(F.lit(1)), misses), F.array_append(misses, F.size(hashes) + 1)
    met = F.flatten(F.zip_with(low, high, lambda a, b: F.when(b - a > 1, F.sequence(a + 1, b - 1, F.lit(2))).otherwise(F.array().cast("array<int>"))))
    ends = F.array_distinct(F.array_append(met, F.size(hashes)))
    before = F.concat(F.array(F.lit(0)), F.slice(ends, F.lit(1), F.size(ends) - 1))
    return F.flatten(F.zip_with(before, ends, lambda a, b: F.when(b - a > most, F.array_append(F.sequence(a + most, b - 1, F.lit(most)), b)).otherwise(F.array(b))))


def chunks(hashes: Column, **how) -> Column:
    """First line and number of lines of each chunk, in order; together they are all lines."""
    ends = chunk_ends(hashes, **how)
    begins = F.concat(F.array(F.lit(1)), F.transform(F.slice(ends, F.lit(1), F.size(ends) - 1), lambda e: e + 1))
    return F.zip_with(begins, ends, lambda a, b: F.struct(a.alias("line"), (b - a + 1).alias("lines")))


def _few(table: DataFrame, size: Column) -> DataFrame:
    """Sent to all tasks if the bytes of its rows are summed to be few; joined by shuffle otherwise."""
    return F.broadcast(table) if (table.agg(F.sum(size)).first()[0] or 0) <= BROADCAST_BYTES else table


def _repeats(meta: DataFrame, again: DataFrame) -> DataFrame:
    """Rows of ``meta`` whose chunk is in ``again``, with its count.

    Where ``again`` is large, chunks of more than HOT_ROWS occurrences are sent to all tasks, at most a row for
    so many of ``meta``, so the shuffle of the rest deals no key of more rows than that.
    """
    keys = ["h1", "h2"]
    if again.count() * 64 <= BROADCAST_BYTES:
        return meta.join(F.broadcast(again), keys)
    hot = again.where(F.col("n") > HOT_ROWS)
    tagged = meta.join(F.broadcast(hot), keys, "left")
    rest = tagged.where("n is null").drop("n").join(again.where(F.col("n") <= HOT_ROWS), keys)
    return tagged.where("n is not null").unionByName(rest)


def _around(own: Column, lines: Column, mark: Column) -> Column:
    """What surrounds a chunk, line by line away from it: side, distance, hashes of the whole stretch, the line.

    ``back`` and ``after`` are how many lines it goes. Beyond the next boundary equal lines are equal chunks, which are
    found for themselves; the boundary before needs ROLL more lines, which its pairs see.
    """
    begin, end = mark["line"], mark["line"] + mark["lines"]

    def step(side: int, k: Column) -> Column:
        at = end + k - 1 if side > 0 else begin - k
        stretch = F.slice(own, end, k) if side > 0 else F.slice(own, at, k)
        return F.struct(F.lit(side).alias("side"), k.alias("k"), at.alias("at"), F.xxhash64(mark["h1"], stretch).alias("s1"), F.xxhash64(F.lit(7), mark["h2"], stretch).alias("s2"), F.get(lines, at - 1).alias("body"))

    def steps(side: int, reach: Column) -> Column:
        return F.transform(F.when(reach > 0, F.sequence(F.lit(1), reach)).otherwise(F.array().cast("array<int>")), lambda k: step(side, k))

    return F.concat(steps(-1, F.least(mark["back"], begin - 1)), steps(1, mark["after"]))


def _later(parts: DataFrame, keys: list[str]) -> DataFrame:
    """Rows of equal keys but those at the first place: by id (null first), then line.

    ``n`` is at least the number of rows of a key, and the same for all of them. First places are found with
    partial sums; where they go back to the rows, a key of many rows is dealt to several tasks.
    """
    place = F.struct(F.col("doc_id").isNotNull().alias("known"), "doc_id", "line", "owner")
    lanes = F.ceil(F.col("n") / SALT_ROWS)
    first = parts.groupBy(*keys, "n").agg(F.min(place).alias("first")).withColumn("lane", F.explode(F.sequence(F.lit(0).cast("bigint"), lanes - 1)))
    dealt = parts.withColumn("lane", F.pmod(F.xxhash64("owner", "line"), lanes))
    return dealt.join(first, [*keys, "n", "lane"]).where(~place.eqNullSafe(F.col("first")))


def dedup_chunks(docs: DataFrame, *, least_lines: int = LEAST_LINES, modulus: int = MODULUS, most: int = MOST, extend: bool = False) -> DataFrame:
    """Every document with its repeated chunks removed.

    Returns ``doc_id``, ``text`` (what is left; null stays null), ``n_removed`` (chunks) and
    ``removed_lines``. The first place of a chunk, by id (null first), then line, keeps it; rows that
    repeat one id and text share a place and keep or lose it alike. A chunk whose lines are all blank
    is never removed. Texts without a line break, empty ones among them, are left as they are; an empty
    table gives no rows; other columns are left out, whatever their names.

    ``extend`` looks up the two lines that make each boundary by content, too, whether or not a whole chunk
    repeats; ``n_removed`` then counts such pairs as chunks. It removes with a chunk the lines on both sides that surround it at an earlier place too,
    whichever that is for each line. A line so removed equals, as bytes, one that stands earlier by as
    many lines as its chunk does; the lines between are compared by two hashes.

    Chunks are counted by hash, so no text moves; texts of chunks whose hashes repeat are then
    compared as bytes; what is lost goes back to the documents, by broadcast only if summed small. A document
    is known by two hashes of its id and text.
    """
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").alias("text"))
    owner = F.struct(F.xxhash64("doc_id", "text").alias("a"), F.xxhash64(F.lit(7), F.col("doc_id"), F.col("text")).alias("b")).alias("owner")
    several = F.coalesce(F.col("text").contains("\n"), F.lit(False))
    cut = rows.where(several).select(owner, line_hashes(F.col("text")).alias("hs")).withColumn("cs", chunks(F.col("hs"), modulus=modulus, most=most))
    entry = lambda line, lines, back, after: F.struct(line.alias("line"), lines.alias("lines"), back.alias("back"), after.alias("after"))
    near = F.transform("cs", lambda c, i: entry(c["line"], c["lines"], F.coalesce(F.get("cs", i - 1)["lines"], F.lit(0)) + ROLL, F.coalesce(F.get("cs", i + 1)["lines"], F.lit(0))))
    found = F.filter(near, lambda c: c["lines"] >= least_lines)
    if extend and least_lines <= ROLL:
        cut = cut.withColumn("at", closing_lines(F.col("hs"), modulus=modulus))
        # up to the lines of the pairs before and after, which go on from there; longer gaps have boundaries by length
        closing = F.transform("at", lambda p, i: entry(p - 1, F.lit(ROLL), F.least(p - 1 - F.coalesce(F.get("at", i - 1), F.lit(1)), F.lit(most)), F.least(F.coalesce(F.get("at", i + 1), F.size("hs") + 1) - p - 1, F.lit(most))))
        others = F.filter(found, lambda c: (c["lines"] != ROLL) | ~_meets(F.get("hs", c["line"] - 1), F.get("hs", c["line"]), modulus))
        found = F.concat(others, closing)
    spread = cut.select("owner", "hs", F.inline(found))
    own = F.slice("hs", F.col("line"), F.col("lines"))
    # all hashes equal to that of an empty line: dropped at once; other blank lines are seen with their texts
    meta = stored(spread.where(F.size(F.array_except(own, F.array(F.xxhash64(F.lit(""))))) > 0).select("owner", "line", "lines", "back", "after", F.xxhash64(own).alias("h1"), F.xxhash64(F.lit(7), own).alias("h2")), "chunks")
    again = stored(meta.groupBy("h1", "h2").agg(F.count("*").alias("n")).where("n > 1"), "repeated")
    marks = stored(_repeats(meta, again).groupBy("owner").agg(F.collect_set(F.struct("line", "lines", "back", "after", "h1", "h2", "n")).alias("marks")), "marked")
    lines = F.split("text", "\n", -1)
    held = rows.where(several).withColumn("owner", owner).join(_few(marks, 64 + 64 * F.size("marks")), "owner").withColumn("ls", lines)
    bodies = F.transform("marks", lambda m: F.struct(*[m[c].alias(c) for c in ("line", "lines", "h1", "h2", "n")], F.array_join(F.slice(F.col("ls"), m["line"], m["lines"]), "\n").alias("body")))
    doubled = stored(held.select("doc_id", "owner", F.inline(F.filter(bodies, lambda b: b["body"].rlike(r"[^\s]")))), "doubled")
    lost = stored(_later(doubled, ["h1", "h2", "body"]).select("owner", "line", "lines").distinct(), "lost")
    gone = lost.select("owner", "line", (F.col("line") + F.col("lines")).alias("end"), F.lit(1).alias("chunk"))
    if extend:
        beside = F.flatten(F.transform(F.filter("marks", lambda m: F.array_join(F.slice(F.col("ls"), m["line"], m["lines"]), "\n").rlike(r"[^\s]")), lambda m: F.transform(_around(F.col("hs"), F.col("ls"), m), lambda x: F.struct(m["line"].alias("line"), m["n"].alias("n"), *[x[c].alias(c) for c in ("side", "at", "s1", "s2", "body")]))))
        around = stored(held.withColumn("hs", line_hashes(F.col("text"))).select("doc_id", "owner", F.inline(beside)), "around")
        more = _later(around, ["side", "s1", "s2", "body"]).select("owner", F.col("at").alias("line"), (F.col("at") + 1).alias("end"), F.lit(0).alias("chunk")).distinct()
        gone = gone.unionByName(more)
    # stretches that touch or overlap are one; what is left lies between them
    order = Window.partitionBy("owner").orderBy("line", "end")
    begun = gone.withColumn("apart", F.coalesce(F.col("line") > F.max("end").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(True)))
    whole = begun.withColumn("stretch", F.sum(F.col("apart").cast("int")).over(order.rowsBetween(Window.unboundedPreceding, 0))).groupBy("owner", "stretch").agg(F.min("line").alias("line"), F.max("end").alias("end"), F.sum("chunk").alias("chunk"))
    taken = stored(whole.groupBy("owner").agg(F.array_sort(F.collect_list(F.struct("line", "end"))).alias("gone"), F.sum("chunk").alias("n_removed"), F.sum(F.col("end") - F.col("line")).alias("removed_lines")), "taken")
    for table in (meta, again, marks, doubled, lost, *([around] if extend else [])):
        discard(table)
    joined = rows.where(several).withColumn("owner", owner).join(_few(taken, 64 + 32 * F.size("gone")), "owner", "left")
    starts = F.concat(F.array(F.lit(1)), F.col("gone.end"))
    stops = F.array_append(F.col("gone.line"), F.size(lines) + 1)
    left = F.flatten(F.zip_with(starts, stops, lambda a, b: F.slice(lines, a, b - a)))
    cleaned = joined.select(
        "doc_id",
        F.when(F.col("gone").isNull(), F.col("text")).otherwise(F.array_join(left, "\n")).alias("text"),
        F.coalesce("n_removed", F.lit(0)).cast("bigint").alias("n_removed"),
        F.coalesce("removed_lines", F.lit(0)).cast("bigint").alias("removed_lines"),
    )
    # texts of one line meet no join, so rows alike in id and text, such as nulls, gather nowhere
    return cleaned.unionByName(rows.where(~several).select("doc_id", "text", F.lit(0).cast("bigint").alias("n_removed"), F.lit(0).cast("bigint").alias("removed_lines")))
