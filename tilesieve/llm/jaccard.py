"""N-gram Jaccard join: a size-aware heavy-light join over sets of word shingles.

Equal sets are one class. Small sets (light) are joined by enumerating the fixed-size subsets that two
sets of given sizes must share to link; sharing one is proof. Large sets (heavy) are joined by scanning
inverted lists, which hold only the rarest shingles of each set: two sets that link share one of
those. The size at which light ends is chosen by the cost of either side.

What is wanted is each document's component, so lists are scanned in rounds. A hub round checks each
member of a list against one hub of the list; what links is one component from then on. Then every
pair of a list that still lies in two components is checked, whichever they are: no link is lost, and
the pairs within a group of copies are never made.
"""

from __future__ import annotations

import hashlib
import itertools
import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tilesieve.llm.bytewords import Powers, mix, words
from tilesieve.llm.common import discard, frugal, ship, stored, text_bytes, text_slices
from tilesieve.llm.components import components

ship(__name__)

WORDS = 4
#: Two sets link when PERCENT * union <= 100 * intersection.
PERCENT = 85
#: Buckets of the frequency sketch that orders shingles; its size doesn't grow with the corpus.
SKETCH_BITS = 20
SKETCH_CHUNKS = 16
#: Largest set that may be light; the boundary is chosen at or below it.
MOST_LIGHT = 24
HUB_ROUNDS = 2
#: Ids up to this many are sent to all tasks; more are joined by shuffle.
BROADCAST_IDS = 2_000_000
#: Sets of more copies than this are looked up apart from the others; there are few of those, whatever the corpus.
HOT_COPIES = 1_000_000


def needed(total: int, percent: int = PERCENT) -> int:
    """Least intersection of two linked sets whose sizes sum to ``total``."""
    return -(-percent * total // (100 + percent))


def shingle_sets(data: np.ndarray, begins: np.ndarray, powers: Powers, n: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each text, ascending, one text after another, and how many each has.

    A text with fewer than ``n`` words has one shingle, all its words; one without words has none.
    """
    _, _, owner, h = words(data, begins, powers)
    texts = len(begins) - 1
    counts = np.bincount(owner, minlength=texts)
    odd = [np.uint64(int(x) | 1) for x in mix(np.arange(11, 11 + n, dtype=np.uint64))]
    if len(h) >= n:
        m = len(h) - n + 1
        total = np.zeros(m, np.uint64)
        for i in range(n):
            total += h[i : i + m] * odd[i]
        whole = owner[:m] == owner[n - 1 :]
        shingles, who = mix(total[whole]), owner[:m][whole]
    else:
        shingles, who = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    short = np.flatnonzero((counts > 0) & (counts < n))
    if len(short):
        first = np.cumsum(counts) - counts
        value = [mix(np.array([sum(int(h[first[t] + i]) * int(odd[i]) for i in range(counts[t])) + 0x51ED27 * int(counts[t]) & (2**64 - 1)], np.uint64))[0] for t in short]
        shingles, who = np.concatenate([shingles, np.array(value, np.uint64)]), np.concatenate([who, short])
        order = np.argsort(who, kind="stable")
        shingles, who = shingles[order], who[order]
    edge = np.searchsorted(who, np.arange(texts + 1))
    parts = [np.unique(shingles[a:b], sorted=True) for a, b in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)]
    return (np.concatenate(parts) if parts else shingles), np.array([len(p) for p in parts], np.int64)


def _bucket(h: np.ndarray) -> np.ndarray:
    return (mix(h ^ np.uint64(0x2545F4914F6CDD1D)) >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)


def frequency_sketch(docs: DataFrame, n: int = WORDS) -> np.ndarray:
    """How many documents have a shingle in each bucket, over all documents.

    Tasks send compressed counts by chunk; chunks are summed in two steps, so no task or driver holds
    more than a share of tasks, and the driver ends with 2**SKETCH_BITS numbers.
    """
    size = (1 << SKETCH_BITS) // SKETCH_CHUNKS

    @frugal
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        powers, total = Powers(), np.zeros(1 << SKETCH_BITS, np.int64)
        for batch in batches:
            for part in text_slices(batch):
                total += np.bincount(_bucket(shingle_sets(*text_bytes(part.column(0)), powers, n)[0]), minlength=len(total))
        group = TaskContext.get().partitionId() % 64
        blobs = [zlib.compress(total[k * size : (k + 1) * size].astype("<i8").tobytes(), 1) for k in range(SKETCH_CHUNKS)]
        yield pa.RecordBatch.from_arrays([pa.array(range(SKETCH_CHUNKS), pa.int32()), pa.array([group] * SKETCH_CHUNKS, pa.int32()), pa.array(blobs, pa.binary())], names=["chunk", "grp", "counts"])

    def add(part: pa.Table) -> pa.Table:
        total = np.zeros(size, np.int64)
        for blob in part.column("counts"):
            total += np.frombuffer(zlib.decompress(blob.as_py()), "<i8")
        return part.slice(0, 1).set_column(2, "counts", pa.array([zlib.compress(total.tobytes(), 1)], pa.binary()))

    schema = "chunk int, grp int, counts binary"
    some = docs.select("text").mapInArrow(count, schema).groupBy("chunk", "grp").applyInArrow(add, schema)
    out = np.zeros(1 << SKETCH_BITS, np.int64)
    for r in some.groupBy("chunk").applyInArrow(add, schema).collect():
        out[r["chunk"] * size : (r["chunk"] + 1) * size] = np.frombuffer(zlib.decompress(bytes(r["counts"])), "<i8")
    return out


def _digest(shingles: np.ndarray) -> bytes | None:
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest() if len(shingles) else None


def _signatures(docs: DataFrame, sketch: np.ndarray, percent: int, n: int) -> DataFrame:
    """doc_id, size, a digest of the whole set, the rarest shingles in order, and small sets whole."""
    sent = docs.sparkSession.sparkContext.broadcast(np.minimum(sketch, 2**31 - 1).astype(np.int32))

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        powers, freq = Powers(), sent.value
        for batch in batches:
            for part in text_slices(batch):
                sets, counts = shingle_sets(*text_bytes(part.column(1)), powers, n)
                rank = freq[_bucket(sets)]
                digests, prefix, small = [], [], []
                edge = np.concatenate([[0], np.cumsum(counts)]).tolist()
                for a, b in itertools.pairwise(edge):
                    s = sets[a:b]
                    digests.append(_digest(s))
                    keep = b - a - -(-percent * (b - a) // 100) + 1 if b > a else 0
                    prefix.append(s[np.lexsort((s, rank[a:b]))[:keep]].view(np.int64))
                    small.append(s.view(np.int64) if 0 < b - a <= MOST_LIGHT else None)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(counts, pa.int64()), pa.array(digests, pa.binary()), pa.array(prefix, pa.list_(pa.int64())), pa.array(small, pa.list_(pa.int64()))], names=["doc_id", "n", "digest", "prefix", "small"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n bigint, digest binary, prefix array<bigint>, small array<bigint>")


def subset_plan(size: int, percent: int = PERCENT) -> list[tuple[int, int, int]]:
    """(smaller size, larger size, subset size) of the partners that a set of ``size`` can link with."""
    out = []
    for other in range(-(-percent * size // 100), 100 * size // percent + 1):
        c = needed(size + other, percent)
        if other > 0 and c <= min(size, other):
            out.append((min(size, other), max(size, other), c))
    return out


def light_boundary(sizes: dict[int, int], scan_cost: float, percent: int = PERCENT) -> int:
    """The largest light size with the least total cost: subsets to enumerate against lists to scan.

    ``scan_cost`` is what a list entry costs beside a subset row: a shuffle row and its share of
    verification, which moves whole sets.
    """
    light = {s: c * sum(math.comb(s, k) for _, _, k in subset_plan(s, percent)) for s, c in sizes.items()}
    heavy = {s: c * (s - -(-percent * s // 100) + 1) * scan_cost for s, c in sizes.items()}
    cost = {b: sum(light[s] for s in sizes if s <= b) + sum(heavy[s] for s in sizes if s > b) for b in range(MOST_LIGHT + 1)}
    return min(cost, key=lambda b: (cost[b], b))


def _light_edges(classes: DataFrame, boundary: int, percent: int) -> DataFrame:
    """Edges among light classes: those that share a subset of the size their two sizes demand."""

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rep, items in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                keys, sizes = [], []
                for a, b, c in subset_plan(len(items), percent):
                    if b <= boundary:
                        head = a.to_bytes(2, "little") + b.to_bytes(2, "little")
                        for some in itertools.combinations(items, c):
                            keys.append(hashlib.blake2b(head + np.array(some, "<i8").tobytes(), digest_size=16).digest())
                            sizes.append(a == b)
                if keys:
                    yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array([rep] * len(keys), pa.int64()), pa.array([len(items)] * len(keys), pa.int64()), pa.array(sizes, pa.bool_())], names=["key", "rep", "n", "same"])

    rows = classes.where((F.col("n") > 0) & (F.col("n") <= boundary)).select("rep", "small").mapInArrow(run, "key binary, rep bigint, n bigint, same boolean")
    # all members of a key link across its two sizes, so a star joins them; with one size of two present, nothing links
    stars = rows.groupBy("key").agg(F.min("rep").alias("a"), F.count("*").alias("c"), F.min("n").alias("lo"), F.max("n").alias("hi"), F.first("same").alias("same")).where("c > 1 and (same or lo < hi)")
    return rows.join(stars.select("key", "a"), "key").where("rep != a").select("a", F.col("rep").alias("b")).distinct()


def _can_link(a: str, b: str, percent: int) -> Column:
    """Size and position filters for two entries of one list, were this their first common shingle."""
    n, m = F.col(f"{a}_n"), F.col(f"{b}_n")
    need = F.ceil((n + m) * percent / F.lit(100.0 + percent) - F.lit(1e-9))
    return (n * percent <= m * 100) & (m * percent <= n * 100) & (F.least(n - F.col(f"{a}_pos"), m - F.col(f"{b}_pos")) >= need)


def _only(table: DataFrame, ids: DataFrame, column: str) -> DataFrame:
    """Rows of ``table`` whose ``column`` is among ``ids``: by broadcast if those are counted few, else by shuffle."""
    named = ids.select(F.col("doc_id").alias(column))
    return table.join(F.broadcast(named) if named.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS else named, column, "left_semi")


def _named(pairs: DataFrame) -> DataFrame:
    return stored(pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct(), "named")


def _band(n: Column, percent: int) -> Column:
    """Of sets that can link, bands differ by one at most."""
    return F.floor(F.log(n.cast("double")) / math.log(100 / percent) + 1e-9).cast("int")


def _possible(pairs: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """Pairs that their rarest shingles don't rule out.

    Of two sets, one's prefix ends first in the global order; what they share up to there is in both
    prefixes, so the whole intersection is at most the prefixes' plus that set's remainder.
    """
    named = _named(pairs)
    small = stored(_only(classes.select("rep", "n", "prefix"), named, "rep"), "prefixes")
    discard(named)
    left = pairs.join(small.select(F.col("rep").alias("a"), F.col("n").alias("na"), F.col("prefix").alias("pa")), "a")
    both = left.join(small.select(F.col("rep").alias("b"), F.col("n").alias("nb"), F.col("prefix").alias("pb")), "b")
    most = F.size(F.array_intersect("pa", "pb")) + F.greatest(F.col("na") - F.size("pa"), F.col("nb") - F.size("pb"))
    possible = stored(both.where(most * (100 + percent) >= percent * (F.col("na") + F.col("nb"))).select("a", "b"), "possible")
    discard(small)
    return possible


def _linked(pairs: DataFrame, classes: DataFrame, docs: DataFrame, percent: int, n: int, repeats: bool) -> DataFrame:
    """Of distinct pairs (a, b), those whose whole sets link. Only the sets that pairs still name are made and moved."""
    pairs = _possible(pairs, classes, percent)
    named = _named(pairs)
    whole = _sets_of(docs, named, n)
    sets = stored(whole.dropDuplicates(["rep"]) if repeats else whole, "sets")
    left = pairs.join(sets.select(F.col("rep").alias("a"), F.col("s").alias("sa")), "a")
    both = left.join(sets.select(F.col("rep").alias("b"), F.col("s").alias("sb")), "b")
    common = F.size(F.array_intersect("sa", "sb"))
    links = stored(both.where(100 * common >= percent * (F.size("sa") + F.size("sb") - common)).select("a", "b"), "linked")
    for table in (sets, named, pairs):
        discard(table)
    return links


def _sets_of(docs: DataFrame, ids: DataFrame, n: int) -> DataFrame:
    """Whole sets of the documents whose ids are given, from their whole texts."""
    picked = _only(docs.select("doc_id", "text"), ids, "doc_id")

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        powers = Powers()
        for batch in batches:
            for part in text_slices(batch):
                sets, counts = shingle_sets(*text_bytes(part.column(1)), powers, n)
                edge = pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(edge, pa.array(sets.view(np.int64)))], names=["rep", "s"])

    return picked.mapInArrow(run, "rep bigint, s array<bigint>")


def _rooted(postings: DataFrame, edges: DataFrame | None) -> DataFrame:
    """Postings with the component of their class so far."""
    if edges is None:
        return postings.withColumn("root", F.col("rep"))
    roots = components(edges)
    return postings.join(roots.withColumnRenamed("id", "rep"), "rep", "left").withColumn("root", F.coalesce("root", "rep"))


def _digested_classes(docs: DataFrame, percent: int, n: int) -> DataFrame:
    """``near_duplicate_classes`` with the digest of each set, null where it is empty."""
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    sketch = frequency_sketch(docs, n)
    signed = stored(_signatures(docs, sketch, percent, n), "signatures")
    known = signed.where("digest is not null and doc_id is not null")
    grouped = known.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"))
    own = known.select(F.col("doc_id").alias("rep"), F.col("digest").alias("d"), "n", "prefix", "small").dropDuplicates(["rep", "d"])
    classes = stored(grouped.join(own, "rep").where("digest = d").select("digest", "rep", "copies", "n", "prefix", "small"), "classes")

    sizes = {r["n"]: r["c"] for r in classes.where(F.col("n") <= MOST_LIGHT).groupBy("n").agg(F.count("*").alias("c")).collect()}
    boundary = light_boundary(sizes, scan_cost=8.0, percent=percent)
    edges = stored(_light_edges(classes, boundary, percent), "links")

    least = -(-percent * (boundary + 1) // 100)
    place = F.shiftleft(F.col("n"), 31) + F.col("pos")  # size and position in one number: a row less wide to deal
    entries = classes.where(F.col("n") >= least).select("rep", "n", F.posexplode("prefix").alias("pos", "token")).select("token", "rep", place.alias("place"))
    dealt = entries.repartition("token")  # one exchange serves the count and the join
    size, at = F.shiftright("place", 31), F.col("place").bitwiseAND(F.lit((1 << 31) - 1))
    # of two linked sets, the smaller one (or either of equal ones) has its first common shingle this early
    early = size - at >= F.ceil(size * 2 * percent / F.lit(100.0 + percent) - F.lit(1e-9))
    lists = dealt.groupBy("token").agg(F.count("*").alias("c"), F.bool_or(early).alias("early")).where("c > 1 and early").select("token")
    listed = dealt.join(lists, "token").select("token", "rep", size.alias("n"), at.alias("pos"))
    postings = stored(listed.join(classes.select("rep", "copies"), "rep"), "postings")
    repeats = bool(known.groupBy("doc_id").count().where("count > 1").head(1))

    done: list[DataFrame] = []

    def checked(pairs: DataFrame) -> DataFrame:
        named = pairs.where(F.greatest("a_n", "b_n") > boundary).select(F.least("a_rep", "b_rep").alias("a"), F.greatest("a_rep", "b_rep").alias("b")).distinct()
        for before in done:  # a pair is checked once
            named = named.join(before, ["a", "b"], "left_anti")
        done.append(stored(named, "pairs"))
        return _linked(done[-1], classes, docs, percent, n, repeats)

    def side(df: DataFrame, name: str) -> DataFrame:
        return df.select("token", *[F.col(c).alias(f"{name}_{c}") for c in ("rep", "n", "pos", "root")])

    for turn in range(HUB_ROUNDS):
        rooted = stored(_rooted(postings, edges if edges.head(1) else None), "rooted")
        # the hub of a list: the most copied class first, any class by hash in later rounds; lists of one group agree on it
        rank = F.struct(F.col("copies") if turn == 0 else F.lit(0), F.xxhash64(F.lit(turn), "rep"), "rep", "n", "pos", "root")
        hubs = rooted.groupBy("token").agg(F.max(rank).alias("h"), F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 != r1").select("token", *[F.col(f"h.{c}").alias(f"b_{c}") for c in ("rep", "n", "pos", "root")])
        new = checked(side(rooted, "a").join(hubs, "token").where((F.col("a_root") != F.col("b_root")) & _can_link("a", "b", percent)))
        edges = stored(edges.unionByName(new), "links")
        discard(rooted)

    rooted = stored(_rooted(postings, edges if edges.head(1) else None), "rooted")
    # in each list, members outside its largest component meet all members of other components
    shares = rooted.groupBy("token", "root").agg(F.count("*").alias("c"))
    major = shares.groupBy("token").agg(F.max(F.struct("c", "root")).alias("m"), F.count("*").alias("k")).where("k > 1").select("token", F.col("m.root").alias("major"))
    split = stored(rooted.join(major, "token"), "split")
    # and only those of a size they can link with: a band's members meet those of the bands next to it
    near = F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda x: x + _band(F.col("a_n"), percent))).alias("band")
    minor = side(split.where("root != major"), "a").select("*", near)
    other = split.select("token", _band(F.col("n"), percent).alias("band"), *[F.col(c).alias(f"b_{c}") for c in ("rep", "n", "pos", "root", "major")])
    crossed = minor.join(other, ["token", "band"]).where((F.col("a_root") != F.col("b_root")) & ((F.col("b_root") == F.col("b_major")) | (F.col("a_rep") < F.col("b_rep"))) & _can_link("a", "b", percent))
    edges = stored(edges.unionByName(checked(crossed)), "links")  # the last of four tables of links

    named = classes.select("digest", "rep", "copies")
    if edges.head(1):
        named = named.join(components(edges).withColumnRenamed("id", "rep"), "rep", "left").select("digest", "copies", F.coalesce("root", "rep").alias("root"))
    else:
        named = named.select("digest", "copies", F.col("rep").alias("root"))
    named = stored(named, "roots")
    for table in (postings, rooted, split, classes, edges, *done):
        discard(table)
    ids = signed.select("doc_id", F.col("n").alias("n_shingles"), "digest")
    shape = lambda df, root: df.select("doc_id", "n_shingles", "digest", F.when(F.col("doc_id").isNotNull(), root).alias("component_id"))
    # empty sets meet nothing; the most copied sets, a row for each HOT_COPIES documents at most, go to all tasks; the
    # others are dealt by digest, at most so many rows a key
    held = ids.where("digest is not null")
    hot = named.where(F.col("copies") > HOT_COPIES).select("digest", F.col("root").alias("hot"))
    tagged = held.join(F.broadcast(hot), "digest", "left")
    rest = tagged.where("hot is null").join(named.where(F.col("copies") <= HOT_COPIES).select("digest", "root"), "digest", "left")
    found = shape(tagged.where("hot is not null"), F.col("hot")).unionByName(shape(rest, F.coalesce("root", "doc_id")))
    return found.unionByName(shape(ids.where("digest is null"), F.col("doc_id")))


def near_duplicate_classes(docs: DataFrame, *, percent: int = PERCENT, n: int = WORDS) -> DataFrame:
    """``doc_id``, ``n_shingles`` and ``component_id`` of every document.

    A set holds the distinct shingles of ``n`` words of the whole text, A-Z in lower case; fewer words
    are one shingle; null and empty texts have none and link with nothing. Shingles are compared by 64-bit hash. Two documents link when
    percent * union <= 100 * intersection; a component is what links reach, named by its smallest id.
    Rows that repeat an id and text share a class; null ids are kept, with component null; ids are
    taken to name one text each otherwise. An empty table gives no rows; other columns are left out.
    """
    return _digested_classes(docs, percent, n).drop("digest")


def _digests(docs: DataFrame, n: int) -> DataFrame:
    """``docs`` with a last column ``_digest``: that of the row's whole set, null where it is empty."""
    schema = docs.withColumn("_digest", F.lit(None).cast("binary")).schema
    at = docs.columns.index("text")

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        powers = Powers()
        for batch in batches:
            for part in text_slices(batch):
                sets, counts = shingle_sets(*text_bytes(part.column(at)), powers, n)
                edge = np.concatenate([[0], np.cumsum(counts)]).tolist()
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array([_digest(sets[a:b]) for a, b in itertools.pairwise(edge)], pa.binary())], names=[*part.schema.names, "_digest"])

    return docs.mapInArrow(run, schema)


def _one_of_repeated(odd: DataFrame, classes: DataFrame, n: int) -> DataFrame:
    """Of rows that repeat an id and a set, one; of those without an id, one of each set that no known id has.

    Sets without shingles link with nothing, so rows with neither id nor shingles all stay.
    """
    digested = _digests(odd, n)
    known = classes.where("doc_id is not null and digest is not null").select(F.col("digest").alias("_digest"), F.lit(False).alias("_new")).distinct()
    new = digested.join(known, "_digest", "left").where(F.col("doc_id").isNotNull() | F.col("_new").isNull())
    turn = F.row_number().over(Window.partitionBy("doc_id", "_digest").orderBy(F.xxhash64(*odd.columns)))
    lone = F.col("doc_id").isNull() & F.col("_digest").isNull()
    return new.where(lone).select(*odd.columns).unionByName(new.where(~lone).withColumn("_turn", turn).where("_turn = 1").select(*odd.columns))


def keep_one(docs: DataFrame, *, percent: int = PERCENT, n: int = WORDS) -> DataFrame:
    """One document of each component, that of the smallest id, with all columns.

    Of rows that repeat that id and set one stays. Rows without an id are a copy of what has the same set,
    and of each such set one stays, a row with an id first; near copies of them are not looked for.
    """
    classes = stored(_digested_classes(docs, percent, n).select("doc_id", "digest", "component_id"), "digested")
    found = stored(classes.where("doc_id != component_id").select("doc_id").distinct(), "repeated")

    def few(ids: DataFrame) -> DataFrame:
        return F.broadcast(ids) if ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS else ids

    kept = docs.join(few(found), "doc_id", "left_anti").select(*docs.columns)
    twice = stored(classes.where("doc_id = component_id").groupBy("doc_id").count().where("count > 1").select("doc_id"), "twice")
    if not (twice.head(1) or classes.where("doc_id is null").head(1)):
        return kept
    ids = few(twice)
    odd = kept.where("doc_id is null").unionByName(kept.join(ids, "doc_id", "left_semi").select(*docs.columns))
    return kept.where("doc_id is not null").join(ids, "doc_id", "left_anti").select(*docs.columns).unionByName(_one_of_repeated(odd, classes, n))
