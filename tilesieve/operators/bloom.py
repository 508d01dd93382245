"""Tiled Bloom filters as tables of bitmaps: build, probe, merge, count, pack.

Texts are cut and hashed in one vectorised pass over whole texts (``text_lanes``), so no gram is ever a row
of strings: a build moves bits, a probe two hashes of a window or, with a packed filter, the hits alone.
DataFrames of grams go the way of column expressions, with the same bits.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilesieve.functions.digests import md5_lanes
from tilesieve.functions.grams import WORDS, local_grams, tile_grams
from tilesieve.functions.hashing import bit_positions, lanes, local_lanes, positions_of
from tilesieve.functions.placecodes import coded, decoded
from tilesieve.functions.sizing import BUCKET_BITS, FilterSpec, plan_filter
from tilesieve.functions.text import normalize

#: A filter of at most this many bytes is sent whole to every executor; a larger one is joined.
PACKED_BYTES = 256 << 20
#: A filter of at most this many bytes is built as a whole array in each task.
TASK_BYTES = 32 << 20
#: Grams that a task hashes at once.
SLICE_GRAMS = 1 << 16
#: Characters of texts that a tokenizer is given at once, or that are hashed at once.
SLICE_CHARS = 1 << 18
#: Bytes of places that a task sorts and codes at once, bits of a filter that are set together, lanes worked out at once.
FLUSH_BYTES, UNIT_BITS, STEP_LANES = 256 << 20, 1 << 24, 1 << 14


@dataclass(frozen=True)
class Filter:
    """``table``: (bucket bigint, bitmap binary of 4 KiB); buckets without a set bit are absent.

    ``sent`` remembers the packed form once it was made, so a filter is collected and broadcast once.
    """

    spec: FilterSpec
    table: DataFrame
    sent: dict = field(default_factory=dict, compare=False, repr=False)


def count_tiles(df: DataFrame, *, text: str = "text", n: int = 50, norm: str = "collapse") -> int:
    """Tiles of a corpus, from text lengths alone: one pass, no shuffle, an upper bound of distinct ones."""
    return df.agg(F.sum(F.floor(F.length(normalize(F.col(text), norm)) / n)).alias("t")).first()["t"] or 0


def corpus_filter(df: DataFrame, *, text: str = "text", key: str = "doc_id", fpp: float = 1e-3, spec: FilterSpec | None = None, build: str = "text", cut=None, **geometry) -> Filter:
    """Normalise, tile, size by the number of tiles, and build.

    ``text`` may be an array of tokens, whatever made them, for a filter of ``unit="token"``; name the maker in
    ``tokenizer``, which a probe must share. ``build="text"`` hashes whole texts, the others rows of grams. A costly
    maker is better given as ``cut``, texts to lists of tokens in a worker: it then runs once, where texts are hashed,
    and only the hashes are kept to be counted and set.
    """
    if cut is not None:
        from tilesieve.sources.io import scratch_root

        shape = spec or FilterSpec(**geometry)
        path = f"{scratch_root(df.sparkSession)}/lanes-{uuid.uuid4().hex}"
        text_lanes(normalized(df, shape, text=text, key=key), shape, key=key, stride=shape.stride, cut=cut).select("a", "b").write.parquet(path)
        found = df.sparkSession.read.schema("a bigint, b bigint").parquet(path)
        return _from_lanes(found, spec or plan_filter(found.count(), fpp, **geometry))
    if spec is None:
        spec = corpus_spec(df, text=text, key=key, fpp=fpp, **geometry)
    rows = normalized(df, spec, text=text, key=key)
    if build == "text":
        return _from_lanes(text_lanes(rows, spec, key=key, stride=spec.stride).select("a", "b"), spec)
    return build_filter(tile_grams(rows, key=key, n=spec.n, stride=spec.stride, unit=spec.unit), spec, build=build)


def corpus_spec(df: DataFrame, *, text: str = "text", key: str = "doc_id", fpp: float = 1e-3, **geometry) -> FilterSpec:
    """The size of the filter of a corpus, by its number of tiles."""
    shape = FilterSpec(**geometry)
    if shape.unit == "char" and shape.stride == shape.n:
        items = count_tiles(df, text=text, n=shape.n, norm=shape.norm)
    else:
        items = normalized(df, shape, text=text, key=key).agg(F.sum(_count_of("text", df, shape, text)).alias("t")).first()["t"] or 0
    return plan_filter(items, fpp, **geometry)


def _from_lanes(hashed: DataFrame, spec: FilterSpec) -> Filter:
    if spec.m_bits // 8 <= TASK_BYTES:
        return _from_parts(hashed, spec)
    return _from_coded(hashed, spec, lambda batch: [(batch.column(0).to_numpy(), batch.column(1).to_numpy())])


def sliced_build(df: DataFrame, spec: FilterSpec, use: Callable[[Filter], DataFrame], *, slices: int, text: str = "text", key: str = "doc_id") -> DataFrame:
    """What ``use`` makes of the filter's bitmaps, ``slices`` ranges of buckets one after the other, stored.

    For filters whose bits would be too much to move at once: every range hashes all texts again and moves its bits
    alone, and its shuffle files go before the next range begins.
    """
    from tilesieve.operators.repeats import files_go_at_the_end
    from tilesieve.sources.io import scratch_root

    spark, rows = df.sparkSession, normalized(df, spec, text=text, key=key)
    root, edges = f"{scratch_root(spark)}/slices-{uuid.uuid4().hex}", [spec.buckets * i // slices * BUCKET_BITS for i in range(slices + 1)]
    made = [(low, high) for low, high in zip(edges, edges[1:]) if low < high]
    with files_go_at_the_end(spark):
        for low, high in made:
            out = use(_from_coded(rows, spec, lambda batch: (x[2:] for x in _cut(spec, spec.stride, batch)), low, high))
            out.write.parquet(f"{root}/{low}")
    return spark.read.schema(out.schema).parquet(*[f"{root}/{low}" for low, _ in made])


def _is_array(df: DataFrame, column: str) -> bool:
    return dict(df.dtypes)[column].startswith("array")


def _count_of(column: str, df: DataFrame, spec: FilterSpec, text: str) -> Column:
    """How many grams a normalised text has."""
    c = F.col(column)
    units = F.length(c) if spec.unit == "char" else F.size(c) if _is_array(df, text) else F.regexp_count(c, F.lit(WORDS.pattern))
    return F.greatest(F.lit(0), F.call_function("div", units - spec.n, F.lit(spec.stride)) + 1) * (units >= spec.n).cast("int")


def normalized(df: DataFrame, spec: FilterSpec, *, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, text) with the white space that the filter wants; arrays of tokens stay as they are."""
    return df.select(key, F.col(text).alias("text") if _is_array(df, text) else normalize(F.col(text), spec.norm).alias("text"))


def _values(column: pa.Array, cut) -> Iterator:
    """A column's texts, or what ``cut`` makes of them, some SLICE_CHARS at a time."""
    if cut is None:
        yield from (x.as_py() for x in column)
        return
    part, chars = [], 0
    for x in column:
        part.append(value := x.as_py())
        chars += len(value or "")
        if chars >= SLICE_CHARS:
            yield from cut(part)
            part, chars = [], 0
    yield from cut(part)


def _cut_md5(spec: FilterSpec, stride: int, column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """As ``_cut``, of character grams under plain md5: hashed where they stand, some SLICE_CHARS at a time."""
    step = max(1, SLICE_CHARS // stride) * stride
    pieces: list[str] = []
    rows: list[int] = []
    numbers: list[int] = []

    def flush():
        data = (whole := "".join(pieces)).encode()
        at = np.arange(len(data) + 1) if len(data) == len(whole) else np.append(np.flatnonzero((np.frombuffer(data, np.uint8) & 0xC0) != 0x80), len(data))
        chars = np.array([len(x) for x in pieces])
        n = (chars - spec.n) // stride + 1
        mine = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        begin = np.repeat(np.cumsum(chars) - chars, n) + mine * stride
        return np.repeat(np.array(rows), n), mine + np.repeat(np.array(numbers), n), *md5_lanes(data, at[begin], at[begin + spec.n])

    held = 0
    for j, value in enumerate(column):
        text = value.as_py() or ""
        for i in range(0, len(text) - spec.n + 1, step):  # a long text in stretches that overlap
            pieces.append(text[i : i + step + spec.n - 1])
            rows.append(j), numbers.append(i // stride)
            held += len(pieces[-1])
            if held >= SLICE_CHARS:
                yield flush()
                pieces, rows, numbers, held = [], [], [], 0
    if pieces:
        yield flush()


def _cut(spec: FilterSpec, stride: int, batch: pa.RecordBatch, cut=None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(row, number, lane, lane) of the grams of a batch's second column, some SLICE_GRAMS at a time."""
    if spec.unit == "char" and spec.hash == "md5" and not spec.salt and cut is None:
        yield from _cut_md5(spec, stride, batch.column(1))
        return
    grams: list[bytes] = []
    rows: list[int] = []
    counts: list[int] = []
    starts: list[int] = []

    def flush():
        n = np.array(counts, np.int64)
        number = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(np.array(starts, np.int64), n)
        return np.repeat(np.array(rows, np.int64), n), number, *local_lanes(grams, spec)

    for j, value in enumerate(_values(batch.column(1), cut)):
        if value is None:
            continue
        mine = local_grams(value, spec.n, stride, spec.unit)
        for at in range(0, len(mine), SLICE_GRAMS):
            part = mine[at : at + SLICE_GRAMS]
            grams += part
            rows.append(j), counts.append(len(part)), starts.append(at)
            if len(grams) >= SLICE_GRAMS:
                yield flush()
                grams, rows, counts, starts = [], [], [], []
    if grams:
        yield flush()


def text_lanes(rows: DataFrame, spec: FilterSpec, *, key: str = "doc_id", stride: int = 1, cut=None) -> DataFrame:
    """(key, pos, a, b): number and two hashes of every gram of the normalised texts (key, text), cut by ``cut`` if given."""
    kind = rows.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, number, a, b in _cut(spec, stride, batch, cut):
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row)), pa.array(number, pa.int32()), pa.array(a), pa.array(b)], names=["k", "pos", "a", "b"])

    return rows.select(F.col(key).alias("k"), "text").mapInArrow(run, f"k {kind}, pos int, a bigint, b bigint").withColumnRenamed("k", key)


def _places_within(spec: FilterSpec, a: np.ndarray, b: np.ndarray, low: int, high: int) -> Iterator[np.ndarray]:
    """The places of all bits of some lanes, less ``low``, that lie below ``high``."""
    span = np.uint64(high - low)
    for at in range(0, len(a), STEP_LANES):
        base, start, jump, size = _bases(spec, a[at : at + STEP_LANES], b[at : at + STEP_LANES])
        p, jump, base, size = start.view(np.uint64), jump.view(np.uint64), (base - low).view(np.uint64), np.uint64(size)
        found, over, within = np.empty_like(p), np.empty_like(p), np.empty(len(p), bool)
        for _ in range(spec.k):
            np.add(p, base, out=found)  # those below ``low`` wrap round to great ones
            np.less(found, span, out=within)
            yield found.compress(within)
            p += jump
            np.subtract(p, size, out=over)  # modulo size: what is below it wraps round too
            np.minimum(p, over, out=p)


def _coder(spec: FilterSpec, lanes_of: Callable[[pa.RecordBatch], Iterator[tuple[np.ndarray, np.ndarray]]], low: int, high: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = np.dtype(np.uint32 if high - low <= 1 << 32 else np.uint64)
        held = np.empty(max(STEP_LANES, min(FLUSH_BYTES // kind.itemsize, (high - low) // 4)), kind)
        n = 0

        def flush() -> Iterator[pa.RecordBatch]:
            held[:n].sort()
            cuts = np.searchsorted(held[:n], np.arange(0, high - low, UNIT_BITS).astype(held.dtype)).tolist() + [n]
            units = [i for i in range(len(cuts) - 1) if cuts[i] < cuts[i + 1]]
            for at in range(0, len(units), 64):
                some = units[at : at + 64]
                data = [coded(held[cuts[i] : cuts[i + 1]] - held.dtype.type(i * UNIT_BITS)) for i in some]
                yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(data, pa.binary())], names=["unit", "data"])

        for batch in batches:
            for a, b in lanes_of(batch):
                for found in _places_within(spec, a, b, low, high):
                    if n + len(found) > len(held):
                        yield from flush()
                        n = 0
                    held[n : n + len(found)] = found
                    n += len(found)
        if n:
            yield from flush()

    return run


def _setter(first: int):
    """Coded places, a unit's together, to the bitmaps of buckets from ``first`` on."""
    per = UNIT_BITS // BUCKET_BITS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits, now = np.zeros(UNIT_BITS, bool), None

        def done() -> Iterator[pa.RecordBatch]:
            rows = np.packbits(bits, bitorder="little").reshape(per, -1)
            used = np.flatnonzero(rows.any(axis=1))
            yield pa.RecordBatch.from_arrays([pa.array(first + now * per + used, pa.int64()), pa.array([rows[i].tobytes() for i in used], pa.binary())], names=["bucket", "bitmap"])
            bits[:] = False

        for batch in batches:
            for unit, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if unit != now:
                    if now is not None:
                        yield from done()
                    now = unit
                bits[decoded(data.as_buffer())] = True
        if now is not None:
            yield from done()

    return run


def _from_coded(rows: DataFrame, spec: FilterSpec, lanes_of, low: int = 0, high: int | None = None) -> Filter:
    """The bitmaps of a range of places: tasks sort what they set and code the gaps, a byte or two a bit, so that is what moves."""
    sent = rows.mapInArrow(_coder(spec, lanes_of, low, high or spec.m_bits), "unit bigint, data binary")
    return Filter(spec, sent.repartition("unit").sortWithinPartitions("unit").mapInArrow(_setter(low // BUCKET_BITS), "bucket bigint, bitmap binary"))


def _from_bits(bits: DataFrame, spec: FilterSpec) -> Filter:
    """Bitmaps of places ``p``, begun before the shuffle, so it moves bits."""
    number, place = F.bitmap_bucket_number(F.col("p") + 1), F.bitmap_bit_position(F.col("p") + 1)
    return Filter(spec, bits.groupBy((number - 1).alias("bucket")).agg(F.bitmap_construct_agg(place).alias("bitmap")))


def _from_parts(hashed: DataFrame, spec: FilterSpec) -> Filter:
    """Bitmaps of a small filter: each task sets the bits of all its grams in one array."""
    parts = hashed.mapInArrow(_packed_builder(spec), "bucket bigint, bitmap binary")
    return Filter(spec, parts.groupBy("bucket").agg(F.bitmap_or_agg("bitmap").alias("bitmap")))


def build_filter(grams: DataFrame, spec: FilterSpec, gram: str = "gram", *, build: str = "native") -> Filter:
    """Set the bits of all grams, given as rows.

    ``native`` stays in the engine at any size. ``packed`` sets bits in numpy, each task in a whole bit
    array of its own, and ORs those: several times as fast for a filter small enough (dense builds).
    """
    if build == "packed":
        if spec.m_bits // 8 > TASK_BYTES:
            raise ValueError("too large a filter to be built in each task")
        h1, h2 = lanes(F.col(gram), spec)
        return _from_parts(grams.select(h1.alias("a"), h2.alias("b")), spec)
    return _from_bits(grams.select(F.explode_outer(bit_positions(F.col(gram), spec)).alias("p")).where("p is not null"), spec)


def _modulo(x: np.ndarray, m: int) -> np.ndarray:
    """``x % m`` of numbers not negative, by numpy's vectorised division."""
    out = x // m
    out *= m
    return np.subtract(x, out, out=out)


def _bases(spec: FilterSpec, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Bucket start, first place, step and modulus of double hashing, from two lanes."""
    if spec.layout == "blocked":
        return a % spec.buckets * BUCKET_BITS, b % BUCKET_BITS, (a // spec.buckets) % BUCKET_BITS | 1, BUCKET_BITS
    return np.zeros(len(a), np.int64), _modulo(a, spec.m_bits), _modulo(b if spec.hash == "md5" else b | 1, spec.m_bits), spec.m_bits


def _packed_builder(spec: FilterSpec):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.zeros(spec.m_bits // 8, np.uint8)
        for batch in batches:
            base, start, jump, size = _bases(spec, batch.column(0).to_numpy(), batch.column(1).to_numpy())
            for i in range(spec.k):
                p = np.unique(base + (start + i * jump) % size)
                np.bitwise_or.at(bits, p >> 3, np.left_shift(1, p & 7).astype(np.uint8))
        rows = bits.reshape(-1, BUCKET_BITS // 8)
        used = np.flatnonzero(rows.any(axis=1))
        for at in range(0, len(used), 1024):
            some = used[at : at + 1024]
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array([rows[i].tobytes() for i in some], pa.binary())], names=["bucket", "bitmap"])

    return run


def merge_filters(*filters: Filter) -> Filter:
    """The filter of all corpora together: the OR of the bitmaps."""
    first = filters[0]
    table = first.table
    for f in filters[1:]:
        first.spec.require(f.spec)
        table = table.unionByName(f.table)
    merged = table.groupBy("bucket").agg(F.bitmap_or_agg("bitmap").alias("bitmap"))
    return Filter(FilterSpec(**{**first.spec.__dict__, "n_items": sum(f.spec.n_items for f in filters)}), merged)


def _bit(bitmap: Column, place: Column) -> Column:
    byte = F.conv(F.hex(F.substring(bitmap, (place / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("bigint")
    return F.getbit(byte, (place % 8).cast("int")) == 1


def _mode(spec: FilterSpec, mode: str) -> str:
    return mode if mode != "auto" else "packed" if spec.m_bits // 8 <= PACKED_BYTES else "shuffle"


def _looked_up(rows: DataFrame, filter_: Filter, mode: str, bits: Column) -> DataFrame:
    """``rows``, each of distinct lanes ``_a`` and ``_b``, of which all bits are set."""
    spec = filter_.spec
    table = filter_.table.select(F.col("bucket").alias("_bucket"), F.col("bitmap").alias("_bitmap"))
    table = F.broadcast(table) if mode == "broadcast" else table.hint("merge")
    rows = rows.select("_a", "_b", bits.alias("_bits"))
    div = lambda p: F.call_function("div", p, F.lit(BUCKET_BITS))
    if spec.layout == "blocked":  # all bits in one bucket: one look-up
        found = rows.withColumn("_bucket", div(F.element_at("_bits", 1))).join(table, "_bucket")
        return found.where(F.forall("_bits", lambda p: _bit(F.col("_bitmap"), p % BUCKET_BITS))).select("_a", "_b")
    # a window whose first bits are clear is done: most go here, before the other bits are looked up
    for part in (F.slice("_bits", 1, 2), F.slice("_bits", 3, spec.k)):
        cells = rows.select("_a", "_b", "_bits", F.size(part).alias("_n"), F.explode_outer(part).alias("_p")).withColumn("_bucket", div(F.col("_p")))
        met = cells.join(table, "_bucket").where(_bit(F.col("_bitmap"), F.col("_p") % BUCKET_BITS))
        passed = met.groupBy("_a", "_b").agg(F.first("_bits").alias("_bits"), F.count("*").alias("_c"), F.first("_n").alias("_n")).where("_c = _n")
        rows = passed.select("_a", "_b", "_bits")
        if spec.k <= 2:
            break
    return rows.select("_a", "_b")


def _with_hits(rows: DataFrame, filter_: Filter, mode: str) -> DataFrame:
    """``rows`` with ``hit``, by their lanes ``_a`` and ``_b``; equal grams are looked up once, and a null one misses.

    Nothing is joined by a caller's column, so null and repeated keys keep their hits.
    """
    asked = rows.select("_a", "_b").where("_a is not null").distinct()
    hits = _looked_up(asked, filter_, mode, positions_of(F.col("_a"), F.col("_b"), filter_.spec)).withColumn("_hit", F.lit(True))
    return rows.join(hits, ["_a", "_b"], "left").withColumn("hit", F.coalesce("_hit", F.lit(False)))


def probe(windows: DataFrame, filter_: Filter, *, mode: str = "auto", gram: str = "gram") -> DataFrame:
    """``windows`` with ``hit``: whether all bits of its gram are set. Never false for a stored gram.

    ``packed`` sends a small filter to all executors and tests bits in numpy; ``broadcast`` and
    ``shuffle`` join on the bucket; ``auto`` packs a filter of at most PACKED_BYTES and shuffles else.
    Null grams miss; rows alike are kept as they are.
    """
    spec = filter_.spec
    h1, h2 = lanes(F.col(gram), spec)
    if (mode := _mode(spec, mode)) == "packed":
        return windows.withColumn("hit", F.coalesce(packed_probe_udf(filter_, windows.sparkSession)(h1, h2), F.lit(False)))
    return _with_hits(windows.withColumn("_a", h1).withColumn("_b", h2), filter_, mode).select(*windows.columns, "hit")


def probe_texts(df: DataFrame, filter_: Filter, *, text: str = "text", key: str = "doc_id", mode: str = "auto", hits_only: bool = False, hashes: bool = False) -> DataFrame:
    """(key, pos, hit) of all windows of the given texts, or of those that hit; with ``hashes`` also their lanes a, b.

    Texts are cut and hashed whole. With a packed filter they are tested there too, so that ``hits_only``
    makes no row of any other window.
    """
    s, spark = filter_.spec, df.sparkSession
    rows = normalized(df, s, text=text, key=key)
    if _mode(s, mode) != "packed":
        found = text_lanes(rows, s, key=key).withColumnsRenamed({"a": "_a", "b": "_b"})
        out = _with_hits(found, filter_, _mode(s, mode)).select(key, "pos", "hit", *([F.col("_a").alias("a"), F.col("_b").alias("b")] if hashes else []))
        return out.where("hit") if hits_only else out
    sent, kind = packed_broadcast(filter_, spark), rows.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        array = np.frombuffer(sent.value, np.uint8)
        for batch in batches:
            for row, number, a, b in _cut(s, 1, batch):
                hit = _all_set(array, s, a, b)
                if hits_only:
                    row, number, a, b, hit = row[hit], number[hit], a[hit], b[hit], hit[hit]
                if len(row):
                    cells = [batch.column(0).take(pa.array(row)), pa.array(number, pa.int32()), pa.array(hit)]
                    yield pa.RecordBatch.from_arrays(cells + [pa.array(a), pa.array(b)] if hashes else cells, names=["k", "pos", "hit", "a", "b"][: 5 if hashes else 3])

    return rows.select(F.col(key).alias("k"), "text").mapInArrow(run, f"k {kind}, pos int, hit boolean{', a bigint, b bigint' if hashes else ''}").withColumnRenamed("k", key)


def members(rows: DataFrame, spec: FilterSpec, grams: list[str], *, key: str = "doc_id") -> dict[str, bool]:
    """What the filter of the normalised texts would say of a few grams, whatever its size: only bits they ask for are kept."""
    a, b = local_lanes([g.encode() for g in grams], spec)
    base, start, jump, size = _bases(spec, a, b)
    places = np.stack([base + (start + i * jump) % size for i in range(spec.k)])
    asked = np.unique(places)
    rough = np.zeros(1 << 23, bool)  # most places are done after one look
    rough[asked & (len(rough) - 1)] = True
    sent = rows.sparkSession.sparkContext.broadcast((asked, np.packbits(rough)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked, rough = sent.value[0], np.unpackbits(sent.value[1]).view(bool)
        found = np.zeros(len(asked), bool)
        for batch in batches:
            base, start, jump, size = _bases(spec, *(batch.column(c).to_numpy() for c in range(2)))
            for i in range(spec.k):
                p = base + (start + i * jump) % size
                p = p[rough[p & (len(rough) - 1)]]
                at = np.minimum(np.searchsorted(asked, p), len(asked) - 1)
                found[at[asked[at] == p]] = True
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(found))], names=["i"])

    held = text_lanes(rows, spec, key=key, stride=spec.stride).select("a", "b").mapInArrow(run, "i bigint").distinct()
    bits = np.zeros(len(asked), bool)
    bits[[r["i"] for r in held.collect()]] = True  # at most the bits asked for
    return dict(zip(grams, bits[np.searchsorted(asked, places)].all(axis=0).tolist(), strict=True))


def probe_keys(df: DataFrame, column: str, filter_: Filter) -> DataFrame:
    """Rows whose key may be in the filter: a reduction before a join; no matching row is lost."""
    rows = df.withColumn("gram", F.col(column).cast("string"))
    return probe(rows, filter_).where("hit").drop("hit", "gram")


def probe_many(df: DataFrame, filters: dict[str, Filter], **how) -> DataFrame:
    """Hits against several filters, with the filter's name."""
    out = None
    for name, f in filters.items():
        some = probe_texts(df, f, **how).withColumn("filter", F.lit(name))
        out = some if out is None else out.unionByName(some)
    return out


def pack(filter_: Filter) -> bytes:
    """The whole bit array, for a filter that the spec says is small."""
    if "bytes" not in filter_.sent:
        size = filter_.spec.m_bits // 8
        if size > PACKED_BYTES:
            raise ValueError(f"{size} bytes are too many to pack; join the table")
        out = bytearray(size)
        for r in filter_.table.toLocalIterator():
            out[r["bucket"] * (BUCKET_BITS // 8) : (r["bucket"] + 1) * (BUCKET_BITS // 8)] = r["bitmap"]
        filter_.sent["bytes"] = bytes(out)
    return filter_.sent["bytes"]


def packed_broadcast(filter_: Filter, spark):
    """The packed filter, sent to the executors once."""
    if "broadcast" not in filter_.sent:
        filter_.sent["broadcast"] = spark.sparkContext.broadcast(pack(filter_))
    return filter_.sent["broadcast"]


def _all_set(array: np.ndarray, spec: FilterSpec, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Whether all k bits of each pair of lanes are set; a window is done at its first clear bit."""
    base, start, jump, size = _bases(spec, a, b)
    alive = np.arange(len(base))
    for i in range(spec.k):
        p = base[alive] + (start[alive] + i * jump[alive]) % size
        alive = alive[(array[p >> 3] >> (p & 7).astype(np.uint8)) & 1 == 1]
        if not len(alive):
            break
    hit = np.zeros(len(base), bool)
    hit[alive] = True
    return hit


def packed_probe_udf(filter_: Filter, spark):
    """Two hash lanes -> whether all k bits are set in the packed filter; null lanes give null."""
    sent, spec = packed_broadcast(filter_, spark), filter_.spec

    @F.pandas_udf("boolean")
    def test(h1: pd.Series, h2: pd.Series) -> pd.Series:
        known = h1.notna().to_numpy()
        hit = np.zeros(len(h1), bool)
        hit[known] = _all_set(np.frombuffer(sent.value, np.uint8), spec, h1[known].to_numpy(np.int64), h2[known].to_numpy(np.int64))
        return pd.Series(hit)

    return test


class LocalProbe:
    """A packed filter in one process: no job, a text of any size in one vectorised pass."""

    def __init__(self, spec: FilterSpec, data: bytes):
        self.spec, self.bits = spec, np.frombuffer(data, np.uint8)

    def contains(self, gram: str) -> bool:
        return bool(_all_set(self.bits, self.spec, *local_lanes([gram.encode()], self.spec))[0])

    def contains_all(self, grams: list[str]) -> np.ndarray:
        return _all_set(self.bits, self.spec, *local_lanes([g.encode() for g in grams], self.spec))

    def hits(self, text: str | list[str]) -> list[int]:
        """Positions of the windows that hit, of a normalised text or of its tokens."""
        grams = local_grams(text, self.spec.n, 1, self.spec.unit)
        return np.flatnonzero(_all_set(self.bits, self.spec, *local_lanes(grams, self.spec))).tolist() if grams else []

    def chains(self, text: str | list[str]) -> list[tuple[int, int]]:
        """(start, tiles) of the maximal runs of hits one stride apart, longest first."""
        hits, step = set(self.hits(text)), self.spec.stride
        found = []
        for p in sorted(hits):
            if p - step not in hits:
                c = 1
                while p + c * step in hits:
                    c += 1
                found.append((p, c))
        return sorted(found, key=lambda x: (-x[1], x[0]))


def filter_stats(filter_: Filter) -> DataFrame:
    """Bits, set bits, fill, items estimated from the fill, and the rate that the fill implies."""
    m, k = float(filter_.spec.m_bits), float(filter_.spec.k)
    fill = F.col("set_bits") / m
    return filter_.table.agg(F.coalesce(F.sum(F.bitmap_count("bitmap")), F.lit(0)).alias("set_bits")).select(
        F.lit(filter_.spec.m_bits).cast("bigint").alias("m_bits"), F.lit(filter_.spec.k).alias("k"), F.col("set_bits").cast("bigint").alias("set_bits"),
        F.round(fill, 6).alias("fill"), F.round(-m / k * F.log(1 - fill), 2).alias("est_items"), F.round(F.pow(fill, F.lit(k)), 9).alias("est_fpp"),
    )


def filter_digest(filter_: Filter) -> DataFrame:
    """(bucket, set_bits, place_sum): enough to tell two filters apart without binaries."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little")
        many, inner = each.sum(axis=1).astype(np.float64), (each @ np.arange(8)).astype(np.float64)
        ahead = 8.0 * np.arange(BUCKET_BITS // 8)
        for batch in batches:
            sums = []
            for b in batch.column(1):
                read = np.frombuffer(b.as_buffer(), np.uint8)
                bits = many[read]
                sums.append((int(bits.sum()), int(bits @ ahead[: len(bits)] + inner[read].sum())))  # whole numbers below 2 ** 53
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array([x[i] for x in sums], pa.int64()) for i in range(2)]], names=["bucket", "set_bits", "place_sum"])

    return filter_.table.select(F.col("bucket").cast("bigint").alias("bucket"), "bitmap").mapInArrow(run, "bucket bigint, set_bits bigint, place_sum bigint")
