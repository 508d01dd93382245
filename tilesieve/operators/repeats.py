"""Exact counts of all n-grams of a corpus without a row a gram: pieces of text meet in buckets and are counted there.

A window belongs to the bucket that the least hash of the k-grams in its head names, so equal windows share one, and
so do most neighbours: what is moved is a piece of text for each run of windows of one bucket, compressed, about two
bytes a window (four, of short heads). Buckets are taken in slices, one job after the other, whose shuffle files go before the next begins.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesieve.sources.io import scratch_root, small_batches

#: Characters that a task hashes at once, and that it cuts into pieces before these are sent.
STEP_CHARS, FLUSH_CHARS = 1 << 19, 1 << 23
#: Windows of a bucket to aim at, and characters of pieces after which repeated ones are put together.
BUCKET_WINDOWS, SQUEEZE_CHARS = 1 << 20, 1 << 22
#: Jobs that the buckets are dealt to.
SLICES = 2
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_BASE, _ODD, _MIX = 0x9E3779B97F4A7C15 & ~7 | 5, np.uint64(0xD6E8FEB86659FD93), np.uint64(0xC2B2AE3D27D4EB4F)
_INVERSE = pow(_BASE, -1, 1 << 64)
_BLOCK = 1 << 12
_TABLES: dict = {}


# -- hashes ------------------------------------------------------------------------------------


def _powers(n: int, base: int) -> np.ndarray:
    """base ** i modulo 2 ** 64 for all i < n."""
    if base not in _TABLES:
        _TABLES[base] = np.multiply.accumulate(np.array([1] + [base] * (_BLOCK - 1), np.uint64))
    if n <= 2 * STEP_CHARS:  # as a task cuts texts: kept
        if len(_TABLES.get((base, "step"), ())) < n:
            _TABLES[base, "step"] = np.multiply.accumulate(np.array([1] + [base] * (2 * STEP_CHARS - 1), np.uint64))
        return _TABLES[base, "step"][:n]
    high = np.full(-(-n // _BLOCK), pow(base, _BLOCK, 1 << 64), np.uint64)
    high[:1] = 1
    return (np.multiply.accumulate(high)[:, None] * _TABLES[base][None, :]).ravel()[:n]


class Sums:
    """Hashes of any stretch of some codes: differences of prefix sums of a polynomial with a random value a character."""

    def __init__(self, codes: np.ndarray):
        if "codes" not in _TABLES:
            x = np.arange(1, 0x110001, dtype=np.uint64) * _ODD
            for _ in range(2):
                x = (x ^ (x >> np.uint64(31))) * _MIX
            _TABLES["codes"] = x ^ (x >> np.uint64(29))
        n = len(codes)
        self.back = _powers(n + 1, _INVERSE)
        self.upto = np.zeros(n + 1, np.uint64)
        np.cumsum(_TABLES["codes"][codes] * _powers(n, _BASE), out=self.upto[1:])

    def all(self, width: int) -> np.ndarray:
        """The hash of each whole window of a width."""
        n = max(0, len(self.upto) - width)
        return (self.upto[width:] - self.upto[:n]) * self.back[:n]

    def at(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        return (self.upto[end] - self.upto[begin]) * self.back[begin]


def _least(values: np.ndarray, width: int) -> np.ndarray:
    """The least of each ``width`` neighbours."""
    k = 1
    while 2 * k <= width and len(values) > k:
        values = np.minimum(values[:-k], values[k:])
        k *= 2
    return np.minimum(values[: len(values) - (width - k)], values[width - k :]) if width > k else values


def grouped(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order that puts equal hashes together, and where in it each group begins."""
    bits = np.uint64(max(1, (len(hashes) - 1).bit_length()))
    packed = (hashes >> bits << bits) | np.arange(len(hashes), dtype=np.uint64)
    packed.sort()
    order = (packed & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)
    found, top = hashes[order], packed >> bits
    odd = np.flatnonzero((top[1:] == top[:-1]) & (found[1:] != found[:-1]))
    for t in np.unique(top[odd]):  # different hashes whose upper bits agree: few
        a, b = np.searchsorted(top, t), np.searchsorted(top, t, side="right")
        order[a:b] = order[a:b][np.argsort(hashes[order[a:b]], kind="stable")]
    if len(odd):
        found = hashes[order]
    return order, np.flatnonzero(np.concatenate(([True], found[1:] != found[:-1]))) if len(found) else order


# -- cutting -----------------------------------------------------------------------------------


@dataclass(frozen=True)
class Shape:
    """Windows of ``n`` units, or down to ``head`` at a text's end; equal heads share a bucket, named by their k-grams."""

    n: int
    head: int
    k: int
    buckets: int
    slices: int


#: Bits of the codes of grams that are counted.
GRAM_BITS = 18


@dataclass(frozen=True)
class Rare:
    """Of each code of a k-gram its rank, the rarest first, and of each rank how many buckets share the heads it names."""

    rank: np.ndarray
    parts: np.ndarray


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    return x ^ (x >> np.uint32(16))


def _summed(codes: np.ndarray, k: int) -> np.ndarray:
    """32 bits of each k-gram."""
    n = max(0, len(codes) - k + 1)
    out = np.zeros(n, np.uint32)
    for i in range(k):
        out += codes[i : n + i] * np.uint32(pow(0x9E3779B1, i + 1, 1 << 32))
    return out


def _codes(summed: np.ndarray) -> np.ndarray:
    return _mixed(summed) >> np.uint32(32 - GRAM_BITS)


def _bucket(shape: Shape, codes: np.ndarray, rare: Rare | None) -> np.ndarray:
    """The bucket of the window at each place: of the least hash in its head, or of its rarest k-gram if those are known."""
    if rare is None:
        hashes = Sums(codes).all(shape.k)
        least = _least((((hashes ^ (hashes >> np.uint64(32))) * _MIX) >> np.uint64(32)).astype(np.uint32), shape.head - shape.k + 1)
        named = _mixed(least)
    else:
        summed = _summed(codes, shape.k)
        least = _least(rare.rank[_codes(summed)], shape.head - shape.k + 1)
        named, parts = least * np.uint32(0x85EBCA6B), rare.parts[least]
        many = np.flatnonzero(parts > 1)  # too often the rarest: dealt on by the whole head
        heads = _mixed(sum((summed[many + i] * np.uint32(0xC2B2AE35 + 2 * i) for i in range(0, shape.head - shape.k + 1)), np.zeros(len(many), np.uint32)))
        named[many] += (heads % parts[many]) * np.uint32(0x27D4EB2F)
        named = _mixed(_mixed(named))
    return (named.astype(np.uint64) * np.uint64(shape.buckets) >> np.uint64(32)).astype(np.int32)


def _counted(k: int):
    """(code, n): the k-grams of a task's texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(1 << GRAM_BITS, np.int64)
        for batch in batches:
            texts, chars = [], 0
            for text in batch.column(0):
                whole = text.as_py() or ""
                for i in range(0, max(0, len(whole) - k + 1), STEP_CHARS):
                    texts.append(whole[i : i + STEP_CHARS + k - 1])
                    chars += len(texts[-1])
                    if chars >= STEP_CHARS:
                        seen += _seen(texts, k)
                        texts, chars = [], 0
            if texts:
                seen += _seen(texts, k)
        some = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(seen[some])], names=["code", "n"])

    return run


def _seen(texts: list[str], k: int) -> np.ndarray:
    """How often each code occurs; k-grams over the ends of texts are counted too, it is only a measure of load."""
    return np.bincount(_codes(_summed(np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32), k)), minlength=1 << GRAM_BITS)


def rarest(texts: DataFrame, *, head: int, k: int) -> Rare:
    """Counts the codes of all k-grams; the driver gets a number for each code, however many texts there are."""
    told = texts.select("text").mapInArrow(_counted(k), "code int, n bigint").groupBy("code").agg(F.sum("n").alias("n")).toArrow()
    seen = np.zeros(1 << GRAM_BITS, np.int64)
    seen[told["code"].to_numpy()] = told["n"].to_numpy()
    return ranked(seen, head - k + 1)


def ranked(seen: np.ndarray, heads: int) -> Rare:
    """``heads``: of so many heads each k-gram may be the rarest."""
    order = np.argsort(seen, kind="stable")
    rank = np.empty(len(order), np.uint32)
    rank[order] = np.arange(len(order), dtype=np.uint32)
    return Rare(rank, np.maximum(1, -(-seen[order] * heads // BUCKET_WINDOWS)).astype(np.uint32))


def _runs(shape: Shape, codes: np.ndarray, lengths: np.ndarray, part: int, rare: Rare | None = None) -> tuple[np.ndarray, ...]:
    """(begin, windows, characters, bucket, text) of the runs of windows of one bucket, of a part's buckets."""
    begins = np.cumsum(lengths) - lengths
    windows = np.clip(np.minimum(lengths - shape.head + 1, STEP_CHARS), 0, None)
    named = _bucket(shape, codes, rare)
    bucket = np.full(len(codes) + 1, -1, np.int32)
    bucket[: len(named)] = named
    step = np.zeros(len(codes) + 1, np.int8)
    some = windows > 0
    np.add.at(step, begins[some], 1)
    np.add.at(step, (begins + windows)[some], -1)
    bucket[np.cumsum(step) == 0] = -1
    edge = np.concatenate(([True], bucket[1:] != bucket[:-1]))
    edge[begins] = True
    at = np.flatnonzero(edge)
    size = np.diff(np.append(at, len(bucket)))
    keep = (bucket[at] >= 0) & (bucket[at] % shape.slices == part)
    at, size = at[keep], size[keep]
    text = np.searchsorted(begins, at, side="right") - 1
    return at, size, np.minimum(size + shape.n - 1, (begins + lengths)[text] - at), bucket[at], text


def _planes(x: np.ndarray) -> bytes:
    return x.view(np.uint8).reshape(len(x), -1).T.tobytes()


def _unplaned(data: memoryview, kind, n: int) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(data, np.uint8, size * n).reshape(size, n).T).view(kind).ravel()


_SENT = "bucket int, pieces int, chars int, planes int, size int, data binary"


def _cutter(shape: Shape, part: int, sent=None):
    """``sent``: a broadcast ``Rare``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = pa.Codec("zstd", 1)
        texts, keys, chars, done, held = [], [], 0, [], 0

        def step():
            codes = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
            at, size, plen, bucket, text = _runs(shape, codes, np.array([len(t) for t in texts], np.int64), part, sent and sent.value)
            done.append((codes, at + held, size.astype(np.int32), plen.astype(np.int32), bucket.astype(np.int32), np.array(keys, np.int64)[text]))

        def flush() -> Iterator[pa.RecordBatch]:
            codes, at, size, plen, bucket, key = (np.concatenate(x) for x in zip(*done, strict=True))
            order = np.argsort(bucket, kind="stable")
            at, size, plen, bucket, key = at[order], size[order], plen[order], bucket[order], key[order]
            first = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1]))) if len(at) else np.zeros(0, np.int64)
            rows = []
            for a, b in zip(first, np.append(first, len(at))[1:], strict=True):
                p = plen[a:b].astype(np.int64)
                ends = np.cumsum(p)
                own = codes[np.arange(ends[-1]) + np.repeat(at[a:b] - (ends - p), p)]
                planes = 1 if own.max() < 256 else 3
                data = own.astype(np.uint8).tobytes() if planes == 1 else b"".join((own >> (8 * i)).astype(np.uint8).tobytes() for i in range(3))
                data += _planes(size[a:b]) + _planes(plen[a:b]) + _planes(np.diff(key[a:b], prepend=0))
                rows.append((bucket[a], b - a, len(own), planes, len(data), codec.compress(data, asbytes=True)))
            done.clear()
            for i in range(0, len(rows), 256):
                cells = list(zip(*rows[i : i + 256], strict=True))
                yield pa.RecordBatch.from_arrays([*[pa.array(np.array(c, np.int32)) for c in cells[:5]], pa.array(cells[5], pa.binary())], names=["bucket", "pieces", "chars", "planes", "size", "data"])

        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                whole = text.as_py() or ""
                for i in range(0, max(0, len(whole) - shape.head + 1), STEP_CHARS):  # a long text in stretches that overlap
                    texts.append(cut := whole[i : i + STEP_CHARS + shape.n - 1])
                    keys.append(key)
                    chars += len(cut)
                    if chars >= STEP_CHARS:
                        step()
                        held, chars = held + chars, 0
                        texts, keys = [], []
                        if held >= FLUSH_CHARS:
                            yield from flush()
                            held = 0
        if texts:
            step()
        if done:
            yield from flush()

    return run


# -- counting ----------------------------------------------------------------------------------


class Bucket:
    """The different pieces of a bucket: their codes, and of each its windows, its characters, how often it occurs and
    the least and greatest key of its texts."""

    def __init__(self):
        self.parts: list[tuple[np.ndarray, ...]] = []
        self.chars, self.most = 0, SQUEEZE_CHARS

    def add(self, pieces: int, chars: int, planes: int, data: bytes) -> None:
        view = memoryview(data)
        each = [np.frombuffer(view[i * chars : (i + 1) * chars], np.uint8) for i in range(planes)]
        codes = each[0] if planes == 1 else sum(x.astype(np.uint32) << np.uint32(8 * i) for i, x in enumerate(each))
        view = view[planes * chars :]
        size, plen = _unplaned(view, np.int32, pieces), _unplaned(view[4 * pieces :], np.int32, pieces)
        key = np.cumsum(_unplaned(view[8 * pieces :], np.int64, pieces))
        self.parts.append((codes, size, plen, np.ones(pieces, np.int64), np.where(key == NO_KEY, np.iinfo(np.int64).max, key), key))
        self.chars += chars
        if self.chars > self.most:
            self.squeeze()
            self.most = 2 * self.chars + SQUEEZE_CHARS

    def _different(self) -> tuple:
        """All codes and their sums; begin, windows, characters, times, least and greatest key of each different piece."""
        codes, size, plen, times, low, high = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        size, plen = size.astype(np.int64), plen.astype(np.int64)
        ends, sums = np.cumsum(plen), Sums(codes)
        begin = ends - plen
        order, first = grouped(sums.at(begin, ends) + size.astype(np.uint64) * _ODD + plen.astype(np.uint64) * _MIX)
        if len(first) < len(order):
            times, low, high = np.add.reduceat(times[order], first), np.minimum.reduceat(low[order], first), np.maximum.reduceat(high[order], first)
            one = order[first]
            as_read = np.argsort(one)  # neighbours stay neighbours
            one, times, low, high = one[as_read], times[as_read], low[as_read], high[as_read]
            begin, size, plen = begin[one], size[one], plen[one]
        return codes, sums, begin, size, plen, times, low, high

    def squeeze(self) -> None:
        """Puts equal pieces together."""
        codes, _, begin, size, plen, times, low, high = self._different()
        codes = codes[np.arange(int(plen.sum())) + np.repeat(begin - (np.cumsum(plen) - plen), plen)]
        self.parts, self.chars = [(codes, size, plen, times, low, high)], len(codes)

    def places(self, most: int) -> tuple[np.ndarray, ...]:
        """Codes, and of each window of all pieces, equal ones too: where it begins, characters from there up to ``most``, times."""
        codes, size, plen, times, _, _ = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        size, plen = size.astype(np.int64), plen.astype(np.int64)
        before = np.cumsum(size) - size
        place = np.arange(int(size.sum()))
        return codes, place + np.repeat(np.cumsum(plen) - plen - before, size), np.minimum(np.repeat(plen + before, size) - place, most).astype(np.int16), np.repeat(times, size) if times.max(initial=1) > 1 else None

    def windows(self, keys: bool = False) -> tuple:
        """Hashes of stretches, and of each different piece's windows: where it begins, characters from there, times, keys."""
        _, sums, begin, size, plen, times, low, high = self._different()
        before = np.cumsum(size) - size
        place = np.arange(int(size.sum()))
        at = place + np.repeat(begin - before, size)
        room = np.repeat(plen + before, size) - place
        return sums, at, room, np.repeat(times, size), *([np.repeat(low, size), np.repeat(high, size)] if keys else [None, None])


#: Stands for a key that is null: no text of its own.
NO_KEY = np.iinfo(np.int64).min


def _teller(tell: Callable[[Bucket], dict[int, int]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec, now, bucket, sums = pa.Codec("zstd"), None, None, {}

        def end():
            if bucket is not None:
                for name, n in tell(bucket).items():
                    sums[name] = sums.get(name, 0) + n

        for batch in batches:
            for i in range(batch.num_rows):
                at, pieces, chars, planes, size, data = (batch.column(c)[i] for c in range(6))
                if at.as_py() != now:
                    end()
                    now, bucket = at.as_py(), Bucket()
                bucket.add(pieces.as_py(), chars.as_py(), planes.as_py(), codec.decompress(data.as_buffer(), size.as_py(), asbytes=True))
        end()
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array(list(sums.values()), pa.int64())], names=["name", "n"])

    return run


@contextmanager
def files_go_at_the_end(spark):
    """Shuffle files of jobs in here are removed when the job ends, not when the driver collects its garbage."""
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)


def stored_texts(df: DataFrame, *, key: str = "doc_id") -> DataFrame:
    """(key, text) as it is, stored: what made the texts runs once, however often they are read."""
    rows, path = df.select(key, "text"), f"{scratch_root(df.sparkSession)}/texts-{uuid.uuid4().hex}"
    rows.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(rows.schema).parquet(path)


def bucket_sums(df: DataFrame, tell: Callable[[Bucket], dict[int, int]], *, n: int, head: int | None = None, k: int | None = None, key: str = "doc_id", slices: int = SLICES, by_rarest: bool = False) -> DataFrame:
    """(name, n): the sums of what ``tell`` says of each bucket of the windows of the normalised texts (key, text).

    Texts are read once for each slice, so they are better stored before, and once more with ``by_rarest``: short heads
    have few k-grams, of which some name far more windows than others; the rarest of each head deals them evenly.
    """
    spark, head = df.sparkSession, head or n
    chars = df.agg(F.sum(F.length("text").cast("bigint"))).first()[0] or 0
    shape = Shape(n, head, k or max(1, min(16, head // 3 + 1), min(5, head // 2)), max(1, -(-chars // BUCKET_WINDOWS)) * slices, slices)
    whole = df.schema[key].dataType.simpleString() in ("tinyint", "smallint", "int", "bigint")
    named = F.coalesce(F.col(key).cast("bigint") if whole else F.when(F.col(key).isNotNull(), F.xxhash64(key)), F.lit(int(NO_KEY)))
    texts = df.select(named.alias("key"), "text")
    root = f"{scratch_root(spark)}/repeats-{uuid.uuid4().hex}"
    with files_go_at_the_end(spark), small_batches(spark, by_rarest):
        rare = spark.sparkContext.broadcast(rarest(texts, head=shape.head, k=shape.k)) if by_rarest else None
        for part in range(slices):
            sent = texts.mapInArrow(_cutter(shape, part, rare), _SENT)
            sent.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_teller(tell), "name bigint, n bigint").write.parquet(f"{root}/{part}")
    return spark.read.schema("name bigint, n bigint").parquet(*[f"{root}/{part}" for part in range(slices)]).groupBy("name").agg(F.sum("n").alias("n"))


def times_of_windows(n: int):
    """How many windows occur a number of times, for each number above one."""

    def tell(bucket: Bucket) -> dict[int, int]:
        sums, begin, _, times, _, _ = bucket.windows()
        order, first = grouped(sums.all(n)[begin])
        count = np.add.reduceat(times[order], first)
        return dict(zip(*(x.tolist() for x in np.unique(count[count > 1], return_counts=True)), strict=True))

    return tell


def shares_of_windows(n: int):
    """0: occurrences, 1: windows, 2: occurrences of those seen twice, 3: their number, 4: the number of those in several texts."""

    def tell(bucket: Bucket) -> dict[int, int]:
        sums, begin, _, times, low, high = bucket.windows(keys=True)
        order, first = grouped(sums.all(n)[begin])
        count = np.add.reduceat(times[order], first)
        many = np.minimum.reduceat(low[order], first) < np.maximum.reduceat(high[order], first)
        return dict(enumerate(map(int, (count.sum(), len(count), count[count > 1].sum(), (count > 1).sum(), many.sum()))))

    return tell


def excess_of_widths(low: int, high: int):
    """For each width the occurrences of windows less the different ones: sorted neighbours that share as much.

    Windows are sorted by as many characters at a time as a number holds; those that differ from all others go out.
    """

    def tell(bucket: Bucket) -> dict[int, int]:
        codes, begin, room, times = bucket.places(high)
        there = np.zeros(int(codes.max(initial=0)) + 1, bool)
        there[codes] = True
        known = np.flatnonzero(there)
        bits = len(known).bit_length()  # 0 stands for the end of a text
        name = np.zeros(len(there), np.uint8 if bits <= 8 else np.uint32)
        name[known] = np.arange(1, len(known) + 1)
        codes = np.concatenate((name[codes], np.zeros(high, name.dtype)))
        shared = np.zeros(high + 1, np.int64) if times is None else np.bincount(room, times - 1, high + 1).astype(np.int64)
        group, at = np.zeros(len(begin), np.uint64), 0
        while at < high and len(begin):
            step = min(high - at, (64 - int(group.max()).bit_length()) // bits)
            own = np.zeros(len(begin), np.uint64)
            for i in range(step):
                own = own << np.uint64(bits) | codes[at + i :][begin]
            short = np.flatnonzero(room < at + step)
            over = ((at + step - np.maximum(room[short], at)) * bits).astype(np.uint64)
            own[short] = np.where(over < 64, own[short] >> np.minimum(over, np.uint64(63)) << np.minimum(over, np.uint64(63)), np.uint64(0))
            wide = np.uint64(bits * step)
            if at:
                own |= group << wide
            order = np.argsort(own)
            own, begin, room = own[order], begin[order], room[order]
            differ = own[1:] ^ own[:-1]
            parted = np.flatnonzero((differ != 0) & (differ >> wide == 0) if at else differ)
            first, apart = np.zeros(len(parted), np.int64), differ[parted]  # characters of this step that are shared
            for i in range(1, step):
                first += apart >> np.uint64(bits * (step - i)) == 0
            shared += np.bincount(np.minimum(at + first, room[parted + 1]), minlength=high + 1)
            edge = np.concatenate(([True], differ != 0, [True]))
            stays = ~(edge[1:] & edge[:-1])
            group = (np.cumsum(edge[:-1])[stays] - 1).astype(np.uint64)
            begin, room, at = begin[stays], room[stays], at + step
            if len(group):  # numbers without gaps
                group = np.cumsum(np.concatenate(([0], group[1:] != group[:-1]))).astype(np.uint64)
        if len(begin):
            shared += np.bincount(room[1:][group[1:] == group[:-1]], minlength=high + 1)
        return {width: int(shared[width:].sum()) for width in range(low, high + 1)}

    return tell


# -- what is asked -----------------------------------------------------------------------------


def repeat_counts(df: DataFrame, *, n: int, key: str = "doc_id") -> DataFrame:
    """(n, grams): how many strings of ``n`` characters begin so many suffixes, more than one."""
    return bucket_sums(stored_texts(df, key=key), times_of_windows(n), n=n, key=key).select(F.col("name").alias("n"), F.col("n").alias("grams"))


def neighbour_lcp(df: DataFrame, *, depth: int, key: str = "doc_id", least: int = 8) -> DataFrame:
    """(lcp, pairs): neighbours among the sorted suffixes by their longest common prefix, from ``least`` up to ``depth``.

    As many neighbours share a width or more as it has windows above the different ones, so nothing is sorted as a whole.
    """
    texts = stored_texts(df.select(F.lit(0).alias(key), "text"), key=key)  # whose a window is doesn't matter
    more = bucket_sums(texts, excess_of_widths(least, depth), n=depth, head=least, k=min(least, 4), key=key, slices=3, by_rarest=True)
    both = more.select(F.col("name").alias("lcp"), "n").unionByName(more.where(F.col("name") > least).select((F.col("name") - 1).alias("lcp"), (-F.col("n")).alias("n")))
    return both.groupBy(F.col("lcp").cast("int").alias("lcp")).agg(F.sum("n").alias("pairs")).where("pairs > 0")
