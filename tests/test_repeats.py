import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from tilesieve.operators import analysis, baselines, repeats


def corpus(seed: int = 3) -> list[tuple[int | None, str | None]]:
    """Copies, parts of copies, long runs of one character, letters of all widths, short and null texts, null and repeated keys."""
    rng = random.Random(seed)
    own = ["".join(rng.choices("ab é😀", k=rng.randint(0, 90))) for _ in range(30)]
    texts = own + own[:9] + [t[5:60] + "end" for t in own[:12]] + ["a" * 300, "a" * 120, "", None, "aé", "\0" * 40, "end\0\0"]
    return [(None if i % 17 == 4 else i // 2 if i % 5 == 0 else i, t) for i, t in enumerate(texts)]


def grams(rows, n):
    return [(t[i : i + n], k) for k, t in rows for i in range(len(t or "") - n + 1)]


@pytest.fixture(params=[(1 << 19, 1 << 23, 1 << 20, 1 << 22), (64, 300, 50, 10)], ids=["whole", "cut small"])
def sizes(request, monkeypatch):
    for name, value in zip(("STEP_CHARS", "FLUSH_CHARS", "BUCKET_WINDOWS", "SQUEEZE_CHARS"), request.param, strict=True):
        monkeypatch.setattr(repeats, name, value)


def told(rows, tell, part_of=2, n=10, head=None, buckets=7):
    """What the tasks do, without Spark."""
    import pyarrow as pa

    shape, sums = repeats.Shape(n, head or n, 3, buckets, part_of), Counter()
    keys = pa.array([repeats.NO_KEY if k is None else k for k, _ in rows], pa.int64())
    for part in range(part_of):
        sent = [b for b in repeats._cutter(shape, part)(iter([pa.RecordBatch.from_arrays([keys, pa.array([t for _, t in rows], pa.string())], names=["key", "text"])]))]
        table = pa.Table.from_batches(sent).sort_by("bucket") if sent else None
        for out in repeats._teller(tell)(iter(table.to_batches() if table else [])):
            sums.update(dict(zip(out.column(0).to_pylist(), out.column(1).to_pylist(), strict=True)))
    return sums


def plain_shares(rows, n):
    found: dict = {}
    for g, k in grams(rows, n):
        found.setdefault(g, []).append(k)
    known = [{k for k in ks if k is not None} for ks in found.values()]
    return [sum(map(len, found.values())), len(found), sum(len(x) for x in found.values() if len(x) > 1), sum(len(x) > 1 for x in found.values()), sum(len(k) > 1 for k in known)]


@pytest.mark.parametrize("n", [3, 10, 25])
def test_windows_are_counted_as_plain_code_does(sizes, n):
    rows = corpus()
    got = told(rows, repeats.shares_of_windows(n), n=n)
    assert [got[i] for i in range(5)] == plain_shares(rows, n)
    assert told(rows, repeats.times_of_windows(n), n=n) == Counter(c for c in Counter(g for g, _ in grams(rows, n)).values() if c > 1)
    excess = told(rows, repeats.excess_of_widths(4, 12), n=12, head=4)
    assert [excess[w] for w in range(4, 13)] == [len(grams(rows, w)) - len({g for g, _ in grams(rows, w)}) for w in range(4, 13)]


def test_groups_of_hashes_that_agree_in_their_upper_bits():
    hashes = np.array([5, 3, 5, 1 << 63, 3, 4, 5, (1 << 63) + 1] * 3, np.uint64)
    order, first = repeats.grouped(hashes)
    assert sorted(order) == list(range(24)) and len(first) == 5
    assert all(len(set(hashes[order[a:b]])) == 1 for a, b in zip(first, [*first[1:], 24], strict=True))


def test_queries_on_spark_move_no_row_a_gram(spark):
    rows = corpus()
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)
    share = {r["n"]: r for r in analysis.duplicate_share(docs, (3, 10)).collect()}
    for n, r in share.items():
        occurrences, windows, dup, dup_windows, several = plain_shares(rows, n)
        assert tuple(r)[1:] == (occurrences, windows, round(dup / occurrences, 6), round(dup_windows / windows, 6), round(several / windows, 6))
    want = Counter(c for c in Counter(g for g, _ in grams(rows, 10)).values() if c > 1)
    assert dict(map(tuple, repeats.repeat_counts(docs, n=10).collect())) == want
    plain = docs.where(~F.contains("text", F.lit("\0")))  # the suffix table takes them for its padding
    table = baselines.build_suffix_table(plain, depth=24)
    assert sorted(map(tuple, repeats.neighbour_lcp(plain, depth=24).collect())) == sorted(map(tuple, baselines.neighbour_lcp(table).collect()))
    nothing = docs.where("doc_id < 0")
    assert [tuple(r) for r in analysis.duplicate_share(nothing, (3,)).collect()] == [(3, None, 0, None, None, None)]
    assert repeats.repeat_counts(nothing, n=10).count() == repeats.neighbour_lcp(nothing, depth=24).count() == 0
    by_name = docs.select(F.concat(F.lit("k"), F.col("doc_id")).alias("doc_id"), "text")
    assert [tuple(r) for r in analysis.duplicate_share(by_name, (10,)).collect()] == [tuple(share[10])]
    sent = docs.where("doc_id is not null").select("doc_id", "text").mapInArrow(repeats._cutter(repeats.Shape(10, 10, 4, 7, 1), 0), repeats._SENT)
    assert sent.count() < docs.where("text is not null").count() < len(grams(rows, 10)) / 10


def test_heads_are_dealt_evenly_by_their_rarest_gram(monkeypatch):
    monkeypatch.setattr(repeats, "BUCKET_WINDOWS", 2000)
    rng = random.Random(5)
    rows = [(0, " ".join(rng.choices("in the of tion and ing that".split(), k=400)) + "".join(rng.choices("abcdefgh", k=400))) for _ in range(60)]
    codes, lengths = np.frombuffer("".join(t for _, t in rows).encode("utf-32-le"), np.uint32), np.array([len(t) for _, t in rows])
    rare = repeats.ranked(repeats._seen([t for _, t in rows], 4), 5)
    shape = repeats.Shape(24, 8, 4, 90, 1)
    _, size, _, bucket, _ = repeats._runs(shape, codes, lengths, 0, rare)
    assert size.sum() == sum(lengths - 7)
    heads = Counter(t[i : i + 8] for _, t in rows for i in range(len(t) - 7))
    assert np.bincount(bucket, size).max() < 2000 + 5 * max(heads.values())  # by the least hash of three characters one has a tenth of all
    sent = type("Sent", (), {"value": rare})
    batch = pa.RecordBatch.from_arrays([pa.array([0] * len(rows), pa.int64()), pa.array([t for _, t in rows])], names=["key", "text"])
    table = pa.Table.from_batches(repeats._cutter(shape, 0, sent)(iter([batch]))).sort_by("bucket")
    got = next(repeats._teller(repeats.excess_of_widths(8, 24))(iter(table.to_batches())))
    for w, n in zip(got["name"].to_pylist(), got["n"].to_pylist(), strict=True):
        assert n == len(grams(rows, w)) - len({g for g, _ in grams(rows, w)})
