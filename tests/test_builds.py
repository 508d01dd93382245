"""Builds of filters too large for a whole array in each task, and the two pieces they are made of."""

import hashlib

import numpy as np
import pytest

from tilesieve.functions.digests import md5_lanes
from tilesieve.functions.placecodes import coded, decoded
from tilesieve.functions.sizing import BUCKET_BITS, FilterSpec
from tilesieve.operators import bloom


@pytest.mark.parametrize("space,n", [(1, 1), (300, 200), (1 << 24, 5), (1 << 24, 40_000), (1 << 24, 3_000_000), (1 << 32, 70_000)])
def test_places_come_back(space, n):
    places = np.sort(np.random.default_rng(n).integers(0, space, n).astype(np.uint32))
    data = coded(places)
    assert np.array_equal(decoded(data), np.unique(places))
    assert n < 40_000 or len(data) * 8 < 1.1 * n * np.log2(np.e * max(2, space / n))  # near the entropy of the gaps


def test_no_places():
    assert len(decoded(coded(np.zeros(0, np.uint32)))) == 0


def test_md5_of_stretches():
    data = np.random.default_rng(1).integers(0, 256, 700).astype(np.uint8).tobytes()
    begin = np.repeat(np.arange(200), 3)
    end = begin + np.random.default_rng(2).integers(0, 400, len(begin)).clip(0, 500)
    a, b = md5_lanes(data, begin, end)
    want = [hashlib.md5(data[i:j]).hexdigest() for i, j in zip(begin, end, strict=True)]
    assert a.tolist() == [int(x[:15], 16) for x in want] and b.tolist() == [int(x[16:31], 16) for x in want]


TEXTS = [(1, "abc " * 60), (2, None), (3, "é" * 30 + "漢字" * 40 + "x" * 80), (4, ""), (5, "short"), (None, "".join(chr(33 + i * 7 % 90) for i in range(900)))]


@pytest.mark.parametrize("geometry", [{}, {"stride": 1}, {"stride": 7}, {"layout": "blocked"}, {"hash": "xxhash64", "stride": 3}, {"salt": "s", "stride": 25}])
def test_large_build_sets_the_same_bits(spark, geometry, monkeypatch):
    """Bits move as coded places, no row a bit: that was sorted in the executors' heaps."""
    df = spark.createDataFrame(TEXTS, "doc_id bigint, text string")
    spec = FilterSpec(m_bits=700 * BUCKET_BITS, k=10, **geometry)  # two units, the second not whole
    want = sorted(map(tuple, bloom.filter_digest(bloom.corpus_filter(df, spec=spec, build="native")).collect()))
    monkeypatch.setattr(bloom, "TASK_BYTES", 0)
    monkeypatch.setattr(bloom, "FLUSH_BYTES", 4 * bloom.STEP_LANES)
    large = bloom.corpus_filter(df, spec=spec)
    assert "bitmap_construct_agg" not in large.table._jdf.queryExecution().toString()
    assert sorted(map(tuple, bloom.filter_digest(large).collect())) == want
    for slices in (1, 3):
        assert sorted(map(tuple, bloom.sliced_build(df, spec, bloom.filter_digest, slices=slices).collect())) == want


def test_long_text_is_hashed_in_stretches(spark, monkeypatch):
    df = spark.createDataFrame([(1, "".join(chr(97 + i * i % 26) + ("é" if i % 9 == 0 else "") for i in range(1000)))], "doc_id bigint, text string")
    spec = FilterSpec(n=50, stride=7)
    want = bloom.text_lanes(df, spec, stride=7).collect()
    monkeypatch.setattr(bloom, "SLICE_CHARS", 64)
    assert bloom.text_lanes(df, spec, stride=7).collect() == want and [r["pos"] for r in want] == list(range(len(want)))


def test_tokens_are_the_librarys():
    import random

    import public_tokenizers
    from tokenizers import Tokenizer

    from tilesieve.functions.tokens import local_tokens

    path = str(public_tokenizers.path("byte_bpe_50k.json"))
    random.seed(3)
    texts = ["".join(random.choice("ab cZ09'\n\t.,;-_é ßÑ\xad\x00\x7f\x85ÿĀ漢'sll  ") for _ in range(60)) for _ in range(300)]
    want = [[str(i) for i in e.ids] for e in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]
    assert [list(x) for x in local_tokens(path)(texts)] == want
