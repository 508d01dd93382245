import random

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from tilesieve.functions.grams import guaranteed_hits, local_grams, min_query_length, slide_grams, tile_grams
from tilesieve.functions.hashing import bit_positions
from tilesieve.functions.measures import expected_hits
from tilesieve.functions.sizing import FilterSpec, bits_for, from_budget, plan_filter
from tilesieve.operators import analysis, baselines, bloom, chain
from tilesieve.sources import io


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id bigint, text string")


def rows(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


def test_toy_walk_through(spark):
    """A string behind a two-letter prefix: tiles of 4, hits 4 apart, one chain of 3, two symbols hanging."""
    corpus = frame(spark, [(1, "xyabcdefghijklmn")])
    assert [r["gram"] for r in tile_grams(corpus, n=4).orderBy("tile_no").collect()] == ["xyab", "cdef", "ghij", "klmn"]
    f = bloom.corpus_filter(corpus, fpp=1e-6, n=4, stride=4)
    asked = frame(spark, [(7, "abcdefghijklmn")])
    hits = bloom.probe_texts(asked, f)
    assert rows(hits.where("hit"), "pos") == [(2,), (6,), (10,)]
    chains = chain.chain_hits(hits, n=4)
    assert rows(chains, "start", "n_tiles", "n_chars") == [(2, 3, 12)]
    best = chain.longest_chain(chains, asked)
    assert rows(chain.hanging(asked, best), "head", "tail") == [(2, 0)]


TEXTS = [(1, None), (2, ""), (3, "ab"), (4, "abcd"), (5, "abcde"), (6, "éàü😀xyzÿ" * 3), (7, "a\nb\nc\nd\ne\nf"), (8, "abcd" * 5), (8, "abcd" * 5)]


@pytest.mark.parametrize("n", [1, 3, 4, 7])
def test_grams_against_slices(spark, n):
    df = frame(spark, TEXTS)
    want = sorted((i, k // n, t[k : k + n]) for i, t in TEXTS if t for k in range(0, len(t) - n + 1, n))
    assert rows(tile_grams(df, n=n), "doc_id", "tile_no", "gram") == want
    want = sorted((i, k, t[k : k + n]) for i, t in TEXTS if t for k in range(len(t) - n + 1))
    assert rows(slide_grams(df, n=n), "doc_id", "pos", "gram") == want


def test_token_grams(spark):
    df = frame(spark, [(1, "a b c d e"), (2, "a"), (3, None)])
    assert rows(tile_grams(df, n=2, unit="token"), "tile_no", "gram") == [(0, "a\x1fb"), (1, "c\x1fd")]
    assert len(slide_grams(df, n=2, unit="token").collect()) == 4


@pytest.mark.parametrize("layout", ["classic", "blocked"])
@pytest.mark.parametrize("family", ["md5", "xxhash64"])
@pytest.mark.parametrize("mode", ["packed", "broadcast", "shuffle"])
def test_no_false_negative_and_modes_agree(spark, layout, family, mode):
    df = frame(spark, [(i, f"document {i} with some words of its own {i * i} and more text behind") for i in range(40)])
    f = bloom.corpus_filter(df, n=10, stride=10, layout=layout, hash=family)
    tiles = tile_grams(bloom.normalized(df, f.spec), n=10)
    assert bloom.probe(tiles, f, mode=mode).where("not hit").count() == 0
    other = slide_grams(frame(spark, [(1, "entirely other words that nobody stored before")]), n=10)
    assert rows(bloom.probe(other, f, mode=mode), "pos", "hit") == rows(bloom.probe(other, f, mode="packed"), "pos", "hit")


@pytest.mark.parametrize("mode", ["packed", "broadcast", "shuffle"])
def test_null_and_repeated_keys_keep_their_hits(spark, mode):
    text = "one stored text, long enough to hold several tiles of ten"
    f = bloom.corpus_filter(frame(spark, [(1, text)]), n=10, stride=10)
    asked = frame(spark, [(None, text), (5, text[:20]), (5, text[:20]), (6, None), (None, "")])
    want = {True: 2 * 2 + 5, False: (len(text) - 9 - 5) + 2 * 9}
    hits = bloom.probe_texts(asked, f, mode=mode)
    assert {h: hits.where(F.col("hit") == h).count() for h in (True, False)} == want
    only = bloom.probe_texts(asked, f, mode=mode, hits_only=True)
    assert rows(only.na.fill(-1), "doc_id", "pos") == rows(hits.where("hit").na.fill(-1), "doc_id", "pos")
    windows = slide_grams(asked, n=10).unionAll(spark.createDataFrame([(7, 0, None)], "doc_id bigint, pos int, gram string"))
    probed = bloom.probe(windows, f, mode=mode)
    assert probed.where("hit").count() == want[True] and probed.count() == sum(want.values()) + 1
    chains = chain.chain_hits(only.where("doc_id is null"), n=10)
    best = chain.longest_chain(chains, asked.where("doc_id is null and text != ''"))
    assert rows(best, "max_tiles") == [(5,)]
    assert rows(chain.hanging(asked.where("doc_id is null and text != ''"), best), "head", "tail") == [(0, len(text) - 50)]


def test_tokens_of_any_tokenizer(spark):
    """Token filters take arrays, whatever made them: here pairs of letters."""
    cut = lambda df: df.withColumn("text", F.regexp_extract_all("text", F.lit("(?s)(..)"), 1))
    docs = cut(frame(spark, [(1, "abcdefghijklmnop"), (2, None), (3, "ab")]))
    f = bloom.corpus_filter(docs, unit="token", n=2, stride=2, fpp=1e-6, tokenizer="pairs")
    assert f.spec.n_items == 4
    native = bloom.corpus_filter(docs, spec=f.spec, build="native")
    assert rows(bloom.filter_digest(f), "bucket", "set_bits", "place_sum") == rows(bloom.filter_digest(native), "bucket", "set_bits", "place_sum")
    asked = cut(frame(spark, [(9, "xxabcdefgh")]))
    for mode in ("packed", "shuffle"):
        assert rows(bloom.probe_texts(asked, f, mode=mode, hits_only=True), "doc_id", "pos") == [(9, 1), (9, 3)]
    local = bloom.LocalProbe(f.spec, bloom.pack(f))
    assert local.chains(["xx", "ab", "cd", "ef", "gh"]) == [(1, 2)]
    with pytest.raises(ValueError):
        bloom.corpus_filter(docs, unit="token", n=2, stride=2).spec.require(f.spec)


@settings(max_examples=60, deadline=None)
@given(st.text(st.sampled_from("ab é😀\n"), max_size=30), st.integers(1, 6), st.integers(1, 6))
def test_local_grams(text, n, stride):
    assert local_grams(text, n, stride) == [text[i : i + n].encode() for i in range(0, len(text) - n + 1, stride)]


@pytest.mark.parametrize("layout", ["classic", "blocked"])
@pytest.mark.parametrize("family", ["md5", "xxhash64"])
def test_builds_agree(spark, layout, family):
    df = frame(spark, [(i, f"text number {i} " * 20) for i in range(30)])
    one, *others = [bloom.corpus_filter(df, n=10, stride=10, layout=layout, hash=family, salt="s", build=b) for b in ("native", "packed", "text")]
    for other in others:
        assert rows(bloom.filter_digest(one), "bucket", "set_bits", "place_sum") == rows(bloom.filter_digest(other), "bucket", "set_bits", "place_sum")


def test_local_probe_agrees(spark):
    df = frame(spark, [(1, "the quick brown fox jumps over the lazy dog and runs away again")])
    for layout in ("classic", "blocked"):
        f = bloom.corpus_filter(df, n=8, stride=8, layout=layout)
        local = bloom.LocalProbe(f.spec, bloom.pack(f))
        text = "so the quick brown fox jumps over it"
        assert local.hits(text) == [r["pos"] for r in bloom.probe_texts(frame(spark, [(1, text)]), f).where("hit").orderBy("pos").collect()]


def test_rate_near_target(spark):
    f = bloom.build_filter(spark.range(20000).select(F.col("id").cast("string").alias("gram")), plan_filter(20000, 1e-2, hash="xxhash64"))
    hits = bloom.probe(spark.range(10**6, 10**6 + 50000).select(F.col("id").cast("string").alias("gram")), f).where("hit").count()
    assert 300 < hits < 750
    s = bloom.filter_stats(f).first()
    assert abs(s["est_items"] - 20000) < 400 and 0.005 < s["est_fpp"] < 0.015


def test_merge_repartition_and_repeats_leave_bits(spark):
    a, b = frame(spark, [(1, "x" * 30 + "y" * 30)]), frame(spark, [(2, "z" * 45)])
    spec = plan_filter(100, n=15, stride=15)
    both = bloom.corpus_filter(a.unionAll(b).unionAll(a).repartition(7), spec=spec)
    merged = bloom.merge_filters(bloom.corpus_filter(a, spec=spec), bloom.corpus_filter(b, spec=spec))
    assert rows(bloom.filter_digest(both), "bucket", "set_bits", "place_sum") == rows(bloom.filter_digest(merged), "bucket", "set_bits", "place_sum")
    with pytest.raises(ValueError):
        bloom.merge_filters(both, bloom.corpus_filter(b, n=10, stride=10))


def test_filter_files(spark, tmp_path):
    f = bloom.corpus_filter(frame(spark, [(1, "some text that is long enough for tiles")]), n=10, stride=10)
    io.save_filter(f, f"file://{tmp_path}/f")
    assert io.load_filter(spark, f"file://{tmp_path}/f", expect=f.spec).spec == f.spec
    with pytest.raises(ValueError):
        io.load_filter(spark, f"file://{tmp_path}/f", expect=FilterSpec(n=11))
    io.save_packed(f, f"{tmp_path}/packed")
    assert io.load_packed(f"{tmp_path}/packed") == (f.spec, bloom.pack(f))
    assert set(f.table.columns) == {"bucket", "bitmap"}  # no text is handed out


def test_empty_corpus(spark):
    f = bloom.corpus_filter(frame(spark, []))
    assert bloom.probe_texts(frame(spark, [(1, "x" * 60)]), f).where("hit").count() == 0


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 400), st.integers(1, 60))
def test_expected_hits_is_the_mean_over_offsets(length, width):
    mean = sum((length - r) // width if length >= r else 0 for r in range(width)) / width
    assert abs(mean - max(0, (length - width + 1) / width)) < 1e-9 or length < width


def test_expected_hits_columns(spark):
    df = spark.createDataFrame([(14,), (3,), (7,)], "l int")
    got = df.select("l", expected_hits(F.col("l"), 4).alias("u"), expected_hits(F.col("l"), 4, "guaranteed").alias("g"), expected_hits(F.col("l"), 4, "aligned").alias("a"), guaranteed_hits(F.col("l"), 4).alias("s"))
    assert rows(got, "l", "u", "g", "a", "s") == [(3, 0.0, 0.0, 0.0, 0), (7, 1.0, 1.0, 1.0, 1), (14, 2.75, 2.0, 3.0, 2)]
    assert min_query_length(4) == 7


def test_sizes():
    assert round(bits_for(1, 1e-3), 2) == 14.38
    assert round(bits_for(1, 1e-4) / bits_for(1, 1e-3), 4) == round(4 / 3, 4)
    assert plan_filter(10**6).k == 10
    assert from_budget(1 << 20, 600_000).m_bits == 8 << 20


def test_spans_and_disjoint_chains(spark):
    hits = spark.createDataFrame([(1, p, True) for p in (0, 4, 8, 3, 7, 30)], "doc_id bigint, pos int, hit boolean")
    assert rows(chain.merged_spans(hits, n=4), "begin", "end") == [(0, 12), (30, 34)]
    chains = chain.chain_hits(hits, n=4)
    assert rows(chains, "start", "n_tiles") == [(0, 3), (3, 2), (30, 1)]
    assert rows(chain.disjoint_chains(chains), "start", "n_tiles") == [(0, 3), (30, 1)]
    shown = chain.highlight(frame(spark, [(1, "abcdefghijkl" + "." * 18 + "wxyz"), (2, None)]), hits, n=4)
    assert rows(shown.where("doc_id = 1"), "marked") == [("[[abcdefghijkl]]" + "." * 18 + "[[wxyz]]",)]


def test_boundary_guarantee(spark):
    df = frame(spark, [(1, "".join(random.Random(4).choices("abcdefghijklmnopqrstuvwxyz", k=300)))])
    f = bloom.corpus_filter(df, n=20, stride=20, fpp=1e-9, norm="none")
    closed = {r["length"]: r["misses"] for r in analysis.boundary_miss(df, (20, 30, 38, 39), n=20).collect()}
    probed = {r["length"]: r["misses"] for r in analysis.boundary_probe(df, f, (20, 30, 38, 39)).collect()}
    assert closed == probed and closed[39] == 0 and closed[38] == 1 and closed[20] == 19


def test_search_classifier_against_plain_code(spark):
    """Verdicts of full-text search: the common stretch with the best document, by a suffix automaton and by SQL's rule."""
    rng = random.Random(21)
    texts = [(i, " ".join(rng.choice("alpha beta gamma delta epsilon zeta eta theta".split()) + str(rng.randint(0, 40)) for _ in range(30))) for i in range(12)]
    asked = [(1, texts[3][1]), (2, texts[4][1][:150] + " other words at the end of this one"), (3, "nothing of it"), (4, None), (5, "")]
    docs, q = frame(spark, texts), spark.createDataFrame(asked, "item_id bigint, text string")
    for chars in (200, 50):
        got = {r["item_id"]: r for r in baselines.fts_classify(baselines.build_index(docs), docs, q, prefix_chars=chars).collect()}
        for k, t in asked:
            top = dict(texts).get(got[k]["top"])
            size = baselines.longest_common_substring(top, t) if top and t else 0
            need = int(len(t or "") * 0.9) + 1
            assert got[k]["lcs_chars"] == size and got[k]["pred"] == bool(t and size / len(t) > 0.9)
            assert got[k]["pred"] == any(t[i : i + need] in top for i in range(len(t) - need + 1)) if t and top else not got[k]["pred"]
        assert got[1]["pred"] and not got[2]["pred"]


def test_extension_attack_stalls_on_tiles(spark):
    text = "the secret recipe needs three eggs, a pinch of salt and patience"
    for stride, reach in ((1, len(text)), (12, 12)):
        f = bloom.corpus_filter(frame(spark, [(1, text)]), n=12, stride=stride, fpp=1e-9, norm="none")
        local = bloom.LocalProbe(f.spec, bloom.pack(f))
        assert len(analysis.extension_attack(local.contains, text[:12], "abcdefghijklmnopqrstuvwxyz, ", n=12, steps=100)) == reach


@settings(max_examples=80, deadline=None)
@given(st.text("abc", max_size=25), st.text("abc", max_size=25))
def test_longest_common_substring(a, b):
    want = max((j - i for i in range(len(a)) for j in range(i + 1, len(a) + 1) if a[i:j] in b), default=0)
    assert baselines.longest_common_substring(a, b) == want


def test_scan_phrase_and_suffix_agree(spark):
    docs = frame(spark, [(1, "one two three four five"), (2, "zero one two three"), (3, "three two one"), (4, None), (5, "")])
    asked = spark.createDataFrame([(1, "one two three"), (2, "two one"), (3, "nothing here")], "item_id bigint, text string")
    scan = rows(baselines.scan_exact(docs, asked), "item_id", "doc_id")
    assert scan == [(1, 1), (1, 2), (2, 3)]
    assert rows(baselines.phrase_search(baselines.build_index(docs, positions=True), asked), "item_id", "doc_id") == scan
    table = baselines.build_suffix_table(docs, depth=16)
    assert rows(baselines.suffix_lookup(table, asked.where("length(text) >= 8"), docs, depth=16), "item_id", "doc_id") == [(1, 1), (1, 2)]
    assert table.count() == sum(len(t) for _, t in [(1, "one two three four five"), (2, "zero one two three"), (3, "three two one")])


def test_classifier_and_permutation(spark):
    from tilesieve.operators.analysis import classify, confusion, permute_tiles, verify_chains

    text = "".join(random.Random(5).choices("abcdefghijklmnopqrstuvwxyz", k=600))
    docs = frame(spark, [(1, text)])
    f = bloom.corpus_filter(docs, fpp=1e-9)
    asked = frame(spark, [(1, text), (2, text[::-1])]).withColumn("label", F.col("doc_id") == 1)
    best = chain.longest_chain(chain.chain_hits(bloom.probe_texts(asked, f)), asked)
    assert confusion(classify(best, asked)).first()["f1"] == 1.0
    moved = permute_tiles(docs)
    chains = chain.chain_hits(bloom.probe_texts(moved, f), texts=moved)
    assert chains.agg(F.max("n_tiles")).first()[0] == 12
    assert rows(verify_chains(chains, docs).where("n_tiles = 12"), "contiguous") == [(False,)]


def test_plans(spark, sf):
    """Builds read the text alone and shuffle bitmaps; probes never nest loops; top ten never sorts all."""
    from tilesieve.plans import membership as m

    docs = io.load_table(spark, sf, "documents")
    f = bloom.corpus_filter(docs)
    plan = f.table._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<doc_id:bigint,text:string>" in plan or "ReadSchema: struct<text:string>" in plan
    assert plan.count("MapInArrow") == 2 and plan.count("Exchange hashpartitioning") == 1
    native = bloom.corpus_filter(docs, build="native").table._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in native and "Arrow" not in native and native.count("Exchange hashpartitioning") == 1
    hits = bloom.probe(slide_grams(m.items(spark, sf), key="item_id"), f, mode="shuffle")
    text = hits._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastNestedLoopJoin" not in text and "CartesianProduct" not in text
    top = m.top_chains(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in top


def test_bit_positions_in_range(spark):
    df = spark.createDataFrame([("a",), ("",), ("é",)], "gram string")
    for layout in ("classic", "blocked"):
        for family in ("md5", "xxhash64"):
            spec = plan_filter(10_000, layout=layout, hash=family, salt="k")
            for r in df.select(bit_positions(F.col("gram"), spec).alias("p")).collect():
                assert len(r["p"]) == spec.k and all(0 <= p < spec.m_bits for p in r["p"])
                assert layout == "classic" or len({p // 32768 for p in r["p"]}) == 1


def _joins(df):
    return [x for x in df._jdf.queryExecution().executedPlan().toString().splitlines() if "Join" in x]


def test_exact_hits_move_hashes_alone(spark, sf):
    """Windows meet tiles by hashes: no string is a join key, and nothing is broadcast."""
    from tilesieve.plans import membership as m

    docs = frame(spark, [(1, "abcdefghij" * 3), (2, "é" * 12), (3, None)])
    asked = frame(spark, [(7, "xxabcdefghijé"), (8, "é" * 11), (None, "abcdefghij"), (9, "")])
    hits = baselines.exact_hits(bloom.text_lanes(asked, FilterSpec(n=10, stride=10)), baselines.tile_hashes(docs, n=10))
    assert rows(hits.na.fill(-1), "doc_id", "pos") == [(-1, 0), (7, 2), (8, 0), (8, 1)]
    for df in (m.coincidental_hits(spark, sf), m.empirical_fpr(spark, sf), m.permutation_attack(spark, sf)):
        assert not [x for x in _joins(df) if "gram" in x]
        assert not [x for x in _joins(df) if "[a#" in x and "Broadcast" in x]


def test_empirical_fpr_counts_each_window(spark):
    docs = frame(spark, [(1, "abcdefghij" * 3)])
    f = bloom.corpus_filter(docs, n=10, stride=10, fpp=1e-6)
    asked = frame(spark, [(1, "abcdefghij" + "k"), (2, "abcdefghij"), (3, "abcdefghij")])
    other, tiles = bloom.corpus_filter(docs, n=10, stride=10, layout="blocked"), baselines.tile_hashes(docs, n=10)
    assert tuple(analysis.empirical_fpr(asked, f, other, tiles).first()) == (4, 3, 0, 0, 0.0)
    full = frame(spark, [(1, "abcdefghij"), (1, "bcdefghijk")])  # takes what the corpus does not hold
    assert tuple(analysis.empirical_fpr(asked, bloom.corpus_filter(full, spec=f.spec), other, tiles).first()) == (4, 3, 1, 0, 1.0)
    empty = bloom.corpus_filter(frame(spark, []), spec=f.spec)  # misses all: each miss of a stored gram is counted
    assert tuple(analysis.empirical_fpr(asked, empty, other, tiles).first()) == (4, 3, 0, 3, 0.0)
    assert tuple(analysis.empirical_fpr(asked.where("false"), f, other, tiles).first()) == (0, 0, 0, 0, None)


def test_permuted_tiles_keep_blanks(spark):
    text = "".join(f"{i:02d}cdefgh " for i in range(9))
    moved = analysis.permute_tiles(frame(spark, [(1, text + "tail"), (2, "short"), (3, None)]), n=9)
    import hashlib

    order = sorted(range(9), key=lambda i: (hashlib.md5(str(i).encode()).hexdigest(), i))
    assert rows(moved, "doc_id", "text") == [(1, "".join(text[9 * i : 9 * i + 9] for i in order))]


def test_word_overlap_drops_grams_before_the_shuffle(spark):
    """Corpus grams that no item has are not moved."""
    docs, asked = frame(spark, [(1, "a b c d e f"), (2, "x y z"), (3, None)]), spark.createDataFrame([(1, "b c d q"), (2, "x"), (3, None)], "item_id bigint, text string")
    got = baselines.word_overlap(asked, docs, words=2)
    assert rows(got, "item_id", "grams", "shared") == [(1, 3, 2), (2, 0, 0), (3, 0, 0)]
    assert "LeftSemi" in got._jdf.queryExecution().optimizedPlan().toString()


def test_phrase_search_against_plain_code(spark):
    """Phrases of one, two and more terms, repeated and unknown ones, by the rarest term first."""
    rng = random.Random(8)
    texts = [(i, " ".join(rng.choice("abcd") for _ in range(rng.randint(0, 40)))) for i in range(30)] + [(30, None), (31, "rare a a a b")]
    asked = [(1, "a"), (2, "a b"), (3, "a a b"), (4, "rare a a"), (5, "unknown a b"), (6, ""), (7, None), (8, "b b b b"), (9, "c d a b c")]
    got = baselines.phrase_search(baselines.build_index(frame(spark, texts), positions=True), spark.createDataFrame(asked, "item_id bigint, text string"))
    want = sorted((q, k) for q, p in asked if p for k, t in texts if t and f" {p} " in f" {t} ")
    assert rows(got, "item_id", "doc_id") == want


def test_phrase_search_opens_the_rarest_term_alone(spark):
    """Places of frequent terms are not made into rows."""
    docs = frame(spark, [(1, "often " * 500 + "rare often"), (2, "often " * 500)])
    got = baselines.phrase_search(baselines.build_index(docs, positions=True), spark.createDataFrame([(1, "often rare often")], "item_id bigint, text string"))
    assert rows(got, "item_id", "doc_id") == [(1, 1)]
    assert "array_contains(positions" in got._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("name", ["expected_hits", "guess_cost", "universe_bits", "property_matrix"])
def test_measures_read_a_given_table(spark, sf, name):
    from tilesieve.plans import membership as m

    df = m.REGISTRY[name][0](spark, sf)
    assert "documents.parquet" in "".join(df.inputFiles()) and df.count() > 0


@pytest.mark.parametrize("slice_words", [1, 7, 1 << 18])
def test_index_against_plain_code_without_a_shuffle(spark, monkeypatch, slice_words):
    from collections import defaultdict

    monkeypatch.setattr(baselines, "SLICE_WORDS", slice_words)
    texts = [(1, "b a b É"), (2, None), (3, ""), (4, "..."), (5, "a"), (6, "c a b a c")]
    postings, totals = baselines.build_index(frame(spark, texts).coalesce(1), positions=True)
    want = defaultdict(list)
    for k, t in texts:
        for p, w in enumerate([x for x in (t or "").lower().replace(".", " ").split()]):
            want[w, k].append(p)
    size = {k: sum(len(v) for (_, j), v in want.items() if j == k) for k, _ in texts}
    assert sorted((r["term"], r["doc_id"], r["dl"], r["tf"], r["positions"]) for r in postings.collect()) == sorted((w, k, size[k], len(v), v) for (w, k), v in want.items())
    assert tuple(totals.first()) == (6, 2.0)
    assert "Exchange hashpartitioning" not in postings._jdf.queryExecution().executedPlan().toString()


def test_cut_texts_give_the_filter_of_token_arrays(spark, monkeypatch):
    """A tokenizer that runs where texts are hashed, on a few characters at a time, sets the bits of arrays made before."""
    monkeypatch.setattr(bloom, "SLICE_CHARS", 40)
    texts = [(i, "".join(random.Random(i).choices("abc ", k=7 * i))) for i in range(30)] + [(30, None), (31, "")]
    most = 40 + max(len(t or "") for _, t in texts)

    def cut(part):
        assert sum(len(t or "") for t in part) < most
        for t in part:
            yield None if t is None else [t[i : i + 2] for i in range(0, len(t), 2)]

    arrays = spark.createDataFrame([(k, *cut([t])) for k, t in [(k, t and " ".join(t.split())) for k, t in texts]], "doc_id bigint, text array<string>")
    for stride in (3, 1):
        want = bloom.corpus_filter(arrays, n=3, stride=stride, unit="token", tokenizer="pairs")
        got = bloom.corpus_filter(frame(spark, texts).coalesce(1), n=3, stride=stride, unit="token", tokenizer="pairs", cut=cut)
        assert got.spec == want.spec and bloom.filter_digest(got).exceptAll(bloom.filter_digest(want)).count() == 0


def test_remembered_pieces_are_the_library_s_tokens(monkeypatch):
    import public_tokenizers
    from tokenizers import Tokenizer

    from tilesieve.functions import tokens

    monkeypatch.setattr(tokens, "PIECES", 50)
    path = str(public_tokenizers.path("byte_bpe_50k.json"))
    rng, whole, cut = random.Random(4), Tokenizer.from_file(path), tokens.local_tokens(path)
    known = [chr(i) for i in range(tokens.KNOWN)]
    texts = ["".join(rng.choice(known if rng.random() < 0.3 else "ab '’sretvlld  \n\t1²_.,\x85\xa0") for _ in range(rng.randint(0, 40))) for _ in range(600)]
    texts += [None, "", "中文 and 한글", "a<|endoftext|>b", "we'll see''s"]
    asked: list[str] = []
    for t, got in zip(texts, cut(texts), strict=True):
        assert got == (None if t is None else [str(i) for i in whole.encode(t, add_special_tokens=False).ids]), t
        asked += got or []
    assert len(tokens._LOADED[path][-1]) < 200 and asked


@pytest.mark.parametrize("slice_words,sent", [(1, 1), (60, 7), (1 << 18, 1 << 21)])
def test_block_search_finds_what_the_term_index_finds(spark, monkeypatch, slice_words, sent):
    """Ties, copies, unknown terms and empty texts, in blocks of one document and of all."""
    monkeypatch.setattr(baselines, "SLICE_WORDS", slice_words)
    monkeypatch.setattr(baselines, "SENT_TERMS", sent)
    monkeypatch.setattr(baselines, "QUERIES", 3)
    rng = random.Random(31)
    texts = [(90 - i, " ".join(rng.choice("abcdefgh") for _ in range(rng.randint(0, 25)))) for i in range(40)] + [(95, None), (1, "rare a b"), (2, "rare a b"), (96, "a b rare")]
    asked = [(i, " ".join(rng.choice("abcdefghx") for _ in range(rng.randint(1, 5)))) for i in range(8)] + [(8, None), (9, ""), (10, "unknown"), (11, "b rare rare"), (12, texts[5][1])]
    docs, q = frame(spark, texts).coalesce(1), spark.createDataFrame(asked, "item_id bigint, text string").coalesce(1)
    want = rows(baselines.bm25_search(baselines.build_index(docs), q), "item_id", "doc_id", "score")
    blocks = baselines.build_blocks(docs)
    assert rows(baselines.block_search(blocks, q), "item_id", "doc_id", "score") == want and want
    full = [rows(baselines.fts_classify(x, docs, q, prefix_chars=200), "item_id", "lcs_chars", "pred") for x in (baselines.build_index(docs), blocks)]
    assert full[0] == full[1] and len(full[0]) == len(asked)


@settings(max_examples=300, deadline=None)
@given(st.text("abc", max_size=30), st.text("abc", max_size=12), st.text("abc", max_size=12), st.sampled_from([0.3, 0.5, 0.6, 0.8, 0.9]))
def test_shares_more_is_the_longest_stretch(a, before, after, share):
    for b in (before + a[1:] + after, before + a[2:-1] + after, before + a + after, before):
        want = bool(a) and baselines.longest_common_substring(a, b) / len(a) > share
        assert baselines.shares_more(a, b, share) == want


@pytest.mark.parametrize("name", ["classify_fts50", "classify_fts200"])
def test_search_classifiers_ask_every_twentieth_text(spark, sf, name):
    from tilesieve.plans import membership as m

    got = m.REGISTRY[name][0](spark, sf).first()
    ids = [int(r["id"][1:]) for r in m.labelled(spark, sf).select("id").collect()]
    assert got["tp"] + got["fp"] + got["fn"] + got["tn"] == sum(i % 20 == 0 for i in ids) > 0


def test_members_are_what_the_whole_filter_says(spark):
    texts = [(i, "".join(random.Random(i).choices("abc", k=60))) for i in range(8)] + [(9, None)]
    df = frame(spark, texts)
    grams = ["".join(random.Random(i).choices("abc", k=6)) for i in range(300)]
    for fpp in (0.4, 1e-6):
        f = bloom.corpus_filter(df, n=6, stride=6, fpp=fpp)
        local = bloom.LocalProbe(f.spec, bloom.pack(f))
        assert bloom.corpus_spec(df, n=6, stride=6, fpp=fpp) == f.spec
        assert bloom.members(bloom.normalized(df, f.spec), f.spec, grams) == {g: local.contains(g) for g in grams}


def test_balanced_set_pairs_ranks_and_sorts_no_text(spark, tmp_path):
    """Ties, repeated and null keys, texts too short to be cut; more documents than novel texts."""
    from tilesieve.plans import membership as m

    rng = random.Random(8)
    talk = [(i % 9, i, "user", "t" + "x" * rng.randint(0, 300)) for i in range(20)]
    sizes = [100, 135, 136, 137, 200, 200, 200, 260, 800, 801, 3000] + [rng.randint(100, 900) for _ in range(40)]
    texts = [(None if i == 9 else i // 2, chr(97 + i % 26) * 40 + "".join(rng.choices("uvw", k=n - 40))) for i, n in enumerate(sizes)]
    spark.createDataFrame(talk, "conv_id bigint, turn bigint, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    spark.createDataFrame(texts, "doc_id bigint, text string").selectExpr("*", "'en' AS lang", "'x' AS source", "1L AS n_chars").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    made = m.balanced(spark, str(tmp_path))
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in plan and "TakeOrdered" not in plan
    new = sorted(((r["text"], r["conv_id"]) for r in m.novel(spark, str(tmp_path)).collect()), key=lambda r: (-len(r[0]), r[1]))
    old = sorted((t for t in texts if len(t[1]) >= 99 + 37), key=lambda t: (-len(t[1]), -1 if t[0] is None else t[0]))[: len(new)]
    got = [tuple(r) for r in made.collect()]
    assert sorted((r[0] or "", r[1], len(r[2])) for r in got) == sorted([(f"c{c}", False, n) for (a, c), (_, b) in zip(new, old, strict=True) for n in [min(len(a), len(b) - 37)]] + [("" if k is None else f"d{k}", True, min(len(a), len(b) - 37)) for (a, _), (k, b) in zip(new, old, strict=True)])
    whole = {t for _, t in texts}
    assert all(any(r[2] in t[37:] for t in whole) for r in got if r[1])


@pytest.mark.parametrize("cells, common", [(1 << 20, 16), (40, 16), (1, 16), (1 << 20, 0), (1 << 20, 1 << 20)])
def test_a_task_tells_each_query_once_whatever_its_matrices_hold(spark, monkeypatch, cells, common):
    monkeypatch.setattr(baselines, "SLICE_WORDS", 60)
    rng = random.Random(4)
    texts = [(i, " ".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(0, 30)))) for i in range(60)]
    asked = [(i, " ".join(rng.choice("abcdefghijklmnopq") for _ in range(rng.randint(0, 9)))) for i in range(30)]
    docs, q = frame(spark, texts).coalesce(1), spark.createDataFrame(asked, "item_id bigint, text string").coalesce(1)
    want = rows(baselines.bm25_search(baselines.build_index(docs), q), "item_id", "doc_id", "score")
    monkeypatch.setattr(baselines, "CELLS", cells)
    monkeypatch.setattr(baselines, "COMMON", common)
    assert rows(baselines.block_search(baselines.build_blocks(docs), q), "item_id", "doc_id", "score") == want
    blocks = baselines.build_blocks(docs)[0].toArrow().to_batches()
    assert sum(b.num_rows for b in blocks) > 3
    words = pa.array(list("abcdefghijklmnop"))
    sent = type("Sent", (), {"value": (pa.array([7, 8]), np.array([16, 2]), np.array([*range(16), 3, 4], np.int32), words, np.ones(18))})
    told = pa.Table.from_batches(baselines._scored(sent, 15.0)(iter(blocks)))
    assert told["q"].to_pylist() == [7, 8]  # a row a query, not one a block


@pytest.mark.parametrize("chars", [50, 200])
def test_stored_verdicts_are_those_beside_the_common_stretch(spark, chars):
    rng = random.Random(12)
    texts = [(i, " ".join("".join(rng.choices("abcdef", k=4)) for _ in range(60))) for i in range(12)]
    asked = [(i, t[20:260] if i % 3 else t[:90] + "other words " * 12) for i, t in texts] + [(50, None), (51, "nothing")]
    docs, q = frame(spark, texts), spark.createDataFrame(asked, "item_id bigint, text string")
    index = baselines.build_blocks(docs)
    want = rows(baselines.fts_classify(index, docs, q, prefix_chars=chars), "item_id", "pred")
    got = baselines.fts_classify(index, docs, q, prefix_chars=chars, lcs=False)
    assert rows(got, "item_id", "pred") == want and {p for _, p in want} == {True, False}
    assert got.columns == ["item_id", "top", "pred"]
