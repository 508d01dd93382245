import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from tilesieve.llm import bitpack, collision, curriculum, decontam, jaccard, linechunks, quality, secrets, shards, toxicity
from tilesieve.llm.components import components
from tilesieve.llm.registry import word_tokenizer

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
FILL = "lorem ipsum dolor sit amet consectetur adipiscing elit sed do eiusmod tempor incididunt ut labore et dolore magna aliqua".split()


def prose(rng, n):
    return " ".join(rng.choice(FILL) + str(rng.randint(0, 99)) for _ in range(n))


def documents(rng, n=60):
    """Texts with copies, near copies, nulls, blanks, one very long, and null columns."""
    texts = [prose(rng, rng.randint(3, 120)) for _ in range(n)]
    for k in range(0, n, 5):
        words = texts[k].split()
        words[len(words) // 2] = "changed"
        texts.append(" ".join(words))
        texts.append(texts[k])
    texts += [None, "", " \n\t ", "one", "one two", "ONE two", "x" * 200_000, prose(rng, 9000), "a b c d\n" * 3000]
    return [(i, t, None if i % 7 == 0 else "en", None if i % 11 == 0 else f"s{i % 3}" if i % 3 else "hot", None) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def rows():
    return documents(random.Random(9))


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(5)


@pytest.fixture(scope="module")
def labels(spark, rows):
    return spark.createDataFrame([(i, i % 2 if i % 9 else None, int(i % 4 == 0)) for i, *_ in rows] + [(None, 1, 1), (99999, 1, 0)], "doc_id bigint, quality int, toxic int")


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def clash(df):
    """Columns that operators name inside, as extra columns of the input."""
    return df.select("*", *[F.lit("z").alias(c) for c in ("size", "block", "owner", "n", "rep", "token", "score", "row", "at", "position", "c0", "label", "line", "spin", "lane", "_text", "component_id")])


def sets_of(rows, n=4):
    out = {}
    for i, t, *_ in rows:
        w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        out[i] = {tuple(w[j : j + n]) for j in range(max(1, len(w) - n + 1))} if w else set()
    return out


def true_components(sets, percent=85):
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                both = len(sets[a] & sets[b])
                if 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                    x, y = find(a), find(b)
                    root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


# -- 1 quality, 8 toxicity ---------------------------------------------------------------------


def test_quality_learns_and_handles_cases(spark, rows):
    rng = random.Random(1)
    good = [(i, prose(rng, rng.randint(5, 60))) for i in range(300)]
    bad = [(300 + i, " ".join(x.upper() + "!!" for x in prose(rng, rng.randint(5, 60)).split())) for i in range(150)]
    df = spark.createDataFrame(good + bad, "doc_id bigint, text string")
    marks = spark.createDataFrame([(i, int(i < 300), 0) for i, _ in good + bad], "doc_id bigint, quality int, toxic int")
    out = quality.score_documents(df, quality.train(df, marks)).collect()
    held = [r for r in out if r["held_out"]]
    assert len(out) == 450 and len(held) > 50
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in out)
    assert sum(r["predicted"] == int(r["doc_id"] < 300) for r in held) >= 0.98 * len(held)


@pytest.mark.parametrize("module", [quality, toxicity])
def test_classifiers_on_odd_tables(spark, docs, labels, rows, module):
    model = module.train(docs, labels)
    out = module.score_documents(clash(docs.unionAll(docs.limit(3))), model)
    assert out.count() == len(rows) + 3 and out.where("score is null or score < 0 or score > 1").count() == 0
    none = module.train(docs, labels.limit(0))
    assert module.score_documents(docs, none).count() == len(rows)
    assert module.score_documents(empty(spark), model).count() == 0
    assert module.score_documents(docs.withColumn("doc_id", F.lit(None).cast("bigint")), model).where("held_out").count() == 0


def test_quality_keeps_columns(spark, docs, labels):
    model = quality.train(docs, labels)
    assert quality.keep_good(clash(docs), model).columns == clash(docs).columns


def test_grammar_modes():
    m = toxicity.Matcher({"fool": 2.0, "lowei*": 3.0})
    modes = lambda t: [x[0][0] + "".join(sorted(x[0][1:])) for x in m.clauses(t)]
    assert modes("what a fool") == ["I"]
    assert modes("you fool") == ["It"]
    assert modes("he is not a fool") == ["Int"]
    assert modes('she said "fool" today') == ["Irt"]
    assert modes("i will kill you. nothing. kill") == ["H"]
    assert modes("you, i will kill you") == ["Ht"]
    assert modes("die loweischaft dort") == ["I"]
    assert modes("a quiet day") == []
    assert m.features(None) == m.features("") == m.features("calm words")


def test_quotations_end():
    m = toxicity.Matcher({"fool": 2.0})
    quoted = lambda t: ["r" in x[0] for x in m.clauses(t)]
    assert quoted('she said "hello and left.\nwhat a fool') == [False]
    assert quoted('she said "hello and left. ' + "calm " * 60 + "what a fool") == [False]
    assert quoted('she said "hello, fool. fool" and then, fool') == [True, True, False]


@pytest.mark.parametrize("n", [30, 60, 120, 300])
def test_layer_converges(n):
    """On separable, inseparable and one-sided labels: the minimum is met, and no clause stays below the threshold."""
    rng = np.random.default_rng(n)
    m = toxicity.Matcher({"fool": 2.0})
    toxic = np.array([m.features("you fool " * rng.integers(1, 4) + "calm words " * rng.integers(0, 40)) for _ in range(n // 3)])
    clean = np.array([m.features("calm words " * rng.integers(0, 40) if rng.random() < 0.9 else 'he said "fool" again') for _ in range(n)])
    x = np.vstack([toxic, clean])
    for y in (np.arange(len(x)) < len(toxic), np.arange(len(x)) < len(toxic) // 2 + 1, np.zeros(len(x), bool)):
        model = toxicity.ToxicityModel(layer=toxicity.fit_layer(x, y.astype(float)))
        none, aimed = model.score(np.array([m.features("calm words"), m.features("you fool, you fool")]))
        assert none < 0.5 and (y.sum() == 0 or aimed > none)
    best = toxicity.fit_layer(x, (np.arange(len(x)) < len(toxic)).astype(float))
    again = toxicity.fit_layer(x, (np.arange(len(x)) < len(toxic)).astype(float), steps=1000)
    assert np.allclose(best, again)


def test_toxicity_learns_stems(spark):
    rng = random.Random(3)
    bad = [(i, prose(rng, 30) + " grumlo" + rng.choice(FILL) + " " + prose(rng, 10)) for i in range(200)]
    good = [(1000 + i, prose(rng, 40)) for i in range(400)]
    df = spark.createDataFrame(bad + good, "doc_id bigint, text string")
    marks = spark.createDataFrame([(i, 1, int(i < 1000)) for i, _ in bad + good], "doc_id bigint, quality int, toxic int")
    model = toxicity.train(df, marks)
    held = toxicity.score_documents(df, model).where("held_out").collect()
    assert len(held) > 100 and all(r["predicted"] == int(r["doc_id"] < 1000) for r in held)


# -- 2 decontamination -------------------------------------------------------------------------


def test_decontamination(spark):
    rng = random.Random(5)
    items = [(k, prose(rng, 30)) for k in range(6)] + [(90, None), (91, ""), (92, "short"), (None, "x" * 50)]
    typo = list(items[1][1])
    for p in (20, 60, 100, 140):
        typo[p] = "#"
    texts = [(1, prose(rng, 20) + " " + items[0][1].upper().replace(" ", "\n") + " " + prose(rng, 20)), (2, prose(rng, 200)), (3, prose(rng, 5) + " " + "".join(typo)), (4, None), (5, ""), (6, items[2][1][:60]), (7, prose(rng, 3000) + items[3][1])]
    df = spark.createDataFrame(texts, "doc_id bigint, text string")
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    for most in (decontam.PASS_CHARS, 300):  # one pass, and several
        out = decontam.contaminated(df, bench, most=most).collect()
        assert {(r["doc_id"], r["item_id"]) for r in out} == {(1, 0), (3, 1), (7, 3)}
        assert sorted(r["doc_id"] for r in decontam.drop_contaminated(df, bench, most=most).collect()) == [2, 4, 5, 6]
    hit = next(r for r in out if r["doc_id"] == 7)
    assert items[3][1] in texts[6][1][hit["start"] : hit["end"]] and hit["end"] - hit["start"] < len(items[3][1]) + 40
    assert decontam.contaminated(df, bench.limit(0)).count() == 0 and decontam.contaminated(df.limit(0), bench).count() == 0
    assert decontam.drop_contaminated(clash(spark.createDataFrame([(1, "t", "a", "b", 1)], SCHEMA)), bench).columns[-1] == "component_id"


def window_matches(item, text, q, window, stride, share):
    """Whether any window of an item lies in a text within its edits: by aligning every window with the whole text."""
    a, b = decontam.normal(item.strip())[0], decontam.normal(text)[0]
    if len(a) < q:
        return False
    size = min(window, len(a))
    for s in {*range(0, len(a) - size + 1, stride), len(a) - size}:
        k = int(share * size) if size >= 2 * q else 0
        row = list(range(size + 1))  # cost of each prefix of the window against the stretch that ends here
        for c in b:
            prev, row = row, [0]
            for i in range(1, size + 1):
                row.append(min(prev[i - 1] + (a[s + i - 1] != c), prev[i] + 1, row[i - 1] + 1))
            if row[size] <= k:
                return True
    return False


@settings(max_examples=120, deadline=None)
@given(st.data(), st.sampled_from([1, 60, 1 << 18]), st.sampled_from([0, 2]))
def test_filter_loses_no_window(data, segment, dense):
    """Against alignment of all windows, on alphabets small enough for repetition, in segments and dense or not."""
    rng = random.Random(data.draw(st.integers(0, 10**6)))
    alphabet = data.draw(st.sampled_from(["ab", "abc ", "a"]))
    make = lambda n: "".join(rng.choice(alphabet) for _ in range(n))
    items = [(k, make(rng.randint(2, 45))) for k in range(4)] + [(9, "ab" * 15), (9, "ab" * 15)]
    text = list(make(rng.randint(0, 40)) + rng.choice(items)[1] + make(rng.randint(0, 40)))
    for _ in range(rng.randint(0, 3)):
        if text:
            text[rng.randrange(len(text))] = rng.choice(["", "a", "z"])
    text = "".join(text)
    how = dict(q=4, window=20, stride=10, share=0.1)
    before = decontam.SEGMENT, decontam.DENSE
    try:
        decontam.SEGMENT, decontam.DENSE = max(segment, 41), dense
        got = {m[0] for m in decontam.matches(decontam.build_index(items, **how), text)}
    finally:
        decontam.SEGMENT, decontam.DENSE = before
    assert got == {k for k, t in items if window_matches(t, text, **how)}


@settings(max_examples=60, deadline=None)
@given(st.text("ab", min_size=1, max_size=12), st.text("ab", max_size=16), st.integers(0, 4))
def test_banded_edits_against_all_stretches(window, region, k):
    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, c in enumerate(a, 1):
            row, last = [i], row
            for j, d in enumerate(b, 1):
                row.append(min(row[-1] + 1, last[j] + 1, last[j - 1] + (c != d)))
        return row[-1]

    want = min(distance(window, region[i:j]) for i in range(len(region) + 1) for j in range(i, len(region) + 1))
    points = lambda t: np.array([ord(c) for c in t], np.uint32)
    assert decontam.banded_edits(points(window), points(region), k) == min(want, k + 1)


# -- 3 Jaccard join ----------------------------------------------------------------------------


def test_jaccard_against_all_pairs(spark, docs, rows):
    sets = sets_of(rows)
    want = true_components(sets)
    out = jaccard.near_duplicate_classes(clash(docs)).collect()
    assert {r["doc_id"]: r["component_id"] for r in out} == want
    assert {r["doc_id"]: r["n_shingles"] for r in out} == {i: len(s) for i, s in sets.items()}
    kept = jaccard.keep_one(docs)
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(set(want.values())) and kept.columns == docs.columns


def test_jaccard_hot_shingle_in_unlinked_texts(spark):
    """A sentence in thousands of texts that don't link: its lists are gone before any pair is made."""
    rng = random.Random(31)
    texts = [(i, "this very sentence stands in every one of these texts " + " ".join(f"w{rng.randint(0, 10**9)}" for _ in range(rng.randint(8, 40)))) for i in range(6000)]
    texts += [(6000 + i, texts[i][1]) for i in range(5)]
    out = jaccard.near_duplicate_classes(spark.createDataFrame(texts, "doc_id bigint, text string")).collect()
    assert {r["doc_id"]: r["component_id"] for r in out} == {i: i if i < 6000 else i - 6000 for i, _ in texts}


def test_jaccard_hot_sets_apart(spark, monkeypatch):
    texts = [(i, "the same few words again and again") for i in range(9)] + [(20 + i, None if i % 2 else "") for i in range(6)] + [(40, "alone")]
    df = spark.createDataFrame(texts, "doc_id bigint, text string")
    want = {i: 0 if i < 9 else i for i, _ in texts}
    for hot in (3, 10**6):
        monkeypatch.setattr(jaccard, "HOT_COPIES", hot)
        assert {r["doc_id"]: r["component_id"] for r in jaccard.near_duplicate_classes(df).collect()} == want


def test_jaccard_small_sets_and_chains(spark):
    """Short texts one word apart (light sets) and a drifting chain of longer ones (heavy sets)."""
    rng = random.Random(8)
    rows, base = [], [f"w{i}" for i in range(26)]
    for i in range(120):
        words = base[: rng.randint(1, 26)]
        if rng.random() < 0.5:
            words = ["x", *words] if rng.random() < 0.5 else [*words, "y"]
        rows.append((i, " ".join(words)))
    drift = [f"v{i}" for i in range(120)]
    for i in range(40):
        drift[(i * 37) % 120] = f"n{i}"
        rows.append((200 + i, " ".join(drift)))
    out = jaccard.near_duplicate_classes(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert {r["doc_id"]: r["component_id"] for r in out} == true_components(sets_of(rows))


def test_jaccard_odd_tables(spark):
    df = spark.createDataFrame([(None, "a b c d e"), (1, "a b c d e"), (1, "a b c d e"), (5, None)], "doc_id bigint, text string")
    out = sorted((str(r["doc_id"]), str(r["component_id"])) for r in jaccard.near_duplicate_classes(df).collect())
    assert out == [("1", "1"), ("1", "1"), ("5", "5"), ("None", "None")]
    assert jaccard.near_duplicate_classes(df.limit(0)).count() == 0
    assert jaccard.needed(20) == 10 and jaccard.light_boundary({}, 8.0) == 0


def test_keep_one_of_repeated_rows_and_null_ids(spark):
    rows = [(1, "a b c d e"), (1, "a b c d e"), (2, "A b c d e"), (None, "a b c d e"), (None, "p q r s t"), (None, "P q r s t"), (None, None), (None, ""), (3, "x y z"), (4, None), (4, None), (5, "f g h i j k")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = sorted((str(r["doc_id"]), (r["text"] or "").lower()) for r in jaccard.keep_one(df.repartition(3)).collect())
    assert got == sorted([("1", "a b c d e"), ("None", "p q r s t"), ("None", ""), ("None", ""), ("3", "x y z"), ("4", ""), ("5", "f g h i j k")])
    wide = jaccard.keep_one(clash(spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], SCHEMA)))
    assert wide.count() == len(got) and wide.columns[-1] == "component_id"


@pytest.mark.parametrize("seed", [1, 2])
def test_components(spark, seed):
    rng = random.Random(seed)
    edges = [(rng.randint(0, 300), rng.randint(0, 300)) for _ in range(200)] + [(i, i + 1) for i in range(400, 600)]
    root = {}
    for a, b in edges:
        root.setdefault(a, a), root.setdefault(b, b)

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    got = {r["id"]: r["root"] for r in components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert got == {i: find(i) for a, b in edges if a != b for i in (a, b)}


# -- 4 secrets ---------------------------------------------------------------------------------


def test_base_spans_against_plain_patterns(spark):
    texts = ['é token = "abc123def"', "PassWord:short1 passwd = x", "AKIA" + "A" * 16 + " AKIA123", "f" * 30 + " " + "a1" * 12 + "g", None, "", "api_key='q.w-e_r' APIKEY=zzzzzz", "secret" * 3]
    kinds = {"assign": re.compile(r"""(?:(?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""), "access": re.compile("AKIA[A-Z0-9]+"), "hex": re.compile("[0-9a-f]+")}
    least = {"assign": 6, "access": 20, "hex": 24}
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for r in secrets.find_secrets(clash(df)).collect():
        t = texts[r["doc_id"]] or ""
        spans = sorted((m.start(), list(kinds).index(k), f"{k}:{m.start()}:{m.end()}") for k, p in kinds.items() for m in p.finditer(t) if len(m[1] if k == "assign" else m[0]) >= least[k])
        joined = ",".join(s for *_, s in spans)
        assert r["base_sha256"] == hashlib.sha256(joined.encode()).hexdigest()
        assert set(filter(None, joined.split(","))) <= set(r["spans"].split(","))
        counted = Counter(kind for _, kind, _ in spans)
        assert (r["n_assign"], r["n_access"], r["n_hex"]) == (counted[0], counted[1], counted[2])
    assert secrets.find_secrets(df.limit(0)).count() == 0


def test_weak_parts_need_company():
    opaque = "Zk93hQpLx82mVb71TyRw0AqEs5"
    assert secrets.scan(opaque)[1] == []
    assert secrets.scan("https://host.example/path")[1] == []
    found = {k for *_, k in secrets.scan(f"user=alice {opaque} at https://host.example/path")[1]}
    assert found == {"identity", "opaque", "endpoint"}
    assert secrets.scan(f"user=alice {'filler ' * 100} {opaque}")[1] == []
    assert secrets.scan(f"user=alice\n\n{opaque}")[1] == []


def test_nested_spans_hide_no_part():
    long = "token=" + "f" * 30 + "Zq" * 300
    assert {k for *_, k in secrets.scan(f"{long} user=alice")[1]} >= {"assign", "hex", "identity"}
    base = [(0, 100, "assign"), *[(10 + 5 * k, 12 + 5 * k, "hex") for k in range(5)]]
    assert secrets.linked_parts("x" * 200, base, [(50, 90, "opaque"), (110, 120, "identity")]) == [(110, 120, "identity")]


def linked_by_pairs(text, scope):
    """Linked weak parts by comparing all pairs."""
    base, weak = secrets.base_spans(text), secrets.weak_parts(text)
    weak = [w for w in weak if not (w[2] == "opaque" and any(a < w[1] and w[0] < b for a, b, _ in base))]
    breaks = [m.start() for m in secrets.BREAK.finditer(text)]

    def near(x, y):
        lo, hi = min(x[0], y[0]), max(x[0], y[0])
        return hi - min(x[1], y[1]) <= scope and not any(lo < p <= hi for p in breaks)

    fits = lambda x, y: ("secret" in (secrets.ROLE[x[2]], secrets.ROLE[y[2]])) and secrets.ROLE[x[2]] != secrets.ROLE[y[2]]
    return {w for w in weak if any(fits(w, o) and near(w, o) for o in base + weak if o != w)}


PARTS = ["user=alice", "token=abcdef12", "Zk93hQpLx82mVb71TyRw0AqEs5", "https://h.example/x", "db.local:5432", "f" * 30, "AKIA" + "Q" * 18, "\n\n", "filler words", "x" * 15, "password: " + "a1" * 30]


@settings(max_examples=150, deadline=None)
@given(st.lists(st.sampled_from(PARTS), max_size=14), st.sampled_from([5, 40, 400]))
def test_linked_spans_against_all_pairs(parts, scope):
    text = " ".join(parts)
    base, every = secrets.scan(text, scope)
    assert set(every) - set(base) == linked_by_pairs(text, scope) - set(base)


def test_secrets_on_repeated_and_null_rows(spark):
    df = spark.createDataFrame([(1, "token=abcdef12 user=bob"), (1, "token=abcdef12 user=bob"), (None, "token=abcdef12"), (2, None)], "doc_id bigint, text string")
    out = secrets.find_secrets(df).collect()
    assert sorted((r["doc_id"] or 0, r["n_assign"], r["n_linked"]) for r in out) == [(0, 1, 0), (1, 1, 1), (1, 1, 1), (2, 0, 0)]


# -- 5 curriculum ------------------------------------------------------------------------------


def test_mix_targets_and_takings(spark, docs, rows):
    out = curriculum.plan_mix(clash(docs)).collect()
    size = {i: len(WORD.findall(t or "")) for i, t, *_ in rows}
    source = {i: s for i, _, _, s, _ in rows}
    totals = Counter()
    for i, s in source.items():
        totals[s] += size[i]
    names = sorted((s for s in totals if s is not None), key=lambda s: s.encode()) + [None]
    weight = {s: (1, 2, 3)[k % 3] for k, s in enumerate(names)}
    target, free, left = {}, set(names), float(sum(totals.values()))
    while free:
        share = left / sum(weight[s] for s in free)
        over = {s for s in free if share * weight[s] > 3 * totals[s]}
        if not over:
            target |= {s: share * weight[s] for s in free}
            break
        target |= {s: 3.0 * totals[s] for s in over}
        left -= sum(3 * totals[s] for s in over)
        free -= over
    taken, most = Counter(), defaultdict(int)
    assert len(out) == len(rows)
    for r in out:
        s = source[r["doc_id"]]
        assert r["size"] == size[r["doc_id"]] and r["source_size"] == totals[s] and abs(r["target"] - target[s]) < 1e-6 * max(1, target[s])
        assert r["taken"] == r["size"] * r["copies"] <= 3 * r["size"] and all(0 <= p <= 1 for p in r["positions"]) and len(r["positions"]) == r["copies"]
        taken[s] += r["taken"]
        most[s] = max(most[s], r["size"])
    assert all(abs(taken[s] - target[s]) <= most[s] + 1 for s in totals)
    again = {(r["doc_id"], r["taken"]) for r in curriculum.plan_mix(docs.repartition(3)).collect()}
    assert again == {(r["doc_id"], r["taken"]) for r in out}
    stream = curriculum.mixed_documents(clash(docs), position=None)
    assert stream.columns == clash(docs).columns and stream.count() == sum(r["copies"] for r in out)
    assert curriculum.plan_mix(empty(spark)).count() == 0


def test_ranks_are_the_training_order(spark, docs):
    both = clash(docs).unionAll(clash(docs).limit(4))  # repeated rows too
    out = curriculum.ranked_mix(both).collect()
    pairs = sorted((k, p) for r in out for k, p in zip(r["ranks"], r["positions"], strict=True))
    assert [k for k, _ in pairs] == list(range(len(pairs))) and [p for _, p in pairs] == sorted(p for _, p in pairs)
    assert all(len(r["ranks"]) == r["copies"] for r in out) and len(out) == both.count()
    again = Counter((r["doc_id"], tuple(r["ranks"])) for r in curriculum.ranked_mix(both.repartition(3)).collect())
    stream = [r["doc_id"] for r in curriculum.mixed_documents(both, position="due").orderBy("due").collect()]
    assert len(stream) == len(pairs) and again == Counter((r["doc_id"], tuple(r["ranks"])) for r in out)
    assert curriculum.ranked_mix(empty(spark)).count() == 0


def test_null_ids_are_told_apart_by_text(spark):
    df = spark.createDataFrame([(None, f"word {i} " * 3, "en", "s", None) for i in range(30)], SCHEMA)
    runs = [Counter(r["text"] for r in curriculum.mixed_documents(df.repartition(n), most_repeats=2).collect()) for n in (1, 4)]
    assert runs[0] == runs[1] and runs[0]


def test_schedule_inverts_its_integral(spark):
    df = spark.createDataFrame([(s, a, b) for s in (0.0, 0.2, 0.5, 0.9, 1.0) for a, b in ((1.0, 1.0), (1.5, 0.5), (0.5, 1.5), (0.0, 2.0))], "s double, a double, b double")
    for r in df.withColumn("t", curriculum.training_time(F.col("s"), F.col("a"), F.col("b"))).collect():
        assert abs(r["a"] * r["t"] + (r["b"] - r["a"]) * r["t"] ** 2 / 2 - r["s"] * (r["a"] + r["b"]) / 2) < 1e-9


# -- 6 line chunks -----------------------------------------------------------------------------


def test_chunks_against_replay(spark):
    rng = random.Random(4)
    shared = [f"shared line {i} with words" for i in range(12)]
    texts = []
    for i in range(30):
        own = [prose(rng, 5) for _ in range(rng.randint(1, 15))]
        k = rng.randint(0, len(own))
        texts.append("\n".join(own[:k] + (shared if i % 3 else shared[:9]) + own[k:]))
    texts += [texts[0], texts[0], None, "", "\n\n\n\n", "\n\n\n\n", "one line", "one line", "a\n" * 200, " \n \n \n \n", " \n \n \n \n"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    cut = {r["doc_id"]: [(c["line"], c["lines"]) for c in r["c"]] for r in df.where("text is not null").select("doc_id", linechunks.chunks(linechunks.line_hashes(F.col("text"))).alias("c")).collect()}
    seen, want = set(), {}
    for i, t in enumerate(texts):
        if t is None:
            want[i] = (None, 0)
            continue
        lines, kept, gone = t.split("\n"), [], 0
        assert sum(n for _, n in cut[i]) == len(lines) and [a for a, _ in cut[i]] == [1 + sum(n for _, n in cut[i][:k]) for k in range(len(cut[i]))]
        for a, n in cut[i]:
            body = "\n".join(lines[a - 1 : a - 1 + n])
            if n >= 2 and body.strip() and body in seen:
                gone += 1
            else:
                kept += lines[a - 1 : a - 1 + n]
                if n >= 2:
                    seen.add(body)
        want[i] = ("\n".join(kept), gone)
    out = {r["doc_id"]: (r["text"], r["n_removed"]) for r in linechunks.dedup_chunks(clash(df)).collect()}
    assert out == want and sum(g for _, g in want.values()) > 30
    assert linechunks.dedup_chunks(df.limit(0)).count() == 0


def chunk_ends_of(spark, texts, **how):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    out = {r["doc_id"]: r["e"] for r in df.select("doc_id", linechunks.chunk_ends(linechunks.line_hashes(F.col("text")), **how).alias("e")).collect()}
    return [out[i] for i in range(len(texts))]


@pytest.mark.parametrize("modulus", [3, 40])
def test_chunk_ends_move_with_their_lines(spark, modulus):
    """Lines put before a passage move its boundaries by as many; those by length count from the last one."""
    rng = random.Random(6)
    lines = [prose(rng, 4) for _ in range(400)] + ["again"] * 150 + [prose(rng, 4) for _ in range(50)]
    shifts = [1, 5, 31]
    base, *moved = chunk_ends_of(spark, ["\n".join([f"top {k}" for k in range(s)] + lines) for s in (0, *shifts)], modulus=modulus)
    assert max(b - a for a, b in zip([0, *base], base, strict=False)) <= linechunks.MOST
    for s, ends in zip(shifts, moved, strict=True):
        back = [e - s for e in ends if e > s]
        common = next(e for e in base if e in back and e > 2 and e % linechunks.MOST)
        assert common < 200 and [e for e in base if e >= common] == [e for e in back if e >= common]


def test_chunks_have_two_lines(spark):
    rng = random.Random(7)
    texts = ["\n".join(prose(rng, 4) for _ in range(rng.randint(2, 120))) for _ in range(40)]
    for t, ends in zip(texts, chunk_ends_of(spark, texts), strict=True):
        n = t.count("\n") + 1
        sizes = [b - a for a, b in zip([0, *ends], ends, strict=False)]
        assert sum(sizes) == n and all(k >= 2 for k in sizes[:-1])


def test_repeated_stretches_go_whole(spark):
    """Copies, and passages between other lines, lose every line; each line that is left has no earlier twin around it."""
    rng = random.Random(11)
    fresh = lambda n: [prose(rng, 4) + f" {rng.random()}" for _ in range(n)]
    whole, passage = fresh(41), fresh(30)
    docs = [whole, fresh(5) + passage + fresh(6), whole, whole, fresh(3) + passage + fresh(2), passage, fresh(9) + passage[4:] + fresh(1), fresh(4)]
    df = spark.createDataFrame([(i, "\n".join(x)) for i, x in enumerate(docs)], "doc_id bigint, text string")
    out = {r["doc_id"]: r for r in linechunks.dedup_chunks(clash(df), extend=True).collect()}
    once, seen = {}, set()
    for i, x in enumerate(docs):
        once[i] = "\n".join(y for y in x if y not in seen)
        seen |= set(x)
    assert {i: r["text"] for i, r in out.items()} == once
    assert all(r["removed_lines"] == len(docs[i]) - (len(once[i].split("\n")) if once[i] else 0) for i, r in out.items())


def test_short_passages_go_by_their_boundary_pairs(spark):
    """A passage of few lines goes from all later places if two of its lines make a boundary, whatever surrounds it; else none does."""
    rng = random.Random(13)
    fresh = lambda n: [prose(rng, 4) + f" {rng.random()}" for _ in range(n)]
    passages = [fresh(2 + k % 3) for k in range(40)]
    docs = [fresh(rng.randint(1, 4)) + passages[k % 40] + fresh(rng.randint(1, 4)) for k in range(120)]
    found = [r["c"] for r in spark.createDataFrame([(k, "\n".join(x)) for k, x in enumerate(passages)], "k long, text string").select("k", linechunks.closing_lines(linechunks.line_hashes(F.col("text"))).alias("c")).orderBy("k").collect()]
    out = {r["doc_id"]: r["text"].split("\n") for r in linechunks.dedup_chunks(spark.createDataFrame([(i, "\n".join(x)) for i, x in enumerate(docs)], "doc_id bigint, text string"), extend=True).collect()}
    for i, x in enumerate(docs):
        gone = set(passages[i % 40]) if i >= 40 and found[i % 40] else set()
        assert out[i] == [y for y in x if y not in gone]
    assert 10 < sum(bool(c) for c in found) < 40


def test_one_line_repeated_goes(spark):
    df = spark.createDataFrame([(i, "\n".join(["top", *[f"line {i} again"] * n, "end"])) for i, n in enumerate(range(4, 30))], "doc_id bigint, text string")
    out = linechunks.dedup_chunks(df, extend=True).collect()
    assert all(r["text"].split("\n").count(f"line {r['doc_id']} again") <= 5 for r in out)


def test_no_line_is_lost_by_extension(spark):
    """Of few different lines, repeated at random, within a document too, every one stays somewhere."""
    rng = random.Random(12)
    some = [f"line {k}" for k in range(9)] + ["", " "]
    docs = ["\n".join(rng.choice(some) for _ in range(rng.randint(1, 60))) for _ in range(60)] + ["x\n" * 200, "x\n" * 90]
    df = spark.createDataFrame(list(enumerate(docs)), "doc_id bigint, text string")
    out = {r["doc_id"]: r for r in linechunks.dedup_chunks(df, extend=True).collect()}
    assert {x for r in out.values() for x in r["text"].split("\n")} == {x for t in docs for x in t.split("\n")}
    for i, t in enumerate(docs):
        was, kept = t.split("\n"), len(t.split("\n")) - out[i]["removed_lines"]
        left = out[i]["text"].split("\n") if kept else []
        at = iter(was)
        assert len(left) == kept and all(x in at for x in left) and (kept or out[i]["text"] == "")
    assert sum(r["removed_lines"] for r in out.values()) > 300


def test_chunk_joins_of_any_size_agree(spark, monkeypatch):
    """Broadcast or shuffled, hot chunks apart or not, lanes of any size: the same texts."""
    rng = random.Random(8)
    common = ["\n".join(f"common {k} line {i}" for i in range(4)) for k in range(3)]
    texts = ["\n".join(rng.choice(common) if rng.random() < 0.5 else prose(rng, 4) for _ in range(rng.randint(1, 6))) for _ in range(40)] + [None, "", "one"] * 3
    df = spark.createDataFrame([(None if i % 13 == 0 else i % 35, t) for i, t in enumerate(texts)], "doc_id bigint, text string")
    run = lambda: sorted(((r["doc_id"] or -1, r["text"] or "", r["n_removed"], r["removed_lines"]) for r in linechunks.dedup_chunks(df, extend=True).collect()))
    want = run()
    assert sum(r[2] for r in want) > 20
    for name, value in (("BROADCAST_BYTES", 0), ("HOT_ROWS", 5), ("SALT_ROWS", 2)):
        monkeypatch.setattr(linechunks, name, value)
    assert run() == want


def test_chunk_dedup_is_native(spark, docs):
    plan = linechunks.dedup_chunks(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


# -- 7 packed ids ------------------------------------------------------------------------------


@settings(max_examples=100, deadline=None)
@given(st.integers(1, 32), st.data())
def test_packing_round_trip(bits, data):
    ids = np.array(data.draw(st.lists(st.integers(0, 2**bits - 1), max_size=70)), np.uint32)
    packed = bitpack.pack(ids, bits)
    assert len(packed) <= -(-len(ids) * bits // 8) + 1
    a = data.draw(st.integers(0, len(ids)))
    b = data.draw(st.integers(a, len(ids)))
    assert bitpack.unpack(packed, bits, a, b - a).tolist() == ids[a:b].tolist()


def test_packed_documents_exact(spark, docs, rows, tmp_path):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(word_tokenizer())
    more = [(900, "Éa ΑΣ ς İ ﬁ x́ 中文 <|endoftext|>y don't I'LL 12½ 😀 z\x1c\x85w"), (901, "a" * 3000)]
    every = [(i, t) for i, t, *_ in rows] + more
    df = spark.createDataFrame(every, "doc_id bigint, text string").repartition(4)
    got = {r["doc_id"]: (r["start"], r["n_tokens"], r["ids_crc32"]) for r in bitpack.packed_documents(clash(df), word_tokenizer(), path=f"file://{tmp_path}/p").collect()}
    at = 0
    for i, t in sorted(every):
        ids = np.array(library.encode(t or "", add_special_tokens=False).ids + [1], "<u4")
        assert got[i] == (at, len(ids), zlib.crc32(ids.tobytes())), i
        at += len(ids)
    block = spark.read.parquet(f"file://{tmp_path}/p").orderBy("part", "block").first()
    view = bitpack.Block(bytes(block["payload"]))
    assert view.bits == 16 and view.token(0) == int(view.document(0)[0])
    assert bitpack.packed_documents(df.limit(0), word_tokenizer()).count() == 0
    twice = spark.createDataFrame([(None, "a"), (3, "b"), (3, "b")], "doc_id bigint, text string")
    assert bitpack.packed_documents(twice, word_tokenizer()).count() == 3


# -- 9 shards ----------------------------------------------------------------------------------


def test_shards_are_exact_and_uniform(spark, docs, rows):
    out = shards.shard_rows(clash(docs), 8).collect()
    assert len(out) == len(rows)
    per = defaultdict(list)
    for r in out:
        t = rows[r["doc_id"]][1]
        assert r["size"] == len((t or "").encode()) + 1 and r["text_crc32"] == zlib.crc32((t or "").encode())
        per[r["shard"]].append(r["slot"])
    assert all(sorted(v) == list(range(len(v))) for v in per.values()) and max(map(len, per.values())) - min(map(len, per.values())) <= 1
    assert {(r["doc_id"], r["shard"], r["slot"]) for r in out} == {(r["doc_id"], r["shard"], r["slot"]) for r in shards.shard_rows(docs.repartition(2), 8).collect()}
    assert shards.shard_rows(empty(spark), 8).count() == 0
    plan = shards.shard_rows(docs, 8)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan


def test_written_shards_are_in_slot_order(spark, docs, rows, tmp_path):
    shards.write_shards(docs, f"file://{tmp_path}/shards", 3)
    got = spark.read.parquet(f"file://{tmp_path}/shards").select("*", F.col("_metadata.file_name").alias("f"), F.col("_metadata.row_index").alias("i")).collect()
    want = {(r["shard"], r["slot"]): r["doc_id"] for r in shards.shard_rows(docs, 3).collect()}
    assert {(r["shard"], r["slot"]): r["doc_id"] for r in got} == want
    for shard in range(3):
        mine = sorted((r for r in got if r["shard"] == shard), key=lambda r: (r["f"], r["i"]))
        assert [r["slot"] for r in mine] == list(range(len(mine)))
    assert {r["doc_id"]: r["text"] for r in got} == {i: t for i, t, *_ in rows}


def test_hypergeometric_law():
    rng = random.Random(0)
    draws = [shards.hypergeometric(30, 40, 100, rng) for _ in range(4000)]
    assert abs(np.mean(draws) - 12) < 0.15 and abs(np.var(draws) - 30 * 0.4 * 0.6 * 70 / 99) < 0.5
    m = shards.communication_matrix([5, 0, 17, 40], [16, 16, 15, 15], 3)
    assert [sum(r) for r in m] == [5, 0, 17, 40] and [sum(c) for c in zip(*m, strict=True)] == [16, 16, 15, 15]


# -- 10 nearest neighbours ---------------------------------------------------------------------


@pytest.mark.parametrize("unit", [True, False])
def test_nearest_recall_and_scores(spark, unit):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((1500, 32))
    if unit:
        x /= np.linalg.norm(x, axis=1)[:, None]
    x[7] = x[8] = x[9]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)] + [(5000, None), (5020, [0.0] * 32), (5040, [float("nan")] * 32), (5060, [1.0]), (None, [1.0] * 32)], "vec_id bigint, embedding array<double>")
    out = collision.nearest(clash(df)).collect()
    hits = 0
    for q in range(0, 1500, 20):
        mine = sorted((r for r in out if r["query_id"] == q), key=lambda r: r["rank"])
        assert [r["rank"] for r in mine] == list(range(1, 21)) and all(r["vec_id"] != q for r in mine)
        assert all(abs(r["score"] - float(x[r["vec_id"]] @ x[q])) < 1e-9 for r in mine)
        assert all((-a["score"], a["vec_id"]) < (-b["score"], b["vec_id"]) for a, b in zip(mine, mine[1:], strict=False))
        s = x @ x[q]
        s[q] = -np.inf
        hits += len({r["vec_id"] for r in mine} & set(np.lexsort((np.arange(1500), -s))[:20].tolist()))
    assert hits >= 0.9 * 75 * 20 and {r["query_id"] for r in out} == set(range(0, 1500, 20))


@pytest.mark.parametrize("scale", ["sf0.001", "sf0.01"])
def test_nearest_recall_on_the_tables(spark, scale):
    table = spark.read.parquet(f"/root/testdata/{scale}/embeddings.parquet")
    rows = {r["vec_id"]: np.array(r["embedding"], np.float64) for r in table.collect() if r["embedding"] is not None}
    ids = np.array(sorted(rows))
    x = np.array([rows[i] for i in ids])
    found = defaultdict(set)
    for r in collision.nearest(table).collect():
        found[r["query_id"]].add(r["vec_id"])
    asked = [i for i in ids if i % 20 == 0]
    hits = 0
    for q in asked:
        score = (x * rows[q]).sum(1)
        score[ids == q] = -np.inf
        hits += len(found[q] & set(ids[np.lexsort((ids, -score))[:20]].tolist()))
    assert hits >= 0.9 * 20 * len(asked)


def test_equal_vectors_tie_to_the_smaller_id(spark):
    """Many equal vectors in several blocks score alike to the last bit, whatever rows stand around them."""
    rng = np.random.default_rng(4)
    v = rng.standard_normal(48) / 3
    x = [v if i % 3 else rng.standard_normal(48) for i in range(600)]
    out = collision.nearest(spark.createDataFrame([(i, a.tolist()) for i, a in enumerate(x)], "vec_id bigint, embedding array<double>")).collect()
    for q in (20, 40):
        mine = sorted((r for r in out if r["query_id"] == q), key=lambda r: r["rank"])
        assert all((-a["score"], a["vec_id"]) < (-b["score"], b["vec_id"]) for a, b in zip(mine, mine[1:], strict=False))
        assert len({r["score"] for r in mine if r["vec_id"] % 3}) <= 1


def test_nearest_few_rows(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.5, 0.5]), (2, [0.5, 0.5])], "vec_id bigint, embedding array<float>")
    assert [(r["rank"], r["vec_id"]) for r in collision.nearest(df).orderBy("rank").collect()] == [(1, 1), (2, 2)]
    assert collision.nearest(df.limit(0)).count() == 0
    assert collision.nearest(df.where("vec_id = 1")).count() == 0


# -- pipeline ----------------------------------------------------------------------------------


def test_pipeline_stages(spark, sf):
    import corpus_pipeline as p
    from tilesieve.llm.common import stored
    from tilesieve.llm.registry import table

    docs, kept = table(spark, sf, "documents"), {}
    for name, stage in p.STAGES:
        out = stored(stage(spark, docs, sf), "test-stage")
        kept[name] = out.collect()
        if name != "token_ids":
            assert out.columns == docs.columns
        docs = out
    ids = {k: [r["doc_id"] for r in v] for k, v in kept.items()}
    assert set(ids["near_duplicates"]) <= set(ids["quality"])
    good = [(r["doc_id"], r["text"]) for r in kept["quality"]]
    assert sorted(ids["near_duplicates"]) == sorted(set(true_components(sets_of(good)).values()))
    bench = [re.sub(r"\s+", " ", r["text"].lower()) for r in table(spark, sf, "benchmark").collect()]
    clean = {r["doc_id"] for r in kept["near_duplicates"] if not any(b in re.sub(r"\s+", " ", r["text"].lower()) for b in bench)}
    assert set(ids["decontamination"]) == clean
    assert set(ids["mixing"]) <= set(ids["decontamination"]) and max(Counter(ids["mixing"]).values()) <= 3
    assert sorted(ids["token_ids"]) == sorted(ids["mixing"])


def test_pipeline_keeps_the_training_order(spark, docs, sf):
    """Packed ids follow the order in which the mixing stage wrote its copies."""
    import corpus_pipeline as p
    from tilesieve.llm.common import stored

    mixed = stored(p.mix_sources(spark, docs, sf), "test-mixed")
    want = [r["doc_id"] for r in mixed.select("doc_id", F.col("_metadata.file_name").alias("f"), F.col("_metadata.row_index").alias("i")).orderBy("f", "i").collect()]
    position = {r["doc_id"]: r["positions"] for r in curriculum.plan_mix(docs).collect()}
    seen, last = Counter(), -1.0
    for i in want:
        assert position[i][seen[i]] >= last
        last = position[i][seen[i]]
        seen[i] += 1
    packed = p.pack_tokens(spark, mixed, sf).orderBy("start").collect()
    assert [r["doc_id"] for r in packed] == want
    begin = 0
    for r in packed:
        assert r["start"] == begin
        begin += r["n_tokens"]


@pytest.mark.parametrize("name", [n for n, _ in __import__("corpus_pipeline").STAGES])
def test_pipeline_stages_on_odd_tables(spark, rows, sf, name):
    """Null and empty texts, null ids, repeated rows, clashing columns and no rows at all."""
    import corpus_pipeline as p

    stage = dict(p.STAGES)[name]
    odd = [(None, None, None, None, None), (None, "", None, "a", 0), (1, None, "en", "a", None), (2, "", "en", "b", 0), (3, "one text of some words", "en", "b", 4), (3, "one text of some words", "en", "b", 4)]
    df = clash(spark.createDataFrame(odd + rows[:8], SCHEMA))
    out = stage(spark, df, sf)
    got = out.collect()
    none = stage(spark, empty(spark), sf)
    assert none.count() == 0
    if name != "token_ids":
        assert out.columns == df.columns
    if name in ("near_duplicates", "decontamination"):  # neither null nor empty texts are copies or hold a benchmark
        assert sum(r["text"] is None for r in got) == sum(t is None for _, t, *_ in odd + rows[:8])
    if name == "near_duplicates":
        assert sum(r["doc_id"] == 3 and r["text"] == "one text of some words" for r in got) == 1
    if name == "token_ids":
        assert len(got) == len(odd) + 8


def test_pipeline_near_duplicates_at_five_words(spark):
    import corpus_pipeline as p

    rng = random.Random(21)
    texts = []
    for k in range(30):
        words = [f"{rng.choice(FILL)}{rng.randint(0, 10**6)}" for _ in range(rng.randint(38, 60))]
        texts.append(" ".join(words))
        for at in rng.sample(range(5, len(words) - 5), 1 + k % 2):
            words[at] = "changed"
        texts.append(" ".join(words))
    rows = [(i, t, "en", "s", None) for i, t in enumerate(texts)]
    want, narrow = (sorted(set(true_components(sets_of(rows, n), percent).values())) for n, percent in ((5, 80), (4, 85)))
    out = p.drop_near_duplicates(spark, spark.createDataFrame(rows, SCHEMA), "")
    assert sorted(r["doc_id"] for r in out.collect()) == want != narrow


# -- hard texts --------------------------------------------------------------------------------

MB = 1 << 20
HARD = {
    "slug": ":" + "a-" * (MB // 2), "dotted": ":" + "a." * (MB // 2), "one": "a" * MB, "rule": "=" * MB, "line": "the same line again\n" * (MB // 20),
    "keys": "token=" * (MB // 6), "users": "user" * (MB // 4) + ":", "pairs": "ab" * (MB // 2), "lines": "\n" * MB, "words": "idiot you " * (MB // 10),
}


@pytest.mark.parametrize("name", HARD)
def test_no_text_hangs_a_task(name):
    """A megabyte that repeats itself takes each operator that reads texts in Python a few seconds at most."""
    import time

    text = HARD[name]
    index = decontam.build_index([(1, "=" * 200), (2, "ab" * 100), (3, "a" * 96), (4, "the same line again " * 12), (5, "a-" * 96)])
    encoder = bitpack.ColumnEncoder(word_tokenizer())
    data, begins = np.frombuffer(text.encode(), np.uint8), np.array([0, len(text)])
    from tilesieve.llm.bytewords import Powers

    jobs = {
        "quality": lambda: quality.features(data, begins, Powers()),
        "decontam": lambda: decontam.matches(index, text),
        "jaccard": lambda: jaccard.shingle_sets(data, begins, Powers()),
        "secrets": lambda: secrets.scan(text),
        "packing": lambda: encoder.encode(pa.array([text])),
        "toxicity": lambda: toxicity.Matcher(dict.fromkeys(toxicity.SEEDS, 1.5)).features(text),
    }
    for job, run in jobs.items():
        began = time.perf_counter()
        run()
        assert time.perf_counter() - began < 8, job
