"""Toxicity by a weighted finite-state pattern grammar.

Tokens fall into classes (insult, target, threat, intent, negation, report, quote, break, line). Four small
transducers over classes are composed into one that reads a clause once and gives, for each insult or
threat, the way it is said: plain, aimed at someone, negated or reported. A document's features are
weighted counts of such matched clauses, never of isolated words alone; a logistic layer joins them.

Insults are seeds plus words and stems learnt from labels (log odds, with a likelihood-ratio test), so
languages without seeds are covered. Labels are read from a bounded sample; all texts are scored whole.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesieve.llm.bytewords import Powers, mix, words
from tilesieve.llm.common import frugal, held_out, labelled_sample, ship, stored, text_bytes, text_slices

ship(__name__)

FOLDS, FOLD = 3, 1
THRESHOLD = 0.7
#: Most labelled rows of each class that a fit reads.
SAMPLE_ROWS = 4_000
#: Most learnt lexemes, and most candidates (those in most toxic texts) that the driver ranks; stems have these
#: lengths and end in ``*``. Bounds of the model, as ``SAMPLE_ROWS`` is: no text or row is left out by them.
LEXEMES, CANDIDATES = 5_000, 100_000
STEMS = (4, 5, 6, 7)
LEAST_SUPPORT, LEAST_ODDS, LEAST_RATIO = 4, 3.0, 24.0

# Fixed word lists of the grammar.
SEEDS = "asshole bastard bitch cunt dickhead dumbass idiot imbecile jerk loser moron pathetic scum stupid trash vermin worthless arschloch dummkopf schwachkopf wichser abschaum connard salaud crétin abruti gilipollas cabrón pendejo imbécil".split()
TARGETS = "you your you're u ur he she they him her them his their these those people person du dich dir dein deine ihr euch sie tu toi vous votre ton ils elles tú usted ustedes ellos eres".split()
THREATS = "kill hurt destroy beat shoot stab burn strangle murder töten umbringen schlagen tuer frapper brûler matar golpear quemar".split()
INTENTS = "will shall gonna going i'll we'll should must werde werden vais allons voy vamos".split()
NEGATIONS = "not no never isn't aren't wasn't don't doesn't didn't won't nobody none nicht kein keine niemals ne pas jamais aucun nunca jamás ningún".split()
REPORTS = "said says say wrote writes called calls claimed according quoted quote tweeted sagte schrieb laut nannte dit écrit selon appelé dijo escribió según llamó".split()

TOKEN = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?|[.!?;:\n\"«»“”]")
CLASSES = {**dict.fromkeys(TARGETS, "T"), **dict.fromkeys(THREATS, "V"), **dict.fromkeys(INTENTS, "M"), **dict.fromkeys(NEGATIONS, "N"), **dict.fromkeys(REPORTS, "R"), **dict.fromkeys(".!?;:", "B"), "\n": "L", **dict.fromkeys('"«»“”', "Q")}
FEATURES = ("plain", "aimed", "negated", "reported", "threat", "spread", "strongest", "density")
#: What the features weigh before any label is seen; fits are drawn towards it.
PRIOR = np.array([0.9, 1.2, 0.2, 0.2, 2.0, 0.5, 0.5, 0.0])
PRIOR_BIAS = -3.0
#: How firmly the bias is held to its prior.
BIAS_RIDGE = 0.1


class Transducer:
    """A deterministic weighted transducer over token classes.

    An arc leads from (state, class) to (state, output, weight); a state without an arc for a class decays
    and copies it at weight 1.
    """

    def __init__(self, arcs: dict[tuple[int, str], tuple[int, str, float]], decay: dict[int, int] | None = None):
        self.arcs, self.decay = arcs, decay or {}

    def step(self, state: int, symbol: str) -> tuple[int, str, float]:
        if (hit := self.arcs.get((state, symbol[0]))) is not None:
            return hit[0], hit[1] + symbol[1:] if hit[1] else symbol, hit[2]
        return self.decay.get(state, state), symbol, 1.0


def _resets(states: range, to: int = 0, classes: str = "BL") -> dict[tuple[int, str], tuple[int, str, float]]:
    """Arcs that end a clause: every state returns to the beginning."""
    return {(s, c): (to, "", 1.0) for s in states for c in classes}


def _grammar() -> list[Transducer]:
    """Threat, negation, report and aim, in the order of the cascade; nearer partners weigh more."""
    near, intent, aimed, quoted = 3, 5, 6, 40
    # a threat is an intent, then a violent verb, within a few tokens
    threat = Transducer(
        _resets(range(intent + 1)) | {(s, "M"): (intent, "", 1.0) for s in range(intent + 1)} | {(s, "V"): (0, "H", 1.25 + 0.05 * s) for s in range(1, intent + 1)},
        {s: s - 1 for s in range(1, intent + 1)},
    )
    negation = Transducer(
        _resets(range(near + 1)) | {(s, "N"): (near, "", 1.0) for s in range(near + 1)} | {(s, c): (s - 1, c + "n", 1.0) for s in range(1, near + 1) for c in "IH"},
        {s: s - 1 for s in range(1, near + 1)},
    )
    # 1: after a reporting word; 2 and more: inside its quotation, which ends at a quote mark, a line or QUOTED tokens
    inside = range(2, 2 + quoted)
    report = Transducer(
        _resets(range(2)) | _resets(inside, classes="L") | {(0, "R"): (1, "", 1.0), (1, "Q"): (inside[-1], "", 1.0)} | {(s, "Q"): (0, "", 1.0) for s in inside}
        | {(1, c): (1, c + "r", 1.0) for c in "IH"} | {(s, c): (s - 1 if s > 2 else 0, c + "r", 1.0) for s in inside for c in "IH"},
        {s: s - 1 if s > 2 else 0 for s in inside},
    )
    # insults and threats said to or of someone a few tokens before
    aim = Transducer(
        _resets(range(aimed + 1)) | {(s, "T"): (aimed, "", 1.0) for s in range(aimed + 1)} | {(s, c): (s, c + "t", 1.0 + 0.05 * s) for s in range(1, aimed + 1) for c in "IH"},
        {s: s - 1 for s in range(1, aimed + 1)},
    )
    return [threat, negation, report, aim]


class Composed:
    """The composition of a cascade: product states, built as they are met; weights along an arc multiply."""

    def __init__(self, cascade: list[Transducer]):
        self.cascade, self.known, self.start = cascade, {}, (0,) * len(cascade)

    def step(self, state: tuple, symbol: str) -> tuple[tuple, str, float]:
        if (hit := self.known.get((state, symbol))) is None:
            out, states, weight = symbol, [], 1.0
            for t, s in zip(self.cascade, state, strict=True):
                s, out, w = t.step(s, out)
                states.append(s)
                weight *= w
            hit = self.known[state, symbol] = tuple(states), out, weight
        return hit


@dataclass
class ToxicityModel:
    weights: dict[str, float] = field(default_factory=lambda: dict.fromkeys(SEEDS, 1.5))
    layer: np.ndarray = field(default_factory=lambda: np.concatenate([[PRIOR_BIAS], PRIOR]))

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.layer[0] + x @ self.layer[1:], -30, 30)))


class Matcher:
    """Runs the composed grammar over texts; remembers the class of each word it met."""

    def __init__(self, weights: dict[str, float], remembered: int = 300_000):
        self.weights, self.remembered, self.seen, self.machine = weights, remembered, {}, Composed(_grammar())

    def classify(self, word: str) -> tuple[str, float]:
        if (hit := self.seen.get(word)) is None:
            found = max((self.weights.get(k, 0.0) for k in (word, *(word[:n] + "*" for n in STEMS if n < len(word)))), default=0.0)
            hit = ("I", found) if found > 0 else (CLASSES.get(word, "O"), 0.0)
            if len(self.seen) >= self.remembered:
                self.seen = {}
            self.seen[word] = hit
        return hit

    def clauses(self, text: str) -> Iterator[tuple[str, float, str]]:
        """(mode, weight, word) of each insult or threat; mode has n, r, t for negated, reported, aimed."""
        tokens = TOKEN.findall(text.lower())
        if not any(self.classify(w)[0] in "IV" for w in set(tokens)):
            return
        state = self.machine.start
        for w in tokens:
            symbol, weight = self.classify(w)
            state, out, arc = self.machine.step(state, symbol)
            if out[0] in "IH":
                yield out, arc * (weight if out[0] == "I" else 1.0), w

    def features(self, text: str | None) -> list[float]:
        plain = aimed = negated = reported = threat = strongest = 0.0
        spread: set[str] = set()
        n = 0
        for mode, weight, word in self.clauses(text or ""):
            n += 1
            if "r" in mode:
                reported += weight
            elif "n" in mode:
                negated += weight
            elif mode[0] == "H":
                threat += weight
            elif "t" in mode:
                aimed += weight
            else:
                plain += weight
            if "r" not in mode and "n" not in mode:
                spread.add(word)
                strongest = max(strongest, weight)
        f = lambda v: math.log1p(v)
        return [f(plain), f(aimed), f(negated), f(reported), f(threat), f(len(spread)), strongest, 100.0 * n / (100 + len(text or ""))]


def lexemes(text: str) -> set[str]:
    """Distinct words and stems of a text."""
    words = {w for w in re.findall(r"[^\W\d_]+", text.lower()) if 3 <= len(w) <= 30}
    return words | {w[:n] + "*" for w in words for n in STEMS if n < len(w)}


def _lexeme_counts(sample: DataFrame) -> DataFrame:
    """How many toxic and clean sample texts have each lexeme: counted by task, then summed."""

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[int, Counter] = {0: Counter(), 1: Counter()}

        def flush() -> pa.RecordBatch:
            keys = list(counts[0].keys() | counts[1].keys())
            out = pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([counts[1][k] for k in keys], pa.int64()), pa.array([counts[0][k] for k in keys], pa.int64())], names=["lexeme", "toxic", "clean"])
            counts[0].clear(), counts[1].clear()
            return out

        for batch in batches:
            for part in text_slices(batch):
                for label, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    counts[int(label > 0)].update(lexemes(text or ""))
                if len(counts[0]) + len(counts[1]) > 400_000:
                    yield flush()
        yield flush()

    return sample.mapInArrow(run, "lexeme string, toxic bigint, clean bigint").groupBy("lexeme").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))


def _ratio(a: float, b: float, n: float, m: float) -> float:
    """Log-likelihood ratio of a among n against b among m."""
    term = lambda x, e: x * math.log(x / e) if x else 0.0
    p = (a + b) / (n + m)
    return 2 * (term(a, n * p) + term(b, m * p) + term(n - a, n * (1 - p)) + term(m - b, m * (1 - p)))


def _marked(df: DataFrame) -> DataFrame:
    """Adds the least and the largest hash of a text's runs of four words: near copies share one or both."""

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        powers = Powers()
        for batch in batches:
            for part in text_slices(batch):
                data, begins = text_bytes(part.column(1))
                _, _, owner, h = words(data, begins, powers)
                four = mix(h[:-3] + np.uint64(3) * h[1:-2] + np.uint64(5) * h[2:-1] + np.uint64(7) * h[3:]) if len(h) > 3 else h[:0]
                whole = owner[: len(four)] == owner[len(h) - len(four) :]
                low, high = np.full(len(begins) - 1, np.uint64(2**64 - 1)), np.zeros(len(begins) - 1, np.uint64)
                np.minimum.at(low, owner[: len(four)][whole], four[whole])
                np.maximum.at(high, owner[: len(four)][whole], four[whole])
                short = np.flatnonzero(high == 0)
                for k in short:  # too short for a run: its bytes alone
                    low[k] = high[k] = np.uint64(zlib.crc32(data[begins[k] : begins[k + 1]].tobytes()))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(low.view(np.int64)), pa.array(high.view(np.int64))], names=["label", "text", "low", "high"])

    return df.mapInArrow(run, "label int, text string, low bigint, high bigint")


def learn_lexicon(sample: DataFrame, toxic: int, clean: int) -> dict[str, float]:
    """Weights of insults: seeds, and the LEXEMES strongest of the CANDIDATES most frequent whose odds and likelihood ratio pass."""
    weights = dict.fromkeys(SEEDS, 1.5)
    if not toxic or not clean:
        return weights
    odds = F.log((F.col("toxic") + 0.5) / (toxic + 1)) - F.log((F.col("clean") + 0.5) / (clean + 1))
    passed = _lexeme_counts(sample).where(F.col("toxic") >= LEAST_SUPPORT).withColumn("odds", odds).where(F.col("odds") >= LEAST_ODDS)
    found = passed.orderBy(F.desc("toxic"), "clean", "lexeme").limit(CANDIDATES).collect()
    support = {r["lexeme"]: r["toxic"] for r in found}
    # a stem gives way to a longer one that nearly all of its texts share
    longer = {k[:n] + "*" for k in support if k.endswith("*") for n in STEMS if n < len(k) - 1 and support[k] >= 0.8 * support.get(k[:n] + "*", math.inf)}
    rows = [(r["lexeme"], r["odds"], _ratio(r["toxic"], r["clean"], toxic, clean)) for r in found if r["lexeme"] not in longer]
    best = sorted((r for r in rows if r[2] >= LEAST_RATIO), key=lambda r: (-r[2], r[0]))[:LEXEMES]
    return weights | {k: min(odds, 8.0) for k, odds, _ in best}


def fit_layer(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 200) -> np.ndarray:
    """Logistic layer drawn towards the prior weights; classes count alike.

    The penalised loss is strictly convex; each Newton step is halved until the loss falls enough, so the
    fit ends at its one minimum. A fit that hasn't got there in ``steps`` raises.
    """
    a = np.hstack([np.ones((len(x), 1)), x])
    prior = np.concatenate([[PRIOR_BIAS], PRIOR])
    if len(np.unique(y)) < 2:
        return prior
    w = np.where(y > 0, 0.5 / y.sum(), 0.5 / (1 - y).sum()) * len(y)
    pull = np.array([BIAS_RIDGE, *[ridge] * x.shape[1]])

    def loss(beta: np.ndarray) -> float:
        return float(w @ np.logaddexp(0.0, np.where(y > 0, -1.0, 1.0) * (a @ beta)) + 0.5 * pull @ (beta - prior) ** 2)

    beta, now = prior.copy(), loss(prior)
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ beta, -500, 500)))
        g = a.T @ (w * (p - y)) + pull * (beta - prior)
        if np.abs(g).max() <= 1e-6 * len(y):
            return beta
        step = -np.linalg.solve((a * (w * p * (1 - p))[:, None]).T @ a + np.diag(pull), g)
        t = 1.0
        while t > 1e-12 and not (after := loss(beta + t * step)) <= now + 1e-4 * t * (g @ step):
            t /= 2
        if t <= 1e-12:  # no step of any size gains: the minimum, as far as doubles tell
            return beta
        beta, now = beta + t * step, after
    raise RuntimeError("the toxicity layer did not converge")


def _feature_rows(sample: DataFrame, weights: dict[str, float]) -> DataFrame:
    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(weights)
        for batch in batches:
            for part in text_slices(batch):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([matcher.features(t) for t in part.column(1).to_pylist()], pa.list_(pa.float64()))], names=["label", "x"])

    return sample.mapInArrow(run, "label int, x array<double>")


def train(docs: DataFrame, labels: DataFrame, *, sample_rows: int = SAMPLE_ROWS, folds: int = FOLDS, fold: int = FOLD) -> ToxicityModel:
    """Learn the lexicon and the layer from at most ``sample_rows`` labelled documents of each class.

    Copies and near copies count once, so those of one toxic document don't make its words insults.
    """
    picked = labelled_sample(labels, "toxic", folds, fold, sample_rows, value=1).unionByName(labelled_sample(labels, "toxic", folds, fold, sample_rows, value=0))
    texts = docs.select("doc_id", "text").where(F.col("text").isNotNull()).join(F.broadcast(picked), "doc_id")
    one = lambda df, key: df.groupBy(key).agg(F.max(F.struct("label", "low", "high", "text")).alias("r")).select("r.*")
    sample = stored(one(one(_marked(texts.select("label", "text")), "low"), "high").select("label", "text"), "toxicity-sample")
    sizes = {r["label"]: r["n"] for r in sample.groupBy("label").agg(F.count("*").alias("n")).collect()}
    weights = learn_lexicon(sample, sizes.get(1, 0), sizes.get(0, 0))
    rows = _feature_rows(sample, weights).collect()
    x = np.array([r["x"] for r in rows], float).reshape(len(rows), len(FEATURES))
    y = np.array([r["label"] for r in rows], float)
    order = np.lexsort((*x.T, y))
    return ToxicityModel(weights, fit_layer(x[order], y[order]))


def score_documents(docs: DataFrame, model: ToxicityModel, *, threshold: float = THRESHOLD, folds: int = FOLDS, fold: int = FOLD) -> DataFrame:
    """``doc_id``, ``held_out``, ``score`` and ``predicted`` of every document.

    Null and empty texts match no clause and get the score of that; null ids aren't held out;
    repeated rows score alike; an empty table gives no rows; other columns are left out.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), held_out(F.col("doc_id"), folds, fold).alias("held_out"), "text")

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(sent.value.weights)
        for batch in batches:
            for part in text_slices(batch):
                x = np.array([matcher.features(t) for t in part.column(2).to_pylist()], float).reshape(-1, len(FEATURES))
                score = sent.value.score(x)
                yield pa.RecordBatch.from_arrays([*part.columns[:2], pa.array(score), pa.array((score >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return rows.mapInArrow(run, "doc_id bigint, held_out boolean, score double, predicted int")
