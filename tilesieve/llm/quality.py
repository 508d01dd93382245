"""Quality classifier: a generalised additive model with pairwise interactions.

Each feature has a lookup table over its bins, learnt by cyclic boosting of shallow trees; so have the
few pairs of features that explain most of what is left. Scoring adds table entries, vectorised over
all texts of a slice. Labels are read from a bounded sample; every text is scored whole.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesieve.llm.bytewords import Powers, runs, span_hashes, words
from tilesieve.llm.common import frugal, held_out, labelled_sample, ship, text_bytes, text_slices

ship(__name__)

FEATURES = ("log_words", "word_length", "upper", "symbols", "marks", "digits", "doubled_marks", "next_same", "distinct", "line_repeats", "line_length", "short_words", "capitals", "bare_marks")
FOLDS, FOLD = 5, 0
THRESHOLD = 0.3
#: Most labelled rows that a fit reads.
SAMPLE_ROWS = 20_000


def features(data: np.ndarray, begins: np.ndarray, powers: Powers) -> np.ndarray:
    """A row of FEATURES for each text; a text without words has zeros."""
    n = len(begins) - 1
    table = np.zeros((256,), np.uint8)
    for name, code in (("ABCDEFGHIJKLMNOPQRSTUVWXYZ", 1), ("abcdefghijklmnopqrstuvwxyz", 2), ("0123456789", 3), (".,;:?!'\"-()", 4), ("#$%&*+/<=>@[\\]^_`{|}~", 5)):
        table[np.frombuffer(name.encode(), np.uint8)] = code
    table[0x80:0xC0] = 6
    table[0xC0:] = 7
    kind = table[data]

    def per_text(mask: np.ndarray) -> np.ndarray:
        sums = np.concatenate([[0], np.cumsum(mask, dtype=np.int64)])
        return (sums[begins[1:]] - sums[begins[:-1]]).astype(float)

    def per_owner(owner: np.ndarray, weight: np.ndarray | None = None) -> np.ndarray:
        return np.bincount(owner, weight, n).astype(float)

    def distinct(owner: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        order = np.lexsort((hashes, owner))
        o, h = owner[order], hashes[order]
        return per_owner(o[np.concatenate([[True], (o[1:] != o[:-1]) | (h[1:] != h[:-1])])]) if len(o) else np.zeros(n)

    upper, lower, digits, marks, symbols = (per_text(kind == c) for c in (1, 2, 3, 4, 5))
    letters = np.maximum(upper + lower + per_text(kind == 7), 1)
    chars = np.maximum(per_text(kind != 6), 1)
    mark = (kind == 4) | (kind == 5)
    doubled = np.concatenate([[False], mark[1:] & (data[1:] == data[:-1])]) if len(data) else mark
    starts, ends, owner, hashes = words(data, begins, powers)
    count = per_owner(owner)
    most = np.maximum(count, 1)
    same = np.concatenate([[False], (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])]) if len(owner) else np.zeros(0, bool)
    plain = np.concatenate([[0], np.cumsum(~mark, dtype=np.int64)])
    bare = plain[ends] == plain[starts]
    l_starts, l_ends = runs(data, begins, data == 10)
    l_owner = np.searchsorted(begins, l_starts, side="right") - 1
    lines = per_owner(l_owner)
    l_distinct = distinct(l_owner, span_hashes(data, l_starts, l_ends, powers))
    length = (ends - starts).astype(float)
    columns = (
        np.log1p(count), per_owner(owner, length) / most, upper / letters, symbols / chars, marks / most, digits / chars, per_text(doubled) / most,
        per_owner(owner[same]) / most, distinct(owner, hashes) / most, 1 - l_distinct / np.maximum(lines, 1), np.log1p(count / np.maximum(lines, 1)),
        per_owner(owner[length <= 3]) / most, per_owner(owner[kind[starts] == 1]) / most, per_owner(owner[bare]) / most,
    )
    return np.where((count > 0)[:, None], np.stack(columns, 1), 0.0)


@dataclass
class AdditiveModel:
    """Bias, bin edges and one table for each feature, and (i, j, table) for each chosen pair."""

    bias: float
    edges: list[np.ndarray]
    tables: list[np.ndarray]
    pairs: list[tuple[int, int, np.ndarray]]
    coarse: int

    def score(self, x: np.ndarray) -> np.ndarray:
        bins = np.stack([np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(self.edges)], 1) if len(x) else np.zeros((0, len(self.edges)), int)
        total = np.full(len(x), self.bias)
        for j, t in enumerate(self.tables):
            total += t[bins[:, j]]
        for i, j, t in self.pairs:
            total += t[bins[:, i] // self.coarse, bins[:, j] // self.coarse]
        return 1 / (1 + np.exp(-np.clip(total, -30, 30)))


def _leaves(g: np.ndarray, h: np.ndarray, depth: int, ridge: float, least: float) -> np.ndarray:
    """Newton steps of the best tree with ``depth`` levels over ordered bins."""
    whole = np.full(len(g), g.sum() / (h.sum() + ridge))
    if depth == 0 or len(g) < 2:
        return whole
    gl, hl = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
    gr, hr = g.sum() - gl, h.sum() - hl
    gain = np.where((hl >= least) & (hr >= least), gl**2 / (hl + ridge) + gr**2 / (hr + ridge), -1.0)
    k = int(gain.argmax())
    if gain[k] <= g.sum() ** 2 / (h.sum() + ridge):
        return whole
    return np.concatenate([_leaves(g[: k + 1], h[: k + 1], depth - 1, ridge, least), _leaves(g[k + 1 :], h[k + 1 :], depth - 1, ridge, least)])


def _quadrants(g: np.ndarray, h: np.ndarray, ridge: float) -> tuple[np.ndarray, float]:
    """The best cut of a table into four: its steps and its gain."""
    cg, ch = (np.pad(m.cumsum(0).cumsum(1), ((1, 0), (1, 0))) for m in (g, h))
    best, at = -1.0, (1, 1)
    value = lambda c, a, b: (c[a, b], c[a, -1] - c[a, b], c[-1, b] - c[a, b], c[-1, -1] - c[a, -1] - c[-1, b] + c[a, b])
    for a, b in itertools.product(range(1, g.shape[0]), range(1, g.shape[1])):
        gain = sum(x * x / (y + ridge) for x, y in zip(value(cg, a, b), value(ch, a, b), strict=True))
        if gain > best:
            best, at = gain, (a, b)
    a, b = at
    steps = [x / (y + ridge) for x, y in zip(value(cg, a, b), value(ch, a, b), strict=True)]
    out = np.empty_like(g)
    out[:a, :b], out[:a, b:], out[a:, :b], out[a:, b:] = steps
    return out, best - g.sum() ** 2 / (h.sum() + ridge)


def fit(x: np.ndarray, y: np.ndarray, *, bins: int = 32, coarse: int = 4, rounds: int = 120, pair_rounds: int = 40, pairs: int = 8, rate: float = 0.15, ridge: float = 1.0) -> AdditiveModel:
    """Cyclic boosting: every round visits each feature once; then the same over the chosen pairs.

    Without labels the score is 0.5; with one class only, its smoothed rate.
    """
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) if len(x) else np.zeros(0) for j in range(len(FEATURES))]
    rate0 = (y.sum() + 1) / (len(y) + 2)
    model = AdditiveModel(float(np.log(rate0 / (1 - rate0))), edges, [np.zeros(len(e) + 1) for e in edges], [], coarse)
    if len(np.unique(y)) < 2:
        return model
    b = np.stack([np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(edges)], 1)
    total = np.full(len(y), model.bias)

    def slopes() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-np.clip(total, -30, 30)))
        return y - p, p * (1 - p)

    for _ in range(rounds):
        for j, t in enumerate(model.tables):
            g, h = slopes()
            step = rate * _leaves(np.bincount(b[:, j], g, len(t)), np.bincount(b[:, j], h, len(t)), 2, ridge, 1e-3 * len(y) ** 0.5)
            t += step
            total += step[b[:, j]]
    side = bins // coarse
    cell = lambda i, j: (b[:, i] // coarse) * side + b[:, j] // coarse
    sums = lambda c, v: np.bincount(c, v, side * side).reshape(side, side)
    g, h = slopes()
    ranked = sorted(itertools.combinations(range(len(FEATURES)), 2), key=lambda p: -_quadrants(sums(c := cell(*p), g), sums(c, h), ridge)[1])
    chosen = [(i, j, np.zeros((side, side))) for i, j in ranked[:pairs]]
    for _ in range(pair_rounds):
        for i, j, t in chosen:
            g, h = slopes()
            step = rate * _quadrants(sums(c := cell(i, j), g), sums(c, h), ridge)[0]
            t += step
            total += step.reshape(-1)[c]
    model.pairs = chosen
    return model


def _feature_rows(df: DataFrame) -> DataFrame:
    """label and the feature vector of each row of (label, text)."""

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        powers = Powers()
        for batch in batches:
            for part in text_slices(batch):
                x = features(*text_bytes(part.column(1)), powers)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(list(x), pa.list_(pa.float64()))], names=["label", "x"])

    return df.select("label", "text").mapInArrow(run, "label int, x array<double>")


def train(docs: DataFrame, labels: DataFrame, *, sample_rows: int = SAMPLE_ROWS, folds: int = FOLDS, fold: int = FOLD) -> AdditiveModel:
    """Fit on at most ``sample_rows`` labelled documents outside the held-out fold."""
    picked = labelled_sample(labels, "quality", folds, fold, sample_rows)
    texts = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id")
    rows = _feature_rows(texts.select("label", "text")).collect()
    x = np.array([r["x"] for r in rows], float).reshape(len(rows), len(FEATURES))
    y = np.array([r["label"] > 0 for r in rows], float)
    order = np.lexsort((*x.T, y))  # sums then don't depend on the order in which rows arrive
    return fit(x[order], y[order])


def score_documents(docs: DataFrame, model: AdditiveModel, *, threshold: float = THRESHOLD, folds: int = FOLDS, fold: int = FOLD, keep: list[str] | None = None) -> DataFrame:
    """``doc_id``, ``held_out``, ``score`` and ``predicted`` of every document.

    ``keep`` gives other columns to carry in place of ``doc_id`` and ``held_out``. Null and empty
    texts get the score of a text without words; null ids aren't held out; repeated rows score alike.
    """
    spark = docs.sparkSession
    sent = spark.sparkContext.broadcast(model)
    if keep is None:
        rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), held_out(F.col("doc_id"), folds, fold).alias("held_out"), "text")
    else:
        rows = docs.select(*keep, F.col("text").alias("_text"))
    last = rows.columns[-1]
    names = rows.columns[:-1]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1]) + ", score double, predicted int"

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        powers = Powers()
        for batch in batches:
            for part in text_slices(batch, last):
                score = sent.value.score(features(*text_bytes(part.column(part.num_columns - 1)), powers))
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(score), pa.array((score >= threshold).astype(np.int32))], names=[*names, "score", "predicted"])

    return rows.mapInArrow(run, schema)


def keep_good(docs: DataFrame, model: AdditiveModel, *, threshold: float = THRESHOLD) -> DataFrame:
    """The documents that the model accepts, with all their columns, whatever the names."""
    names = docs.columns
    safe = docs.toDF(*[f"c{i}" for i in range(len(names))]).withColumn("text", F.col(f"c{names.index('text')}"))
    kept = score_documents(safe, model, threshold=threshold, keep=[f"c{i}" for i in range(len(names))])
    return kept.where("predicted = 1").select(*[F.col(f"c{i}").alias(n) for i, n in enumerate(names)])
