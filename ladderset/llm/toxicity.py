"""Toxicity by a classifier chain of linear models.

Categories are predicted one after another: each model sees the hashed words of the text and the
probabilities of the categories before it. While training, those probabilities are out of fold (each
document's come from models that have not seen it), so a later model learns how far an earlier one can
be trusted. A model is a logistic regression on naive-Bayes-weighted word presence. The chain over the
given labels is "degraded" (quality 0), then "toxic"; any list of 0/1 columns works.

Training reads at most `max_rows` labelled documents, chosen by a hash of doc_id (a documented bound:
features of that many documents fit the driver). Scoring reads every document. The model is a fixed
2^18 weights per category, so its broadcast does not grow.

Defined cases: null or empty text has no words and gets the prior; documents without labels are only
scored; null labels are left out of training; with no positive or no negative label a category's
probability is its constant prior; rows that repeat are scored one by one; all input columns are carried,
and computed ones replace columns of their names; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import plainly_named, quoted, table
from .textscan import LOWER, SPACE, buffer_of, mix, range_hash, slices, unique_per_row, words_of

BITS = 18
MAX_ROWS = 12_000
TRAIN_TEXT_BYTES = 1 << 15
FOLDS = 3
#: Standard errors that a word's log odds must be away from nothing.
MIN_Z = 3.0
#: Training texts that a word must be in.
MIN_TEXTS = 6
#: No verdict below this probability, whatever the out-of-fold cut.
MIN_CUT = 0.2
SLICE_BYTES = 2 << 20

_INNER = np.zeros(256, bool)
_INNER[[*range(48, 58), *range(97, 123), *range(128, 256), 39]] = True


def word_features(buf: np.ndarray, off: np.ndarray, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """(row, slot): the distinct hashed words of each text, letters and digits only, A-Z lowered."""
    low = LOWER[buf]
    low = np.where(_INNER[low] | SPACE[low], low, 32).astype(np.uint8)
    w = words_of(low, off)
    slot = (range_hash(low, w.start, w.end) >> np.uint64(64 - bits)).astype(np.int64)
    return unique_per_row(w.row, slot)


@dataclass
class Linear:
    """A logistic regression on scaled word presence and a few dense inputs."""

    weights: np.ndarray
    dense: np.ndarray
    bias: float

    def log_odds(self, row: np.ndarray, slot: np.ndarray, rows: int, dense: np.ndarray) -> np.ndarray:
        return np.bincount(row, self.weights[slot], rows) + dense @ self.dense + self.bias


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def fit_linear(row: np.ndarray, slot: np.ndarray, dense: np.ndarray, y: np.ndarray, bits: int = BITS, steps: int = 60, l2: float = 2e-2) -> Linear:
    rows, size = len(y), 1 << bits
    prior = (y.sum() + 0.5) / (rows + 1)
    flat = Linear(np.zeros(size, np.float32), np.zeros(dense.shape[1]), float(np.log(prior / (1 - prior))))
    if not rows or y.min() == y.max():
        return flat
    pos, neg = np.bincount(slot, y[row], size), np.bincount(slot, 1 - y[row], size)
    ratio = np.log((pos + 0.5) / (y.sum() + 1)) - np.log((neg + 0.5) / ((1 - y).sum() + 1))
    # only words whose log odds stand clear of their sampling error (few texts say little, however lopsided)
    clear = (np.abs(ratio) >= MIN_Z * np.sqrt(1 / (pos + 0.5) + 1 / (neg + 0.5))) & (pos + neg >= MIN_TEXTS)
    some = clear[slot]
    row, slot = row[some], slot[some]
    if not len(row):
        return flat
    used, at = np.unique(slot, return_inverse=True)
    scale = ratio[used]
    w, d, b = np.zeros(len(used)), np.zeros(dense.shape[1]), flat.bias
    state = [np.zeros_like(w), np.zeros_like(d), 0.0]
    square = [np.zeros_like(w), np.zeros_like(d), 0.0]
    x = scale[at]
    for t in range(1, steps + 1):
        err = (sigmoid(np.bincount(row, x * w[at], rows) + dense @ d + b) - y) / rows
        grads = [np.bincount(at, x * err[row], len(used)) + l2 * w / rows, dense.T @ err, err.sum()]
        moves = []
        for i, g in enumerate(grads):  # Adam
            state[i], square[i] = 0.9 * state[i] + 0.1 * g, 0.99 * square[i] + 0.01 * g * g
            moves.append(0.12 * (state[i] / (1 - 0.9**t)) / (np.sqrt(square[i] / (1 - 0.99**t)) + 1e-9))
        w, d, b = w - moves[0], d - moves[1], b - float(moves[2])
    weights = np.zeros(size, np.float32)
    weights[used] = w * scale
    return Linear(weights, d, float(b))


@dataclass
class Chain:
    categories: list[str]
    models: list[Linear]
    thresholds: list[float]

    def probabilities(self, row: np.ndarray, slot: np.ndarray, rows: int) -> np.ndarray:
        out = np.zeros((rows, 0))
        for m in self.models:
            out = np.column_stack([out, sigmoid(m.log_odds(row, slot, rows, out))])
        return out


def best_threshold(p: np.ndarray, y: np.ndarray) -> float:
    """The cut with the best F1 on out-of-fold probabilities."""
    order = np.argsort(-p, kind="stable")
    hits = np.cumsum(y[order])
    score = 2 * hits / (np.arange(1, len(y) + 1) + max(1, y.sum()))
    # only cut between different values
    ok = np.append(p[order][1:] < p[order][:-1], True)
    k = int(np.argmax(np.where(ok, score, -1)))
    nxt = p[order][k + 1] if k + 1 < len(p) else 0.0
    return max(MIN_CUT, float((p[order][k] + nxt) / 2))


def fit_chain(row: np.ndarray, slot: np.ndarray, labels: np.ndarray, categories: list[str], fold: np.ndarray, folds: int = FOLDS, bits: int = BITS) -> Chain:
    """Trains the chain; labels is rows x categories, fold has each row's fold."""
    models, cuts, earlier = [], [], np.zeros((len(labels), 0))
    for k in range(len(categories)):
        y = labels[:, k].astype(float)
        out = np.zeros(len(y))
        for f in range(folds):
            train, test = fold != f, fold == f
            renumber = np.cumsum(train) - 1
            mine = train[row]
            m = fit_linear(renumber[row[mine]], slot[mine], earlier[train], y[train], bits)
            out[test] = sigmoid(m.log_odds(row, slot, len(y), earlier))[test]
        models.append(fit_linear(row, slot, earlier, y, bits))
        cuts.append(best_threshold(out, y) if len(y) and y.max() > y.min() else 2.0)
        earlier = np.column_stack([earlier, out])
    return Chain(categories, models, cuts)


def train_toxicity(
    docs: DataFrame, labels: DataFrame, categories: list[str], id_col: str = "doc_id", text_col: str = "text", max_rows: int = MAX_ROWS, folds: int = FOLDS
) -> Chain:
    """Fits the chain on at most `max_rows` labelled documents, drawn by hash, of at most TRAIN_TEXT_BYTES each (so what the driver gathers
    is bounded in rows and in bytes); labels has id_col and one 0/1 column per category."""
    labelled = labels.select(F.col(id_col).alias("doc_id"), *[F.col(c).cast("int").alias(c) for c in categories]).dropna()
    total = labelled.count()
    share = min(1.0, max_rows / max(1, total))
    draw = F.pmod(F.xxhash64(F.lit(11), "doc_id"), F.lit(1_000_000))
    chosen = labelled.where(draw < int(min(1.0, 1.1 * share) * 1_000_000)).orderBy(draw, "doc_id").limit(max_rows)
    short = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).where(F.coalesce(F.octet_length("text"), F.lit(0)) <= TRAIN_TEXT_BYTES)
    texts = short.join(F.broadcast(chosen), "doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = buffer_of(batch.column("text"))
            for lo, hi in slices(off, SLICE_BYTES):
                row, slot = word_features(buf[off[lo] : off[hi]], off[lo : hi + 1] - off[lo])
                at = np.searchsorted(row, np.arange(hi - lo + 1))
                blob = [slot[a:b].astype("<i4").tobytes() for a, b in zip(at[:-1], at[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(lo, hi - lo), *(batch.column(c).slice(lo, hi - lo) for c in categories), pa.array(blob, pa.binary())], ["doc_id", *categories, "slots"])

    got = texts.mapInArrow(run, "doc_id long, " + ", ".join(f"`{c}` int" for c in categories) + ", slots binary").toArrow().sort_by("doc_id")
    ids = got["doc_id"].to_numpy()
    slots = [np.frombuffer(b, "<i4") for b in got["slots"].to_pylist()]
    row = np.repeat(np.arange(len(slots)), [len(s) for s in slots])
    slot = np.concatenate([*slots, np.empty(0, np.int32)]).astype(np.int64)
    y = np.column_stack([got[c].to_numpy() for c in categories]) if len(ids) else np.zeros((0, len(categories)), int)
    fold = (mix(ids.astype(np.uint64)) % np.uint64(folds)).astype(np.int64)
    return fit_chain(row, slot, y, categories, fold, folds)


def score_toxicity(docs: DataFrame, chain: Chain, text_col: str = "text") -> DataFrame:
    """All columns of `docs`, then p_<category> (double) and is_<category> (boolean) for each category."""
    extra = [f"p_{c}" for c in chain.categories] + [f"is_{c}" for c in chain.categories]
    names = [n for n in docs.columns if n not in extra]
    place = names.index(text_col)
    shared = docs.sparkSession.sparkContext.broadcast(chain)  # 2^18 weights a category

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model: Chain = shared.value
        for batch in batches:
            buf, off = buffer_of(batch.column(place))
            for lo, hi in slices(off, SLICE_BYTES):
                row, slot = word_features(buf[off[lo] : off[hi]], off[lo : hi + 1] - off[lo])
                p = model.probabilities(row, slot, hi - lo)
                cols = [pa.array(p[:, k]) for k in range(p.shape[1])] + [pa.array(p[:, k] >= t) for k, t in enumerate(model.thresholds)]
                yield pa.RecordBatch.from_arrays([*batch.slice(lo, hi - lo).columns, *cols], [*names, *extra])

    chosen, kinds = plainly_named(docs, names)
    schema = [f"{quoted(n)} {kind}" for n, kind in zip(names, kinds, strict=True)] + [f"{quoted(e)} {'double' if e.startswith('p_') else 'boolean'}" for e in extra]
    return chosen.mapInArrow(run, ", ".join(schema))


CATEGORIES = ["degraded", "toxic"]


def category_labels(labels: DataFrame) -> DataFrame:
    """The chain's categories from the given labels: degraded is quality 0."""
    return labels.select("doc_id", (1 - F.col("quality")).alias("degraded"), F.col("toxic").alias("toxic"))


def detect_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Scores `docs` by a chain trained on the labelled documents of the whole table."""
    chain = train_toxicity(table(spark, sf_dir, "documents"), category_labels(table(spark, sf_dir, "labels")), CATEGORIES)
    return score_toxicity(docs, chain)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return detect_toxic(spark, docs, sf_dir).select("doc_id", "p_degraded", "p_toxic", "is_degraded", "is_toxic")
