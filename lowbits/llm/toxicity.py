"""Toxicity: classifier chain over categories (operator 9).

Categories are predicted in a fixed order, each by a linear (logistic) model over word features whose
further inputs are the probabilities of the categories before it.  While training, those inputs come from
models that did not see the row (out-of-fold), so later models learn from what earlier ones really know.

Words are runs of letters and digits, lower-cased.  A model is fitted on a bounded sample of labelled rows
(``sample`` rows, those with the smallest id hash); candidates for features are the words whose
presence is tied to a category beyond chance.  Scoring reads every word of every text.

Edge cases: null or empty texts and texts without known words score the model's base rate; a
category without positive or without negative rows predicts its rate; no labelled rows at all predicts 0.  Several
label rows of one id: the greatest label.
Ties and repeated rows score alike.  Extra columns are kept by ``accept``, ignored otherwise.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytewords import ALNUM_WORDS, U64, text_slices, word_hashes, words
from .engine import lean, map_batches

#: Categories in the order of the chain, each with its value (0 or 1) over the columns of the label table; the last one decides.
CATEGORIES = {"low_quality": "1 - quality", "toxic": "toxic"}
SAMPLE, FOLDS, SEED, THRESHOLD, LEAST_Z = 16000, 3, 11, 0.3, 4.0


def logistic(rows: np.ndarray, cols: np.ndarray, size: tuple[int, int], dense: np.ndarray, y: np.ndarray, l2: float = 0.3, steps: int = 12) -> np.ndarray:
    """Weights of sparse features (ones at rows, cols), then of dense columns, then the intercept (not penalised).

    Newton steps, each solved by conjugate gradients, so only sparse products are ever formed."""
    n, d = size
    k = dense.shape[1]
    w = np.zeros(d + k + 1)
    if not n or y.min() == y.max():
        w[-1] = np.log((y.sum() + 0.5) / (n - y.sum() + 0.5)) if n and y.max() > 0 else -20.0
        return w
    ridge = np.full(len(w), l2)
    ridge[-1] = 1e-6

    def times(v):
        return np.bincount(rows, weights=v[cols], minlength=n) + dense @ v[d : d + k] + v[-1]

    def back(u):
        return np.concatenate((np.bincount(cols, weights=u[rows], minlength=d), dense.T @ u, [u.sum()]))

    for _ in range(steps):
        p = sigmoid(times(w))
        g, h = back(p - y) + ridge * w, np.maximum(p * (1 - p), 1e-9)
        x, r = np.zeros(len(w)), g.copy()
        q, rr = r.copy(), float(r @ r)
        for _ in range(30):
            if rr < 1e-8:
                break
            hq = back(h * times(q)) + ridge * q
            alpha = rr / float(q @ hq)
            x += alpha * q
            r -= alpha * hq
            new = float(r @ r)
            q, rr = r + new / rr * q, new
        w -= x * min(1.0, 5.0 / max(np.abs(x).max(), 1e-12))
        if np.abs(x).max() < 1e-3:
            break
    return w


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class Chain:
    """vocabulary: sorted word hashes; weights[c]: features, then earlier categories, then intercept."""

    vocabulary: np.ndarray
    weights: list[np.ndarray]
    categories: Sequence[str] = tuple(CATEGORIES)
    held_out: dict = field(default_factory=dict)

    def predict(self, h: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
        """Probabilities, one column per category, each fed the ones before, of n texts given as word hashes."""
        rows, cols = present(self.vocabulary, h, doc)
        d, out = len(self.vocabulary), np.zeros((n, 0))
        for w in self.weights:
            z = np.bincount(rows, weights=w[cols], minlength=n) + out @ w[d:-1] + w[-1]
            out = np.hstack([out, sigmoid(z)[:, None]])
        return out


def present(vocabulary: np.ndarray, h: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (document, vocabulary slot) pairs that occur."""
    if not len(vocabulary) or not len(h):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.minimum(np.searchsorted(vocabulary, h), len(vocabulary) - 1)
    k = vocabulary[at] == h
    pair = np.unique(doc[k] * len(vocabulary) + at[k])
    return pair // len(vocabulary), pair % len(vocabulary)


def fit(texts: Sequence[bytes], labels: Sequence[Sequence[int]], categories: Sequence[str] = tuple(CATEGORIES), folds: int = FOLDS, most_features: int = 4000) -> Chain:
    """Fit a chain on texts with a label for each category."""
    n = len(texts)
    if not n:
        return Chain(np.zeros(0, U64), [np.array([*[0.0] * c, -20.0]) for c in range(len(categories))], categories)
    labels = np.asarray(labels, float).reshape(n, len(categories))
    held_h, held_d = [], []
    column = pa.record_batch([pa.array(texts, pa.large_binary())], ["text"])
    for lo, _, buf, off in text_slices(column, "text"):
        starts, ends, d = words(buf, off, ALNUM_WORDS)
        x = word_hashes(buf, starts, ends, ALNUM_WORDS)
        o = np.lexsort((x, d))
        x, d = x[o], d[o]
        k = np.concatenate(([True], (x[1:] != x[:-1]) | (d[1:] != d[:-1]))) if len(x) else np.zeros(0, bool)
        held_h.append(x[k])
        held_d.append((d[k] + lo).astype(np.int32))
    h, doc = np.concatenate(held_h), np.concatenate(held_d)
    vocab = np.unique(h)
    inv = np.searchsorted(vocab, h).astype(np.int32)
    d1 = doc
    df = np.bincount(inv, minlength=len(vocab)).astype(float)
    chosen = np.zeros(len(vocab), float)
    for c in range(len(categories)):
        rate = labels[:, c].mean()
        if 0 < rate < 1 and len(vocab):
            pos = np.bincount(inv, weights=labels[d1, c], minlength=len(vocab))
            z = (pos - df * rate) / np.sqrt(df * rate * (1 - rate) + 1.0)
            chosen = np.maximum(chosen, np.where(pos >= 2, z, 0))
    keep = np.flatnonzero(chosen >= LEAST_Z)
    keep = keep[np.lexsort((vocab[keep], -chosen[keep]))][:most_features]
    vocabulary = np.sort(vocab[keep])
    rows, cols = present(vocabulary, h, doc.astype(np.int64))
    fold = np.arange(n) % folds
    earlier, weights, held = np.zeros((n, 0)), [], {}

    def model(use: np.ndarray, y: np.ndarray) -> np.ndarray:
        number, k = np.cumsum(use) - 1, use[rows]
        return logistic(number[rows[k]], cols[k], (int(use.sum()), len(vocabulary)), earlier[use], y[use])

    for c, name in enumerate(categories):
        y, oof = labels[:, c], np.zeros(n)
        for f in range(folds):
            w = model(fold != f, y)
            z = np.bincount(rows, weights=w[cols], minlength=n) + earlier @ w[len(vocabulary) : -1] + w[-1]
            oof[fold == f] = sigmoid(z)[fold == f]
        weights.append(model(np.ones(n, bool), y))
        held[name] = {"precision": float(y[oof >= THRESHOLD].mean()) if (oof >= THRESHOLD).any() else None, "recall": float((oof[y > 0] >= THRESHOLD).mean()) if y.any() else None}
        earlier = np.hstack([earlier, oof[:, None]])
    return Chain(vocabulary, weights, categories, held)


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, max_mb: int = 40, categories: dict[str, str] = CATEGORIES) -> Chain:
    """Fit on at most ``sample`` labelled rows and max_mb of text, both drawn by id hash (a documented bound).

    Texts over a 256th of max_mb come after all others, so a long one takes only what the rest leave.  categories: value of
    each over the columns of labels; null is 0, but rows without a value of the last are left out."""
    names, last = tuple(categories), list(categories.values())[-1]
    lab = labels.where(f"doc_id is not null and ({last}) is not null").select(F.col("doc_id").cast("long").alias("_id"), *(F.coalesce(F.expr(e).cast("int"), F.lit(0)).alias(f"_y{c}") for c, e in enumerate(categories.values())))
    lab = lab.groupBy("_id").agg(F.array(*(F.max(f"_y{c}") for c in range(len(names)))).alias("_y")).orderBy(F.xxhash64(F.lit(SEED), "_id"), "_id").limit(sample)
    chosen = {r._id: r._y for r in lab.collect()}
    if not chosen:
        return fit([], [], names)
    ids = docs.sparkSession.createDataFrame(sorted(chosen.items()), "_id long, _y array<int>")
    rows = docs.select(docs["doc_id"].cast("long").alias("_doc"), F.coalesce(docs["text"], F.lit("")).alias("text")).join(F.broadcast(ids), F.col("_doc") == F.col("_id")).select("_id", "_y", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts, left = {}, max_mb << 20
        for b in batches:
            for i, y, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).cast(pa.binary()).to_pylist()):
                if i not in texts and len(t) <= left:
                    texts[i] = (t, y)
                    left -= len(t)
        order = sorted(texts)
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(fit([texts[i][0] for i in order], [texts[i][1] for i in order], names))])], ["chain"])

    # one task fits the chain: its input is bounded by sample and max_mb
    fitted = rows.repartition(1).sortWithinPartitions(F.octet_length("text") > (max_mb << 20) // 256, F.xxhash64(F.lit(SEED), "_id"), "_id").mapInArrow(lean(run), "chain binary").first()
    return pickle.loads(fitted.chain) if fitted else fit([], [], names)


def _scores(batch: pa.RecordBatch, chain: Chain, text_col: str) -> np.ndarray:
    out = np.zeros((batch.num_rows, len(chain.categories)))
    for lo, hi, buf, off in text_slices(batch, text_col):
        starts, ends, doc = words(buf, off, ALNUM_WORDS)
        h = word_hashes(buf, starts, ends, ALNUM_WORDS)
        out[lo:hi] = chain.predict(h, doc, hi - lo)
    return out


def score(docs: DataFrame, chain: Chain, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, a probability per category (rounded to 6 digits) and rejected, one row per row of docs."""
    held = docs.sparkSession.sparkContext.broadcast(chain)

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        p = np.round(_scores(batch, held.value, "text"), 6)
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(p[:, c]) for c in range(p.shape[1])), pa.array(p[:, -1] >= threshold)], ["doc_id", *held.value.categories, "rejected"])

    schema = f"doc_id long, {', '.join(f'{c} double' for c in chain.categories)}, rejected boolean"
    return map_batches(docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text")), run, schema)


def accept(docs: DataFrame, chain: Chain, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs, all columns, whose last category stays under the threshold."""
    held = docs.sparkSession.sparkContext.broadcast(chain)

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        yield batch.filter(pa.array(np.round(_scores(batch, held.value, "text")[:, -1], 6) < threshold))

    return map_batches(docs, run, docs.schema)
