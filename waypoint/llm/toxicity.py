"""Toxicity by subword-bag embeddings: averaged vectors into a linear softmax, both trained together in numpy.

A word's bag holds the word and its n-grams of 3 to 7 bytes, with a space at either end, hashed into a table
of fixed size; n-grams let an unseen misspelling share the vectors of the word that it comes from. A word's
vector is the mean of its bag's vectors, a passage's vector is the mean over its words (a text is cut into
passages of 8 words), and a linear softmax maps it to the two classes. A text is toxic if any passage is: its
probability is 1 minus the product of the passages' chances of being clean, in training as in scoring, so one bad
sentence in a long text isn't averaged away. Since all is linear up to the softmax, scoring needs one number for
each bag entry (its vector's projection on the difference of the two classes), a table of fixed size (4 MB)
whatever the corpus, which is what goes to the executors. A last number moves the scores so that THRESHOLD is near the best cut (by F1, on the side of few rejections) on
training rows that the model was not fitted on: a quarter of them, or of small samples each quarter in turn. Held-out rows choose nothing.

Edge cases: a null or empty text (or one of white space) is one passage without words, which scores the bias alone; very
long texts are read whole, a step of words at a time; repeated rows score alike; with no labelled row, or rows of one
class alone, the model is the prior; extra columns are ignored by the query and kept by :func:`accepted`.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waypoint.llm import packed
from waypoint.llm.labelled import MOST_BYTES, fitted, fold

U64 = np.uint64
BITS = 20
GRAMS = (3, 4, 5, 6, 7)
DIM = 8
THRESHOLD = 0.7
#: Words of a passage.
PASSAGE = 8
#: Labelled rows that the model is fitted on at most (and their texts' bytes, see ``labelled.MOST_BYTES``).
MOST_ROWS = 4000


@dataclass(frozen=True)
class Model:
    table: np.ndarray  # float32, one projection for each bag entry
    bias: float
    shift: float = 0.0  # added to the logit of a text's probability


def word_bags(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Table places of all bag entries of the words, and where each word's begin. ``raw``: lower-cased bytes."""
    lens = ends - starts
    # every word with a space on either side, one after another
    wide = lens + 2
    first = np.concatenate([[0], np.cumsum(wide)])
    own = np.full(first[-1], 32, dtype=np.uint8)
    inner = np.arange(int(lens.sum())) - np.repeat(np.concatenate([[0], np.cumsum(lens)[:-1]]), lens)
    own[inner + np.repeat(first[:-1] + 1, lens)] = raw[inner + np.repeat(starts, lens)]
    prefix = packed.prefix_hash(own)
    word = np.repeat(np.arange(len(lens)), wide)
    place = np.arange(first[-1])
    hashes = [packed.span_hash(prefix, first[:-1], first[1:])]
    owner = [np.arange(len(lens))]
    for n in GRAMS:
        at = place[(place + n <= first[word + 1])]
        hashes.append(packed.span_hash(prefix, at, at + n))
        owner.append(word[at])
    h, o = np.concatenate(hashes), np.concatenate(owner)
    order = np.argsort(o, kind="stable")
    return (h[order] >> U64(64 - BITS)).astype(np.int64), np.concatenate([[0], np.cumsum(np.bincount(o, minlength=len(lens)))])


def passages(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Start, end, hash and passage of every word of a run of texts, and the text of each passage."""
    s, e, doc = packed.words(raw, off)
    n = len(off) - 1
    count = np.bincount(doc, minlength=n) if len(doc) else np.zeros(n, dtype=np.int64)
    per = np.maximum(-(-count // PASSAGE), 1)
    first_word, first_passage = np.cumsum(count) - count, np.cumsum(per) - per
    passage = first_passage[doc] + (np.arange(len(doc)) - first_word[doc]) // PASSAGE if len(doc) else np.zeros(0, dtype=np.int64)
    return s, e, packed.span_hash(packed.prefix_hash(raw), s, e), passage, np.repeat(np.arange(n), per)


def _sample(raw: np.ndarray, off: np.ndarray):
    """:func:`passages` of a whole sample, a piece at a time, with the distinct words numbered."""
    parts, n_passages = [], 0
    for i, j in packed.pieces(off):
        s, e, h, passage, text_of = passages(raw[off[i] : off[j]], off[i : j + 1] - off[i])
        parts.append(((s + off[i]).astype(np.int64), (e - s).astype(np.int32), h, (passage + n_passages).astype(np.int32), (text_of + i).astype(np.int32)))
        n_passages += len(text_of)
    s, size, h, passage, text_of = (np.concatenate(x) for x in zip(*parts, strict=True))
    del parts
    _, at, word = np.unique(h, return_index=True, return_inverse=True)
    return s[at], s[at] + size[at], passage, word.astype(np.int32), text_of


def _means(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Means of consecutive groups; an empty group's is 0."""
    counts = np.diff(first)
    out = np.zeros((len(counts), *values.shape[1:]), dtype=values.dtype)
    full = counts > 0
    if full.any():
        out[full] = np.add.reduceat(values, first[:-1][full], axis=0)
        out[full] /= counts[full].reshape(-1, *[1] * (values.ndim - 1))
    return out


class _Sparse:
    """A row-averaging matrix with its transpose, by sorted sums, a dimension at a time so that little memory is in use."""

    def __init__(self, cols: np.ndarray, first: np.ndarray, n_cols: int):
        self.cols, self.counts = cols.astype(np.int32), np.diff(first)
        self.full_rows, self.first = self.counts > 0, first[:-1][self.counts > 0]
        rows = np.repeat(np.arange(len(self.counts), dtype=np.int32), self.counts)
        self.t_rows = rows[np.argsort(cols, kind="stable")]
        t_counts = np.bincount(cols, minlength=n_cols)
        self.full_cols, self.t_first = t_counts > 0, (np.cumsum(t_counts) - t_counts)[t_counts > 0]

    def times(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros((len(self.counts), x.shape[1]), dtype=np.float32)
        if self.full_rows.any():
            for k in range(x.shape[1]):
                out[self.full_rows, k] = np.add.reduceat(x[:, k].copy()[self.cols], self.first)
        return out / np.maximum(self.counts, 1)[:, None].astype(np.float32)

    def back(self, g: np.ndarray) -> np.ndarray:
        out = np.zeros((len(self.full_cols), g.shape[1]), dtype=np.float32)
        if self.full_cols.any():
            each = 1 / np.maximum(self.counts, 1).astype(np.float32)
            for k in range(g.shape[1]):
                out[self.full_cols, k] = np.add.reduceat((g[:, k] * each)[self.t_rows], self.t_first)
        return out


def fit(texts: pa.Array, y: np.ndarray, epochs: int = 50, rate: float = 0.5, decay: float = 3e-3, least_texts: int = 3, start: float = -5.0, seed: int = 7) -> Model:
    """Train the vectors and the softmax together by Adam on the whole sample."""
    n = len(y)
    prior = (float(y.sum()) + 1.0) / (n + 2.0)
    if n == 0 or y.min() == y.max():
        # no passage says anything: every text, however long, gets the prior
        return Model(np.zeros(1 << BITS, dtype=np.float32), -60.0, float(np.log(prior / (1 - prior)) - _logit(np.zeros(1))[0]))
    raw, off = packed.texts(texts)
    raw = packed.lowered(raw)
    ws, we, passage, word, text_of = _sample(raw, off)
    # words of one or two texts teach nothing that holds elsewhere; they count as words with the zero vector
    pairs = np.unique(text_of[passage].astype(np.int64) * len(ws) + word)
    used = np.bincount(pairs % max(len(ws), 1), minlength=len(ws)) >= least_texts
    del pairs
    number = (np.cumsum(used) - 1).astype(np.int32)
    ok = used[word]
    size = np.bincount(passage, minlength=len(text_of))
    passage, word = passage[ok], number[word[ok]]
    ws, we = ws[used], we[used]
    ids, sizes = [np.zeros(0, dtype=np.int32)], [np.zeros(1, dtype=np.int64)]
    for k in range(0, len(ws), 1 << 14):
        some, begins = word_bags(raw, ws[k : k + (1 << 14)], we[k : k + (1 << 14)])
        ids.append(some.astype(np.int32))
        sizes.append(np.diff(begins))
    first = np.cumsum(np.concatenate(sizes))
    buckets, ids = np.unique(np.concatenate(ids), return_inverse=True)
    bags = _Sparse(ids, first, len(buckets))
    kept = np.bincount(passage, minlength=len(text_of))
    parts = _Sparse(word, np.concatenate([[0], np.cumsum(kept)]), int(used.sum()))
    share = (kept / np.maximum(size, 1)).astype(np.float32)[:, None]
    begin = np.searchsorted(text_of, np.arange(n))
    rng = np.random.default_rng(seed)
    vectors = rng.normal(0, 0.01, (len(buckets), DIM)).astype(np.float32)
    heads = rng.normal(0, 0.5, (DIM, 2)).astype(np.float32)
    b = np.array([0.0, start], dtype=np.float32)
    params = [vectors, heads, b]
    moments = [(np.zeros_like(p), np.zeros_like(p)) for p in params]
    for t in range(1, epochs + 1):
        mean = parts.times(bags.times(vectors)) * share
        z = mean @ heads + b
        p = 1 / (1 + np.exp(np.clip(z[:, 0] - z[:, 1], -30, 30)))
        any_bad = -np.expm1(np.add.reduceat(np.log1p(-np.minimum(p, 1 - 1e-6)), begin))
        # of the log loss by the difference of the two logits
        d = np.where(y[text_of] == 1, -p * ((1 - any_bad) / np.maximum(any_bad, 1e-9))[text_of], p)
        g = np.stack([-d, d], axis=1).astype(np.float32) / n
        grads = [bags.back(parts.back((g @ heads.T) * share)) + decay / n * vectors, mean.T @ g, g.sum(axis=0)]
        step = rate * min(1.0, 2.0 * (1 - t / (epochs + 1)))
        for q, d, (m, v) in zip(params, grads, moments, strict=True):
            m *= 0.9
            m += 0.1 * d
            v *= 0.99
            v += 0.01 * d * d
            q -= step * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
    table = np.zeros(1 << BITS, dtype=np.float32)
    table[buckets] = vectors @ (heads[:, 1] - heads[:, 0])
    return Model(table, float(b[1] - b[0]))


def scores(model: Model, column: pa.Array) -> np.ndarray:
    """Probability of label 1 of every text."""
    raw, off = packed.texts(column)
    out = np.zeros(len(off) - 1)
    for i, j in packed.pieces(off):
        part, edges = packed.lowered(raw[off[i] : off[j]]), off[i : j + 1] - off[i]
        s, e, h, passage, text_of = passages(part, edges)
        _, at, word = np.unique(h, return_index=True, return_inverse=True)
        s, e = s[at], e[at]
        value = np.zeros(len(s))
        for k in range(0, len(s), 1 << 16):
            ids, first = word_bags(part, s[k : k + (1 << 16)], e[k : k + (1 << 16)])
            value[k : k + (1 << 16)] = _means(model.table[ids].astype(np.float64), first)
        n = len(text_of)
        mean = np.bincount(passage, weights=value[word], minlength=n) / np.maximum(np.bincount(passage, minlength=n), 1)
        clean = -np.logaddexp(0, mean + model.bias)
        out[i:j] = -np.expm1(np.bincount(text_of, weights=clean, minlength=j - i))
    return 1 / (1 + np.exp(-(_logit(out) + model.shift)))


def _logit(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, 1e-12, 1 - 1e-12)
    return np.log(p) - np.log1p(-p)


def best_cut(score: np.ndarray, y: np.ndarray) -> float:
    """Between two scores that occur: the highest cut whose F1 comes near the best one, so that few clean texts are rejected."""
    order = np.argsort(-score, kind="stable")
    s, hits = score[order], np.cumsum(y[order])
    f1 = 2 * hits / (np.arange(1, len(s) + 1) + y.sum())
    f1[:-1][s[1:] == s[:-1]] = -1  # equal scores stay together
    first = int(np.flatnonzero(f1 >= f1.max() - 0.01)[0])
    return float((s[first] + (s[first + 1] if first + 1 < len(s) else s[first] - 1.0)) / 2)


def calibrated(texts: pa.Array, y: np.ndarray, parts: int = 4, enough: int = 2000) -> Model:
    """:func:`fit` on all rows, with the scores moved by what rows left out of a fit show."""
    model = fit(texts, y)
    if len(y) < parts or y.min() == y.max():
        return model
    part = np.arange(len(y)) % parts
    seen, score = np.zeros(len(y), dtype=bool), np.zeros(len(y))
    for k in range(1 if len(y) >= enough else parts):
        rest, out = part != k, part == k
        if y[rest].min() != y[rest].max():
            seen |= out
            score[out] = _logit(scores(fit(texts.filter(pa.array(rest)), y[rest]), texts.filter(pa.array(out))))
    if not y[seen].any():
        return model
    return Model(model.table, model.bias, float(np.log(THRESHOLD / (1 - THRESHOLD)) - best_cut(score[seen], y[seen])))


def trained(docs: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS, most_bytes: int = MOST_BYTES) -> Model:
    def run(texts: pa.Array, y: np.ndarray) -> tuple[np.ndarray, tuple[float, ...]]:
        model = calibrated(texts, y)
        return model.table, (model.bias, model.shift)

    table, numbers = fitted(docs, labels, "toxic", run, most_rows, most_bytes)
    return Model(table, *numbers)


def with_scores(docs: DataFrame, model: Model, scorer=scores, name: str = "score") -> DataFrame:
    """``doc_id`` and the score of every row of ``docs``. The model is of fixed size, so it is broadcast."""
    spark = docs.sparkSession
    sent = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scorer(sent.value, batch.column(1)))], names=["doc_id", name])

    rows = docs.select("doc_id", F.col("text").cast("binary").alias("text"))
    return rows.mapInArrow(run, rows.select("doc_id").schema.add(name, "double"))


def scored(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, most_rows: int = MOST_ROWS) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every document."""
    out = with_scores(docs, trained(docs, labels, most_rows))
    return out.select("doc_id", (fold(F.col("doc_id"), 3) == 1).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def accepted(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, most_rows: int = MOST_ROWS) -> DataFrame:
    """The rows of ``docs`` that score under ``threshold``, with all their columns."""
    model = trained(docs, labels, most_rows)
    sent = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(scores(sent.value, batch.column(at)) < threshold))

    return docs.mapInArrow(run, docs.schema)
