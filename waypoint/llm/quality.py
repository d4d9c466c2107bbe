"""Quality by hashed word n-grams and logistic regression, trained with follow-the-regularised-leader updates.

Beside the n-grams of words there are n-grams of the words' shapes, which tell junk from prose by case, digits and marks
where the words themselves are new.

Tokens are runs of letters, of digits, or of one punctuation mark. Two sequences of a text give n-grams: the
lower-cased tokens (of 1 and 2), and the tokens' shapes (of 1 to 3: lower, capitalised, upper, digits, the mark
itself with 1, 2 or more repeats, and whether the token repeats the one before). An n-gram's value is the
square root of its share of the text's n-grams of that kind, so texts of all lengths have rows of equal norm. All are hashed into a
table of fixed size, and a text's score is the sparse dot product of its n-grams with the table's weights. The weights follow
the per-coordinate schedule with L1, which leaves most places 0; the table (4 MB) is all that goes to the executors.

Edge cases: a null or empty text scores the bias alone; very long texts are read whole; repeated rows score alike;
without labelled rows of both classes the model is the prior; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waypoint.llm import packed
from waypoint.llm.labelled import MOST_BYTES, fitted, fold
from waypoint.llm.toxicity import with_scores

U64 = np.uint64
BITS = 20
THRESHOLD = 0.5
#: Labelled rows that the model is fitted on at most (and their texts' bytes, see ``labelled.MOST_BYTES``).
MOST_ROWS = 8000

# Kinds of bytes: 0 white space, 1 lower letter (and bytes over 127), 2 upper letter, 3 digit, 4 other.
_kind = np.full(256, 4, dtype=np.uint8)
_kind[[0x20, 9, 10, 11, 12, 13]] = 0
_kind[97:123] = 1
_kind[128:] = 1
_kind[65:91] = 2
_kind[48:58] = 3


@dataclass(frozen=True)
class Model:
    table: np.ndarray  # float32
    bias: float


def _tokens(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Start, end, text, hash and shape of every token."""
    n = len(raw)
    kind = _kind[raw]
    group = np.where(kind == 2, 1, kind)  # letters of either case are one run
    cut = np.ones(n, dtype=bool)
    cut[1:] = (group[1:] != group[:-1]) | ((kind[1:] == 4) & (raw[1:] != raw[:-1]))
    edge = np.zeros(n + 1, dtype=bool)
    edge[off] = True
    cut |= edge[:-1]
    starts = np.flatnonzero(cut)
    ends = np.append(starts[1:], n)
    ink = kind[starts] != 0
    starts, ends = starts[ink], ends[ink]
    doc = np.searchsorted(off, starts, "right") - 1
    h = packed.span_hash(packed.prefix_hash(packed.lowered(raw)), starts, ends)
    first = kind[starts]
    upper = np.concatenate([[0], np.cumsum(kind == 2)])
    n_upper = upper[ends] - upper[starts]
    length = ends - starts
    shape = np.select(
        [first == 3, first == 4, (n_upper == length) & (length > 1), (n_upper >= 1) & (first == 2), n_upper > 0],
        [10 + np.minimum(length, 5), 1000 + raw[starts].astype(np.int64) * 4 + np.minimum(length, 3), 3, 2, 4], 1,
    )
    again = np.zeros(len(h), dtype=np.int64)
    again[1:] = (h[1:] == h[:-1]) & (doc[1:] == doc[:-1])
    return starts, ends, doc, h, (shape * 2 + again).astype(U64)


def _grams(seq: np.ndarray, doc: np.ndarray, k: int, salt: int) -> tuple[np.ndarray, np.ndarray]:
    if len(seq) < k:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    m = len(seq) - k + 1
    h = np.full(m, salt * 0x9E3779B9 + k, dtype=U64)
    for j in range(k):
        h = packed.mixed(h * U64(packed.BASE) + seq[j : j + m])
    ok = doc[:m] == doc[k - 1 :]
    return (h[ok] >> U64(64 - BITS)).astype(np.int64), doc[:m][ok]


def features(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text, table place and value of every n-gram of a run of texts."""
    _, _, doc, h, shape = _tokens(raw, off)
    docs, places, values = [], [], []
    n = len(off) - 1
    for seq, salt, orders in ((h, 1, (1, 2)), (shape, 2, (1, 2, 3))):
        for k in orders:
            place, of = _grams(seq, doc, k, salt)
            key, count = np.unique((of << BITS) | place, return_counts=True)
            of, place = key >> BITS, key & ((1 << BITS) - 1)
            total = np.bincount(of, weights=count, minlength=n)
            docs.append(of)
            places.append(place)
            values.append(np.sqrt(count / total[of]))
    return np.concatenate(docs), np.concatenate(places), np.concatenate(values)


def fit(texts: pa.Array, y: np.ndarray, epochs: int = 4, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.02, l2: float = 0.1) -> Model:
    """One pass after another over the sample, a text at a time."""
    prior = (float(y.sum()) + 1.0) / (len(y) + 2.0)
    bias = float(np.log(prior / (1 - prior)))
    size = 1 << BITS
    if len(y) == 0 or y.min() == y.max():
        return Model(np.zeros(size, dtype=np.float32), bias)
    raw, off = packed.texts(texts)
    z, n = np.zeros(size + 1), np.zeros(size + 1)
    z[size] = -bias * beta / alpha
    for epoch in range(epochs):
        for i, j in packed.pieces(off):
            doc, place, value = features(raw[off[i] : off[j]], off[i : j + 1] - off[i])
            order = np.argsort(doc, kind="stable")
            place, value = place[order], value[order]
            first = np.searchsorted(doc[order], np.arange(j - i + 1))
            for t in range(j - i):
                at = np.append(place[first[t] : first[t + 1]], size)
                x = np.append(value[first[t] : first[t + 1]], 1.0)
                w = _weights(z[at], n[at], alpha, beta, np.where(at == size, 0.0, l1), np.where(at == size, 0.0, l2))
                p = 1 / (1 + np.exp(-np.clip(w @ x, -35, 35)))
                g = (p - y[i + t]) * x
                # places may repeat in a text, by collisions
                now = n[at] + g * g
                np.add.at(z, at, g - (np.sqrt(now) - np.sqrt(n[at])) / alpha * w)
                np.add.at(n, at, g * g)
    last = np.zeros(size + 1)
    w = _weights(z, n, alpha, beta, np.append(np.full(size, l1), 0.0), np.append(np.full(size, l2), 0.0))
    last[:] = w
    return Model(last[:size].astype(np.float32), float(last[size]))


def _weights(z, n, alpha, beta, l1, l2):
    return np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((beta + np.sqrt(n)) / alpha + l2))


def scores(model: Model, column: pa.Array) -> np.ndarray:
    """Probability of label 1 of every text."""
    raw, off = packed.texts(column)
    out = np.zeros(len(off) - 1)
    for i, j in packed.pieces(off):
        doc, place, value = features(raw[off[i] : off[j]], off[i : j + 1] - off[i])
        dot = np.bincount(doc, weights=model.table[place] * value, minlength=j - i)
        out[i:j] = 1 / (1 + np.exp(-np.clip(dot + model.bias, -60, 60)))
    return out


def trained(docs: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS, most_bytes: int = MOST_BYTES) -> Model:
    def run(texts: pa.Array, y: np.ndarray) -> tuple[np.ndarray, tuple[float, ...]]:
        model = fit(texts, y)
        return model.table, (model.bias,)

    table, numbers = fitted(docs, labels, "quality", run, most_rows, most_bytes)
    return Model(table, *numbers)


def scored(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, most_rows: int = MOST_ROWS) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every document."""
    out = with_scores(docs, trained(docs, labels, most_rows), scores)
    return out.select("doc_id", (fold(F.col("doc_id"), 3) == 1).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
