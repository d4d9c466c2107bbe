"""Labelled rows for the two classifiers: which may be learnt from, a sample of bounded size, and a fit in one task.

The sample is bounded by rows and by bytes, both parameters of the operators: labelled rows come in a fixed pseudo-random order of
ids, each with its whole text, until either bound is reached; a text that alone is larger than the bytes left is passed over. The fit
runs in one task of an executor (which starts anew if that executor is lost), and only the model, whose size is fixed, comes to the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

HELD = "held_out"
#: Bytes of all texts that a model is fitted on, at most.
MOST_BYTES = 32 << 20


def fold(doc_id: Column, of: int) -> Column:
    """crc32 of the id as text, modulo ``of``; a null id counts as the text of length 0."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % of


def training_rows(docs: DataFrame, labels: DataFrame, label: str, most: int, most_bytes: int = MOST_BYTES) -> DataFrame:
    """``place, doc_id, y, text`` of at most ``most`` labelled ids whose fold of 3 is not 1; ids with several labels take the largest."""
    open_rows = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & (fold(F.col("doc_id"), 3) != 1))
    place = F.xxhash64("doc_id").alias("place")
    ids = open_rows.groupBy("doc_id").agg(F.max(F.col(label).cast("int")).alias("y")).select(place, "doc_id", "y").orderBy("place", "doc_id").limit(most)
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text")
    return docs.select("doc_id", text).filter(F.length("text") <= most_bytes).join(F.broadcast(ids), "doc_id").select("place", "doc_id", "y", "text")


def gathered(batches: Iterator[pa.RecordBatch], most: int, most_bytes: int) -> tuple[pa.Array, np.ndarray]:
    """The texts and labels of rows in order (``place, doc_id, y, text``), up to both bounds."""
    texts, y, size = [], [], 0
    for batch in batches:
        n_bytes = np.asarray(pc.binary_length(batch.column(3)))
        take = []
        for k, n in enumerate(n_bytes.tolist()):
            if len(y) + len(take) < most and size + n <= most_bytes:
                take.append(k)
                size += n
        texts.append(batch.column(3).take(pa.array(take, pa.int64())))
        y.extend(batch.column(2).take(pa.array(take, pa.int64())).to_pylist())
    return (pa.concat_arrays(texts) if texts else pa.array([], pa.binary())), np.array(y, dtype=np.int64)


def fitted(docs: DataFrame, labels: DataFrame, label: str, fit: Callable, most: int, most_bytes: int = MOST_BYTES) -> tuple[np.ndarray, tuple[float, ...]]:
    """What ``fit(texts, y)`` returns, a float32 table and some numbers; it runs in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, numbers = fit(*gathered(batches, most, most_bytes))
        yield pa.RecordBatch.from_arrays([pa.array([table.astype(np.float32).tobytes()], pa.binary()), pa.array([list(numbers)], pa.list_(pa.float64()))], names=["table", "numbers"])

    rows = training_rows(docs, labels, label, most, most_bytes)
    row = rows.repartition(1).sortWithinPartitions("place", "doc_id", "text").mapInArrow(run, "table binary, numbers array<double>").first()
    if row is None:
        return fit(pa.array([], pa.binary()), np.zeros(0, dtype=np.int64))
    return np.frombuffer(row["table"], dtype=np.float32), tuple(row["numbers"])
