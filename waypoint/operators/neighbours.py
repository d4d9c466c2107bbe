"""Nearest vectors by cosine, as blocks of queries against blocks of vectors in matrix products."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from waypoint.plans.storage import counted, written

#: Vectors of a block.
BLOCK = 4096
_OUT = "id long, other long, cosine double"


def _matrix(column: pa.ChunkedArray) -> np.ndarray:
    flat = column.combine_chunks()
    x = flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1)
    return x / np.maximum(np.sqrt((x * x).sum(axis=1, keepdims=True)), 1e-300)


def _best(k: int):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return pa.table({"id": pa.array([], pa.int64()), "other": pa.array([], pa.int64()), "cosine": pa.array([], pa.float64())})
        ids, others = left["id"].to_numpy(), right["id"].to_numpy()
        cosine = np.round(_matrix(left["vector"]) @ _matrix(right["vector"]).T, 9)
        cosine[ids[:, None] == others[None, :]] = -np.inf
        order = np.lexsort((np.broadcast_to(others, cosine.shape), -cosine), axis=1)[:, :k]
        of = np.repeat(np.arange(len(ids)), order.shape[1])
        at = order.reshape(-1)
        good = cosine[of, at] > -np.inf
        return pa.table({"id": ids[of[good]], "other": others[at[good]], "cosine": cosine[of[good], at[good]]})

    return run


def nearest(vectors: DataFrame, k: int, cells: int | None = None, probes: int = 8) -> DataFrame:
    """``id, other, cosine``: the ``k`` best others of every one of ``vectors`` (id, vector); cosines are rounded to 9 places, ties go to the smaller id.

    Exact without ``cells``. With it, centres are the vectors of least hash (so many rows come to the driver); a cell of more than BLOCK vectors is split in blocks.
    """
    vectors, n = counted(vectors.filter("id is not null and vector is not null"), "vectors")
    if cells is None:
        blocks = max(1, -(-n // BLOCK))
        block = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
        every = F.sequence(F.lit(0), F.lit(blocks - 1))
        left = vectors.select("id", "vector", block.alias("l")).withColumn("r", F.explode(every))
        right = vectors.select("id", "vector", block.alias("r")).withColumn("l", F.explode(every))
        keys = ["l", "r"]
    else:
        centres = [(i, [float(x) for x in r["vector"]]) for i, r in enumerate(vectors.orderBy(F.xxhash64("id")).limit(cells).collect())]
        c = _matrix(pa.chunked_array([pa.array([x for _, x in centres], pa.list_(pa.float64()))])) if centres else np.zeros((1, 1))

        def dealt(batches):
            for b in batches:
                if b.num_rows:
                    near = np.argsort(-(_matrix(pa.chunked_array([b.column(1)])) @ c.T), axis=1, kind="stable")[:, :probes]
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(list(near.astype(np.int32)), pa.list_(pa.int32()))], names=["id", "vector", "near"])

        kind = vectors.schema["vector"].dataType.simpleString()
        dealt_ = written(vectors.mapInArrow(dealt, f"id long, vector {kind}, near array<int>"), "dealt")
        sizes = dealt_.groupBy(F.get("near", F.lit(0)).alias("cell")).count().select("cell", F.ceil(F.col("count") / BLOCK).cast("int").alias("parts"))
        own = dealt_.select("id", "vector", F.get("near", F.lit(0)).alias("cell")).join(F.broadcast(sizes), "cell")
        right = own.select("id", "vector", "cell", F.pmod(F.xxhash64("id"), "parts").cast("int").alias("part"))
        left = dealt_.select("id", "vector", F.explode("near").alias("cell")).join(F.broadcast(sizes), "cell").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        lots = F.pmod(F.xxhash64("id"), F.lit(max(1, -(-n // BLOCK)))).cast("int")
        left = left.withColumn("lot", lots)
        right = right.withColumn("lot", F.explode(F.sequence(F.lit(0), F.lit(max(1, -(-n // BLOCK)) - 1))))
        keys = ["cell", "part", "lot"]
    hits = left.select("id", "vector", *keys).groupBy(*keys).cogroup(right.select(*[F.col(c).alias(c) for c in ("id", "vector", *keys)]).groupBy(*keys)).applyInArrow(_best(k), _OUT)
    order = Window.partitionBy("id").orderBy(F.desc("cosine"), "other")
    return hits.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= k).select("id", "other", "cosine")
