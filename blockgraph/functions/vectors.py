"""Similarity of array columns."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

QUERY_BLOCK = 2_000


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a, b) -> Column:
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def _matrix(column: pa.Array) -> np.ndarray:
    return np.array(column.to_pylist(), dtype=np.float64).reshape(len(column), -1)


def nearest(rows: DataFrame, queries: DataFrame, k: int, block: int = QUERY_BLOCK) -> DataFrame:
    """src, dst, cosine (rounded to 9 digits): the k rows most alike to each query, itself left out, ties by id.

    Queries go in blocks of ``block`` vectors, one broadcast matrix at a time; each task keeps its own k best per query, and
    those meet by query. Exact."""
    sc, out = rows.sparkSession.sparkContext, None
    blocks = max(1, -(-queries.count() // block))
    for at in range(blocks):
        part = queries.select("vec_id", "embedding").where(F.pmod("vec_id", F.lit(blocks)) == at).toArrow() if blocks > 1 else queries.select("vec_id", "embedding").toArrow()
        q = _matrix(part["embedding"].combine_chunks())
        q /= np.sqrt((q * q).sum(1, keepdims=True))
        shared = sc.broadcast((part["vec_id"].to_numpy(), q))

        def best(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            names, q = shared.value
            have_id, have = np.full((len(names), 0), -1), np.full((len(names), 0), -np.inf)
            for b in batches:
                x = _matrix(b.column("embedding"))
                x /= np.sqrt((x * x).sum(1, keepdims=True))
                d = b.column("vec_id").to_numpy()
                c = np.round(q @ x.T, 9)
                c[names[:, None] == d[None, :]] = -np.inf
                have, have_id = np.hstack([have, c]), np.hstack([have_id, np.broadcast_to(d, c.shape)])
                order = np.lexsort((have_id, -have), axis=1)[:, :k]
                have, have_id = np.take_along_axis(have, order, 1), np.take_along_axis(have_id, order, 1)
            ok = np.isfinite(have)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(names, ok.sum(1))), pa.array(have_id[ok].astype(np.int64)), pa.array(have[ok])], ["src", "dst", "cosine"])

        found = rows.select("vec_id", "embedding").mapInArrow(best, "src long, dst long, cosine double")
        out = found if out is None else out.unionByName(found)
    top = out.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cosine"), "dst"))).where(F.col("r") <= k)
    return top.drop("r")
