"""Exact top-k inner-product search by distributed histogram selection.

Every pass scores all rows against a block of queries (one matrix product per Arrow batch).  Passes
refine, for each query, a histogram of scores until one score value, the k-th largest, is left; a last
pass keeps what lies above it and breaks ties at it by the smaller id.  No pass moves more than a few
counts or k rows per query and batch, so nothing depends on how many rows tie.

Queries are handled in blocks of bounded size (``block`` queries, ``BLOCK_BYTES`` of components), because a query set
that is a share of the rows grows with them; a block is all that is ever broadcast.  Where there are several, each
one's result is written and its broadcast released before the next, so neither plan nor memory grows with their number.

Defined cases: vectors that are null, or hold null or non-finite components, and rows without id take
no part; only vectors of the query's length are its candidates; rows with the query's id are its own.
An empty table gives an empty result.  Components are floor(scale * x) with x as double; scores are
exact integers while norms' products stay under 2**53.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import scratch

_HITS = "qno long, query_id long, vec_id long, score long"
_OUT = "query_id long, rank int, vec_id long, score long"
BLOCK_BYTES = 16 << 20


def _usable(df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    finite = ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    cast = df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("v"))
    return cast.where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & finite)


def _matrices(batch: pa.RecordBatch, scale: float) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(length, ids, quantised rows) for each vector length in the batch."""
    column = batch.column(1)
    lengths = np.diff(column.offsets.to_numpy())
    values = np.floor(scale * column.flatten().to_numpy(zero_copy_only=False))
    ids, starts = batch.column(0).to_numpy(zero_copy_only=False), column.offsets.to_numpy()[:-1] - column.offsets[0].as_py()
    for n in np.unique(lengths):
        at = np.flatnonzero(lengths == n)
        yield int(n), ids[at], values[starts[at][:, None] + np.arange(n)]


def exact_topk(vectors: DataFrame, queries: DataFrame, k: int = 10, scale: float = 1024.0, id_col: str = "vec_id", vec_col: str = "embedding", block: int = 1024, bins: int = 4096) -> DataFrame:
    """query_id, rank, vec_id, score: the k best rows of ``vectors`` for every row of ``queries``."""
    spark = vectors.sparkSession
    rows, asked = _usable(vectors, id_col, vec_col), _usable(queries, id_col, vec_col)
    size = asked.agg(F.count("*").alias("n"), F.max(F.size("v")).alias("widest")).first()
    block = max(1, min(block, BLOCK_BYTES // (8 * max(1, size["widest"] or 1))))
    parts = max(1, -(-size["n"] // block))
    norm = rows.select(F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + F.pow(F.floor(x * scale), 2))).alias("m")).first()["m"] or 0.0
    order, folder, done = W.partitionBy("qno").orderBy(F.desc("score"), "vec_id"), scratch(spark, "topk"), []
    for part in range(parts):
        mine = asked if parts == 1 else asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(parts)) == part)
        held = sorted((r["vec_id"], tuple(r["v"])) for r in mine.collect())  # about ``block`` rows
        if not held:
            continue
        hits, shared = _one_block(rows, held, k, scale, bins, norm)
        best = hits.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
        if parts == 1:
            return best
        done.append(f"{folder}/{part:06d}")
        best.write.parquet(done[-1])
        shared.unpersist()
    return spark.read.schema(_OUT).parquet(*done) if done else spark.createDataFrame([], _OUT)


def _one_block(rows: DataFrame, held: list, k: int, scale: float, bins: int, norm: float) -> tuple[DataFrame, object]:
    spark = rows.sparkSession
    qids = np.array([i for i, _ in held], np.int64)
    groups: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    for n in {len(v) for _, v in held}:
        at = np.array([j for j, (_, v) in enumerate(held) if len(v) == n])
        groups[n] = at, np.floor(scale * np.array([held[j][1] for j in at], np.float64).reshape(len(at), n))
    shared = spark.sparkContext.broadcast((qids, groups))

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(query numbers, ids, scores) by vector length and batch; a query's own rows have the least score."""
        all_ids, by_length = shared.value
        for batch in batches:
            for n, ids, matrix in _matrices(batch, scale):
                if n in by_length:
                    at, wanted = by_length[n]
                    for i in range(0, len(ids), 4096):
                        s = (wanted @ matrix[i : i + 4096].T).astype(np.int64)
                        s[all_ids[at][:, None] == ids[None, i : i + 4096]] = np.iinfo(np.int64).min
                        yield at, ids[i : i + 4096], s

    own = np.iinfo(np.int64).min
    bound = np.array([0] * len(held), np.int64)
    for at, q in groups.values():
        bound[at] = np.ceil(np.sqrt((q**2).sum(axis=1) * norm)).astype(np.int64) + 1
    low, size, left = -bound, 2 * bound + 1, np.full(len(held), k)
    least = np.full(len(held), own, np.int64)  # of scores that are kept; own: all of them
    open_ = np.ones(len(held), bool)

    while open_.any():
        step = np.maximum(1, -(-size // bins))

        def counts(batches: Iterator[pa.RecordBatch], low=low, size=size, step=step, left=left, open_=open_) -> Iterator[pa.RecordBatch]:
            for at, _, s in scored(batches):
                at_open = np.flatnonzero(open_[at])
                if not len(at_open):
                    continue
                q, s = at[at_open], s[at_open]
                inside = (s >= low[q][:, None]) & (s < (low + size)[q][:, None])
                s = np.where(inside, s, own)
                if s.shape[1] > k:  # what is under this batch's own k-th value can't be the k-th of all
                    floor = np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k]
                    inside &= s >= floor[:, None]
                i, j = np.nonzero(inside)
                keys, n = np.unique(np.stack([q[i], (s[i, j] - low[q[i]]) // step[q[i]]]), axis=1, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(keys[0], pa.int64()), pa.array(keys[1], pa.int64()), pa.array(n, pa.int64())], names=["qno", "bin", "n"])

        summed = rows.mapInArrow(counts, "qno long, bin long, n long").groupBy("qno", "bin").agg(F.sum("n").alias("n"))
        above = F.sum("n").over(W.partitionBy("qno").orderBy(F.desc("bin")))
        ranked = summed.withColumn("upto", above)
        due = spark.createDataFrame([(int(q), int(left[q])) for q in np.flatnonzero(open_)], "qno long, due long")  # a row a query of the block
        hit = ranked.join(F.broadcast(due), "qno").where((F.col("upto") >= F.col("due")) & (F.col("upto") - F.col("n") < F.col("due")))
        got = {r["qno"]: r for r in hit.collect()}
        low, size, left, open_ = low.copy(), size.copy(), left.copy(), open_.copy()
        for q in np.flatnonzero(open_):
            if q not in got:  # fewer than k candidates: all of them
                open_[q] = False
                continue
            r = got[q]
            low[q], size[q], left[q] = low[q] + r["bin"] * step[q], step[q], left[q] - (r["upto"] - r["n"])
            if step[q] == 1:
                least[q], open_[q] = low[q], False

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for at, ids, s in scored(batches):
            order = np.argsort(ids, kind="stable")
            ids, s = ids[order], s[:, order]
            out = []
            for row, q in enumerate(at):
                j = np.flatnonzero((s[row] >= least[q]) & (s[row] > own))
                if len(j) > k:
                    j = j[np.argsort(-s[row, j], kind="stable")[:k]]
                out.append((np.full(len(j), q), np.full(len(j), qids[q]), ids[j], s[row, j]))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), pa.int64()) for c in zip(*out, strict=True)], names=["qno", "query_id", "vec_id", "score"])

    return rows.mapInArrow(kept, _HITS), shared


ORACLE = """
WITH t AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
         CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM t q JOIN t c ON q.vec_id <> c.vec_id
  WHERE q.vec_id % 100 = 0
), r AS (
  SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""
