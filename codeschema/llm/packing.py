"""Packing of token streams into windows by best-fit decreasing.

Documents longer than a window are first cut into full windows; what remains of each document is
packed by best-fit decreasing.  Pieces of one length are interchangeable, so the packing is decided on
the histogram of lengths (at most ``window - 1`` counts, whatever the corpus): a segment tree indexed
by remaining capacity finds the tightest open windows for each length in turn, and whole runs of
equal windows are filled at once.  Every piece then reads its window off its rank among the pieces of
its length, which is found without any global sort: ranks in ``RANK_GROUPS`` groups by hash plus
the groups' counts.

Defined cases: a null text is an empty one and still ends with the end id; repeated rows are packed
separately; null ids are kept; a text of any length is cut whole; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import in_pieces, slices, written
from .bpe_codec import codec

RANK_GROUPS = 256  # bounds the table of group counts that is broadcast: RANK_GROUPS * window rows


class CapacityTree:
    """Segment tree over capacities 0..window; each leaf holds runs (first window, how many) of open windows."""

    def __init__(self, window: int) -> None:
        self.leaves = 1 << window.bit_length()
        self.any = [False] * (2 * self.leaves)
        self.runs: list[list[tuple[int, int]]] = [[] for _ in range(window + 1)]

    def _mark(self, capacity: int) -> None:
        node = capacity + self.leaves
        self.any[node] = bool(self.runs[capacity])
        while node > 1:
            node //= 2
            self.any[node] = self.any[2 * node] or self.any[2 * node + 1]

    def push(self, capacity: int, first: int, n: int) -> None:
        if n and capacity:
            self.runs[capacity].append((first, n))
            self._mark(capacity)

    def pop(self, capacity: int) -> tuple[int, int]:
        got = self.runs[capacity].pop()
        self._mark(capacity)
        return got

    def tightest(self, least: int) -> int | None:
        """The smallest capacity of at least ``least`` with an open window."""
        node = least + self.leaves
        if self.any[node]:
            return least
        while node > 1:
            if node % 2 == 0 and self.any[node + 1]:
                node += 1
                while node < self.leaves:
                    node = 2 * node if self.any[2 * node] else 2 * node + 1
                return node - self.leaves
            node //= 2
        return None


def schedule(counts: dict[int, int], window: int) -> tuple[np.ndarray, int]:
    """Rows (length, first rank, first window, pieces a window, offset) and the number of windows.

    The piece of ``length`` with rank r in a row's span goes to window first + (r - first rank) // per.
    """
    tree, opened, rows = CapacityTree(window), 0, []
    for length in sorted((n for n in counts if counts[n]), reverse=True):
        left, rank = counts[length], 0
        while left:
            capacity = tree.tightest(length)
            if capacity is None:
                capacity = window
                first, n = opened, -(-left // (window // length))
                opened += n
            else:
                first, n = tree.pop(capacity)
            per = capacity // length
            full = min(n, left // per)
            if full:
                rows.append((length, rank, first, per, window - capacity))
                tree.push(capacity - per * length, first, full)
                rank, left, first, n = rank + full * per, left - full * per, first + full, n - full
            if n and 0 < left < per:
                rows.append((length, rank, first, left, window - capacity))
                tree.push(capacity - left * length, first, 1)
                rank, left, first, n = rank + left, 0, first + 1, n - 1
            tree.push(capacity, first, n)
    plan = np.array(sorted(rows), np.int64).reshape(-1, 5)  # by length and rank, to be searched
    return plan, opened


def cut_tokens(docs: DataFrame, tokenizer_path: str, window: int, end_id: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, doc_tokens and the checksum of the ids of each piece of up to ``window`` ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = codec(tokenizer_path)
        end = end_id.to_bytes(4, "little")
        for batch in in_pieces(batches, 1):
            texts = batch.column(1).to_pylist()
            tokens, sums = [], []
            for i, j in slices([t or "" for t in texts], 2_000_000):
                for ids in coder.encode(texts[i:j]):
                    ids += end
                    tokens.append(len(ids) // 4)
                    sums.append([zlib.crc32(ids[a : a + 4 * window]) for a in range(0, len(ids), 4 * window)])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(tokens, pa.int64()), pa.array(sums, pa.list_(pa.int64()))], names=["doc_id", "doc_tokens", "sums"])

    wanted = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return wanted.mapInArrow(run, "doc_id long, doc_tokens long, sums array<long>")


def pack(docs: DataFrame, tokenizer_path: str, window: int = 1024, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset: a row for each piece."""
    cut = written(cut_tokens(docs, tokenizer_path, window, end_id, id_col, text_col), "pack-cut")
    cut = cut.select("*", (F.col("doc_tokens") % window).alias("rest"), F.floor(F.col("doc_tokens") / window).alias("full"), F.pmod(F.xxhash64("doc_id", "doc_tokens", "sums"), F.lit(RANK_GROUPS)).alias("part"))
    # Counts by (group, length), and each group's full windows: RANK_GROUPS * window rows at most.
    counted = cut.groupBy("part", "rest").agg(F.count("*").alias("n"), F.sum("full").alias("full"))
    table = counted.orderBy("rest", "part").toPandas()
    ones = table[table.rest > 0]
    rows, opened = schedule(ones.groupby("rest").n.sum().to_dict(), window)
    before = {(int(r), int(p)): int(b) for r, p, b in zip(ones.rest, ones.part, ones.groupby("rest").n.cumsum() - ones.n, strict=True)}
    fulls = table.groupby("part").full.sum().sort_index()
    full_before = {int(p): opened + int(b) for p, b in zip(fulls.index, fulls.cumsum() - fulls, strict=True)}

    rank = F.row_number().over(W.partitionBy("part", "rest").orderBy("doc_id", "doc_tokens", "sums")) - 1
    run_before = F.sum("full").over(W.partitionBy("part").orderBy("doc_id", "doc_tokens", "sums").rowsBetween(W.unboundedPreceding, -1))
    short = cut.where("full = 0").select("*", rank.alias("rank"), F.lit(0).cast("long").alias("full_rank"))
    # Documents with full windows are ranked after the others of their length, in two windows over the same groups.
    offset_rank = F.row_number().over(W.partitionBy("part", "rest").orderBy("doc_id", "doc_tokens", "sums")) - 1
    long = cut.where("full > 0").select("*", offset_rank.alias("rank"), F.coalesce(run_before, F.lit(0)).alias("full_rank"))
    shorts = cut.where("full = 0 and rest > 0").groupBy("part", "rest").count().toPandas()
    short_n = {(int(r), int(p)): int(n) for r, p, n in zip(shorts.rest, shorts["part"], shorts["count"], strict=True)}
    shared = docs.sparkSession.sparkContext.broadcast((rows, before, full_before, short_n))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan, before, full_before, short_n = shared.value
        keys = (plan[:, 0] << 44) + plan[:, 1]
        for batch in batches:
            c = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
            rest, part, full, ranks, full_rank = (c[n].to_numpy(zero_copy_only=False).astype(np.int64) for n in ("rest", "part", "full", "rank", "full_rank"))
            tail = np.array([before.get((r, p), 0) + (short_n.get((r, p), 0) if f else 0) for r, p, f in zip(rest.tolist(), part.tolist(), full.tolist(), strict=True)], np.int64) + ranks
            if len(plan):
                row = plan[np.maximum(np.searchsorted(keys, (rest << 44) + tail, "right") - 1, 0)]
                nth = tail - row[:, 1]
                seq, off = row[:, 2] + nth // row[:, 3], row[:, 4] + nth % row[:, 3] * rest
            else:
                seq = off = np.zeros(len(rest), np.int64)
            base = np.array([full_before.get(p, 0) for p in part.tolist()], np.int64) + full_rank
            n = full + (rest > 0)
            doc = np.repeat(np.arange(len(n)), n)
            nth = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
            is_full = nth < full[doc]
            sums = c["sums"].flatten()
            yield pa.RecordBatch.from_arrays(
                [c["doc_id"].take(pa.array(doc)), pa.array(nth * window), pa.array(np.where(is_full, window, rest[doc])), sums, c["doc_tokens"].take(pa.array(doc)), pa.array(np.where(is_full, base[doc] + nth, seq[doc])), pa.array(np.where(is_full, 0, off[doc]))],
                names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"],
            )

    return short.unionByName(long).mapInArrow(place, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
