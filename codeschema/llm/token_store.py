"""Token-id output: a content-addressed store of chunks of id streams.

Files of a store (all Parquet, below one folder):
  chunks/    digest, n_ids, ids (little-endian unsigned integers of ``width`` bytes), width;
             each distinct chunk once
  recipes/   a row a document, in ascending doc_id order over files and rows: part, place in the part,
             doc_id, n_tokens, digests of its chunks, leaf (hash of all that)
  manifest/  Merkle nodes: a root for each block of ``LEAVES`` recipes, for each part, and for the store

A rolling hash over ``SPAN`` ids cuts the streams, so copies and shared passages fall into the same
chunks; only chunks that a task has not met yet leave it.  Reading checks every chunk against its
digest, every recipe against its leaf and the manifest, and joins checksums (not contents) along
the recipes; ``reconstruct`` gives the ids themselves.

Defined cases: a null text is an empty one, holding the end id alone; rows repeated in the input are
documents of their own, in the order doc_id (nulls first), length, digests; an empty table gives an empty store.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import in_pieces, remove_path, scratch, slices
from .bpe_codec import codec

SPAN, LEAST, MEAN, MOST, LEAVES = 16, 64, 256, 1024, 1024
_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def cut_points(ids: np.ndarray, starts: np.ndarray, least: int = LEAST, mean: int = MEAN, most: int = MOST) -> list[list[int]]:
    """For each document (``starts``: where each begins, and the end) the ends of its chunks, from its start."""
    h = (ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    step, power = 1, _MULTIPLIER
    with np.errstate(over="ignore"):
        while step < SPAN:
            h[step:] = h[step:] + power * h[:-step]  # the right side is made before it is stored
            step, power = 2 * step, power * power
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
    marks = np.flatnonzero((h >> np.uint64(40)) % np.uint64(mean) == 0) + 1
    begin = np.searchsorted(marks, starts)
    out = []
    for d in range(len(starts) - 1):
        a, b, cuts, at = int(starts[d]), int(starts[d + 1]), [], int(starts[d])
        for m in marks[begin[d] : begin[d + 1]].tolist():
            while m - at > most:
                at += most
                cuts.append(at - a)
            if m - at >= least and m < b:
                at = m
                cuts.append(at - a)
        while b - at > most:
            at += most
            cuts.append(at - a)
        out.append([*cuts, b - a])
    return out


def leaf(doc_id: int | None, n_tokens: int, digests: list[bytes]) -> bytes:
    return hashlib.sha256(f"{doc_id}:{n_tokens}:".encode() + b"".join(digests)).digest()


def write_store(docs: DataFrame, path: str, tokenizer_path: str, end_id: int, width: int = 2, id_col: str = "doc_id", text_col: str = "text", most_seen: int = 400_000) -> None:
    """Writes the store; an id beyond ``width`` bytes is an error.  ``most_seen``: how many digests a task remembers; it only saves traffic."""
    spark = docs.sparkSession

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, seen = codec(tokenizer_path), set()
        end, narrow = end_id.to_bytes(4, "little"), f"<u{width}"
        for batch in in_pieces(batches, 1):
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for i, j in slices(texts, 2_000_000):
                streams = [x + end for x in coder.encode(texts[i:j])]
                starts = np.cumsum([0, *(len(x) // 4 for x in streams)])
                ids = np.frombuffer(b"".join(streams), "<u4")
                if len(ids) and int(ids.max()) >> 8 * width:
                    raise ValueError(f"an id needs more than {width} bytes")
                packed, rows = ids.astype(narrow).tobytes(), []
                for d, cuts in enumerate(cut_points(ids, starts)):
                    a, names, new, new_ids = int(starts[d]) * width, [], [], []
                    for begin, stop in zip([0, *cuts], cuts):
                        chunk = packed[a + begin * width : a + stop * width]
                        name = hashlib.blake2b(chunk, digest_size=16).digest()
                        names.append(name)
                        if name not in seen:
                            if len(seen) >= most_seen:
                                seen.clear()
                            seen.add(name)
                            new.append(name)
                            new_ids.append(chunk)
                    rows.append((cuts[-1], names, new, new_ids))
                n, names, new, new_ids = zip(*rows, strict=True)
                many = pa.list_(pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(n, pa.int64()), pa.array(names, many), pa.array(new, many), pa.array(new_ids, many)], names=["doc_id", "n_tokens", "digests", "new", "new_ids"])

    wanted = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    staged_at = scratch(spark, "store-staged")
    staged = wanted.mapInArrow(run, "doc_id long, n_tokens long, digests array<binary>, new array<binary>, new_ids array<binary>")
    staged.write.option("compression", "zstd").parquet(staged_at)
    staged = spark.read.schema(staged.schema).parquet(staged_at)

    chunk = staged.select(F.explode(F.arrays_zip("new", "new_ids")).alias("c")).select(F.col("c.new").alias("digest"), F.col("c.new_ids").alias("ids"))
    # A task gives a chunk once, so grouping before the exchange would only sort them one time more.
    once = chunk.repartition("digest").groupBy("digest").agg(F.first("ids").alias("ids"))
    once.select("digest", (F.length("ids") / width).cast("int").alias("n_ids"), "ids", F.lit(width).alias("width")).write.mode("overwrite").option("compression", "zstd").parquet(f"{path}/chunks")

    ordered = staged.select("doc_id", "n_tokens", "digests").repartitionByRange("doc_id", "n_tokens", "digests").sortWithinPartitions("doc_id", "n_tokens", "digests")
    placed = ordered.withColumn("part", F.spark_partition_id()).mapInArrow(_place, "part int, place long, doc_id long, n_tokens long, before long, digests array<binary>, leaf binary")
    placed.write.mode("overwrite").parquet(f"{path}/recipes")
    remove_path(spark, staged_at)
    _manifest(spark, path).write.mode("overwrite").parquet(f"{path}/manifest")


def _place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Numbers the rows of a partition, in their order, and counts the ids before each in it."""
    place = before = 0
    for batch in batches:
        ids, n, names, part = (batch.column(batch.schema.get_field_index(c)) for c in ("doc_id", "n_tokens", "digests", "part"))
        counts = n.to_numpy().astype(np.int64)
        starts = before + np.cumsum(counts) - counts
        leaves = [leaf(*row) for row in zip(ids.to_pylist(), counts.tolist(), names.to_pylist(), strict=True)]
        yield pa.RecordBatch.from_arrays([part, pa.array(place + np.arange(len(counts))), ids, n, pa.array(starts), names, pa.array(leaves, pa.binary())], names=["part", "place", "doc_id", "n_tokens", "before", "digests", "leaf"])
        place, before = place + len(counts), before + int(counts.sum())


def recipes(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("part int, place long, doc_id long, n_tokens long, before long, digests array<binary>, leaf binary").parquet(f"{path}/recipes")


def _manifest(spark: SparkSession, path: str) -> DataFrame:
    """Merkle nodes of the recipes as they are stored: blocks, parts, store."""
    hashed = lambda of: F.unhex(F.sha2(F.concat(F.lit(b""), F.array_join(F.transform(F.sort_array(F.collect_list(F.struct(of[0], of[1]))), lambda x: F.hex(x[of[1]])), "").cast("binary")), 256))
    rows = recipes(spark, path).withColumn("block", F.floor(F.col("place") / LEAVES))
    blocks = rows.groupBy("part", "block").agg(hashed(("place", "leaf")).alias("node"), F.sum("n_tokens").alias("n_tokens"))
    parts = blocks.groupBy("part").agg(hashed(("block", "node")).alias("node"), F.sum("n_tokens").alias("n_tokens"))
    top = parts.agg(hashed(("part", "node")).alias("node"), F.sum("n_tokens").alias("n_tokens"))
    none = F.lit(None).cast("long")
    return (
        blocks.select(F.lit(0).alias("level"), F.col("part").cast("long").alias("part"), "block", "node", "n_tokens")
        .unionByName(parts.select(F.lit(1).alias("level"), F.col("part").cast("long").alias("part"), none.alias("block"), "node", "n_tokens"))
        .unionByName(top.select(F.lit(2).alias("level"), none.alias("part"), none.alias("block"), "node", "n_tokens"))
    )


def verify_manifest(spark: SparkSession, path: str) -> int:
    """How many Merkle nodes differ from what the recipes give now: 0 for an intact store."""
    stored = spark.read.schema("level int, part long, block long, node binary, n_tokens long").parquet(f"{path}/manifest")
    made = _manifest(spark, path)
    on = ["level", "part", "block"]
    both = stored.alias("a").join(made.alias("b"), [F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in on], "full")
    return both.where(~F.col("a.node").eqNullSafe(F.col("b.node")) | ~F.col("a.n_tokens").eqNullSafe(F.col("b.n_tokens"))).count()


def read_chunks(spark: SparkSession, path: str) -> DataFrame:
    """digest, n, crc: of each stored chunk, read, checked against its digest, widened to 32 bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, crc = [], []
            for name, data, width in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                if hashlib.blake2b(data, digest_size=16).digest() != name:
                    raise ValueError(f"chunk {name.hex()} is damaged")
                ids = np.frombuffer(data, f"<u{width}").astype("<u4")
                n.append(len(ids))
                crc.append(zlib.crc32(ids.tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(crc, pa.int64())], names=["digest", "n", "crc"])

    stored = spark.read.schema("digest binary, n_ids int, ids binary, width int").parquet(f"{path}/chunks")
    return stored.select("digest", "ids", "width").mapInArrow(run, "digest binary, n long, crc long")


# -- checksums of joined streams: arithmetic in GF(2)[x] modulo the CRC-32 polynomial, bits reflected -----
_POLY, _ONE = np.uint64(0xEDB88320), np.uint64(1 << 31)


def _times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    out, b = np.zeros_like(a), b.copy()
    for bit in range(31, -1, -1):
        out ^= np.where(a >> np.uint64(bit) & np.uint64(1), b, np.uint64(0))
        b = b >> np.uint64(1) ^ np.where(b & np.uint64(1), _POLY, np.uint64(0))
    return out


def shifted_crc(crc: np.ndarray, n_bytes: np.ndarray) -> np.ndarray:
    """What each checksum adds to that of a stream that goes on for ``n_bytes`` more."""
    out, square, k = crc.astype(np.uint64), np.array([1 << 23], np.uint64), 0
    n = n_bytes.astype(np.int64)
    while len(n) and int(n.max()) >> k:
        on = (n >> k & 1).astype(bool)
        if on.any():
            out[on] = _times(out[on], np.broadcast_to(square, int(on.sum())).copy())
        square, k = _times(square, square), k + 1
    return out


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        doc, start, n_tokens, links = (batch.column(i) for i in range(4))
        flat = links.flatten()
        n, crc = flat.field("n").to_numpy().astype(np.int64), flat.field("crc").to_numpy().astype(np.int64)
        sizes = np.diff(links.offsets.to_numpy())
        ends = np.cumsum(n)
        last = np.concatenate([[0], ends])[np.cumsum(sizes)]
        total = last - np.concatenate([[0], last])[:-1]
        if (total != n_tokens.to_numpy()).any():
            raise ValueError("a document's chunks do not add up to its length")
        parts = shifted_crc(crc, 4 * (np.repeat(last, sizes) - ends))
        whole = np.bitwise_xor.reduceat(parts, np.cumsum(sizes) - sizes) if len(parts) else parts
        yield pa.RecordBatch.from_arrays([doc, start, n_tokens, pa.array(whole.astype(np.int64))], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def with_starts(rows: DataFrame) -> DataFrame:
    """Recipes with ``start``: the ids of all documents before.  Only a row a part is gathered."""
    parts = rows.groupBy("part").agg(F.sum("n_tokens").alias("n")).orderBy("part").collect()
    offsets, at = [], 0
    for r in parts:
        offsets.append((r["part"], at))
        at += r["n"]
    table = rows.sparkSession.createDataFrame(offsets, "part int, base long")
    return rows.join(F.broadcast(table), "part").withColumn("start", F.col("base") + F.col("before"))


def _checked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = batch.to_pydict()
        for row in zip(rows["doc_id"], rows["n_tokens"], rows["digests"], rows["leaf"], strict=True):
            if leaf(*row[:3]) != row[3]:
                raise ValueError(f"the recipe of document {row[0]} is damaged")
        yield batch


def _links(spark: SparkSession, path: str) -> DataFrame:
    stored = recipes(spark, path)
    rows = with_starts(stored.mapInArrow(_checked, stored.schema))
    return rows.select("doc_id", "start", "n_tokens", F.posexplode("digests").alias("pos", "digest"))


def read_store(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files, everything verified."""
    if verify_manifest(spark, path):
        raise ValueError("the manifest does not fit the recipes")
    linked = _links(spark, path).join(read_chunks(spark, path), "digest", "left")
    docs = linked.groupBy("start", "doc_id", "n_tokens").agg(F.sort_array(F.collect_list(F.struct("pos", "n", "crc"))).alias("links"))
    return docs.select("doc_id", "start", "n_tokens", "links").mapInArrow(_joined, "doc_id long, start long, n_tokens long, ids_crc32 long")


def reconstruct(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, ids array<long>: the streams themselves."""
    stored = spark.read.schema("digest binary, n_ids int, ids binary, width int").parquet(f"{path}/chunks")
    rows = _links(spark, path).join(stored, "digest").groupBy("start", "doc_id").agg(F.max("width").alias("width"), F.sort_array(F.collect_list(F.struct("pos", "ids"))).alias("parts"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = [np.frombuffer(b"".join(p["ids"] for p in parts), f"<u{w}").astype(np.int64) for parts, w in zip(batch.column(3).to_pylist(), batch.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(ids, pa.list_(pa.int64()))], names=["doc_id", "start", "ids"])

    return rows.select("doc_id", "start", "width", "parts").mapInArrow(run, "doc_id long, start long, ids array<long>")
