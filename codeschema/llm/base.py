"""Small helpers that the operators of this subpackage share."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    A folder of our own is made only where the session names none and is local (tests); on a cluster that is an error.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir has to name a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="codeschema-")
        spark.conf.set("spark.checkpoint.dir", found)
    return found.rstrip("/")


def scratch(spark: SparkSession, label: str) -> str:
    return f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex[:12]}"


def written(df: DataFrame, label: str, path: str | None = None) -> DataFrame:
    """``df`` written to the shared folder and read back: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = path or scratch(spark, label)
    df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def remove_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def free_name(df: DataFrame, stem: str) -> str:
    """A column name that ``df`` does not have, in any case."""
    have, name = {c.lower() for c in df.columns}, f"__{stem}"
    while name.lower() in have:
        name += "_"
    return name


def over_batches(fn: Callable[[dict[str, list]], dict[str, list] | None], schema: pa.Schema) -> Callable:
    """A ``mapInArrow`` function from one that maps columns as lists to columns as lists."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = fn({name: batch.column(i).to_pylist() for i, name in enumerate(batch.schema.names)})
            if got is not None:
                yield pa.RecordBatch.from_arrays([pa.array(got[f.name], f.type) for f in schema], schema=schema)

    return run


def slices(items: list, most_chars: int) -> Iterable[tuple[int, int]]:
    """Index ranges of ``items`` (texts) of about ``most_chars`` characters each, one item at least."""
    start = held = 0
    for i, x in enumerate(items):
        if held and held + len(x) > most_chars:
            yield start, i
            start, held = i, 0
        held += len(x)
    if start < len(items):
        yield start, len(items)


def in_pieces(batches: Iterable[pa.RecordBatch], column: int, most_bytes: int = 2_000_000) -> Iterator[pa.RecordBatch]:
    """The batches in slices of about ``most_bytes`` of a text column (one row at least), so that few texts are Python objects at once."""
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        ends = np.cumsum(sizes)
        at = 0
        while at < batch.num_rows:
            done = ends[at - 1] if at else 0
            stop = max(at + 1, int(np.searchsorted(ends, done + most_bytes, "right")))
            yield batch.slice(at, stop - at)
            at = stop
        pa.default_memory_pool().release_unused()


def held_out(column: str = "doc_id"):
    """crc32 of the id as text, modulo 5, is 0; an unknown id counts as held out."""
    return F.coalesce(F.crc32(F.col(column).cast("string").cast("binary")) % 5 == 0, F.lit(True))


_CACHES: dict[str, Callable[[], None]] = {}


def only_caches(owner: str, clear: Callable[[], None] | None = None) -> None:
    """Empties what other operators have kept in this worker process, which outlives their tasks; ``clear`` empties the owner's."""
    for other in [x for x in _CACHES if x != owner]:
        _CACHES.pop(other)()
    if clear is not None:
        _CACHES[owner] = clear


# -- a filter of bounded size before a shuffle ----------------------------------------------------
MOST_BITS = 1 << 27  # 16 MB: what is broadcast never gets larger, it only lets more rows pass


def _bit_places(values: np.ndarray, bits: int) -> list[np.ndarray]:
    x, out = values.view(np.uint64), []
    with np.errstate(over="ignore"):
        for k in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93):
            y = (x ^ x >> np.uint64(29)) * np.uint64(k)
            out.append((y >> np.uint64(32)) & np.uint64(bits - 1))
    return out


def bloom_filter(wanted: DataFrame, column: str, most_bits: int = MOST_BITS) -> np.ndarray:
    """Bits (as 64-bit words) that pass every value of the long ``column``, and few others."""
    bits = 1 << min(most_bits.bit_length() - 1, max(10, (16 * wanted.count()).bit_length()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = np.concatenate(_bit_places(batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64), bits))
            at.sort()
            word = at >> np.uint64(6)
            first = np.flatnonzero(np.append(True, word[1:] != word[:-1])) if len(at) else np.zeros(0, np.int64)
            value = np.bitwise_or.reduceat(np.uint64(1) << (at & np.uint64(63)), first) if len(at) else np.zeros(0, np.uint64)
            word = word[first]
            yield pa.RecordBatch.from_arrays([pa.array(word.astype(np.int64)), pa.array(value.view(np.int64))], names=["word", "value"])

    some = wanted.select(F.col(column).cast("long").alias("v")).where("v is not null").mapInArrow(run, "word long, value long")
    out = np.zeros(bits // 64, np.uint64)
    found = some.groupBy("word").agg(F.expr("bit_or(value)").alias("value")).toArrow()  # as many rows as the filter has words, at most
    out[found.column("word").to_numpy()] = found.column("value").to_numpy().view(np.uint64)
    return out


def bloom_hits(words: np.ndarray, values: np.ndarray) -> np.ndarray:
    keep = np.ones(len(values), bool)
    for place in _bit_places(values, len(words) * 64):
        keep &= (words[(place >> np.uint64(6)).astype(np.int64)] >> (place & np.uint64(63)) & np.uint64(1)).astype(bool)
    return keep


def passed(rows: DataFrame, column: str, bits: np.ndarray, mark: str | None = None) -> DataFrame:
    """The rows whose long ``column`` the filter passes, or all rows with that said in a column ``mark``."""
    shared, at = rows.sparkSession.sparkContext.broadcast(bits), rows.columns.index(column)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = pa.array(bloom_hits(shared.value, batch.column(at).to_numpy(zero_copy_only=False).astype(np.int64)))
            yield pa.RecordBatch.from_arrays([*batch.columns, keep], names=[*batch.schema.names, mark]) if mark else batch.filter(keep)

    return rows.mapInArrow(run, T.StructType([*rows.schema.fields, T.StructField(mark, T.BooleanType())]) if mark else rows.schema)
