"""Removal of repeated passages with a log-structured fingerprint index.

A window is 20 consecutive words of one text.  Of each window the six-word run with the least hash is its
anchor; equal windows have equal anchors, and only about every eighth run of words is one.  The index holds, in
immutable runs that are each sorted by fingerprint: the anchors of all texts seen so far with the one text of those
that came once; the windows around anchors that came more often, with the least document of each; the hashes of whole
texts.  A batch of new texts (with larger ids than all before) is handled so:

1. its anchors are counted, written as a run of their own, and that run is merge-joined with every older one;
2. anchors that occur twice, in the batch or the runs, pick the windows around them; of old texts only those are read
   again that alone held an anchor which now comes a second time, and their windows join the index;
3. the batch's windows are merge-joined with the older runs of windows; equal ones are told by a 64-bit hash of all
   their words and verified by a second, independent one; those that also start earlier (smaller doc_id) are
   repeated; repetitions inside one text are found in the text itself, word by word;
4. words that a repeated window covers are removed; runs are merged once there are more than ``fan_out``.

A later copy of a whole text is told by its hash and needs no windows; it is never the earliest.
Nothing is decided by samples, and no group of equal windows meets in one task: firsts come from a partial
aggregate, and joins with them can be split.  Filters of bounded size keep rows of old runs that can't match out of
the merge joins; a full filter lets more rows pass and changes no result.

Defined cases: a null text has no words; texts of any length are compared whole; ids that are unknown come
before all others; rows with the same id are one document as far as order goes, so none repeats the other;
batches must come in ascending order of ids.
"""

from __future__ import annotations

import gc
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import bloom_filter, bloom_hits, free_name, in_pieces, only_caches, passed, remove_path, scratch, slices, written
from .shingles import Words, mix, runs, window_minima, words_of

WINDOW, GRAM, FAN_OUT = 20, 6, 4
MOST_ANCHOR_BITS = 1 << 29  # 64 MB: bounds what is broadcast; beyond it more windows are compared, none is lost
SALTS = 8  # tasks over which the copies of one text are dealt
UNKNOWN = -(1 << 63)


def anchors_of(hashes: np.ndarray, sizes: list[int], window: int = WINDOW, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """For all windows of all texts: (text, start, fingerprint of the anchor, place of the anchor)."""
    grams = runs(hashes, gram)
    owner, starts, prints, places, at = [], [], [], [], 0
    for i, n in enumerate(sizes):
        if n >= window:
            mine = grams[at : at + n - gram + 1]
            least = window_minima(mine, window - gram + 1)[: n - window + 1]
            owner.append(np.full(n - window + 1, i))
            starts.append(np.arange(n - window + 1))
            prints.append(mine[least])
            places.append(at + least)
        at += n
    if not owner:
        none = np.zeros(0, np.int64)
        return none, none, none.astype(np.uint64), none
    return np.concatenate(owner), np.concatenate(starts), np.concatenate(prints), np.concatenate(places)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Place in the order (unknown ids first), a hash that tells apart rows of one id, and the text."""
    text = F.col(text_col).cast("string")
    return docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(UNKNOWN)).alias("ord"), F.hash(text).alias("h"), text.alias("text"))


def _bytes(texts: pa.Array) -> list[bytes]:
    return [t or b"" for t in texts.cast(pa.binary()).to_pylist()]


def catalogue(rows: DataFrame) -> DataFrame:
    """ord, h, n_words, key (hash of the word sequence), whole (sha256 of the words joined), loops (whether an
    anchor comes twice), anchors (distinct)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only_caches("substring_dedup")
        for batch in in_pieces(batches, 2):
            texts = _bytes(batch.column(2))
            for i, j in slices(texts, 2_000_000):
                words = Words(texts[i:j])
                joined, sizes = words.joined(), words.sizes
                owner, _, prints, places = anchors_of(words.hashes()[0], sizes)
                ends = np.searchsorted(owner, np.arange(len(sizes) + 1))
                anchors, loops = [], []
                for d in range(len(sizes)):
                    at, mine = places[ends[d] : ends[d + 1]], prints[ends[d] : ends[d + 1]]
                    mine = mine[np.append(True, at[1:] != at[:-1])] if len(at) else mine  # once for each place
                    once = np.unique(mine)
                    anchors.append(once.view(np.int64))
                    loops.append(len(once) < len(mine))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i), pa.array(sizes, pa.int64()), pa.array([hashlib.blake2b(x, digest_size=16).digest() for x in joined], pa.binary()), pa.array([hashlib.sha256(x).digest() for x in joined], pa.binary()), pa.array(loops), pa.array(anchors, pa.list_(pa.int64()))],
                    names=["ord", "h", "n_words", "key", "whole", "loops", "anchors"],
                )

    return rows.mapInArrow(run, "ord long, h int, n_words long, key binary, whole binary, loops boolean, anchors array<long>")


def picked_windows(rows: DataFrame, bits: np.ndarray, of_rows: np.ndarray | None = None) -> DataFrame:
    """w1, w2, ord, h, start: the first of equal windows in each text whose anchor passes the filter ``bits``.

    The few windows that pass by chance have no partner and fall away.  ``of_rows``: only texts whose ``row`` passes that filter.
    """
    spark = rows.sparkSession
    shared, some_rows = spark.sparkContext.broadcast(bits), None if of_rows is None else spark.sparkContext.broadcast(of_rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if some_rows is not None:
            batches = (b.filter(pa.array(bloom_hits(some_rows.value, b.column(3).to_numpy(zero_copy_only=False).astype(np.int64)))) for b in batches)
        only_caches("substring_dedup")
        for batch in in_pieces(batches, 2):
            texts = _bytes(batch.column(2))
            for i, j in slices(texts, 1_000_000):
                words = Words(texts[i:j])
                sizes, (one, two) = words.sizes, words.hashes()
                owner, starts, prints, places = anchors_of(one, sizes)
                turn = np.append(True, places[1:] != places[:-1]) if len(places) else np.zeros(0, bool)
                keep = bloom_hits(shared.value, prints[turn].view(np.int64))[np.cumsum(turn) - 1] if len(turn) else turn
                offset = np.cumsum([0, *sizes])
                at = (offset[owner] + starts)[keep]
                owner, starts = owner[keep], starts[keep]
                w1, w2 = runs(one, WINDOW)[at], runs(two, WINDOW)[at]
                _, first = np.unique(mix(w1 + mix(owner.astype(np.uint64))), return_index=True)
                first.sort()
                owner = pa.array(owner[first])
                yield pa.RecordBatch.from_arrays([pa.array(w1[first].view(np.int64)), pa.array(w2[first].view(np.int64)), batch.column(0).slice(i, j - i).take(owner), batch.column(1).slice(i, j - i).take(owner), pa.array(starts[first].astype(np.int32))], names=["w1", "w2", "ord", "h", "start"])

    columns = ["ord", "h", "text"] if of_rows is None else ["ord", "h", "text", F.xxhash64("ord", "h").alias("row")]
    return rows.select(*columns).mapInArrow(run, "w1 long, w2 long, ord long, h int, start int")


def own_repeats(words: list[bytes], others: np.ndarray) -> np.ndarray:
    """Starts of the repeated windows of one text: later ones of equal windows, and windows equal to ``others`` (starts)."""
    n = len(words) - WINDOW + 1
    known: dict[bytes, int] = {}
    number = np.fromiter((known.setdefault(w, len(known)) for w in words), np.int64, len(words))
    all_ = np.lib.stride_tricks.sliding_window_view(number, WINDOW)
    _, group = np.unique(runs(mix(number.astype(np.uint64)), WINDOW)[:n], return_inverse=True)
    order = np.argsort(group, kind="stable")
    later = np.zeros(n, bool)
    later[order[1:]] = group[order[1:]] == group[order[:-1]]
    twice = np.flatnonzero(group[order[1:]] == group[order[:-1]])
    if (all_[order[twice + 1]] != all_[order[twice]]).any():  # equal hashes of other words: compare all windows word by word
        _, group = np.unique(all_, axis=0, return_inverse=True)
        order = np.argsort(group, kind="stable")
        later = np.zeros(n, bool)
        later[order[1:]] = group[order[1:]] == group[order[:-1]]
    bad = np.zeros(int(group.max()) + 1, bool)
    bad[group[others]] = True
    return np.flatnonzero(later | bad[group])


def covered(n: int, starts: np.ndarray) -> np.ndarray:
    """Which of n words a window from ``starts`` covers."""
    step = np.zeros(n + 1, np.int64)
    np.add.at(step, starts, 1)
    np.add.at(step, starts + WINDOW, -1)
    return np.cumsum(step)[:n] > 0


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """ord, h, n_removed, kept text from ord, h, text, starts of windows that earlier documents have."""
    for batch in in_pieces(batches, 2):
        removed, kept = [], []
        for text, starts in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
            words = words_of(text)
            out = covered(len(words), own_repeats(words, np.array(starts or [], np.int64))) if len(words) >= WINDOW else np.zeros(len(words), bool)
            removed.append(int(out.sum()))
            kept.append(b" ".join([w for w, x in zip(words, out.tolist(), strict=True) if not x]).decode("utf-8", "surrogatepass"))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(removed, pa.int64()), pa.array(kept, pa.string())], names=["ord", "h", "n_removed", "kept"])


class FingerprintLog:
    """The index, in a folder that all executors share: sorted runs of anchors, windows and whole texts, and the texts."""

    #: Columns of the runs, by what they hold; the first one is what a run is sorted and joined by.
    RUNS = {"anchors": "anchor long, n long, ord long, h int", "windows": "w1 long, w2 long, first long", "texts": "key long, whole_key binary, first long"}
    #: How the rows of several runs become one.
    MERGED = {"anchors": (["anchor"], ["sum(n) as n", "min(ord) as ord", "min_by(h, ord) as h"]), "windows": (["w1", "w2"], ["min(first) as first"]), "texts": (["key", "whole_key"], ["min(first) as first"])}

    def __init__(self, spark: SparkSession, path: str | None = None, fan_out: int = FAN_OUT) -> None:
        self.spark, self.path, self.fan_out = spark, path or scratch(spark, "fingerprints"), fan_out
        self.runs: dict[str, list[str]] = {kind: [] for kind in self.RUNS}
        self.texts: list[DataFrame] = []
        self.made = self.compactions = 0

    def read(self, kind: str, names: list[str] | None = None) -> DataFrame:
        return self.spark.read.schema(self.RUNS[kind]).parquet(*(self.runs[kind] if names is None else names))

    def _write(self, kind: str, rows: DataFrame) -> str:
        """An immutable run: each file sorted by fingerprint."""
        self.made += 1
        name = f"{self.path}/{kind}-{self.made:05d}"
        columns = [c.split()[0] for c in self.RUNS[kind].split(", ")]
        rows.select(*columns).sortWithinPartitions(columns[0]).write.parquet(name)
        return name

    def _merged(self, kind: str, rows: DataFrame) -> DataFrame:
        by, how = self.MERGED[kind]
        return rows.groupBy(*by).agg(*[F.expr(x) for x in how])

    def older(self, kind: str, keys: DataFrame) -> DataFrame | None:
        """Merged rows of the runs that may have one of the ``keys`` (a column named like the runs' first one)."""
        if not self.runs[kind]:
            return None
        by = self.RUNS[kind].split()[0]
        return self._merged(kind, passed(self.read(kind), by, bloom_filter(keys, by, MOST_ANCHOR_BITS)))

    def compact(self) -> None:
        """All runs of a kind become one."""
        for kind, names in self.runs.items():
            if len(names) > 1:
                new = self._write(kind, self._merged(kind, self.read(kind)))
                for name in names:
                    remove_path(self.spark, name)
                self.runs[kind] = [new]
        self.compactions += 1

    def ingest(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", last: bool = False) -> tuple[DataFrame, DataFrame]:
        """(ord, h, n_words, whole, copy of each row; ord, h, n_removed, kept of each changed text) after comparison
        with all that came before.  ``copy``: a later copy of a whole text.  ``last``: no batch will be compared with this
        one, so what only later ones would read (its runs of windows and texts, the merging of runs) is not written."""
        batch = f"{self.path}/batch-{len(self.texts):05d}"
        rows = _rows(docs, id_col, text_col)
        found = written(catalogue(rows), "catalogue", f"{batch}-catalogue")
        light = self._light(found, batch, last)

        # Anchors of all rows but copies: the filter tells most rows apart without moving their anchors.
        row = F.xxhash64("ord", "h")
        copies = light.where("copy").select("ord", "h").distinct()
        bits = bloom_filter(copies.select(row.alias("row")), "row")
        flagged = passed(found.select("ord", "h", "anchors", row.alias("row")), "row", bits, mark="maybe")
        sure = flagged.where("not maybe").select("ord", "h", "anchors")
        unsure = flagged.where("maybe").join(copies, ["ord", "h"], "left_anti").select("ord", "h", "anchors")
        counts = sure.unionAll(unsure).select(F.explode("anchors").alias("anchor"), "ord", "h").groupBy("anchor").agg(F.count("*").alias("n"), F.min("ord").alias("ord"), F.expr("min_by(h, ord)").alias("h"))
        name = self._write("anchors", counts)
        mine = self.read("anchors", [name])
        hot, old_windows = mine.where("n > 1").select("anchor"), None
        old = self.older("anchors", mine.select("anchor"))
        if old is not None:  # what both have, and the old texts that had it alone
            met = written(old.join(mine.select("anchor"), "anchor"), "met", f"{batch}-met")
            hot = hot.unionAll(met.select("anchor"))
            alone = met.where("n = 1")
            old_windows = self._old_windows(alone, row, batch)
        self.runs["anchors"].append(name)
        remove_path(self.spark, f"{batch}-catalogue")

        windows = written(picked_windows(rows, bloom_filter(hot, "anchor", MOST_ANCHOR_BITS)), "windows", f"{batch}-windows")
        remove_path(self.spark, f"{batch}-met")
        own = windows.groupBy("w1", "w2").agg(F.min("ord").alias("first"), F.max("ord").alias("last"))
        own = written(own, "own", f"{batch}-own")
        before = self.older("windows", own.select("w1"))
        if old_windows is not None:
            self.runs["windows"].append(old_windows)
            more = self.read("windows", [old_windows])
            before = more if before is None else before.unionAll(more)
        if before is not None:
            before = before.groupBy("w1", "w2").agg(F.min("first").alias("before"))
            first = own.join(before, ["w1", "w2"], "left").select("w1", "w2", F.coalesce(F.least("first", "before"), "first").alias("first"), "last")
        else:
            first = own
        # Most windows have no equal: a filter keeps them out of the join.
        twice = written(first.where("first < last").select("w1", "w2", "first"), "twice", f"{batch}-twice")
        some = passed(windows, "w1", bloom_filter(twice, "w1", MOST_ANCHOR_BITS))
        later = some.join(twice, ["w1", "w2"]).where("first < ord").select("ord", "h", "start")
        repeats = written(later.groupBy("ord", "h").agg(F.collect_list("start").alias("starts")), "repeats", f"{batch}-repeats")
        remove_path(self.spark, f"{batch}-windows")
        if not last:
            self.runs["windows"].append(self._write("windows", own))
        remove_path(self.spark, f"{batch}-own")
        remove_path(self.spark, f"{batch}-twice")

        touched = light.where("not copy").select("ord", "h", "loops").distinct().join(repeats, ["ord", "h"], "left").where("starts is not null or loops").select("ord", "h", "starts")
        touched = written(touched, "touched", f"{batch}-touched")
        some = passed(rows.withColumn("row", row), "row", bloom_filter(touched.select(row.alias("row")), "row")).select("ord", "h", "text")
        changed = some.join(touched, ["ord", "h"]).select("ord", "h", "text", "starts").mapInArrow(_cut, "ord long, h int, n_removed long, kept string")
        changed = written(changed.dropDuplicates(["ord", "h"]), "changed", f"{batch}-changed")
        for part in ("repeats", "touched"):
            remove_path(self.spark, f"{batch}-{part}")
        self.texts.append(rows)
        if not last and max(map(len, self.runs.values())) > self.fan_out:
            self.compact()
        return light.select("ord", "h", "n_words", "whole", "copy"), changed

    def _light(self, found: DataFrame, batch: str, last: bool) -> DataFrame:
        """The catalogue without anchors, with later copies of whole texts marked; their hashes go into a run."""
        key = F.expr("xxhash64(key)").alias("key")
        own = found.groupBy(key, F.col("key").alias("whole_key")).agg(F.min("ord").alias("first"), F.max("ord").alias("last"))
        own = written(own, "keys", f"{batch}-keys")
        before = self.older("texts", own.select("key"))
        first = own if before is None else own.join(before.withColumnRenamed("first", "before"), ["key", "whole_key"], "left").select("key", "whole_key", F.coalesce(F.least("first", "before"), "first").alias("first"), "last")
        # Copies of one text may be many: they are dealt over several tasks, and the row they are compared with goes to each.
        salted = first.where("first < last").select(F.col("whole_key").alias("key"), "first", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
        rows = found.select("ord", "h", "n_words", "key", "whole", "loops", F.pmod(F.xxhash64("ord", "h"), F.lit(SALTS)).cast("int").alias("salt"))
        light = rows.join(salted, ["key", "salt"], "left").select("ord", "h", "n_words", "whole", "loops", F.coalesce((F.col("first") < F.col("ord")) & (F.col("n_words") >= WINDOW), F.lit(False)).alias("copy"))
        light = written(light, "light", f"{batch}-light")
        if not last:
            self.runs["texts"].append(self._write("texts", own))
        remove_path(self.spark, f"{batch}-keys")
        return light

    def _old_windows(self, alone: DataFrame, row, batch: str) -> str | None:
        """A run of the windows that old texts have around anchors which were theirs alone until now; no other text is read again."""
        if alone.isEmpty():
            return None
        anchors, rows = bloom_filter(alone.select("anchor"), "anchor", MOST_ANCHOR_BITS), bloom_filter(alone.select(row.alias("row")), "row")
        span = alone.agg(F.min("ord").alias("low"), F.max("ord").alias("high")).first()
        texts = None
        for t in self.texts:
            t = t.where(F.col("ord").between(span["low"], span["high"]))
            texts = t if texts is None else texts.unionAll(t)
        found = picked_windows(texts, anchors, rows).groupBy("w1", "w2").agg(F.min("ord").alias("first"))
        return self._write("windows", found)


def settled(spark: SparkSession) -> None:
    """Lets Spark remove the shuffle files of finished batches, which it does once nothing refers to them."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def deduplicated(docs: DataFrame, batches: int = 3, id_col: str = "doc_id", text_col: str = "text", index: FingerprintLog | None = None) -> DataFrame:
    """doc_id, h, n_words, n_removed, whole (sha256 of all words joined), kept (the kept words joined, null if nothing is removed).

    The texts go through the index in ``batches`` batches of ascending ids.
    """
    own = index is None
    index = index or FingerprintLog(docs.sparkSession)
    parts = [docs]
    if batches > 1:
        marks = docs.where(F.col(id_col).isNotNull()).agg(F.percentile_approx(id_col, [k / batches for k in range(1, batches)], 10_000).alias("q")).first()["q"]
        if marks:
            ends, of = sorted(set(marks)), F.col(id_col)
            parts = [docs.where((of <= ends[0]) | of.isNull()), *(docs.where((of > a) & (of <= b)) for a, b in zip(ends, ends[1:])), docs.where(of > ends[-1])]
    out = None
    for i, part in enumerate(parts):
        light, changed = index.ingest(part, id_col, text_col, last=own and i == len(parts) - 1)
        settled(docs.sparkSession)
        rows = light.join(changed, ["ord", "h"], "left").select(
            F.when(F.col("ord") != UNKNOWN, F.col("ord")).alias("doc_id"), "h", "n_words",
            F.when(F.col("copy"), F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0))).alias("n_removed"),
            F.lower(F.hex("whole")).alias("whole"),
            F.when(F.col("copy"), F.lit("")).when(F.col("n_removed") > 0, F.col("kept")).alias("kept"),
        )
        out = rows if out is None else out.unionAll(rows)
    return out


def digests(rows: DataFrame) -> DataFrame:
    return rows.select("doc_id", "n_words", "n_removed", F.when(F.col("kept").isNull(), F.col("whole")).otherwise(F.sha2("kept", 256)).alias("kept_sha256"))


def cleaned(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with repeated passages removed; texts without any stay as they are, changed ones are their kept
    words joined by one space."""
    text_col, id_col = options.get("text_col", "text"), options.get("id_col", "doc_id")
    rows = deduplicated(docs, **options).where("kept is not null").groupBy("doc_id", "h").agg(F.max("kept").alias("kept"))
    key, h, kept = free_name(docs, "key"), free_name(docs, "h"), free_name(docs, "kept")
    rows = written(rows.select(F.col("doc_id").alias(key), F.col("h").alias(h), F.col("kept").alias(kept)), "cleaned")
    text = F.col(text_col).cast("string")
    out = docs.withColumn(f"{h}t", F.hash(text)).join(rows, F.col(id_col).eqNullSafe(F.col(key)) & (F.col(f"{h}t") == F.col(h)), "left")
    return out.select(*[F.coalesce(F.col(kept), text).alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns])


ORACLE = """
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS words
  FROM documents
), s AS (
  SELECT doc_id, i AS start, md5(array_to_string(words[i:i + 19], ' ')) AS m
  FROM (SELECT doc_id, words, unnest(range(1, len(words) - 18)) AS i FROM w)
), f AS (
  SELECT doc_id, start, row_number() OVER (PARTITION BY m ORDER BY doc_id, start) AS nth FROM s
), c AS (
  SELECT DISTINCT doc_id, start + k AS word FROM f, (SELECT unnest(range(20)) AS k) WHERE nth > 1
), g AS (
  SELECT doc_id, list(word) AS gone FROM c GROUP BY doc_id
), k AS (
  SELECT w.doc_id, len(words) AS n_words, coalesce(len(gone), 0) AS n_removed,
         CASE WHEN gone IS NULL THEN words
              ELSE list_filter(words, lambda x, i: NOT list_contains(gone, i)) END AS kept
  FROM w LEFT JOIN g ON w.doc_id = g.doc_id
)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(n_removed AS BIGINT) AS n_removed,
       sha256(coalesce(array_to_string(kept, ' '), '')) AS kept_sha256
FROM k
"""
