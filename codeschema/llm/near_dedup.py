"""Near-duplicate detection by ProbMinHash.

A text is a weighted set of its five-word shingles.  Each element sends arrivals of a Poisson process, with its
weight as rate, to random slots; a slot keeps the element that came first, and an element stops once its
next arrival is later than every slot's first.  Two texts agree in a slot with the probability Jaccard
similarity of their weighted sets.  Bands of slots put texts into buckets; every candidate pair is
verified on the texts themselves.

Weights: a text gets a signature with weight 1 for each distinct shingle (the probability Jaccard is then the
plain one) and, if it repeats shingles, a second one with weights 1 + log2(count); all meet in the same
buckets.  A pair is linked if its plain or its weighted similarity, both exact, is at least ``least``.

Equal texts (as word sequences) are one node.  In a bucket each node is first compared with a hub, not with
all others; buckets whose nodes are then in several classes get other hubs (1, then 4 at once for those of more
than ``TILE`` nodes: ``HUBS``), and what is still split is compared in full, whatever its size, in tiles of about
``TILE`` by ``TILE`` nodes.  Classes are the connected components of the links.

Defined cases: a text that is null or has no word is alone in its class; a text of one to four words is one
shingle; repeated rows are copies; rows without id count as copies like others (an id that is unknown
sorts first, and the class id is the least known one); further columns are ignored or handed through.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import bloom_filter, free_name, in_pieces, only_caches, passed, slices, written
from .shingles import WordHasher, mix, runs, words_of

WORDS, LEAST, BANDS, ROWS = 5, 0.8, 36, 6
TILE, FIRST_BANDS, HUBS = 64, 8, (1, 4)
_HASHER = WordHasher()


def shingled(split: list[list[bytes]], n: int = WORDS) -> list[tuple[np.ndarray, np.ndarray]]:
    """(distinct shingles, how often each occurs) of each text."""
    only_caches("near_dedup", _HASHER.clear)
    hashes = _HASHER(split)
    grams = runs(hashes, n)
    out, at = [], 0
    for words in split:
        size = len(words)
        if size >= n:
            mine = grams[at : at + size - n + 1]
        elif size:
            mine = runs(hashes[at : at + size], size)[:1]
        else:
            mine = grams[:0]
        out.append(np.unique(mine, return_counts=True))
        at += size
    return out


def prob_minhash(elements: np.ndarray, weights: np.ndarray, owner: np.ndarray, texts: int, slots: int) -> np.ndarray:
    """Signatures (texts x slots): the element of the earliest arrival at each slot."""
    best, out = np.full(texts * slots, np.inf), np.zeros(texts * slots, np.uint64)
    limit, clock, active, draw = np.full(texts, np.inf), np.zeros(len(elements)), np.arange(len(elements)), 0
    while len(active):
        draw += 1
        with np.errstate(over="ignore"):
            x = mix(elements[active] + np.uint64(draw) * np.uint64(0xD1342543DE82EF95))
            slot = (mix(x ^ np.uint64(0x2545F4914F6CDD1D)) % np.uint64(slots)).astype(np.int64)
        clock[active] -= np.log(((x >> np.uint64(11)).astype(np.float64) + 1) * 2.0**-53) / weights[active]
        now, mine = clock[active], owner[active]
        early = now < limit[mine]
        active, key, now, mine = active[early], mine[early] * slots + slot[early], now[early], mine[early]
        np.minimum.at(best, key, now)
        won = best[key] == now
        out[key[won]] = elements[active[won]]
        limit = best.reshape(texts, slots).max(axis=1)
        active = active[now < limit[mine]]
    return out.reshape(texts, slots)


def banded(signatures: np.ndarray, bands: int, rows: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        out = np.zeros((len(signatures), bands), np.uint64)
        for k in range(rows):
            out = mix(out * np.uint64(31) + signatures[:, k::rows][:, :bands] + np.uint64(k))
        out = mix(out + np.arange(bands, dtype=np.uint64) * np.uint64(0xA24BAED4963EE407))
    return out.view(np.int64)


def band_hashes(sets: list[tuple[np.ndarray, np.ndarray]], bands: int = BANDS, rows: int = ROWS) -> list[np.ndarray]:
    """Bucket numbers of each text: of its plain signature, and of its weighted one if that differs."""
    full = [i for i, (e, _) in enumerate(sets) if len(e)]
    repeating = [i for i in full if sets[i][1].max() > 1]
    out = [np.zeros(0, np.int64)] * len(sets)
    for group, weigh in ((full, False), (repeating, True)):
        if group:
            elements = np.concatenate([sets[i][0] for i in group])
            weights = np.concatenate([1 + np.log2(sets[i][1]) if weigh else np.ones(len(sets[i][0])) for i in group])
            owner = np.repeat(np.arange(len(group)), [len(sets[i][0]) for i in group])
            for i, b in zip(group, banded(prob_minhash(elements, weights, owner, len(group), bands * rows), bands, rows), strict=True):
                out[i] = np.concatenate([out[i], b])
    return out


def probability_jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Exact, of two weight vectors over the same elements, by one sort along the ratios of weights."""
    both = (a > 0) & (b > 0)
    if not both.any():
        return 0.0
    ratio = np.divide(a, b, out=np.full(len(a), np.inf), where=b > 0)
    order = np.argsort(ratio, kind="stable")
    r, upto_b = ratio[order], np.concatenate([[0], np.cumsum(b[order])])
    from_a = np.concatenate([np.cumsum(a[order][::-1])[::-1], [0]])
    at = np.searchsorted(r, ratio[both], "left")
    return float((1 / (from_a[at] / a[both] + upto_b[at] / b[both])).sum())


def similarity(x: tuple[np.ndarray, np.ndarray], y: tuple[np.ndarray, np.ndarray]) -> float:
    """The greater of the plain and the weighted similarity."""
    union = np.union1d(x[0], y[0])
    if not len(union):
        return 0.0
    plain = (len(x[0]) + len(y[0]) - len(union)) / len(union)
    if plain == 1.0 or (x[1].max() == 1 and y[1].max() == 1):
        return plain
    a, b = np.zeros(len(union)), np.zeros(len(union))
    a[np.searchsorted(union, x[0])] = 1 + np.log2(x[1])
    b[np.searchsorted(union, y[0])] = 1 + np.log2(y[1])
    return max(plain, probability_jaccard(a, b))


def _identity(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text).alias("h"), text.alias("text"))


def _key(words: list[bytes]) -> bytes:
    return hashlib.blake2b(b" ".join(words), digest_size=16).digest()


def sketch(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, h (hash of the text), key (of its word sequence), bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in in_pieces(batches, 2):
            texts = [t or "" for t in batch.column(2).to_pylist()]
            for i, j in slices(texts, 3_000_000):
                split = [words_of(t) for t in texts[i:j]]
                found = band_hashes(shingled(split), bands, rows)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i), pa.array([_key(w) for w in split], pa.binary()), pa.array(found, pa.list_(pa.int64()))], names=["doc_id", "h", "key", "bands"])

    return _identity(docs, id_col, text_col).mapInArrow(run, "doc_id long, h long, key binary, bands array<long>")


def _node_texts(docs: DataFrame, wanted: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """key, text of the wanted nodes (key, doc_id, h: a row that has the text)."""
    rows = passed(_identity(docs, id_col, text_col), "h", bloom_filter(wanted, "h")).alias("d").join(wanted.alias("w"), F.col("d.doc_id").eqNullSafe(F.col("w.doc_id")) & (F.col("d.h") == F.col("w.h")))
    return rows.select("w.key", "d.text").dropDuplicates(["key"])


def _verified(pairs: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """The pairs (a, b) whose texts are similar enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last_key, last = None, None
        for batch in in_pieces(batches, 3):
            keep = []
            for k, ta, tb in zip(batch.column(0).to_pylist(), batch.column(2), batch.column(3), strict=True):
                if k != last_key:  # a hub's pairs come one after the other
                    last_key, last = k, shingled([words_of(ta.as_py())])[0]
                keep.append(similarity(last, shingled([words_of(tb.as_py())])[0]) >= least - 1e-9)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    with_b = pairs.join(texts.select(F.col("key").alias("b"), F.col("text").alias("tb")), "b")
    with_a = with_b.join(texts.select(F.col("key").alias("a"), F.col("text").alias("ta")), "a")
    return with_a.select("a", "b", "ta", "tb").mapInArrow(run, "a binary, b binary")


def tile_links(sets: list[tuple[np.ndarray, np.ndarray]], sides: list[int], groups: list, least: float) -> list[tuple[int, int]]:
    """Links that join the groups of a tile's nodes: all pairs of different groups (and sides, if there are two) are compared."""
    if len(set(groups)) < 2:
        return []
    side, group = np.array(sides), np.unique(np.array(groups, object), return_inverse=True)[1]
    sizes = np.array([len(e) for e, _ in sets])
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    known, element = np.unique(np.concatenate([e for e, _ in sets]), return_inverse=True)
    repeats = np.array([c.max() > 1 for _, c in sets])
    shares = np.concatenate([(w := 1 + np.log2(c)) / w.sum() for _, c in sets]) if repeats.any() else None
    two, out = len(np.unique(side)) > 1, []
    for i in range(len(sets) - 1):
        other = group[i + 1 :] != group[i]
        if two:
            other &= side[i + 1 :] != side[i]
        if not other.any():
            continue
        at, mine = starts[i + 1], element[starts[i] : starts[i] + sizes[i]]
        has = np.zeros(len(known), np.int64)
        has[mine] = 1
        common = np.add.reduceat(has[element[at:]], starts[i + 1 :] - at)
        plain = common / (sizes[i] + sizes[i + 1 :] - common)
        close = other & (plain >= least - 1e-9)
        if shares is not None:  # the weighted similarity is at most what the shares of the weights have in common
            share = np.zeros(len(known))
            share[mine] = shares[starts[i] : starts[i] + sizes[i]]
            most = np.add.reduceat(np.minimum(share[element[at:]], shares[at:]), starts[i + 1 :] - at)
            for j in np.flatnonzero(other & ~close & (repeats[i] | repeats[i + 1 :]) & (most >= least - 1e-6)):
                close[j] = similarity(sets[i], sets[i + 1 + j]) >= least - 1e-9
        for j in np.flatnonzero(close) + i + 1:
            if group[j] != group[i]:
                out.append((i, int(j)))
                group[group == group[j]] = group[i]
    return out


def _tiled(held: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """Links (a, b) between the classes of each bucket: (band, key, label), every pair of two classes compared.

    The nodes of a bucket's greatest class are not compared with each other, so they are dealt apart from the rest;
    a bucket of any size becomes tiles of two blocks, and a tile is compared in one place.
    """
    sized = held.groupBy("band", "label").agg(F.count("*").alias("c")).groupBy("band").agg(F.max_by("label", F.struct("c", "label")).alias("main"), F.sum("c").alias("n"), F.max("c").alias("most"))
    blocks = lambda c: F.ceil(c / TILE).cast("int")
    sized = sized.select("band", "main", (F.col("n") <= TILE).alias("single"), blocks(F.col("n") - F.col("most")).alias("r"), blocks(F.col("most")).alias("m"))
    number = lambda c: F.pmod(F.xxhash64("key", "band"), F.col(c)).cast("int")
    main = F.col("label") == F.col("main")
    dealt = held.join(sized, "band").select(
        "band", "key", "label",
        F.when(F.col("single"), 0).when(main, F.col("r") + number("m")).otherwise(number("r")).alias("side"),
        F.when(F.col("single"), F.array(F.lit(0))).when(main, F.sequence(F.lit(0), F.col("r") - 1)).otherwise(F.sequence(F.lit(0), F.col("r") + F.col("m") - 1)).alias("with"),
    ).select("band", "key", "label", "side", F.explode("with").alias("with"))
    tiles = dealt.select("band", F.least("side", "with").alias("low"), F.greatest("side", "with").alias("high"), "side", "key", "label")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def links() -> pa.RecordBatch:
            found = tile_links([r[3] for r in rows], [r[0] for r in rows], [r[2] for r in rows], least)
            return pa.RecordBatch.from_arrays([pa.array([rows[i][1] for i, _ in found], pa.binary()), pa.array([rows[j][1] for _, j in found], pa.binary())], names=["a", "b"])

        tile, rows = None, []
        for batch in in_pieces(batches, 6):
            band, low, high, side, key, label = (batch.column(i).to_pylist() for i in range(6))
            sets = shingled([words_of(t) for t in batch.column(6).to_pylist()])
            for i, now in enumerate(zip(band, low, high, strict=True)):
                if now != tile and rows:
                    yield links()
                    rows = []
                tile = now
                rows.append((side[i], key[i], label[i], sets[i]))
        if rows:
            yield links()

    dealt = tiles.join(texts.select("key", "text"), "key").select("band", "low", "high", "side", "key", "label", "text")
    return dealt.repartition("band", "low", "high").sortWithinPartitions("band", "low", "high").mapInArrow(run, "a binary, b binary")


def components(edges: DataFrame) -> DataFrame:
    """node, label (its component's least node) for every node of the edges (a, b).

    Labels are handed on along edges and then followed to their own labels, so chains shrink by more than half
    each round; every round is written out.
    """
    both = written(edges.select("a", "b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))), "edges")
    labels = written(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("a"), F.min("b")).alias("label")), "labels")
    while True:
        heard = both.join(labels.select(F.col("node").alias("b"), "label"), "b").select(F.col("a").alias("node"), "label", F.lit(None).cast("binary").alias("old"))
        near = labels.select("node", "label", F.col("label").alias("old")).unionAll(heard).groupBy("node").agg(F.min("label").alias("label"), F.max("old").alias("old"))
        jumped = near.join(labels.select(F.col("node").alias("label"), F.col("label").alias("next")), "label")
        new = written(jumped.select("node", "old", F.least("label", "next").alias("label")), "labels")
        labels = new.select("node", "label")
        if new.where("old != label").isEmpty():
            return labels


def _merged(labels: DataFrame, links: DataFrame) -> DataFrame:
    """Labels after more links: only the labels that these join are followed anew."""
    of = lambda c: F.coalesce(F.col(f"{c}_label"), F.col(c))
    named = links.join(labels.select(F.col("node").alias("a"), F.col("label").alias("a_label")), "a", "left").join(labels.select(F.col("node").alias("b"), F.col("label").alias("b_label")), "b", "left")
    moved = components(named.select(of("a").alias("a"), of("b").alias("b")).where("a != b").distinct()).select(F.col("node").alias("label"), F.col("label").alias("new"))
    kept = labels.join(moved, "label", "left").select("node", F.coalesce("new", "label").alias("label"))
    alone = moved.select(F.col("label").alias("node"), F.col("new").alias("label")).join(labels.select("node"), "node", "left_anti")
    return written(kept.unionByName(alone), "labels")


def classes(docs: DataFrame, least: float = LEAST, bands: int = BANDS, rows: int = ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, h, class_id, first (the doc_id and h of the class's first row) for every row."""
    sketches = written(sketch(docs, id_col, text_col, bands, rows), "sketches")
    worded = sketches.where(F.size("bands") > 0)
    nodes = written(worded.groupBy("key").agg(F.min(F.struct("doc_id", "h")).alias("row"), F.min("doc_id").alias("least_id"), F.first("bands").alias("bands")), "nodes")
    bucket = nodes.select("key", F.posexplode("bands").alias("at", "band"))
    hubs = bucket.groupBy("band").agg(F.min("key").alias("hub"), F.max("key").alias("other")).where("hub != other").select("band", "hub")
    members = written(bucket.join(hubs, "band"), "members")
    wanted = written(members.select("key").distinct().join(nodes, "key").select("key", "row.doc_id", "row.h"), "wanted")
    texts = written(_node_texts(docs, wanted, id_col, text_col), "texts")

    # A few bands link nearly all of a class; the others then only matter where classes meet in a bucket.
    pairs = written(members.where(f"key != hub and at % {bands} < {FIRST_BANDS}").select(F.col("hub").alias("a"), F.col("key").alias("b")).distinct(), "pairs")
    labels = components(written(_verified(pairs, texts, least), "links"))

    # Buckets whose nodes are in several classes: other hubs, some at a time; what is split after that in full.
    for turn, count in enumerate((*HUBS, 0)):
        held = members.select("band", "key").join(labels, F.col("key") == F.col("node"), "left").select("band", "key", F.coalesce("label", "key").alias("label"))
        hub = [F.min(F.struct(F.xxhash64("key", "band" if turn else F.lit(0), F.lit(turn * 8 + i)).alias("x"), F.col("key").alias("hub"), F.col("label").alias("of"))) for i in range(count)]
        same = [F.bit_xor(F.xxhash64("key", F.lit(i))).alias(f"same{i}") for i in range(2)]  # buckets of the same nodes
        split = held.groupBy("band").agg(F.min("label").alias("low"), F.max("label").alias("high"), F.count("*").alias("n"), F.array(*hub).alias("hubs"), *same).where("low != high")
        if count:
            # Small buckets get one hub only: they are compared in full below.
            held = written(held.join(split.where(F.col("n") > (TILE if turn else 0)).select("band", "hubs"), "band"), "split")
            asked = held.select("key", "label", F.explode("hubs").alias("h")).where("label != h.of")
            pairs = written(asked.select(F.least("h.hub", "key").alias("a"), F.greatest("h.hub", "key").alias("b")).distinct(), "pairs")
            found = written(_verified(pairs, texts, least), "links")
        else:  # two nodes have met when either was the hub
            found = written(_tiled(written(held.join(split.where("n > 2").groupBy("n", "same0", "same1").agg(F.min("band").alias("band")).select("band"), "band"), "split"), texts, least), "links")
        if not found.isEmpty():
            labels = _merged(labels, found)

    named = nodes.select("key", "row", "least_id").join(labels, F.col("key") == F.col("node"), "left").select("key", "row", "least_id", F.coalesce("label", "key").alias("label"))
    firsts = named.groupBy("label").agg(F.min("least_id").alias("class_id"), F.min("row").alias("first"))
    of_node = named.select("key", "label").join(firsts, "label").select("key", "class_id", "first")
    alone = F.size("bands") == 0
    return sketches.join(of_node, "key", "left").select(
        "doc_id", "h",
        F.when(alone, F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"),
        F.when(alone, F.struct("doc_id", "h")).otherwise(F.col("first")).alias("first"),
    )


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """``docs`` without all but the first row of each class (least doc_id)."""
    found = written(classes(docs, **options), "classes")
    first = (F.col("first.doc_id").eqNullSafe(F.col("doc_id"))) & (F.col("first.h") == F.col("h"))
    kept = found.where(first).groupBy("doc_id", "h").agg(F.count("*").alias("n"))
    h, n, key = free_name(docs, "h"), free_name(docs, "n"), free_name(docs, "key")
    kept = written(kept.select(F.col("doc_id").alias(key), F.col("h").alias(h), F.col("n").alias(n)), "kept")
    text = F.col(options.get("text_col", "text")).cast("string")
    rows = docs.withColumn(f"{h}t", F.xxhash64(text))
    out = rows.join(kept, F.col(options.get("id_col", "doc_id")).eqNullSafe(F.col(key)) & (F.col(f"{h}t") == F.col(h)))
    if not kept.where(F.col(n) > 1).isEmpty():  # rows that are repeated with their id
        worded = F.length(F.regexp_replace(F.coalesce(text, F.lit("")), "[\\x20\\x09-\\x0D]", "")) > 0
        out = out.where(worded).dropDuplicates([key, h]).unionByName(out.where(~worded))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])
