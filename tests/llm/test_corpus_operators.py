"""Operators over the whole corpus, against brute force: packing, store, search, near duplicates, passages, pipeline."""

from __future__ import annotations

import hashlib
import itertools
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as P
import pytest
from codeschema.llm import near_dedup, packing, substring_dedup, token_store, topk_search
from codeschema.llm.base import bloom_filter, passed
from conftest import SF, rows, sql_rows
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

EDGE = [(None, "some words here"), (5, None), (6, ""), (7, "a b c"), (7, "a b c"), (7, "other text of the same id"), (8, "word " * 9000), (9, " \n\t ")]


def docs(spark, data=EDGE, extra=True):
    df = spark.createDataFrame(data, "doc_id long, text string")
    return df.withColumns({"key": F.lit(1), "h": F.lit("x"), "ord": F.lit(2), "label": F.lit(None).cast("int"), "band": F.lit(0)}) if extra else df


# -- packing ------------------------------------------------------------------------------------------
@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 15), min_size=1, max_size=120))
def test_schedule_is_best_fit_decreasing(lengths):
    window, bins = 16, []
    for n in sorted(lengths, reverse=True):
        fit = [b for b in bins if b[0] >= n]
        if fit:
            min(fit, key=lambda b: b[0])[0] -= n
        else:
            bins.append([window - n])
    plan, opened = packing.schedule(Counter(lengths), window)
    assert opened == len(bins)
    used = defaultdict(list)
    for n, count in Counter(lengths).items():
        mine = plan[plan[:, 0] == n]
        for r in range(count):
            row = mine[np.searchsorted(mine[:, 1], r, "right") - 1]
            k = r - row[1]
            used[row[2] + k // row[3]].append((row[4] + k % row[3] * n, n))
    rest = []
    for pieces in used.values():
        at = 0
        for off, n in sorted(pieces):
            assert off == at
            at += n
        rest.append(window - at)
    assert sorted(rest) == sorted(b[0] for b in bins)


def test_packing_cases(spark):
    t = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    got = packing.pack(docs(spark), P.path("byte_bpe_50k.json"), window=64).collect()
    want = Counter()
    for i, text in EDGE:
        ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        want.update((i, a, min(64, len(ids) - a), zlib.crc32(ids[a : a + 64].tobytes()), len(ids)) for a in range(0, len(ids), 64))
    assert Counter((r.doc_id, r.start, r.length, r.ids_crc32, r.doc_tokens) for r in got) == want
    by = defaultdict(list)
    for r in got:
        by[r.sequence_id].append((r.offset, r.length))
    assert sorted(by) == list(range(len(by)))
    for pieces in by.values():
        at = 0
        for off, n in sorted(pieces):
            assert off == at
            at += n
        assert at <= 64
    assert packing.pack(docs(spark).where("false"), P.path("byte_bpe_50k.json")).count() == 0


# -- token store ----------------------------------------------------------------------------------------
def test_cuts_follow_content():
    rng = np.random.default_rng(3)
    a = rng.integers(0, 40_000, 5000).astype("<u4")
    b = np.concatenate([rng.integers(0, 40_000, 777).astype("<u4"), a])
    cuts = token_store.cut_points(np.concatenate([a, b]), np.array([0, len(a), len(a) + len(b)]))
    chunks = [{x[i:j].tobytes() for i, j in itertools.pairwise([0, *c])} for x, c in zip((a, b), cuts, strict=True)]
    assert len(chunks[0] & chunks[1]) > 0.8 * len(chunks[0])
    assert all(j - i <= token_store.MOST for i, j in itertools.pairwise([0, *cuts[0]]))


@settings(max_examples=40, deadline=None)
@given(st.lists(st.binary(max_size=300), min_size=1, max_size=5))
def test_joined_checksums(parts):
    lengths = np.array([len(p) for p in parts])
    after = lengths[::-1].cumsum()[::-1] - lengths
    got = np.bitwise_xor.reduce(token_store.shifted_crc(np.array([zlib.crc32(p) for p in parts]), after))
    assert int(got) == zlib.crc32(b"".join(parts))


def test_store_cases(spark, tmp_path):
    t, path = Tokenizer.from_file(P.path("word_bpe_49k.json")), str(tmp_path / "store")
    data = [*EDGE, (10, "repeat this " * 3000), (11, "repeat this " * 3000)]
    token_store.write_store(docs(spark, data), path, P.path("word_bpe_49k.json"), end_id=2)
    got = sorted(token_store.read_store(spark, path).collect(), key=lambda r: r.start)
    ids = {i: np.array([*t.encode(x or "", add_special_tokens=False).ids, 2], "<u4") for i, x in data if i != 7}
    at = 0
    for r in got:
        assert r.start == at
        if r.doc_id != 7:
            assert (r.n_tokens, r.ids_crc32) == (len(ids[r.doc_id]), zlib.crc32(ids[r.doc_id].tobytes()))
        at += r.n_tokens
    known = [r.doc_id for r in got]
    assert known == sorted(known, key=lambda x: (x is not None, x)) and len(got) == len(data)
    whole = {r.start: r.ids for r in token_store.reconstruct(spark, path).collect()}
    assert all(len(whole[r.start]) == r.n_tokens for r in got)
    assert spark.read.parquet(f"{path}/chunks").groupBy("digest").count().where("count > 1").count() == 0
    assert token_store.verify_manifest(spark, path) == 0


def test_store_damage_is_seen(spark, tmp_path):
    path = str(tmp_path / "store")
    token_store.write_store(docs(spark), path, P.path("word_bpe_49k.json"), end_id=2)
    r = token_store.recipes(spark, path).withColumn("leaf", F.when(F.col("doc_id") == 6, F.unhex(F.lit("00"))).otherwise(F.col("leaf"))).collect()
    spark.createDataFrame(r, token_store.recipes(spark, path).schema).write.mode("overwrite").parquet(f"{path}/recipes")
    assert token_store.verify_manifest(spark, path) > 0


def test_empty_store(spark, tmp_path):
    path = str(tmp_path / "none")
    token_store.write_store(docs(spark).where("false"), path, P.path("word_bpe_49k.json"), end_id=2)
    assert token_store.read_store(spark, path).count() == 0


# -- search ----------------------------------------------------------------------------------------------
def test_topk_equals_brute_force(spark):
    rng = np.random.default_rng(4)
    v = {i: rng.standard_normal(5).astype(np.float32).tolist() for i in range(60)}
    v |= {100 + i: [1.0] * 5 for i in range(30)}  # ties
    v |= {200: None, 201: [1.0, None, 1.0, 1.0, 1.0], 202: [float("nan")] * 5, 203: [float("inf")] * 5, 204: [1.0, 2.0]}
    df = spark.createDataFrame(list(v.items()), "vec_id long, embedding array<float>").withColumn("score", F.lit("x"))
    got = topk_search.exact_topk(df, df.where("vec_id % 10 = 0"), k=7, block=4, bins=8).collect()
    q = {i: np.floor(1024 * np.array(x, np.float64)) for i, x in v.items() if x is not None and None not in x and np.isfinite(x).all()}
    want = []
    for i in q:
        if i % 10 == 0:
            best = sorted((-int(q[i] @ q[j]), j) for j in q if j != i and len(q[j]) == len(q[i]))[:7]
            want += [(i, k + 1, j, -s) for k, (s, j) in enumerate(best)]
    assert sorted((r.query_id, r.rank, r.vec_id, r.score) for r in got) == sorted(want)
    assert topk_search.exact_topk(df.where("false"), df.where("false")).count() == 0


def test_topk_sql(spark, duck):
    df = spark.read.parquet(f"{SF}/embeddings.parquet")
    assert rows(topk_search.exact_topk(df, df.where("vec_id % 100 = 0"))) == sql_rows(duck, topk_search.ORACLE)


# -- near duplicates -----------------------------------------------------------------------------------------
def brute_classes(data, least=0.8):
    sets = {}
    for i, (_, t) in enumerate(data):
        w = (t or "").encode().split()
        sets[i] = Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else Counter([tuple(w)]) if w else None
    parent = list(range(len(data)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    def alike(a, b):
        union, common = set(a) | set(b), set(a) & set(b)
        if len(common) / len(union) >= least:
            return True
        x, y = ({k: 1 + np.log2(c) for k, c in s.items()} for s in (a, b))
        total = sum(1 / sum(max(x.get(j, 0) / x[i], y.get(j, 0) / y[i]) for j in union) for i in common)
        return total >= least - 1e-9

    for a, b in itertools.combinations(range(len(data)), 2):
        if sets[a] and sets[b] and alike(sets[a], sets[b]):
            parent[max(find(a), find(b))] = min(find(a), find(b))
    groups = defaultdict(set)
    for i in range(len(data)):
        groups[find(i)].add(i)
    return {frozenset(g) for g in groups.values()}


def near_fixture():
    rng = np.random.default_rng(6)
    words = [f"w{i}" for i in range(400)]
    data, base = [], [list(rng.choice(words, n)) for n in (60, 120, 300)]
    for b in base:
        data.append(" ".join(b))
        for k in (0, 1, 2, 6, 25):
            c = list(b)
            for at in rng.choice(len(b), k, replace=False):
                c[at] = "x"
            data.append(" ".join(c))
    data += [" ".join(rng.choice(words, 80)) for _ in range(20)]
    data += ["one line repeated here " * 40 + " ".join(base[0][:30]), "one line repeated here " * 40 + " ".join(base[1][:30])]
    data += ["few words", "few words", "few other"]
    return [(i + 1, t) for i, t in enumerate(data)]


def test_classes_equal_brute_force(spark):
    data = near_fixture()
    got = defaultdict(set)
    for r in near_dedup.classes(docs(spark, data)).collect():
        got[r.class_id].add(r.doc_id - 1)
    assert {frozenset(g) for g in got.values()} == brute_classes(data)
    assert all(min(g) + 1 == c for c, g in got.items())


def edited_copies(copies: int, seed: int = 5) -> list[str]:
    """A text of 400 words and copies with eight words changed: at 0.816 to the text, mostly below 0.7 to each other."""
    rng = np.random.default_rng(seed)
    base = [f"w{i}" for i in range(400)]
    out = [" ".join(base)]
    for c in range(copies):
        new = list(base)
        for place in rng.choice(np.arange(6, 390, 6), 8, replace=False):
            new[place] = f"c{c}x{place}"
        out.append(" ".join(new))
    return out


def test_large_buckets_are_compared_in_full(spark):
    texts = edited_copies(400)
    sets = [near_dedup.shingled([near_dedup.words_of(t)])[0] for t in texts]
    assert all(near_dedup.similarity(sets[0], x) >= 0.8 for x in sets[1:])
    assert max(near_dedup.similarity(sets[i], sets[j]) for i in range(1, 40) for j in range(i + 1, 40)) < 0.8
    assert Counter(b for x in near_dedup.band_hashes(sets) for b in x.tolist()).most_common(1)[0][1] > 64
    got = near_dedup.classes(docs(spark, list(enumerate(texts)))).collect()
    assert len(got) == 401 and len({r.class_id for r in got}) == 1


@pytest.mark.parametrize("two_sides", [False, True])
def test_tile_links_equal_pairs(two_sides):
    rng = np.random.default_rng(8)
    sets = []
    for _ in range(12):
        base = rng.choice(10**6, 60, replace=False).astype(np.uint64)
        for _ in range(4):
            e = np.unique(np.concatenate([base[: int(rng.integers(50, 61))], rng.choice(10**6, int(rng.integers(1, 6))).astype(np.uint64)]))
            sets.append((e, rng.integers(1, int(rng.choice([2, 2, 9])), len(e))))
    sides, groups = [i % 2 if two_sides else 0 for i in range(len(sets))], [b"%d" % (i // 3) for i in range(len(sets))]

    def joined(links):
        group = list(groups)
        for i, j in links:
            group = [group[i] if g == group[j] else g for g in group]
        return {frozenset(i for i, g in enumerate(group) if g == x) for x in group}

    every = [(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if (not two_sides or sides[i] != sides[j]) and near_dedup.similarity(sets[i], sets[j]) >= 0.8]
    got = near_dedup.tile_links(sets, sides, groups, 0.8)
    assert set(got) <= set(every) and joined(got) == joined(every)


def test_signatures_estimate_probability_jaccard():
    rng = np.random.default_rng(7)
    e = rng.integers(0, 2**63, 300).astype(np.uint64)
    a, b = rng.random(300) * 3, rng.random(300) * 3
    a[200:], b[:100] = 0, 0
    exact = near_dedup.probability_jaccard(a, b)
    brute = sum(1 / sum(max(a[j] / a[i], b[j] / b[i]) for j in range(300)) for i in range(100, 200))
    assert np.isclose(exact, brute)
    sets = [(e[w > 0], w[w > 0]) for w in (a, b)]
    s = near_dedup.prob_minhash(np.concatenate([x for x, _ in sets]), np.concatenate([w for _, w in sets]), np.repeat([0, 1], [len(x) for x, _ in sets]), 2, 4096)
    assert abs((s[0] == s[1]).mean() - exact) < 0.03


def test_near_dedup_cases(spark):
    df = docs(spark, [*EDGE, (12, "a b c")])
    got = near_dedup.classes(df).collect()
    assert len(got) == len(EDGE) + 1
    by = defaultdict(list)
    for r in got:
        by[r.doc_id].append(r.class_id)
    assert by[12] == [7] and by[5] == [5] and by[6] == [6] and by[9] == [9] and sorted(by[7]) == [7, 7, 7]
    kept = near_dedup.one_of_each(df)
    assert kept.columns == df.columns
    assert sorted((r.doc_id is None, r.doc_id or 0, r.text or "") for r in kept.collect()) == sorted((i is None, i or 0, t or "") for i, t in dict.fromkeys(EDGE))
    assert near_dedup.classes(df.where("false")).count() == 0


# -- passages -----------------------------------------------------------------------------------------------
def brute_passages(data):
    order = sorted(range(len(data)), key=lambda i: (data[i][0] is not None, data[i][0] or 0))
    words = [(t or "").encode().split() for _, t in data]
    first: dict[tuple, tuple] = {}
    for i in order:
        for s in range(len(words[i]) - 19):
            first.setdefault(tuple(words[i][s : s + 20]), (data[i][0], s))
    out = []
    for i, w in enumerate(words):
        gone = set()
        for s in range(len(w) - 19):
            doc, at = first[tuple(w[s : s + 20])]
            if (doc, at) != (data[i][0], s) and (doc != data[i][0] or at < s):
                gone |= set(range(s, s + 20))
        kept = b" ".join(x for k, x in enumerate(w) if k not in gone)
        out.append((data[i][0], len(w), len(gone), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def passage_fixture():
    rng = np.random.default_rng(8)
    words = [f"v{i}" for i in range(300)]
    text = lambda n: list(rng.choice(words, n))
    shared, data = text(55), []
    for i in range(12):
        data.append((i, " ".join(text(int(rng.integers(5, 90))) + (shared[i % 3 : 55 - i] if i % 2 else []) + text(30))))
    data += [(20, data[3][1]), (21, data[3][1].replace(" ", "\n ")), (22, "the " * 100), (23, "the " * 45), (24, " ".join(["a b c"] * 30)), (25, "short one")]
    loop = " ".join(text(25))
    data += [(26, f"{loop} mid {loop} {loop}"), (27, f"x {loop}")]
    return data


def digested(df):
    return sorted(((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.digests(df).collect()), key=str)


def test_passages_equal_brute_force(spark):
    data = passage_fixture()
    for batches in (1, 2, 3):
        assert digested(substring_dedup.deduplicated(docs(spark, data), batches=batches)) == brute_passages(data)


def test_runs_are_sorted_merged_and_compacted(spark):
    data = passage_fixture()
    index = substring_dedup.FingerprintLog(spark, fan_out=2)
    got = digested(substring_dedup.deduplicated(docs(spark, data), batches=7, index=index))
    assert got == brute_passages(data) and index.compactions >= 2 and all(len(x) <= 2 for x in index.runs.values())
    for kind, first in (("anchors", "anchor"), ("windows", "w1"), ("texts", "key")):
        for f in spark.read.parquet(*index.runs[kind]).inputFiles():
            a = [r[first] for r in spark.read.parquet(f).collect()]
            assert a == sorted(a)


def test_later_batches_meet_older_runs(spark):
    """A passage that one text has alone in the first batch, twice in later ones; copies of whole texts over batches."""
    words = [f"w{i}" for i in range(200)]
    join = lambda a, b: " ".join(words[a:b])
    data = [(1, join(0, 60)), (2, join(60, 100)), (3, "a " + join(10, 45)), (4, join(60, 100)), (5, join(20, 50) + " b " + join(70, 95)), (6, "z")]
    index, got = substring_dedup.FingerprintLog(spark, fan_out=1), []
    for part in (data[:2], data[2:4], data[4:]):
        light, changed = index.ingest(docs(spark, part))
        got.append({r.ord: (r.n_removed, r.kept) for r in changed.collect()} | {r.ord: "copy" for r in light.where("copy").collect()})
    assert got == [{}, {3: (35, "a"), 4: "copy"}, {5: (55, "b")}]
    assert index.compactions == 2 and index.read("anchors").where("n = 1").count() > 0
    merged = index.read("windows").groupBy("w1", "w2").count()
    assert merged.where("count > 1").isEmpty()


def test_own_repeats_by_words():
    rng = np.random.default_rng(3)
    words = [b"%d" % x for x in rng.integers(0, 3, 90)] + [b"x"] * 50 + [b"%d" % (i % 7) for i in range(100)]
    tuples = [tuple(words[i : i + 20]) for i in range(len(words) - 19)]
    others = np.array([5, 60])
    bad = {tuples[i] for i in others}
    due = [i for i, t in enumerate(tuples) if t in tuples[:i] or t in bad]
    assert substring_dedup.own_repeats(words, others).tolist() == due


def test_passage_cases(spark):
    df = docs(spark, [*EDGE, (7, "k " * 30), (30, "word " * 40)])
    got = {(r.doc_id, r.n_words): r for r in substring_dedup.digests(substring_dedup.deduplicated(df)).collect()}
    assert got[5, 0].n_removed == got[6, 0].n_removed == 0 and got[30, 40].n_removed == 40
    assert got[8, 9000].n_removed == 9000 - 1 and got[7, 30].n_removed == 29
    clean = substring_dedup.cleaned(df)
    assert clean.columns == df.columns and clean.count() == df.count()
    assert {r.doc_id: r.text for r in clean.collect()}[9] == " \n\t "
    assert substring_dedup.deduplicated(df.where("false")).count() == 0


def test_passages_sql(spark, duck):
    df = spark.read.parquet(f"{SF}/documents.parquet")
    assert rows(substring_dedup.digests(substring_dedup.deduplicated(df))) == sql_rows(duck, substring_dedup.ORACLE)


def test_filter_passes_every_value(spark):
    wanted = spark.range(0, 1000).select((F.col("id") * 7919).alias("v"))
    bits = bloom_filter(wanted, "v")
    assert passed(wanted, "v", bits).count() == 1000
    assert passed(spark.range(10_000_000, 10_010_000).select(F.col("id").alias("v")), "v", bits).count() < 300
    assert passed(wanted, "v", bloom_filter(wanted.where("false"), "v")).count() == 0


# -- pipeline -----------------------------------------------------------------------------------------------
def test_pipeline_equals_plain_version(spark):
    import corpus_pipeline

    start = spark.read.parquet(f"{SF}/documents.parquet")
    before = {r.doc_id: r for r in start.collect()}
    a = {r.doc_id: r for r in corpus_pipeline.languages(spark, start, SF).collect()}
    assert a == before  # every document here has a language
    kept = corpus_pipeline.near_duplicates(spark, start, SF)
    b = sorted(r.doc_id for r in kept.collect())
    ids = sorted(before)
    assert b == sorted(ids[min(g)] for g in brute_classes([(i, before[i].text) for i in ids]))
    c = {r.doc_id: r.text for r in corpus_pipeline.passages(spark, kept, SF).collect()}
    plain = {x[0]: x[3] for x in brute_passages([(i, before[i].text) for i in b])}
    assert sorted(c) == b and all(hashlib.sha256(b" ".join(t.encode().split())).hexdigest() == plain[i] for i, t in c.items())
    out = corpus_pipeline.run(spark, SF)
    assert {r.doc_id for r in out.select("doc_id").distinct().collect()} == set(b)


def test_pipeline_keeps_one_of_a_large_group(spark):
    import corpus_pipeline

    data = list(enumerate(edited_copies(300, seed=9) + ["a text of its own " + " ".join(f"v{i}" for i in range(50))]))
    kept = corpus_pipeline.near_duplicates(spark, docs(spark, data, extra=False), SF)
    assert sorted(r.doc_id for r in kept.collect()) == [0, 301]


def test_pipeline_edge_rows(spark):
    import corpus_pipeline

    df = docs(spark, EDGE, extra=False).withColumns({"lang": F.lit("en"), "source": F.lit("s"), "n_chars": F.lit(1).cast("long"), "score": F.lit("clash")})
    for _, stage in corpus_pipeline.STAGES[:4]:
        assert stage(spark, df, SF).columns == df.columns
        assert stage(spark, df.where("false"), SF).count() == 0
