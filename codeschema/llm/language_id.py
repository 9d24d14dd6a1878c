"""Language identification by unigram pieces, marginalised over segmentations.

The pieces of a fixed public vocabulary get a probability in each language.  The likelihood of a word is
the sum over all its segmentations into pieces (forward algorithm), for all languages at once; a text's is
the product over its words.  Probabilities are fitted by expectation maximisation (forward-backward) on
word counts of a bounded sample of labelled texts; scoring covers every word of every text.

Defined cases: a text that is null or has no letter is ``und`` with score 0; ties go to the language
that sorts first; texts of any length are read whole; without any labelled text all are ``und``.
Bounds of the fit: ``most_langs`` languages (those with most labelled texts), ``per_lang`` texts (by hash of the id) and
``most_words`` distinct words a language; words of more than 40 characters are learned from in runs of 40.  Scoring sums over
whole words, however long, in memory that grows with a word's length by a few bytes a character.
"""

from __future__ import annotations

import uuid
from collections import Counter, defaultdict
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .base import free_name, held_out, in_pieces, only_caches, slices

MARK, UNKNOWN_P, FLOOR = "▁", 1e-7, 1e-8
_BASE = np.uint64(0x9E3779B97F4A7C15)
_LONG = 40  # beyond so many characters sums are rescaled as they grow
_SCORERS: dict[str, Scorer | None] = {}  # by the name that the driver gives each model


class Vocabulary:
    """Pieces of a public sentencepiece model, found by a hash of their characters."""

    def __init__(self, path: str) -> None:
        from sentencepiece import sentencepiece_model_pb2 as pb

        with open(path, "rb") as f:
            proto = pb.ModelProto.FromString(f.read())
        # Texts are lower-cased, so only such pieces can occur.
        pieces = sorted({p.piece for p in proto.pieces if p.type == 1 and p.piece == p.piece.lower()}, key=lambda p: (len(p), p))
        self.pieces, self.longest = pieces, max(map(len, pieces))
        self.powers = [np.uint64(1)]
        with np.errstate(over="ignore"):
            for _ in range(self.longest):
                self.powers.append(self.powers[-1] * _BASE)
        keys = np.empty(len(pieces), np.uint64)
        for n, group in _by_length(pieces).items():
            keys[group] = self._prefixes(_codes([pieces[i] for i in group], n))[n] + np.uint64(n)
        order = np.argsort(keys)
        self.keys, self.numbers = keys[order], order.astype(np.int32)
        self.none, self.unknown, self.size = len(pieces), len(pieces) + 1, len(pieces) + 2

    def _prefixes(self, codes: np.ndarray) -> list[np.ndarray]:
        out = [np.zeros(len(codes), np.uint64)]
        with np.errstate(over="ignore"):
            for j in range(codes.shape[1]):
                out.append(out[-1] * _BASE + codes[:, j])
        return out

    def lookups(self, words: list[str], n: int) -> list[list[np.ndarray]]:
        """For words of n characters: [end - 1][length - 1] -> piece numbers."""
        prefix = self._prefixes(_codes(words, n))
        out = []
        with np.errstate(over="ignore"):
            for j in range(1, n + 1):
                row = []
                for length in range(1, min(j, self.longest) + 1):
                    key = prefix[j] - prefix[j - length] * self.powers[length] + np.uint64(length)
                    at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
                    row.append(np.where(self.keys[at] == key, self.numbers[at], np.int32(self.unknown if length == 1 else self.none)))
                out.append(row)
        return out


def _by_length(words: list[str]) -> dict[int, list[int]]:
    groups: dict[int, list[int]] = defaultdict(list)
    for i, w in enumerate(words):
        groups[len(w)].append(i)
    return groups


def _codes(words: list[str], n: int) -> np.ndarray:
    return np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), "<u4").reshape(len(words), n).astype(np.uint64)


def spelled(word: str) -> str | None:
    """The word as it is scored: lower case, without signs at its ends; None if it has no letter."""
    word = word.lower()
    if not word.isalpha():
        a, b = 0, len(word)
        while a < b and not word[a].isalpha():
            a += 1
        while b > a and not word[b - 1].isalpha():
            b -= 1
        if a == b:
            return None
        word = word[a:b]
    return MARK + word


def forward(found: list[list[np.ndarray]], p: np.ndarray) -> list[np.ndarray]:
    """Sums over segmentations of each beginning: [end] -> words x languages."""
    alpha = [np.ones((len(found[0][0]), p.shape[1]))]
    for row in found:
        acc = alpha[-1] * p[row[0]]
        for length in range(2, len(row) + 1):
            acc += alpha[-length] * p[row[length - 1]]
        alpha.append(acc)
    return alpha


def long_forward(words: list[str], vocabulary: Vocabulary, p: np.ndarray, most_cells: int = 1 << 20) -> np.ndarray:
    """Logarithms of the words' sums, words x languages, for words of any length.

    Words of like length go together; only the last ``longest`` sums of each are held, and rescaled every few steps.
    """
    out, order, at = np.zeros((len(words), p.shape[1])), sorted(range(len(words)), key=lambda i: len(words[i])), 0
    while at < len(order):
        stop = at + 1
        while stop < len(order) and (stop + 1 - at) * len(words[order[stop]]) <= most_cells:
            stop += 1
        some, at = order[at:stop], stop
        out[some] = _long_batch([words[i] for i in some], vocabulary, p)
    return out


def _long_batch(words: list[str], vocabulary: Vocabulary, p: np.ndarray) -> np.ndarray:
    w, sizes, reach = len(words), np.array([len(x) for x in words]), vocabulary.longest
    n = int(sizes.max())
    codes = _codes([x.ljust(n, "\0") for x in words], n)
    prefix = np.zeros((w, n + 1), np.uint64)
    with np.errstate(over="ignore"):
        for j in range(n):
            prefix[:, j + 1] = prefix[:, j] * _BASE + codes[:, j]
    powers = np.array(vocabulary.powers[1 : reach + 1], np.uint64)
    out, scale = np.zeros((w, p.shape[1])), np.zeros((w, p.shape[1]))
    held = np.zeros((reach, w, p.shape[1]))  # sums up to the last places, the latest first
    held[0] = 1.0
    step = max(1, min(n, 200_000 // (w * reach)))
    for start in range(1, n + 1, step):
        ends = np.arange(start, min(n, start + step - 1) + 1)
        back = ends[:, None] - np.arange(1, reach + 1)
        with np.errstate(over="ignore"):
            keys = prefix[:, ends][:, :, None] - prefix[:, np.maximum(back, 0)] * powers + np.arange(1, reach + 1, dtype=np.uint64)
        found = np.minimum(np.searchsorted(vocabulary.keys, keys), len(vocabulary.keys) - 1)
        known = (vocabulary.keys[found] == keys) & (back >= 0)
        number = np.where(known, vocabulary.numbers[found], vocabulary.none)
        number[:, :, 0] = np.where(known[:, :, 0], number[:, :, 0], vocabulary.unknown)
        for k, j in enumerate(ends.tolist()):
            acc = np.einsum("lwg,wlg->wg", held, p[number[:, k]])
            done = np.flatnonzero(sizes == j)
            if len(done):
                out[done] = np.log(np.maximum(acc[done], 1e-300)) + scale[done]
            held = np.concatenate([acc[None], held[:-1]])
            if j % 8 == 0:
                top = np.maximum(held.max(axis=0), 1e-300)
                held, scale = held / top, scale + np.log(top)
    return out


def expected_counts(found: list[list[np.ndarray]], p: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """Expected uses of each piece in each language; weights: words x languages."""
    n, alpha = len(found), forward(found, p)
    beta = [np.zeros_like(alpha[0]) for _ in range(n)] + [np.ones_like(alpha[0])]
    scale = weights / np.maximum(alpha[n], 1e-300)
    out = np.zeros_like(p)
    for j in range(n, 0, -1):
        for length in range(1, len(found[j - 1]) + 1):
            number = found[j - 1][length - 1]
            step = p[number] * beta[j]
            beta[j - length] += step
            use = alpha[j - length] * step * scale
            for lang in range(p.shape[1]):
                out[:, lang] += np.bincount(number, use[:, lang], len(p))
    return out


def in_runs(counts: Counter) -> Counter:
    """Counts of words, long ones in runs of ``_LONG`` characters."""
    out: Counter = Counter()
    for word, n in counts.items():
        for i in range(0, len(word), _LONG):
            out[word[i : i + _LONG]] += n
    return out


def fit(counts: dict[str, Counter], vocabulary: Vocabulary, rounds: int = 4, shared: float = 0.05) -> np.ndarray:
    """Piece probabilities, pieces x languages (sorted), mixed with ``shared`` of their mean."""
    langs = sorted(counts)
    counts = {lang: in_runs(counts[lang]) for lang in langs}
    words = sorted(set(chain.from_iterable(counts.values())))
    weights = np.array([[counts[lang].get(w, 0) for lang in langs] for w in words], np.float64).reshape(len(words), len(langs))
    groups = []
    for n, at in _by_length(words).items():
        for i in range(0, len(at), 20_000):
            some = at[i : i + 20_000]
            groups.append((vocabulary.lookups([words[k] for k in some], n), weights[some]))
    p = np.full((vocabulary.size, len(langs)), 1.0 / vocabulary.size)
    for _ in range(rounds):
        p[vocabulary.none], p[vocabulary.unknown] = 0.0, UNKNOWN_P
        uses = sum((expected_counts(found, p, w) for found, w in groups), np.zeros_like(p))
        uses[vocabulary.none] = 0.0
        uses += 0.01
        p = uses / uses.sum(axis=0)
        p = (1 - shared) * p + shared * p.mean(axis=1, keepdims=True) + FLOOR
    p[vocabulary.none], p[vocabulary.unknown] = 0.0, UNKNOWN_P
    return p


class Scorer:
    def __init__(self, path: str, p: np.ndarray, prior: np.ndarray, most_words: int = 300_000) -> None:
        self.vocabulary, self.p, self.prior, self.most = Vocabulary(path), p, prior, most_words
        self.known: dict[str, int] = {}
        self.rows = np.zeros((0, p.shape[1] + 1))

    def word_scores(self, words: list[str]) -> np.ndarray:
        """Log-likelihood in each language, and in the last column whether the word has a letter."""
        out = np.zeros((len(words), self.p.shape[1] + 1))
        shape = [spelled(w) for w in words]
        at = [i for i, s in enumerate(shape) if s]
        long = [i for i in at if len(shape[i]) > _LONG]
        if long:
            out[long, :-1] = long_forward([shape[i] for i in long], self.vocabulary, self.p)
            out[long, -1] = 1
            at = [i for i in at if len(shape[i]) <= _LONG]
        for n, group in _by_length([shape[i] for i in at]).items():
            for k in range(0, len(group), 20_000):
                rows = [at[i] for i in group[k : k + 20_000]]
                found = self.vocabulary.lookups([shape[i] for i in rows], n)
                out[rows, :-1] = np.log(forward(found, self.p)[n])
                out[rows, -1] = 1
        return out

    def texts(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(best language's number or -1, its posterior) for each text."""
        parts = [t.split() for t in texts]
        words = set(chain.from_iterable(parts))
        new = [w for w in words if w not in self.known]
        if len(self.known) + len(new) > self.most:
            self.known, self.rows, new = {}, self.rows[:0], list(words)
        self.known.update(zip(new, range(len(self.rows), len(self.rows) + len(new)), strict=True))
        self.rows = np.concatenate([self.rows, self.word_scores(new)])
        best, score = np.full(len(texts), -1), np.zeros(len(texts))
        for i, p in enumerate(parts):
            total = self.rows[np.fromiter(map(self.known.__getitem__, p), np.int64, len(p))].sum(axis=0)
            if total[-1]:
                logs = total[:-1] + self.prior
                best[i] = int(np.argmax(logs))
                score[i] = 1.0 / np.exp(logs - logs.max()).sum()
        return best, score


def training_sample(docs: DataFrame, per_group: int, group: Column, id_col: str, most_groups: int = 200) -> DataFrame:
    """About ``per_group`` rows of each of the ``most_groups`` greatest groups, by a hash of the id: the same ones at every run."""
    mark = free_name(docs, "group")
    rows = docs.withColumn(mark, group.cast("string")).where(F.col(mark).isNotNull())
    counts = rows.groupBy(mark).agg(F.count("*").alias("n")).orderBy(F.desc("n"), mark).limit(most_groups).collect()
    if not counts:
        return rows.where("false").drop(mark)
    rates = F.create_map(*chain.from_iterable((F.lit(r[mark]), F.lit(min(1_000_000, -(-per_group * 1_000_000 // r["n"])))) for r in counts))
    rate = F.coalesce(F.try_element_at(rates, F.col(mark)), F.lit(0))
    return rows.where(F.pmod(F.xxhash64(F.col(id_col).cast("string"), F.lit("sample")), F.lit(1_000_000)) < rate).drop(mark)


def train(docs: DataFrame, vocabulary_path: str, per_lang: int = 500, most_words: int = 30_000, most_langs: int = 200, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> tuple[list[str], np.ndarray, np.ndarray]:
    """(languages, piece probabilities, log prior), learned from rows that are not held out."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).where(~held_out() & F.col("text").isNotNull() & F.col("lang").isNotNull())
    counts: dict[str, Counter] = defaultdict(Counter)
    texts: Counter = Counter()
    for r in training_sample(rows, per_lang, F.col("lang"), "doc_id", most_langs).orderBy("doc_id").toLocalIterator():
        counts[r["lang"]].update(filter(None, map(spelled, r["text"].split())))
        texts[r["lang"]] += 1
    langs = sorted(lang for lang in counts if counts[lang])
    if not langs:
        return [], np.zeros((0, 0)), np.zeros(0)
    kept = {lang: Counter(dict(sorted(counts[lang].items(), key=lambda x: (-x[1], x[0]))[:most_words])) for lang in langs}
    n = np.array([texts[lang] for lang in langs], np.float64)
    return langs, fit(kept, Vocabulary(vocabulary_path)), np.log(n / n.sum())


def identify(docs: DataFrame, model: tuple[list[str], np.ndarray, np.ndarray], vocabulary_path: str, id_col: str = "doc_id", text_col: str = "text", keep: bool = False, pred_col: str = "lang_pred", score_col: str = "lang_score") -> DataFrame:
    """Language and score for each row, in ``pred_col`` and ``score_col``: beside ``id_col``, or beside all columns if ``keep``
    (then the two names must be free)."""
    langs, p, prior = model
    shared = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, langs, p, prior))  # pieces x languages
    columns = docs.columns if keep else [id_col]
    base = docs.select(*[F.col(f"`{c}`") for c in columns], F.col(text_col).cast("string").alias(free_name(docs, "text")))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema.fields[:-1]), f"`{pred_col}` string", f"`{score_col}` double"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, langs, p, prior = shared.value
        only_caches("language_id", _SCORERS.clear)
        if name not in _SCORERS:
            _SCORERS.clear()
            _SCORERS[name] = Scorer(vocabulary_path, p, prior) if langs else None
        scorer, names = _SCORERS[name], [*langs, "und"]
        for batch in in_pieces(batches, len(columns)):
            texts = [t or "" for t in batch.column(batch.num_columns - 1).to_pylist()]
            best, score = np.full(len(texts), -1), np.zeros(len(texts))
            if scorer:
                for i, j in slices(texts, 1_000_000):
                    best[i:j], score[i:j] = scorer.texts(texts[i:j])
            said = pa.array([names[b] for b in best], pa.string())
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], said, pa.array(score)], names=[*batch.schema.names[:-1], pred_col, score_col])

    return base.mapInArrow(run, schema)


def predictions(docs: DataFrame, vocabulary_path: str) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document."""
    got = identify(docs, train(docs, vocabulary_path), vocabulary_path)
    return got.select("doc_id", held_out().alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))
