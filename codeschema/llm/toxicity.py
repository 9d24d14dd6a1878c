"""Toxicity: a bidirectional gated recurrent network with attention pooling, in numpy.

A word enters by two inputs: an embedding of the word (if the training sample has it often enough) and the
mean embedding of its character trigrams, so unseen forms of a word are still read.  A gated recurrent
layer runs over each window of ``SPAN`` words in both directions; attention pools its states into one
logit.  Windows overlap by half, every window of a text is scored, and the text's score is its highest
window's.  Training goes back through all of that; a text's loss reaches its windows by a soft maximum.

Defined cases: a text that is null or has no words gets the share of toxic training texts as its score; without
any labelled text all scores are 0; repeated rows get equal scores; texts of any length are read whole.
Bounds of the fit: ``per_label`` labelled texts of each label (by hash of the id), ``most_words`` words.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import held_out, in_pieces, slices
from .language_id import training_sample

SPAN, STRIDE, HIDDEN, WIDE, ATTEND, GRAMS = 16, 8, 8, 12, 8, 1 << 14
SIGNS = ".,;:!?\"'()[]{}<>|*#%&$/\\-_+=~`^@…«»“”„’‘"
_SCORERS: dict[int, Scorer] = {}


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


def words_of(text: str) -> list[str]:
    return text.lower().split()


def trigrams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed character trigrams of all words (ends marked), and where each word's begin."""
    codes = np.frombuffer("".join([f"\x02{w}\x03" for w in words]).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    lengths = np.fromiter(map(len, words), np.int64, len(words)) + 2
    with np.errstate(over="ignore"):
        h = codes[:-2] * np.uint64(0x9E3779B97F4A7C15) + codes[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + codes[2:] * np.uint64(0x165667B19E3779F9)
        h ^= h >> np.uint64(31)
        h *= np.uint64(0xBF58476D1CE4E5B9)
    h = (h >> np.uint64(40)).astype(np.int64) % GRAMS
    ends = np.cumsum(lengths)
    keep = np.ones(len(codes), bool)
    keep[ends - 1] = keep[np.maximum(ends - 2, 0)] = False  # a trigram of a word with one letter is whole: \x02 a \x03
    return h[keep[:-2]], np.concatenate([[0], np.cumsum(lengths - 2)])[:-1]


def stripped(word: str) -> str:
    return word.strip(SIGNS) or word


@dataclass
class Network:
    words: dict[str, int]
    p: dict[str, np.ndarray]
    prior: float
    shift: float = 0.0  # of logits, from the sample's share of toxic texts to that of all labelled ones

    @staticmethod
    def fresh(words: dict[str, int], prior: float, seed: int = 7) -> Network:
        rng = np.random.default_rng(seed)
        draw = lambda *shape, s=0.1: (rng.standard_normal(shape) * s).astype(np.float32)
        p = {"word": draw(len(words) + 1, WIDE), "gram": draw(GRAMS, WIDE, s=0.3), "attend": draw(2 * HIDDEN, ATTEND, s=0.3), "attend_b": draw(ATTEND, s=0.0), "query": draw(ATTEND, s=0.3), "out": draw(2 * HIDDEN, s=0.3), "out_b": draw(1, s=0.0)}
        p["word"][-1] = 0  # of words that the sample doesn't have
        for d in "fb":
            p |= {f"x_{d}": draw(2 * WIDE, 3 * HIDDEN, s=0.3), f"b_{d}": draw(3 * HIDDEN, s=0.0), f"u_{d}": draw(HIDDEN, 2 * HIDDEN, s=0.3), f"n_{d}": draw(HIDDEN, HIDDEN, s=0.3)}
        return Network(words, p, prior)

    def inputs(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Input vectors of distinct words; also their numbers, trigrams and where those begin."""
        plain = [stripped(w) for w in words]
        numbers = np.fromiter((self.words.get(w, len(self.words)) for w in plain), np.int64, len(plain))
        grams, starts = trigrams(plain)
        counts = np.diff(np.append(starts, len(grams)))[:, None]
        mean = np.add.reduceat(self.p["gram"][grams], starts, axis=0) / counts
        return np.concatenate([self.p["word"][numbers], mean.astype(np.float32)], axis=1), numbers, grams, starts


def gru(x: np.ndarray, mask: np.ndarray, u: np.ndarray, un: np.ndarray, back: bool, keep: bool) -> tuple[np.ndarray, list]:
    """States (time, windows, HIDDEN) from projected inputs (time, windows, 3 * HIDDEN); padding holds the state."""
    steps, n = x.shape[0], x.shape[1]
    states, saved, h = np.empty((steps, n, HIDDEN), np.float32), [], np.zeros((n, HIDDEN), np.float32)
    for t in range(steps - 1, -1, -1) if back else range(steps):
        gates = sigmoid(x[t, :, : 2 * HIDDEN] + h @ u)
        r, z = gates[:, :HIDDEN], gates[:, HIDDEN:]
        inner = h @ un
        new = np.tanh(x[t, :, 2 * HIDDEN :] + r * inner)
        m = mask[t][:, None]
        if keep:
            saved.append((t, h, r, z, inner, new, m))
        h = h + m * (1 - z) * (new - h)
        states[t] = h
    return states, saved


def gru_back(d_states: np.ndarray, saved: list, u: np.ndarray, un: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    dx = np.zeros((d_states.shape[0], d_states.shape[1], 3 * HIDDEN), np.float32)
    du, dun, dh = np.zeros_like(u), np.zeros_like(un), np.zeros_like(d_states[0])
    for t, h, r, z, inner, new, m in reversed(saved):
        dh = dh + d_states[t]
        d_new = dh * m * (1 - z) * (1 - new * new)
        d_z = -dh * m * (new - h) * z * (1 - z)
        d_r = d_new * inner * r * (1 - r)
        gates, d_inner = np.concatenate([d_r, d_z], axis=1), d_new * r
        dx[t, :, : 2 * HIDDEN], dx[t, :, 2 * HIDDEN :] = gates, d_new
        du += h.T @ gates
        dun += h.T @ d_inner
        dh = dh * (1 - m * (1 - z)) + gates @ u.T + d_inner @ un.T
    return dx, du, dun


def forward(p: dict[str, np.ndarray], xf: np.ndarray, xb: np.ndarray, mask: np.ndarray, keep: bool = False) -> tuple[np.ndarray, tuple]:
    """Logits of windows; xf and xb: projected inputs (time, windows, 3 * HIDDEN)."""
    hf, sf = gru(xf, mask, p["u_f"], p["n_f"], False, keep)
    hb, sb = gru(xb, mask, p["u_b"], p["n_b"], True, keep)
    h = np.concatenate([hf, hb], axis=2)
    a = np.tanh(h @ p["attend"] + p["attend_b"])
    s = a @ p["query"] + (mask - 1) * 1e9
    w = np.exp(s - s.max(axis=0))
    w /= w.sum(axis=0)
    pooled = np.einsum("tn,tnh->nh", w, h)
    return pooled @ p["out"] + p["out_b"][0], (h, a, w, pooled, sf, sb)


def backward(p: dict[str, np.ndarray], d_logit: np.ndarray, saved: tuple) -> tuple[np.ndarray, np.ndarray, dict[str, np.ndarray]]:
    """Gradients of the projected inputs in both directions, and of the parameters above them."""
    h, a, w, pooled, sf, sb = saved
    g = {"out": d_logit @ pooled, "out_b": d_logit.sum(keepdims=True)}
    d_pooled = d_logit[:, None] * p["out"]
    dh = w[:, :, None] * d_pooled
    dw = np.einsum("nh,tnh->tn", d_pooled, h)
    ds = w * (dw - (w * dw).sum(axis=0))
    g["query"] = np.einsum("tn,tna->a", ds, a)
    da = ds[:, :, None] * p["query"] * (1 - a * a)
    g["attend"], g["attend_b"] = np.einsum("tnh,tna->ha", h, da, optimize=True), da.sum(axis=(0, 1))
    dh = dh + da @ p["attend"].T
    xf, g["u_f"], g["n_f"] = gru_back(dh[:, :, :HIDDEN], sf, p["u_f"], p["n_f"])
    xb, g["u_b"], g["n_b"] = gru_back(dh[:, :, HIDDEN:], sb, p["u_b"], p["n_b"])
    return xf, xb, g


def window_starts(n: int) -> np.ndarray:
    """Where the windows over n words begin: every STRIDE words, the last one ending with the text."""
    if n <= SPAN:
        return np.zeros(min(n, 1), np.int64)
    return np.append(np.arange(0, n - SPAN, STRIDE), n - SPAN)


def windows(numbers: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row numbers time x windows, mask, text of each window) from each text's word rows."""
    starts = [window_starts(len(x)) for x in numbers]
    owner = np.repeat(np.arange(len(numbers)), [len(s) for s in starts])
    flat = np.concatenate([*numbers, np.zeros(SPAN, np.int64)])
    offset = np.concatenate([[0], np.cumsum([len(x) for x in numbers])])
    first = np.concatenate([*starts, np.zeros(0, np.int64)]) + offset[owner]
    at = first + np.arange(SPAN)[:, None]
    return flat[np.minimum(at, len(flat) - 1)], (at < offset[owner + 1]).astype(np.float32), owner


def train(texts: list[str], labels: list[int], most_words: int = 20_000, least_texts: int = 3, batch: int = 1200, updates: int = 400, rate: float = 0.01, decay: float = 0.02, keep: float = 0.7, seed: int = 7) -> Network | None:
    """Adam on the logistic loss of whole texts."""
    if not texts or len(set(labels)) < 2:
        return None
    split = [words_of(t) for t in texts]
    seen = Counter(chain.from_iterable({stripped(w) for w in s} for s in split))
    often = sorted((w for w, n in seen.items() if n >= least_texts), key=lambda w: (-seen[w], w))[:most_words]
    net, rng = Network.fresh({w: i for i, w in enumerate(often)}, float(np.mean(labels))), np.random.default_rng(seed)
    y = np.array(labels, np.float32)
    p, m1, m2, step = net.p, {k: np.zeros_like(v) for k, v in net.p.items()}, {k: np.zeros_like(v) for k, v in net.p.items()}, 0
    sizes = [len(window_starts(len(s))) for s in split]
    epochs = int(np.clip(-(-updates * batch // max(1, sum(sizes))), 3, 30))
    for epoch in range(epochs):
        order, at = rng.permutation(len(texts)), 0
        while at < len(order):
            some, held = [], 0
            while at < len(order) and (not some or held + sizes[order[at]] <= batch):
                some.append(order[at])
                held += sizes[order[at]]
                at += 1
            if not held:
                continue
            words = sorted(set(chain.from_iterable(split[i] for i in some)))
            index = {w: i for i, w in enumerate(words)}
            x, numbers, grams, starts = net.inputs(words)
            hide = rng.random(len(words)) < 0.3  # the characters have to do without the word
            x[hide, :WIDE] = 0
            thin = (rng.random((len(words), 2 * WIDE)) < keep).astype(np.float32) / keep
            x *= thin
            rows, mask, owner = windows([np.fromiter(map(index.__getitem__, split[i]), np.int64, len(split[i])) for i in some])
            logits, saved = forward(p, (x @ p["x_f"] + p["b_f"])[rows], (x @ p["x_b"] + p["b_b"])[rows], mask, keep=True)
            share = np.exp(2 * (logits - np.maximum.reduceat(logits, np.searchsorted(owner, np.unique(owner)))[np.unique(owner, return_inverse=True)[1]]))
            share /= np.bincount(owner, share, len(some))[owner]
            doc = np.bincount(owner, share * logits, len(some))
            error = (sigmoid(doc) - y[some]) / len(some)
            d_xf, d_xb, g = backward(p, (share * error[owner]).astype(np.float32), saved)
            dx = np.zeros_like(x)
            for d, dxs in (("f", d_xf), ("b", d_xb)):
                flat = dxs.reshape(-1, 3 * HIDDEN)
                by_word = np.stack([np.bincount(rows.ravel(), flat[:, k], len(words)) for k in range(3 * HIDDEN)], axis=1).astype(np.float32)
                g[f"x_{d}"], g[f"b_{d}"] = x.T @ by_word, by_word.sum(axis=0)
                dx += by_word @ p[f"x_{d}"].T
            dx *= thin
            g["word"], g["gram"] = np.zeros_like(p["word"]), np.zeros_like(p["gram"])
            np.add.at(g["word"], numbers[~hide], dx[~hide, :WIDE])
            g["word"][-1] = 0
            counts = np.diff(np.append(starts, len(grams)))
            np.add.at(g["gram"], grams, np.repeat(dx[:, WIDE:] / counts[:, None], counts, axis=0))
            step += 1
            pace = rate * (1 - epoch / (epochs + 1))
            for k, v in g.items():
                v = np.clip(v, -1, 1)
                m1[k] += 0.1 * (v - m1[k])
                m2[k] += 0.001 * (v * v - m2[k])
                if k in ("word", "gram"):
                    p[k] *= 1 - pace * decay
                p[k] -= pace * (m1[k] / (1 - 0.9**step)) / (np.sqrt(m2[k] / (1 - 0.999**step)) + 1e-6)
    return net


class Scorer:
    def __init__(self, net: Network, most_words: int = 200_000) -> None:
        self.net, self.most, self.known = net, most_words, {}
        self.rows = np.zeros((0, 6 * HIDDEN), np.float32)
        self.weights = np.concatenate([net.p["x_f"], net.p["x_b"]], axis=1)
        self.bias = np.concatenate([net.p["b_f"], net.p["b_b"]])

    def _numbers(self, split: list[list[str]]) -> list[np.ndarray]:
        words = set(chain.from_iterable(split))
        new = [w for w in words if w not in self.known]
        if len(self.known) + len(new) > self.most:
            self.known, self.rows, new = {}, self.rows[:0], list(words)
        if new:
            self.known.update(zip(new, range(len(self.rows), len(self.rows) + len(new)), strict=True))
            self.rows = np.concatenate([self.rows, self.net.inputs(new)[0] @ self.weights + self.bias])
        return [np.fromiter(map(self.known.__getitem__, s), np.int64, len(s)) for s in split]

    def scores(self, texts: list[str], most_windows: int = 8192) -> np.ndarray:
        split = [words_of(t) for t in texts]
        rows, mask, owner = windows(self._numbers(split))
        best = np.full(len(texts), -np.inf)
        for i in range(0, rows.shape[1], most_windows):
            x = self.rows[rows[:, i : i + most_windows]]
            logits, _ = forward(self.net.p, x[:, :, : 3 * HIDDEN], x[:, :, 3 * HIDDEN :], mask[:, i : i + most_windows])
            np.maximum.at(best, owner[i : i + most_windows], logits)
        return np.where(np.isfinite(best), sigmoid(np.where(np.isfinite(best), best + self.net.shift, 0.0)), self.net.prior)


def fit(docs: DataFrame, labels: DataFrame, per_label: int = 1500, most_chars: int = 100_000) -> Network | None:
    """A network from labelled texts that are not held out; both tables by doc_id.

    Bounds of the fit: about ``per_label`` texts of each label, none of more than ``most_chars`` characters.
    """
    marks = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    marks = marks.where(~held_out())
    shares = marks.agg(F.avg((F.col("toxic") > 0).cast("double")).alias("share")).first()["share"]
    known = training_sample(marks, per_label, F.col("toxic"), "doc_id")
    # A bounded sample of ids picks the texts.
    rows = docs.select("doc_id", "text").where(F.length("text") <= most_chars).join(F.broadcast(known), "doc_id").orderBy("doc_id", "text").collect()
    net = train([r["text"] for r in rows], [int(r["toxic"] > 0) for r in rows])
    if net and 0 < shares < 1:
        net.shift = float(np.log(shares / (1 - shares)) - np.log(net.prior / (1 - net.prior)))
        net.prior = float(shares)
    return net


def score(docs: DataFrame, net: Network | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and score of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = shared.value
        if net is not None and id(net) not in _SCORERS:
            _SCORERS.clear()
            _SCORERS[id(net)] = Scorer(net)
        for batch in in_pieces(batches, 1):
            texts = [t or "" for t in batch.column(1).to_pylist()]
            out = np.zeros(len(texts))
            if net is not None:
                for i, j in slices(texts, 500_000):
                    out[i:j] = _SCORERS[id(net)].scores(texts[i:j])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out)], names=["doc_id", "score"])

    wanted = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return wanted.mapInArrow(run, "doc_id long, score double")


def predictions(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    got = score(docs, fit(docs, labels))
    return got.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
