"""Toxicity scores from averaged subword embeddings under a linear softmax, trained jointly in numpy.

A word is the bag of its character n-grams (with word boundaries) and itself, hashed into a table of embeddings.
A window of words is the average of its word vectors, each the average of its subwords; a two-class softmax on
that average gives the window's probability. A text's score is the highest among its windows, so one insult in a
long text is not averaged away. Embeddings and softmax weights are trained together: first on whole texts, then
on the window that scores highest in each text (positives learn from their worst window, negatives from theirs).
Unseen misspellings share most n-grams with known words and so get similar vectors.

Fitting uses a bounded sample: the ``positives`` toxic and ``negatives`` other labelled texts with the smallest
id hash among texts of at most ``max_chars`` characters outside the held-out fold. Scoring reads whole texts.

Edge cases: null, empty and wordless texts get the score of an empty window, the bias alone; rows are independent;
a label that is null is ignored; with no usable labels every score is 0.
"""

from __future__ import annotations

import zlib
from array import array
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .texts import held_out, map_texts, new_key, per_worker, words_of


@dataclass(frozen=True)
class ToxicConfig:
    #: Bounds of the training sample: toxic texts and others.
    positives: int = 2000
    negatives: int = 6000
    max_chars: int = 8000
    log2_rows: int = 17
    dim: int = 8
    grams: tuple[int, ...] = (3, 4, 5)
    window: int = 24
    text_epochs: int = 6
    window_epochs: int = 14
    rate: float = 0.5
    #: Windows of each negative text that the second phase learns from.
    hard: int = 2
    batch: int = 64
    threshold: float = 0.3
    seed: int = 7


def subwords(word: str, cfg: ToxicConfig) -> list[int]:
    """Table rows of a word's n-grams and of the word itself."""
    raw = ("<" + word.lower() + ">").encode("utf-8", "replace")
    mask = (1 << cfg.log2_rows) - 1
    crc = zlib.crc32
    out = [crc(raw) & mask]
    for n in cfg.grams:
        out += [crc(raw[i : i + n]) & mask for i in range(len(raw) - n + 1)]
    return out


def window_means(values: np.ndarray, words: np.ndarray, size: int) -> np.ndarray:
    """Mean value of each window of ``size`` words; a word's repeats inside a window count in the length only."""
    n = len(values)
    if not n:
        return np.zeros(0)
    window = np.arange(n) // size
    _, first = np.unique(window * (int(words.max()) + 1) + words.astype(np.int64), return_index=True)
    return np.bincount(window[first], weights=values[first]) / np.bincount(window)


class Trainer:
    def __init__(self, texts: list[str], labels: list[int], cfg: ToxicConfig):
        self.cfg = cfg
        self.y = np.array(labels, np.int64)
        ids: dict[str, int] = {}
        self.docs = [np.fromiter((ids.setdefault(w, len(ids)) for w in words_of(t)), np.int32) for t in texts]
        flat, size = array("i"), array("i")
        for w in ids:
            bag = subwords(w, cfg)
            flat.extend(bag)
            size.append(len(bag))
        self.flat, self.size = np.array(flat, np.int32), np.array(size, np.int64)
        self.at = np.concatenate([[0], np.cumsum(self.size)])
        rng = np.random.default_rng(cfg.seed)
        self.rng = rng
        self.table = rng.uniform(-1, 1, (1 << cfg.log2_rows, cfg.dim)).astype(np.float32) / cfg.dim
        self.table_sq = np.full((1 << cfg.log2_rows, 1), 1e-8, np.float32)
        self.out = rng.normal(0, 0.1, (cfg.dim, 2)).astype(np.float32)
        self.bias = np.zeros(2, np.float32)
        self.out_sq, self.bias_sq = np.full_like(self.out, 1e-8), np.full_like(self.bias, 1e-8)

    def words(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Vectors of distinct words; the subword rows and their owners, for the gradient."""
        size = self.size[ids]
        owner = np.repeat(np.arange(len(ids)), size)
        start = np.concatenate([[0], np.cumsum(size)[:-1]])
        rows = self.flat[np.repeat(self.at[ids] - start, size) + np.arange(size.sum())]
        return np.add.reduceat(self.table[rows], start, 0) / size[:, None], rows, owner

    def step(self, bags: list[np.ndarray], y: np.ndarray) -> None:
        """One AdaGrad step on a batch of word bags."""
        n = np.array([len(b) for b in bags])  # repeats of a word count in the length only
        bags = [np.unique(b) for b in bags]
        cat = np.concatenate(bags)
        distinct = np.array([len(b) for b in bags])
        ids, inverse = np.unique(cat, return_inverse=True)
        vec, rows, owner = self.words(ids)
        start = np.concatenate([[0], np.cumsum(distinct)[:-1]])
        x = np.add.reduceat(vec[inverse], start, 0) / n[:, None]
        z = x @ self.out + self.bias
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        p[np.arange(len(y)), y] -= 1
        g = p / len(y)
        gx = g @ self.out.T / n[:, None]
        for w, sq, d in ((self.out, self.out_sq, x.T @ g), (self.bias, self.bias_sq, g.sum(0))):
            sq += d * d
            w -= self.cfg.rate * d / np.sqrt(sq)
        gw = np.zeros((len(ids), self.cfg.dim), np.float32)
        where = np.repeat(np.arange(len(bags)), distinct)
        for k in range(self.cfg.dim):
            gw[:, k] = np.bincount(inverse, weights=gx[where, k], minlength=len(ids))
        gw /= self.size[ids][:, None]
        used, back = np.unique(rows, return_inverse=True)
        gt = np.stack([np.bincount(back, weights=gw[owner, k], minlength=len(used)) for k in range(self.cfg.dim)], 1)
        self.table_sq[used] += (gt * gt).mean(1, keepdims=True)
        self.table[used] -= self.cfg.rate * gt / np.sqrt(self.table_sq[used])

    def values(self) -> np.ndarray:
        """Logit difference that each known word adds."""
        d = self.table @ (self.out[:, 1] - self.out[:, 0])
        return np.add.reduceat(d[self.flat], self.at[:-1]) / self.size

    def epoch(self, bags: list[tuple[np.ndarray, int]]) -> None:
        keep = [i for i in self.rng.permutation(len(bags)) if len(bags[i][0])]
        for a in range(0, len(keep), self.cfg.batch):
            part = [bags[i] for i in keep[a : a + self.cfg.batch]]
            self.step([b for b, _ in part], np.array([y for _, y in part]))

    def worst(self) -> list[tuple[np.ndarray, int]]:
        """The highest window of each positive text, the ``hard`` highest windows of each negative one."""
        v, w, out = self.values(), self.cfg.window, []
        for d, y in zip(self.docs, self.y, strict=True):
            means = window_means(v[d], d, w)
            for k in np.argsort(-means, kind="stable")[: 1 if y else self.cfg.hard]:
                out.append((d[k * w : (k + 1) * w], int(y)))
        return out

    def fit(self) -> tuple[np.ndarray, float]:
        for _ in range(self.cfg.text_epochs):
            self.epoch(list(zip(self.docs, self.y.tolist(), strict=True)))
        for _ in range(self.cfg.window_epochs):
            self.epoch(self.worst())
        return (self.table @ (self.out[:, 1] - self.out[:, 0])).astype(np.float32), float(self.bias[1] - self.bias[0])


def sample(docs: DataFrame, labels: DataFrame, cfg: ToxicConfig) -> tuple[list[str], list[int]]:
    """At most ``positives`` toxic and ``negatives`` other texts, never from the held-out fold."""
    lab = labels.select("doc_id", "toxic").filter(F.col("toxic").isin(0, 1) & ~held_out(F.col("doc_id"))).distinct()
    short = docs.select("doc_id").filter(F.length("text").between(1, cfg.max_chars))
    ranked = lab.join(short, "doc_id", "left_semi").select("doc_id", "toxic", F.xxhash64("doc_id").alias("h"))
    picked = [r for c, n in ((0, cfg.negatives), (1, cfg.positives)) for r in ranked.filter(F.col("toxic") == c).orderBy("h", "doc_id").limit(n).collect()]
    if not picked:
        return [], []
    ids = docs.sparkSession.createDataFrame([(r.doc_id, r.toxic) for r in picked], "doc_id long, toxic int")
    rows = docs.select("doc_id", "text").filter(F.length("text").between(1, cfg.max_chars)).join(F.broadcast(ids), "doc_id").collect()
    rows.sort(key=lambda r: (r.doc_id, r.toxic, r.text))
    return [r.text for r in rows], [r.toxic for r in rows]


class Scorer:
    def __init__(self, values: np.ndarray, bias: float, cfg: ToxicConfig, memo_size: int = 400_000):
        self.values, self.bias, self.cfg, self.memo, self.memo_size = values.tolist(), bias, cfg, {}, memo_size

    def word(self, w: str) -> float:
        v = self.memo.get(w)
        if v is None:
            s = subwords(w, self.cfg)
            values = self.values
            v = sum([values[k] for k in s]) / len(s)
            if len(w) <= 64:
                if len(self.memo) >= self.memo_size:
                    self.memo.clear()
                self.memo[w] = v
        return v

    def score(self, text: str | None) -> float:
        words = words_of(text)
        z = self.bias
        if words:
            ids: dict[str, int] = {}
            seq = np.fromiter([ids.setdefault(w, len(ids)) for w in words], np.int64, len(words))
            v = np.fromiter(map(self.word, ids), np.float64, len(ids))
            z += float(np.max(window_means(v[seq], seq, self.cfg.window)))
        return float(1 / (1 + np.exp(-np.clip(z, -50, 50))))


def fit(docs: DataFrame, labels: DataFrame, cfg: ToxicConfig = ToxicConfig()) -> tuple[np.ndarray, float]:
    texts, y = sample(docs, labels, cfg)
    if len(set(y)) < 2:
        return np.zeros(1 << cfg.log2_rows, np.float32), -50.0
    return Trainer(texts, y, cfg).fit()


def score(docs: DataFrame, model: tuple[np.ndarray, float], cfg: ToxicConfig = ToxicConfig(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted for each row; the model is a vector of fixed length."""
    shared, key = docs.sparkSession.sparkContext.broadcast(model), new_key()
    d = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), held_out(F.col(id_col)).alias("held_out"))

    def make():
        f = per_worker("toxicity", key, lambda: Scorer(*shared.value, cfg)).score

        def rows(ids, texts, held):
            out = []
            for i, t, h in zip(ids, texts, held, strict=True):
                s = f(t)
                out.append((i, h, s, int(s >= cfg.threshold)))
            return out

        return rows

    return map_texts(d, ["doc_id", "text", "held_out"], make, "doc_id long, held_out boolean, score double, predicted int")
