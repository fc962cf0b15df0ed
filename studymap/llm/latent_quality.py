"""Quality by votes of the nearest labelled documents in a latent-semantic space.

A document is a bag of hashed terms over its whole text: words, shapes of words (letters by case, digits, other characters, runs collapsed), endings of punctuation,
shares of repeated words. Counts are damped by log(1 + n), weighted by inverse document frequency and scaled to length 1. A truncated singular value
decomposition of the labelled sample's matrix gives the latent space; labelled documents and every document are projected into it and scaled to length 1.

The labelled vectors are a bounded sample (`sample` rows of at most `longest` bytes, half of each class, by a hash of the identifier), so they and the projection are
broadcast. Every document is compared with all of them by exact blocked cosine products; the `k` nearest vote with their similarity (negative ones don't
vote), each class's votes divided by its share of the sample so that the even sample doesn't move the threshold.

Null and empty texts, and texts without words, have the zero vector: they get `prior`, the score of no evidence (0.5). Rows with a null label don't train.
Without labelled rows every score is 0.5; with one class the votes say that class. Repeated rows are scored each; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import bounded_sample

BITS = 13
#: Kinds of terms, so that a word and a shape never share a cell by spelling; the first half of the cells holds words, the rest what describes form.
HALF = 1 << (BITS - 1)
_RUNS = [(re.compile(p), r) for p, r in ((r"[^\W\d_]+", lambda m: "X" if m[0].isupper() and len(m[0]) > 1 else "Xx" if m[0][0].isupper() else "x"), (r"\d+", lambda m: "9"), (r"([^\w\s])\1+", lambda m: m[1] * 2))]


def _cell(term: str, form: bool) -> int:
    return xxhash.xxh64_intdigest(term.encode("utf-8", "replace")) % HALF + HALF * form


def shape(word: str) -> str:
    for pattern, by in _RUNS:
        word = pattern.sub(by, word)
    return word[:24]


class Terms(dict):
    """Cells of a word: itself in lower case, its shape, its last sign that is no letter."""

    def __missing__(self, word: str) -> tuple[int, int]:
        if len(self) >= 300_000:
            self.clear()
        found = self[word] = (_cell(word.lower(), False), _cell("s:" + shape(word), True))
        return found


def bag(text: str | None, terms: Terms, word_share: float = 0.25) -> tuple[np.ndarray, np.ndarray]:
    """(cells, damped counts) of a whole text, cells ascending."""
    words = re.findall("[^ \t-\r]+", text) if text else []
    if not words:
        return np.empty(0, np.int64), np.empty(0)
    pairs = np.fromiter((c for w in words for c in terms[w]), np.int64, 2 * len(words)).reshape(-1, 2)
    counts = Counter(words)
    n = len(words)
    repeated = 1 - len(counts) / n
    same = sum(map(str.__eq__, words, words[1:])) / n
    most = counts.most_common(1)[0][1] / n
    forms = [f"r:{int(10 * repeated)}", f"n:{int(10 * same)}", f"m:{int(10 * most)}"]
    cells, k = np.unique(pairs, return_counts=True)
    # Shares of form count more than single words, whatever the text's length.
    value = np.where(cells < HALF, word_share * np.log1p(k), 4 * np.sqrt(k / n))
    extra = {_cell(f, True): 1.0 for f in forms}
    every = np.concatenate([cells, np.fromiter(extra, np.int64)])
    value = np.concatenate([value, np.fromiter(extra.values(), float)])
    order = np.argsort(every, kind="stable")
    return every[order], value[order]


class LatentVotes:
    def __init__(self, projection, vectors, label, k, weight, constant=None):
        self.projection, self.vectors, self.label, self.k, self.weight, self.constant = projection, vectors, label, k, weight, constant

    def place(self, texts: list[str | None], terms: Terms) -> np.ndarray:
        return _placed([bag(t, terms) for t in texts], self.projection)

    def score(self, texts: list[str | None], terms: Terms) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(texts), self.constant)
        x = self.place(texts, terms)
        out = np.full(len(texts), 0.5)
        seen = np.flatnonzero(np.abs(x).sum(1) > 0)
        k = min(self.k, len(self.vectors))
        for at in range(0, len(seen), 512):
            rows = seen[at : at + 512]
            cosine = x[rows] @ self.vectors.T
            near = np.argpartition(-cosine, k - 1, axis=1)[:, :k]
            vote = np.maximum(np.take_along_axis(cosine, near, 1), 0) ** 8 * self.weight[near]
            total = vote.sum(1)
            out[rows] = np.where(total > 0, (vote * self.label[near]).sum(1) / np.where(total > 0, total, 1), 0.5)
        return np.clip(out, 0, 1)


def _placed(bags, projection) -> np.ndarray:
    out = np.zeros((len(bags), projection.shape[1]), np.float32)
    sizes = np.array([len(c) for c, _ in bags])
    some = np.flatnonzero(sizes)
    for at in range(0, len(some), 256):
        rows = some[at : at + 256]
        cells = np.concatenate([bags[i][0] for i in rows])
        values = np.concatenate([bags[i][1] for i in rows]).astype(np.float32)
        starts = np.cumsum(sizes[rows]) - sizes[rows]
        out[rows] = np.add.reduceat(projection[cells] * values[:, None], starts)
    length = np.linalg.norm(out, axis=1, keepdims=True)
    return np.where(length > 1e-9, out / np.where(length > 1e-9, length, 1), 0).astype(np.float32)


def fit(texts: list[str | None], labels: np.ndarray, base_rate: float, dimensions: int = 48, k: int = 31, seed: int = 5) -> LatentVotes:
    labels = np.asarray(labels, float)
    if not len(labels) or labels.min() == labels.max():
        return LatentVotes(None, None, labels, k, None, float(labels[0]) if len(labels) else 0.5)
    terms = Terms()
    bags = [bag(t, terms) for t in texts]
    n = len(bags)
    df = np.bincount(np.concatenate([c for c, _ in bags]), minlength=1 << BITS)
    idf = np.log((1 + n) / (1 + df)) + 0.3
    used = np.flatnonzero(df)
    at = np.full(1 << BITS, -1)
    at[used] = np.arange(len(used))
    matrix = np.zeros((n, len(used)), np.float32)
    for i, (c, v) in enumerate(bags):
        if len(c):
            row = v * idf[c]
            matrix[i, at[c]] = row / (np.linalg.norm(row) or 1)
    # Randomised range finder with power iterations.
    d = min(dimensions, n, len(used))
    basis = matrix @ np.random.default_rng(seed).normal(size=(len(used), d + 8)).astype(np.float32)
    for _ in range(3):
        basis = matrix @ (matrix.T @ np.linalg.qr(basis)[0])
    q = np.linalg.qr(basis)[0]
    right = np.linalg.svd(q.T @ matrix, full_matrices=False)[2][:d]
    projection = np.zeros((1 << BITS, d), np.float32)
    projection[used] = right.T * idf[used, None]
    vectors = _placed(bags, projection)
    share = labels.mean()
    # Votes as if the sample had the classes' shares among all labelled rows, moved halfway towards even.
    aim = (base_rate + 0.5) / 2
    return LatentVotes(projection, vectors, labels, k, np.where(labels == 1, aim / share, (1 - aim) / (1 - share)))


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = 3000, longest: int = 40_000, trains=None, id_col: str = "doc_id", text_col: str = "text") -> LatentVotes:
    trains = F.lit(True) if trains is None else trains
    rate = labels.where(trains).agg(F.avg(F.col(label).cast("double"))).first()[0]
    rows = bounded_sample(docs, labels, label, sample, trains, longest, id_col, text_col)
    got = sorted(rows.collect(), key=lambda r: (r["_h"], r["_text"] or ""))[:sample]
    return fit([r["_text"] for r in got], np.array([r["_y"] for r in got]), 0.5 if rate is None else rate)


def score(docs: DataFrame, model: LatentVotes, id_col: str = "doc_id", text_col: str = "text", block_chars: int = 2_000_000) -> DataFrame:
    """One row per input row: id and score."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # `sample` vectors and 2^13 rows of the projection, whatever the input

    def run(batches):
        m, terms = sent.value, Terms()
        for b in batches:
            texts, at = b[text_col].tolist(), 0
            while at < len(texts):
                to, n = at, 0
                while to < len(texts) and (to == at or n < block_chars):
                    n += len(texts[to] or "")
                    to += 1
                yield pd.DataFrame({id_col: b[id_col].iloc[at:to], "score": m.score(texts[at:to], terms)})
                at = to

    return docs.select(id_col, text_col).mapInPandas(run, f"`{id_col}` {dict(docs.dtypes)[id_col]}, score double")
