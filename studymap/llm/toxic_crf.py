"""Toxic spans by a linear-chain conditional random field over words.

Training. Only documents are labelled, so words get labels from a lexicon that the training documents themselves give: words and word beginnings that more toxic than clean documents
hold, by a likelihood-ratio test of presence and by the ratio of the two rates, neither of which tightens as the classes get even. How much evidence is asked for is chosen among `levels`:
a chain fitted to either half of the training documents judges the other half, and the level with the least loss is taken (the loosest of equal ones).
Words that are or begin with a lexicon unit are tagged 1 in a toxic document, all others 0. A two-state chain (clean, toxic) with hashed features (a word and its prefixes) and a full transition table is then fitted to those tags by
gradient ascent on the penalised conditional log-likelihood, whose gradient is observed minus expected counts from forward-backward marginals. The training documents are a bounded
sample of whole texts (`sample` documents of at most `longest` bytes each, half of each class, chosen by a hash of the identifier), written down; fits are tasks that read all of it.

Scoring covers every word of every text. Marginals come from forward and backward messages over all words of a block of documents at once: products of 2x2 matrices run in
parallel over strips, then strips are joined. A document's score is a logistic function of its summed marginals, its largest marginal and the summed marginals'
share of its words (one chance hit in a long text is no evidence), fitted on the training documents as the other half's chain sees them; offending spans are maximal runs of words whose marginal is at least `span_least`, given as byte offsets into the UTF-8 text.

Null and empty texts, and texts without words, get the score of no evidence and no spans. Rows with a null label don't train; of training rows that repeat an identifier the least text trains; a null identifier is scored like
any other. Without both classes among the training rows every score is the share of toxic rows (0 if there are none). Repeated rows are scored each; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import bounded_sample, checkpointed

BITS = 18
#: Lengths, in characters, of the prefixes that stand beside the word itself as features and as lexicon units.
PREFIXES = (3, 4, 5, 6, 7)
WIDTH = 1 + len(PREFIXES)
#: Features of a document's score.
HEAD = 4
#: Levels of evidence for lexicon units, loosest first: least likelihood-ratio statistic of presence, least log ratio of the rates.
LEVELS = ((15.0, 2.0), (15.0, 3.0), (24.0, 3.0), (40.0, 3.0))


def units(word: bytes) -> list[bytes]:
    """The word without punctuation around it, and its proper prefixes."""
    bare = word.strip(b".,;:!?\"'()[]{}*&%$#|<>-_/") or word
    text = bare.decode("utf-8", "replace")
    return [bare, *(b"^" + text[:k].encode() for k in PREFIXES if len(text) > k)]


def cells_of(word: bytes) -> list[int]:
    """Feature cells of a word, padded with the last cell, whose weight stays 0."""
    out = [xxhash.xxh64_intdigest(u) % ((1 << BITS) - 1) for u in units(word)]
    return out + [(1 << BITS) - 1] * (WIDTH - len(out))


class Odds(dict):
    """Emission log odds of words, kept for up to `room` distinct words."""

    def __init__(self, weights: np.ndarray, bias: float, room: int = 400_000):
        self.weights, self.bias, self.room = weights, bias, room

    def __missing__(self, word: bytes) -> float:
        if len(self) >= self.room:
            self.clear()
        found = self[word] = self.bias + float(self.weights[cells_of(word)].sum())
        return found


def marginals(odds: np.ndarray, starts: np.ndarray, pair: np.ndarray, strip: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """P(toxic) of each word, and the expected pairs (word, 2, 2) as sums over all words.

    `odds`: emission log odds of the toxic state; `starts`: first words; `pair`: log potentials of transitions (2, 2).
    A first word forgets what stands before it, so documents follow each other in one array.
    """
    n = len(odds)
    if n == 0:
        return np.empty(0), np.zeros((2, 2))
    t = np.exp(pair)
    m = -(-n // strip) * strip
    e = np.ones(m)
    e[:n] = np.exp(np.clip(odds, -30, 30))
    s = np.ones(m, bool)
    s[:n] = starts
    e, s = e.reshape(-1, strip), s.reshape(-1, strip)
    rows = len(e)

    def matrix(j):
        """Entries a, b, c, d of the step into column j."""
        x, first = e[:, j], s[:, j]
        return np.where(first, 1.0, t[0, 0]), np.where(first, x, t[0, 1] * x), np.where(first, 1.0, t[1, 0]), np.where(first, x, t[1, 1] * x)

    # Product of each strip's matrices, scaled.
    p = [np.ones(rows), np.zeros(rows), np.zeros(rows), np.ones(rows)]
    for j in range(strip):
        a, b, c, d = matrix(j)
        p = [p[0] * a + p[1] * c, p[0] * b + p[1] * d, p[2] * a + p[3] * c, p[2] * b + p[3] * d]
        z = p[0] + p[1] + p[2] + p[3]
        p = [x / z for x in p]
    # Messages at the borders of strips.
    into, out = np.empty((rows, 2)), np.empty((rows, 2))
    u, v = 0.5, 0.5
    p0, p1, p2, p3 = (x.tolist() for x in p)
    for i in range(rows):
        into[i] = u, v
        u, v = u * p0[i] + v * p2[i], u * p1[i] + v * p3[i]
        z = u + v
        u, v = u / z, v / z
    u, v = 0.5, 0.5
    for i in range(rows - 1, -1, -1):
        out[i] = u, v
        u, v = p0[i] * u + p1[i] * v, p2[i] * u + p3[i] * v
        z = u + v
        u, v = u / z, v / z
    # Messages inside strips.
    f0, f1 = np.empty((strip, rows)), np.empty((strip, rows))
    u, v = into[:, 0], into[:, 1]
    for j in range(strip):
        a, b, c, d = matrix(j)
        u, v = u * a + v * c, u * b + v * d
        z = u + v
        u, v = u / z, v / z
        f0[j], f1[j] = u, v
    prob = np.empty((strip, rows))
    expected = np.zeros((2, 2))
    u, v = out[:, 0], out[:, 1]
    for j in range(strip - 1, -1, -1):
        z = f0[j] * u + f1[j] * v
        prob[j] = f1[j] * v / z
        a, b, c, d = matrix(j)
        inner = ~s[:, j]
        if inner.any():
            w0, w1 = (f0[j - 1], f1[j - 1]) if j else (into[:, 0], into[:, 1])
            q = np.stack([w0 * a * u, w0 * b * v, w1 * c * u, w1 * d * v])[:, inner]
            expected += (q / q.sum(0)).sum(1).reshape(2, 2)
        u, v = a * u + b * v, c * u + d * v
        z = u + v
        u, v = u / z, v / z
    return prob.T.reshape(-1)[:n], expected


class ToxicModel:
    def __init__(self, weights, pair, bias, head, constant=None):
        self.weights, self.pair, self.bias, self.head, self.constant = weights, pair, bias, head, constant

    def odds(self) -> Odds:
        return Odds(self.weights, self.bias)

    def tag(self, docs: list[list[bytes]], odds: Odds) -> tuple[np.ndarray, np.ndarray]:
        """Marginals of all words in a row, and the documents' word counts."""
        sizes = np.fromiter(map(len, docs), np.int64, len(docs))
        n = int(sizes.sum())
        odds = np.fromiter((odds[w] for d in docs for w in d), np.float64, n)
        starts = np.zeros(n, bool)
        starts[(np.cumsum(sizes) - sizes)[sizes > 0]] = True
        return marginals(odds, starts, self.pair)[0], sizes

    def score(self, prob: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(sizes), self.constant)
        return 1 / (1 + np.exp(-(document_features(prob, sizes) @ self.head)))


def document_features(prob: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Rows (1, log of summed marginals, largest marginal, log of the sum per 200 words)."""
    x = np.zeros((len(sizes), HEAD))
    x[:, 0] = 1
    some = np.flatnonzero(sizes)
    if len(some):
        at = (np.cumsum(sizes) - sizes)[some]
        total = np.add.reduceat(np.where(prob > 0.05, prob, 0), at)
        x[some, 1] = np.log1p(total)
        x[some, 2] = np.maximum.reduceat(prob, at)
        x[some, 3] = np.log1p(200 * total / (sizes[some] + 20))
    return x


class Sample:
    """Training documents as arrays: words, units of words, and the units each document holds."""

    def __init__(self, docs: list[list[bytes]]):
        number, unit_no, of_word = {}, {}, []
        for d in docs:
            for w in d:
                if w not in number:
                    number[w] = len(number)
                    of_word.append([unit_no.setdefault(u, len(unit_no)) for u in units(w)])
        self.table = np.array([cells_of(w) for w in number], np.int64).reshape(-1, WIDTH)
        # The chain is fitted over the cells that occur; the last one is the padding.
        self.cells, self.local = np.unique(np.append(self.table, (1 << BITS) - 1), return_inverse=True)
        self.local = self.local[:-1].reshape(-1, WIDTH)
        self.sizes = np.fromiter(map(len, docs), np.int64, len(docs))
        self.word = np.fromiter((number[w] for d in docs for w in d), np.int64, int(self.sizes.sum()))
        self.n_units = len(unit_no)
        # Units of a word, padded with a unit that no document holds.
        self.units = np.full((len(number), WIDTH), self.n_units, np.int64)
        for i, us in enumerate(of_word):
            self.units[i, : len(us)] = us
        held, ends = [], np.cumsum(self.sizes)
        for n, to in zip(self.sizes, ends):
            us = np.unique(self.units[np.unique(self.word[to - n : to])])
            held.append(us[us < self.n_units])
        self.held_size = np.fromiter(map(len, held), np.int64, len(docs))
        self.held = np.concatenate([*held, np.empty(0, np.int64)])

    def words(self, chosen: np.ndarray) -> np.ndarray:
        """Word numbers of the chosen documents in a row."""
        return self.word[np.repeat(chosen, self.sizes)]


def first_words(sizes: np.ndarray) -> np.ndarray:
    starts = np.zeros(int(sizes.sum()), bool)
    starts[(np.cumsum(sizes) - sizes)[sizes > 0]] = True
    return starts


def evidence(sample: Sample, toxic: np.ndarray, chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each unit: the likelihood-ratio statistic of its presence in toxic against clean documents (0 where clean ones hold it as often), and the smoothed log ratio of the two rates."""
    of_doc = np.repeat(chosen & toxic, sample.held_size), np.repeat(chosen & ~toxic, sample.held_size)
    k, c = (np.bincount(sample.held[m], minlength=sample.n_units).astype(float) for m in of_doc)
    n1, n0 = float((chosen & toxic).sum()), float((chosen & ~toxic).sum())
    p = np.maximum(k + c, 0.5) / (n1 + n0)

    def part(seen, expected):
        return np.where(seen > 0, seen * np.log(np.maximum(seen, 1e-9) / np.maximum(expected, 1e-12)), 0)

    g = 2 * (part(k, n1 * p) + part(c, n0 * p) + part(n1 - k, n1 * (1 - p)) + part(n0 - c, n0 * (1 - p)))
    # Both rates are smoothed by the same pseudo-document of the pooled rate, whatever the balance of the classes.
    ratio = np.log((k + p) / (n1 + 1)) - np.log((c + p) / (n0 + 1))
    return np.where(k * n0 > c * n1, g, 0), np.where(k + c > 0, ratio, 0)


def fit_chain(sample: Sample, toxic: np.ndarray, chosen: np.ndarray, level: tuple[float, float], rounds: int, penalty: float, rate: float) -> ToxicModel:
    """The chain without a document score, fitted to the chosen documents' tags at one level of evidence."""
    g, ratio = evidence(sample, toxic, chosen)
    lexicon = np.append((g >= level[0]) & (ratio >= level[1]), False)
    word, sizes, table = sample.words(chosen), sample.sizes[chosen], sample.local
    room = len(sample.cells)
    tags = lexicon[sample.units].any(1)[word] & np.repeat(toxic[chosen], sizes)
    starts = first_words(sizes)
    weights, pair, bias = np.zeros(room), np.zeros((2, 2)), -3.0
    seen_w, seen_p, seen_b = np.full(room, 1e-8), np.full((2, 2), 1e-8), 1e-8
    gold_pairs = np.zeros((2, 2))
    inner = np.flatnonzero(~starts)
    np.add.at(gold_pairs, (tags[inner - 1].astype(int), tags[inner].astype(int)), 1)
    total = max(1, tags.sum())
    for _ in range(rounds):
        prob, expected = marginals(bias + weights[table].sum(1)[word], starts, pair)
        gap = (tags - prob) / total
        of_word = np.bincount(word, gap, len(table))
        g = sum(np.bincount(table[:, k], of_word, room) for k in range(WIDTH)) - penalty * weights
        g[-1] = 0
        gp = (gold_pairs - expected) / total - penalty * pair
        gb = gap.sum()
        seen_w += g * g
        seen_p += gp * gp
        seen_b += gb * gb
        weights += rate * g / np.sqrt(seen_w)
        pair += 0.3 * rate * gp / np.sqrt(seen_p)
        bias += 0.3 * rate * gb / np.sqrt(seen_b)
    spread = np.zeros(1 << BITS)
    spread[sample.cells] = weights
    return ToxicModel(spread, pair, bias, None)


def features_of(model: ToxicModel, sample: Sample, chosen: np.ndarray) -> np.ndarray:
    sizes = sample.sizes[chosen]
    return document_features(marginals(model.bias + model.weights[sample.table].sum(1)[sample.words(chosen)], first_words(sizes), model.pair)[0], sizes)


def fit_score(x: np.ndarray, toxic: np.ndarray) -> tuple[np.ndarray, float]:
    """Coefficients of the document score, both classes weighing the same, and the loss reached."""
    share, head = np.where(toxic, 0.5 / toxic.sum(), 0.5 / (~toxic).sum()), np.zeros(HEAD)
    for _ in range(50):  # Newton steps
        p = 1 / (1 + np.exp(-np.clip(x @ head, -30, 30)))
        grad = x.T @ (share * (toxic - p)) - 1e-3 * head
        head = head + np.linalg.solve(x.T @ (x * (share * p * (1 - p))[:, None]) + 1e-3 * np.eye(HEAD), grad)
    z = np.clip(x @ head, -30, 30)
    return head, float((share * np.log1p(np.exp(np.where(toxic, -z, z)))).sum())


def halves(toxic: np.ndarray) -> np.ndarray:
    """One half of each class in turn, so that both halves hold both classes where there are two of each."""
    half = np.zeros(len(toxic), bool)
    for y in (True, False):
        half[np.flatnonzero(toxic == y)[::2]] = True
    return half


def held_features(sample: Sample, toxic: np.ndarray, level, part: bool, how) -> tuple[np.ndarray, np.ndarray]:
    """Places and document features of one half, as a chain sees them that was fitted to the other."""
    held = halves(toxic) == part
    return np.flatnonzero(held), features_of(fit_chain(sample, toxic, ~held, level, *how), sample, held)


def chosen_level(by_level: list[np.ndarray], toxic: np.ndarray) -> tuple[int, np.ndarray]:
    """The level whose document score has the least loss (the loosest of equal ones), with that score's coefficients."""
    scores = [fit_score(x, toxic) for x in by_level]
    best = min(range(len(scores)), key=lambda i: (scores[i][1], i))
    return best, scores[best][0]


def _constant(toxic: np.ndarray) -> ToxicModel:
    return ToxicModel(np.zeros(1 << BITS), np.zeros((2, 2)), 0.0, None, float(toxic.mean()) if len(toxic) else 0.0)


HOW = (40, 1e-4, 0.5)  # rounds, penalty, rate


def fit(docs: list[list[bytes]], toxic: np.ndarray, levels=LEVELS, how=HOW) -> ToxicModel:
    """The whole fit in this process; `train` does the same on the executors."""
    toxic = np.asarray(toxic, bool)
    if not len(toxic) or toxic.all() or not toxic.any():
        return _constant(toxic)
    sample, by_level = Sample(docs), []
    for level in levels:
        x = np.zeros((len(toxic), HEAD))
        for part in (True, False):
            at, features = held_features(sample, toxic, level, part, how)
            x[at] = features
        by_level.append(x)
    best, head = chosen_level(by_level, toxic)
    model = fit_chain(sample, toxic, np.ones(len(toxic), bool), levels[best], *how)
    model.head = head
    return model


def _ordered(pdf: pd.DataFrame) -> tuple[Sample, np.ndarray]:
    """A sample in a fixed order, whatever the order of its rows."""
    got = sorted(zip(pdf["_h"], pdf["_text"], pdf["_y"]), key=lambda r: (r[0], r[1] or ""))
    return Sample([(t or "").encode("utf-8", "replace").lower().split() for _, t, _ in got]), np.array([y == 1 for _, _, y in got])


def train(docs: DataFrame, labels: DataFrame, label: str = "toxic", sample: int = 2400, longest: int = 40_000, trains=None, id_col: str = "doc_id", text_col: str = "text", levels=LEVELS, how=HOW) -> ToxicModel:
    """Fits run as tasks, one for each level and half at once, over the written sample of at most `sample` rows; features of documents and one chain come back."""
    rows = checkpointed(bounded_sample(docs, labels, label, sample, F.lit(True) if trains is None else trains, longest, id_col, text_col))
    toxic = np.array([r["_y"] == 1 for r in rows.select("_y").collect()], bool)
    if not len(toxic) or toxic.all() or not toxic.any():
        return _constant(toxic)

    def candidate(key, pdf):
        docs_, y = _ordered(pdf)
        at, x = held_features(docs_, y, levels[key[0]], bool(key[1]), how)
        return pd.DataFrame({"level": key[0], "at": at, "x": list(x), "y": y[at]})

    cells = F.explode(F.array(*(F.struct(F.lit(i).alias("level"), F.lit(p).alias("part")) for i in range(len(levels)) for p in (0, 1))))
    each = rows.withColumn("_cell", cells).select("_text", "_y", "_h", "_cell.level", "_cell.part")
    by_level, y = [np.zeros((len(toxic), HEAD)) for _ in levels], np.zeros(len(toxic), bool)
    for r in each.groupBy("level", "part").applyInPandas(candidate, "level int, at int, x array<double>, y boolean").collect():  # `sample` rows for each level
        by_level[r["level"]][r["at"]] = r["x"]
        y[r["at"]] = r["y"]
    best, head = chosen_level(by_level, y)

    def whole(pdf):
        docs_, y_ = _ordered(pdf)
        m = fit_chain(docs_, y_, np.ones(len(y_), bool), levels[best], *how)
        cell = np.flatnonzero(m.weights)
        return pd.DataFrame({"cell": [cell], "weight": [m.weights[cell]], "pair": [m.pair.reshape(-1)], "bias": [m.bias]})

    r = rows.withColumn("_one", F.lit(0)).groupBy("_one").applyInPandas(whole, "cell array<int>, weight array<double>, pair array<double>, bias double").first()
    weights = np.zeros(1 << BITS)
    weights[r["cell"]] = r["weight"]
    return ToxicModel(weights, np.array(r["pair"]).reshape(2, 2), r["bias"], head)


def score(docs: DataFrame, model: ToxicModel, spans: bool = False, span_least: float = 0.5, id_col: str = "doc_id", text_col: str = "text", block_words: int = 400_000) -> DataFrame:
    """One row per input row: id, score and, if asked for, spans (array of begin and end byte offsets)."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # 2^18 weights, whatever the input

    def run(batches):
        m = sent.value
        cache = m.odds()

        def done(keys, raw):
            words = [r.lower().split() for r in raw]
            prob, sizes = m.tag(words, cache)
            out = pd.DataFrame({id_col: keys, "score": m.score(prob, sizes)})
            if spans:
                ends = np.cumsum(sizes)
                out["spans"] = [toxic_spans(r, w, prob[b - len(w) : b], span_least) for r, w, b in zip(raw, words, ends)]
            return out

        for b in batches:
            keys, raw, n = [], [], 0
            for k, t in zip(b[id_col], b[text_col]):
                keys.append(k)
                raw.append((t or "").encode("utf-8", "replace"))
                n += len(raw[-1]) // 5 + 1
                if n > block_words:
                    yield done(pd.Series(keys, dtype=b[id_col].dtype), raw)
                    keys, raw, n = [], [], 0
            if keys:
                yield done(pd.Series(keys, dtype=b[id_col].dtype), raw)

    kind = dict(docs.dtypes)[id_col]
    return docs.select(id_col, text_col).mapInPandas(run, f"`{id_col}` {kind}, score double" + ", spans array<struct<begin:int,end:int>>" * spans)


def toxic_spans(raw: bytes, words: list[bytes], prob: np.ndarray, least: float) -> list[dict]:
    """Maximal runs of words whose marginal reaches `least`."""
    out, at, low = [], 0, raw.lower()
    open_ = False
    for w, p in zip(words, prob):
        begin = low.index(w, at)
        at = begin + len(w)
        if p >= least:
            if open_:
                out[-1]["end"] = at
            else:
                out.append({"begin": begin, "end": at})
        open_ = p >= least
    return out


def without_toxic(docs: DataFrame, labels: DataFrame, least: float = 0.7, id_col: str = "doc_id", text_col: str = "text", trains=None) -> DataFrame:
    """The rows whose score stays below `least`, with exactly the input's columns."""
    names = docs.columns
    model = docs.sparkSession.sparkContext.broadcast(train(docs, labels, trains=trains, id_col=id_col, text_col=text_col))
    text_at = names.index(text_col)

    def run(batches):
        import pyarrow as pa

        m = model.value
        cache = m.odds()
        for b in batches:
            raw = [(t or "").encode("utf-8", "replace") for t in b.column(text_at).to_pylist()]
            keep, at = [], 0
            while at < len(raw):
                to, n = at, 0
                while to < len(raw) and (to == at or n < 2_000_000):
                    n += len(raw[to])
                    to += 1
                prob, sizes = m.tag([r.lower().split() for r in raw[at:to]], cache)
                keep.append(m.score(prob, sizes) < least)
                at = to
            yield b.filter(pa.array(np.concatenate(keep) if keep else np.empty(0, bool)))

    return docs.toDF(*(f"_c{i}" for i in range(len(names)))).mapInArrow(run, docs.toDF(*(f"_c{i}" for i in range(len(names)))).schema).toDF(*names)
