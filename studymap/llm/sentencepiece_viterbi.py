"""SentencePiece encoding by unigram Viterbi over a double-array trie, and decoding.

A vocabulary is read from a SentencePiece model file: pieces, log scores, kinds and the normaliser's switches. Blanks become the marker U+2581; a text is
cut where no piece can cross (before a run of markers that follows other text, and around line feeds, if the vocabulary allows it, which is
checked), so equal chunks are segmented once. The chunks of a batch that have not been met are segmented together: numpy walks the trie and relaxes the
best path for all of them at once, position by position. A character without a piece of its own costs the least score minus 10 and becomes its UTF-8
bytes where the vocabulary has byte pieces, else the unknown piece. Of equal paths the one found first (from the earliest start, then shortest) wins.

Decoding joins pieces, turns markers into blanks and byte pieces into bytes, and drops the blank that encoding put in front.

Null and empty texts have no tokens and decode to the empty text. Repeated rows are encoded each. Memory: a batch of documents, and at most `room` chunks.
An empty table gives an empty result.
"""

from __future__ import annotations

import re
import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .base import ragged

MARK = "▁"
DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
NORMAL, UNKNOWN, CONTROL, USER, BYTE = 1, 2, 3, 4, 6
UNKNOWN_PENALTY = 10.0


def _fields(data: bytes):
    """(number, value) of each field of a protobuf message."""
    at = 0

    def varint():
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out

    while at < len(data):
        tag = varint()
        kind = tag & 7
        if kind == 0:
            yield tag >> 3, varint()
        elif kind == 2:
            size = varint()
            yield tag >> 3, data[at : at + size]
            at += size
        else:
            size = 4 if kind == 5 else 8
            yield tag >> 3, data[at : at + size]
            at += size


class DoubleArray:
    """A trie over bytes in two arrays: the child of s by byte c is base[s] + c + 1 where check of that cell is s."""

    def __init__(self, keys: list[bytes], values: list[int]):
        tree: list[dict[int, int]] = [{}]
        ends: dict[int, int] = {}
        for key, value in zip(keys, values):
            s = 0
            for c in key:
                if c not in tree[s]:
                    tree[s][c] = len(tree)
                    tree.append({})
                s = tree[s][c]
            ends.setdefault(s, value)
        size = 2 * len(tree) + 1024
        base, check, value = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
        used = bytearray(size)
        used[0] = 1
        cell, low, dense, todo = {0: 0}, 257, 257, [0]
        while todo:
            node = todo.pop()
            s = cell[node]
            if node in ends:
                value[s] = ends[node]
            kids = tree[node]
            if not kids:
                continue
            codes = sorted(kids)
            while used[low]:
                low += 1
            first = low if len(codes) == 1 else max(low, dense)  # single children fill the holes
            b, tried = max(first - codes[0] - 1, 0), 0
            while any(used[b + c + 1] for c in codes):
                b, tried = b + 1, tried + 1
            if len(codes) > 1 and tried > 32:
                dense = b + codes[0] + 1
            base[s] = b
            for c in codes:
                t = b + c + 1
                used[t], check[t], cell[kids[c]] = 1, s, t
                todo.append(kids[c])
            if b + 1024 > size - 600:
                size *= 2
                base, check, value = (np.concatenate([x, np.full(size - len(x), f, np.int32)]) for x, f in ((base, 0), (check, -1), (value, -1)))
                used.extend(bytes(size - len(used)))
        self.base, self.check, self.value = base, check, value


class Vocabulary:
    def __init__(self, pieces: list[tuple[str, float, int]], dummy_prefix: bool = True, squeeze: bool = False):
        self.pieces = pieces
        self.dummy_prefix, self.squeeze = dummy_prefix, squeeze
        plain = [(p.encode(), i) for i, (p, _, kind) in enumerate(pieces) if kind in (NORMAL, USER) and p]
        self.trie = DoubleArray([p for p, _ in plain], [i for _, i in plain])
        self.score = np.array([s for _, s, _ in pieces], np.float64)
        self.unknown_score = min((s for _, s, k in pieces if k == NORMAL), default=0.0) - UNKNOWN_PENALTY
        self.unknown = next((i for i, (_, _, k) in enumerate(pieces) if k == UNKNOWN), 0)
        self.byte_id = np.full(256, -1, np.int32)
        for i, (p, _, k) in enumerate(pieces):
            if k == BYTE:
                self.byte_id[int(p[3:5], 16)] = i
        self.has_bytes = bool((self.byte_id >= 0).all())
        crossing = any(MARK in p.lstrip(MARK) or "\n" in p for p, _, k in pieces if k in (NORMAL, USER))
        self.chunk = r"(?s).+" if crossing else rf"{MARK}*[^{MARK}\n]+|{MARK}+|\n"
        self.surface = [bytes([int(p[3:5], 16)]) if k == BYTE else b"" if k == CONTROL else " ⁇ ".encode() if k == UNKNOWN else p.replace(MARK, " ").encode() for p, _, k in pieces]

    @classmethod
    def load(cls, path: str = DEFAULT_MODEL) -> Vocabulary:
        pieces, dummy, squeeze = [], True, True
        with open(path, "rb") as f:
            data = f.read()
        for number, value in _fields(data):
            if number == 1:
                x = dict(_fields(value))
                pieces.append((x[1].decode(), struct.unpack("<f", x[2])[0] if 2 in x else 0.0, x.get(3, NORMAL)))
            elif number == 3:
                x = dict(_fields(value))
                dummy, squeeze = bool(x.get(3, 1)), bool(x.get(4, 1))
                if x.get(2):
                    raise ValueError("models with a table of character rewriting are not supported")
        return cls(pieces, dummy, squeeze)

    def normalised(self, text: str | None) -> str:
        if self.squeeze and text:
            text = re.sub(" +", " ", text).strip(" ")
        return (MARK * self.dummy_prefix + text.replace(" ", MARK)) if text else ""

    def decode(self, ids) -> str:
        out = b"".join(map(self.surface.__getitem__, ids))
        return (out[1:] if self.dummy_prefix and out[:1] == b" " else out).decode("utf-8", "replace")


def segment(chunks: list[bytes], v: Vocabulary) -> tuple[np.ndarray, np.ndarray]:
    """Best path of each chunk (none is empty): all ids in a row, and how many each chunk has."""
    sizes = np.fromiter(map(len, chunks), np.int64, len(chunks))
    order = np.argsort(sizes, kind="stable")
    counts, parts = np.zeros(len(chunks), np.int64), []
    at = 0
    while at < len(order):
        widest = int(sizes[order[min(at + 8191, len(order) - 1)]])
        rows = order[at : at + max(1, min(8192, 4_000_000 // max(widest, 1)))]
        at += len(rows)
        ids, n = _segment_block([chunks[i] for i in rows], sizes[rows], v)
        counts[rows] = n
        parts.append(ids)
    flat = np.concatenate(parts) if parts else np.empty(0, np.int32)
    # From sorted order back to the order of the chunks.
    starts_sorted = np.zeros(len(chunks), np.int64)
    starts_sorted[1:] = np.cumsum(counts[order])[:-1]
    start = np.empty(len(chunks), np.int64)
    start[order] = starts_sorted
    return flat[ragged(start, counts)], counts


def _segment_block(chunks: list[bytes], sizes: np.ndarray, v: Vocabulary) -> tuple[np.ndarray, np.ndarray]:
    base, check, value = v.trie.base, v.trie.check, v.trie.value
    n, width = len(chunks), int(sizes.max())
    text = np.frombuffer(b"".join(c.ljust(width, b"\0") for c in chunks), np.uint8).reshape(n, width).astype(np.int32)
    best = np.full((n, width + 1), -np.inf)
    best[:, 0] = 0
    came, piece = np.zeros((n, width + 1), np.int32), np.full((n, width + 1), -1, np.int32)
    lead = text[:, :]
    step = np.where(lead < 0x80, 1, np.where(lead < 0xE0, 2, np.where(lead < 0xF0, 3, 4)))
    for i in range(width):
        rows = np.flatnonzero((sizes > i) & ((text[:, i] & 0xC0) != 0x80))
        if not len(rows):
            continue
        here, char = best[rows, i], step[rows, i]
        alone = np.zeros(n, bool)
        r, s, j = rows, np.zeros(len(rows), np.int32), i
        h = here
        while len(r) and j < width:
            t = base[s] + text[r, j] + 1
            ok = (check[t] == s) & (sizes[r] > j)
            r, s, h = r[ok], t[ok], h[ok]
            j += 1
            found = value[s]
            hit = found >= 0
            if hit.any():
                q, f = r[hit], found[hit]
                score = h[hit] + v.score[f]
                alone[q[step[q, i] == j - i]] = True
                better = score > best[q, j]
                q, f = q[better], f[better]
                best[q, j], came[q, j], piece[q, j] = score[better], i, f
        lost = ~alone[rows]
        if lost.any():
            q, e = rows[lost], np.minimum(i + char[lost], sizes[rows[lost]])
            score = here[lost] + v.unknown_score
            better = score > best[q, e]
            q, e = q[better], e[better]
            best[q, e], came[q, e], piece[q, e] = score[better], i, -1
    # Backwards along the best paths; an unknown character leaves its bytes.
    out, fill = np.zeros((n, width), np.int32), np.full(n, width, np.int64)
    rows, pos = np.arange(n), sizes.copy()
    while len(rows):
        p, start = piece[rows, pos], came[rows, pos]
        known = p >= 0
        q = rows[known]
        fill[q] -= 1
        out[q, fill[q]] = p[known]
        if not known.all():
            q, a, b = rows[~known], start[~known], pos[~known].copy()
            if v.has_bytes:
                while len(q):
                    b -= 1
                    fill[q] -= 1
                    out[q, fill[q]] = v.byte_id[text[q, b]]
                    more = b > a
                    q, a, b = q[more], a[more], b[more]
            else:
                fill[q] -= 1
                out[q, fill[q]] = v.unknown
        pos = start
        left = pos > 0
        rows, pos = rows[left], pos[left]
    counts = width - fill
    return out[np.arange(width)[None, :] >= fill[:, None]].astype(np.int32), counts


class Encoder:
    """Encodes lists of texts; remembers the segmentation of chunks it has met."""

    def __init__(self, v: Vocabulary, room: int = 300_000):
        self.v, self.room, self.find = v, room, re.compile(v.chunk).findall
        self._forget()

    def _forget(self):
        self.slot: dict[str, int] = {}
        self.flat, self.start, self.count = np.empty(0, np.int32), np.empty(0, np.int64), np.empty(0, np.int64)

    def __call__(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """All ids in a row, and how many each text has."""
        cut = [self.find(self.v.normalised(t)) for t in texts]
        flat = [c for x in cut for c in x]
        if len(self.slot) > self.room:
            self._forget()
        new = [c for c in dict.fromkeys(flat) if c not in self.slot]
        if new:
            ids, counts = segment([c.encode("utf-8", "replace") for c in new], self.v)
            self.slot.update(zip(new, range(len(self.slot), len(self.slot) + len(new))))
            self.start = np.concatenate([self.start, len(self.flat) + np.cumsum(counts) - counts])
            self.count = np.concatenate([self.count, counts])
            self.flat = np.concatenate([self.flat, ids])
        at = np.fromiter(map(self.slot.__getitem__, flat), np.int64, len(flat))
        counts = self.count[at]
        ends = np.concatenate([[0], np.cumsum(counts)])[np.cumsum([0, *map(len, cut)])]
        return self.flat[ragged(self.start[at], counts)], np.diff(ends)


def encode(docs: DataFrame, model: str = DEFAULT_MODEL, id_col: str = "doc_id", text_col: str = "text", block_chars: int = 1_000_000) -> DataFrame:
    """One row per input row: id, ids, n_tokens, n_byte_tokens, round_trip (decoding gives the normalised text back)."""
    v = docs.sparkSession.sparkContext.broadcast(Vocabulary.load(model))  # bounded by the vocabulary file

    def run(batches):
        vocab = v.value
        encoder = Encoder(vocab)
        is_byte = np.zeros(len(vocab.pieces) + 1, np.int64)
        is_byte[vocab.byte_id[vocab.byte_id >= 0]] = 1

        def done(keys, texts):
            ids, counts = encoder(texts)
            offsets = np.concatenate([[0], np.cumsum(counts)])
            every = ids.tolist()
            same = [vocab.decode(every[a:b]) == vocab.normalised(t).replace(MARK, " ")[vocab.dummy_prefix :] for a, b, t in zip(offsets, offsets[1:], texts)]
            bytes_ = np.concatenate([[0], np.cumsum(is_byte[ids])])
            return pa.RecordBatch.from_arrays(
                [keys, pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(ids, pa.int32())), pa.array(counts, pa.int64()), pa.array(np.diff(bytes_[offsets]), pa.int64()), pa.array(same, pa.bool_())],
                names=[id_col, "ids", "n_tokens", "n_byte_tokens", "round_trip"],
            )

        for batch in batches:
            keys, texts = batch.column(0), batch.column(1)
            size = np.cumsum(np.asarray(texts.cast(pa.large_string()).fill_null("").to_pandas().str.len(), np.int64)) if len(texts) else np.empty(0)
            at = 0
            while at < len(texts):
                to = max(at + 1, int(np.searchsorted(size, (size[at - 1] if at else 0) + block_chars, "right")))
                yield done(keys.slice(at, to - at), texts.slice(at, to - at).to_pylist())
                at = to

    kind = dict(docs.dtypes)[id_col]
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, ids array<int>, n_tokens long, n_byte_tokens long, round_trip boolean")


def decode(encoded: DataFrame, model: str = DEFAULT_MODEL, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """One row per input row: id and the decoded text; null ids give a null text."""
    v = encoded.sparkSession.sparkContext.broadcast(Vocabulary.load(model))

    def run(batches):
        for batch in batches:
            texts = [None if x is None else v.value.decode(x) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=[id_col, "text"])

    return encoded.select(id_col, ids_col).mapInArrow(run, f"`{id_col}` {dict(encoded.dtypes)[id_col]}, text string")
