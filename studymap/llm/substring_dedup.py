"""Substring duplicates by super-k-mer partitioning over words.

A window is `window` consecutive words of one document. Its minimiser is the least hash among its runs of `piece` words; consecutive windows with the same minimiser form
a super-k-mer, which travels as one packed string (its words, joined by blanks) to the minimiser's bucket. Equal windows have equal minimisers, so every
bucket can be judged alone.

1. One pass over all texts writes the minimisers of each document. A minimiser that occurs in one document only cannot hold a repeated window,
   so only super-k-mers of minimisers that two documents share travel on: a lossless cut.
2. Super-k-mers are packed; equal ones within a task are combined to the least document before the shuffle, so a group of copies sends one string per task.
3. Each bucket expands its distinct strings into windows and sorts them by two rolling hashes over two word hashes; the least document of each window is read off the sorted runs.
4. Every occurrence looks up its string's windows; those that also start in a smaller document are marked, and words that a marked window covers go.
5. A minimiser whose super-k-mers hold more than `heavy_words` words in all (a passage that a large share of all documents has, in ever other surroundings) gets no bucket: its windows
   are dealt one by one by their own two hashes, least documents are combined before the shuffle, and a window of very many documents is joined back by salt.

Windows are judged on the input, not on what is left. Null and empty texts have no words; texts shorter than a window lose nothing; a null identifier is
neither smaller nor larger than another, so such rows stay whole. Rows that repeat an identifier are judged each by its own text, and never against each other. An
empty table gives an empty result. Memory: a batch of texts, and the strings of one minimiser, at most `heavy_words` words.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import WordHashes, checkpointed, ragged, rolling, salt, salts_seen, spread, words_of

SKMER = "array<struct<v:bigint,s:int,c:int>>"


def sliding_least(x: np.ndarray, k: int) -> np.ndarray:
    """The least of each k neighbours, by doubling."""
    have = 1
    while have < k:
        step = min(have, k - have)
        x = np.minimum(x[: len(x) - step], x[step:])
        have += step
    return x


def super_kmers(hashes: np.ndarray, window: int, piece: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(minimiser, first window, number of windows) of the maximal runs of windows that share a minimiser."""
    if len(hashes) < window:
        return np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64)
    least = sliding_least(rolling(hashes, piece), window - piece + 1)
    starts = np.concatenate([[0], np.flatnonzero(least[1:] != least[:-1]) + 1])
    return least[starts], starts, np.diff(np.append(starts, len(least)))


def _minimisers(docs: DataFrame, window: int, piece: int) -> DataFrame:
    def run(batches):
        cache = WordHashes()
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                found = [super_kmers(cache.of(words_of(t.as_py())), window, piece) for t in part.column("_t")]
                n = np.array([len(f[0]) for f in found])
                keep = pa.array(n > 0)
                found = [f for f in found if len(f[0])]
                v, s, c = (np.concatenate([f[k] for f in found]) if found else np.empty(0, np.int64) for k in range(3))
                cells = pa.StructArray.from_arrays([pa.array(v.view(np.int64)), pa.array(s.astype(np.int32)), pa.array(c.astype(np.int32))], names=["v", "s", "c"])
                offsets = pa.array(np.concatenate([[0], np.cumsum(n[n > 0])]), pa.int32())
                yield pa.RecordBatch.from_arrays([part.column("_id").filter(keep), part.column("_th").filter(keep), pa.ListArray.from_arrays(offsets, cells)], names=["_id", "_th", "_k"])

    return docs.select("_id", "_th", "_t").mapInArrow(run, f"_id long, _th long, _k {SKMER}")


def _packed_of(words: list[bytes], cells, window: int):
    for x in cells:
        packed = b" ".join(words[x["s"] : x["s"] + x["c"] + window - 1])
        yield x, packed, xxhash.xxh128_digest(packed)


def _pack(hit: DataFrame, window: int, most_bytes: int = 8_000_000) -> DataFrame:
    """Packed super-k-mers with the least document that has them, combined within the task (flushed at `most_bytes`)."""

    def run(batches):
        held: dict[bytes, list] = {}
        size = 0

        def flush():
            digests = np.frombuffer(b"".join(held), np.int64).reshape(-1, 2)
            rows = list(held.values())
            return pa.RecordBatch.from_arrays(
                [pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary()), pa.array(digests[:, 0]), pa.array(digests[:, 1]), pa.array([r[2] for r in rows], pa.int64())],
                names=["_v", "_packed", "_p1", "_p2", "_min"],
            )

        for batch in batches:
            for key, text, cells in zip(batch.column("_id").to_pylist(), batch.column("_t"), batch.column("_k")):
                for x, packed, digest in _packed_of(words_of(text.as_py()), cells.as_py(), window):
                    row = held.get(digest)
                    if row is None:
                        held[digest] = [x["v"], packed, key]
                        size += len(packed) + 120
                    elif key < row[2]:
                        row[2] = key
                if size > most_bytes:
                    yield flush()
                    held, size = {}, 0
        if held:
            yield flush()

    return hit.select("_id", "_t", "_k").mapInArrow(run, "_v long, _packed binary, _p1 long, _p2 long, _min long")


def _places(hit: DataFrame, window: int) -> DataFrame:
    """Where each packed super-k-mer occurs: the same strings, by digest only."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                ids, hashes, starts, digests = [], [], [], []
                for key, th, text, cells in zip(part.column("_id").to_pylist(), part.column("_th").to_pylist(), part.column("_t"), part.column("_k")):
                    for x, _, digest in _packed_of(words_of(text.as_py()), cells.as_py(), window):
                        ids.append(key)
                        hashes.append(th)
                        starts.append(x["s"])
                        digests.append(digest)
                d = np.frombuffer(b"".join(digests), np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(hashes, pa.int64()), pa.array(starts, pa.int32()), pa.array(d[:, 0]), pa.array(d[:, 1])], names=["_id", "_th", "_s", "_p1", "_p2"])

    return hit.select("_id", "_th", "_t", "_k").mapInArrow(run, "_id long, _th long, _s int, _p1 long, _p2 long")


def _judge(packed: list[bytes], least: np.ndarray, window: int, caches: tuple[WordHashes, WordHashes]) -> list[np.ndarray]:
    """For each packed string, the least document of each of its windows among all strings given."""
    parts = [p.split() for p in packed]
    sizes = np.fromiter(map(len, parts), np.int64, len(parts))
    counts = sizes - window + 1
    flat = [w for p in parts for w in p]
    inside = ragged(np.cumsum(sizes) - sizes, counts)  # first words of windows that end in their own string
    first, second = (rolling(c.of(flat), window, seed=k)[inside] for k, c in enumerate(caches))
    mine = np.repeat(least, counts)
    order = np.lexsort((second, first))
    a, b = first[order], second[order]
    new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
    lows = np.minimum.reduceat(mine[order], np.flatnonzero(new))
    out = np.empty(len(mine), np.int64)
    out[order] = lows[np.cumsum(new) - 1]
    return np.split(out, np.cumsum(counts)[:-1])


def _buckets(packed: DataFrame, window: int, least_bytes: int = 2_000_000) -> DataFrame:
    """Rows sorted by minimiser and string within their partition -> (_p1, _p2, _mins) of every distinct string."""

    def run(batches):
        caches = WordHashes(), WordHashes(seed=1)

        def done(rows):
            mins = _judge([r[1] for r in rows], np.array([r[4] for r in rows], np.int64), window, caches)
            offsets = np.concatenate([[0], np.cumsum([len(m) for m in mins])])
            keys = np.array([r[2:4] for r in rows], np.int64)
            return pa.RecordBatch.from_arrays([pa.array(keys[:, 0]), pa.array(keys[:, 1]), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(np.concatenate(mins)))], names=["_p1", "_p2", "_mins"])

        rows, size = [], 0
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if rows and row[2] == rows[-1][2] and row[3] == rows[-1][3]:
                    rows[-1][4] = min(rows[-1][4], row[4])  # the same string from another task
                    continue
                if size > least_bytes and row[0] != rows[-1][0]:
                    yield done(rows)
                    rows, size = [], 0
                rows.append(list(row))
                size += len(row[1])
        if rows:
            yield done(rows)

    return packed.mapInArrow(run, "_p1 long, _p2 long, _mins array<long>")


def _windows(hit: DataFrame, window: int) -> DataFrame:
    """(_id, _th, _at, _w1, _w2): every window of the super-k-mers given, by its first word and its two hashes."""

    def run(batches):
        caches = WordHashes(), WordHashes(seed=1)
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part = batch.slice(at, 200)
                ids, hashes, places, firsts, seconds = [], [], [], [], []
                for key, th, text, cells in zip(part.column("_id").to_pylist(), part.column("_th").to_pylist(), part.column("_t"), part.column("_k")):
                    words = words_of(text.as_py())
                    runs = cells.as_py()
                    here = ragged(np.array([x["s"] for x in runs]), np.array([x["c"] for x in runs]))
                    a, b = (rolling(c.of(words), window, seed=k)[here] for k, c in enumerate(caches))
                    ids.append(np.full(len(here), key))
                    hashes.append(np.full(len(here), th))
                    places.append(here.astype(np.int32))
                    firsts.append(a.view(np.int64))
                    seconds.append(b.view(np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (ids, hashes, places, firsts, seconds)], names=["_id", "_th", "_at", "_w1", "_w2"])

    return hit.select("_id", "_th", "_t", "_k").mapInArrow(run, "_id long, _th long, _at int, _w1 long, _w2 long")


def _marked(docs: DataFrame, window: int, piece: int, heavy_words: int) -> DataFrame:
    """(_id, _th, _w): the first words of the windows of each document that also start in a smaller one."""
    kmers = checkpointed(_minimisers(docs, window, piece)).select("_id", "_th", F.explode("_k").alias("_k"), salt("_id").alias("_salt")).select("_id", "_th", "_k", F.col("_k.v").alias("_v"), "_salt")
    shared = kmers.groupBy("_v").agg(F.min("_id").alias("_lo"), F.max("_id").alias("_hi"), F.sum(F.col("_k.c") + window - 1).alias("_words"), salts_seen()).where("_lo < _hi")
    shared = spread(shared.select("_v", (F.col("_words") > heavy_words).alias("h"), "_salts"))
    hits = kmers.join(shared, ["_v", "_salt"]).groupBy("_id", "_th").agg(F.collect_set(F.struct("_k.v", "_k.s", "_k.c", "h")).alias("_k"))
    hit = docs.join(hits.hint("shuffle_hash"), ["_id", "_th"])
    light = hit.withColumn("_k", F.filter("_k", lambda k: ~k["h"])).where("size(_k) > 0")
    heavy = hit.withColumn("_k", F.filter("_k", lambda k: k["h"])).where("size(_k) > 0")

    packed = _pack(light, window).repartition("_v").sortWithinPartitions("_v", "_p1", "_p2")
    found = _places(light, window).join(_buckets(packed, window), ["_p1", "_p2"])
    low = F.filter(F.sequence(F.lit(0), F.size("_mins") - 1), lambda i: F.get("_mins", i) < F.col("_id"))
    found = found.select("_id", "_th", F.transform(low, lambda i: i + F.col("_s")).alias("_w")).where("size(_w) > 0")

    each = _windows(heavy, window).withColumn("_salt", salt("_id"))
    least = each.groupBy("_w1", "_w2").agg(F.min("_id").alias("_lo"), F.max("_id").alias("_hi"), salts_seen()).where("_lo < _hi").drop("_hi")
    late = each.join(spread(least), ["_w1", "_w2", "_salt"]).where("_lo < _id").groupBy("_id", "_th").agg(F.collect_set("_at").alias("_w"))
    return found.unionByName(late).groupBy("_id", "_th").agg(F.flatten(F.collect_list("_w")).alias("_w"))


def kept_words(words: list[bytes], marked, window: int) -> list[bytes]:
    if not len(marked):
        return words
    cover = np.zeros(len(words) + 1, np.int64)
    starts = np.unique(np.asarray(marked, np.int64))
    cover[starts] += 1
    np.add.at(cover, starts + window, -1)
    return [words[i] for i in np.flatnonzero(np.cumsum(cover[:-1]) == 0)]


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = 50, piece: int = 8, texts: bool = False, heavy_words: int = 100_000) -> DataFrame:
    """One row per input row: id, n_words, n_removed, kept_sha256 and, if asked for, kept_text (the kept words joined by one blank)."""
    plain = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_t")).withColumn("_th", F.xxhash64("_t"))
    marked = _marked(plain.where("_id is not null"), window, piece, heavy_words)
    joined = plain.where("_id is not null").join(marked.hint("shuffle_hash"), ["_id", "_th"], "left")
    joined = joined.select("_id", "_t", "_w").unionByName(plain.where("_id is null").select("_id", "_t", F.lit(None).cast("array<int>").alias("_w")))

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                n, gone, digest, kept = [], [], [], []
                for t, w in zip(part.column("_t"), part.column("_w")):
                    words = words_of(t.as_py())
                    left = kept_words(words, w.values.to_numpy() if w.is_valid else (), window)
                    text = b" ".join(left)
                    n.append(len(words))
                    gone.append(len(words) - len(left))
                    digest.append(hashlib.sha256(text).hexdigest())
                    if texts:
                        kept.append(text.decode("utf-8", "replace"))
                columns = [part.column("_id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(digest, pa.string())] + [pa.array(kept, pa.string())] * texts
                yield pa.RecordBatch.from_arrays(columns, names=[id_col, "n_words", "n_removed", "kept_sha256"] + ["kept_text"] * texts)

    return joined.mapInArrow(run, f"`{id_col}` long, n_words long, n_removed long, kept_sha256 string" + ", kept_text string" * texts)
