"""Near duplicates by min-max hashing, with every link confirmed on full shingle sets.

1. Each text becomes the set of its distinct `shingle`-word sequences, as 64-bit hashes. For each of `permutations` hash functions both the least and the greatest value over
   the set are kept: two signature values for one evaluation, each equal between two sets with probability their Jaccard similarity, with the lower variance that the
   negative dependence of minimum and maximum brings. Values are banded by `rows`; texts sharing a band are candidates. At similarity
   0.75 and 4 rows, 40 bands miss a pair with probability (1 - 0.75^4)^40 = 2.5e-7.
2. Texts with equal sets are one class from the start (a 128-bit fingerprint of the set, with its size), whatever identifiers they stand under. Classes, not identifiers, have
   signatures, sets and links, so copies never meet in pairs and two texts under one identifier keep their own links.
3. Each band's bucket compares its members with the bucket's least class only, where the two sizes allow the similarity; those pairs are confirmed by the exact intersection of
   the sets. Confirmed links, and links between the classes of one identifier, form components by star contraction.
4. Buckets whose members still lie in several components get every remaining pair of different components tested, inside blocks of bounded size that hold their
   sets; members of the bucket's largest component are not paired with each other. So no pair that shares a band goes untested unless it is already connected.

A bucket, class or hub that holds a large share of all rows is dealt to up to 64 tasks by a salt (base.spread).

The similarity test is in integers: 100 * intersection >= 75 * union. A text with fewer words than a shingle is one shingle; a text without words, or null, has none and is linked
with nothing. Words are runs of anything but ASCII white space, lower-cased over A-Z. Rows with a null identifier have no component and are kept. Rows that repeat an
identifier are one document: all are in one component, linked with whatever any of their texts is linked with, and all are kept if the identifier is. An
empty table gives an empty result. Sets are hashed to 64 bits: that two different shingles of two compared documents fall together has probability below 1e-10 for texts of
20,000 words.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import WordHashes, checkpointed, lower_words_of, mixed, rolling, salt, salts_seen, spread
from .components import components


def shingle_set(text: str | None, cache: WordHashes, shingle: int) -> np.ndarray:
    """Distinct hashes of a whole text's shingles, ascending."""
    words = lower_words_of(text)
    if not words:
        return np.empty(0, np.uint64)
    return np.unique(rolling(cache.of(words), min(shingle, len(words))))


def fingerprints(sets: list[np.ndarray]) -> np.ndarray:
    """(sets, 2) 128-bit fingerprints."""
    return np.array([np.frombuffer(xxhash.xxh128_digest(s.tobytes()), np.int64) for s in sets], np.int64).reshape(-1, 2)


def _signatures(sets: list[np.ndarray], a: np.ndarray, rows: int) -> np.ndarray:
    """(documents, bands) band hashes of non-empty sets: minima and maxima under multiplicative permutations."""
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    starts = np.cumsum(sizes) - sizes
    flat = mixed(np.concatenate(sets))
    values = np.empty((2 * len(a), len(sets)), np.uint64)
    for i, m in enumerate(a):
        x = flat * m
        x ^= x >> np.uint64(32)
        values[2 * i] = np.minimum.reduceat(x, starts)
        values[2 * i + 1] = np.maximum.reduceat(x, starts)
    bands = len(values) // rows
    # A band takes values that lie far apart, so minimum and maximum of one function are in different bands.
    out = np.zeros((len(sets), bands), np.uint64)
    for b in range(bands):
        h = np.full(len(sets), np.uint64(b + 1))
        for r in range(rows):
            h = mixed(h * np.uint64(0x9E3779B97F4A7C15) + values[b + r * bands])
        out[:, b] = h
    return out


def signatures(docs: DataFrame, shingle: int, permutations: int, rows: int, seed: int, id_col: str, text_col: str, block: int = 200_000) -> DataFrame:
    """(_id, _n, _f1, _f2, _bands): set size, fingerprint of the set and band hashes of every document with an identifier."""
    a = np.random.default_rng(seed).integers(0, 2**63, permutations, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    bands = 2 * permutations // rows

    def run(batches):
        cache = WordHashes()

        def done(keys, sets):
            full = [i for i, s in enumerate(sets) if len(s)]
            band = np.zeros((len(sets), bands), np.uint64)
            if full:
                band[full] = _signatures([sets[i] for i in full], a, rows)
            prints = fingerprints(sets)
            n = np.fromiter(map(len, sets), np.int64, len(sets))
            offsets = np.concatenate([[0], np.cumsum(np.where(n > 0, bands, 0))])
            values = band[n > 0].reshape(-1).view(np.int64)
            return pa.RecordBatch.from_arrays(
                [pa.array(keys, pa.int64()), pa.array(n), pa.array(prints[:, 0]), pa.array(prints[:, 1]), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(values))],
                names=["_id", "_n", "_f1", "_f2", "_bands"],
            )

        for batch in batches:
            keys, sets, n = [], [], 0
            for k, t in zip(batch.column(0).to_pylist(), batch.column(1)):
                keys.append(k)
                sets.append(shingle_set(t.as_py(), cache, shingle))
                n += len(sets[-1])
                if n > block:
                    yield done(keys, sets)
                    keys, sets, n = [], [], 0
            if keys:
                yield done(keys, sets)

    plain = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_t")).where("_id is not null")
    return plain.mapInArrow(run, "_id long, _n long, _f1 long, _f2 long, _bands array<long>")


SET = ["_n", "_f1", "_f2"]


def full_sets(texts: DataFrame, shingle: int) -> DataFrame:
    """(_c, _n, _f1, _f2, _t): classes with a text that may be theirs -> (_c, _set array<long>), once in a task for each class that a text belongs to."""

    def run(batches):
        cache, seen = WordHashes(), set()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                owner, n, f1, f2 = (part.column(c).to_pylist() for c in ("_c", *SET))
                sets = [shingle_set(t.as_py(), cache, shingle) for t in part.column("_t")]
                mine = []
                for i, (s, (a, b)) in enumerate(zip(sets, fingerprints(sets).tolist())):
                    if owner[i] not in seen and (len(s), a, b) == (n[i], f1[i], f2[i]):
                        seen.add(owner[i])
                        mine.append(i)
                if mine:
                    offsets = np.concatenate([[0], np.cumsum([len(sets[i]) for i in mine])])
                    values = pa.array(np.concatenate([sets[i] for i in mine]).view(np.int64))
                    yield pa.RecordBatch.from_arrays([pa.array([owner[i] for i in mine], pa.int64()), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), values)], names=["_c", "_set"])

    return texts.select("_c", *SET, "_t").mapInArrow(run, "_c long, _set array<long>")


def _alike(n1, n2, both, percent: int):
    return 100 * both >= percent * (n1 + n2 - both)


def _confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of classes whose sets are alike enough. b is a bucket's least class and may recur often: its set is sent once to each part of its pairs."""
    pairs = pairs.withColumn("_salt", salt("a"))
    hubs = pairs.groupBy("b").agg(salts_seen()).join(sets.select(F.col("_c").alias("b"), F.col("_set").alias("_sb")), "b")
    both = pairs.join(sets.select(F.col("_c").alias("a"), F.col("_set").alias("_sa")), "a").join(spread(hubs), ["b", "_salt"])
    return both.where(_alike(F.size("_sa"), F.size("_sb"), F.size(F.array_intersect("_sa", "_sb")), percent)).select("a", "b")


def _open_members(placed: DataFrame, block: int) -> DataFrame:
    """(_key, _c, _component, _salt) -> (_key, _i, _j, _c, _component): members of buckets that hold several components, once for each pair of blocks they are tested in.

    Blocks 0 to _others - 1 hold what isn't in the bucket's largest component, the blocks behind them that component, whose own pairs need no test.
    """
    parts = placed.groupBy("_key", "_component").agg(F.count(F.lit(1)).alias("_k"), salts_seen())
    open_ = parts.groupBy("_key").agg(F.max_by("_component", "_k").alias("_main"), F.max("_k").alias("_in"), F.sum("_k").alias("_m"), F.count(F.lit(1)).alias("_of"), F.bit_or("_salts").alias("_salts"))
    blocks = lambda n: F.ceil(n / block).cast("int")
    small = F.col("_m") <= block  # one block holds it all
    open_ = open_.where("_of > 1").select(
        "_key", F.when(~small, F.col("_main")).alias("_main"), F.when(small, 0).otherwise(blocks(F.col("_in"))).alias("_mains"), F.when(small, 1).otherwise(blocks(F.col("_m") - F.col("_in"))).alias("_others"), "_salts"
    )
    x = placed.join(spread(open_), ["_key", "_salt"])
    main, h = F.coalesce(F.col("_component") == F.col("_main"), F.lit(False)), F.xxhash64("_c")
    own = F.when(main, F.col("_others") + F.pmod(h, F.col("_mains"))).otherwise(F.pmod(h, F.col("_others"))).cast("int")
    last = F.when(main, F.col("_others")).otherwise(F.col("_others") + F.col("_mains")) - 1
    x = x.withColumn("_own", own).withColumn("_other", F.explode(F.sequence(F.lit(0), last)))
    return x.select("_key", F.least("_own", "_other").alias("_i"), F.greatest("_own", "_other").alias("_j"), "_c", "_component")


def _open_links(members: DataFrame, percent: int) -> DataFrame:
    """Rows (_key, _i, _j, _c, _component, _set) -> links (a, b) between different components of a pair of blocks."""

    def test(table: pa.Table) -> pa.Table:
        ids = table.column("_c").to_numpy()
        group = table.column("_component").to_numpy()
        lists = table.column("_set").combine_chunks()
        sizes = np.diff(lists.offsets.to_numpy())
        names, at = np.unique(lists.flatten().to_numpy(), return_inverse=True)
        owner = np.repeat(np.arange(len(ids)), sizes)
        order = np.argsort(at, kind="stable")
        posting, starts = owner[order], np.searchsorted(at[order], np.arange(len(names) + 1))
        ends = np.cumsum(sizes)
        root = {}

        def find(g):
            while root.setdefault(g, g) != g:
                root[g] = root[root[g]]
                g = root[g]
            return g

        a, b = [], []
        for i in range(len(ids)):
            mine = at[ends[i] - sizes[i] : ends[i]]
            hits = np.concatenate([posting[starts[m] : starts[m + 1]] for m in mine]) if len(mine) else np.empty(0, int)
            both = np.bincount(hits, minlength=len(ids))
            for j in np.flatnonzero(_alike(sizes[i], sizes, both, percent)):
                if j > i and find(group[i]) != find(group[j]):
                    root[find(group[i])] = find(group[j])
                    a.append(ids[i])
                    b.append(ids[j])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return members.groupBy("_key", "_i", "_j").applyInArrow(test, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, percent: int = 75, permutations: int = 80, rows: int = 4, seed: int = 17, block: int = 512) -> DataFrame:
    """One row per input row: id, n_shingles, component_id, kept (id = component_id)."""
    sig = checkpointed(signatures(docs, shingle, permutations, rows, seed, id_col, text_col).withColumn("_salt", salt("_id")))
    full = sig.where("_n > 0")
    classes = full.groupBy(*SET).agg(F.min("_id").alias("_rep"), F.first("_bands").alias("_bands"), salts_seen())
    classes = checkpointed(classes.withColumn("_c", F.monotonically_increasing_id()))  # the numbers are fixed by the written table
    named = checkpointed(full.select("_id", "_salt", *SET).join(spread(classes.select(*SET, "_c", "_salts")), [*SET, "_salt"]).select("_id", "_n", "_c", "_salt"))

    banded = classes.select("_c", "_n", F.explode("_bands").alias("_key")).withColumn("_salt", salt("_c"))
    buckets = banded.groupBy("_key").agg(F.min("_c").alias("_least"), F.min_by("_n", "_c").alias("_least_n"), F.count(F.lit(1)).alias("_m"), salts_seen()).where("_m > 1")
    inside = checkpointed(banded.join(spread(buckets), ["_key", "_salt"]).select("_key", "_least", "_least_n", "_m", "_c", "_n", "_salt"))
    sized = 100 * F.least("_n", "_least_n") >= percent * F.greatest("_n", "_least_n")
    pairs = inside.where((F.col("_c") != F.col("_least")) & sized).select(F.col("_c").alias("a"), F.col("_least").alias("b")).distinct()
    need = classes.join(inside.select("_c").distinct(), "_c", "left_semi").select("_c", F.col("_rep").alias("_id"), *SET)
    texts = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_t")).join(need, "_id")
    sets = checkpointed(full_sets(texts, shingle))
    # Classes of one identifier are one document.
    tied = named.groupBy("_id").agg(F.min("_c").alias("_lo"), F.max("_c").alias("_hi")).where("_lo < _hi")
    ties = named.join(tied, "_id").where("_c <> _lo").select(F.col("_c").alias("a"), F.col("_lo").alias("b")).distinct()
    found = components(_confirm(pairs, sets, percent).unionByName(ties))

    placed = inside.where("_m > 2").select("_key", "_c", "_salt").join(found.withColumnRenamed("node", "_c"), "_c", "left")
    placed = checkpointed(placed.select("_key", "_c", "_salt", F.coalesce("component", "_c").alias("_component")))
    more = checkpointed(_open_links(_open_members(placed, block).join(sets, "_c"), percent).distinct())
    if not more.isEmpty():
        found = components(found.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(more))

    grouped = classes.select("_c", "_rep", "_salts").join(found.withColumnRenamed("node", "_c"), "_c", "left").select("_c", "_rep", "_salts", F.coalesce("component", "_c").alias("_g"))
    least = grouped.select("_g", "_rep", salt("_c").alias("_salt")).groupBy("_g").agg(F.min("_rep").alias("_component"), salts_seen())
    decided = grouped.withColumn("_salt", salt("_c")).join(spread(least), ["_g", "_salt"]).select("_c", "_component", "_salts")
    out = named.join(spread(decided), ["_c", "_salt"]).select("_id", "_n", "_component")
    lone = sig.where("_n = 0").select("_id", "_n")
    beside = out.join(lone.select("_id").distinct(), "_id", "left_semi").groupBy("_id").agg(F.min("_component").alias("_component"))
    out = out.unionByName(lone.join(beside, "_id", "left").select("_id", "_n", F.coalesce("_component", "_id").alias("_component")))
    out = out.select(F.col("_id").alias(id_col), F.col("_n").alias("n_shingles"), F.col("_component").alias("component_id"), (F.col("_id") == F.col("_component")).alias("kept"))
    nameless = docs.where(F.col(id_col).isNull()).select(F.lit(None).cast("long").alias(id_col), F.lit(None).cast("long").alias("n_shingles"), F.lit(None).cast("long").alias("component_id"), F.lit(True).alias("kept"))
    return out.unionByName(nameless)


def without_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """The rows that stay (the least identifier of each component), with exactly the input's columns."""
    names = docs.columns
    plain = docs.toDF(*(f"_c{i}" for i in range(len(names))))
    at = f"_c{names.index(id_col)}"
    dropped = near_duplicates(docs.select(id_col, text_col), id_col, text_col, **how).where(~F.col("kept")).select(F.col(id_col).alias("_gone")).distinct()
    return plain.join(dropped, F.col(at) == F.col("_gone"), "left_anti").toDF(*names)
