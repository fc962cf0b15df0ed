"""What the training-data operators share: checkpoints, salted joins, word splitting, hashing and bounded samples."""

from __future__ import annotations

import tempfile

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space only: a word is a run of anything else.
WORD = r"[^ \t-\r]+"
MASK = (1 << 64) - 1


def work_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, from spark.checkpoint.dir. Only a session on one machine may lack it: then one is set."""
    context = spark.sparkContext
    named = context.getConf().get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if context._jsc.sc().getCheckpointDir().isEmpty():
        if not context.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="studymap-checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get().rstrip("/")


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut lineage through the shared folder."""
    work_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def remove(spark: SparkSession, folder: str) -> None:
    """Delete a folder of intermediate results, on whatever file system it lies."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


#: Parts that the rows of one key may be dealt to; a bit mask of 64 bits tells which parts a key's rows use.
SALTS = 64


def salt(*columns) -> Column:
    return F.pmod(F.xxhash64(*columns), F.lit(SALTS)).cast("int")


def salts_seen() -> Column:
    """Aggregate beside others over rows with `_salt`: the parts that a key's rows use, as `_salts`."""
    return F.expr("bit_or(shiftleft(1L, _salt))").alias("_salts")


def spread(keys: DataFrame) -> DataFrame:
    """Rows with `_salts` once for each part in use, as `_salt`: the small side of a join on key and `_salt`, never longer than the other side.

    A key with a third of all rows is so dealt to up to 64 tasks, beyond which adaptive execution can split the long side.
    """
    return keys.withColumn("_salt", F.expr(f"explode(filter(sequence(0, {SALTS - 1}), i -> (shiftright(_salts, i) & 1) = 1))")).drop("_salts")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_count(text: Column) -> Column:
    """Words of a text; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def crc_fold(doc_id: Column) -> Column:
    """crc32 of the id as text, modulo 3; a null id hashes as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 3


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").split() if text else []


def lower_words_of(text: str | None) -> list[bytes]:
    """bytes.lower changes A-Z only and bytes.split splits at ASCII white space only."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


class WordHashes(dict):
    """64-bit hashes of words, kept for up to `room` distinct words."""

    def __init__(self, room: int = 150_000, seed: int = 0):
        self.room, self.seed = room, seed

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.room:
            self.clear()
        found = self[word] = xxhash.xxh64_intdigest(word, self.seed)
        return found

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection on 64 bits whose every output bit depends on every input bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def rolling(hashes: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """One 64-bit hash for each run of k consecutive word hashes, by doubling; a shorter input has none."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    x, have, factor = mixed(hashes + np.uint64(seed + 1)), 1, 0x9E3779B97F4A7C15
    while have < k:
        step = min(have, k - have)  # the last two halves may overlap
        x = x[: len(x) - step] * np.uint64(factor) + x[step:]
        have, factor = have + step, factor * factor & MASK
    return mixed(x)


def ragged(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Indexes of all cells of runs that begin at `starts` and hold `counts` cells."""
    total = int(counts.sum())
    ends = np.cumsum(counts)
    return np.arange(total) + np.repeat(starts - (ends - counts), counts)


def bounded_sample(docs: DataFrame, labels: DataFrame, label: str, sample: int, trains, longest: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """At most `sample` labelled documents (half of each class) of at most `longest` bytes for which `trains` holds, by a hash of the identifier.

    An identifier with several rows of labels counts once; one whose rows say both classes doesn't train. Of an identifier's several texts the least one is taken.
    """
    known = labels.where(F.col(label).isNotNull() & F.col(id_col).isNotNull() & trains).groupBy(id_col).agg(F.min(F.col(label).cast("int")).alias("_y"), F.max(F.col(label).cast("int")).alias("_z"))
    known = known.where("_y = _z").select(id_col, "_y", F.xxhash64(F.lit(3), id_col).alias("_h"))
    # Each side is a top-k report of fixed size.
    chosen = known.where("_y = 1").orderBy("_h", id_col).limit(sample // 2).unionByName(known.where("_y = 0").orderBy("_h", id_col).limit(sample - sample // 2))
    short = docs.where(F.octet_length(F.coalesce(F.col(text_col), F.lit(""))) <= longest).select(id_col, F.col(text_col).alias("_text"))
    rows = short.join(F.broadcast(chosen.select(id_col, "_y")), id_col)
    # One text for each identifier: rows that repeat it don't make the sample grow.
    return rows.groupBy(id_col).agg(F.min("_text").alias("_text"), F.min("_y").alias("_y")).select("_text", "_y", F.xxhash64(id_col).alias("_h"))
