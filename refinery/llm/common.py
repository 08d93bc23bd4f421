"""Shared pieces: stage tables in the cluster's shared folder, words, shingle hashes."""

from __future__ import annotations

import gc
import re
import uuid

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed value: a word is a run without ASCII blanks.
WORD = r"[^\x20\x09-\x0D]+"
BLANK = r"[\x20\x09-\x0D]+"
WORD_RE = re.compile(WORD)
#: Fixed values of near-duplicate operators: words in a shingle, least similarity.
SHINGLE_WORDS, MIN_SIMILARITY = 5, 0.8


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir, which all executors share. On a cluster without one this raises: a folder of one machine would lose what other
    executors write. In local mode a folder beside the warehouse serves."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not path:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        path = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}-shared"
    return path.rstrip("/")


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write once to the shared folder and read back: cuts lineage, and any executor can reread it."""
    path = f"{shared_dir(df.sparkSession)}/stage-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Has the driver let go of finished queries, so that the executors delete their shuffle files now and not when it happens to collect its garbage."""
    gc.collect()
    spark._jvm.System.gc()


def drop_stage(df: DataFrame) -> None:
    """Delete a stage table that no later step reads."""
    spark = df.sparkSession
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/stage-" in path:
            p = spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def words_col(text: Column) -> Column:
    """Array of the words of a text, on the JVM; null has none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), BLANK), lambda w: w != "")


def let(value: Column, body) -> Column:
    """body of a value that is computed once: lambdas evaluate what they capture again for each element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def byte_words(text: str | None) -> list[bytes]:
    """The words of a text in UTF-8: bytes.split() parts at exactly the six ASCII blanks."""
    return (text or "").encode("utf-8", "surrogatepass").split()


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


class WordHashes:
    """64-bit hash of each word, remembered while the memory bound holds."""

    def __init__(self, most: int = 500_000):
        self.known: dict[bytes, int] = {}
        self.most = most

    def __call__(self, words: list[bytes]) -> np.ndarray:
        known = self.known
        try:
            return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        except KeyError:
            pass
        if len(known) > self.most:
            known.clear()
        for w in words:
            if w not in known:
                known[w] = xxhash.xxh3_64_intdigest(w)
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def mix(h: np.ndarray, seed: int = 0) -> np.ndarray:
    """A finalizer of 64-bit hashes (multiply and shift rounds)."""
    with np.errstate(over="ignore"):
        h = h + np.uint64((seed * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
        h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return h ^ (h >> np.uint64(31))


def shingle_set(hashes: np.ndarray, width: int = SHINGLE_WORDS) -> np.ndarray:
    """Sorted distinct hashes of the windows of `width` words; a shorter text is one window; no words, none."""
    n = len(hashes)
    if n == 0:
        return np.empty(0, dtype=np.uint64)
    take = min(width, n)
    out = np.zeros(n - take + 1, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k in range(take):
            out = out * np.uint64(0x100000001B3) + mix(hashes[k : n - take + 1 + k], k)
    return np.unique(mix(out))
