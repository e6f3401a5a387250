"""Helpers that the operators share: tables, scratch tables in the shared folder, cutting lineage."""

from __future__ import annotations

import ctypes
import hashlib
import sys
import types
import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regioncount.sources.shared import cut, shared_dir  # noqa: F401

#: Pattern of one separator between words: ASCII white space only.
SPACE = "[\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Scratch:
    """Written intermediate tables. They outlive lost executors, and go once the next table is written."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_dir(spark)}/scratch-{uuid.uuid4().hex}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        return self.save_each([df], name)

    def save_each(self, frames: Iterable[DataFrame], name: str) -> DataFrame:
        """One table of all frames, written one after another: the shuffle files of one go before the next is made."""
        path = f"{self.root}/{name}-{uuid.uuid4().hex[:8]}"
        for df in frames:
            df.write.mode("append").parquet(path)
            # shuffle files go when the driver's collector finds their plan unused; left to itself it runs by the driver's
            # own garbage, so on large inputs the files of every table so far would stay on disk
            self.spark._jvm.System.gc()
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *frames: DataFrame) -> None:
        """Delete what `save` wrote for these frames; nothing may read them afterwards."""
        for df in frames:
            for file in df.inputFiles()[:1]:
                self._delete(file.rsplit("/", 1)[0])

    def close(self) -> None:
        self._delete(self.root)

    def _delete(self, path: str) -> None:
        jvm = self.spark._jvm
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def spread_join(rows: DataFrame, combined: DataFrame, key: str, by: str, salts: int = 4) -> DataFrame:
    """rows joined with `combined`, which has one row a key. Rows are dealt by the key and a hash of `by`, so that a
    frequent key is split at once, and further by the skew handling of joins, as neither side arrives already dealt."""
    salt = F.pmod(F.xxhash64(by), F.lit(salts)).cast("int")
    copies = combined.withColumn("__rc_salt", F.explode(F.array(*[F.lit(k) for k in range(salts)])))
    return rows.withColumn("__rc_salt", salt).join(copies, [key, "__rc_salt"]).drop("__rc_salt")


def clean_text(name: str = "text"):
    return F.coalesce(F.col(name), F.lit(""))


class Recent:
    """Bounded memory of a function's results, by key: `young` takes new ones, and becomes `old` when it is full.

    Keys that are asked for again move back to `young`, so frequent ones stay and rare ones go. Keys longer than
    `longest` are not kept.
    """

    def __init__(self, make, size: int, longest: int = 64):
        self.make, self.size, self.longest = make, size, longest
        self.young: dict = {}
        self.old: dict = {}
        #: Fast path of callers: `get(key)`, then `miss(key)` if that is None. Both dicts stay the same objects.
        self.get = self.young.get

    def miss(self, key):
        found = self.old.get(key)
        if found is None:
            found = self.make(key)
            if len(key) > self.longest:
                return found
        if len(self.young) >= self.size:
            self.old.clear()
            self.old.update(self.young)
            self.young.clear()
        self.young[key] = found
        return found

    def __call__(self, key):
        found = self.get(key)
        return self.miss(key) if found is None else found

    def clear(self) -> None:
        self.young.clear()
        self.old.clear()


def slices(batches: Iterator, rows: int = 256) -> Iterator:
    """Record batches cut into short ones, so that what a task makes of one stays small."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


class Hashes(dict):
    """64-bit hashes of words (bytes), computed when first asked for; `trim` between batches bounds its size."""

    def __missing__(self, word: bytes) -> int:
        h = int.from_bytes(hashlib.blake2b(word, digest_size=8).digest(), "little")
        self[word] = h
        return h

    def trim(self, most: int) -> None:
        if len(self) > most:
            self.clear()


def give_back() -> None:
    """Return freed memory to the system at the end of a task: the worker lives on, idle or for other tasks."""
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim:
            trim(0)


def once_per_process(key: str, make):
    """What `make` gives, kept in this process under `key`; only the last key is kept.

    Functions reach workers by value, so their modules' globals are new in every task; this holder is not.
    """
    holder = sys.modules.setdefault("__regioncount_process__", types.ModuleType("__regioncount_process__"))
    if getattr(holder, "key", None) != key:
        holder.key, holder.value = None, None
        holder.value = make()
        holder.key = key
    return holder.value
