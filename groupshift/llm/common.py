"""What the training-data operators share: tokens, per-worker caches, work tables of the library."""

from __future__ import annotations

import sys
import types

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from groupshift.sources.work import shared_folder, work_table

#: The class of the ASCII white space that separates words, as Java and Python patterns write it.
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def worker_cache(name: str, make, key=None):
    """make(), kept in the Python worker under name while key stays the same; workers live on between tasks."""
    store = sys.modules.setdefault("_groupshift_worker_cache", types.ModuleType("_groupshift_worker_cache")).__dict__
    if name not in store or store[name][0] != key:
        store[name] = (key, make())
    return store[name][1]


def each_text(column, step: int = 512):
    """The texts of an Arrow column, few of them as Python strings at a time; null is empty."""
    for at in range(0, len(column), step):
        for text in column.slice(at, step).to_pylist():
            yield text or ""


def frugal(run):
    """run, which maps batches to batches, giving back to the system what memory it leaves unused in the worker."""

    def wrapped(batches):
        import ctypes

        import pyarrow as pa

        yield from run(batches)
        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc
        if trim is not None:
            trim(0)

    return wrapped


def tokens(text: str | None) -> list[bytes]:
    """The words of a text in UTF-8 with A-Z in lower case; bytes.split and bytes.lower know ASCII only."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def crc_of(column: str) -> Column:
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")))


def broadcast_if_small(df: DataFrame, rows: int, bound: int) -> DataFrame:
    """A broadcast hint only where a count has shown that at most bound rows go to each executor."""
    return F.broadcast(df) if rows <= bound else df


def shielded(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """docs with its columns named c0, c1, .., and the new name of each old one: no helper column can clash with them."""
    names = [f"c{i}" for i in range(len(docs.columns))]
    return docs.toDF(*names), dict(zip(docs.columns, names, strict=True))


#: Rows of one key that a task of salted_join may get at least, before the key is split.
LEAST_SPLIT = 256


def salted_join(
    left: DataFrame, right: DataFrame, on: list[str], weight: str, total: int, hot_rows: int = 100_000, how: str = "inner", broadcast_rows: int = 0
) -> DataFrame:
    """left joined with right, whose keys occur once and come with the number (weight) of left rows that they have of total in all.

    A key of more than total / hot_rows rows is split: its left rows are dealt by hash over several salts, and its row of
    right is repeated for each. There are fewer than hot_rows such keys, so that their list may be broadcast, and fewer than twice as
    many repeated rows. how is inner, left or left_semi. Keys that are null join nothing. The names _salt, _salts and _k0, .. must be free.
    right, which has no more rows than left, is broadcast whole where left has broadcast_rows at most: for rows of a few bytes.
    """
    if total <= broadcast_rows:
        return left.join(F.broadcast(right), on, how)
    most = max(LEAST_SPLIT, -(-total // hot_rows))
    keys = [f"_k{i}" for i in range(len(on))]
    hot = right.where(F.col(weight) > most).select(*[F.col(c).alias(k) for c, k in zip(on, keys, strict=True)], F.ceil(F.col(weight) / most).cast("int").alias("_salts"))
    same = None
    for c, k in zip(on, keys, strict=True):
        same = (F.col(c) == F.col(k)) if same is None else same & (F.col(c) == F.col(k))
    dealt = left.join(F.broadcast(hot), same, "left").drop(*keys)
    own = F.pmod(F.xxhash64(*left.columns), F.coalesce("_salts", F.lit(1))).cast("int")
    dealt = dealt.withColumn("_salt", own).drop("_salts")
    copies = F.when(F.col(weight) > most, F.ceil(F.col(weight) / most)).otherwise(1).cast("int")
    spread = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), copies - 1)))
    return dealt.join(spread, [*on, "_salt"], how).drop("_salt")


__all__ = ["SPACE", "WORD", "broadcast_if_small", "crc_of", "each_text", "frugal", "salted_join", "shared_folder", "shielded", "table", "tokens", "work_table", "worker_cache"]
