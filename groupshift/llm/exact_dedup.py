"""Exact duplicates by progressive refinement: length, then prefix hash, then full hash.

Only rows that survive one step enter the next, so the strong hash is taken of few texts. Keys of a few
bytes move between machines, texts do not.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, salted_join, shielded, work_table

#: Most rows of keys or ids that go to every executor; about 16 bytes each.
BROADCAST_ROWS = 1_000_000


def normalised(text: str | Column) -> Column:
    """The text with every run of ASCII white space as one space; null is the empty text."""
    return F.regexp_replace(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), SPACE, " ")


def _hashed(docs: DataFrame, id_col: str, text_col: str, prefix_chars: int, digest_all: bool, broadcast_rows: int) -> DataFrame:
    """(id, uid, alive, sha) for every row: alive where another row has the same length and prefix hash, sha where it was taken.

    uid numbers the rows of the table as written, so that rows which repeat an id, or have none, stay apart.
    """
    rows = docs.select(F.col(id_col).alias("id"), normalised(text_col).alias("norm"))
    rows = rows.select("id", "norm", F.length("norm").alias("len"), F.xxhash64(F.substring("norm", 1, prefix_chars)).alias("head"))
    keys = work_table(rows.select("len", "head"), "refinement_keys")
    # Step 1: lengths that occur more than once. There are no more lengths than the longest text has characters.
    lengths = keys.groupBy("len").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("len")
    # Step 2: of those, the pairs of length and prefix hash that occur more than once. Dealt by length, a frequent one
    # would fill a task, so the lengths are broadcast; too many of them are left to the pairs, which imply them.
    lengths = work_table(lengths, "lengths")
    same_length = keys.join(F.broadcast(lengths), "len", "left_semi") if lengths.count() <= broadcast_rows else keys
    heads = work_table(same_length.groupBy("len", "head").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "heads")
    digest = F.sha2(F.col("norm").cast("binary"), 256)
    # Step 3: full hashes of the survivors.
    if heads.count() <= broadcast_rows:
        marked = rows.join(F.broadcast(heads), ["len", "head"], "left")
        alive = F.col("n").isNotNull()
        sha = digest if digest_all else F.when(alive, digest)
        return work_table(marked.select("id", alive.alias("alive"), sha.alias("sha")).withColumn("uid", F.monotonically_increasing_id()), "hashes")
    # Too many keys to send: every text is hashed where it is read, and rows of a few bytes meet the keys.
    small = work_table(rows.select("id", "len", "head", digest.alias("sha")).withColumn("uid", F.monotonically_increasing_id()), "digests")
    marked = salted_join(small, heads, ["len", "head"], "n", small.count(), how="left")
    alive = F.col("n").isNotNull()
    return work_table(marked.select("id", alive.alias("alive"), F.col("sha") if digest_all else F.when(alive, F.col("sha")).alias("sha"), "uid"), "hashes")


def _grouped(hashed: DataFrame, broadcast_rows: int) -> DataFrame:
    """(id, sha, keep_id, group_size, kept) for every row of hashed. A row that is not alive is a group of its own; null hashes are never compared."""
    alive = hashed.where("alive")
    # Partial minima come before the exchange, whatever the number of copies. A null id is larger than any other.
    first = F.min(F.struct(F.col("id").isNull().alias("none"), F.col("id").alias("id"), F.col("uid").alias("uid"))).alias("first")
    groups = work_table(alive.groupBy("sha").agg(first, F.count(F.lit(1)).alias("group_size")), "groups")
    if groups.count() <= broadcast_rows:
        joined = alive.join(F.broadcast(groups), "sha")
    else:
        joined = salted_join(alive, groups, ["sha"], "group_size", alive.count())
    joined = joined.select("id", "sha", F.col("first.id").alias("keep_id"), "group_size", (F.col("uid") == F.col("first.uid")).alias("kept"))
    alone = hashed.where("not alive").select("id", "sha", F.col("id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"))
    return joined.unionByName(alone)


def exact_dedup(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    prefix_chars: int = 64,
    digest_all: bool = False,
    broadcast_rows: int = BROADCAST_ROWS,
) -> DataFrame:
    """One row for every input row: id, keep_id, group_size, kept, text_sha256.

    Texts are equal when their normalised forms are; the row with the smallest id stays. text_sha256 is null
    where length and prefix hash alone told a text apart, unless digest_all asks for every digest.
    Null and empty texts are equal to each other. A null id counts as larger than any other. Rows that repeat an id, or
    have none, are rows of their own: of those with equal texts one stays. An empty table gives no rows; other columns
    are ignored, whatever their names.
    """
    found = _grouped(_hashed(docs, id_col, text_col, prefix_chars, digest_all, broadcast_rows), broadcast_rows)
    return found.select(F.col("id").alias(id_col), "keep_id", "group_size", "kept", F.col("sha").alias("text_sha256"))


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """The rows of docs that exact_dedup keeps, with all their columns, whatever their names."""
    plain, name = shielded(docs)
    found = _grouped(_hashed(docs, id_col, text_col, 64, False, broadcast_rows), broadcast_rows)
    per_id = found.groupBy("id").agg(F.count(F.lit(1)).alias("rows_of_id"), F.sum(F.col("kept").cast("long")).alias("rows_kept"))
    lossy = work_table(per_id.where("rows_kept < rows_of_id").select("id", "rows_kept"), "lossy_ids")
    small = lossy.count() <= broadcast_rows
    of = lambda ids: plain.join(F.broadcast(ids) if small else ids, plain[name[id_col]].eqNullSafe(ids["id"]), "left_semi")
    kept = plain.join(F.broadcast(lossy) if small else lossy, plain[name[id_col]].eqNullSafe(lossy["id"]), "left_anti")
    # Rows of an id of which some stay and some go are told apart by their texts' hashes. Such ids repeat, or are null.
    partly = lossy.where("rows_kept > 0").select("id")
    if not partly.isEmpty():
        gone = found.join(F.broadcast(partly) if small else partly, found["id"].eqNullSafe(partly["id"]), "left_semi").where("sha is not null")
        gone = gone.groupBy("id", "sha").agg(F.max("kept").alias("any")).where("not any").select("id", "sha")
        some = of(partly).withColumn("digest", F.sha2(normalised(name[text_col]).cast("binary"), 256))
        some = some.join(gone, some[name[id_col]].eqNullSafe(gone["id"]) & (some["digest"] == gone["sha"]), "left_anti")
        kept = kept.unionByName(some.dropDuplicates([name[id_col], "digest"]).drop("digest"))
    return kept.toDF(*docs.columns)
