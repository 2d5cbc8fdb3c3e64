"""Mixing sources to target weights by a low-discrepancy schedule of equal blocks; DataFrame operations only.

Each source's documents, shuffled by hash, form a stream of words that is cut into equal blocks. Slot i of the
schedule takes point frac(i * golden ratio), which falls into one source's stretch of the unit interval; the
slot's rank among its source's slots names the block it takes, going round the stream again for later epochs.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, broadcast_if_small, shielded, work_table

#: 2**32 divided by the golden ratio, made odd: multiples of it modulo 2**32 are golden-ratio points.
GOLDEN = 2_654_435_769
CELLS = 4096
#: Documents of a source are dealt into so many hash ranges, and prefix sums are taken within and over ranges.
RANGES = 4096
BROADCAST_ROWS = 1_000_000


def word_count(text: str) -> Column:
    return F.regexp_count(F.coalesce(F.col(text), F.lit("")), F.lit(WORD)).cast("long")


def golden_point(i: Column) -> Column:
    """frac(i * golden ratio) as an integer below 2**32, without overflow for i below 2**47."""
    high = (F.shiftrightunsigned(i, 16) * F.lit(GOLDEN)).bitwiseAND(F.lit(2**32 - 1))
    return (high * 65536 + i.bitwiseAND(F.lit(65535)) * F.lit(GOLDEN)).bitwiseAND(F.lit(2**32 - 1))


def running_start(df: DataFrame, key: str, part: str, order: list[str], value: Column, name: str) -> DataFrame:
    """Adds the sum of value over rows of the same key before the row, in the order of part and then order.

    Two levels keep a large key from meeting in one task: sums within each part, and a sum over the parts' totals.
    """
    inner = Window.partitionBy(key, part).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    totals = df.groupBy(F.col(key).alias("_k"), F.col(part).alias("_p")).agg(F.sum(value).alias("_t"))
    outer = Window.partitionBy("_k").orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("_k", "_p", F.coalesce(F.sum("_t").over(outer), F.lit(0)).alias("_o"))
    local = df.withColumn("_l", F.coalesce(F.sum(value).over(inner), F.lit(0)))
    joined = local.join(offsets, (local[key] == offsets["_k"]) & (local[part] == offsets["_p"]))
    return joined.withColumn(name, (F.col("_o") + F.col("_l")).cast("long")).drop("_k", "_p", "_o", "_l")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: int = 3) -> DataFrame:
    """source, sid, source_size, weight, target for each source of sizes (source, size).

    Sources in order of code points, null last, get the weights in turn and share the sum of all sizes. A target
    stops at most times its source's size; what is over goes to the others by weight until none is above. Sorted by
    cap over weight the capped sources come first, so running sums find them. Its windows see one row a source.
    """
    per = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    by_name, whole = Window.orderBy(F.col("source").asc_nulls_last()), Window.partitionBy()
    w = F.element_at(F.array(*map(F.lit, weights)), (F.col("sid") % len(weights) + 1).cast("int"))
    per = per.withColumn("sid", F.row_number().over(by_name) - 1).withColumn("weight", w)
    per = per.withColumn("cap", F.col("source_size") * most)
    before = Window.orderBy(F.col("cap") / F.col("weight"), "sid").rowsBetween(Window.unboundedPreceding, -1)
    left_size = F.sum("source_size").over(whole) - F.coalesce(F.sum("cap").over(before), F.lit(0))
    left_weight = F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0))
    per = per.withColumn("capped", F.col("cap") < left_size / left_weight * F.col("weight"))
    free_size = F.sum("source_size").over(whole) - F.sum(F.when(F.col("capped"), F.col("cap")).otherwise(0)).over(whole)
    free_weight = F.sum(F.when(~F.col("capped"), F.col("weight")).otherwise(0)).over(whole)
    level = F.try_divide(free_size, free_weight)
    target = F.when(F.col("capped"), F.col("cap").cast("double")).otherwise(level * F.col("weight"))
    return per.select("source", "sid", "source_size", "weight", target.cast("double").alias("target"))


@dataclass(frozen=True)
class Mix:
    sources: DataFrame  # source, sid, source_size, weight, target, quota, blocks, slots
    schedule: DataFrame  # position, sid, rank, block, words
    documents: DataFrame  # doc_id, source, size, source_size, target, taken


def mix(
    docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: int = 3, block_words: int = 256, seed: str = "mix"
) -> Mix:
    """Mixes docs (doc_id, source, text) to weights; other columns are ignored.

    Every row of docs is in documents, with the words that the mix takes of it. The words of a source that are taken
    equal its target rounded, so a document is taken at most most times. An empty or null text has size 0 and nothing
    is taken of it; a null source is a source. Rows that agree in id, source and size may swap their takings.
    An empty table gives empty results.
    """
    # A document without an id has the hash of its text, so that such rows spread over their source's stream.
    name = F.coalesce(F.col("doc_id").cast("string"), F.md5(F.coalesce("text", F.lit(""))))
    key = F.md5(F.concat_ws(":", F.lit(seed), name))
    base = work_table(
        docs.select("doc_id", "source", word_count("text").alias("size"), F.conv(F.substring(key, 1, 15), 16, 10).cast("long").alias("h")),
        "sizes",
    )
    per = source_targets(base, weights, most)
    quota, whole_rounds = F.round("target").cast("long"), F.expr("quota div source_size")
    per = per.withColumn("quota", quota).withColumn("blocks", F.ceil(F.col("source_size") / block_words).cast("long"))
    rounds = F.when(F.col("source_size") > 0, whole_rounds).otherwise(0)
    rest = F.when(F.col("source_size") > 0, F.col("quota") % F.col("source_size")).otherwise(0)
    per = per.withColumn("slots", (rounds * F.col("blocks") + F.ceil(rest / block_words)).cast("long"))
    sources = work_table(per, "sources")
    n_sources = sources.count()

    # The schedule. Each source's stretch of [0, 2**32) is spread over the cells it meets, so that a slot finds
    # its source by an equality on its point's cell and a check of bounds.
    totals = sources.agg(F.sum("slots").alias("n")).first()
    n_slots = int(totals["n"] or 0)
    spark, up_to = docs.sparkSession, Window.orderBy("sid").rowsBetween(Window.unboundedPreceding, 0)
    edge = F.floor(F.sum("slots").over(up_to) * F.lit(float(2**32)) / F.lit(float(max(n_slots, 1)))).cast("long")
    width = 2**32 // CELLS
    stretch = sources.where("slots > 0").select("sid", edge.alias("hi"))
    stretch = stretch.withColumn("lo", F.coalesce(F.lag("hi").over(Window.orderBy("sid")), F.lit(0))).where("hi > lo")
    cells = stretch.withColumn("cell", F.explode(F.sequence(F.expr(f"lo div {width}"), F.expr(f"(hi - 1) div {width}"))))
    slots = spark.range(n_slots).select(F.col("id").alias("position"), golden_point(F.col("id")).alias("u"))
    slots = slots.withColumn("cell", F.expr(f"u div {width}"))
    # At most CELLS rows, and one more for each source.
    cells = broadcast_if_small(cells, n_sources + CELLS, BROADCAST_ROWS)
    hit = (slots["cell"] == cells["cell"]) & (slots["u"] >= cells["lo"]) & (slots["u"] < cells["hi"])
    drawn = slots.join(cells, hit).select("position", "sid", F.expr("position div 65536").alias("part"))
    ranked = running_start(drawn, "sid", "part", ["position"], F.lit(1), "rank").select("position", "sid", "rank")
    found = ranked.groupBy(F.col("sid").alias("s")).agg(F.count(F.lit(1)).alias("got"))
    # Discrepancy leaves a source a few slots short or over: those over go, those short come at the end.
    short = sources.join(found, F.col("sid") == F.col("s"), "left").withColumn("got", F.coalesce("got", F.lit(0)))
    short = short.where("slots > got").select("sid", F.explode(F.sequence("got", F.col("slots") - 1)).alias("rank"))
    short = short.select((F.col("rank") + n_slots).alias("position"), "sid", "rank")
    plan = ranked.unionByName(short).join(broadcast_if_small(sources, n_sources, BROADCAST_ROWS), "sid").where("rank < slots")
    plan = plan.withColumn("block", F.col("rank") % F.col("blocks"))
    begins = F.expr(f"(rank div blocks) * source_size + block * {block_words}")
    length = F.least(F.lit(block_words), F.col("source_size") - F.col("block") * block_words)
    schedule = plan.select("position", "sid", "rank", "block", F.least(length, F.col("quota") - begins).cast("long").alias("words"), length.cast("long").alias("length"))
    visits = schedule.groupBy("sid", "block").agg(
        F.sum(F.when(F.col("words") == F.col("length"), 1).otherwise(0)).alias("whole"),
        F.max(F.when(F.col("words") < F.col("length"), F.col("words")).otherwise(0)).alias("partial"),
    )

    # The documents' places in their sources' streams, and the pieces of them in each block.
    known = broadcast_if_small(sources.select(F.col("source").alias("src"), "sid", "source_size", "target"), n_sources, BROADCAST_ROWS)
    placed = base.join(known, base["source"].eqNullSafe(known["src"])).drop("src")
    placed = placed.withColumn("part", F.shiftright("h", 60 - RANGES.bit_length() + 1))
    # Empty texts take no place in a stream.
    starts = running_start(placed.where("size > 0"), "sid", "part", ["h", "doc_id", "size"], F.col("size"), "start")
    placed = work_table(starts.unionByName(placed.where("size = 0").withColumn("start", F.lit(None).cast("long"))).drop("part", "h"), "streams")
    pieces = placed.where("size > 0").select(
        "sid", "start", "size",
        F.explode(F.sequence(F.expr(f"start div {block_words}"), F.expr(f"(start + size - 1) div {block_words}"))).alias("block"),
    )
    low = F.greatest(F.col("start") - F.col("block") * block_words, F.lit(0))
    high = F.least(F.col("start") + F.col("size") - F.col("block") * block_words, F.lit(block_words))
    pieces = pieces.withColumns({"low": low, "high": high}).join(visits, ["sid", "block"])
    part = F.col("whole") * (F.col("high") - F.col("low")) + F.greatest(
        F.least(F.col("partial"), F.col("high")) - F.col("low"), F.lit(0)
    )
    taken = pieces.groupBy(F.col("sid").alias("s"), F.col("start").alias("b")).agg(F.sum(part).cast("long").alias("taken"))
    # A document with words is alone in starting where it does.
    same = (placed["sid"] == taken["s"]) & (placed["start"] == taken["b"]) & (placed["size"] > 0)
    documents = placed.join(taken, same, "left").select(
        "doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken")
    )
    return Mix(sources, schedule.drop("length"), documents)


def mixed_documents(docs: DataFrame, broadcast_rows: int = BROADCAST_ROWS, **options) -> DataFrame:
    """The rows of docs, each as often as the mix takes it, to the nearest whole number.

    At most one document of a source is taken in part. Rows that agree in id, source and size come equally often.
    """
    taken = mix(docs, **options).documents
    copies = taken.groupBy(F.col("doc_id").alias("d"), F.col("source").alias("s"), F.col("size").alias("n")).agg(
        F.round(F.try_divide(F.sum("taken"), F.sum("size"))).cast("int").alias("copies")
    )
    copies = work_table(copies.where("copies > 0"), "copies")
    copies = broadcast_if_small(copies, copies.count(), broadcast_rows)
    plain, name = shielded(docs)
    sized = plain.withColumn("words", word_count(name["text"]))
    same = sized[name["doc_id"]].eqNullSafe(copies["d"]) & sized[name["source"]].eqNullSafe(copies["s"]) & (sized["words"] == copies["n"])
    repeated = sized.join(copies, same).withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies"))))
    return repeated.select(*name.values()).toDF(*docs.columns)
