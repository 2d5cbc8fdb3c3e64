"""Panels (series_id, t, x) built from the given tables, and changes planted in them."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from groupshift.operators.relops import numbered

from .tables import table

#: Money is summed as decimals, so that sums don't depend on the order of rows.
MONEY = "decimal(18,4)"
PANEL_SCHEMA = "series_id long, t long, x double"


def period(date: Column, anchor: str, days: int) -> Column:
    """1-based number of the period of so many days from anchor."""
    return (F.floor(F.datediff(date, F.lit(anchor).cast("date")) / days) + 1).cast("long")


def densify(cells: DataFrame, series: DataFrame, n: int, fill: float = 0.0) -> DataFrame:
    """Every series at every time 1..n; fill where cells has no row. Each series brings its own calendar."""
    grid = series.select(F.col("series_id").cast("long").alias("series_id"), F.explode(F.sequence(F.lit(1).cast("long"), F.lit(n).cast("long"))).alias("t"))
    return grid.join(cells, ["series_id", "t"], "left").select("series_id", "t", F.coalesce("x", F.lit(fill)).alias("x"))


def complete_series(panel: DataFrame, n: int) -> DataFrame:
    """The series that have all n times."""
    whole = panel.groupBy("series_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") == n)
    return panel.join(whole.select("series_id"), "series_id", "left_semi")


def log_return(panel: DataFrame) -> DataFrame:
    """log(x / previous x) of each series, times from 1; one time fewer."""
    before = F.lag("x").over(Window.partitionBy("series_id").orderBy("t"))
    return panel.withColumn("b", before).where("b is not null").select("series_id", (F.col("t") - 1).alias("t"), F.log(F.col("x") / F.col("b")).alias("x"))


def nation_week(spark: SparkSession, sf: str, weeks: int = 343) -> DataFrame:
    orders = table(spark, sf, "orders").select("o_custkey", "o_totalprice", period(F.col("o_orderdate"), "1995-01-01", 7).alias("t"))
    nations = table(spark, sf, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("series_id"))
    cells = orders.where(F.col("t").between(1, weeks)).join(nations, orders["o_custkey"] == nations["c_custkey"])
    cells = cells.groupBy("series_id", "t").agg(F.sum(F.col("o_totalprice").cast(MONEY)).cast("double").alias("x"))
    return densify(cells, table(spark, sf, "nation").select(F.col("n_nationkey").alias("series_id")), weeks)


def supplier_week(spark: SparkSession, sf: str, weeks: int = 356) -> DataFrame:
    rows = table(spark, sf, "lineitem").select(
        F.col("l_suppkey").alias("series_id"), period(F.col("l_shipdate"), "1995-01-02", 7).alias("t"), (F.col("l_extendedprice") * (1 - F.col("l_discount"))).cast(MONEY).alias("v")
    )
    cells = rows.where(F.col("t").between(1, weeks)).groupBy("series_id", "t").agg(F.sum("v").cast("double").alias("x"))
    return densify(cells, table(spark, sf, "supplier").select(F.col("s_suppkey").alias("series_id")), weeks)


def brand_return(spark: SparkSession, sf: str, months: int = 82) -> DataFrame:
    """Log returns of each brand's monthly mean unit price; brands with all months only. n is months - 1."""
    lines = table(spark, sf, "lineitem").select("l_partkey", "l_shipdate", (F.col("l_extendedprice") / F.col("l_quantity")).cast(MONEY).alias("v"))
    t = ((F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate")).cast("long")
    parts = table(spark, sf, "part").select("p_partkey", F.regexp_extract("p_brand", r"(\d+)", 1).cast("long").alias("series_id"))
    cells = lines.withColumn("t", t).where(F.col("t").between(1, months)).join(parts, lines["l_partkey"] == parts["p_partkey"])
    cells = cells.groupBy("series_id", "t").agg((F.sum("v").cast("double") / F.count(F.lit(1))).alias("x"))
    return log_return(complete_series(cells, months))


def event_hour(spark: SparkSession, sf: str, hours: int = 720, what: str = "count") -> DataFrame:
    """Events of each type and user bucket by hour: their number, or the sum of their values. Types in alphabetical order."""
    events = table(spark, sf, "events").select("ts", "user_id", "event_type", "value")
    types = events.select("event_type").distinct().withColumn("type_no", F.row_number().over(Window.orderBy("event_type")) - 1)
    t = (F.floor(F.expr("timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts)") / 3600) + 1).cast("long")
    rows = events.withColumn("t", t).where(F.col("t").between(1, hours)).join(types, "event_type")
    series = (F.col("type_no") * 10 + F.pmod("user_id", F.lit(10))).cast("long")
    value = F.count(F.lit(1)).cast("double") if what == "count" else F.sum(F.col("value").cast(MONEY)).cast("double")
    cells = rows.groupBy(series.alias("series_id"), "t").agg(value.alias("x"))
    every = types.select(F.explode(F.sequence(F.col("type_no") * 10, F.col("type_no") * 10 + 9)).alias("series_id"))
    return densify(cells, every, hours)


def embedding_stream(spark: SparkSession, sf: str) -> DataFrame:
    """Series are the vectors' components, times the vectors in order of id."""
    rows = table(spark, sf, "embeddings").select((F.col("vec_id") + 1).alias("t"), "embedding")
    return rows.select("t", F.posexplode("embedding").alias("i", "v")).select((F.col("i") + 1).cast("long").alias("series_id"), "t", F.col("v").cast("double").alias("x"))


def text_features() -> dict[str, Column]:
    """Numbers that describe a text, by name; counts per character are shares."""
    text = F.coalesce(F.col("text"), F.lit(""))
    words = F.regexp_extract_all(text, F.lit(r"(\S+)"), F.lit(1))
    share = lambda pattern: F.regexp_count(text, F.lit(pattern)) / F.greatest(F.length(text), F.lit(1))
    return {
        "log_chars": F.log(1.0 + F.length(text)), "log_words": F.log(1.0 + F.size(words)), "log_lines": F.log(1.0 + F.regexp_count(text, F.lit("\n"))),
        "digit_share": share("[0-9]"), "upper_share": share("[A-Z]"), "punct_share": share("[.,;:!?]"), "space_share": share("[ \n\t]"),
        "distinct_ratio": F.size(F.array_distinct(words)) / F.greatest(F.size(words), F.lit(1)),
    }


def corpus_stats(spark: SparkSession, sf: str) -> DataFrame:
    """Series are features of the documents' texts, times the documents in order of id."""
    features = text_features()
    pairs = F.array(*[F.struct(F.lit(i).cast("long").alias("series_id"), F.col(k).cast("double").alias("x")) for i, k in enumerate(features)])
    rows = table(spark, sf, "documents").select((F.col("doc_id") + 1).alias("t"), *[c.alias(k) for k, c in features.items()])
    return rows.select("t", F.inline(pairs)).select("series_id", "t", "x")


def chat_stats(spark: SparkSession, sf: str) -> DataFrame:
    """Messages, mean and longest length for users and assistants, conversation by conversation in order of id."""
    rows = table(spark, sf, "conversations").where("role in ('user', 'assistant')")
    per = rows.groupBy("conv_id").pivot("role", ["user", "assistant"]).agg(F.count(F.lit(1)).alias("n"), F.avg(F.length("text")).alias("mean"), F.max(F.length("text")).alias("most"))
    names = [f"{role}_{k}" for role in ("user", "assistant") for k in ("n", "mean", "most")]
    pairs = F.array(*[F.struct(F.lit(i).cast("long").alias("series_id"), F.coalesce(F.col(k), F.lit(0)).cast("double").alias("x")) for i, k in enumerate(names)])
    return numbered(per, "conv_id").select("t", F.inline(pairs)).select("series_id", "t", "x")


PANELS = {
    "nation_week": nation_week, "supplier_week": supplier_week, "brand_return": brand_return, "event_hour": event_hour,
    "embedding_stream": embedding_stream, "corpus_stats": corpus_stats, "chat_stats": chat_stats,
}


@dataclass(frozen=True)
class Step:
    """A change after time z in all members of the given groups, equal in size, of the given length."""

    z: int
    groups: tuple[int, ...]
    size: float


def support(groups: DataFrame, chosen: tuple[int, ...]) -> DataFrame:
    return groups.where(F.col("group_id").isin(*chosen)).select("series_id").distinct()


def plant(panel: DataFrame, groups: DataFrame, steps: list[Step]) -> tuple[DataFrame, DataFrame]:
    """The panel with the steps added, and the truth (cp_id, z, series_id, theta)."""
    spark = panel.sparkSession
    truth = None
    for i, step in enumerate(steps):
        members = support(groups, step.groups)
        k = members.count()
        part = members.select(F.lit(i).alias("cp_id"), F.lit(step.z).cast("long").alias("z"), "series_id", F.lit(step.size / math.sqrt(max(k, 1))).alias("theta"))
        truth = part if truth is None else truth.unionByName(part)
    if truth is None:
        return panel, spark.createDataFrame([], "cp_id int, z long, series_id long, theta double")
    per = truth.groupBy("series_id").agg(F.collect_list(F.struct("z", "theta")).alias("steps"))
    added = F.aggregate(F.coalesce("steps", F.array().cast("array<struct<z:bigint,theta:double>>")), F.lit(0.0), lambda a, s: a + F.when(F.col("t") > s["z"], s["theta"]).otherwise(0.0))
    return panel.join(per, "series_id", "left").select("series_id", "t", (F.col("x") + added).alias("x")), truth


def check(panel: DataFrame) -> dict[str, int]:
    """p and n of a panel that has every series at every time 1..n once and no null; else an error."""
    per = panel.groupBy("series_id").agg(F.count("x").alias("n"), F.count(F.lit(1)).alias("rows"), F.countDistinct("t").alias("times"), F.min("t").alias("lo"), F.max("t").alias("hi"))
    r = per.agg(F.count(F.lit(1)).alias("p"), *[f(c).alias(f"{f.__name__}_{c}") for c in ("n", "rows", "times", "lo", "hi") for f in (F.min, F.max)]).first()
    n = r["max_hi"]
    if r["p"] and not (n == r["min_n"] == r["max_rows"] == r["min_times"] == r["min_hi"] and r["min_lo"] == r["max_lo"] == 1):
        raise ValueError("a panel needs every series at every time 1..n, once, without nulls")
    return {"p": r["p"], "n": n or 0}
