"""Toxicity: a weighted lexicon matched by Aho-Corasick on folded text, normalised by length, with exception phrases.

The lexicon starts from a short list of insults and gains the word beginnings that mark toxic texts among labelled
rows. Hits count by weight and against the text's length, and a logistic curve fitted to the same rows gives the score.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from dataclasses import dataclass, field
from types import SimpleNamespace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import each_text, frugal, worker_cache

# Characters that look like a Latin letter, digits and signs that stand for one, and what is invisible.
HOMOGLYPHS = dict(zip("аеіјорсухѕԁһӏкмтвнαεικνορτυχ", "aeijopcyxsdhlkmtbhaeiknoptux", strict=True))
DIGITS = dict(zip("013457@$", "oieastas", strict=True))
INVISIBLE = "​‌‍⁠﻿­"
#: Insults that count before anything is learned, and phrases in which they are none.
SEED = ("idiot", "moron", "stupid", "pathetic", "worthless", "disgusting", "loser", "scum", "trash", "clown")
EXCEPTIONS = ("trash can", "trash bin", "take out the trash", "clown fish", "clownfish", "circus clown", "pond scum", "trash collection")
SEED_WEIGHT = 4.0


@dataclass
class Model:
    weights: dict[str, float] = field(default_factory=lambda: dict.fromkeys(SEED, SEED_WEIGHT))
    curve: tuple[float, ...] = (-4.0, 2.0, 1.0)  # of 1, log(1 + weight of hits), log(1 + 100 * weight of hits / words)
    exceptions: tuple[str, ...] = EXCEPTIONS


def _plain(model: Model) -> SimpleNamespace:
    """The model without its class, which executors need not have."""
    return SimpleNamespace(**vars(model))


def _fold_table() -> dict:
    table = {}
    for c in map(chr, range(0x250)):
        if not c.isalnum():
            table[ord(c)] = " "
    for c in "‐‑‒–—‘’“”•…　":
        table[ord(c)] = " "
    table |= {ord(a): b for a, b in (HOMOGLYPHS | DIGITS).items()}
    table |= {0xFF01 + i: chr(0x21 + i).lower() for i in range(94) if chr(0x21 + i).isalpha()}
    table |= dict.fromkeys(map(ord, INVISIBLE))
    return table


_SPELT = re.compile(r"(?<=\s)(?:\w ){3,}\w(?=\s)")
_SPACES = re.compile(r"\s+")


def fold(text: str) -> str:
    """Lower case, look-alikes and digits as letters, anything else as one space, letters spelt apart together; spaces around."""
    low = text.lower().translate(worker_cache("toxicity_fold", _fold_table))
    low = _SPACES.sub(" ", f" {low} ")
    return _SPELT.sub(lambda m: m[0].replace(" ", ""), low)


def automaton(model: Model):
    """Keys begin with the space before a word, so that a key matches at word starts only. Value: (length, weight, is exception)."""
    import ahocorasick

    found = ahocorasick.Automaton()
    for stem, weight in model.weights.items():
        found.add_word(" " + stem, (len(stem) + 1, weight, False))
    for phrase in model.exceptions:
        found.add_word(" " + phrase, (len(phrase) + 1, 0.0, True))
    found.make_automaton()
    return found


def features(text: str, machine) -> tuple[float, float, float]:
    """1, log(1 + w), log(1 + 100 w / words) for the weight w of the hits; each word counts once, by its best key."""
    low = fold(text)
    best: dict[int, float] = {}
    excused: list[tuple[int, int]] = []
    for end, (length, weight, exception) in machine.iter(low):
        begin = end - length + 1
        if exception:
            excused.append((begin, end))
        else:
            best[begin] = max(weight, best.get(begin, 0.0))
    for begin, end in excused:
        for at in [at for at in best if begin <= at <= end]:
            del best[at]
    total = sum(best.values())
    return 1.0, math.log1p(total), math.log1p(100 * total / max(1, low.count(" ") - 1))


def score(text: str, machine, curve) -> float:
    z = sum(a * b for a, b in zip(features(text, machine), curve, strict=True))
    return 1 / (1 + math.exp(-max(-60.0, min(60.0, z))))


def _stems(word: str, shortest: int = 4, longest: int = 9):
    for n in range(shortest, min(len(word), longest) + 1):
        yield word[:n]


def learn(
    docs: DataFrame, labels: DataFrame, held_out=None, most_docs: int = 12_000, most_stems: int = 4_000, least_share: float = 0.015, least_ratio: float = 2.0
) -> Model:
    """Learns weights and curve from labelled rows (doc_id, toxic) that held_out(doc_id column) does not mark.

    At most most_docs labelled rows are used, chosen by hash; whole texts are read. Texts of one label that are equal when
    folded count once, so that a group of copies is not taken for a pattern; all others count. A word beginning gets a weight when it occurs in at
    least least_share of the toxic texts and its share of words is exp(least_ratio) times that among clean ones. Without
    labels of both kinds the model is the list of insults alone. Null texts count as empty, null labels are left out.
    """
    import numpy as np

    known = labels.select(F.col("doc_id").alias("lid"), F.col("toxic").cast("int").alias("y")).where("lid is not null and y is not null")
    if held_out is not None:
        known = known.where(~held_out(F.col("lid")))
    known = known.groupBy("lid").agg(F.max("y").alias("y")).orderBy(F.xxhash64("lid"), "lid").limit(most_docs)
    sample = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(known), F.col("doc_id") == F.col("lid"))

    def folded(batches):
        import pyarrow as pa

        for batch in batches:
            lows = [fold(t) for t in each_text(batch.column("text"))]
            yield pa.RecordBatch.from_arrays(
                [pa.array([hashlib.sha256(x.encode(errors="surrogatepass")).digest() for x in lows], pa.binary()), batch.column("y"), pa.array(lows, pa.string())], names=["digest", "y", "low"]
            )

    texts = sample.select("doc_id", "text", "y").mapInArrow(frugal(folded), "digest binary, y int, low string")
    # One of equal texts of a label; most_docs texts at most, so they are small beside any task.
    unique = texts.groupBy("y", "digest").agg(F.first("low").alias("low")).persist()
    sums = {r["y"]: r for r in unique.groupBy("y").agg(F.count(F.lit(1)).alias("n"), F.sum(F.size(F.split("low", " ")) - 2).alias("words")).collect()}
    model = Model()
    if not (sums.get(0) and sums.get(1)):
        unique.unpersist()
        return model

    def counts(batches):
        import pyarrow as pa

        schema = pa.schema([("stem", pa.string()), ("y", pa.int32()), ("docs", pa.int64()), ("uses", pa.int64())])
        docs_of, uses = Counter(), Counter()

        def flush():
            batch = pa.RecordBatch.from_arrays(
                [pa.array(x, t) for x, t in zip(([k[0] for k in uses], [k[1] for k in uses], [docs_of[k] for k in uses], list(uses.values())), schema.types, strict=True)], schema=schema
            )
            docs_of.clear()
            uses.clear()
            return batch

        for batch in batches:
            for low, y in zip(batch.column("low").to_pylist(), batch.column("y").to_pylist(), strict=True):
                own = Counter(stem for word in low.split() for stem in _stems(word))
                uses.update({(s, y): n for s, n in own.items()})
                docs_of.update((s, y) for s in own)
                if len(uses) > 50_000:
                    yield flush()
        yield flush()

    # Only beginnings that occur in enough toxic texts leave the executors.
    toxic, clean = sums[1], sums[0]
    stems = unique.select("low", "y").mapInArrow(frugal(counts), "stem string, y int, docs long, uses long")
    per = stems.groupBy("stem").agg(
        F.sum(F.when(F.col("y") == 1, F.col("docs")).otherwise(0)).alias("docs1"), F.sum(F.when(F.col("y") == 1, F.col("uses")).otherwise(0)).alias("uses1"),
        F.sum(F.when(F.col("y") == 0, F.col("uses")).otherwise(0)).alias("uses0"),
    )
    ratio = F.log((F.col("uses1") + 0.5) / toxic["words"]) - F.log((F.col("uses0") + 0.5) / clean["words"])
    kept = per.withColumn("ratio", ratio).where((F.col("docs1") >= max(4, least_share * toxic["n"])) & (F.col("ratio") >= least_ratio))
    chosen = kept.orderBy(F.desc(F.col("docs1") * F.col("ratio")), "stem").limit(most_stems).collect()
    for r in sorted(chosen, key=lambda r: len(r["stem"])):
        shorter = max((model.weights[s] for s in _stems(r["stem"]) if s in model.weights), default=0.0)
        if r["ratio"] > shorter + 0.25:  # a longer beginning only where it says more
            model.weights[r["stem"]] = min(float(r["ratio"]), 8.0)
    shared = docs.sparkSession.sparkContext.broadcast(_plain(model))

    def measured(batches):
        import pyarrow as pa

        machine = automaton(shared.value)
        for batch in batches:
            rows = [features(x, machine) for x in batch.column("low").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("y"), pa.array([r[1] for r in rows], pa.float64()), pa.array([r[2] for r in rows], pa.float64())], names=["y", "a", "b"])

    points = unique.select("low", "y").mapInArrow(measured, "y int, a double, b double").collect()  # most_docs rows at most
    unique.unpersist()
    points = sorted(tuple(r) for r in points)
    y = np.array([r[0] for r in points], float)
    x = np.array([(1.0, r[1], r[2]) for r in points])
    w = np.zeros(3)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        gradient = x.T @ (p - y) + 1e-2 * w
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(3), gradient)
        w -= step
        if abs(step).max() < 1e-9:
            break
    model.curve = tuple(map(float, w))
    return model


def score_documents(docs: DataFrame, model: Model, threshold: float = 0.7, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns, score and predicted (1 where score >= threshold) for every row; whole texts are scored.

    Null texts count as empty; an empty text has the score of a text without hits. Rows are scored each by itself.
    """
    shared = docs.sparkSession.sparkContext.broadcast(_plain(model))
    rows = docs.select(*carry, F.coalesce("text", F.lit("")).alias("__text"))

    def run(batches):
        import pyarrow as pa

        machine = automaton(shared.value)
        for batch in batches:
            scores = pa.array([score(t, machine, shared.value.curve) for t in each_text(batch.column("__text"))], pa.float64())
            keep = [batch.column(c) for c in carry]
            yield pa.RecordBatch.from_arrays([*keep, scores], names=[*carry, "score"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields if f.name in carry)
    return rows.mapInArrow(frugal(run), f"{fields}, score double").withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def clean_documents(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """The rows of docs whose score is below threshold, with all their columns; each row is judged by itself."""
    shared = docs.sparkSession.sparkContext.broadcast(_plain(model))
    at = docs.columns.index("text")

    def run(batches):
        import pyarrow as pa

        machine = automaton(shared.value)
        for batch in batches:
            low = [score(t, machine, shared.value.curve) < threshold for t in each_text(batch.column(at))]
            yield batch.filter(pa.array(low, pa.bool_()))

    return docs.mapInArrow(frugal(run), docs.schema)
