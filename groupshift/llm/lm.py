"""Language-model scoring: a log-bilinear model trained in numpy by noise-contrastive estimation.

The words before a token, each weighted by its place, add up to a context vector. A token's probability is that of its class
given the context times that of the token among its class; both are products of the context vector with vectors of classes
and of words, so that a batch of tokens is a few matrix products and the probabilities are normalised exactly. Every word that occurs
least_count times has vectors of its own; all others share one token, within which each has its add-one share.

Training goes over every training text once, dealt into rounds. In a round each task starts from the same parameters and
follows the gradient over minibatches, telling tokens from drawn noise; the tasks' parameters are then averaged.
Counts of all words come from all texts.
"""

from __future__ import annotations

import math
import uuid
from collections import Counter
from dataclasses import dataclass, field
from itertools import repeat
from types import SimpleNamespace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import each_text, frugal, tokens, work_table, worker_cache

END, REST = 0, 1
#: Words longer than this are held by a digest, so that tables and dictionaries of words have rows of bounded size.
LONGEST = 64
#: Training tokens of a task and round at most for small corpora: a round's traffic is one set of parameters a task.
TASK_TOKENS = 1_000_000
#: Bytes of parameters that travel as one row.
CHUNK = 1 << 18


@dataclass
class Model:
    words: list[bytes]  # frequent words; the first n_vectors have vectors of their own
    counts: list[int]  # of those words among training tokens
    n_vectors: int
    n: int  # training tokens
    v: int  # distinct training tokens
    n_rest: int
    v_rest: int
    ends: int
    places: int  # words of context
    cls: object = None  # class of each item: END, REST, then words
    start: object = None  # first item of each class; items of a class follow each other
    params: dict = field(default_factory=dict)


def word_key(word: bytes) -> bytes:
    """The word, or for a very long one a digest that no word can be."""
    import hashlib

    return word if len(word) <= LONGEST else b"\xff" + hashlib.blake2b(word, digest_size=16).digest()


def word_counts(docs: DataFrame, held_out: Column) -> DataFrame:
    """word, c, a over all of docs (text): occurrences among texts that are not held out, and among all. Ends are not counted here."""

    def run(batches):
        import pyarrow as pa

        every, aside = Counter(), Counter()

        def flush():
            words, a = list(every), list(every.values())
            c = [n - aside[w] if w in aside else n for w, n in every.items()] if aside else a
            if words and max(map(len, words)) > LONGEST:
                words = list(map(word_key, words))
            every.clear()
            aside.clear()
            return pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), pa.array(c, pa.int64()), pa.array(a, pa.int64())], names=["word", "c", "a"])

        for batch in batches:
            for held, text in zip(batch.column("held").to_pylist(), each_text(batch.column("text")), strict=True):
                found = tokens(text)
                every.update(found)
                if held:
                    aside.update(found)
                if len(every) > 200_000:
                    yield flush()
        yield flush()

    rows = docs.select(held_out.alias("held"), "text").mapInArrow(frugal(run), "word binary, c long, a long")
    return rows.groupBy("word").agg(F.sum("c").alias("c"), F.sum("a").alias("a"))


def classes(counts, most: int):
    """(class of each item, first item of each class): END and REST alone, words by falling count, equal sums of root counts."""
    import numpy as np

    root = np.sqrt(np.asarray(counts[2:], float))
    before = np.cumsum(root) - root
    cls = np.concatenate(([0, 1], 2 + np.minimum(most - 3, (before * (most - 2) / max(root.sum(), 1.0)).astype(int))))
    cls = np.unique(cls, return_inverse=True)[1]
    return cls, np.searchsorted(cls, np.arange(cls.max() + 1))


def initial(counts, cls, start, dims: int, places: int, seed: int) -> dict:
    """Parameters that give every token its share of the training tokens, whatever the context."""
    import numpy as np

    counts = np.asarray(counts, float) + 1
    mass = np.add.reduceat(counts, start)
    draw = np.random.default_rng(seed)
    out = {
        "context": draw.normal(0, 0.1, (len(cls), dims)), "place": np.full((places, dims), 1 / math.sqrt(places)),
        "class": draw.normal(0, 0.1, (len(start), dims)), "class_bias": np.log(mass / mass.sum()),
        "word": np.zeros((len(cls), dims)), "word_bias": np.log(counts / mass[cls]),
    }
    return {k: x.astype("f4") for k, x in out.items()}


def _by_row(at, slopes):
    """The rows that occur in at, and the sum of slopes of each."""
    import numpy as np

    order = np.argsort(at.astype("u2") if at.max(initial=0) < 65536 else at, kind="stable")  # short keys are sorted by radix
    at = at[order]
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    return at[first], np.add.reduceat(slopes[order], first, axis=0)


class Trainer:
    """Follows the gradient from given parameters; energy is each row's sum of squared slopes, which sets its steps (one number a row)."""

    def __init__(self, params: dict, energy: dict, counts, cls, start, noise: int, word_noise: int, rate: float, seed: int):
        import numpy as np

        self.params, self.energy = {k: x.copy() for k, x in params.items()}, {k: x.copy() for k, x in energy.items()}
        self.cls, self.start, self.rate = cls, start, rate
        self.noise, self.word_noise = noise, word_noise
        counts = np.asarray(counts, float) + 1
        self.mass, self.sums = np.add.reduceat(counts, start), np.concatenate(([0.0], np.cumsum(counts)))
        self.share = self.mass / self.mass.sum()
        self.log_share = (np.log(self.share) + math.log(noise)).astype("f4")
        self.log_within = (np.log(counts / self.mass[cls]) + math.log(word_noise)).astype("f4")
        self.several = np.diff(np.append(start, len(cls))) > 1
        self.draw = np.random.default_rng(seed)

    def _move(self, name: str, rows, slope):
        import numpy as np

        self.energy[name][rows] += (slope * slope).mean(1) if slope.ndim == 2 else slope * slope
        step = self.rate / np.sqrt(self.energy[name][rows])
        self.params[name][rows] -= (step[:, None] if slope.ndim == 2 else step) * slope

    def minibatch(self, context, target) -> None:
        """One step on tokens target (n), after items context (places, n)."""
        import numpy as np

        p, n = self.params, len(target)
        vectors = p["context"][context]
        h = (vectors * p["place"][:, None, :]).sum(0)
        own = self.cls[target]
        # Classes: the minibatch shares its noise.
        fake = self.draw.choice(len(self.start), self.noise, p=self.share)
        own_class, fake_class = p["class"][own], p["class"][fake]
        real = 1 / (1 + np.exp(self.log_share[own] - p["class_bias"][own] - (h * own_class).sum(1))) - 1
        others = 1 / (1 + np.exp((self.log_share[fake] - p["class_bias"][fake]) - h @ fake_class.T))
        back = real[:, None] * own_class + others @ fake_class
        class_slope = np.zeros((len(self.start), h.shape[1] + 1), "f4")
        rows, slopes = _by_row(own, np.concatenate((real[:, None] * h, real[:, None]), 1))
        class_slope[rows] = slopes
        np.add.at(class_slope, fake, np.concatenate((others.T @ h, others.sum(0)[:, None]), 1))
        # Words among their classes: each token has noise of its own, drawn from its class by counts.
        at = np.flatnonzero(self.several[own])
        if len(at):
            low, mass = self.sums[self.start[own[at]]], self.mass[own[at]]
            points = low[:, None] + self.draw.random((len(at), self.word_noise)) * mass[:, None]
            drawn = np.minimum(np.searchsorted(self.sums, points.ravel(), "right") - 1, len(self.cls) - 1).reshape(points.shape)
            rows = np.concatenate((target[at, None], drawn), 1)
            words, mine = p["word"][rows], h[at]
            g = np.einsum("bkd,bd->bk", words, mine) + p["word_bias"][rows] - self.log_within[rows]
            g = 1 / (1 + np.exp(-g))
            g[:, 0] -= 1
            back[at] += np.einsum("bk,bkd->bd", g, words)
            slopes = np.concatenate(((g[:, :, None] * mine[:, None, :]).reshape(-1, h.shape[1]), g.reshape(-1, 1)), 1)
            rows, slopes = _by_row(rows.ravel(), slopes)
            self._move("word", rows, slopes[:, :-1])
            self._move("word_bias", rows, slopes[:, -1])
        every = np.arange(len(self.start))
        self._move("class", every, class_slope[:, :-1])
        self._move("class_bias", every, class_slope[:, -1])
        place_slope = (vectors * back[None]).sum(1)
        rows, slopes = _by_row(context.ravel(), (p["place"][:, None, :] * back[None]).reshape(-1, h.shape[1]))
        self._move("context", rows, slopes)
        self._move("place", np.arange(len(context)), place_slope)


def sequences(id_lists: list[list[int]], places: int):
    """(context (places, n), target (n), text (n)) of all tokens of some texts, ends included; before a text begins there are ends."""
    import numpy as np

    sizes = np.array([len(x) + 1 for x in id_lists])
    flat = np.zeros(int(sizes.sum()) + places * len(id_lists), np.int64)
    at = np.cumsum(sizes + places) - sizes
    for begin, ids in zip(at, id_lists, strict=True):
        flat[begin : begin + len(ids)] = ids
    text = np.repeat(np.arange(len(sizes)), sizes)
    positions = np.arange(int(sizes.sum())) + places * (text + 1)
    return np.stack([flat[positions - k - 1] for k in range(places)]), flat[positions], text


def _log_sum(scores):
    """The logarithm of each row's sum of exponentials."""
    import numpy as np

    with np.errstate(over="ignore"):
        sums = np.exp(scores).sum(1)
    if np.isfinite(sums).all() and (sums > 1e-25).all():
        return np.log(sums)
    top = scores.max(1, keepdims=True)
    return np.log(np.exp(scores - top).sum(1)) + top[:, 0]


def log_probabilities(model, context, target, step: int = 65536, rows_at_once: int = 4096):
    """log10 P(target | context) for tokens, by matrix products over batches; normalised over classes and within each class."""
    import numpy as np

    p, out = model.params, np.zeros(len(target))
    ends = np.append(model.start[1:], len(model.cls))
    for low in range(0, len(target), step):
        w = target[low : low + step]
        h = (p["context"][context[:, low : low + step]] * p["place"][:, None, :]).sum(0)
        own, found = model.cls[w], out[low : low + step]
        for at in range(0, len(w), rows_at_once):
            scores = h[at : at + rows_at_once] @ p["class"].T + p["class_bias"]
            hit = scores[np.arange(len(scores)), own[at : at + rows_at_once]]
            found[at : at + rows_at_once] = hit - _log_sum(scores)
        order = np.argsort(own.astype("u2"), kind="stable")
        bounds = np.searchsorted(own[order], np.arange(len(ends) + 1))
        for c in np.flatnonzero(np.diff(bounds)):
            first, last = model.start[c], ends[c]
            if last - first > 1:
                rows = order[bounds[c] : bounds[c + 1]]
                scores = h[rows] @ p["word"][first:last].T + p["word_bias"][first:last]
                hit = scores[np.arange(len(rows)), w[rows] - first]
                found[rows] += hit - _log_sum(scores)
    return out / math.log(10)


def _packed(values: dict) -> bytes:
    return b"".join(values[k].astype("f4").tobytes() for k in sorted(values))


def _unpacked(data, like: dict) -> dict:
    import numpy as np

    flat, at, out = np.frombuffer(data, "f4"), 0, {}
    for k in sorted(like):
        out[k] = flat[at : at + like[k].size].reshape(like[k].shape)
        at += like[k].size
    return out


def _round(texts: DataFrame, shared, batch_tokens: int) -> bytes | None:
    """The sum over tasks of each parameter's move times its row's energy, and of the energies; none if there are no texts.

    Each task's sums are cut into rows of CHUNK bytes, which are added up as they arrive, a few at a time.
    """

    def run(batches):
        import numpy as np
        import pyarrow as pa

        s = shared.value
        index = {w: i + 2 for i, w in enumerate(s.words)}
        trainer, held, size = Trainer(s.params, s.energy, s.counts, s.cls, s.start, s.noise, s.word_noise, s.rate, s.seed), [], 0

        def learn():
            context, target, _ = sequences(held, s.places)
            order = trainer.draw.permutation(len(target))
            for at in range(0, len(order), batch_tokens):
                some = order[at : at + batch_tokens]
                trainer.minibatch(context[:, some], target[some])

        seen = False
        for batch in batches:
            for text in each_text(batch.column("text")):
                held.append([index.get(w, REST) for w in tokens(text)])
                size += len(held[-1]) + 1
                seen = True
                if size >= 16 * batch_tokens:
                    learn()
                    held, size = [], 0
        if held:
            learn()
        if not seen:
            return
        gained = {k: trainer.energy[k] - s.energy[k] for k in s.energy}
        moved = {k: (trainer.params[k] - s.params[k]) * gained[k].reshape((-1,) + (1,) * (s.params[k].ndim - 1)) for k in s.params}
        data = _packed(moved) + _packed(gained)
        parts = [data[at : at + CHUNK] for at in range(0, len(data), CHUNK)]
        for i, part in enumerate(parts):
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([part], pa.binary())], names=["i", "x"])

    def add(batches):
        import numpy as np
        import pyarrow as pa

        sums = {}
        for batch in batches:
            for i, x in zip(batch.column("i").to_pylist(), batch.column("x"), strict=True):
                x = np.frombuffer(x.as_buffer(), "f4")
                sums[i] = sums[i] + x if i in sums else x.astype("f8")
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.astype("f4").tobytes() for x in sums.values()], pa.binary())], names=["i", "x"])

    rows = texts.select("text").mapInArrow(frugal(run), "i int, x binary").repartition("i").mapInArrow(add, "i int, x binary")
    parts = sorted((r["i"], bytes(r["x"])) for r in rows.collect())
    return b"".join(x for _, x in parts) if parts else None


def train(
    texts: DataFrame, words: list[bytes], counts: list[int], dims: int, places: int, most_classes: int, rounds: int,
    batch_tokens: int = 4096, noise: int = 16, word_noise: int = 2, rate: float = 0.1, seed: int = 7,
):
    """(classes, starts, parameters) after one pass over texts (doc_id, text), in rounds; counts are those of END, REST, and words.

    The driver and every task hold one set of parameters, 2 * dims numbers for each word and class.
    """
    import numpy as np

    cls, start = classes(counts, most_classes)
    params = initial(counts, cls, start, dims, places, seed)
    energy = {k: np.full(len(x), 1e-2, "f4") for k, x in params.items()}
    spark, n = texts.sparkSession, sum(counts)
    tasks = max(1, math.ceil(n / TASK_TOKENS))
    turn = F.pmod(F.xxhash64("doc_id", F.length("text")), F.lit(rounds))
    for r in range(rounds):
        sent = SimpleNamespace(words=words, counts=counts, cls=cls, start=start, params=params, energy=energy, places=places, noise=noise, word_noise=word_noise, rate=rate, seed=seed + r)
        shared = spark.sparkContext.broadcast(sent)
        data = _round(texts.where(turn == r).coalesce(tasks), shared, batch_tokens)
        if data is not None:
            size = 4 * sum(x.size for x in params.values())
            moved, gained = _unpacked(data[:size], params), _unpacked(data[size:], energy)
            for k, x in params.items():
                # Tasks that saw more of a row weigh more in its average.
                weight = gained[k].reshape((-1,) + (1,) * (x.ndim - 1))
                params[k] = (x + np.where(weight > 0, moved[k] / np.where(weight > 0, weight, 1), 0)).astype("f4")
                energy[k] = energy[k] + gained[k]
        shared.unpersist()
    return cls, start, params


def learn(
    docs: DataFrame, held_out: Column, least_count: int = 8, most_vectors: int = 16_384, hot_words: int = 262_144, dims: int = 16, places: int = 3, most_classes: int = 128, rounds: int = 3,
) -> tuple[Model, DataFrame]:
    """The model of those of docs (doc_id, text) that are not held out, and the table of the counts of all words of docs.

    The driver and each worker hold hot_words words of at most LONGEST bytes, and the parameters of at most most_vectors words that
    occur least_count times; all other counts stay in the table. Null texts count as empty. Without training texts every token is unknown.
    """
    docs = docs.select("doc_id", "text", held_out.alias("held"))
    counts = work_table(word_counts(docs, F.col("held")), "word_counts")
    texts = docs.where("not held")
    sums = counts.agg(F.sum("c").alias("n"), F.sum((F.col("c") > 0).cast("long")).alias("v")).first()
    ends, n_words, v_words = texts.count(), sums["n"] or 0, sums["v"] or 0
    # Words frequent in all texts are held by the workers, so that no word of the table that is joined later is frequent.
    least, held = 0, 0
    for row in counts.groupBy("a").agg(F.count(F.lit(1)).alias("words")).orderBy(F.desc("a")).toLocalIterator():
        if held + row["words"] > hot_words:
            least = row["a"] + 1
            break
        held += row["words"]
    hot = sorted((-r["c"], bytes(r["word"])) for r in counts.where(F.col("a") >= least).collect())
    words, own = [w for _, w in hot], [-c for c, _ in hot]
    k = sum(c >= least_count for c in own[:most_vectors])
    n_rest = n_words - sum(own[:k])
    cls, start, params = train(texts, words[:k], [ends, n_rest, *own[:k]], dims, places, most_classes, rounds)
    return Model(words, own, k, n_words + ends, v_words + (ends > 0), n_rest, v_words - k, ends, places, cls, start, params), counts


def score_documents(docs: DataFrame, model: Model, counts: DataFrame, held_out: Column) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row of docs; whole texts are scored.

    Null texts count as empty: one end. Rows are scored each by itself. Frequent words are looked up in each worker;
    a text's other words are joined with the table of counts by word, none of which is frequent in the texts it was made of.
    """
    shared = docs.sparkSession.sparkContext.broadcast(SimpleNamespace(**vars(model)))  # no class, which executors need not have
    rows = docs.select("doc_id", held_out.alias("held_out"), "text").withColumn("uid", F.monotonically_increasing_id())
    name = uuid.uuid4().hex

    def run(batches):
        import numpy as np
        import pyarrow as pa

        model = shared.value
        index = worker_cache("lm", lambda: {w: i for i, w in enumerate(model.words)}, name)
        counted = np.array(model.counts, np.int64)
        logs = np.log10(counted + 1.0)
        in_rest = np.where(np.arange(len(logs)) < model.n_vectors, 0.0, logs - math.log10(model.n_rest + model.v_rest + 1))

        def measured(cut, texts):
            out, items = {"n": [], "known": [], "base": [], "model": [], "tail": []}, []
            for text in texts:
                words = tokens(text)
                ids = np.fromiter(map(index.get, words, repeat(-1)), np.int64, len(words))
                hot = ids[ids >= 0]
                items.append(np.where((ids >= 0) & (ids < model.n_vectors), ids + 2, REST))
                out["n"].append(len(words) + 1)
                out["known"].append(int((counted[hot] > 0).sum()) + (model.ends > 0))
                out["base"].append(logs[hot].sum() + math.log10(model.ends + 1))
                out["model"].append(in_rest[hot].sum())
                out["tail"].append([word_key(words[i]) for i in np.flatnonzero(ids < 0)])
            context, target, text = sequences(items, model.places)
            out["model"] = np.array(out["model"]) + np.bincount(text, log_probabilities(model, context, target), len(items))
            made = [pa.array(out["n"], pa.int64()), pa.array(out["known"], pa.int64()), pa.array(out["base"], pa.float64()), pa.array(out["model"], pa.float64()), pa.array(out["tail"], pa.list_(pa.binary()))]
            return pa.RecordBatch.from_arrays([*cut, *made], names=["uid", "doc_id", "held_out", *out])

        for batch in batches:
            for at in range(0, len(batch), 256):
                yield measured([batch.column(c).slice(at, 256) for c in ("uid", "doc_id", "held_out")], batch.column("text").slice(at, 256).to_pylist())

    fields = "uid long, doc_id long, held_out boolean, n long, known long, base double, model double, tail array<binary>"
    part = work_table(rows.select("uid", "doc_id", "held_out", "text").mapInArrow(frugal(run), fields), "scores")
    tail = part.select("uid", F.explode("tail").alias("w"))
    known = tail.join(counts.select(F.col("word"), "c"), F.col("w") == F.col("word"), "left").select("uid", F.coalesce("c", F.lit(0)).alias("c"))
    sums = known.groupBy(F.col("uid").alias("tuid")).agg(
        F.sum(F.log10(F.col("c") + 1)).alias("t_log"), F.count(F.lit(1)).alias("t_n"), F.sum((F.col("c") > 0).cast("long")).alias("t_known")
    )
    zero = lambda c: F.coalesce(F.col(c), F.lit(0))
    rest = math.log10(model.n_rest + model.v_rest + 1)
    return part.join(sums, F.col("uid") == F.col("tuid"), "left").select(
        "doc_id", "held_out", F.col("n").alias("n_tokens"), (F.col("known") + zero("t_known")).cast("long").alias("n_known"),
        F.lit(model.n).cast("long").alias("train_tokens"),
        (F.col("base") + zero("t_log") - F.col("n") * math.log10(model.n + model.v + 1)).alias("base_score"),
        (F.col("model") + zero("t_log") - zero("t_n") * rest).alias("score"),
    )
