"""Secret scanning with an inverted index of trigrams; DataFrame operations only.

On the driver each rule's pattern is parsed and the trigrams that any match must contain are derived, as a Boolean
query. The index has postings (trigram, document) for the trigrams that some query names. Postings are
intersected by the queries, and only the candidates' texts are matched. A rule whose pattern has no mandatory
trigram is matched against every text.
"""

from __future__ import annotations

import re._constants as sre
import re._parser as sre_parser
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import work_table

BROADCAST_ROWS = 1_000_000


@dataclass(frozen=True)
class Rule:
    """kind; a pattern that Java and Python read alike; the group whose length in characters is held against least."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1


#: The base kinds, in the order in which spans of one start are listed.
BASE = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20),
    Rule("hex", r"[0-9a-f]{24,}", 0, 24),
)
#: Further kinds that this scanner adds.
EXTRA = (
    Rule("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{30,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("bearer", r"(?i:authorization:\x20*bearer\x20+)([A-Za-z0-9+/_.=~-]+)", 1, 16),
)

#: A query is True (no mandatory trigram), a trigram, or ("and" | "or", queries).
Query = bool | str | tuple

#: Up to so many strings are followed; beyond them the pattern counts as opaque there.
_MOST_STRINGS = 64


def _needs(query: Query) -> frozenset:
    """The parts that all must hold."""
    return frozenset(query[1] if isinstance(query, tuple) and query[0] == "and" else [query])


def _join(op: str, parts) -> Query:
    """and / or of queries, with True taken out; equal parts count once, and parts that others imply are left out."""
    flat = []
    for part in parts:
        flat += part[1] if isinstance(part, tuple) and part[0] == op else [part]
    if op == "or" and (True in flat or not flat):
        return True
    flat = list(dict.fromkeys(x for x in flat if x is not True))
    if op == "or":
        # A branch that asks for all that another asks for, and more, adds nothing.
        flat = [x for x in flat if not any(_needs(y) < _needs(x) for y in flat)]
    else:
        sure = set(flat)
        flat = [x for x in flat if not (isinstance(x, tuple) and any(_needs(y) <= sure for y in x[1]))]
    if not flat:
        return True
    return flat[0] if len(flat) == 1 else (op, tuple(flat))


def _letters(members) -> set[str] | None:
    """The characters of a class, in lower case, if they are few; None for negated and named classes."""
    out: set[str] = set()
    for kind, value in members:
        if kind is sre.LITERAL:
            out.add(chr(value).lower())
        elif kind is sre.RANGE and value[1] - value[0] < 4 * _MOST_STRINGS:
            out |= {chr(c).lower() for c in range(value[0], value[1] + 1)}
        else:
            return None
    return out if len(out) <= _MOST_STRINGS else None


def _grams(strings: set[str]) -> Query:
    """What a text that holds one of the strings must contain."""
    return _join("or", [_join("and", [s[i : i + 3] for i in range(len(s) - 2)] or [True]) for s in sorted(strings)])


def _walk(items) -> tuple[set[str] | None, Query]:
    """(the strings that the items can match, if few; else None), and the query that any match satisfies."""
    run, exact, found = {""}, True, []

    def close():
        nonlocal run, exact
        found.append(_grams(run))
        run, exact = {""}, False

    for op, value in items:
        options, query = None, True
        if op is sre.LITERAL:
            options = {chr(value).lower()}
        elif op is sre.IN:
            options = _letters(value)
        elif op is sre.SUBPATTERN:
            options, query = _walk(value[3])
        elif op is sre.BRANCH:
            walked = [_walk(x) for x in value[1]]
            if all(strings is not None for strings, _ in walked):
                options = set().union(*(strings for strings, _ in walked))
            query = _join("or", [q for _, q in walked])
        elif op in (sre.MAX_REPEAT, sre.MIN_REPEAT):
            low, high, inner = value
            strings, inner_query = _walk(inner)
            if strings is not None and (low, high) == (0, 1):
                options = strings | {""}
            elif strings is not None and low == high and low <= 8 and len(strings) == 1:
                options = {next(iter(strings)) * low}
            elif low >= 1:
                query = inner_query
        elif op is sre.AT:
            options = {""}
        if options is not None and len(run) * len(options) <= _MOST_STRINGS:
            run = {a + b for a in run for b in options}
            continue
        close()
        found.append(query if options is None else _grams(options))
    strings = run if exact else None
    found.append(_grams(run))
    return strings, _join("and", found)


def trigram_query(pattern: str) -> Query:
    """The Boolean query of trigrams, in lower case, that every text with a match of pattern satisfies."""
    return _walk(sre_parser.parse(pattern))[1]


def trigrams_of(query: Query) -> set[str]:
    if isinstance(query, tuple):
        return set().union(*map(trigrams_of, query[1]))
    return {query} if isinstance(query, str) else set()


def _holds(query: Query, has) -> Column:
    if isinstance(query, str):
        return has(query)
    parts = [_holds(x, has) for x in query[1]]
    out = parts[0]
    for part in parts[1:]:
        out = out & part if query[0] == "and" else out | part
    return out


def build_index(docs: DataFrame, grams: list[str]) -> DataFrame:
    """The inverted index: postings (gram, doc_id) of the given trigrams, over texts in lower case."""
    low = docs.select("doc_id", F.lower(F.coalesce("text", F.lit(""))).alias("low"))
    present = F.filter(F.array(*map(F.lit, grams)), lambda g: F.contains(F.col("low"), g))
    return low.select("doc_id", F.explode(present).alias("gram")).select("gram", "doc_id")


def candidates(postings: DataFrame, queries: dict[str, Query], grams: list[str]) -> DataFrame:
    """doc_id and, for each query's name, whether the document's postings satisfy it; documents that satisfy none are left out.

    Each document's postings meet as bits, ored before the exchange; 62 trigrams fill a word.
    """
    at = {g: divmod(i, 62) for i, g in enumerate(grams)}
    places = F.create_map(*[F.lit(x) for g, i in zip(grams, range(len(grams)), strict=True) for x in (g, i)])
    numbered = postings.withColumn("i", places[F.col("gram")])
    words = [
        F.bit_or(F.when(F.expr(f"i div 62 = {k}"), F.expr("shiftleft(1L, i % 62)")).otherwise(F.lit(0).cast("long"))).alias(f"w{k}")
        for k in range((len(grams) + 61) // 62)
    ]
    has = lambda g: F.col(f"w{at[g][0]}").bitwiseAND(F.lit(1 << at[g][1])) != 0
    flags = numbered.groupBy("doc_id").agg(*words).select("doc_id", *[_holds(q, has).alias(f"may_{k}") for k, q in queries.items()])
    any_of = F.lit(False)
    for k in queries:
        any_of = any_of | F.col(f"may_{k}")
    return flags.where(any_of)


def _starts(gaps: Column, lengths: Column) -> Column:
    """Where matches start: match i follows gap i. Sums go over blocks of 128 first, so many matches take few steps."""
    add = lambda a, b: a + b
    total = lambda x: F.aggregate(x, F.lit(0), add)
    n, size = F.size(lengths), 128
    steps = F.zip_with(F.slice(gaps, 1, n), lengths, add)
    blocks = F.transform(F.sequence(F.lit(0), F.floor((n - 1) / size).cast("int")), lambda b: total(F.slice(steps, b * size + 1, size)))
    numbers = F.sequence(F.lit(0), n - 1)
    start = lambda i: (
        total(F.slice(blocks, F.lit(1), F.floor(i / size).cast("int")))
        + total(F.slice(steps, F.floor(i / size).cast("int") * size + 1, i % size))
        + F.element_at(gaps, i + 1)
    )
    return F.transform(numbers, start)


def _spans(rank: int, rule: Rule) -> Column:
    """The spans of one rule's matches in column text, whose texts are in column m_<kind>."""
    matches = F.col(f"m_{rule.kind}")
    lengths = F.transform(matches, F.char_length)
    gaps = F.transform(F.split("text", rule.pattern, -1), F.char_length)
    held = F.transform(F.regexp_extract_all("text", F.lit(rule.pattern), F.lit(rule.group)), F.char_length) if rule.group else lengths
    found = F.arrays_zip(_starts(gaps, lengths).alias("start"), lengths.alias("length"), held.alias("held"))

    def span(x):
        end = (x["start"] + x["length"]).cast("long")
        return F.struct(x["start"].cast("long").alias("start"), F.lit(rank).alias("rank"), end.alias("end"), F.lit(rule.kind).alias("kind"))

    made = F.transform(F.filter(found, lambda x: x["held"] >= rule.least), span)
    none = F.array().cast("array<struct<start:bigint,rank:int,end:bigint,kind:string>>")
    return F.when(F.size(matches) > 0, made).otherwise(none)


def find_secrets(
    docs: DataFrame, rules: tuple[Rule, ...] = BASE + EXTRA, broadcast_rows: int = BROADCAST_ROWS
) -> DataFrame:
    """doc_id and spans, an array of (start, rank, end, kind) in that order, for every row of docs (doc_id, text).

    Matches are leftmost and don't overlap within a kind; those whose group is too short are dropped afterwards.
    start and end count code points, end exclusive. A null text counts as empty and has no spans. Rows with the same
    id are matched each by itself. Texts are matched whole. An empty table gives no rows.
    """
    queries = {r.kind: trigram_query(r.pattern) for r in rules}
    indexed = {k: q for k, q in queries.items() if q is not True}
    grams = sorted(set().union(*map(trigrams_of, indexed.values())) if indexed else set())
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    if indexed:
        postings = work_table(build_index(docs, grams), "postings")
        may = work_table(candidates(postings, indexed, grams), "candidates").withColumnRenamed("doc_id", "cid")
        if may.count() <= broadcast_rows:
            may = F.broadcast(may)
        rows = rows.join(may, rows["doc_id"].eqNullSafe(may["cid"]), "left").drop("cid")
    none = F.array().cast("array<string>")
    for r in rules:
        hit = F.regexp_extract_all("text", F.lit(r.pattern), F.lit(0))
        rows = rows.withColumn(f"m_{r.kind}", F.when(F.coalesce(F.col(f"may_{r.kind}"), F.lit(False)), hit).otherwise(none) if r.kind in indexed else hit)
    spans = [_spans(rank, r) for rank, r in enumerate(rules)]
    return rows.select("doc_id", F.array_sort(F.concat(*spans)).alias("spans"))


def listed(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"], x["end"])), ",")


def count_of(kind: str) -> Column:
    """How many of the row's spans are of a kind."""
    return F.size(F.filter("spans", lambda x: x["kind"] == kind)).cast("long")
