"""Bounded-space online packing of token sequences.

Each partition keeps a fixed number of open windows. A document's whole windows leave at once; its rest goes to
the open window with the least room that holds it. When none does, the fullest window is emitted: a rest
tops it up first if that leaves less padding than it costs a cut. What partitions leave open is merged at the end.
"""

from __future__ import annotations

import zlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import frugal, work_table, worker_cache

PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, ids array<int>"
#: Texts of these characters only: both libraries split them alike, which the tests hold for every one of them.
PLAIN_UP_TO = 0x24F


def _first_number(batch, base: int) -> int | None:
    """The first sequence number of the partition that a batch lies in; one task may run several partitions."""
    return base | batch.column("place")[0].as_py() << 40 if len(batch) else None


def byte_bpe(json_path: str, ranks_path: str | None = None):
    """encode(texts) -> lists of ids, of the vocabulary in json_path; special tokens' strings are ordinary text.

    ranks_path may name the same vocabulary as ranks. It then serves the texts of plain characters, several
    times faster and with the same ids.
    """
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    full = Tokenizer.from_file(json_path)
    full.encode_special_tokens = True
    slow = lambda texts: [e.ids for e in full.encode_batch_fast(texts, add_special_tokens=False)]
    if ranks_path is None:
        return slow
    import base64
    import re

    import tiktoken
    from public_tokenizers import PATTERN

    with open(ranks_path, "rb") as file:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, file)}
    fast = tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
    odd = re.compile(f"[^\\x09-\\x0d\\x20-\\x7e\\xa0-{chr(PLAIN_UP_TO)}]").search

    def encode(texts):
        out = [None if odd(t) else fast.encode_ordinary(t) for t in texts]
        rest = [i for i, ids in enumerate(out) if ids is None]
        for i, ids in zip(rest, slow([texts[i] for i in rest]) if rest else [], strict=True):
            out[i] = ids
        return out

    return encode


class Windows:
    """The open windows of one partition. A window is a list of pieces (doc_id, start, ids, doc_tokens)."""

    def __init__(self, size: int, count: int, least_cut: int):
        self.size, self.count, self.least_cut = size, count, least_cut
        self.open: list[tuple[int, list]] = []  # (tokens in it, pieces)

    def add(self, doc_id, ids, doc_tokens: int, start: int = 0):
        """Places a document's ids from start on; yields the windows that are emitted."""
        n, size = len(ids), self.size
        at = 0
        while n - at >= size:
            yield [(doc_id, start + at, ids[at : at + size], doc_tokens)]
            at += size
        if at < n:
            yield from self._rest(doc_id, ids[at:], doc_tokens, start + at)

    def _rest(self, doc_id, ids, doc_tokens, start):
        n = len(ids)
        fit = max((w for w in self.open if w[0] + n <= self.size), key=lambda w: w[0], default=None)
        if fit is None and len(self.open) >= self.count:
            full = max(self.open, key=lambda w: w[0])
            self.open.remove(full)
            room = self.size - full[0]
            if room >= self.least_cut:
                full[1].append((doc_id, start, ids[:room], doc_tokens))
                ids, start, n = ids[room:], start + room, n - room
            yield full[1]
            fit = max((w for w in self.open if w[0] + n <= self.size), key=lambda w: w[0], default=None)
        if fit is not None:
            self.open.remove(fit)
            fit[1].append((doc_id, start, ids, doc_tokens))
            if fit[0] + n == self.size:
                yield fit[1]
            else:
                self.open.append((fit[0] + n, fit[1]))
        else:
            self.open.append((n, [(doc_id, start, ids, doc_tokens)]))


def _batch(rows: list[tuple], emit_ids: bool):
    import numpy as np
    import pyarrow as pa

    cols = list(zip(*rows, strict=True)) if rows else [()] * 8
    crc = [zlib.crc32(np.asarray(ids, dtype="<u4").tobytes()) for ids in cols[2]]
    kept = [ids if emit_ids or seq is None else None for ids, seq in zip(cols[2], cols[4], strict=True)]
    long = pa.int64()
    return pa.RecordBatch.from_arrays(
        [
            pa.array(cols[0], long), pa.array(cols[1], long), pa.array([len(x) for x in cols[2]], long), pa.array(crc, long),
            pa.array(cols[3], long), pa.array(cols[4], long), pa.array(cols[5], long), pa.array(kept, pa.list_(pa.int32())),
        ],
        names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "ids"],
    )


def _laid_out(window: list, sequence_id: int | None) -> list[tuple]:
    out, offset = [], 0
    for doc_id, start, ids, doc_tokens in window:
        out.append((doc_id, start, ids, doc_tokens, sequence_id, offset if sequence_id is not None else None))
        offset += len(ids)
    return out


def pack(
    docs: DataFrame,
    json_path: str,
    ranks_path: str | None = None,
    size: int = 1024,
    open_windows: int = 64,
    least_cut: int = 24,
    end_id: int = 0,
    merge_tokens: int = 4_000_000,
    emit_ids: bool = True,
) -> DataFrame:
    """One row for each piece of a document's ids (those of its text, then end_id), with its place in a sequence.

    Every id lies in one piece, sequences have at most size ids, pieces follow each other without gaps. Null texts
    count as empty: a lone end_id. Rows with the same id are packed each by itself. An empty table gives no rows.
    ids is null unless emit_ids. A partition holds open_windows windows of size ids and one batch of texts.
    Leftovers are dealt into groups of about merge_tokens ids, each filled without a gap, so each group leaves one
    sequence short of size at most.
    """
    import os

    stamp = tuple((p, os.path.getsize(p)) for p in (json_path, ranks_path) if p)

    def first(batches):
        encode = worker_cache("byte_bpe", lambda: byte_bpe(json_path, ranks_path), stamp)
        windows, number = Windows(size, open_windows, least_cut), None
        for batch in batches:
            number = _first_number(batch, 0) if number is None else number
            ids, texts = batch.column("doc_id").to_pylist(), batch.column("text")
            for at in range(0, len(ids), 256):
                rows = []
                some = [t or "" for t in texts.slice(at, 256).to_pylist()]
                for doc_id, found in zip(ids[at : at + 256], encode(some), strict=True):
                    found.append(end_id)
                    for window in windows.add(doc_id, found, len(found)):
                        rows += _laid_out(window, number)
                        number += 1
                yield _batch(rows, emit_ids)
        left = [row for _, window in windows.open for row in _laid_out(window, None)]
        for at in range(0, len(left), 4096):
            yield _batch(left[at : at + 4096], emit_ids)

    placed = work_table(docs.select("doc_id", "text", F.spark_partition_id().alias("place")).mapInArrow(frugal(first), PIECE), "pieces")
    left = placed.where("sequence_id is null")
    total = left.agg(F.sum("length")).first()[0] or 0
    groups = -(-total // merge_tokens)
    if not groups:
        return placed

    def merge(batches):
        # The windows here are filled to the brim: one is open, and what does not fit in it is cut.
        number, window, held = None, [], 0
        for batch in batches:
            number = _first_number(batch, 1 << 62) if number is None else number
            rows = []
            cols = [batch.column(c).to_pylist() for c in ("doc_id", "start", "ids", "doc_tokens")]
            for doc_id, start, ids, doc_tokens in zip(*cols, strict=True):
                while ids:
                    took = ids[: size - held]
                    window.append((doc_id, start, took, doc_tokens))
                    held, start, ids = held + len(took), start + len(took), ids[len(took) :]
                    if held == size:
                        rows += _laid_out(window, number)
                        number, window, held = number + 1, [], 0
            yield _batch(rows, emit_ids)
        if window:
            yield _batch(_laid_out(window, number), emit_ids)

    dealt = left.select("doc_id", "start", "ids", "doc_tokens").repartition(groups, "doc_id", "start") if groups > 1 else left.coalesce(1)
    return placed.where("sequence_id is not null").unionByName(dealt.select("*", F.spark_partition_id().alias("place")).mapInArrow(frugal(merge), PIECE))
