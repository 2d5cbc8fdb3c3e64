"""Near duplicates: a multi-index Hamming join of b-bit MinHash signatures, confirmed on the full shingle sets.

A signature is a row of b-bit symbols, each the low bits of one minimum; its distance to another is the number of
symbols that differ. The first symbols are split into chunks. By the pigeonhole principle two signatures
within distance 2 * chunks - 1 agree in some chunk up to one error, so every chunk is indexed once for each place
that the error may have, with that place left out: all pairs within that distance share a key.

Sharing a key asks for a check, not for a list of all pairs. In a few rounds every key's members are checked against
one of them, and linked sets become components. Members of one key that are still apart and look alike then meet in
the task of the key's commonest component, where an index of their shingles gives all intersections at once: rows are
made for sets, never for pairs of them.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import frugal, salted_join, shielded, tokens, work_table, worker_cache

WORDS = 5
SYMBOLS = 128
CHUNKS = 10
CHUNK = 4
#: Of SYMBOLS, at least so many agree in any pair that is to be confirmed, unless least_agree says otherwise: at a similarity of
#: 0.75 the expected number is 96 with a deviation of 4.9, so that a pair falls below this with a probability of about 3e-6.
LEAST_AGREE = 74
#: Rounds after the first in which a key's members are checked against one of them only, before all that are apart are compared.
ROUNDS = 1
BROADCAST_ROWS = 1_000_000
BLOCK = 4096
#: Shingles of the sets that meet in a hub's task, from each of its two blocks: 32 MB.
BLOCK_HASHES = 4_000_000
#: A key of more members still apart than this is split by further symbols before they are compared.
REFINE = 200_000
#: Symbols of a finer chunk; SYMBOLS // FINE of them can be told apart.
FINE = 2
#: Up to so many rows a join's other side, of a few numbers a row, goes to every executor.
NARROW_ROWS = 500_000
#: Bytes of full sets that a task confirming pairs reads, about.
CONFIRM_BYTES = 32_000_000


class _Hashes(dict):
    def __missing__(self, word):
        import xxhash

        if len(self) > 150_000:
            self.clear()
        found = self[word] = xxhash.xxh3_64_intdigest(word)
        return found


def shingle_set(text: str | None, words: int = WORDS):
    """The sorted distinct 64-bit hashes of a text's shingles; one of the whole sequence if it has fewer words."""
    import numpy as np

    hashes = worker_cache("near_dedup_words", _Hashes)
    found = tokens(text)
    h = np.fromiter(map(hashes.__getitem__, found), np.uint64, len(found))
    if not len(h):
        return h
    factors = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], np.uint64)
    if words > len(factors):
        factors = np.random.default_rng(words).integers(1, 2**63, words, dtype=np.uint64) | np.uint64(1)
    n = min(words, len(h))
    total = np.full(len(h) - n + 1, n, np.uint64)
    for i in range(n):
        total += (h[i : len(h) - n + 1 + i] ^ (h[i : len(h) - n + 1 + i] >> np.uint64(29))) * factors[i]
    total ^= total >> np.uint64(32)
    total *= np.uint64(0xD6E8FEB86659FD93)
    total ^= total >> np.uint64(32)
    return np.unique(total)


def _permutations():
    import numpy as np

    draw = np.random.default_rng(20_240_601)
    return draw.integers(0, 2**63, SYMBOLS, dtype=np.uint64), draw.integers(0, 2**63, SYMBOLS, dtype=np.uint64) | np.uint64(1)


def signature(shingles):
    """SYMBOLS 16-bit symbols: low bits of the minima of as many hashes."""
    import numpy as np

    masks, factors = worker_cache("near_dedup_hashes", _permutations)
    best = np.full(SYMBOLS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 1024):
        x = (shingles[at : at + 1024, None] ^ masks) * factors
        np.minimum(best, x.min(axis=0), out=best)
    best ^= best >> np.uint64(31)
    return ((best * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(48)).astype("<u2")


def index_keys(signatures):
    """For an array (rows, SYMBOLS) the keys (rows, CHUNKS * CHUNK): each chunk with each of its places left out."""
    import numpy as np

    sym = signatures[:, : CHUNKS * CHUNK].astype(np.uint64).reshape(len(signatures), CHUNKS, CHUNK)
    out = np.empty((len(signatures), CHUNKS, CHUNK), np.uint64)
    for place in range(CHUNK):
        key = np.full((len(signatures), CHUNKS), place + 1, np.uint64) + np.arange(CHUNKS, dtype=np.uint64) * np.uint64(CHUNK)
        for i in range(CHUNK):
            if i != place:
                key = (key ^ sym[:, :, i]) * np.uint64(0x9E3779B97F4A7C15)
                key ^= key >> np.uint64(32)
        out[:, :, place] = key
    return out.reshape(len(signatures), -1).view(np.int64)


def _sketched(docs: DataFrame, words: int) -> DataFrame:
    def run(batches):
        import pyarrow as pa

        for batch in batches:
            ids, texts = batch.column("doc_id"), batch.column("text")
            for at in range(0, len(ids), 2048):
                n, key, sig = [], [], []
                for t in texts.slice(at, 2048).to_pylist():
                    s = shingle_set(t, words)
                    n.append(len(s))
                    key.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
                    sig.append(signature(s).tobytes() if len(s) else None)
                yield pa.RecordBatch.from_arrays([ids.slice(at, 2048), pa.array(n, pa.int64()), pa.array(key, pa.binary()), pa.array(sig, pa.binary())], names=["doc_id", "n", "set_id", "sig"])

    return docs.select("doc_id", "text").mapInArrow(frugal(run), "doc_id long, n long, set_id binary, sig binary")


def _matrix(column):
    import numpy as np

    return np.frombuffer(b"".join(column.to_pylist()), "<u2").reshape(len(column), SYMBOLS)


def _keys(sets: DataFrame) -> DataFrame:
    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            keys = index_keys(_matrix(batch.column("sig")))
            nodes = np.repeat(batch.column("node").to_numpy(zero_copy_only=False), keys.shape[1])
            yield pa.RecordBatch.from_arrays([pa.array(keys.ravel()), pa.array(nodes)], names=["key", "node"])

    return sets.select("node", "sig").mapInArrow(frugal(run), "key long, node long")


def _plausible(pairs: DataFrame, sets: DataFrame, share: tuple[int, int], least_agree: int) -> DataFrame:
    """Pairs (a, b) whose sizes allow the similarity and whose signatures agree often enough."""
    left = sets.select(F.col("node").alias("a"), F.col("n").alias("n_a"), F.col("sig").alias("sig_a"))
    right = sets.select(F.col("node").alias("b"), F.col("n").alias("n_b"), F.col("sig").alias("sig_b"))
    fits = F.least("n_a", "n_b") * share[1] >= F.greatest("n_a", "n_b") * share[0]
    both = pairs.join(left, "a").join(right, "b").where(fits).select("a", "b", "sig_a", "sig_b")

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            if len(batch):
                agree = (_matrix(batch.column("sig_a")) == _matrix(batch.column("sig_b"))).sum(1)
                yield batch.select(["a", "b"]).filter(pa.array(agree >= least_agree))

    return both.mapInArrow(frugal(run), "a long, b long")


def _full_sets(nodes: DataFrame, most: int, sets: DataFrame, docs: DataFrame, words: int, broadcast_rows: int) -> DataFrame:
    """(node, hashes) for the nodes asked for, most rows of them, built anew from their texts."""
    wanted = work_table(nodes.select("node").distinct().join(sets.select("node", "set_id", "first_doc", "n"), "node"), "asked", most)
    ids, n = wanted.select(F.col("first_doc").alias("rid")).distinct(), wanted.count()
    if n <= broadcast_rows:
        ids, wanted = F.broadcast(ids), F.broadcast(wanted)
    rows = docs.select("doc_id", "text").join(ids, F.col("doc_id").eqNullSafe(F.col("rid")), "left_semi")

    def build(batches):
        import pyarrow as pa

        for batch in batches:
            texts = batch.column("text")
            for at in range(0, len(texts), 1024):
                data = [shingle_set(t, words).tobytes() for t in texts.slice(at, 1024).to_pylist()]
                keys = [hashlib.blake2b(d, digest_size=16).digest() for d in data]
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(data, pa.binary())], names=["built_id", "hashes"])

    built = rows.mapInArrow(frugal(build), "built_id binary, hashes binary")
    full = built.join(wanted.select("node", "set_id"), F.col("built_id") == F.col("set_id")).select("node", "hashes")
    mean = wanted.agg(F.avg("n")).first()[0] or 1
    return work_table(full.groupBy("node").agg(F.first("hashes").alias("hashes")), "full_sets", n, max(1, int(CONFIRM_BYTES / (8 * mean))))


def _confirmed(pairs: DataFrame, n: int, full: DataFrame, share: tuple[int, int], each: int) -> DataFrame:
    """The pairs, n of them, whose full shingle sets have intersection / union of share or more; each pairs to a task."""
    both = (
        pairs.join(full.select(F.col("node").alias("b"), F.col("hashes").alias("set_b")), "b")
        .join(full.select(F.col("node").alias("a"), F.col("hashes").alias("set_a")), "a")
        .select("a", "b", "set_a", "set_b")
    )

    def confirm(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            keep = []
            for x, y in zip(batch.column("set_a"), batch.column("set_b"), strict=True):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                common = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(share[1] * common >= share[0] * (len(x) + len(y) - common))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return work_table(both.mapInArrow(frugal(confirm), "a long, b long"), "links", max(1, n), each)


def components(links: DataFrame) -> DataFrame:
    """node, label for the nodes of links (a, b): label is the smallest node that links lead to.

    Large-star and small-star steps by turns, each written to the shared folder, until the edges stay the same.
    Neighbours' minima are summed before the exchange, and the rows of a node with very many links are split, so that no
    such node is a single task.
    """
    edges = links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct()
    seen, n = None, links.count()
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count(F.lit(1)).alias("degree"))
        large = salted_join(both, least, ["u"], "degree", 2 * n, broadcast_rows=NARROW_ROWS).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("degree"))
        small = salted_join(large, least, ["u"], "degree", 2 * n, broadcast_rows=NARROW_ROWS).select("u", "v", "m")
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v")))
        edges = work_table(small.where("u > v").distinct(), "edges", n)
        now = tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == seen:
            break
        seen = now
    return edges.select(F.col("u").alias("node"), F.col("v").alias("label"))


def _labelled(keys: DataFrame, labels: DataFrame) -> DataFrame:
    named = keys.join(labels.withColumnRenamed("node", "lnode"), F.col("node") == F.col("lnode"), "left")
    return named.select("key", "node", F.coalesce("label", "node").alias("label"))


def _mixed(keys: DataFrame) -> DataFrame:
    """(k, members, hub) of the keys of three or more members in different components; hub is the commonest of these.

    Two members are compared in the first round.
    """
    counts = keys.groupBy(F.col("key").alias("k"), "label").agg(F.count(F.lit(1)).alias("c"))
    stats = counts.groupBy("k").agg(F.sum("c").alias("members"), F.count(F.lit(1)).alias("labels"), F.max(F.struct("c", (-F.col("label")).alias("back"))).alias("top"))
    return stats.where("members > 2 and labels > 1").select("k", "members", (-F.col("top.back")).alias("hub"))


def _stars(keys: DataFrame, turn: int, total: int) -> DataFrame:
    """Pairs (a, b) of a key's members with one of them, another for each key and turn, where components differ."""
    order = F.xxhash64("node", "key", F.lit(turn))
    heads = keys.groupBy("key").agg(F.min(F.struct(order.alias("o"), "node", "label")).alias("head"), F.count(F.lit(1)).alias("members"))
    apart = salted_join(keys, heads, ["key"], "members", total, broadcast_rows=NARROW_ROWS).where(F.col("label") != F.col("head.label"))
    return apart.select(F.least("node", "head.node").alias("a"), F.greatest("node", "head.node").alias("b")).distinct()


def _refined(rows: DataFrame, least_agree: int) -> DataFrame:
    """Members of a very large key under finer keys: those that agree in a chunk of FINE symbols as well.

    Of SYMBOLS // FINE chunks, two sets that agree in least_agree symbols share one of any SYMBOLS - least_agree + 1.
    """
    chunks = F.sequence(F.lit(0), F.lit(SYMBOLS - least_agree))
    rows = rows.withColumn("chunk", F.explode(chunks))
    part = F.expr(f"substring(sig, chunk * {2 * FINE} + 1, {2 * FINE})")
    rows = rows.withColumn("key", F.xxhash64("key", "chunk", part)).drop("chunk", "members")
    sizes = rows.groupBy("key").agg(F.count(F.lit(1)).alias("members")).where("members > 1")
    total = sizes.agg(F.sum("members")).first()[0] or 0
    return salted_join(rows, sizes, ["key"], "members", total)


def _lookalikes(keys: DataFrame, sets: DataFrame, share: tuple[int, int], total: int, least_agree: int) -> DataFrame:
    """(hub, node, label, n): nodes with a lookalike, by size and signature, of another component under one key.

    keys is (key, node, label). A key's members are dealt into blocks of about BLOCK; a task compares two blocks. A key of more
    than REFINE members goes by finer keys first, so that work grows with its size, not with the square of it.
    """
    mixed = _mixed(keys)
    rows = salted_join(keys, mixed.withColumnRenamed("k", "key"), ["key"], "members", total, broadcast_rows=NARROW_ROWS)
    rows = rows.join(sets.select(F.col("node").alias("snode"), "n", "sig"), F.col("node") == F.col("snode")).select("key", "node", "label", "n", "sig", "hub", "members")
    if SYMBOLS - least_agree + 1 <= SYMBOLS // FINE:
        large = F.col("members") > REFINE
        if not mixed.where(large).isEmpty():
            rows = rows.where(~large).unionByName(_refined(rows.where(large), least_agree).select(*rows.columns))
    rows = rows.withColumn("blocks", F.ceil(F.col("members") / BLOCK).cast("int"))
    rows = _dealt(rows, "key").select("key", "i", "j", "own", "node", "label", "n", "sig", "hub")

    def compare(batches):
        import numpy as np
        import pyarrow as pa

        schema = pa.schema([(name, pa.int64()) for name in ("hub", "node", "label", "n")])
        for group in _groups(batches):
            node, label, hub = (np.array([r[k] for r in group]) for k in (4, 5, 8))
            n, sig = np.array([r[6] for r in group]), np.frombuffer(b"".join(r[7] for r in group), "<u2").reshape(-1, SYMBOLS)
            left, right = _sides(group)
            like = np.zeros(len(group), bool)
            for at in range(0, len(left), 64):
                x, y = left[at : at + 64, None], right[None, :]
                ok = (label[x] != label[y]) & (np.minimum(n[x], n[y]) * share[1] >= np.maximum(n[x], n[y]) * share[0]) & ~(like[x] & like[y])
                i, j = np.nonzero(ok)
                for part in range(0, len(i), 65536):
                    a, b = left[at + i[part : part + 65536]], right[j[part : part + 65536]]
                    close = (sig[a] == sig[b]).sum(1) >= least_agree
                    like[a[close]] = like[b[close]] = True
            yield pa.RecordBatch.from_arrays([pa.array(v[like], pa.int64()) for v in (hub, node, label, n)], schema=schema)

    return rows.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(frugal(compare), "hub long, node long, label long, n long").distinct()


def _dealt(rows: DataFrame, key: str) -> DataFrame:
    """Rows of a key in blocks, once for each pair (i, j) of blocks that theirs (own) belongs to."""
    own = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    rows = rows.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    return rows.withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")}).drop("other")


def _groups(batches):
    """Lists of rows with the same first three columns, of sorted batches."""
    from itertools import groupby

    def rows():
        for batch in batches:
            yield from zip(*(c.to_pylist() for c in batch.columns), strict=True)

    for _, group in groupby(rows(), key=lambda r: r[:3]):
        yield list(group)


def _sides(group):
    """Places of the rows of block i, and of block j, for rows (key, i, j, own, ..)."""
    import numpy as np

    own = np.array([r[3] for r in group])
    return np.flatnonzero(own == group[0][1]), np.flatnonzero(own == group[0][2])


def _hub_links(alike: DataFrame, full: DataFrame, share: tuple[int, int]) -> DataFrame:
    """Links among the nodes of each hub, enough to connect all that are linked, by an index of their full sets.

    Every node that is not of the hub's own component asks the index for its intersection with all others.
    """
    blocks = F.ceil(F.greatest(F.count(F.lit(1)) / BLOCK, F.sum("n") / BLOCK_HASHES)).cast("int")
    sizes = alike.groupBy(F.col("hub").alias("h")).agg(blocks.alias("blocks"))
    rows = alike.join(sizes, F.col("hub") == F.col("h")).join(full.select(F.col("node").alias("fnode"), "hashes"), F.col("node") == F.col("fnode"))
    rows = _dealt(rows, "hub").select("hub", "i", "j", "own", "node", "label", "hashes")

    def link(batches):
        import numpy as np
        import pyarrow as pa

        for group in _groups(batches):
            sets = [np.frombuffer(r[6], np.uint64) for r in group]
            size, label = np.array([len(x) for x in sets]), np.array([r[5] for r in group])
            every = np.concatenate(sets)
            owner = np.repeat(np.arange(len(sets)), size)
            order = np.argsort(every, kind="stable")
            every, owner = every[order], owner[order]
            left, right = _sides(group)
            within = [np.zeros(len(group), bool), np.zeros(len(group), bool)]
            within[0][left], within[1][right] = True, True
            parent = {}

            def root(x):
                while parent.get(x, x) != x:
                    x = parent[x]
                return x

            a, b = [], []
            for x in np.flatnonzero(label != group[0][0]):
                lo, hi = np.searchsorted(every, sets[x], "left"), np.searchsorted(every, sets[x], "right")
                total = hi - lo
                at = np.repeat(lo - np.cumsum(total) + total, total) + np.arange(total.sum())
                common = np.bincount(owner[at], minlength=len(group))
                other = (within[1] if within[0][x] else within[0]) | (within[0] if within[1][x] else within[1])
                near = (label != label[x]) & other & (share[1] * common >= share[0] * (size + size[x] - common))
                for y in np.flatnonzero(near):
                    p, q = root(int(label[x])), root(int(label[y]))
                    if p != q:
                        parent[max(p, q)] = min(p, q)
                        a.append(min(group[x][4], group[y][4]))
                        b.append(max(group[x][4], group[y][4]))
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    dealt = rows.repartition("hub", "i", "j").sortWithinPartitions("hub", "i", "j")
    return work_table(dealt.mapInArrow(frugal(link), "a long, b long"), "links")


def near_duplicates(
    docs: DataFrame, share: tuple[int, int] = (75, 100), words: int = WORDS, broadcast_rows: int = BROADCAST_ROWS, least_agree: int = LEAST_AGREE
) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of docs (doc_id, text).

    Documents are linked when the intersection of their sets of shingles is at least share of the union. component_id is
    the smallest doc_id that links lead to, the document's own included; kept is whether that is its own. A null or empty
    text has an empty set and is linked with nothing. A null doc_id is larger than any other. Rows with equal sets
    share a component, rows that repeat a doc_id included. Texts are read whole. An empty table gives no rows.

    The index finds every pair whose indexed symbols differ in 2 * CHUNKS - 1 places at most. Of these, pairs of which fewer than least_agree
    symbols of all agree are not confirmed: 0 confirms every pair that the index finds, at more cost.
    """
    rows = work_table(_sketched(docs, words), "sketches")
    # Equal sets are one node; copies need no comparing. Partial sums come first, whatever the number of copies.
    sets = rows.where("set_id is not null").groupBy("set_id").agg(F.min("doc_id").alias("first_doc"), F.first("n").alias("n"), F.first("sig").alias("sig"), F.count(F.lit(1)).alias("copies"))
    sets = work_table(sets.withColumn("node", F.monotonically_increasing_id()), "sets")
    n_keys = sets.count() * CHUNKS * CHUNK
    keys = _keys(sets)
    heads = keys.groupBy("key").agg(F.min("node").alias("a"), F.count(F.lit(1)).alias("members")).where("members > 1")
    stars = salted_join(keys, heads, ["key"], "members", n_keys, broadcast_rows=NARROW_ROWS).where("node > a").select("a", F.col("node").alias("b")).distinct()
    tried = work_table(_plausible(stars, sets, share, least_agree), "stars")
    build = lambda nodes, most: _full_sets(nodes, most, sets, docs, words, broadcast_rows)

    def confirmed(pairs):
        n = pairs.count()
        full = build(pairs.select(F.explode(F.array("a", "b")).alias("node")), 2 * n)
        mean = full.agg(F.avg(F.octet_length("hashes"))).first()[0] or 1
        return _confirmed(pairs, n, full, share, max(1, int(CONFIRM_BYTES / (2 * mean))))

    links = confirmed(tried)
    labels = components(links)
    # Only keys whose members are in different components matter from here on.
    keys = _labelled(keys, labels)
    total = n_keys
    for turn in range(ROUNDS + 1):
        keys = work_table(salted_join(keys, _mixed(keys).select(F.col("k").alias("key"), "members"), ["key"], "members", total, how="left_semi", broadcast_rows=NARROW_ROWS), "apart")
        total = keys.count()
        if not total:
            break
        if turn < ROUNDS:
            found = confirmed(work_table(_plausible(_stars(keys, turn, total), sets, share, least_agree), "more_pairs"))
        else:
            alike = work_table(_lookalikes(keys, sets, share, total, least_agree), "alike")
            found = _hub_links(alike, build(alike, alike.count()), share)
        if not found.isEmpty():
            links = links.unionByName(found)
            labels = components(links)
            keys = _labelled(keys.select("key", "node"), labels)
    named = sets.join(labels.withColumnRenamed("node", "lnode"), F.col("node") == F.col("lnode"), "left")
    named = work_table(named.select("set_id", "first_doc", "copies", F.coalesce("label", "node").alias("label")), "labelled")
    least = named.groupBy("label").agg(F.min("first_doc").alias("component"), F.count(F.lit(1)).alias("members"))
    named = salted_join(named, least, ["label"], "members", n_keys // (CHUNKS * CHUNK), broadcast_rows=NARROW_ROWS).select("set_id", "component", "copies")
    found = salted_join(rows.select("doc_id", "n", "set_id"), named, ["set_id"], "copies", rows.count(), how="left", broadcast_rows=NARROW_ROWS)
    component = F.when(F.col("set_id").isNull(), F.col("doc_id")).otherwise(F.col("component"))
    return found.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), component.eqNullSafe(F.col("doc_id")).alias("kept"))


def keep_one(docs: DataFrame, broadcast_rows: int = BROADCAST_ROWS, **options) -> DataFrame:
    """The rows of docs that near_duplicates keeps, with all their columns; of rows that repeat a kept doc_id, all."""
    gone = near_duplicates(docs, broadcast_rows=broadcast_rows, **options).groupBy(F.col("doc_id").alias("gone")).agg(F.max("kept").alias("any"))
    gone = work_table(gone.where("not any").select("gone"), "gone")
    plain, name = shielded(docs)
    gone = F.broadcast(gone) if gone.count() <= broadcast_rows else gone
    return plain.join(gone, plain[name["doc_id"]].eqNullSafe(gone["gone"]), "left_anti").toDF(*docs.columns)
