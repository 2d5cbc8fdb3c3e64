"""The queries opN_<name>: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, exact_dedup, knn, lm, mixing, near_dedup, packing, secrets, toxicity, warc
from .common import crc_of, table, work_table


def tokenizer_paths() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def op1_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    archive = warc.write_archive(table(spark, sf_dir, "pages"))
    found = warc.records(archive, warc.base32_sha1(F.col("payload")).alias("payload_digest"))
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), *tokenizer_paths(), emit_ids=False).drop("ids")


def op3_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.find_secrets(table(spark, sf_dir, "documents"))
    base = F.filter("spans", lambda x: x["rank"] < len(secrets.BASE))
    counts = [secrets.count_of(r.kind).alias(f"n_{r.kind}") for r in secrets.BASE]
    return found.select("doc_id", *counts, F.sha2(secrets.listed(base).cast("binary"), 256).alias("base_sha256"), secrets.listed(F.col("spans")).alias("spans"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).documents.select("doc_id", "size", "source_size", "target", "taken")


def op5_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = r"\### Assistant: </turn> ok"
    trap = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(trap)
    return chat.read_back(chat.format_conversations(rows))


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents"), digest_all=True)


def op7_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return knn.top_k(table(spark, sf_dir, "embeddings"))


def toxic_held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string")) % 3 == 1


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"), toxic_held_out)
    found = toxicity.score_documents(docs, model)
    return found.select("doc_id", (crc_of("doc_id") % 3 == 1).alias("held_out"), "score", "predicted")


def op9_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    held_out = crc_of("doc_id") % 7 == 2
    model, counts = lm.learn(docs, held_out)
    return lm.score_documents(docs, model, counts, held_out)


def op10_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_warc, op2_packing, op3_secrets, op4_mixing, op5_chat, op6_exact_dedup, op7_knn, op8_toxicity, op9_lm, op10_near_dedup)}

_WORDS = r"[^\x20\x09-\x0D]+"



def _secret_sql() -> str:
    """Each rule's matches in order, and where they start: the lengths of what lies between and of the matches before."""
    quote = lambda p: p.replace("'", "''")
    rules = [
        f"""SELECT doc_id, {rank} AS rank, '{r.kind}' AS kind, i, gaps, hits, length(held[i]) >= {r.least} AS fits FROM (
                SELECT doc_id, string_split_regex(text, '{quote(r.pattern)}') AS gaps, regexp_extract_all(text, '{quote(r.pattern)}') AS hits,
                       regexp_extract_all(text, '{quote(r.pattern)}', {r.group}) AS held FROM d WHERE regexp_matches(text, '{quote(r.pattern)}')),
                range(1, len(hits) + 1) AS g(i)"""
        for rank, r in enumerate(secrets.BASE + secrets.EXTRA)
    ]
    return f"""
        WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
        m AS ({" UNION ALL ".join(rules)}),
        p AS (SELECT doc_id, rank, kind, list_sum(list_transform(gaps[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(hits[1:i-1], lambda x: length(x))), 0) AS start,
                     length(hits[i]) AS size FROM m WHERE fits),
        s AS (SELECT *, kind || ':' || start::BIGINT || ':' || (start + size)::BIGINT AS span FROM p)
        SELECT d.doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
               sha256(coalesce(string_agg(span, ',' ORDER BY start, rank) FILTER (rank < {len(secrets.BASE)}), '')) AS base_sha256,
               coalesce(string_agg(span, ',' ORDER BY start, rank), '') AS spans
        FROM d LEFT JOIN s ON d.doc_id = s.doc_id GROUP BY d.doc_id"""


ORACLE_SQL = {
    "op3_secrets": _secret_sql(),
    "op5_chat": r"""
        WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
                   UNION ALL SELECT -7, i, r, '\### Assistant: </turn> ok' FROM (VALUES (0, 'user'), (1, 'assistant')) AS x(i, r)),
        e AS (SELECT *, length('### : </turn>') + 1 + length(role) + length(text) + length(text) - length(replace(text, '\', ''))
                     + len(list_filter(range(1, length(text)), lambda i: substr(text, i, 3) = '###'))
                     + (length(text) - length(replace(text, '</turn>', ''))) // 7 AS chars FROM t)
        SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn)) AS turns_sha256,
               coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
               sha256(coalesce(string_agg(text, '' ORDER BY turn) FILTER (role = 'assistant'), '')) AS loss_sha256,
               sum(chars)::BIGINT AS formatted_chars
        FROM e GROUP BY conv_id""",
    "op1_warc": """
        WITH p AS (
            SELECT page_id, coalesce(html, '') AS payload, octet_length(encode(coalesce(html, '')))::BIGINT AS payload_bytes,
                   sha1(coalesce(html, '')) AS hex FROM pages),
        five AS (
            SELECT hex, string_agg(substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
                       (('0x' || substr(hex, 1 + 10 * (i // 8), 10))::BIGINT >> (35 - 5 * (i % 8))) % 32 + 1, 1), '' ORDER BY i) AS payload_digest
            FROM (SELECT DISTINCT hex FROM p), range(32) AS r(i) GROUP BY hex),
        first AS (SELECT payload, min(page_id) AS first_id FROM p GROUP BY payload)
        SELECT page_id, payload_bytes, payload_digest,
               CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type,
               CASE WHEN page_id = first_id THEN NULL ELSE first_id END AS refers_to
        FROM p JOIN five USING (hex) JOIN first USING (payload)""",
    "op4_mixing": f"""
        WITH d AS (
            SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{_WORDS}'))::BIGINT AS size,
                   ('0x' || substr(md5('mix:' || coalesce(doc_id::VARCHAR, md5(coalesce(text, '')))), 1, 15))::BIGINT AS h FROM documents),
        s AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS sid FROM d GROUP BY source),
        w AS (SELECT *, (sid % 3 + 1)::BIGINT AS weight, 3 * source_size AS cap FROM s),
        b AS (SELECT *, (sum(source_size) OVER () - coalesce(sum(cap) OVER before, 0))::DOUBLE
                        / (sum(weight) OVER () - coalesce(sum(weight) OVER before, 0)) AS level_before
              FROM w WINDOW before AS (ORDER BY cap::DOUBLE / weight, sid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        c AS (SELECT *, cap < level_before * weight AS capped FROM b),
        t AS (SELECT source, source_size, CASE WHEN capped THEN cap::DOUBLE ELSE
                  (sum(source_size) OVER () - sum(CASE WHEN capped THEN cap ELSE 0 END) OVER ())::DOUBLE
                  / sum(CASE WHEN capped THEN 0 ELSE weight END) OVER () * weight END AS target FROM c),
        p AS (SELECT doc_id, size, source_size, target, round(target)::BIGINT AS quota,
                     coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY h, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start
              FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
        SELECT doc_id, size, source_size, target,
               CASE WHEN source_size = 0 THEN 0 ELSE quota // source_size * size
                    + greatest(least(start + size, quota % source_size) - start, 0) END::BIGINT AS taken FROM p""",
    "op6_exact_dedup": r"""
        WITH d AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS norm FROM documents)
        SELECT doc_id, min(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size, doc_id = min(doc_id) OVER g AS kept, sha256(norm) AS text_sha256
        FROM d WINDOW g AS (PARTITION BY norm)""",
    "op7_knn": """
        WITH v AS (
            SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS v FROM embeddings
            WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
              AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
        s AS (
            SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(range(1, len(q.v) + 1), lambda i: q.v[i] * c.v[i]))::BIGINT AS score
            FROM v q JOIN v c ON c.vec_id <> q.vec_id WHERE q.vec_id % 50 = 0),
        r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
        SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5""",
    "op10_near_dedup": rf"""
        WITH RECURSIVE w AS (
            SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORDS}') AS ws FROM documents),
        sh AS (
            SELECT DISTINCT doc_id, md5(array_to_string(CASE WHEN len(ws) < 5 THEN ws ELSE ws[i:i+4] END, ' ')) AS g
            FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, least(len(ws), 1)) + 1)) AS i FROM w)),
        n AS (SELECT doc_id, count(*)::BIGINT AS n FROM sh GROUP BY doc_id),
        c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS m FROM sh a JOIN sh b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
        links AS (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * m >= 75 * (x.n + y.n - m)),
        reach AS (SELECT doc_id, doc_id AS other FROM documents UNION SELECT reach.doc_id, links.b FROM reach JOIN links ON reach.other = links.a)
        SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, min(other) AS component_id, d.doc_id = min(other) AS kept
        FROM documents d JOIN reach USING (doc_id) LEFT JOIN n USING (doc_id) GROUP BY d.doc_id, n.n""",
}


# Stages of the pipeline: documents in, documents out, but for the last.


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the model does not call toxic, with the columns they came with."""
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"), toxic_held_out)
    return toxicity.clean_documents(docs, model)


def exact_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.keep_first(docs)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup.keep_one(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, *tokenizer_paths(), emit_ids=False).drop("ids")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pipeline over documents; each stage's result is a table in the shared folder that the next reads."""
    docs = table(spark, sf_dir, "documents")
    *before, (_, last) = STAGES
    for name, stage in before:
        docs = work_table(stage(spark, docs, sf_dir), name)
    return last(spark, docs, sf_dir)


STAGES = [
    ("toxicity", toxicity_stage),
    ("exact_dedup", exact_dedup_stage),
    ("near_dedup", near_dedup_stage),
    ("mixing", mixing_stage),
    ("packing", packing_stage),
]
