"""Queries op1 to op10 over whole tables, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import dartminhash, flac, langid, linededup, mixing, mtree, packing, repair, toxicity, warc

TOKENIZER = "word_bpe_49k.json"


def tokenizer_path() -> str:
    return public_tokenizers.path(TOKENIZER)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_flac(spark, sf_dir):
    return flac.digests(flac.store(table(spark, sf_dir, "documents")))


def op2_language(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return langid.predict(docs, langid.train(docs))


def op3_near_duplicates(spark, sf_dir):
    return dartminhash.near_duplicate_classes(table(spark, sf_dir, "documents"))


def op4_packing(spark, sf_dir):
    return packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer_path())


def op5_topk(spark, sf_dir):
    vectors = mtree.whole_vectors(table(spark, sf_dir, "embeddings"))
    return mtree.search(vectors, vectors.where(F.col("vec_id") % 50 == 0))


def op6_mixing(spark, sf_dir):
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op7_tokens(spark, sf_dir):
    return repair.token_table(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_toxicity(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def op9_warc(spark, sf_dir):
    return warc.round_trip(table(spark, sf_dir, "pages"))


def op10_lines(spark, sf_dir):
    return linededup.digests(table(spark, sf_dir, "documents"))


def queries():
    ops = (op1_flac, op2_language, op3_near_duplicates, op4_packing, op5_topk, op6_mixing, op7_tokens, op8_toxicity, op9_warc, op10_lines)
    return {f.__name__: f for f in ops}


_STRIP = "chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"

ORACLE = {
    "op5_topk": """
        WITH parts AS (SELECT vec_id, len(embedding) dim, unnest(embedding) x, generate_subscripts(embedding, 1) i FROM embeddings WHERE vec_id IS NOT NULL),
        bad AS (SELECT DISTINCT vec_id FROM parts WHERE x IS NULL OR NOT isfinite(x)),
        v AS (SELECT vec_id, dim, i, CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT) x FROM parts WHERE vec_id NOT IN (SELECT vec_id FROM bad)),
        s AS (SELECT q.vec_id query_id, c.vec_id, CAST(sum(q.x * c.x) AS BIGINT) score FROM v q JOIN v c ON q.i = c.i AND q.dim = c.dim AND q.vec_id <> c.vec_id
              WHERE q.vec_id % 50 = 0 GROUP BY ALL),
        r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
        SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5""",
    "op9_warc": """
        WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) payload_bytes, sha1(coalesce(html, '')) payload_digest FROM pages),
        m AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS first FROM p)
        SELECT page_id, CAST(payload_bytes AS BIGINT) payload_bytes, payload_digest,
               CASE WHEN payload_bytes >= 1000 AND first > page_id THEN 'revisit' ELSE 'response' END record_type,
               CASE WHEN payload_bytes >= 1000 AND first > page_id THEN first END refers_to FROM m""",
    "op10_lines": f"""
        WITH lines AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) pos FROM documents),
        keyed AS (SELECT *, translate(trim(line, {_STRIP}), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines),
        hot AS (SELECT k, max(doc_id) top FROM keyed WHERE length(k) >= 40 GROUP BY k HAVING count(DISTINCT doc_id) >= 5),
        marked AS (SELECT d.doc_id, d.pos, d.line, coalesce(h.top <> d.doc_id, false) gone FROM keyed d LEFT JOIN hot h USING (k))
        SELECT doc_id, CAST(count(*) AS BIGINT) n_lines, CAST(count(*) FILTER (gone) AS BIGINT) n_dropped,
               sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) kept_sha256 FROM marked GROUP BY doc_id""",
}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLE)
