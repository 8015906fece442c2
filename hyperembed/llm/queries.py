"""Queries of the training-data operators, with SQL twins where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import exact_dedup as dedup, html_text, mixing, ngram_join, quality, sentence_pieces, suffix_dedup, token_files, toxicity, warc
from .common import LOWER, UPPER, table
from .suffix_dedup import LENGTH


def vocabulary(name: str) -> str:
    """Path of a public tokenizer's file, the same on every machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_round_trip(table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.near_duplicate_classes(table(spark, sf_dir, "documents"))


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(table(spark, sf_dir, "documents")).drop("kept")


def op4_quality_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents")).drop("quality")


def op5_entropy_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).drop("copies", "rate")


def op6_sampled_segmentations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentence_pieces.sample_segmentations(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"), digest=True)


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.tokens_round_trip(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"), digest=True)


def op8_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup.exact_dedup(table(spark, sf_dir, "documents"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.learn(docs, table(spark, sf_dir, "labels")))


QUERIES = {f.__name__: f for f in (
    op1_warc_archive, op2_ngram_jaccard_join, op3_suffix_dedup, op4_quality_votes, op5_entropy_mix, op6_sampled_segmentations, op7_token_files, op8_main_text, op9_exact_dedup, op10_toxicity,
)}

ORACLES = {
    "op1_warc_archive": """
        WITH p AS (SELECT page_id, coalesce(html, '') AS t FROM pages),
        g AS (SELECT page_id, octet_length(encode(t))::BIGINT AS payload_bytes, max(page_id) OVER (PARTITION BY t) AS answer,
                     unhex(sha1(t))::BIT::VARCHAR AS bits FROM p)
        SELECT page_id, payload_bytes,
               array_to_string([substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', ('0b' || substr(bits, 5 * i + 1, 5))::INTEGER + 1, 1) FOR i IN range(32)], '') AS payload_digest,
               CASE WHEN page_id = answer THEN 'response' ELSE 'revisit' END AS record_type,
               CASE WHEN page_id <> answer THEN answer END AS refers_to
        FROM g""",
    "op3_suffix_dedup": f"""
        WITH d AS (SELECT doc_id, encode(coalesce(text, '')) AS b, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
        places AS (SELECT doc_id, unnest(range(n - {LENGTH - 1})) AS p, b FROM d WHERE n >= {LENGTH}),
        strings AS (SELECT doc_id, p, b[p + 1 : p + {LENGTH}] AS s FROM places),
        firsts AS (SELECT s, min(doc_id) AS least FROM strings GROUP BY s),
        again AS (SELECT doc_id, p FROM strings JOIN firsts USING (s) WHERE doc_id > least),
        marked AS (SELECT doc_id, p, CASE WHEN p <= lag(p) OVER w + {LENGTH} THEN 0 ELSE 1 END AS opens FROM again WINDOW w AS (PARTITION BY doc_id ORDER BY p)),
        numbered AS (SELECT doc_id, p, sum(opens) OVER (PARTITION BY doc_id ORDER BY p ROWS UNBOUNDED PRECEDING) AS run FROM marked),
        runs AS (SELECT doc_id, min(p) AS first, max(p) + {LENGTH} AS last FROM numbered GROUP BY doc_id, run),
        gaps AS (SELECT doc_id, first, last, coalesce(lag(last) OVER (PARTITION BY doc_id ORDER BY first), 0) AS before FROM runs),
        cut AS (SELECT doc_id, sum(last - first) AS removed, count(*) AS spans, max(last) AS rest,
                       string_agg(CASE WHEN first > before THEN hex(b[before + 1 : first]) ELSE '' END, '' ORDER BY first) AS kept
                FROM gaps JOIN d USING (doc_id) GROUP BY doc_id)
        SELECT doc_id, n::BIGINT AS n_bytes, coalesce(removed, 0)::BIGINT AS n_removed, coalesce(spans, 0)::BIGINT AS n_spans,
               sha256(CASE WHEN rest IS NULL THEN b ELSE unhex(kept || CASE WHEN n > rest THEN hex(b[rest + 1 : n]) ELSE '' END) END) AS kept_sha256
        FROM d LEFT JOIN cut USING (doc_id)""",
    "op2_ngram_jaccard_join": f"""
        WITH RECURSIVE words AS (
            SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
        sets AS (
            SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
                ELSE list_distinct([array_to_string(w[i:i+4], ' ') FOR i IN range(1, len(w) - 3)]) END AS s FROM words),
        groups AS (SELECT list_sort(s) AS k, min(doc_id) AS rep, max(len(s)) AS n FROM sets WHERE len(s) > 0 GROUP BY 1),
        tokens AS (SELECT rep, n, unnest(k) AS t FROM groups),
        overlap AS (SELECT a.rep AS x, b.rep AS y, any_value(a.n) AS nx, any_value(b.n) AS ny, count(*) AS c
            FROM tokens a JOIN tokens b ON a.t = b.t AND a.rep < b.rep GROUP BY 1, 2),
        links AS (SELECT x, y FROM overlap WHERE 100 * c >= 75 * (nx + ny - c)),
        both_ways AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
        reach(node, root) AS (SELECT rep, rep FROM groups UNION SELECT b.y, r.root FROM reach r JOIN both_ways b ON b.x = r.node),
        class AS (SELECT node, min(root) AS c FROM reach GROUP BY node)
        SELECT s.doc_id, CAST(len(s.s) AS BIGINT) AS n_shingles, coalesce(class.c, s.doc_id) AS component_id
        FROM sets s LEFT JOIN groups g ON g.k = list_sort(s.s) AND len(s.s) > 0 LEFT JOIN class ON class.node = g.rep""",
    "op9_exact_dedup": f"""
        WITH n AS (SELECT doc_id, translate(coalesce(text, ''), '{UPPER}', '{LOWER}') AS t FROM documents)
        SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
               doc_id = max(doc_id) OVER w AS kept, sha256(t) AS text_sha256
        FROM n WINDOW w AS (PARTITION BY t)""",
}
