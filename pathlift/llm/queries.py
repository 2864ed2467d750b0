"""The corpus queries, by name, and the SQL that gives the same rows where SQL can."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .frames import held_out, table
from .mixing import oracle_sql as mixing_sql

#: A public vocabulary file; set another path where it lies elsewhere.
PIECE_MODEL = os.environ.get("PATHLIFT_PIECE_MODEL", "/opt/tokenizers/piece_bpe_32k.model")


def op1_ann_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .ann_forest import nearest

    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return nearest(rows, rows.where("vec_id % 20 = 0"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import fit_toxicity, score_toxicity

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "toxic")
    model = fit_toxicity(docs, labels.where(~held_out()))
    scored = score_toxicity(docs, model)
    return scored.select("doc_id", held_out().alias("held_out"), "score", "predicted")


def op3_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .ngram_join import similar_groups

    return similar_groups(table(spark, sf_dir, "documents").select("doc_id", "text"), words=4, percent=85)


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring_dedup import remove_repeats

    return remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .secret_scan import scan_secrets

    found = scan_secrets(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base_spans", 256).alias("base_sha256"), "spans")


def op6_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix_documents

    mixed = mix_documents(table(spark, sf_dir, "documents").select("doc_id", "text", "source", "lang"))
    return mixed.select("doc_id", "source", "lang", "topic", "n_tokens", F.round("probability", 9).alias("probability"), "sampled")


def op7_sentencepiece_nbest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pieces import encode_documents, load_pieces

    found = encode_documents(table(spark, sf_dir, "documents").select("doc_id", "text"), load_pieces(PIECE_MODEL), ids="none")
    return found.select("doc_id", "n_pieces", F.get("nbest_scores", F.lit(0)).alias("best_score"), "nbest_scores", "nbest_digests", "ids_digest", "decoded")


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality_rules import judge

    return judge(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels").select("doc_id", "quality"))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import archive_and_read

    found = archive_and_read(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language_id import fit_language_model, identify_language

    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = fit_language_model(docs.where(~held_out()))
    found = identify_language(docs.select("doc_id", "text"), model)
    return found.select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "rejected")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_ann_forest,
        op2_toxicity,
        op3_ngram_jaccard_join,
        op4_substring_dedup,
        op5_secret_scan,
        op6_source_mixing,
        op7_sentencepiece_nbest,
        op8_quality_rules,
        op9_warc,
        op10_language_id,
    )
}
ORACLES: dict[str, str] = {
    "op6_source_mixing": mixing_sql(),
    "op3_ngram_jaccard_join": r"""
WITH RECURSIVE d AS (
    SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
p AS (SELECT doc_id, w, unnest(CASE WHEN len(w) >= 4 THEN range(1, len(w) - 2) WHEN len(w) > 0 THEN [1] ELSE [] END) AS i FROM d),
g AS (SELECT DISTINCT doc_id, list_slice(w, i, i + 3) AS s FROM p),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
pair AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM g a JOIN g b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY ALL),
link AS (SELECT a, b FROM pair JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
way AS (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
reach AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, e.b FROM reach r JOIN way e ON e.a = r.b)
SELECT d.doc_id, coalesce(n, 0)::BIGINT AS n_shingles, (SELECT min(b) FROM reach r WHERE r.a = d.doc_id) AS component_id
FROM d LEFT JOIN n USING (doc_id)
""",
    "op4_substring_dedup": r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
p AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM d),
win AS (SELECT doc_id, i, list_slice(w, i, i + 12) AS g FROM p WHERE i + 12 <= len(w)),
low AS (SELECT g, min(doc_id) AS lo FROM win GROUP BY g),
hit AS (SELECT DISTINCT doc_id, i + k AS i FROM win JOIN low USING (g), (SELECT unnest(range(0, 13)) AS k) WHERE doc_id > lo),
kept AS (
    SELECT p.doc_id, count(*) AS n, string_agg(w[p.i], ' ' ORDER BY p.i) AS body
    FROM p LEFT JOIN hit ON hit.doc_id = p.doc_id AND hit.i = p.i WHERE hit.i IS NULL GROUP BY p.doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(body, '')) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id)
""",
    "op9_warc": """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS body FROM pages),
d AS (SELECT page_id, octet_length(body) AS n, sha1(body) AS digest FROM p),
g AS (SELECT digest, max(page_id) AS top FROM d WHERE n >= 1000 GROUP BY digest)
SELECT page_id, n::BIGINT AS payload_bytes, digest AS payload_digest,
       CASE WHEN top IS NULL OR top = page_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN top <> page_id THEN top END AS refers_to
FROM d LEFT JOIN g USING (digest)
""",
}
