"""Registered queries of the text operators, each over its whole table with production parameters."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from netjoin.llm import bpe, exact_dedup, langid, minhash, mixing, pii, quality, secrets, urls, warc
from netjoin.llm.common import table

#: Vocabulary of the encoding queries; its path is a parameter of the operator.
TOKENIZER = "word_bpe_49k.json"


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(table(spark, sf_dir, "documents"))


def op2_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_digests(table(spark, sf_dir, "documents"))


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.bpe_digests(table(spark, sf_dir, "documents"), public_tokenizers.path(TOKENIZER))


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pii_digests(table(spark, sf_dir, "documents"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quality.verdicts(quality.ledger(table(spark, sf_dir, "documents")))
    return rows.select("doc_id", *quality.MEASURES, "bits", "base_failed", "kept")


def quality_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.ablation(quality.ledger(table(spark, sf_dir, "documents")))


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify_table(table(spark, sf_dir, "documents"))


def op8_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge_urls(table(spark, sf_dir, "pages"), urls.rule_table(spark, urls.RULES))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_round_trip(table(spark, sf_dir, "pages"))


def op10_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"), words=2)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_exact_dedup, op2_secrets, op3_mixing, op4_bpe, op5_pii, op6_quality, op7_language, op8_urls, op9_warc, op10_minhash, quality_ablation, pipeline)}


_LEDGER = r"""
                 t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
                 w AS (SELECT doc_id, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words,
                              list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines,
                              length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS n_symbols,
                              length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
                              length(regexp_replace(text, '[^\p{L}]', '', 'g')) AS n_letters,
                              length(regexp_replace(text, '[^\p{Lu}]', '', 'g')) AS n_upper FROM t),
                 g AS (SELECT doc_id, i, [words[i], words[i + 1], words[i + 2]] AS gram FROM (SELECT doc_id, words, unnest(range(1, len(words) - 1)) AS i FROM w)),
                 r3 AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, gram) AS n FROM g) WHERE n > 1),
                 c AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words FROM r3, (VALUES (0), (1), (2)) AS o(k) GROUP BY doc_id),
                 m AS (SELECT w.doc_id, len(words)::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols,
                              (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words,
                              len(lines)::BIGINT AS n_lines, n_upper::BIGINT AS n_upper, n_letters::BIGINT AS n_letters FROM w LEFT JOIN c USING (doc_id)),
                 book AS (SELECT *, ((n_words < 50)::BIGINT + 2 * (100 * n_repeat_words > 50 * n_words)::BIGINT + 4 * (100 * n_symbols > 20 * n_words)::BIGINT
                              + 8 * (n_lines >= 10 AND 100 * n_dup_lines > 50 * n_lines)::BIGINT + 16 * (word_chars < 2 * n_words)::BIGINT + 32 * (word_chars > 20 * n_words)::BIGINT
                              + 64 * (100 * n_upper > 60 * n_letters)::BIGINT + 128 * (n_letters < n_words)::BIGINT)::BIGINT AS bits FROM m)"""


def oracle_sql() -> dict[str, str]:
    return {
        "op1_exact_dedup": r"""
            WITH n AS (SELECT doc_id, coalesce(text, '') AS t, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm FROM documents),
                 r AS (SELECT *, first_value(doc_id) OVER (PARTITION BY norm ORDER BY length(t) DESC, doc_id) AS keep_id,
                              count(*) OVER (PARTITION BY norm) AS group_size FROM n)
            SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(norm) AS text_sha256 FROM r""",
        "op6_quality": f"WITH {_LEDGER} SELECT *, (bits & 3) <> 0 AS base_failed, bits = 0 AS kept FROM book",
        "quality_ablation": f"WITH {_LEDGER}, r AS (SELECT * FROM (VALUES {', '.join(f"({b}, '{n}')" for b, (n, _) in quality.RULES.items())}) AS t(b, rule))"
        " SELECT rule, count(*) FILTER ((bits >> b) & 1 = 1) AS n_failed, count(*) FILTER (bits = (1 << b)) AS n_only FROM book, r GROUP BY rule",
        "op10_minhash": r"""
            WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
                 sets AS (SELECT doc_id, CASE WHEN len(ws) < 2 THEN ws ELSE list_sort(list_distinct(list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]))) END AS sh FROM w),
                 k AS (SELECT doc_id, sh, len(sh) AS n, min(doc_id) OVER (PARTITION BY sh) AS rep, count(*) OVER (PARTITION BY sh) AS copies FROM sets),
                 one AS (SELECT rep, n, unnest(sh) AS s FROM k WHERE doc_id = rep AND n > 0),
                 met AS (SELECT a.rep AS a, b.rep AS b, count(*) AS c, any_value(a.n) AS na, any_value(b.n) AS nb FROM one a JOIN one b ON a.s = b.s AND a.rep < b.rep
                          WHERE 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n) GROUP BY 1, 2),
                 link AS (SELECT a, b FROM met WHERE 100 * c >= 80 * (na + nb - c) UNION ALL SELECT b, a FROM met WHERE 100 * c >= 80 * (na + nb - c)),
                 q(x, m) USING KEY (x) AS (SELECT rep, rep FROM one GROUP BY rep
                          UNION SELECT l.b, min(q.m) FROM q JOIN link l ON l.a = q.x JOIN recurring.q o ON o.x = l.b WHERE q.m < o.m GROUP BY l.b)
            SELECT doc_id, n::BIGINT AS n_shingles, CASE WHEN n = 0 THEN doc_id ELSE m END AS component_id, CASE WHEN n = 0 THEN true ELSE m = doc_id END AS kept,
                   CASE WHEN n = 0 THEN 1 ELSE copies END::BIGINT AS n_class FROM k LEFT JOIN q ON q.x = k.rep""",
        "op9_warc": """
            WITH p AS (SELECT page_id, coalesce(html, '') AS h, octet_length(encode(coalesce(html, '')))::BIGINT AS n FROM pages),
                 k AS (SELECT *, max(page_id) OVER (PARTITION BY h) AS keep FROM p)
            SELECT page_id, n AS payload_bytes, sha1(h) AS payload_digest, CASE WHEN n < 1000 OR page_id = keep THEN 'response' ELSE 'revisit' END AS record_type,
                   CASE WHEN n >= 1000 AND page_id <> keep THEN keep END AS refers_to FROM k""",
        "op8_urls": r"""
            WITH u AS (SELECT row_number() OVER () AS row, page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
                 p AS (SELECT row, page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
                              regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
                 r(verdict, rule_host, rule_path) AS (VALUES ('allow', 'com', '/'), ('block', 'example.com', '/en/'), ('allow', 'www.example.com', '/en/'), ('block', 'net', '/es/'), ('block', 'net', '/fr/')),
                 h AS (SELECT row, rule_host || rule_path AS rule, verdict, row_number() OVER (PARTITION BY row ORDER BY length(rule_host || rule_path) DESC) AS n
                       FROM p JOIN r ON (host = rule_host OR ends_with(host, '.' || rule_host)) AND starts_with(path, rule_path))
            SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM p LEFT JOIN h ON p.row = h.row AND h.n = 1""",
    }
