"""One query for each corpus operator, over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from gridchain.llm import rules
from gridchain.llm.bpe import encode_decode
from gridchain.llm.ngram_join import ngram_components
from gridchain.llm.packing import pack_documents
from gridchain.llm.paragraphs import paragraph_report
from gridchain.llm.pivots import top_products
from gridchain.llm.quality import quality_scores
from gridchain.llm.rules import quality_rules
from gridchain.llm.substrings import remove_repeats
from gridchain.llm.toxicity import toxicity_scores
from gridchain.llm.warc import page_records


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op1_suffix_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(_table(spark, sf_dir, "documents"))


def op2_quality_ranking(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op3_adaptive_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules(_table(spark, sf_dir, "documents"))


def op4_residual_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(_table(spark, sf_dir, "documents"), _vocabulary("word_bpe_49k.json"))


def op5_pivot_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_products(_table(spark, sf_dir, "embeddings"))


def op6_toxicity_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op7_warc_normaliser(spark: SparkSession, sf_dir: str) -> DataFrame:
    return page_records(_table(spark, sf_dir, "pages"))


def op8_trie_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_decode(_table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.json"), ("n_tokens", "ids_sha256", "decoded_sha256"))


def op9_paragraph_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    return paragraph_report(_table(spark, sf_dir, "documents"))


def op10_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_components(_table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_suffix_merge, op2_quality_ranking, op3_adaptive_rules, op4_residual_packing, op5_pivot_topk, op6_toxicity_trees, op7_warc_normaliser, op8_trie_bpe, op9_paragraph_bands, op10_ngram_jaccard_join, pipeline)}
#: Limits of a group of rates, and a group's limits drawn towards those around it.
_CAPS = ", ".join(f"quantile_disc({r}, 0.75) + {rules.SPREAD} * greatest({rules.WIDTH[r]}, quantile_disc({r}, 0.75) - quantile_disc({r}, 0.25)) AS {r}_limit" for r in rules.RATES)
_DRAWN = "({own} * {rows} + {around} * {trust}) / ({rows} + {trust})"


def _drawn(r: str) -> str:
    around = _DRAWN.format(own=f"l.{r}_limit", rows="l.n", around=f"e.{r}_limit", trust=rules.TRUST)
    return _DRAWN.format(own=f"o.{r}_limit", rows="o.n", around=around, trust=rules.TRUST)


_RULES_SQL = f"""WITH d AS (SELECT doc_id, coalesce(lang, '') AS lang, coalesce(source, '') AS source, coalesce(text, '') AS text FROM documents),
    w AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS pos
        FROM (SELECT doc_id, list_filter(regexp_split_to_array(text, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM d)),
    t AS (SELECT doc_id, pos, word AS a, lead(word) OVER o AS b, lead(word, 2) OVER o AS c FROM w WINDOW o AS (PARTITION BY doc_id ORDER BY pos)),
    r AS (SELECT doc_id, pos, count(*) OVER (PARTITION BY doc_id, a, b, c) AS n FROM t WHERE c IS NOT NULL),
    rep AS (SELECT doc_id, count(DISTINCT pos + k) AS n_repeat_words FROM r, (SELECT unnest(range(3)) AS k) WHERE n > 1 GROUP BY doc_id),
    sums AS (SELECT doc_id, count(*) AS n_words, CAST(sum(length(word)) AS BIGINT) AS word_chars FROM w GROUP BY doc_id),
    lines AS (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS ls FROM d),
    rows AS (SELECT d.doc_id, lang, source, coalesce(n_words, 0) AS n_words, coalesce(word_chars, 0) AS word_chars,
        length(text) - length(translate(text, '{rules.SYMBOLS}', '')) AS n_symbols, len(ls) - len(list_distinct(ls)) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words
        FROM d LEFT JOIN sums USING (doc_id) LEFT JOIN rep USING (doc_id) LEFT JOIN lines USING (doc_id)),
    rates AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, n_symbols / greatest(n_words, 1) AS symbol_rate,
        n_dup_lines * 10.0::DOUBLE / greatest(n_words, 1) AS dup_line_rate, n_repeat_words / greatest(n_words, 1) AS repeat_rate, word_chars / greatest(n_words, 1) / 60.0::DOUBLE AS long_word_rate FROM rows),
    o AS (SELECT lang, source, count(*) AS n, {_CAPS} FROM rates WHERE NOT base_failed GROUP BY lang, source),
    l AS (SELECT lang, count(*) AS n, {_CAPS} FROM rates WHERE NOT base_failed GROUP BY lang),
    e AS (SELECT {_CAPS} FROM rates WHERE NOT base_failed),
    limits AS (SELECT o.lang, o.source, {", ".join(f"{_drawn(r)} AS {r}_limit" for r in rules.RATES)} FROM o JOIN l USING (lang) CROSS JOIN e)
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
        NOT base_failed AND {" AND ".join(f"coalesce({r} <= {r}_limit, false)" for r in rules.RATES)} AS kept FROM rates LEFT JOIN limits USING (lang, source)"""

#: Every 100-byte window of every text by its digest; the first (doc_id, place) of a digest stays, later ones are joined to spans.
_SUBSTRING_SQL = """WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, strlen(coalesce(text, '')) AS n FROM documents),
    w AS (SELECT doc_id, k, md5(substring(h, 2 * k + 1, 200)) AS x FROM (SELECT doc_id, h, unnest(range(n - 99)) AS k FROM d WHERE n >= 100)),
    f AS (SELECT doc_id, k FROM (SELECT doc_id, k, row_number() OVER (PARTITION BY x ORDER BY doc_id, k) AS place FROM w) WHERE place > 1),
    g AS (SELECT doc_id, k, CASE WHEN k > lag(k) OVER o + 100 THEN 1 ELSE 0 END AS new FROM f WINDOW o AS (PARTITION BY doc_id ORDER BY k)),
    i AS (SELECT doc_id, k, sum(new) OVER (PARTITION BY doc_id ORDER BY k) AS run FROM g),
    spans AS (SELECT doc_id, min(k) AS a, max(k) + 100 AS b FROM i GROUP BY doc_id, run),
    gaps AS (SELECT doc_id, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS last FROM spans),
    cut AS (SELECT doc_id, count(*) AS n_spans, sum(b - a) AS n_removed, max(b) AS tail, string_agg(substring(h, 2 * last + 1, 2 * (a - last)), '' ORDER BY a) AS kept
        FROM gaps JOIN d USING (doc_id) GROUP BY doc_id)
    SELECT doc_id, n AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans,
        sha256(unhex(coalesce(kept || substring(h, 2 * tail + 1), h))) AS kept_sha256 FROM d LEFT JOIN cut USING (doc_id)"""

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: All pairs that share a shingle, their Jaccard similarity, and the smallest id that links reach.
_NGRAM_SQL = f"""WITH RECURSIVE d AS (SELECT doc_id,
        list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM documents),
    s AS (SELECT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
        ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) END) AS g FROM d),
    t AS MATERIALIZED (SELECT DISTINCT doc_id, md5(g) AS g FROM s),
    sizes AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM t GROUP BY doc_id),
    p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM t a JOIN t b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
    l AS MATERIALIZED (SELECT a, b FROM p JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * c >= 80 * (x.n + y.n - c)),
    e AS MATERIALIZED (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
    r AS (SELECT doc_id, doc_id AS node FROM sizes UNION SELECT r.doc_id, e.b FROM r JOIN e ON e.a = r.node)
    SELECT d.doc_id, coalesce(max(n), 0) AS n_shingles, coalesce(min(node), d.doc_id) AS component_id
    FROM d LEFT JOIN sizes USING (doc_id) LEFT JOIN r USING (doc_id) GROUP BY d.doc_id"""

ORACLE_SQL: dict[str, str] = {
    "op1_suffix_merge": _SUBSTRING_SQL,
    "op10_ngram_jaccard_join": _NGRAM_SQL,
    "op3_adaptive_rules": _RULES_SQL,
    "op5_pivot_topk": """WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS x FROM embeddings WHERE len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
    s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.x, c.x) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id)
    SELECT query_id, CAST(place AS INTEGER) AS rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS place FROM s) WHERE place <= 5""",
    "op7_warc_normaliser": """WITH d AS (SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
    f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first_page FROM d)
    SELECT page_id, payload_bytes, payload_digest, CASE WHEN payload_bytes >= 100 AND page_id <> first_page THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN payload_bytes >= 100 AND page_id <> first_page THEN first_page END AS refers_to FROM f""",
}
