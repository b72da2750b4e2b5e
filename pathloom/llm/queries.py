"""Queries of this subpackage's operators on the given tables, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, line_dedup, mixing, ngram_join, preference, quality, token_output, top_k, toxicity, url_filter


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _spans(mask: str):
    return F.array_join(F.transform(mask, lambda m: F.concat_ws("-", m["begin"].cast("string"), m["end"].cast("string"))), ",").alias(mask)


def op1_preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = preference.format_preferences(preference.preference_pairs(_table(spark, sf_dir, "conversations")))
    return rows.select("pair_id", F.col("n_prompt_turns").cast("long").alias("n_prompt_turns"), "prompt", "chosen", _spans("chosen_mask"), "rejected", _spans("rejected_mask"))


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = line_dedup.drop_boilerplate(_table(spark, sf_dir, "pages"))
    return rows.select("page_id", "host", F.col("n_lines").cast("long").alias("n_lines"), F.col("n_dropped").cast("long").alias("n_dropped"), "text")


def op3_impact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = _table(spark, sf_dir, "embeddings")
    return top_k.top_k(vectors, vectors.filter(F.col("vec_id") % top_k.EVERY == 0))


def op4_orc_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_output.round_trip(_table(spark, sf_dir, "documents"), tokenizer_path())


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op6_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_report(_table(spark, sf_dir, "documents"))


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op9_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.filter_urls(_table(spark, sf_dir, "pages"))


def op10_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.jaccard_classes(_table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_preference_pairs, op2_line_dedup, op3_impact_top_k, op4_orc_tokens, op5_toxicity, op6_mixture, op7_decontamination, op8_quality, op9_url_rules, op10_ngram_join)}

_HOST = "translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_PATH = "regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1)"



def _sql_pattern(part: str) -> str:
    """The patterns' expressions without looking round, which DuckDB lacks: here every ^ stands beside a letter and ends a run."""
    return part.replace(".", "[.]").replace("*", "(?s:.*)").replace("^", "(?:^|[^A-Za-z0-9]|$)")


ORACLES: dict[str, str] = {
    "op1_preference_pairs": """
        WITH n AS (SELECT conv_id, coalesce(role, '') AS role, coalesce(text, '') AS text,
                          row_number() OVER (PARTITION BY conv_id ORDER BY turn, coalesce(role, ''), coalesce(text, '')) AS k
                   FROM conversations WHERE conv_id IS NOT NULL),
             a AS (SELECT conv_id, max(k) AS k FROM n WHERE role = 'assistant' GROUP BY conv_id),
             ans AS (SELECT n.conv_id, n.text, n.k FROM n JOIN a ON n.conv_id = a.conv_id AND n.k = a.k),
             p AS (SELECT x.conv_id, x.k - CASE WHEN x.text = y.text THEN 0 ELSE 1 END AS shared, x.text AS own, y.text AS other
                   FROM ans x JOIN ans y ON y.conv_id = xor(x.conv_id, 1)),
             ctx AS (SELECT p.conv_id, string_agg('<|' || role || '|>' || chr(10) || n.text || '<|end|>' || chr(10), '' ORDER BY n.k) AS prompt
                     FROM p JOIN n ON n.conv_id = p.conv_id AND n.k <= p.shared GROUP BY p.conv_id)
        SELECT p.conv_id AS pair_id, CAST(shared AS BIGINT) AS n_prompt_turns, coalesce(prompt, '') AS prompt,
               CASE WHEN own = other THEN '' ELSE '<|assistant|>' || chr(10) || own || '<|end|>' || chr(10) END AS chosen,
               CASE WHEN own = other THEN '' ELSE '14-' || CAST(14 + length(own) + 8 AS VARCHAR) END AS chosen_mask,
               CASE WHEN own = other THEN '' ELSE '<|assistant|>' || chr(10) || other || '<|end|>' || chr(10) END AS rejected,
               CASE WHEN own = other THEN '' ELSE '14-' || CAST(14 + length(other) + 8 AS VARCHAR) END AS rejected_mask
        FROM p LEFT JOIN ctx ON ctx.conv_id = p.conv_id""",
    "op2_line_dedup": rf"""
        WITH cut AS (SELECT row_number() OVER () AS r, page_id, {_HOST} AS host,
                            regexp_split_to_array(coalesce(html, ''), '(?is)<script\b.*?</script[ \t\n\r\f]*>|<style\b.*?</style[ \t\n\r\f]*>|<!--.*?-->|<[^>]*>|[\n\r]+') AS parts
                     FROM pages),
             line AS (SELECT r, page_id, host, i, regexp_replace(parts[i], '\A[ \t\n\r\f]+|[ \t\n\r\f]+\z', '', 'g') AS x
                      FROM (SELECT r, page_id, host, parts, unnest(generate_series(1, len(parts))) AS i FROM cut)),
             held AS (SELECT * FROM line WHERE x <> ''),
             host_n AS (SELECT host, count(*) AS n FROM cut GROUP BY host),
             bad AS (SELECT held.host, x FROM held JOIN host_n ON host_n.host = held.host
                     GROUP BY held.host, x, n HAVING count(DISTINCT r) >= {line_dedup.MIN_HOLDERS} AND count(DISTINCT r) > n * {line_dedup.RATIO}),
             marked AS (SELECT held.r, i, held.x, bad.x IS NOT NULL AS gone FROM held LEFT JOIN bad ON bad.host = held.host AND bad.x = held.x),
             page AS (SELECT r, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped, string_agg(x, chr(10) ORDER BY i) FILTER (WHERE NOT gone) AS text FROM marked GROUP BY r)
        SELECT page_id, host, CAST(coalesce(n_lines, 0) AS BIGINT) AS n_lines, CAST(coalesce(n_dropped, 0) AS BIGINT) AS n_dropped, coalesce(text, '') AS text
        FROM cut LEFT JOIN page ON page.r = cut.r""",
    "op3_impact_top_k": """
        WITH v AS (SELECT row_number() OVER () AS r, vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings
                   WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
             s AS (SELECT q.r, q.vec_id AS query_id, d.vec_id, CAST(list_sum(list_transform(generate_series(1, len(q.e)), lambda i: q.e[i] * d.e[i])) AS BIGINT) AS score
                   FROM v q JOIN v d ON d.vec_id <> q.vec_id WHERE q.vec_id % 50 = 0),
             r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY r ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
        SELECT * FROM r WHERE rank <= 5""",
    "op6_mixture": rf"""
        WITH RECURSIVE sized AS (SELECT doc_id, text, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents),
             tot AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
             w AS (SELECT source, source_size, [5.0, 2.0, 1.0][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS INTEGER)]::DOUBLE AS w,
                          source_size * 2.0::DOUBLE AS cap, sum(source_size) OVER () * 1.5::DOUBLE AS budget,
                          row_number() OVER (ORDER BY source NULLS LAST) AS k FROM tot),
             f AS (SELECT *, coalesce(sum(cap) OVER o, 0) AS below, sum(w) OVER () - coalesce(sum(w) OVER o, 0) AS rest FROM w
                   WINDOW o AS (ORDER BY cap / w, k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
             lev AS (SELECT max((budget - below) / rest) AS level FROM f WHERE (budget - below) / rest < cap / w),
             t AS (SELECT source, source_size, least(cap, coalesce(level * w, cap)) AS target FROM f, lev),
             c AS (SELECT doc_id, size, source_size, target, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS rate,
                          CAST(('0x' || substr(md5('{mixing.SEED}:' || coalesce(CAST(doc_id AS VARCHAR), 'text ' || md5(coalesce(text, '')))), 1, 13)) AS BIGINT) / 4503599627370496.0::DOUBLE AS toss
                   FROM sized JOIN t ON sized.source IS NOT DISTINCT FROM t.source)
        SELECT doc_id, size, source_size, target, CAST(size * (floor(rate) + CASE WHEN toss < rate - floor(rate) THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM c""",
    "op9_url_rules": f"""
        WITH u AS (SELECT row_number() OVER () AS r, page_id, {_HOST} AS host, {_PATH} AS path FROM pages),
             rule(h, p, action) AS (VALUES {", ".join(f"('{h}', '{p}', '{a}')" for h, p, a in url_filter.HOST_RULES)}),
             fit AS (SELECT r, h || p AS rule, action, row_number() OVER (PARTITION BY r ORDER BY length(h || p) DESC, h || p) AS k
                     FROM u JOIN rule ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p)),
             pat(name, x, y, action) AS (VALUES {", ".join(f"('{n}', '{_sql_pattern(p.partition('|')[0])}', '{_sql_pattern(p.partition('|')[2])}', '{a}')" for n, p, a in url_filter.PATTERN_RULES)}),
             hit AS (SELECT r, name, action, row_number() OVER (PARTITION BY r ORDER BY name) AS k FROM u JOIN pat ON regexp_matches(host, x) AND regexp_matches(path, y))
        SELECT page_id, host, path, fit.rule AS rule, CASE WHEN fit.r IS NULL THEN name END AS pattern, coalesce(fit.action, hit.action, 'allow') AS verdict
        FROM u LEFT JOIN fit ON fit.r = u.r AND fit.k = 1 LEFT JOIN hit ON hit.r = u.r AND hit.k = 1""",
}
