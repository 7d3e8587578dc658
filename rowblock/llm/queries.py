"""Queries over the given tables, one for each training-data operator, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import exact_dedup, line_dedup, lm_scoring, packing, piece_codec, quality_rules, simhash, token_counts, toxicity, url_filters
from .common import read

Query = Callable[[SparkSession, str], DataFrame]


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.digests(read(spark, sf_dir, "documents"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(read(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = public_tokenizers.path
    return packing.pack(read(spark, sf_dir, "documents"), path("byte_bpe_50k.json"), path("byte_bpe_50k.tiktoken"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.judge(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.membership(read(spark, sf_dir, "documents"))


def op6_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(read(spark, sf_dir, "documents"))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op9_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filters.judge(read(spark, sf_dir, "pages"), read(spark, sf_dir, "labels"))


def op10_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_codec.coded_digests(read(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


QUERIES: dict[str, Query] = {f.__name__: f for f in (op1_line_dedup, op2_token_counts, op3_packing, op4_toxicity, op5_exact_dedup, op6_lm_scoring, op7_simhash, op8_quality_rules, op9_url_filters, op10_sentencepiece)}

_AZ = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'"


def _quality_sql(control: quality_rules.RiskControl) -> str:
    """The counts, the certified cutoffs and the verdict of the quality rules."""
    grid = ", ".join(f"('{rule}', {k}, {cut}::DOUBLE)" for rule, cuts in control.grid.items() for k, cut in enumerate(cuts))
    strata = ", ".join(f"'{s}'" for s in control.strata)
    a = control.rule_alpha
    value = "CASE g.rule " + " ".join(f"WHEN '{r}' THEN {r}" for r in control.grid) + " END"
    return rf"""
        WITH words AS (
            SELECT doc_id, CASE WHEN lang IN ({strata}) THEN lang ELSE 'other' END AS stratum, t,
                   list_filter(string_split_regex(t, '[ 	-
]+'), lambda x: x <> '') AS w,
                   list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^ 	-
]')) AS l
            FROM (SELECT doc_id, lang, coalesce(text, '') AS t FROM documents)),
        windows AS (
            SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c
            FROM (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM words))),
        covered AS (
            SELECT doc_id, sum(least(8, coalesce(nxt - i, 8)))::BIGINT AS n
            FROM (SELECT doc_id, i, lead(i) OVER (PARTITION BY doc_id ORDER BY i) AS nxt FROM windows WHERE c > 1) GROUP BY doc_id),
        counts AS (
            SELECT words.doc_id, stratum, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
                   (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
                   (length(t) - length(regexp_replace(t, '\p{{Lu}}', '', 'g')))::BIGINT AS n_upper,
                   (length(t) - length(replace(t, '!', '')))::BIGINT AS n_marks, len(l)::BIGINT AS n_lines,
                   (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(n, 0)::BIGINT AS n_repeat_words
            FROM words LEFT JOIN covered ON words.doc_id = covered.doc_id),
        rates AS (
            SELECT *, CASE WHEN word_chars > 0 THEN n_symbols::DOUBLE / word_chars ELSE 0 END AS symbol_rate,
                   CASE WHEN word_chars > 0 THEN n_upper::DOUBLE / word_chars ELSE 0 END AS upper_rate,
                   CASE WHEN n_words > 0 THEN n_marks::DOUBLE / n_words ELSE 0 END AS mark_rate,
                   CASE WHEN n_lines > 0 THEN n_dup_lines::DOUBLE / n_lines ELSE 0 END AS dup_line_rate,
                   n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed
            FROM counts),
        grid(rule, step, cut) AS (VALUES {grid}),
        tried AS (
            SELECT stratum, g.rule, g.step, g.cut, count(*) FILTER (quality = 1) AS n, count(*) FILTER (quality = 1 AND {value} > g.cut) AS lost,
                   count(*) FILTER (quality <> 1 AND {value} > g.cut) AS caught
            FROM rates JOIN labels USING (doc_id), grid g WHERE quality IS NOT NULL GROUP BY ALL),
        tested AS (
            SELECT *, CASE WHEN lost >= n * {a} THEN 1.0 ELSE
                   list_sum(list_transform(range(0, lost + 1), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln({a}) + (n - i) * ln(1 - {a})))) END <= {control.rule_delta} AS passed
            FROM tried),
        certified AS (
            SELECT *, caught - {control.loss_weight} * lost AS gain, bool_and(passed) OVER (PARTITION BY stratum, rule ORDER BY step) AS ok FROM tested),
        cuts AS (
            SELECT stratum, rule, max_by(cut, gain * 1000 - step) AS cut FROM certified WHERE ok AND gain > 0 GROUP BY stratum, rule),
        over AS (
            SELECT DISTINCT doc_id FROM rates JOIN cuts g USING (stratum) WHERE {value} > g.cut)
        SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
               NOT base_failed AND doc_id NOT IN (SELECT doc_id FROM over) AS kept
        FROM rates
    """


def _reputation_sql(rules: tuple, c: url_filters.Reputation) -> str:
    """Rules first, then the verdict on the host."""
    by_length = sorted(rules, key=lambda r: -len(r[0] + r[1]))
    fits = lambda own, start: f"(host = '{own}' OR ends_with(host, '.{own}')) AND starts_with(path, '{start}')"
    rule = "CASE " + " ".join(f"WHEN {fits(o, s)} THEN '{o}{s}'" for o, s, _ in by_length) + " END"
    says = "CASE " + " ".join(f"WHEN {fits(o, s)} THEN '{v}'" for o, s, v in by_length) + " END"
    two = ", ".join(f"'{x}'" for x in c.suffixes)
    strength = lambda t: f"(SELECT 1 / greatest({c.least_rho}, least({c.most_rho}, coalesce(CASE WHEN sum(n) / count(*) > 1 THEN (sum(n * (bad / n - prior) ** 2) / sum(n * prior * (1 - prior)) - count(*) / sum(n)) / (1 - count(*) / sum(n)) END, {c.most_rho}))) - 1 FROM {t} WHERE n > 0)"
    return rf"""
        WITH split AS (
            SELECT page_id, translate(regexp_extract(coalesce(url, ''), '{url_filters.URL}', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
                   regexp_extract(coalesce(url, ''), '{url_filters.URL}', 2) AS path FROM pages),
        outcomes AS (
            SELECT doc_id AS page_id, (coalesce(quality = 0, false) OR coalesce(toxic = 1, false))::DOUBLE AS bad FROM labels WHERE quality IS NOT NULL OR toxic IS NOT NULL),
        sites AS (
            SELECT *, string_split(site, '.') AS l, regexp_matches(site, '{url_filters.ADDRESS}') AS ip, array_to_string(string_split(site, '.')[-2:], '.') IN ({two}) AS two
            FROM (SELECT *, regexp_replace(host, '^.*@|:[0-9]*$', '', 'g') AS site FROM split)),
        hosts AS (
            SELECT site, CASE WHEN ip THEN site WHEN two THEN array_to_string(l[-3:], '.') ELSE array_to_string(l[-2:], '.') END AS domain,
                   CASE WHEN ip THEN site WHEN two THEN array_to_string(l[-2:], '.') ELSE l[-1] END AS suffix, count(bad)::DOUBLE AS n, coalesce(sum(bad), 0)::DOUBLE AS bad
            FROM sites LEFT JOIN outcomes USING (page_id) GROUP BY ALL),
        s0 AS (SELECT suffix, sum(n) AS n, sum(bad) AS bad, (SELECT greatest(1e-6, least(1 - 1e-6, coalesce(sum(bad) / nullif(sum(n), 0), {c.rate_without_labels}))) FROM hosts) AS prior FROM hosts GROUP BY suffix),
        s1 AS (SELECT suffix, (bad + k * prior) / (n + k) AS prior FROM (SELECT *, {strength("s0")} AS k FROM s0)),
        d0 AS (SELECT domain, suffix, n, bad, prior FROM (SELECT domain, suffix, sum(n) AS n, sum(bad) AS bad FROM hosts GROUP BY ALL) JOIN s1 USING (suffix)),
        d1 AS (SELECT domain, suffix, (bad + k * prior) / (n + k) AS prior FROM (SELECT *, {strength("d0")} AS k FROM d0)),
        h0 AS (SELECT site, n, bad, prior FROM hosts JOIN d1 USING (domain, suffix)),
        h1 AS (SELECT site, n + k + 1 AS m, (bad + k * prior) / (n + k) AS mean FROM (SELECT *, {strength("h0")} AS k FROM h0))
        SELECT page_id, host, path, {rule} AS rule, coalesce({says}, CASE WHEN site <> '' AND mean - {c.z} * sqrt(mean * (1 - mean) / m) > {c.limit} THEN 'block' ELSE 'allow' END) AS verdict
        FROM sites JOIN h1 USING (site)
    """


def _line_dedup_sql(c: line_dedup.Chunking) -> str:
    """Chunks by rolling hashes over lines, windows of two lines, the repeats of both by complete text, and what is left."""
    return rf"""
        WITH lines AS (
            SELECT doc_id, i, line, ('0x' || left(md5(line), 8))::BIGINT AS h
            FROM (SELECT doc_id, unnest(l) AS line, generate_subscripts(l, 1) - 1 AS i FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents))),
        rolled AS (
            SELECT *, lag(h, 2) OVER w * {c.base} + lag(h, 1) OVER w AS r, line || chr(10) || lead(line) OVER w AS pair FROM lines WINDOW w AS (PARTITION BY doc_id ORDER BY i)),
        numbered AS (
            SELECT *, sum(CASE WHEN i >= 2 AND r % {c.modulus} < {c.cut} THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY i) AS k FROM rolled),
        chunks AS (
            SELECT doc_id, k, min(i) AS first, count(*) AS n, string_agg(line, chr(10) ORDER BY i) AS t FROM numbered GROUP BY doc_id, k),
        judged AS (
            SELECT *, n >= 2 AND replace(t, chr(10), '') <> '' AND row_number() OVER (PARTITION BY t, n >= 2 ORDER BY doc_id, first) > 1 AS gone FROM chunks),
        pairs AS (
            SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY pair ORDER BY doc_id, i) AS o FROM rolled WHERE pair <> chr(10)) WHERE o > 1),
        kept AS (
            SELECT numbered.*, gone FROM numbered JOIN judged USING (doc_id, k)
            WHERE NOT gone AND (doc_id, i) NOT IN (SELECT (doc_id, i) FROM pairs) AND (doc_id, i - 1) NOT IN (SELECT (doc_id, i) FROM pairs)),
        texts AS (
            SELECT doc_id, count(*) AS n, string_agg(line, chr(10) ORDER BY i) AS t FROM kept GROUP BY doc_id)
        SELECT doc_id, sum(judged.n)::BIGINT AS n_lines, count(*)::BIGINT AS n_chunks, count(*) FILTER (gone)::BIGINT AS removed_chunks, (sum(judged.n) - coalesce(any_value(texts.n), 0))::BIGINT AS removed_lines,
               length(coalesce(any_value(texts.t), ''))::BIGINT AS kept_chars, md5(coalesce(any_value(texts.t), '')) AS text_md5
        FROM judged LEFT JOIN texts USING (doc_id) GROUP BY doc_id
    """


ORACLES: dict[str, str] = {
    "op1_line_dedup": _line_dedup_sql(line_dedup.Chunking()),
    "op5_exact_dedup": f"""
        SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(t) AS text_sha256
        FROM (SELECT doc_id, t, max(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size
              FROM (SELECT doc_id, translate(coalesce(text, ''), {_AZ}) AS t FROM documents))
    """,
    "op8_quality_rules": _quality_sql(quality_rules.RiskControl()),
    "op9_url_filters": _reputation_sql(url_filters.RULES, url_filters.Reputation()),
}
