"""Queries of the training-data operators, each over its whole table, and their SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable
from secrets import token_hex

from pyspark.sql import DataFrame, SparkSession

from . import capfilter, host_rules, langid, licenses, mixing, packing, pii, quality, secrets, simhash


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op4_host_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    judged = host_rules.judge(docs, keep=["doc_id"])
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op5_simhash_bktree(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    named = simhash.near_duplicates(docs, keep=["doc_id"])
    return named.select("doc_id", simhash.as_hex("fp").alias("fingerprint"), "component_id")


def op6_splitting_tree_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return mixing.mix(docs, keep=["doc_id"])


def op9_shortest_pack_first(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"))


def op1_subword_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.score_documents(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op3_hyperdim_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.predict_documents(_table(spark, sf_dir, "documents"))


def op10_license_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(_table(spark, sf_dir, "documents"), keep=["doc_id"])


def op7_cap_filter_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return capfilter.near_duplicates(_table(spark, sf_dir, "embeddings"))


def op8_forest_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(_table(spark, sf_dir, "documents"))


#: The session's key of pseudonyms; where none is set, a run draws its own, so that nobody can invert its pseudonyms.
PII_KEY = "spark.bucketcsr.pii.key"


def op2_feistel_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    key = spark.conf.get(PII_KEY, None) or token_hex(32)
    return pii.pseudonymise(_table(spark, sf_dir, "documents"), key, keep=["doc_id"])


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_subword_quality": op1_subword_quality,
        "op2_feistel_pii": op2_feistel_pii,
        "op3_hyperdim_langid": op3_hyperdim_langid,
        "op4_host_rules": op4_host_rules,
        "op5_simhash_bktree": op5_simhash_bktree,
        "op6_splitting_tree_mix": op6_splitting_tree_mix,
        "op7_cap_filter_neardup": op7_cap_filter_neardup,
        "op8_forest_secrets": op8_forest_secrets,
        "op9_shortest_pack_first": op9_shortest_pack_first,
        "op10_license_index": op10_license_index,
    }


def oracle_sql() -> dict[str, str]:
    return {"op4_host_rules": OP4_SQL, "op7_cap_filter_neardup": OP7_SQL}


#: Failures of each rule in SQL, in the order of host_rules.failures.
_FAILED = {
    "short": "n_words < 20",
    "repeats": "100 * n_repeat_words > 30 * n_words",
    "symbols": "10 * n_symbols > n_words",
    "dup_lines": "10 * n_dup_lines > 3 * n_lines",
    "word_size": "word_chars < 2 * n_words OR word_chars > 15 * n_words",
}
_LONG = " UNION ALL ".join(f"SELECT '{r}' AS rule, source, ({c})::INT AS bad FROM base" for r, c in _FAILED.items())

#: Text counts in list arithmetic; the verdict of hosts by the same moments as the operator's, one row per host and rule.
OP4_SQL = rf"""
WITH d AS (
  SELECT doc_id, source, coalesce(text, '') AS t,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
lines AS (
  SELECT doc_id, source, t, w, list_filter(string_split(t, chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS ls FROM d),
numbered AS (SELECT row_number() OVER () AS rn, * FROM lines),
wins AS (
  SELECT rn, i, w[i : i + 7] AS win FROM (SELECT rn, w, unnest(range(1, len(w) - 6)) AS i FROM numbered WHERE len(w) >= 8)),
dups AS (SELECT rn, i FROM (SELECT rn, i, count(*) OVER (PARTITION BY rn, win) AS c FROM wins) WHERE c > 1),
cover AS (SELECT rn, count(DISTINCT p) AS n_rep FROM (SELECT rn, unnest(range(i, i + 8)) AS p FROM dups) GROUP BY rn),
base AS (
  SELECT n.doc_id, n.source, len(w)::BIGINT AS n_words,
         coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
         length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
         (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, len(ls)::BIGINT AS n_lines,
         coalesce(c.n_rep, 0)::BIGINT AS n_repeat_words
  FROM numbered n LEFT JOIN cover c USING (rn)),
judged AS (SELECT *, ({_FAILED['short']} OR {_FAILED['repeats']}) AS base_failed FROM base),
hosts AS (SELECT rule, source, count(*)::DOUBLE AS n, sum(bad)::DOUBLE AS bad FROM ({_LONG}) GROUP BY rule, source),
total AS (SELECT rule, sum(n) AS n, count(*)::DOUBLE AS k, sum(n * n) AS sq, least(greatest(sum(bad) / sum(n), 1e-6), 1 - 1e-6) AS m FROM hosts GROUP BY rule),
spread AS (SELECT h.rule, sum(h.n * pow(h.bad / h.n - t.m, 2)) AS s FROM hosts h JOIN total t USING (rule) GROUP BY h.rule),
between_hosts AS (
  SELECT t.*, CASE WHEN t.n - t.sq / t.n > 0 THEN greatest(0.0, (s.s - (t.k - 1) * t.m * (1 - t.m)) / (t.n - t.sq / t.n)) ELSE 0.0 END AS v
  FROM total t JOIN spread s USING (rule)),
prior AS (SELECT rule, m, greatest(2.0, least(CASE WHEN v > 0 THEN m * (1 - m) / v - 1 ELSE n / k END, n / k)) AS strength FROM between_hosts),
shrunk AS (SELECT h.source, h.n, p.*, (h.bad + p.m * p.strength) / (h.n + p.strength) AS rate FROM hosts h JOIN prior p USING (rule)),
rejected AS (
  SELECT DISTINCT source FROM shrunk
  WHERE n >= 20 AND rate - 3 * sqrt(rate * (1 - rate) / (n + strength + 1)) > least(CASE WHEN rule IN ('short', 'repeats') THEN 0.8 ELSE 2 END, greatest(0.5, m + 2 * sqrt(m * (1 - m) / (strength + 1)))))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND NOT EXISTS (SELECT 1 FROM rejected r WHERE r.source IS NOT DISTINCT FROM judged.source) AS kept
FROM judged
"""

#: All pairs of equal labels, and everything that links reach; for small tables.
OP7_SQL = """
WITH RECURSIVE v AS (
  SELECT row_number() OVER () AS rn, vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
fine AS (
  SELECT * FROM v WHERE label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0
  AND len(list_filter(e, lambda x: x <> 0)) > 0),
links AS (
  SELECT a.rn AS x, b.rn AS y FROM fine a JOIN fine b ON a.label = b.label AND a.rn <> b.rn AND len(a.e) = len(b.e)
  WHERE list_cosine_similarity(a.e, b.e) >= 0.98),
reach AS (SELECT rn AS s, rn AS t FROM v UNION SELECT r.s, l.y FROM reach r JOIN links l ON r.t = l.x),
named AS (SELECT r.s, min(v.vec_id) AS component_id FROM reach r JOIN v ON v.rn = r.t GROUP BY r.s)
SELECT v.vec_id, (SELECT count(*) FROM links l WHERE l.x = v.rn) AS n_links, n.component_id, v.vec_id = n.component_id AS kept
FROM v JOIN named n ON n.s = v.rn
"""
