"""Shared pieces of the registered queries: tables, pools and the same in SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from poolcurator.sources.adapters import chat_pairs, from_documents, pool_of, read_spread, read_table

SEED = 42
__all__ = ["SEED", "chat_pairs", "docs", "pool_of", "read_table", "r6", "read_spread", "samples", "spread_samples", "K_RULE"]


def docs(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "documents")


def samples(spark: SparkSession, d: str) -> DataFrame:
    return from_documents(docs(spark, d))


def spread_samples(spark: SparkSession, d: str) -> DataFrame:
    """The documents as samples, dealt to all cores, for queries that work through every word."""
    return from_documents(read_spread(spark, d, "documents", "doc_id"))


def r6(c: Column | str) -> Column:
    return F.round(c, 6)


K_RULE = 100

# ---- the same in DuckDB --------------------------------------------------------------------------

NOISE_SQL = r"[^\p{L}\p{M}\p{N}_\s.,;!?()/，．；！？（）／。]"


def share_sql(c: str, cls: str) -> str:
    return f"CASE WHEN length({c}) > 0 THEN (length({c}) - length(regexp_replace({c}, '(?:{cls})+', '', 'g'))) / length({c}) ELSE 0.0 END"


def uniform_sql(c: str, salt: str) -> str:
    return f"(('0x' || substr(md5('{salt}:' || cast({c} AS varchar)), 1, 8))::bigint / 4294967296.0)"


def key_sql(c: str, seed: int | str = SEED) -> str:
    return f"md5('{seed}:' || cast({c} AS varchar))"


TOKENS_SQL = r"regexp_extract_all(lower({c}), '[\p{{L}}\p{{N}}]+')"


def tokens_sql(c: str) -> str:
    return TOKENS_SQL.format(c=c)


FDOC = """fdoc AS (SELECT doc_id AS sample_id, split_part(text, chr(10), 1) AS instruction, '' AS input,
  CASE WHEN contains(text, chr(10)) THEN substr(text, strpos(text, chr(10)) + 1) ELSE '' END AS output,
  text, lang, source, n_chars FROM documents)"""

UNIQUE_SQL = "CASE WHEN len({t}) > 0 THEN len(list_distinct({t})) / len({t}) ELSE 0.0 END"


def unique_sql(c: str) -> str:
    return UNIQUE_SQL.format(t=tokens_sql(c))


BUCKETS_SQL = """SELECT {id} AS id, ('0x' || substr(md5(g), 1, 4))::int % 256 AS bucket, count(*) AS n
  FROM (SELECT {id}, unnest(list_concat(regexp_extract_all(lower({c}), '(?s)..'), regexp_extract_all(substr(lower({c}), 2), '(?s)..'))) AS g FROM {t} WHERE length({c}) >= 2) GROUP BY ALL"""
VEC_SQL = """list_transform(range(16), lambda i: CASE WHEN len({t}) > 0 THEN len(list_filter(list_transform({t}, lambda w: ('0x' || substr(md5(w), 1, 4))::int % 16), lambda b: b = i)) / len({t}) ELSE 0.0 END)"""


def fitted_sql(table: str) -> str:
    """CTEs of the count models fitted on a table's outputs: pairs(h, w, n), vv(v), ctx(h, total, ent), uni(w, n)."""
    return f"""tok AS (SELECT sample_id, {tokens_sql('output')} AS y, {tokens_sql('instruction')} AS x FROM {table}),
fitrows AS (SELECT unnest(list_concat(['<s>'], y[1:len(y) - 1])) AS h, unnest(y) AS w FROM tok WHERE len(y) > 0),
pairs AS (SELECT h, w, count(*) AS n FROM fitrows GROUP BY h, w),
uni AS (SELECT w, sum(n) AS n FROM pairs GROUP BY w),
vv AS (SELECT count(DISTINCT w) + 1 AS v FROM pairs),
tot AS (SELECT h, sum(n) AS total, count(*) AS kinds FROM pairs GROUP BY h),
ctx AS (SELECT h, any_value(total) AS total,
  sum(-(n + 0.1) / (total + 0.1 * v) * ln((n + 0.1) / (total + 0.1 * v))) - any_value((v - kinds) * (0.1 / (total + 0.1 * v)) * ln(0.1 / (total + 0.1 * v))) AS ent
  FROM pairs JOIN tot USING (h), vv GROUP BY h)"""


#: The bigram model of all documents and every token of every document: rows(sample_id, pos, h, w), scored(.., p, ent).
LM = f"""{FDOC},
{fitted_sql('fdoc')},
rows AS (SELECT sample_id, unnest(range(len(y))) AS pos, unnest(list_concat([coalesce(x[-1], '<s>')], y[1:len(y) - 1])) AS h, unnest(y) AS w FROM tok WHERE len(y) > 0),
scored AS (SELECT sample_id, pos, rows.h, rows.w, (coalesce(n, 0) + 0.1) / (coalesce(total, 0) + 0.1 * v) AS p, coalesce(ent, ln(v)) AS ent
  FROM rows LEFT JOIN ctx USING (h) LEFT JOIN pairs ON pairs.h = rows.h AND pairs.w = rows.w, vv)"""
