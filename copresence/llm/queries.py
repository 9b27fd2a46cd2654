"""The ten operators as registered queries, each over its whole table, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontam, linededup, maskedlm, mixing, neardup, ogg, pii, sharding, tokencount, toxicity
from .common import table

Query = Callable[[SparkSession, str], DataFrame]


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents").select("doc_id"))


def op2_ogg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ogg.media_report(table(spark, sf_dir, "documents"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def op5_pseudo_likelihood(spark: SparkSession, sf_dir: str) -> DataFrame:
    return maskedlm.pseudo_likelihood(table(spark, sf_dir, "documents"))


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"))


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokencount.count_tokens(table(spark, sf_dir, "documents"))


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pii_report(table(spark, sf_dir, "documents"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.line_dedup_report(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Query] = {f.__name__: f for f in (op1_sharding, op2_ogg, op3_toxicity, op4_mixing, op5_pseudo_likelihood, op6_near_duplicates, op7_decontamination, op8_token_counts, op9_pii, op10_line_dedup)}


def _sharding_sql() -> str:
    owner = ",".join(map(str, sharding.lookup_table()))
    return f"""
    WITH t AS (SELECT doc_id, (('0x' || substr(md5(coalesce(doc_id::varchar, '')), 1, 15))::bigint % {sharding.SLOTS})::integer AS slot FROM documents)
    SELECT doc_id, slot, ([{owner}])[slot + 1]::integer AS shard FROM t"""


_MIXING_SQL = f"""
WITH d AS (
  SELECT doc_id, source, source IS NULL AS ns, coalesce(source, '') AS src,
         len(regexp_extract_all(coalesce(text, ''), '[^ \\t\\n\\v\\f\\r]+'))::bigint AS size,
         ('0x' || substr(md5('{mixing.SEED}|' || coalesce(doc_id::varchar, '')), 1, 15))::bigint AS k
  FROM documents),
s AS (SELECT ns, src, sum(size)::bigint AS total FROM d GROUP BY ns, src),
w AS (SELECT *, ([1, 2, 3])[((row_number() OVER (ORDER BY ns, src) - 1) % 3 + 1)::integer]::double AS w, 3.0::double * total AS lim FROM s),
f AS (SELECT *, lim / w AS fill FROM w),
l AS (SELECT *, ((SELECT sum(total) FROM s)::double - coalesce(sum(lim) OVER (ORDER BY fill, ns, src ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
        / sum(w) OVER (ORDER BY fill, ns, src ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM f),
o AS (SELECT arg_min(level, (fill, ns, src)) AS lv FROM l WHERE level <= fill),
t AS (SELECT ns, src, total, CASE WHEN level > fill THEN lim ELSE least(lim, w * coalesce((SELECT lv FROM o), 0)) END AS target FROM l),
p AS (SELECT d.*, total, target, CASE WHEN total > 0 THEN floor(target)::bigint // total ELSE 0 END AS epochs,
        sum(size) OVER (PARTITION BY d.ns, d.src ORDER BY k, doc_id NULLS FIRST, size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - size AS before
      FROM d JOIN t ON d.ns = t.ns AND d.src = t.src)
SELECT doc_id, source, size, total AS source_size, target, epochs::bigint AS epochs,
       (epochs * size + greatest(0, least(size, floor(target)::bigint - epochs * total - before)))::bigint AS taken FROM p"""

_LINE_SQL = f"""
WITH d AS (SELECT doc_id, md5(coalesce(text, '')) AS row, text, CASE WHEN coalesce(text, '') = '' THEN [] ELSE string_split(text, chr(10)) END AS lines FROM documents),
n AS (SELECT *, list_transform(lines, lambda x: ('0x' || substr(md5(x), 1, 6))::bigint) AS h FROM d),
q AS (SELECT *, list_transform(range(1, len(lines) + 1), lambda i: (CASE WHEN i > 1 THEN h[i - 1] * {linededup.BASE} ELSE 0 END + h[i]) % {linededup.PRIME} % {linededup.DIVISOR}) AS r FROM n),
b AS (SELECT *, list_filter(range(1, len(lines) + 1), lambda i: i = len(lines) OR (i > 1 AND r[i] = 0 AND r[i - 1] <> 0)) AS ends FROM q),
c AS (SELECT doc_id, row, ends, lines, unnest(range(1, len(ends) + 1)) AS j1 FROM b),
e AS (SELECT doc_id, row, CASE WHEN j1 > 1 THEN ends[j1 - 1] + 1 ELSE 1 END AS s, ends[j1] AS t, lines FROM c),
k AS (SELECT doc_id, row, s - 1 AS start, t - s + 1 AS n, array_to_string(lines[s:t], chr(10)) AS chunk FROM e WHERE t > s),
r AS (SELECT *, count(*) OVER (PARTITION BY chunk) AS times, rank() OVER (PARTITION BY chunk ORDER BY doc_id NULLS FIRST, row, start) AS place FROM k),
p AS (SELECT doc_id, row, lines, unnest(range(0, len(lines) - 1)) AS pos FROM d),
pr AS (SELECT doc_id, row, pos, count(*) OVER (PARTITION BY pair) AS times, rank() OVER (PARTITION BY pair ORDER BY doc_id NULLS FIRST, row, pos) AS place
       FROM (SELECT doc_id, row, pos, lines[pos + 1] || chr(10) || lines[pos + 2] AS pair FROM p)),
l AS (SELECT doc_id, row, unnest(range(start, start + n)) AS line FROM r WHERE times > 1 AND place > 1
      UNION
      SELECT doc_id, row, pos + o AS line FROM pr, (VALUES (0), (1)) AS v(o) WHERE times > 1 GROUP BY doc_id, row, pos + o HAVING NOT bool_or(place = 1)),
i AS (SELECT doc_id, row, line, line - row_number() OVER (PARTITION BY doc_id, row ORDER BY line) AS island FROM l),
z AS (SELECT doc_id, row, min(line) AS start, count(*) AS n FROM i GROUP BY doc_id, row, island),
g AS (SELECT doc_id, row, sum(n) AS gone, string_agg(start || '+' || n, ',' ORDER BY start) AS removed FROM z GROUP BY doc_id, row),
m AS (SELECT doc_id, row, list(line) AS out FROM l GROUP BY doc_id, row)
SELECT d.doc_id, len(d.lines)::bigint AS n_lines, coalesce(gone, 0)::bigint AS n_removed, coalesce(removed, '') AS removed,
       CASE WHEN g.row IS NULL THEN d.text ELSE array_to_string(list_transform(list_filter(range(0, len(d.lines)), lambda x: NOT list_contains(out, x)), lambda x: d.lines[x + 1]), chr(10)) END AS text
FROM d LEFT JOIN g ON d.doc_id IS NOT DISTINCT FROM g.doc_id AND d.row = g.row LEFT JOIN m ON d.doc_id IS NOT DISTINCT FROM m.doc_id AND d.row = m.row"""

ORACLES: dict[str, str] = {"op1_sharding": _sharding_sql(), "op4_mixing": _MIXING_SQL, "op10_line_dedup": _LINE_SQL}
