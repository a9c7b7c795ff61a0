"""Query op7_mixing."""

from __future__ import annotations

from math import log

from pyspark.sql import DataFrame, SparkSession

from tidegraph.llm.common import table
from tidegraph.llm.mixing import _PASSES, _STEPS, _TINY, Mixing, mix


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mix(table(spark, sf_dir, "documents").select("doc_id", "source", "text"))
    return mixed.select("row.doc_id", "source", "n_tokens", "epoch", "block", "place")


def _search(name: str, holds: str) -> str:
    """Common table expressions that narrow (lo, hi) in passes; the last is {name}."""
    out = [f"{name}0 AS (SELECT 0::DOUBLE AS lo, 1::DOUBLE AS hi)"]
    for i in range(_PASSES):
        out.append(f"""{name}{i}t AS (
  SELECT i, any_value(lo) AS lo, any_value(hi) AS hi, sum(exp((lo + i * ((hi - lo) / {_STEPS})) * p)) AS z,
    sum(exp((lo + i * ((hi - lo) / {_STEPS})) * p) * (lo + i * ((hi - lo) / {_STEPS})) * p) AS m, max(exp((lo + i * ((hi - lo) / {_STEPS}) - 1) * p)) AS r
  FROM shares, {name}{i}, (SELECT unnest(range(0, {_STEPS + 1})) AS i) GROUP BY i),
{name}{i + 1} AS (
  SELECT CASE WHEN k = {_STEPS} THEN hi ELSE lo + k * ((hi - lo) / {_STEPS}) END AS lo, CASE WHEN k = {_STEPS} THEN hi ELSE lo + (k + 1) * ((hi - lo) / {_STEPS}) END AS hi
  FROM (SELECT any_value(lo) AS lo, any_value(hi) AS hi, coalesce(max(CASE WHEN {holds} THEN i END), 0) AS k FROM {name}{i}t, wanted))""")
    return ",\n".join(out)


_HOW = Mixing()
_HASH = "('0x' || substr(md5({}), 1, 15))::BIGINT"
SQL = rf"""
WITH docs AS MATERIALIZED (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS n_tokens FROM documents),
sources AS MATERIALIZED (SELECT source, sum(n_tokens)::BIGINT AS t FROM docs GROUP BY source HAVING sum(n_tokens) > 0),
whole AS MATERIALIZED (SELECT sum(t)::BIGINT AS total, count(*) AS c FROM sources),
shares AS MATERIALIZED (SELECT source, t, ln(t / total::DOUBLE) AS p FROM sources, whole),
wanted AS (SELECT {_HOW.target_entropy!r} * ln(c) AS w FROM whole),
{_search("e", f"ln(z) - m / z >= w - {_TINY!r}")},
{_search("r", f"{_HOW.budget_share!r} * r / z > {_HOW.most_repeats!r}")},
chosen AS MATERIALIZED (SELECT greatest(e{_PASSES}.lo, CASE WHEN r{_PASSES}.lo > 0 THEN r{_PASSES}.lo + {_STEPS**-_PASSES!r} ELSE 0 END) AS a FROM e{_PASSES}, r{_PASSES}),
zed AS MATERIALIZED (SELECT sum(exp(a * p)) AS z FROM shares, chosen),
plan AS MATERIALIZED (
  SELECT source, t, floor(exp(a * p) / z * floor({_HOW.budget_share!r} * total)::DOUBLE + 1e-6)::BIGINT AS quota,
    greatest(1, ceil(floor({_HOW.budget_share!r} * total) / {float(_HOW.block_tokens)!r}))::BIGINT AS blocks
  FROM shares, chosen, zed, whole),
laid AS (
  SELECT *, {_HASH.format(f"'{_HOW.seed}:' || epoch || ':' || coalesce(doc_id::VARCHAR, '')")} AS h
  FROM (SELECT d.*, t, quota, blocks, unnest(range(0, quota // t + 1)) AS epoch FROM docs d JOIN plan p ON d.source IS NOT DISTINCT FROM p.source WHERE quota > 0)
  WHERE epoch * t < quota),
summed AS (
  SELECT *, epoch * t + sum(n_tokens) OVER (PARTITION BY source, epoch ORDER BY h, doc_id::VARCHAR, n_tokens ROWS UNBOUNDED PRECEDING)::BIGINT AS upto FROM laid)
SELECT doc_id, source, n_tokens, epoch::INTEGER AS epoch, least(blocks - 1, floor((upto - n_tokens) / quota::DOUBLE * blocks))::BIGINT AS block,
  {_HASH.format("'place:' || h")} AS place
FROM summed WHERE upto <= quota
"""
