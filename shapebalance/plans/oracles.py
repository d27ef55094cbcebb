"""DuckDB SQL of the registered queries, put together from common table expressions."""

from __future__ import annotations

from ..operators.batching import LADDER
from .model import SEED, Bounds, CostModel

B, M = Bounds(), CostModel()

CLIPS = """
clip_q AS (SELECT l_orderkey, sum(l_quantity) AS q FROM lineitem GROUP BY l_orderkey),
clip_f AS (
  SELECT o_orderkey AS sample_id,
    CASE WHEN o_orderstatus = 'P' OR least(32, CAST(floor(coalesce(q, 0) / 8) AS INTEGER)) <= 0 THEN 1 ELSE 1 + 8 * least(32, CAST(floor(coalesce(q, 0) / 8) AS INTEGER)) END AS f,
    CASE o_orderpriority WHEN '1-URGENT' THEN 640 WHEN '2-HIGH' THEN 480 WHEN '3-MEDIUM' THEN 384 WHEN '4-NOT SPECIFIED' THEN 320 ELSE 256 END AS h,
    CASE o_orderpriority WHEN '1-URGENT' THEN 640 WHEN '2-HIGH' THEN 832 WHEN '3-MEDIUM' THEN 640 WHEN '4-NOT SPECIFIED' THEN 512 ELSE 256 END AS w
  FROM orders LEFT JOIN clip_q ON l_orderkey = o_orderkey
),
clips AS (
  SELECT sample_id, CASE WHEN f = 1 THEN 'image' ELSE 'video' END AS modality, f, h, w, CAST(0 AS BIGINT) AS s_text,
    CAST((((f - 1) // 8) + 1) * (h // 16) * (w // 16) AS BIGINT) AS s_visual, CAST((((f - 1) // 8) + 1) * (h // 16) * (w // 16) AS BIGINT) AS s,
    concat(f, 'x', h, 'x', w) AS bucket_id
  FROM clip_f
)"""


STRIPPED = "regexp_replace(html, '<[^>]*>', ' ', 'g')"


def words(column: str) -> str:
    return f"greatest(1, len(list_filter(string_split_regex(coalesce({column}, ''), '[ \\t\\n\\r]+'), lambda x: x <> '')))"


def stats(samples: str = "clips", s: str = "max(s)") -> str:
    return f"stats AS (SELECT bucket_id, count(*) AS n, CAST(sum(s) AS BIGINT) AS sum_s, min(s) AS min_s, max(s) AS max_s, {s} AS s FROM {samples} GROUP BY bucket_id)"


def size(policy: str, b: Bounds = B, fixed: int = 4, s: str = "s") -> str:
    power = f"(CAST({s} AS DOUBLE) * {s})" if b.p == 2 else f"pow(CAST({s} AS DOUBLE), {b.p})"
    mem, comp = f"CAST(floor({b.m_mem} / {s}) AS BIGINT)", f"CAST(floor({b.m_comp} / {power}) AS BIGINT)"
    return f"greatest(1, {({'dual': f'least({mem}, {comp})', 'memory': mem, 'equal_token': mem, 'compute': comp, 'fixed': str(fixed)})[policy]})"


BOUND = f"CASE WHEN floor({B.m_mem} / s) < 1 OR floor({B.m_comp} / (CAST(s AS DOUBLE) * s)) < 1 THEN 'unit' WHEN floor({B.m_mem} / s) < floor({B.m_comp} / (CAST(s AS DOUBLE) * s)) THEN 'memory' WHEN floor({B.m_comp} / (CAST(s AS DOUBLE) * s)) < floor({B.m_mem} / s) THEN 'compute' ELSE 'tie' END"


def batches(policy: str, bounds: Bounds = B, name: str = "batches") -> str:
    x = name
    return f"""
{x}_plan AS (SELECT bucket_id, s, CAST({size(policy, bounds)} AS BIGINT) AS plan_b FROM stats),
{x}_rank AS (SELECT sample_id, bucket_id, s AS own_s, row_number() OVER (PARTITION BY bucket_id ORDER BY md5(concat('{SEED}:', sample_id))) - 1 AS r FROM clips),
{x} AS (
  SELECT concat(p.bucket_id, '#', r // plan_b) AS batch_id, p.bucket_id, CAST(r // plan_b AS BIGINT) AS batch_no, p.s, count(*) AS b, plan_b, count(*) * p.s AS tokens, CAST(sum(own_s) AS BIGINT) AS real_tokens
  FROM {x}_rank k JOIN {x}_plan p ON p.bucket_id = k.bucket_id GROUP BY p.bucket_id, r // plan_b, p.s, plan_b
)"""


def steps(n: int, policy: str = "random", source: str = "batches", name: str = "steps", model: CostModel = M) -> str:
    order = {"random": f"md5(concat('{SEED}:', batch_id))", "round_robin": "bucket_id, batch_no", "load_sorted": f"b * pow(CAST(s AS DOUBLE), 2.0) DESC, md5(concat('{SEED}:', batch_id))"}
    if policy == "bucket_hash":
        rank = f"CAST(CAST(concat('0x', substr(md5(concat('{SEED}:', bucket_id)), 1, 8)) AS BIGINT) % {n} AS INTEGER)"
        g = f"SELECT *, row_number() OVER (PARTITION BY {rank} ORDER BY md5(concat('{SEED}:', batch_id))) - 1 AS step, {rank} AS rank FROM {source}"
    else:
        g = f"SELECT * EXCLUDE (g), CAST(g // {n} AS BIGINT) AS step, CAST(g % {n} AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (ORDER BY {order[policy]}) - 1 AS g FROM {source})"
    return f"""
{name}_g AS ({g}),
{name} AS (
  SELECT *, count(*) OVER (PARTITION BY step) = {n} AS "full", b * (CAST(s AS DOUBLE) * s) AS load, {model.a} + {model.b} * (b * (CAST(s AS DOUBLE) * s)) AS t,
    max({model.a} + {model.b} * (b * (CAST(s AS DOUBLE) * s))) OVER (PARTITION BY step) AS t_sync
  FROM {name}_g
)"""


def run(policy: str, n: int, steps_policy: str = "random", name: str = "steps") -> str:
    return f"{batches(policy, name=f'{name}_b')}, {steps(n, steps_policy, f'{name}_b', name)}"


def text_run(corpus: str, policy: str, n: int, bounds: Bounds, model: CostModel, select: str) -> str:
    """A run over text lengths in geometric buckets; `select` reads it from steps."""
    source = {
        "documents": f"SELECT doc_id AS id, CAST({words('text')} AS BIGINT) AS s FROM documents", "benchmark": f"SELECT item_id AS id, CAST({words('text')} AS BIGINT) AS s FROM benchmark",
        "conversations": f"SELECT conv_id AS id, CAST(sum({words('text')}) AS BIGINT) AS s FROM conversations GROUP BY conv_id", "pages": f"SELECT page_id AS id, CAST({words(STRIPPED)} AS BIGINT) AS s FROM pages",
    }
    own = f"clips AS (SELECT id AS sample_id, s, top, concat('g', top) AS bucket_id FROM (SELECT id, s, CAST(CASE WHEN s <= 1 THEN 1 ELSE 1 << length(bin(s - 1)) END AS BIGINT) AS top FROM ({source[corpus]})))"
    return f"SELECT * FROM ({with_(own, stats('clips', 'max(top)'), batches(policy, bounds, 'own'), steps(n, 'random', 'own', 'steps', model), select=select)})"


def with_(*ctes: str, select: str) -> str:
    return f"WITH {', '.join(ctes)} {select}"


TRACE = """
trace AS (
  SELECT event_id, CAST(event_id % 7 AS INTEGER) AS rep, CAST(user_id % 8 AS INTEGER) AS rank, 1 + user_id % 4 AS b, CAST(512 * (CAST(json_extract(props, '$.k') AS INTEGER) + 1) AS BIGINT) AS s,
    2.0 + 1.2 * (1 + user_id % 4) * pow(512 * (CAST(json_extract(props, '$.k') AS INTEGER) + 1) / 10000.0, 2.1) * (1 + 0.05 * (least(value, 200.0) - 50) / 50) AS t
  FROM events
),
matrix AS (SELECT b, s, count(*) AS n, avg(t) AS t FROM (SELECT rep, b, s, max(t) AS t FROM trace GROUP BY rep, b, s) GROUP BY b, s)"""

FITS = """
fits AS (
  SELECT p, count(*) AS n, regr_intercept(t, x) AS a, regr_slope(t, x) AS slope, regr_r2(t, x) AS r2
  FROM (SELECT b, s, t, round(1.6 + i * 0.01, 6) AS p, b * pow(s / 10000.0, round(1.6 + i * 0.01, 6)) AS x FROM matrix, (SELECT unnest(range(0, 81)) AS i)) GROUP BY p
),
best AS (SELECT * FROM fits ORDER BY round(r2, 9) DESC, p LIMIT 1)"""

LONG = """
params AS (SELECT label, d, ((64 * label + 11 * d) % 19 - 9) / 32.0 AS shift, ((64 * label + 7 * d) % 17 - 8) / 64.0 AS scale, ((64 * label + 5 * d) % 13) / 16.0 AS gate FROM (SELECT DISTINCT label FROM embeddings), (SELECT unnest(range(0, 64)) AS d)),
tok AS (SELECT vec_id, label, d, CAST(embedding[d + 1] AS DOUBLE) AS x, ((31 * vec_id + 17 * d) % 101 - 50) / 128.0 AS dy FROM (SELECT *, unnest(range(0, len(embedding))) AS d FROM embeddings)),
stat AS (SELECT vec_id, avg(x) AS mu, 1 / sqrt(var_pop(x) + 1e-6) AS rstd FROM tok GROUP BY vec_id),
norm AS (SELECT t.*, s.mu, s.rstd, (x - mu) * rstd AS xhat FROM tok t JOIN stat s ON s.vec_id = t.vec_id)"""

LADDER_SQL = ", ".join(map(str, LADDER))
