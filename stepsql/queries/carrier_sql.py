"""The carriers as DuckDB text, for the SQL that checks queries over them."""

from __future__ import annotations

from stepsql.sources.carriers import LINE_ORDER

ORDERS = f"""
numbered AS (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY {", ".join(LINE_ORDER)})::INTEGER AS step_no FROM lineitem),
trail AS (
  SELECT o_custkey AS qid, o_orderkey AS traj_id, step_no, (1 + l_quantity::INTEGER % 5)::INTEGER AS n_tokens,
    greatest(0.01, least(0.99, 1 - 5 * l_discount)) AS score, 0.05 + l_tax AS h_step, (o_orderstatus = 'F')::INTEGER AS outcome
  FROM numbered JOIN orders ON l_orderkey = o_orderkey)"""

TOKENS = """
e AS (
  SELECT event_id, ts, user_id, value, event_type AS token,
    coalesce(lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id), '^') AS prev FROM events),
pairs AS (SELECT prev, token, count(*) AS n FROM e GROUP BY ALL),
policy AS (SELECT prev, token, n, n / sum(n) OVER (PARTITION BY prev) AS p FROM pairs),
entropies AS (SELECT prev, -sum(p * ln(p)) AS entropy FROM policy GROUP BY prev),
reference AS (SELECT token, k / sum(k) OVER () AS q FROM (SELECT token, count(*) AS k FROM e GROUP BY token)),
tokens AS (
  SELECT user_id AS qid, user_id || '-' || (date_diff('day', DATE '2024-01-01', ts::DATE) // 7) AS traj_id, ts::DATE AS day,
    ts, event_id, token, prev, value, ln(p) AS logp, ln(q) AS logp_ref, entropy
  FROM e JOIN policy USING (prev, token) JOIN entropies USING (prev) JOIN reference USING (token))"""

EVENTS = TOKENS + """,
days AS (
  SELECT qid, traj_id, day, count(*)::INTEGER AS n_tokens, avg(value) AS v, avg(entropy) AS h_step, arg_max(token, (ts, event_id)) AS last
  FROM tokens GROUP BY ALL),
trail AS (
  SELECT qid, traj_id, row_number() OVER w::INTEGER AS step_no, n_tokens, v / (1 + v) AS score, h_step,
    (last_value(last) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) = 'purchase')::INTEGER AS outcome
  FROM days WINDOW w AS (PARTITION BY qid, traj_id ORDER BY day))"""

LINES = """
completions AS (
  SELECT source AS qid, d.doc_id AS traj_id, string_split(text, chr(10)) AS steps, quality AS outcome
  FROM documents d JOIN labels USING (doc_id)),
places AS (SELECT qid, traj_id, outcome, steps, unnest(range(1, len(steps) + 1)) AS depth FROM completions),
visits AS (SELECT qid, traj_id, outcome, depth, array_to_string(steps[1:depth], chr(31)) AS prefix, depth = len(steps) AS leaf FROM places)"""


def rewards(trail: str = ORDERS, mode: str = "cumulative", scope: str = "trajectory", agg: str = "sum", weight: bool = True) -> str:
    """CTEs up to `rewarded`, with w, prefix_score and reward."""
    run = "(PARTITION BY qid, traj_id ORDER BY step_no ROWS UNBOUNDED PRECEDING)"
    h = {"cumulative": f"sum(h_step) OVER {run}", "step": "h_step", "mean_prefix": f"avg(h_step) OVER {run}"}[mode]
    top = {"trajectory": "max(h_prefix) OVER (PARTITION BY qid, traj_id)", "group": "max(h_prefix) OVER (PARTITION BY qid)", "corpus": "(SELECT max(h_prefix) FROM hs)"}[scope]
    w = "CASE WHEN h_max > 0 THEN 1 - h_prefix / h_max ELSE 1.0 END" if weight else "1.0::DOUBLE"
    last = {"sum": f"sum(prefix_score) OVER {run}", "mean": f"avg(prefix_score) OVER {run}", "last": "prefix_score"}[agg]
    return f"""{trail},
hs AS (SELECT *, {h} AS h_prefix FROM trail),
tops AS (SELECT *, {top} AS h_max FROM hs),
ws AS (SELECT *, {w} AS w FROM tops),
scored AS (
  SELECT *, CASE WHEN sum(w) OVER {run} > 0 THEN sum(w * score) OVER {run} / sum(w) OVER {run} ELSE avg(score) OVER {run} END AS prefix_score FROM ws),
rewarded AS (SELECT *, {last} AS reward FROM scored)"""
