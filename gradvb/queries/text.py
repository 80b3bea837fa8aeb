"""SQL building blocks of the oracles, written apart from the Spark code."""

from __future__ import annotations

from gradvb.designs import FLIGHT_BETA, PANEL_BETA, PANEL_TAU2
from gradvb.functions.scalars import hash_uniform_sql as u


def logistic(z: str) -> str:
    return f"(1 / (1 + exp(-({z}))))"


def softplus(z: str) -> str:
    return f"(greatest({z}, 0) + ln(1 + exp(-abs({z}))))"


def flag(condition: str) -> str:
    return f"CASE WHEN {condition} THEN 1 ELSE 0 END"


def linear(theta, xs=None) -> str:
    xs = xs or [f"x{k}" for k in range(len(theta))]
    return " + ".join(f"({float(t)!r}::DOUBLE) * {x}" for t, x in zip(theta, xs, strict=True))


def w1(beta=FLIGHT_BETA) -> str:
    z = f"{beta[0]!r} + {beta[1]!r} * rush + {beta[2]!r} * weekend + {beta[3]!r} * distance"
    return f"""w1_rows AS (
  SELECT concat_ws('|', 'w1', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(round(l_extendedprice * 100) AS BIGINT)) AS obs_key,
         {flag("o_orderpriority IN ('1-URGENT', '2-HIGH')")} AS rush, {flag("isodow(o_orderdate) IN (6, 7)")} AS weekend,
         l_quantity / 50 AS distance, {flag("date_diff('day', o_orderdate::DATE, l_shipdate::DATE) > 15")} AS late_raw
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey
), w1 AS (SELECT *, {flag(f"{u('obs_key')} < {logistic(z)}")} AS late_planted FROM w1_rows),
obs AS (SELECT obs_key, late_planted::DOUBLE AS y, 1.0::DOUBLE AS x0, rush::DOUBLE AS x1, weekend::DOUBLE AS x2, distance AS x3 FROM w1)"""


def w1e() -> str:
    b = FLIGHT_BETA
    z = f"{b[0]!r} + {b[1]!r} * night + {b[2]!r} * weekend + {b[3]!r} * distance"
    key = "concat_ws('|', 'w1e', event_id)"
    return f"""w1e_rows AS (
  SELECT event_id, {flag("hour(ts) < 6 OR hour(ts) >= 22")} AS night, {flag("isodow(ts) IN (6, 7)")} AS weekend, value / 100 AS distance,
         {flag("event_type = 'purchase'")} AS purchase_raw FROM events
), w1e AS (SELECT *, {flag(f"{u(key)} < {logistic(z)}")} AS y_planted FROM w1e_rows)"""


def w3() -> str:
    xs = ", ".join(f"{u(f"'x{j}'", 'o_orderkey')} AS x{j}" for j in range(1, 11))
    z = f"{PANEL_BETA[0]!r} + alpha + " + " + ".join(f"{PANEL_BETA[j]!r} * x{j}" for j in range(1, 11))
    alpha = f"sqrt({PANEL_TAU2!r}) * sqrt(-2 * ln(greatest({u("'a1'", 'o_custkey')}, {2.0**-53!r}))) * cos(2 * pi() * {u("'a2'", 'o_custkey')})"
    return f"""w3_all AS (
  SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS t, count(*) OVER (PARTITION BY o_custkey) AS n FROM orders
), w3_ids AS (SELECT o_custkey, row_number() OVER (ORDER BY o_custkey) AS panel_rank FROM w3_all WHERE n >= 5 AND t = 1),
w3_x AS (SELECT a.o_custkey AS panel_id, panel_rank, t, o_orderkey, {alpha.replace('o_custkey', 'a.o_custkey')} AS alpha, {xs} FROM w3_all a JOIN w3_ids k ON a.o_custkey = k.o_custkey WHERE t <= 5),
w3 AS (SELECT panel_id, panel_rank::INTEGER AS panel_rank, t::INTEGER AS t, {flag(f"{u("'w3'", 'o_orderkey')} < {logistic(z)}")} AS y, {', '.join(f'x{j}' for j in range(1, 11))} FROM w3_x)"""


def long_form(values: dict[str, str], source: str, key: str = "k") -> str:
    """One row (key, value) per named expression of a one-row source."""
    return " UNION ALL ".join(f"SELECT '{k}' AS {key}, {v} AS value FROM {source}" for k, v in values.items())


def rounded(expression: str, digits: int = 6) -> str:
    return f"round(({expression})::DOUBLE, {digits}) + 0.0"
