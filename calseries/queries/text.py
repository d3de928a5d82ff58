"""Pieces of DuckDB text that the oracles share: base series as common table expressions, and the final form."""

from __future__ import annotations

LEVEL = "level AS (SELECT 'level' AS series_id, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate) AS idx, avg(o_totalprice) AS v FROM orders GROUP BY ALL)"
TICKS = "ticks AS (SELECT 'ticks' AS series_id, row_number() OVER (ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey) - 1 AS idx, l_extendedprice AS v FROM lineitem)"
QUOTE = """quote AS (SELECT 'quote' AS series_id, date_diff('day', TIMESTAMP '1995-01-02', l_shipdate) AS idx,
  arg_min(l_extendedprice, (l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey)) AS open, max(l_extendedprice) AS high, min(l_extendedprice) AS low,
  arg_max(l_extendedprice, (l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey)) AS close, sum(l_quantity) AS volume FROM lineitem GROUP BY ALL)"""
STOCK = "stock AS (SELECT CAST(l_partkey AS VARCHAR) AS series_id, date_diff('day', TIMESTAMP '1995-01-02', l_shipdate) AS idx, avg(l_extendedprice) AS v FROM lineitem GROUP BY ALL)"
SUPPLIER = "supp AS (SELECT CAST(l_suppkey AS VARCHAR) AS series_id, date_diff('day', TIMESTAMP '1995-01-02', l_shipdate) AS idx, avg(l_extendedprice) AS v FROM lineitem GROUP BY ALL)"
HOURLY = "hourly AS (SELECT 'hourly' AS series_id, date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS idx, avg(value) AS v FROM events GROUP BY ALL)"
BY_TYPE = "hbt AS (SELECT event_type AS series_id, date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS idx, avg(value) AS v FROM events GROUP BY ALL)"
MINUTES = "mins AS (SELECT 'event_minutes' AS series_id, date_diff('minute', TIMESTAMP '2024-01-01', date_trunc('minute', ts)) AS idx, avg(value) AS v FROM events GROUP BY ALL)"
HOLES = f"{LEVEL}, holes AS (SELECT series_id, idx, CASE WHEN idx % 97 = 5 THEN 'nan'::DOUBLE ELSE v END AS v FROM level WHERE idx % 97 = 5 OR idx % 89 <> 3)"
TRIPS = "trips AS (SELECT user_id AS trip_id, epoch_us(ts) / 1e6 AS t, value AS v, event_type AS gear, 800 + 30 * CAST(json_extract_string(props, '$.k') AS DOUBLE) AS rpm, event_id FROM events)"
TRIPS8 = TRIPS.replace("user_id AS trip_id", "user_id % 8 AS trip_id")


def snapped(sql: str) -> str:
    """Give every round(x, digits) of a text the offset that ``series.snap`` has."""
    out, at = [], 0
    while (i := sql.find("round(", at)) >= 0:
        depth, j, comma = 1, i + 6, -1
        while depth:
            c = sql[j]
            depth += (c == "(") - (c == ")")
            if c == "," and depth == 1:
                comma = j
            j += 1
        digits = int(sql[comma + 1 : j - 1])
        out.append(f"{sql[at:i]}round({snapped(sql[i + 6 : comma])} + {0.031415927 / 10**digits!r}, {digits})")
        at = j
    return "".join(out) + sql[at:]


def registry():
    """(queries, oracles, decorator): the decorator registers a query under a name with the oracle's text, if any."""
    queries, oracles = {}, {}

    def query(name: str, sql: str | None = None):
        def add(fn):
            queries[name] = fn
            if sql is not None:
                oracles[name] = snapped(sql)
            return fn

        return add

    return queries, oracles, query


def kind(name: str, i: int) -> str:
    """The hourly series of one event type as table e<i>."""
    return f"e{i} AS (SELECT 'e' AS series_id, date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS idx, avg(value) AS v FROM events WHERE event_type = '{name}' GROUP BY ALL)"


TWO_TYPES = f"{kind('click', 1)}, {kind('view', 2)}"


def series(ctes: str, r: str, digits: int = 4) -> str:
    """WITH ctes, r AS (...) and the form in which queries return a series."""
    return f"""WITH {ctes}, r AS ({r})
SELECT series_id, CAST(idx AS BIGINT) AS idx, CASE WHEN NOT isnan(v) THEN round(v, {digits}) END AS v,
  CASE WHEN v IS NULL THEN 'empty' WHEN isnan(v) THEN 'unknown' ELSE 'value' END AS state FROM r"""


def frame(w: int, lagged: bool = False) -> str:
    span = f"{w} PRECEDING AND 1 PRECEDING" if lagged else f"{w - 1} PRECEDING AND CURRENT ROW"
    return f"(PARTITION BY series_id ORDER BY idx RANGE BETWEEN {span})"


def back(k: int) -> str:
    return f"max(v) OVER (PARTITION BY series_id ORDER BY idx RANGE BETWEEN {k} PRECEDING AND {k} PRECEDING)"
