"""DuckDB SQL of the same results, written over lists and recursion rather than arrays and numpy."""

from __future__ import annotations

from .sources.params import K_MAPS

_EVENTS = "SELECT {m} AS machine_id, event_type AS sensor_id, ts, event_id AS tick, CAST({v} AS BIGINT) AS v FROM events"
_LINE_ORDER = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_quantity, l_extendedprice, l_discount, l_tax"
FEEDS = {
    "ev_single": _EVENTS.format(m="CAST(0 AS BIGINT)", v="floor(value / 20)"),
    "ev_ten": _EVENTS.format(m="user_id % 10", v="floor(value / 20)"),
    "ev_many": _EVENTS.format(m="user_id", v="floor(value / 20)"),
    "ev_alarm": _EVENTS.format(m="CAST(0 AS BIGINT)", v="CASE WHEN value > 150 THEN 1 ELSE 0 END"),
    "li_sensors": f"""SELECT l_suppkey AS machine_id, u.sensor_id, CAST(l_shipdate AS TIMESTAMP) AS ts, tick, u.v FROM (
        SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY {_LINE_ORDER}) AS tick FROM lineitem) l,
        LATERAL (VALUES ('quantity', CAST(round(l_quantity) AS BIGINT)), ('price', CAST(round(l_extendedprice * 100) AS BIGINT)), ('discount', CAST(round(l_discount * 100) AS BIGINT)), ('tax', CAST(round(l_tax * 100) AS BIGINT))) u(sensor_id, v)""",
    "ord_priority": "SELECT o_custkey % 10 AS machine_id, 'prio' AS sensor_id, CAST(o_orderdate AS TIMESTAMP) AS ts, o_orderkey AS tick, CAST(left(o_orderpriority, 1) AS BIGINT) AS v FROM orders",
    "props_k": "SELECT user_id % 10 AS machine_id, 'k' AS sensor_id, ts, event_id AS tick, CAST(json_extract_string(props, '$.k') AS BIGINT) AS v FROM events",
    "doc_flags": "SELECT CAST(regexp_extract(source, '([0-9]+)$', 1) AS BIGINT) AS machine_id, 'toxic' AS sensor_id, TIMESTAMP '2020-01-01' AS ts, doc_id AS tick, CAST(toxic AS BIGINT) AS v FROM labels JOIN documents USING (doc_id)",
    "turn_len": "SELECT conv_id AS machine_id, role AS sensor_id, TIMESTAMP '2020-01-01' AS ts, turn AS tick, CAST(floor(length(text) / 200) AS BIGINT) AS v FROM conversations",
    "emb_windows": "SELECT vec_id AS machine_id, CAST(label AS VARCHAR) AS sensor_id, TIMESTAMP '2020-01-01' AS ts, place - 1 AS tick, CAST(floor(CAST(embedding[place] AS DOUBLE) * 20) AS BIGINT) AS v FROM embeddings, LATERAL (SELECT unnest(range(1, len(embedding) + 1)) AS place)",
}


def params(kmap: str, threshold: float = 0.005) -> str:
    rows = ", ".join(f"('{s}', {k}, {threshold})" for s, k in K_MAPS[kmap].items())
    return f"SELECT * FROM (VALUES {rows}) p(sensor_id, k, threshold)"


def windows(feed: str, kmap: str, w: int = 10, threshold: float = 0.005, inclusive: bool = False) -> str:
    """CTEs up to ``marked``: every full window with its flags and rule."""
    few = "<=" if inclusive else "<"
    return f"""
    feed AS ({FEEDS[feed]}), params AS ({params(kmap, threshold)}),
    rolled AS (
      SELECT machine_id, sensor_id, ts, tick, v, k, threshold,
             row_number() OVER series AS rn, lag(v, {w}) OVER series AS departed,
             list(v) OVER (PARTITION BY machine_id, sensor_id ORDER BY ts, tick ROWS BETWEEN {w - 1} PRECEDING AND CURRENT ROW) AS w,
             list(ts) OVER (PARTITION BY machine_id, sensor_id ORDER BY ts, tick ROWS BETWEEN {w - 1} PRECEDING AND CURRENT ROW) AS times
      FROM feed JOIN params USING (sensor_id) WINDOW series AS (PARTITION BY machine_id, sensor_id ORDER BY ts, tick)
    ),
    seeded AS (SELECT *, list_filter(w, lambda x, i: list_position(w, x) = i) AS values FROM rolled WHERE rn >= {w}),
    compared AS (
      SELECT *, list_sort(values[1:k]) AS seeds, lag(list_sort(values[1:k])) OVER (PARTITION BY machine_id, sensor_id ORDER BY rn) AS before FROM seeded
    ),
    flagged AS (
      SELECT *, coalesce(v = departed AND seeds = before, false) AS rotated, (k = 1 OR len(values) = 1) AS single, len(values) {few} k AS few FROM compared
    ),
    marked AS (
      SELECT *, CASE WHEN rotated THEN 'rotation' WHEN single THEN 'single' WHEN few THEN 'few' ELSE 'iterate' END AS rule FROM flagged
    )"""


_LABEL = "coalesce(CAST(list_sum(list_transform(range(1, len(c)), lambda q: CASE WHEN 2 * x * c[q].n * c[q + 1].n >= c[q].s * c[q + 1].n + c[q + 1].s * c[q].n THEN 1 ELSE 0 END)) AS BIGINT), 0)"


def clusters(most: int = 50) -> str:
    """CTEs from ``marked`` to ``labelled``: k-means by recursion for every window, labels by ascending centre."""
    return f""",
    steps AS (
      SELECT machine_id, sensor_id, rn, w, list_transform(seeds, lambda x: {{'s': CAST(x AS BIGINT), 'n': CAST(1 AS BIGINT)}}) AS c, CAST(NULL AS BIGINT[]) AS labels, 0 AS i, false AS done FROM marked
      UNION ALL
      SELECT machine_id, sensor_id, rn, w, c2, labels2, i + 1, len(list_filter(range(1, len(c) + 1), lambda q: c2[q].s * c[q].n <> c[q].s * c2[q].n)) = 0 FROM (
        SELECT *, list_transform(range(1, len(c) + 1), lambda j: CASE WHEN len(list_filter(labels2, lambda l: l = j - 1)) = 0 THEN c[j]
                 ELSE {{'s': CAST(list_sum(list_filter(w, lambda y, p: labels2[p] = j - 1)) AS BIGINT), 'n': CAST(len(list_filter(labels2, lambda l: l = j - 1)) AS BIGINT)}} END) AS c2
        FROM (SELECT *, list_transform(w, lambda x: {_LABEL}) AS labels2 FROM steps WHERE NOT done AND i < {most})
      )
    ),
    settled AS (SELECT machine_id, sensor_id, rn, arg_max(labels, i) AS labels, max(i) AS iterations FROM steps GROUP BY ALL),
    labelled AS (SELECT m.*, s.labels, s.iterations FROM marked m JOIN settled s USING (machine_id, sensor_id, rn))"""


def scores(w: int = 10, n: int = 5) -> str:
    """CTEs from ``labelled`` to ``scored``."""
    n = min(n, w - 1)
    return f""",
    counted AS (
      SELECT *,
        list_transform(range({w - n}, {w}), lambda t: len(list_filter(range(1, {w}), lambda u: labels[u] = labels[t] AND labels[u + 1] = labels[t + 1]))) AS joint,
        list_transform(range({w - n}, {w}), lambda t: len(list_filter(range(1, {w}), lambda u: labels[u] = labels[t]))) AS leave,
        len(list_distinct(list_transform(range({w - n}, {w}), lambda t: labels[t] * 1000 + labels[t + 1]))) AS divisions
      FROM labelled
    ),
    scored AS (SELECT *, list_product(joint) / list_product(leave) AS p, times[{w - n}] AS first_ts FROM counted)"""


def chain(feed: str, kmap: str, select: str, w: int = 10, n: int = 5, threshold: float = 0.005, most: int = 50, inclusive: bool = False) -> str:
    return f"WITH RECURSIVE {windows(feed, kmap, w, threshold, inclusive)}{clusters(most)}{scores(w, n)} {select}"


def flags(feed: str, kmap: str, select: str, w: int = 10, inclusive: bool = False) -> str:
    return f"WITH {windows(feed, kmap, w, inclusive=inclusive)} {select}"


def codes(feed: str, kmap: str, select: str, w: int = 10, n: int = 5, threshold: float = 0.005) -> str:
    """Where no window has more values than clusters: labels are the values' ranks, without recursion."""
    labelled = ", labelled AS (SELECT *, list_transform(w, lambda x: CAST(list_position(list_sort(values), x) - 1 AS BIGINT)) AS labels, 0 AS iterations FROM marked)"
    return f"WITH {windows(feed, kmap, w, threshold)}{labelled}{scores(w, n)} {select}"
