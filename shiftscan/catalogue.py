"""The engine's queries by name, and the DuckDB SQL that must give the same rows."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as sql
from .functions import codec, udfs
from .operators import memo, relops, release, routing, summaries, windows
from .plans import chain, cost, staged
from .sources import params, streams
from .sources.feeds import SERIES, feed, table
from .store import shared_folder, stored
from .streaming import chain as stream

RUNS: dict = {}
SQL: dict[str, str] = {}
KEY = list(SERIES)


def query(name: str, oracle: str | None = None):
    def keep(f):
        RUNS[name] = f
        if oracle:
            SQL[name] = oracle
        return f

    return keep


def _scored(spark: SparkSession, sf: str, name: str = "ev_single", kmap: str = "A", threshold: float = 0.005, **o) -> DataFrame:
    return chain.score(feed(spark, sf, name), params.load(spark, kmap, threshold), **o)


def _found(spark: SparkSession, sf: str, name: str = "ev_single", kmap: str = "A", threshold: float = 0.005, **o) -> DataFrame:
    return chain.detect(feed(spark, sf, name), params.load(spark, kmap, threshold), **o)


def _text(labels: str = "labels"):
    return F.array_join(F.transform(labels, lambda x: x.cast("string")), ",")


def _wins(spark: SparkSession, sf: str, name: str, kmap: str, w: int = 10) -> DataFrame:
    return params.attach(windows.count_windows(feed(spark, sf, name), w), params.load(spark, kmap))


FEED_SQL = {n: f"SELECT * FROM ({s})" for n, s in sql.FEEDS.items()}

# Feeds, messages and routing.
query("feed_readings", FEED_SQL["ev_ten"])(lambda s, d: feed(s, d, "ev_ten"))
query("feed_unpivot_lineitem", FEED_SQL["li_sensors"])(lambda s, d: feed(s, d, "li_sensors"))
for _n in ("ev_alarm", "ord_priority", "props_k", "doc_flags", "turn_len", "emb_windows"):
    query("props_json_sensor" if _n == "props_k" else f"feed_{_n}", FEED_SQL[_n])(lambda s, d, n=_n: feed(s, d, n))

_MSG = f"""SELECT '<g:' || lpad(CAST(tick AS VARCHAR), 12, '0') || '> <has:machine> "m' || machine_id || '" ; <has:time> "' || strftime(ts, '%Y-%m-%d %H:%M:%S.%f') || '" ; <has:tick> "' || tick || '" .'
  || string_agg(' [<s:' || sensor_id || '> "' || v || '"]', '' ORDER BY sensor_id) AS msg FROM ({sql.FEEDS['li_sensors']}) GROUP BY machine_id, ts, tick"""
query("msg_render", _MSG)(lambda s, d: codec.render(feed(s, d, "li_sensors")))
query("msg_parse_offset", FEED_SQL["li_sensors"])(lambda s, d: codec.parse_by_offset(codec.render(feed(s, d, "li_sensors"))))
query("msg_parse_generic", FEED_SQL["li_sensors"])(lambda s, d: codec.parse_generic(codec.render(feed(s, d, "li_sensors"))))
query("msg_parse_python", FEED_SQL["ev_ten"])(lambda s, d: codec.parse_python_udf(codec.render(feed(s, d, "ev_ten"))))
query("msg_parse_head", f"SELECT machine_id, ts, tick FROM ({sql.FEEDS['ev_ten']})")(lambda s, d: codec.parse_head(codec.render(feed(s, d, "ev_ten"))))
query("msg_peek_machine", f"SELECT machine_id, count(DISTINCT (ts, tick)) AS messages FROM ({sql.FEEDS['li_sensors']}) GROUP BY 1")(
    lambda s, d: codec.peek_machine(codec.render(feed(s, d, "li_sensors"))).groupBy("machine_id").agg(F.count(F.lit(1)).alias("messages"))
)


@query("msg_parse_equal", f"SELECT count(*) AS readings, CAST(0 AS BIGINT) AS differing FROM ({sql.FEEDS['li_sensors']})")
def _(s, d):
    msgs = codec.render(feed(s, d, "li_sensors"))
    a, b = codec.parse_by_offset(msgs).withColumn("n", F.lit(1)), codec.parse_generic(msgs).withColumn("n", F.lit(-1))
    same = a.unionByName(b).groupBy("machine_id", "sensor_id", "ts", "tick", "v").agg(F.sum("n").alias("n"), F.count_if(F.col("n") == 1).alias("a"))
    return same.agg(F.sum("a").alias("readings"), F.sum(F.abs("n")).alias("differing"))


query("msg_bytes", f"SELECT count(*) AS messages, CAST(sum(strlen(msg)) AS BIGINT) AS bytes FROM ({_MSG})")(lambda s, d: cost.message_bytes(codec.render(feed(s, d, "li_sensors"))))
query("html_lang_by_offset", "SELECT page_id, substr(html, 28, 2) AS lang FROM pages")(lambda s, d: codec.html_language(table(s, d, "pages")))
query("route_modulo_load", f"SELECT CAST(machine_id % 12 AS INTEGER) AS worker, count(*) AS readings FROM ({sql.FEEDS['ev_many']}) GROUP BY 1")(
    lambda s, d: routing.modulo(feed(s, d, "ev_many"), 12).groupBy("worker").agg(F.count(F.lit(1)).alias("readings"))
)
query("route_affinity", f"SELECT machine_id, count(DISTINCT machine_id % 12) AS workers, count(*) AS readings FROM ({sql.FEEDS['ev_many']}) GROUP BY 1")(
    lambda s, d: routing.check_affinity(routing.modulo(feed(s, d, "ev_many"), 12))
)
query("route_arrival_order", f"SELECT machine_id, sensor_id, count(*) AS readings, CAST(0 AS BIGINT) AS backwards FROM ({sql.FEEDS['ev_many']}) GROUP BY 1, 2")(lambda s, d: routing.check_order(routing.placed(feed(s, d, "ev_many"), 12)))
query("route_by_series", f"SELECT machine_id, sensor_id, count(*) AS readings, CAST(1 AS BIGINT) AS tasks FROM ({sql.FEEDS['ev_many']}) GROUP BY 1, 2")(
    lambda s, d: routing.by_series(feed(s, d, "ev_many"), 6).withColumn("task", F.spark_partition_id()).groupBy(*KEY).agg(F.count(F.lit(1)).alias("readings"), F.count_distinct("task").alias("tasks"))
)
query(
    "route_load_skew",
    f"""SELECT bucket, worker, readings, CAST(max(readings) OVER b AS DOUBLE) * 12 / sum(readings) OVER b AS skew FROM (
  SELECT date_trunc('day', ts) AS bucket, CAST(machine_id % 12 AS INTEGER) AS worker, count(*) AS readings FROM ({sql.FEEDS['ev_many']}) GROUP BY 1, 2) WINDOW b AS (PARTITION BY bucket)""",
)(lambda s, d: routing.load_profile(feed(s, d, "ev_many"), 12))


@query("route_balanced", f"SELECT count(DISTINCT machine_id) AS machines, count(*) AS readings, true AS within_bound FROM ({sql.FEEDS['ev_ten']})")
def _(s, d):
    """Longest load first never exceeds 4/3 of the best possible; here: of the mean plus the largest machine."""
    load = feed(s, d, "ev_ten").groupBy("machine_id").agg(F.count(F.lit(1)).alias("readings"))
    by = load.join(routing.balanced(s, load, 4), "machine_id").groupBy("worker").agg(F.sum("readings").alias("n"), F.count(F.lit(1)).alias("m"), F.max("readings").alias("top"))
    return by.agg(F.sum("m").alias("machines"), F.sum("n").alias("readings"), (F.max("n") <= F.sum("n") / 4 + F.max("top")).alias("within_bound"))


# Windows.
query("series_windows", sql.flags("ev_ten", "A", "SELECT machine_id, sensor_id, rn, v AS arrived, coalesce(departed, -1) AS departed, array_to_string(w, ',') AS w FROM rolled WHERE rn >= 10"))(
    lambda s, d: _wins(s, d, "ev_ten", "A").select(*KEY, "rn", "arrived", F.coalesce("departed", F.lit(-1)).alias("departed"), _text("w").alias("w"))
)
query("time_windows", f"SELECT machine_id, sensor_id, date_trunc('day', ts) AS start, count(*) AS n, CAST(sum(v) AS BIGINT) AS total, min(v) AS low, max(v) AS high FROM ({sql.FEEDS['ev_ten']}) GROUP BY 1, 2, 3")(
    lambda s, d: windows.time_windows(feed(s, d, "ev_ten"), "1 day").select(*KEY, F.col("window.start").alias("start"), "n", "total", "low", "high")
)
query("window_total", f"SELECT CAST(sum(greatest(n - 9, 0)) AS BIGINT) AS windows FROM (SELECT count(*) AS n FROM ({sql.FEEDS['ev_ten']}) GROUP BY machine_id, sensor_id)")(lambda s, d: cost.window_total(feed(s, d, "ev_ten"), 10))
query("window_pairs_join", f"SELECT machine_id, sensor_id, row_number() OVER x AS rn, v, coalesce(lag(v) OVER x, -1) AS previous FROM ({sql.FEEDS['ev_ten']}) WINDOW x AS (PARTITION BY machine_id, sensor_id ORDER BY ts, tick)")(
    lambda s, d: windows.pairs_by_join(feed(s, d, "ev_ten")).withColumn("previous", F.coalesce("previous", F.lit(-1)))
)
query("seed_values", sql.flags("ev_ten", "A", "SELECT machine_id, sensor_id, rn, array_to_string(values[1:k], ',') AS seeds FROM seeded"))(
    lambda s, d: _wins(s, d, "ev_ten", "A").select(*KEY, "rn", _text(F.slice(F.array_distinct("w"), F.lit(1), F.col("k"))).alias("seeds"))
)
for _name, _col in (("rotation_flags", "rotated"), ("single_flags", "single"), ("few_flags", "few")):
    query(_name, sql.flags("ev_ten", "A", f"SELECT machine_id, sensor_id, rn, {_col} FROM marked"))(lambda s, d, c=_col: _scored(s, d, "ev_ten").select(*KEY, "rn", c))
query("few_inclusive_flags", sql.flags("ev_ten", "A", "SELECT machine_id, sensor_id, rn, few FROM marked", inclusive=True))(lambda s, d: _scored(s, d, "ev_ten", few_inclusive=True).select(*KEY, "rn", "few"))
_SHARES = "SELECT count(*) AS windows, count(*) FILTER (rule = 'rotation') AS rotation, count(*) FILTER (rule = 'single') AS single, count(*) FILTER (rule = 'few') AS few, count(*) FILTER (rule = 'iterate') AS iterate FROM marked"
for _feed, _kmap, _short in (("ev_single", "A", "single"), ("ev_ten", "A", "ten"), ("ev_many", "A", "many"), ("ev_alarm", "alarm", "alarm"), ("ord_priority", "prio", "prio"), ("props_k", "k", "props")):
    for _w in (10, 100) if _short in ("single", "ten") else (10,):
        query(f"rule_shares_w{_w}_{_short}", sql.flags(_feed, _kmap, _SHARES, _w))(lambda s, d, f=_feed, k=_kmap, w=_w: summaries.shares(_scored(s, d, f, k, w=w)))
query("rule_shares_w10_sensors", sql.flags("li_sensors", "B", _SHARES.replace("SELECT ", "SELECT sensor_id, ", 1) + " GROUP BY sensor_id"))(lambda s, d: summaries.shares(_scored(s, d, "li_sensors", "B"), "sensor_id"))
query("rule_shares_w4_flags", sql.flags("doc_flags", "toxic", _SHARES, 4))(lambda s, d: summaries.shares(_scored(s, d, "doc_flags", "toxic", w=4)))
query("shortcut_share", sql.flags("ev_ten", "A", "SELECT count(*) AS windows, count(*) FILTER (rule <> 'iterate') AS shortcut, count(*) FILTER (rule <> 'iterate') / CAST(count(*) AS DOUBLE) AS share FROM marked"))(lambda s, d: cost.shortcut_share(_scored(s, d, "ev_ten")))


@query("rotation_printed_safe", sql.flags("ev_ten", "A", "SELECT count(*) AS windows, count(*) FILTER (rotated) AS declared, count(*) FILTER (rotated) AS complete, CAST(0 AS BIGINT) AS false_alarms FROM marked"))
def _(s, d):
    """The incremental trackers against the declared flag: the complete one agrees, the conservative one never claims more."""
    from .operators.tracker import tracked

    both = tracked(feed(s, d, "ev_ten"), params.load(s, "A"), 10).join(_scored(s, d, "ev_ten").select(*KEY, "rn", "rotated"), [*KEY, "rn"])
    return both.agg(F.count(F.lit(1)).alias("windows"), F.count_if("rotated").alias("declared"), F.count_if("complete").alias("complete"), F.count_if(F.col("conservative") & ~F.col("rotated")).alias("false_alarms"))


query("few_labels", sql.flags("ev_ten", "A", "SELECT machine_id, sensor_id, rn, array_to_string(list_transform(w, lambda x: list_position(list_sort(values), x) - 1), ',') AS labels FROM marked WHERE few AND NOT rotated AND NOT single"))(
    lambda s, d: _scored(s, d, "ev_ten", labels=True).where("rule = 'few'").select(*KEY, "rn", _text().alias("labels"))
)
query(
    "rotation_anchor",
    sql.flags("ev_ten", "A", "SELECT machine_id, sensor_id, rn, max(CASE WHEN NOT rotated THEN rn END) OVER (PARTITION BY machine_id, sensor_id ORDER BY rn) AS anchor FROM marked"),
)(lambda s, d: _anchors(_scored(s, d, "ev_ten")).select(*KEY, "rn", "anchor"))


def _anchors(scored: DataFrame) -> DataFrame:
    """The window whose clusters each window reuses; itself where it does not rotate."""
    order = windows.Window.partitionBy(*SERIES).orderBy("rn")
    return scored.withColumn("anchor", F.last(F.when(~F.col("rotated"), F.col("rn")), ignorenulls=True).over(order))


# Clustering.
_LABELS = "SELECT machine_id, sensor_id, rn, array_to_string(labels, ',') AS labels FROM labelled"


def _labels_sql(where: str = "") -> str:
    return f"WITH RECURSIVE {sql.windows('ev_ten', 'A')}{sql.clusters()} {_LABELS}{where}"


for _name, _o in (("kmeans_naive", {"sorted_sweep": False, "rotation": False, "few": False, "single": False}), ("kmeans_sorted", {"rotation": False, "few": False, "single": False, "kept": False}), ("kmeans_kept", {"rotation": False, "few": False, "single": False}), ("kmeans_rotated", {}), ("kmeans_memo", {"memo": True, "rotation": False})):
    query(_name, _labels_sql())(lambda s, d, o=_o: _scored(s, d, "ev_ten", labels=True, **o).select(*KEY, "rn", _text().alias("labels")))
query("kmeans_native", _labels_sql())(lambda s, d: _native(s, d).select(*KEY, "rn", _text().alias("labels")))
query("kmeans_iterations", f"WITH RECURSIVE {sql.windows('ev_ten', 'three')}{sql.clusters()} SELECT CAST(iterations AS INTEGER) AS iterations, count(*) AS windows FROM labelled GROUP BY 1")(
    lambda s, d: cost.iteration_histogram(_scored(s, d, "ev_ten", "three", rotation=False, few=False, single=False))
)
query("kmeans_w100", f"WITH RECURSIVE {sql.windows('ev_ten', 'A', 100)}{sql.clusters()} SELECT sensor_id, count(*) AS windows, CAST(sum(iterations) AS BIGINT) AS iterations FROM labelled GROUP BY 1")(
    lambda s, d: _scored(s, d, "ev_ten", w=100, rotation=False, few=False, single=False).groupBy("sensor_id").agg(F.count(F.lit(1)).alias("windows"), F.sum("iterations").alias("iterations"))
)


def _native(s, d) -> DataFrame:
    from .operators.native import labelled

    return labelled(_wins(s, d, "ev_ten", "A"))


for _canon in (False, True):
    query(f"memo_{'canonical' if _canon else 'exact'}_labels", _labels_sql())(lambda s, d, c=_canon: memo.clustered(_wins(s, d, "ev_ten", "A"), c).select(*KEY, "rn", _text().alias("labels")))
_RATE = "SELECT sensor_id, count(*) AS windows, count(DISTINCT {key}) AS distinct_keys, 1 - CAST(count(DISTINCT {key}) AS DOUBLE) / count(*) AS hit_rate FROM marked GROUP BY 1"
for _name, _feed, _kmap, _canon, _key in (("memo_exact_hits", "ev_ten", "A", False, "w"), ("memo_canonical_hits", "ev_ten", "A", True, "(seeds, list_sort(w))"), ("memo_dispersion_ladder", "li_sensors", "B", True, "(seeds, list_sort(w))")):
    query(_name, sql.flags(_feed, _kmap, _RATE.format(key=_key)))(lambda s, d, f=_feed, k=_kmap, c=_canon: memo.hit_rate(_wins(s, d, f, k), c))

# Transitions and detection.
_PAIRS = """, pairs AS (SELECT machine_id, sensor_id, rn, CAST(labels[u] AS INTEGER) AS a, CAST(labels[u + 1] AS INTEGER) AS b FROM labelled, LATERAL (SELECT unnest(range(1, 10)) AS u)),
  sums AS (SELECT machine_id, sensor_id, rn, a, b, count(*) AS n FROM pairs GROUP BY 1, 2, 3, 4, 5)
  SELECT machine_id, sensor_id, rn, a, b, n, CAST(sum(n) OVER x AS BIGINT) AS leave, CAST(n AS DOUBLE) / sum(n) OVER x AS prob FROM sums WINDOW x AS (PARTITION BY machine_id, sensor_id, rn, a)"""
query("transition_full", f"WITH RECURSIVE {sql.windows('ev_ten', 'A')}{sql.clusters()} {_PAIRS}")(lambda s, d: _matrix(_scored(s, d, "ev_ten", labels=True)))


def _matrix(scored: DataFrame) -> DataFrame:
    """Every pair of every window with its count, leave count and ratio."""
    pairs = scored.select(*KEY, "rn", F.explode(F.zip_with(F.slice("labels", 1, F.size("labels") - 1), F.slice("labels", 2, F.size("labels") - 1), lambda a, b: F.struct(a.alias("a"), b.alias("b")))).alias("x"))
    counts = pairs.groupBy(*KEY, "rn", F.col("x.a").alias("a"), F.col("x.b").alias("b")).agg(F.count(F.lit(1)).alias("n"))
    leave = F.sum("n").over(windows.Window.partitionBy(*KEY, "rn", "a"))
    return counts.withColumn("leave", leave).withColumn("prob", F.col("n") / F.col("leave"))


_P = "SELECT machine_id, sensor_id, rn, p FROM scored"
for _name, _o in (("transition_lazy", {}), ("transition_ring", {"ring": True}), ("transition_eager", {"lazy": False})):
    query(_name, sql.chain("ev_ten", "A", _P))(lambda s, d, o=_o: _scored(s, d, "ev_ten", **o).select(*KEY, "rn", "p"))
query("transition_probs_priority", sql.codes("ord_priority", "prio", _P))(lambda s, d: _scored(s, d, "ord_priority", "prio").select(*KEY, "rn", "p"))
query("tail_divisions", sql.chain("ev_single", "A", "SELECT sensor_id, CAST(sum(divisions) AS BIGINT) AS divisions FROM scored GROUP BY 1"))(
    lambda s, d: _scored(s, d).groupBy("sensor_id").agg(F.sum("divisions").alias("divisions"))
)
_ANOM = "SELECT machine_id, sensor_id, rn, ts, first_ts, p, rule FROM scored WHERE p < threshold"
_COLS = [*KEY, "rn", "ts", "first_ts", "p", "rule"]
query("anomalies", sql.chain("ev_single", "A", _ANOM))(lambda s, d: _found(s, d).select(*_COLS))
query("anomalies_ten", sql.chain("ev_ten", "A", _ANOM))(lambda s, d: _found(s, d, "ev_ten").select(*_COLS))
query("anomalies_many", sql.chain("ev_many", "A", _ANOM))(lambda s, d: _found(s, d, "ev_many").select(*_COLS))
query("anomalies_baseline", sql.chain("ev_single", "A", _ANOM))(lambda s, d: _found(s, d, **chain.BASELINE).select(*_COLS))
query("anomalies_w100", sql.chain("ev_single", "A", _ANOM, w=100, threshold=0.0001))(lambda s, d: _found(s, d, threshold=0.0001, w=100).select(*_COLS))
query("anomalies_emb", sql.chain("emb_windows", "emb", "SELECT sensor_id, count(*) AS windows, count(*) FILTER (p < 0.005) AS anomalies FROM scored GROUP BY 1"))(
    lambda s, d: _scored(s, d, "emb_windows", "emb").groupBy("sensor_id").agg(F.count(F.lit(1)).alias("windows"), F.count_if(F.col("p") < 0.005).alias("anomalies"))
)


@query("anomalies_all_equal", sql.chain("ev_ten", "A", "SELECT count(*) AS windows, CAST(0 AS BIGINT) AS differing FROM scored"))
def _(s, d):
    """The chain with and without every shortcut, window by window."""
    fast, slow = _scored(s, d, "ev_ten"), _scored(s, d, "ev_ten", **chain.BASELINE)
    both = fast.select(*KEY, "rn", "num", "den").join(slow.select(*KEY, "rn", F.col("num").alias("n2"), F.col("den").alias("d2")), [*KEY, "rn"], "full")
    return both.agg(F.count(F.lit(1)).alias("windows"), F.count_if(~(F.col("num").eqNullSafe(F.col("n2")) & F.col("den").eqNullSafe(F.col("d2")))).alias("differing"))


query("chain_staged", sql.chain("ev_ten", "A", "SELECT machine_id, sensor_id, rn, array_to_string(labels, ',') AS labels, p FROM scored"))(
    lambda s, d: staged.score(feed(s, d, "ev_ten"), params.load(s, "A")).select(*KEY, "rn", _text().alias("labels"), "p")
)
for _lazy in (False, True):
    query(f"ingest_{'lazy' if _lazy else 'eager'}", FEED_SQL["li_sensors"])(lambda s, d, z=_lazy: staged.ingest(codec.render(feed(s, d, "li_sensors")), z))

# Cost measures.
query(
    "cluster_ops",
    sql.chain(
        "ev_ten", "A",
        """SELECT CAST(sum(iterations * least(k, len(values)) * 10) AS BIGINT) AS naive, CAST(sum(iterations * (least(k, len(values)) + 10)) AS BIGINT) AS sweep,
           CAST(sum(CASE WHEN rule = 'iterate' THEN iterations * least(k, len(values)) * 10 WHEN k = 1 THEN 0 ELSE 10 END) AS BIGINT) AS shortcuts FROM scored""",
    ),
)(lambda s, d: cost.cluster_ops(_scored(s, d, "ev_ten", rotation=False, few=False, single=False), 10))
for _kmap in ("A", "A53"):
    query(
        "markov_ops" if _kmap == "A" else "markov_ops_k53",
        sql.chain("ev_single", _kmap, "SELECT CAST(sum(9 + k * k) AS BIGINT) AS full_model, CAST(sum(9) AS BIGINT) AS lazy, CAST(sum(CASE WHEN rule = 'rotation' THEN 2 ELSE 9 END) AS BIGINT) AS with_rotation, CAST(sum(k * k) AS BIGINT) AS all_ratios, CAST(sum(divisions) AS BIGINT) AS tail_ratios FROM scored"),
    )(lambda s, d, k=_kmap: cost.markov_ops(_scored(s, d, kmap=k), 10))
query("mean_k", sql.flags("ev_single", "A", "SELECT avg(k) AS by_window, count(*) AS windows FROM marked"))(lambda s, d: cost.mean_k(_scored(s, d)))
query("state_bytes", f"SELECT count(*) AS series, CAST(sum(least(n, 500) * 8) AS BIGINT) AS bytes FROM (SELECT count(*) AS n FROM ({sql.FEEDS['li_sensors']}) GROUP BY machine_id, sensor_id)")(lambda s, d: cost.state_bytes(feed(s, d, "li_sensors"), 500))

# Ordered release, on the feed whose labels need no iteration.
_A6 = sql.codes("ord_priority", "prio", "SELECT machine_id, sensor_id, rn, ts, tick FROM scored WHERE p < 0.02", threshold=0.02)


def _release_sql(select: str, idle: int | None, silent: bool, name: str = "ord_priority", anoms: str = _A6, workers: int = 10) -> str:
    quiet = "WHERE NOT (machine_id >= 8 AND tick BETWEEN (SELECT max(tick) / 3 FROM feed0) AND (SELECT max(tick) * 2 / 3 FROM feed0))" if silent else ""
    far = f"CASE WHEN last IS NULL OR epoch - last > {idle} THEN TIMESTAMP '{release.FAR}' ELSE progress_ts END" if idle is not None else "progress_ts"
    return f"""WITH feed0 AS ({sql.FEEDS[name]}), feed1 AS (SELECT * FROM feed0 {quiet}),
    anoms AS ({anoms}), seen AS (SELECT tick // 1000 AS epoch, machine_id % {workers} AS worker, max(ts) AS ts FROM feed1 GROUP BY 1, 2),
    grid AS (SELECT epoch, worker FROM (SELECT DISTINCT epoch FROM seen), (SELECT unnest(range({workers})) AS worker)),
    prog AS (SELECT epoch, worker, max(ts) OVER x AS progress_ts, max(CASE WHEN ts IS NOT NULL THEN epoch END) OVER x AS last FROM grid LEFT JOIN seen USING (epoch, worker) WINDOW x AS (PARTITION BY worker ORDER BY epoch)),
    front AS (SELECT epoch, min({far}) AS frontier FROM prog GROUP BY epoch HAVING count(*) = count({far})),
    gated AS (SELECT a.machine_id, a.sensor_id, a.rn, a.ts, a.tick, (SELECT min(epoch) FROM front WHERE frontier > a.ts) AS released_at FROM anoms a)
    {select}"""


def _release(s, d, idle: int | None = None, silent: bool = False):
    readings = feed(s, d, "ord_priority")
    anoms = _found(s, d, "ord_priority", "prio", 0.02)
    if silent:
        top = readings.agg(F.max("tick")).first()[0]
        readings = readings.where(~((F.col("machine_id") >= 8) & F.col("tick").between(top / 3, top * 2 / 3)))
    return release.gate(anoms.select(*KEY, "rn", "ts", "tick"), release.progress(readings, 10, 1000, idle))


_GATED = "SELECT machine_id, sensor_id, rn, ts, coalesce(released_at, -1) AS released_at FROM gated"
query("release_gate", _release_sql(_GATED, None, False))(lambda s, d: _release(s, d).select(*KEY, "rn", "ts", F.coalesce("released_at", F.lit(-1)).alias("released_at")))
query("release_silent", _release_sql(_GATED, None, True))(lambda s, d: _release(s, d, silent=True).select(*KEY, "rn", "ts", F.coalesce("released_at", F.lit(-1)).alias("released_at")))
query("release_idle", _release_sql(_GATED, 3, True))(lambda s, d: _release(s, d, 3, True).select(*KEY, "rn", "ts", F.coalesce("released_at", F.lit(-1)).alias("released_at")))
_INV = "SELECT span, count(*) AS outputs, count(*) FILTER (before > ts) AS inversions FROM (SELECT *, lag(ts) OVER (PARTITION BY span ORDER BY {place}, ts, machine_id, sensor_id, rn) AS before FROM (SELECT *, {span} AS span FROM {src})) GROUP BY 1"
query("release_inversions", _release_sql(_INV.format(place="ts", span="coalesce(released_at, -1)", src="gated"), None, False))(
    lambda s, d: release.inversions(_release(s, d).withColumn("span", F.coalesce("released_at", F.lit(-1))).withColumn("place", F.col("ts")), "place", "span")
)
query("unsynced_inversions", f"WITH anoms AS ({_A6}) " + _INV.format(place="tick + (7 * (machine_id % 10)) % 13 * 100", span="tick // 10000", src="anoms"))(
    lambda s, d: release.inversions(release.unsynced(_found(s, d, "ord_priority", "prio", 0.02), 10).withColumn("span", F.floor(F.col("tick") / 10000)), "finished", "span")
)

_WAIT = "released_at - tick // 1000"
query("release_delay", _release_sql(f"SELECT {_WAIT} AS delay, count(*) AS outputs FROM gated WHERE released_at IS NOT NULL GROUP BY 1", None, False))(lambda s, d: release.delays(_release(s, d).where("released_at is not null")))
query("sync_overhead", _release_sql(f"SELECT count(*) AS outputs, count(released_at) AS released, count(*) FILTER ({_WAIT} > 0) AS held, CAST(sum({_WAIT}) AS BIGINT) AS epochs_waited, max({_WAIT}) AS longest FROM gated", None, False))(
    lambda s, d: release.overhead(_release(s, d))
)
query("release_ordered", _release_sql("SELECT machine_id, sensor_id, rn, ts, row_number() OVER (ORDER BY ts, machine_id, sensor_id) AS place FROM anoms", None, False))(lambda s, d: _in_order(_release(s, d)))


def _in_order(released: DataFrame) -> DataFrame:
    """The place that each row has in the ordered output: its partition's rows follow those of the partitions before."""
    rows = release.ordered(released.select(*KEY, "rn", "ts")).select("*", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("at"))
    upto = windows.Window.partitionBy().orderBy("at")
    return rows.withColumn("place", F.row_number().over(upto)).select(*KEY, "rn", "ts", F.col("place").cast("long").alias("place"))


# Many machines on twelve workers, with the gate and without.
_FLEET = sql.chain("ev_many", "A", "SELECT machine_id, sensor_id, rn, ts, tick FROM scored WHERE p < threshold")


def _fleet(s, d) -> tuple[DataFrame, DataFrame]:
    """Readings placed by machine on workers, and the anomalies found there."""
    readings = routing.placed(feed(s, d, "ev_many"), 12).drop("worker")
    return readings, chain.detect(readings, params.load(s, "A")).select(*KEY, "rn", "ts", "tick")


query("fleet_synced", _release_sql(_GATED, None, False, "ev_many", _FLEET, 12))(lambda s, d: _gated(*_fleet(s, d)).select(*KEY, "rn", "ts", F.coalesce("released_at", F.lit(-1)).alias("released_at")))
query("fleet_unsynced", f"SELECT machine_id, sensor_id, rn, ts, tick + (7 * (machine_id % 12)) % 13 * 100 AS finished FROM ({_FLEET})")(lambda s, d: release.unsynced(_fleet(s, d)[1], 12).select(*KEY, "rn", "ts", "finished"))


def _gated(readings: DataFrame, found: DataFrame) -> DataFrame:
    return release.gate(found, release.progress(readings, 12))


# Relational helpers and summaries.
query("anomaly_topk", sql.chain("ev_ten", "A", "SELECT machine_id, sensor_id, rn, p FROM scored ORDER BY p, machine_id, sensor_id, rn LIMIT 20"))(lambda s, d: summaries.topk(_scored(s, d, "ev_ten"), 20).select(*KEY, "rn", "p"))
query("anomaly_topk_per_machine", sql.chain("ev_ten", "A", "SELECT machine_id, sensor_id, rn, p, place FROM (SELECT *, row_number() OVER (PARTITION BY machine_id ORDER BY p, sensor_id, rn) AS place FROM scored) WHERE place <= 3"))(
    lambda s, d: summaries.topk_per_machine(_scored(s, d, "ev_ten"), 3).select(*KEY, "rn", "p", "place")
)
_LI = sql.flags("li_sensors", "B", "SELECT machine_id, sensor_id, rn FROM marked WHERE rule = 'rotation' AND sensor_id = 'tax'")
query("anomaly_named_machine", f"SELECT machine_id, rn, s_name, n_name, r_name FROM ({_LI}) JOIN supplier ON machine_id = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")(
    lambda s, d: relops.name_machine(_scored(s, d, "li_sensors", "B").where("rule = 'rotation' AND sensor_id = 'tax'"), *(table(s, d, t) for t in ("supplier", "nation", "region"))).select("machine_id", "rn", "s_name", "n_name", "r_name")
)
query("anomaly_coverage", f"SELECT s_suppkey AS machine_id, count(rn) AS anomalies FROM supplier LEFT JOIN ({_LI}) ON machine_id = s_suppkey GROUP BY 1")(
    lambda s, d: relops.coverage(table(s, d, "supplier").select(F.col("s_suppkey").alias("machine_id")), _scored(s, d, "li_sensors", "B").where("rule = 'rotation' AND sensor_id = 'tax'"))
)
query(
    "anomaly_asof_order",
    sql.chain("ev_ten", "A", "SELECT a.machine_id, a.sensor_id, a.rn, (SELECT arg_max(o.o_orderkey, (o.o_orderdate, o.o_orderkey)) FROM (SELECT *, o_custkey % 10 AS machine FROM orders) o WHERE o.machine = a.machine_id AND CAST(o.o_orderdate AS TIMESTAMP) <= a.ts) AS o_orderkey FROM scored a WHERE p < threshold"),
)(
    lambda s, d: relops.asof(_found(s, d, "ev_ten").select(*KEY, "rn", "ts"), table(s, d, "orders").select((F.col("o_custkey") % 10).alias("machine_id"), F.col("o_orderdate").cast("timestamp_ntz").alias("ts"), "o_orderkey"), "machine_id", "ts", "o_orderkey").select(*KEY, "rn", "o_orderkey")
)
query("anomaly_interval_events", sql.chain("ev_single", "A", "SELECT a.machine_id, a.sensor_id, a.rn, count(*) AS around FROM scored a JOIN events e ON e.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR AND e.event_type = a.sensor_id WHERE a.p < a.threshold GROUP BY 1, 2, 3"))(
    lambda s, d: relops.within(_found(s, d).select(*KEY, "rn", "ts"), table(s, d, "events").select(F.col("event_type").alias("sensor_id"), F.col("ts").alias("right_ts")), "sensor_id", 1).groupBy(*KEY, "rn").agg(F.count(F.lit(1)).alias("around"))
)
query("silent_machines", "SELECT DISTINCT user_id AS machine_id FROM events WHERE user_id NOT IN (SELECT user_id FROM events WHERE ts >= (SELECT date_trunc('day', min(ts)) FROM events) AND ts < (SELECT date_trunc('day', min(ts)) + INTERVAL 1 DAY FROM events))")(lambda s, d: _silent(s, d))


def _silent(s, d):
    readings = feed(s, d, "ev_many")
    low = readings.agg(F.date_trunc("day", F.min("ts")).cast("timestamp_ntz")).first()[0]
    return relops.silent_machines(readings.select("machine_id").distinct(), readings, F.lit(low), F.lit(low) + F.expr("INTERVAL 1 DAY"))


query("active_series", sql.codes("ord_priority", "prio", "SELECT DISTINCT machine_id, sensor_id FROM scored WHERE p < threshold", threshold=0.02))(
    lambda s, d: relops.active_series(feed(s, d, "ord_priority").select(*KEY).distinct(), _found(s, d, "ord_priority", "prio", 0.02))
)
query("diff_runs", sql.chain("ev_single", "A", "SELECT machine_id, sensor_id, rn, p AS p_a, p AS p_b FROM scored WHERE false"))(lambda s, d: relops.diff_runs(_scored(s, d), _scored(s, d, sorted_sweep=False, rotation=False)))
query("pivot_tick", "SELECT machine_id, ts, tick, max(v) FILTER (sensor_id = 'tax') AS tax, max(v) FILTER (sensor_id = 'discount') AS discount FROM (" + sql.FEEDS["li_sensors"] + ") GROUP BY 1, 2, 3")(
    lambda s, d: relops.pivot_tick(feed(s, d, "li_sensors"), ["tax", "discount"])
)
query("time_parts", f"SELECT machine_id, sensor_id, tick, date_trunc('day', ts) AS day, CAST(hour(ts) AS INTEGER) AS hour, epoch_us(ts) AS micros FROM ({sql.FEEDS['ev_ten']})")(
    lambda s, d: relops.time_parts(feed(s, d, "ev_ten")).select(*KEY, "tick", F.col("day").cast("timestamp_ntz").alias("day"), "hour", "micros")
)
query("dispersion_exact", f"SELECT sensor_id, count(*) AS readings, count(DISTINCT v) AS distinct_values FROM ({sql.FEEDS['li_sensors']}) GROUP BY 1")(lambda s, d: summaries.dispersion(feed(s, d, "li_sensors")))
query("dispersion_approx")(lambda s, d: summaries.dispersion(feed(s, d, "li_sensors"), exact=False))
_GROUPS = "SELECT {cols}, count(*) AS windows FROM marked GROUP BY {how}"
query("share_rollup", sql.flags("ev_ten", "A", _GROUPS.format(cols="sensor_id, rule", how="ROLLUP (sensor_id, rule)")))(lambda s, d: summaries.share_rollup(_scored(s, d, "ev_ten")))
query("share_cube", sql.flags("ev_ten", "A", _GROUPS.format(cols="sensor_id, rule", how="CUBE (sensor_id, rule)")))(lambda s, d: summaries.share_cube(_scored(s, d, "ev_ten")))
query("share_grouping_sets", sql.flags("ev_ten", "A", _GROUPS.format(cols="sensor_id, coalesce(machine_id, -1) AS machine_id, rule", how="GROUPING SETS ((sensor_id), (marked.machine_id), (rule))")))(lambda s, d: summaries.share_sets(_scored(s, d, "ev_ten")).withColumn("machine_id", F.coalesce("machine_id", F.lit(-1))))
query("score_quantiles", sql.chain("ev_ten", "A", "SELECT sensor_id, quantile_cont(p, 0.01) AS p01, quantile_cont(p, 0.1) AS p10, quantile_cont(p, 0.5) AS p50 FROM scored GROUP BY 1"))(lambda s, d: summaries.quantiles(_scored(s, d, "ev_ten")))
query("worst_window", sql.chain("ev_ten", "A", "SELECT machine_id, sensor_id, min(p) AS p, arg_min(rn, (p, rn)) AS rn, count(*) FILTER (p < threshold) AS anomalies FROM scored GROUP BY 1, 2"))(lambda s, d: summaries.worst_window(_scored(s, d, "ev_ten")))
query(
    "series_ranks",
    sql.chain("ev_ten", "A", """SELECT machine_id, sensor_id, unlikely, CAST(rank() OVER (PARTITION BY machine_id ORDER BY unlikely DESC) AS INTEGER) AS rank, CAST(dense_rank() OVER (PARTITION BY machine_id ORDER BY unlikely DESC) AS INTEGER) AS dense,
      CAST(row_number() OVER (PARTITION BY machine_id ORDER BY unlikely DESC, sensor_id) AS INTEGER) AS place, CAST(ntile(2) OVER (PARTITION BY machine_id ORDER BY unlikely DESC, sensor_id) AS INTEGER) AS half FROM (SELECT machine_id, sensor_id, count(*) FILTER (p < 0.05) AS unlikely FROM scored GROUP BY 1, 2)"""),
)(lambda s, d: summaries.rank_series(_scored(s, d, "ev_ten")))
for _kind, _op in (("union", "UNION ALL"), ("intersect", "INTERSECT"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    query(f"anomaly_setops_{_kind}", f"WITH RECURSIVE {sql.windows('ev_ten', 'A')}{sql.clusters()}{sql.scores()} SELECT machine_id, sensor_id FROM scored WHERE p < 0.02 {_op} SELECT machine_id, sensor_id FROM scored WHERE p < 0.002")(
        lambda s, d, k=_kind: relops.setops(_scored(s, d, "ev_ten").where("p < 0.02").select(*KEY), _scored(s, d, "ev_ten").where("p < 0.002").select(*KEY), k)
    )

# SQL functions.
query("udf_labels_sql", sql.chain("ev_ten", "A", "SELECT machine_id, sensor_id, rn, array_to_string(labels, ',') AS labels, p FROM scored"))(lambda s, d: _by_sql(s, d))


def _by_sql(s, d):
    udfs.register(s)
    _wins(s, d, "ev_ten", "A").createOrReplaceTempView("count_windows")
    return s.sql("SELECT machine_id, sensor_id, rn, array_join(cluster_labels(w, k), ',') AS labels, window_p(w, k, 5) AS p FROM count_windows")


query("udaf_dispersion", f"SELECT sensor_id, count(DISTINCT v) AS distinct_values FROM ({sql.FEEDS['ev_ten']}) GROUP BY 1")(lambda s, d: feed(s, d, "ev_ten").groupBy("sensor_id").agg(udfs.functions()["dispersion"]("v").alias("distinct_values")))


@query("udtf_trace")
def _(s, d):
    udfs.register(s)
    _wins(s, d, "ev_ten", "A").createOrReplaceTempView("all_windows")
    return s.sql("SELECT machine_id, sensor_id, rn, t.* FROM all_windows, LATERAL window_trace(w, k) t")


# Streams run to their end; the batch is the oracle.
def _stream(s, d, twice: bool = False):
    """The ten-machine feed as a stream of its table's files."""
    raw = table(s, d, "events")
    got = s.readStream.schema(raw.schema).parquet(f"{d}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))
    if twice:
        got = got.withColumn("_", F.explode(F.array(F.lit(1), F.lit(2)))).drop("_")
    return got.select((F.col("user_id") % 10).alias("machine_id"), F.col("event_type").alias("sensor_id"), "ts", F.col("event_id").alias("tick"), F.floor(F.col("value") / 20).cast("long").alias("v"))


def _ended(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    return streams.drained(df, f"{name}_{uuid.uuid4().hex[:8]}", mode)


_SPANS = "SELECT sensor_id, {start} AS start, {end} AS \"end\", count(*) AS n FROM (" + sql.FEEDS["ev_ten"] + ") {more} GROUP BY 1, 2, 3"
query("stream_tumbling", _SPANS.format(start="date_trunc('day', ts)", end="date_trunc('day', ts) + INTERVAL 1 DAY", more=""))(lambda s, d: _naive(_ended(stream.tumbling(_stream(s, d)), "tumbling", "complete")))
query("stream_sliding", _SPANS.format(start="date_trunc('day', ts) - x * INTERVAL 1 DAY", end="date_trunc('day', ts) + (2 - x) * INTERVAL 1 DAY", more=", LATERAL (SELECT unnest([0, 1]) AS x)"))(
    lambda s, d: _naive(_ended(stream.sliding(_stream(s, d)), "sliding", "complete"))
)
query(
    "stream_session",
    f"""SELECT sensor_id, min(ts) AS start, max(ts) + INTERVAL 1 HOUR AS "end", count(*) AS n FROM (
  SELECT *, sum(fresh) OVER (PARTITION BY sensor_id ORDER BY ts, tick) AS g FROM (
    SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY sensor_id ORDER BY ts, tick) + INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM ({sql.FEEDS['ev_ten']}))) GROUP BY sensor_id, g""",
)(lambda s, d: _naive(_ended(stream.session(_stream(s, d)), "session", "complete")))
query("stream_dedup", f"SELECT sensor_id, count(*) AS n FROM ({sql.FEEDS['ev_ten']}) GROUP BY 1")(
    lambda s, d: streams.landed(stream.dedup(_stream(s, d, twice=True), ["tick"]).select("sensor_id"), "dedup").groupBy("sensor_id").agg(F.count(F.lit(1)).alias("n"))
)


def _naive(df: DataFrame) -> DataFrame:
    return df.withColumns({"start": F.col("start").cast("timestamp_ntz"), "end": F.col("end").cast("timestamp_ntz")})


@query("stream_anomalies", sql.chain("ev_ten", "A", "SELECT machine_id, sensor_id, rn, p, rule FROM scored WHERE ts <= (SELECT max(ts) - INTERVAL 1 HOUR FROM feed) AND p < threshold"))
def _(s, d):
    """What a stream has released at its end: windows whose newest value the watermark has passed."""
    got = stream.detect(_stream(s, d), params.load(s, "A"))
    return streams.landed(got.where("p < 0.005").select(*KEY, "rn", "p", "rule"), "detected")


_HALF = "(SELECT min(ts) + (max(ts) - min(ts)) / 2 FROM feed0)"


@query("stream_late", f"WITH feed0 AS ({sql.FEEDS['ev_ten']}) SELECT sensor_id, count(*) AS n FROM feed0 WHERE ts < date_trunc('day', (SELECT max(ts) FROM feed0) - INTERVAL 1 HOUR) GROUP BY 1")
def _(s, d):
    """Daily counts of a stream whose fourth file repeats its first half, far behind the watermark: nothing of it counts.

    What is late is told by the watermark of the batch before the last one.
    """
    rows = feed(s, d, "ev_ten").withColumn("ts", F.col("ts").cast("timestamp"))
    low, high = rows.agg(F.min(F.unix_micros("ts")), F.max(F.unix_micros("ts"))).first()
    half = F.unix_micros("ts") < (low + high) // 2
    path = f"{shared_folder(s).rstrip('/')}/late-{uuid.uuid4().hex}"
    newest = rows.orderBy(F.desc("ts")).limit(1)
    for part in (rows.where(half), rows.where(~half), newest, rows.where(half), newest):
        part.coalesce(1).write.mode("append").parquet(path)
        time.sleep(1.1)  # a stream takes files by their time, in seconds
    counts = stream.tumbling(streams.files(s, path, rows.schema), "1 day", "1 hour")
    return _ended(counts, "late").groupBy("sensor_id").agg(F.sum("n").alias("n"))


@query(
    "stream_correlate",
    sql.chain("ev_ten", "A", "SELECT a.machine_id, a.sensor_id, a.rn, count(*) AS errors FROM scored a JOIN feed e ON e.machine_id = a.machine_id AND e.sensor_id = 'error' AND e.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR WHERE a.p < a.threshold GROUP BY 1, 2, 3"),
)
def _(s, d):
    """Errors of a machine around its anomalies, stream against stream."""
    path = f"{shared_folder(s).rstrip('/')}/found-{uuid.uuid4().hex}"
    _found(s, d, "ev_ten").select(*KEY, "rn", "ts").write.parquet(path)
    found = s.readStream.schema(s.read.parquet(path).schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    both = stream.correlate(found, _stream(s, d).where("sensor_id = 'error'"))
    return streams.landed(both.select(*KEY, "rn"), "near").groupBy(*KEY, "rn").agg(F.count(F.lit(1)).alias("errors"))


@query(
    "halo_slice",
    f"""WITH feed0 AS ({sql.FEEDS['ev_ten']}), n AS (SELECT *, row_number() OVER (PARTITION BY machine_id, sensor_id ORDER BY ts, tick) AS rn FROM feed0),
    b AS (SELECT machine_id, sensor_id, min(rn) AS a, max(rn) AS z FROM n WHERE ts >= {_HALF} GROUP BY 1, 2)
    SELECT n.* FROM n JOIN b USING (machine_id, sensor_id) WHERE rn BETWEEN a - 10 AND z""",
)
def _(s, d):
    """The later half of the feed with what its first windows need."""
    readings = feed(s, d, "ev_ten")
    low, high = readings.agg(F.min("ts"), F.max("ts")).first()
    middle = low + (high - low) / 2
    return windows.with_halo(readings, F.lit(middle), F.lit(high) + F.expr("INTERVAL 1 SECOND"), 10)


query("udaf_least_likely", sql.chain("ev_ten", "A", "SELECT machine_id, sensor_id, min(p) AS p FROM scored GROUP BY 1, 2"))(lambda s, d: _scored(s, d, "ev_ten").groupBy(*KEY).agg(udfs.functions()["least_likely"]("p").alias("p")))
query("map_pair_counts", f"WITH RECURSIVE {sql.windows('ev_ten', 'A')}{sql.clusters()}, pairs AS (SELECT machine_id, sensor_id, rn, labels[u] || '>' || labels[u + 1] AS pair FROM labelled, LATERAL (SELECT unnest(range(1, 10)) AS u)), sums AS (SELECT machine_id, sensor_id, rn, pair, count(*) AS n FROM pairs GROUP BY ALL) SELECT machine_id, sensor_id, rn, string_agg(pair || '=' || n, ',' ORDER BY pair) AS counts FROM sums GROUP BY 1, 2, 3")(
    lambda s, d: summaries.pair_maps(_scored(s, d, "ev_ten", labels=True)).select(*KEY, "rn", F.array_join(F.array_sort(F.transform(F.map_entries("counts"), lambda e: F.concat(e.key, F.lit("="), e.value.cast("string")))), ",").alias("counts"))
)
query("hinted_joins", f"SELECT machine_id, rn, s_name, n_name, r_name, hint FROM ({_LI}) JOIN supplier ON machine_id = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey, (VALUES ('merge'), ('shuffle_hash'), ('broadcast')) h(hint)")(lambda s, d: _hinted(s, d))


def _hinted(s, d):
    rows = stored(_scored(s, d, "li_sensors", "B").where("rule = 'rotation' AND sensor_id = 'tax'").select("machine_id", "rn"), "rotated")
    named = [relops.name_machine(rows, *(table(s, d, t) for t in ("supplier", "nation", "region")), hint=h).select("machine_id", "rn", "s_name", "n_name", "r_name", F.lit(h).alias("hint")) for h in ("merge", "shuffle_hash", "broadcast")]
    return named[0].unionByName(named[1]).unionByName(named[2])
