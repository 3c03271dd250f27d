"""Messages of fixed layout: rendering, parsing by position, and the general parser they are measured against.

Layout (ours): ``<g:000000000001> <has:machine> "m42" ; <has:time> "1999-01-02 00:00:00" ; <has:tick> "7" .``
followed by `` [<s:quantity> "17"]`` for each reading. Everything before the machine id
has constant length, and what separates readings is constant.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ID_AT = 37  # code points before the machine id
HEAD = '<has:machine> "m'
PREFIX = 17  # length of '<g:' + 12 digits + '> '
BETWEEN = '" ; <has:time> "'
BEFORE_TICK = '" ; <has:tick> "'
OPEN, MIDDLE, CLOSE = " [<s:", '> "', '"]'


def render(readings: DataFrame) -> DataFrame:
    """One message for each machine and instant, with all its readings by sensor name."""
    one = F.concat(F.lit(OPEN), "sensor_id", F.lit(MIDDLE), F.col("v").cast("string"), F.lit(CLOSE))
    parts = readings.select("machine_id", "ts", "tick", F.struct("sensor_id", one.alias("part")).alias("x"))
    groups = parts.groupBy("machine_id", "ts", "tick").agg(F.array_sort(F.collect_list("x")).alias("xs"))
    body = F.array_join(F.transform("xs", lambda x: x.part), "")
    head = F.concat(F.lit("<g:"), F.lpad(F.col("tick").cast("string"), 12, "0"), F.lit("> "), F.lit(HEAD))
    return groups.select(F.concat(head, F.col("machine_id").cast("string"), F.lit(BETWEEN), F.date_format("ts", "yyyy-MM-dd HH:mm:ss.SSSSSS"), F.lit(BEFORE_TICK), F.col("tick").cast("string"), F.lit('" .'), body).alias("msg"))


def _until(rest: Column, stop: str) -> Column:
    return F.substring_index(rest, stop, 1)


def peek_machine(msgs: DataFrame) -> DataFrame:
    """``machine_id`` alone: one substring at a known place, and a search over the id's own length."""
    at = PREFIX + len(HEAD) + 1
    return msgs.withColumn("machine_id", _until(F.substr("msg", F.lit(at)), '"').cast("long"))


def parse_by_offset(msgs: DataFrame) -> DataFrame:
    """Readings by skipping constant stretches: one pass over the quotation marks, then everything stands at a known place.

    Values are the odd fields. The even ones are constant but for a sensor's name, which
    has a fixed number of characters before and behind it.
    """
    fields = msgs.select(F.split("msg", '"').alias("f"))
    first, next_, behind = len(" ." + OPEN), len("]" + OPEN), len(MIDDLE) - 1

    def reading(i: Column) -> Column:
        skip = F.when(i == 3, first).otherwise(next_)
        gap = F.get("f", 2 * i)
        return F.struct(F.substr(gap, skip + 1, F.length(gap) - skip - behind).alias("sensor_id"), F.get("f", 2 * i + 1).cast("long").alias("v"))

    many = F.sequence(F.lit(3), (F.size("f") / 2).cast("int") - 1)
    rows = fields.select(
        F.substr(F.get("f", F.lit(1)), F.lit(2)).cast("long").alias("machine_id"), F.get("f", F.lit(3)).cast("timestamp_ntz").alias("ts"), F.get("f", F.lit(5)).cast("long").alias("tick"),
        F.explode(F.when(F.size("f") >= 8, F.transform(many, reading))).alias("x"),
    )
    return rows.select("machine_id", F.col("x.sensor_id").alias("sensor_id"), "ts", "tick", F.col("x.v").alias("v"))


def parse_head(msgs: DataFrame) -> DataFrame:
    """Machine, time and tick of each message, its readings untouched: all that progress needs."""
    rest = msgs.select(F.substr("msg", F.lit(PREFIX + len(HEAD) + 1), F.lit(len(BETWEEN) + len(BEFORE_TICK) + 70)).alias("rest"))
    f = rest.select(F.split("rest", '"', 6).alias("f"))
    return f.select(F.get("f", F.lit(0)).cast("long").alias("machine_id"), F.get("f", F.lit(2)).cast("timestamp_ntz").alias("ts"), F.get("f", F.lit(4)).cast("long").alias("tick"))


def parse_generic(msgs: DataFrame) -> DataFrame:
    """The general parser: every property by pattern, wherever it stands."""
    head = {name: F.regexp_extract("msg", rf'<has:{name}> "([^"]*)"', 1) for name in ("machine", "time", "tick")}
    names = F.regexp_extract_all("msg", F.lit(r'<s:([^>]+)> "([^"]*)"'), F.lit(1))
    values = F.regexp_extract_all("msg", F.lit(r'<s:([^>]+)> "([^"]*)"'), F.lit(2))
    rows = msgs.select(
        F.regexp_replace(head["machine"], "^m", "").cast("long").alias("machine_id"), head["time"].cast("timestamp_ntz").alias("ts"), head["tick"].cast("long").alias("tick"), F.explode(F.arrays_zip(names.alias("s"), values.alias("v"))).alias("x")
    )
    return rows.select("machine_id", F.col("x.s").alias("sensor_id"), "ts", "tick", F.col("x.v").cast("long").alias("v"))


def parse_python_udf(msgs: DataFrame, arrow: bool = False) -> DataFrame:
    """The same parse over the language boundary, row by row or in Arrow batches: for measurement only."""
    kind = "struct<machine_id: long, ts: string, tick: long, xs: array<struct<sensor_id: string, v: long>>>"

    def one(msg: str):
        rest = msg[PREFIX + len(HEAD) :]
        machine, rest = rest.split('"', 1)
        rest = rest[len(BETWEEN) - 1 :]
        time, tail = rest[:26], rest[26 + len(BEFORE_TICK) :]
        tick, *parts = tail.split(OPEN)
        return int(machine), time, int(tick.split('"', 1)[0]), [(p.split(MIDDLE, 1)[0], int(p.split(MIDDLE, 1)[1].split('"', 1)[0])) for p in parts]

    got = msgs.select(F.udf(one, kind, useArrow=arrow)("msg").alias("m"))
    rows = got.select("m.machine_id", F.col("m.ts").cast("timestamp_ntz").alias("ts"), "m.tick", F.explode("m.xs").alias("x"))
    return rows.select("machine_id", F.col("x.sensor_id").alias("sensor_id"), "ts", "tick", F.col("x.v").alias("v"))


def html_language(pages: DataFrame) -> DataFrame:
    """The language code of a page, at the place where the fixed head has it."""
    return pages.select("page_id", F.substr("html", F.lit(28), F.lit(2)).alias("lang"))
