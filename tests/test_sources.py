"""Readings, messages and metadata from files, and results into partitioned ones."""

from pyspark.sql import functions as F

from shiftscan.functions import codec
from shiftscan.plans import chain
from shiftscan.sources import feeds, params, sinks

SMALL = "/root/testdata/sf0.001"


def test_files_give_what_tables_give(spark, tmp_path):
    rows = feeds.feed(spark, SMALL, "ev_ten")
    want = sorted(map(tuple, rows.collect()))
    for fmt in ("csv", "json", "parquet"):
        rows.write.option("timestampNTZFormat", feeds.TEXT_TIME).format(fmt).save(f"{tmp_path}/{fmt}")
        assert sorted(map(tuple, feeds.readings(spark, f"{tmp_path}/{fmt}", fmt).collect())) == want
    codec.render(rows).write.text(f"{tmp_path}/text")
    assert sorted(map(tuple, codec.parse_by_offset(feeds.messages(spark, f"{tmp_path}/text")).collect())) == want


def test_metadata_and_partitioned_results(spark, tmp_path, monkeypatch):
    rows, meta = feeds.feed(spark, SMALL, "ev_ten"), params.load(spark, "A")
    meta.write.parquet(f"{tmp_path}/meta")
    sinks.write(chain.score(rows, params.load(spark, f"{tmp_path}/meta")), f"{tmp_path}/out")
    back = spark.read.parquet(f"{tmp_path}/out").where(F.col("sensor_id") == "view")
    assert "PartitionFilters: [isnotnull(sensor_id" in back._jdf.queryExecution().executedPlan().toString()
    assert back.count() == chain.score(rows, meta).where("sensor_id = 'view'").count()
    # Beyond the bound, metadata is joined without a hint and gives the same.
    monkeypatch.setattr(params, "MOST_SENSORS", 2)
    assert chain.detect(rows, params.load(spark, "A")).collect() == chain.detect(rows, meta).collect()
