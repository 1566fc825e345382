"""Sources, sinks, streams with state, SQL functions."""

import pytest
from pyspark.sql import functions as F

from floorcount.operators import encode, levels, sets, udf
from floorcount.sources import store, tables
from floorcount.streaming import distinct

TABLES = "/root/testdata/sf0.001"


@pytest.mark.parametrize("kind", ["csv", "json"])
def test_row_formats_give_the_same_sketch(spark, tmp_path, kind):
    ev = tables.load_table(spark, TABLES, "events", ["event_id", "user_id"])
    ev.write.format(kind).save(str(tmp_path / kind))
    again = tables.load_any(spark, kind, str(tmp_path / kind), ev.schema)
    bits = lambda df: sorted(map(tuple, levels.build_levels(df, ["user_id"], m=64).collect()))
    assert bits(ev) == bits(again)


def test_store_prunes_by_kind(spark, tmp_path):
    made = levels.build_levels(tables.load_table(spark, TABLES, "events"), ["user_id"], ["event_type"], 64)
    for spec in ("a", "b"):
        store.save_sketches(store.packed_sketches(made, ["event_type"], 64, spec), str(tmp_path / "s"))
    one = store.load_sketches(spark, str(tmp_path / "s"), "b")
    assert one.count() == 5 and "PartitionFilters: [isnotnull(spec" in one._jdf.queryExecution().executedPlan().toString()
    regs = encode.unpack(one.select("event_type", "floor", "words"), ["event_type"], 64)
    assert regs.filter("offset > 15 or offset < 0").count() == 0


def test_sketches_kept_by_key_across_micro_batches(spark, tmp_path):
    ev = tables.load_table(spark, TABLES, "events")
    ev.repartition(3).write.parquet(str(tmp_path / "in"))
    events = tables.stream_table(spark, str(tmp_path / "in"), ev.schema, files=1)
    query = distinct.sequential_state(events, "event_type", "user_id", 64).writeStream.outputMode("update").format("memory").queryName("kept").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    query.awaitTermination()
    got = {r["k"]: r for r in spark.sql("SELECT k, max(rows) AS rows, max_by(estimate, rows) AS estimate FROM kept GROUP BY k").collect()}
    want = {r["event_type"]: r for r in ev.groupBy("event_type").agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("d")).collect()}
    assert all(got[k]["rows"] == want[k]["n"] and abs(got[k]["estimate"] / want[k]["d"] - 1) < 0.4 for k in want)


def test_a_replayed_micro_batch_does_no_harm(spark, tmp_path):
    ev = tables.load_table(spark, TABLES, "events")
    ev.repartition(2).write.parquet(str(tmp_path / "in"))
    held = {}

    def merge(df, batch):
        for _ in range(2):
            for r in df.select("reg", "bits").collect():
                held[r["reg"]] = held.get(r["reg"], 0) | r["bits"]

    events = tables.stream_table(spark, str(tmp_path / "in"), ev.schema)
    rows = distinct.windowed_levels(events, ["user_id"], 64, F.lit(1))
    distinct.upsert_totals(rows, merge, str(tmp_path / "state")).trigger(availableNow=True).start().awaitTermination()
    assert held == {r["reg"]: r["bits"] for r in levels.build_levels(ev, ["user_id"], m=64).collect()}


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    ev = tables.load_table(spark, TABLES, "events").orderBy("ts")
    for i, part in enumerate((ev.filter("ts >= '2024-01-20'"), ev.filter("ts < '2024-01-10'"), ev.filter("ts >= '2024-01-29'"))):
        part.coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    source = spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("latestFirst", "false").parquet(str(tmp_path / "in"))
    events = source.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    query = distinct.windowed_levels(events, ["user_id"], 16, F.window("ts", "1 day")).writeStream.outputMode("append").format("memory").queryName("late").trigger(availableNow=True).start()
    query.awaitTermination()
    assert sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"]) > 0


def test_sql_functions(spark):
    udf.register(spark)
    ev = tables.load_table(spark, TABLES, "events")
    udf.sketch_agg(ev, ["user_id"], ["event_type"], 256).createOrReplaceTempView("held")
    rows = spark.sql("SELECT event_type, sketch_estimate(sketch) AS e, count(*) AS tiers FROM held, LATERAL sketch_tiers(sketch) GROUP BY ALL").collect()
    exact = {r["event_type"]: r["n_distinct"] for r in sets.exact_distinct(ev, ["user_id"], ["event_type"]).collect()}
    assert len(rows) == 5 and all(abs(r["e"] / exact[r["event_type"]] - 1) < 0.3 and r["tiers"] > 0 for r in rows)


def test_estimates_are_capped_by_rows(spark):
    df = spark.range(3)
    row = sets.approx_distinct(df, ["id"], m=16).select(sets.capped(F.col("estimate"), F.lit(3)).alias("e")).first()
    assert row["e"] <= 3
