from relpress.model import Relation
from relpress.operators import compression
from relpress.streaming import events

ROWS = [("2024-01-01 08:00:00", "view"), ("2024-01-01 08:20:00", "view"), ("2024-01-01 09:10:00", "click"), ("2024-01-02 09:15:00", "view"), ("2024-01-02 23:00:00", "error")]


def table(spark):
    return spark.createDataFrame(ROWS, "ts string, event_type string").selectExpr("cast(ts AS timestamp) AS ts", "event_type")


def test_stream_gives_the_batch_result(spark, tmp_path):
    source = table(spark)
    source.write.parquet(str(tmp_path / "in"))
    rows = events.tuples(source)
    c = compression.area_cover(Relation.of(rows.where("c1 < 10"), ["c0", "c1"]), s_min=2)
    stream = events.tuples(events.read(spark, str(tmp_path / "in"), "ts timestamp, event_type string"))
    events.append(stream, c, str(tmp_path / "out"), str(tmp_path / "state")).awaitTermination(120)
    got = spark.read.parquet(str(tmp_path / "out"))
    want = events.assign(rows, c)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert events.default_share(want).first()["n_default"] == want.where("entry = -1").count() >= 1


def test_windows_in_both_forms(spark, tmp_path):
    source = table(spark)
    source.write.parquet(str(tmp_path / "in"))
    batch = events.item_counts(events.tuples(source), ["c0", "c1"], "1 day")
    stream = events.item_counts(events.tuples(events.read(spark, str(tmp_path / "in"), "ts timestamp, event_type string")), ["c0", "c1"], "1 day", late="1 hour")
    stream.writeStream.format("memory").queryName("counts").outputMode("complete").trigger(availableNow=True).start().awaitTermination(120)
    assert sorted(map(tuple, spark.table("counts").collect())) == sorted(map(tuple, batch.collect()))


def test_sessions(spark):
    got = events.sessions(events.tuples(table(spark)), "c0", "30 minutes")
    assert sorted((r["c0"], r["n"]) for r in got.collect()) == [(99, 1), (101, 1), (118, 1), (118, 2)]
