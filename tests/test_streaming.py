import datetime as dt

from waypath.streaming import events as ev
from waypath.tables import SCHEMAS

T0 = dt.datetime(2024, 1, 1)


def row(i, hours, user=1, k=5):
    return (i, T0 + dt.timedelta(hours=hours), user, "click", 1.0, '{"k": %d}' % k)


def run(spark, stream, name, mode):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).start()
    q.processAllAvailable()
    q.stop()
    return spark.table(name).collect()


def files(spark, folder, batches):
    for i, b in enumerate(batches):
        spark.createDataFrame(b, SCHEMAS["events"]).coalesce(1).write.parquet(f"{folder}/b{i}")
    return ev.event_stream(spark, f"{folder}/b*")


def test_late_and_repeated_rows(spark, tmp_path):
    s = files(spark, str(tmp_path), [[row(1, 1), row(1, 1), row(2, 2)], [row(3, 60)], [row(4, 3)], [row(5, 120)]])
    got = run(spark, ev.windowed_rel(s), "late", "append")
    first = [r.val for r in got if r.start == T0]
    assert first and first[0] <= 3 and all(r.start < T0 + dt.timedelta(days=5) for r in got)


def test_running_profile(spark, tmp_path):
    s = files(spark, str(tmp_path), [[row(1, 1, k=1), row(2, 2, k=2)], [row(3, 3, k=2)]])
    got = run(spark, ev.running_profiles(s), "running", "update")
    assert max((r.total, r.n_feat) for r in got) == (3, 2)


def test_arrivals_meet_saved_profiles(spark):
    saved = spark.createDataFrame([(1, [1, 2, 3]), (2, [3, 4]), (3, [9])], "obj long, feats array<long>")
    new = spark.createDataFrame([(10, [2, 3, 4]), (2, [3, 4])], "obj long, feats array<long>")
    got = {(r.obj, r.nbr): r.common for r in ev.arrivals_near(new, saved, 1).collect()}
    assert got == {(10, 1): 2, (10, 2): 2, (2, 1): 1}
    assert ev.arrivals_near(new, saved, 2).count() == 2


def test_touched_objects_reach_the_rebuild(spark, sf, tmp_path):
    rows = spark.read.parquet(f"{sf}/events.parquet")
    rows.where("event_id % 2 = 0").write.mode("append").parquet(str(tmp_path / "in"))
    seen = []
    q = ev.on_touched(ev.event_stream(spark, str(tmp_path / "in"), 100), lambda df, i: seen.extend(r.obj for r in df.collect()), str(tmp_path / "checkpoint"))
    q.processAllAvailable()
    q.stop()
    want = {r.user_id for r in ev.event_features(rows.where("event_id % 2 = 0")).select("user_id").distinct().collect()}
    assert set(seen) == want and want
