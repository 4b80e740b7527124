import pytest
from pyspark.sql import functions as F

from wsample.operators import race
from wsample.streaming.stateful import expired, held, keyed_reservoirs, window_reservoirs


@pytest.mark.parametrize("kw", [{}, {"jump": True}, {"role": "inclusion"}])
def test_reservoirs_in_state(spark, sf, tmp_path, kw):
    """Rows come twice in every batch."""
    events = spark.read.parquet(f"{sf}/events.parquet").where("value > 0")
    for i in range(3):
        part = events.where(F.col("event_id") % 3 == i)
        part.union(part).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    last: dict = {}

    def keep(rows, batch):
        for r in rows.collect():
            last.setdefault((batch, r.stratum), []).append((r.id, r.position, r.seen))

    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out = keyed_reservoirs(stream, 5, stratum="event_type", weight="value", id_col="event_id", arrival="ts", seed=3, **kw)
    out.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start().awaitTermination()
    end = {s: last[b, s] for b, s in sorted(last)}
    counts = {r.event_type: r["count"] for r in events.groupBy("event_type").count().collect()}
    assert set(end) == set(counts) and all(len(v) == 5 and len({i for i, _, _ in v}) == 5 and v[0][2] == counts[s] for s, v in end.items())
    if not kw:
        want = race.race_by_group(events, 5, ["event_type"], weight="value", id_cols=["event_id"], seed=3)
        assert {(s, i, p) for s, v in end.items() for i, p, _ in v} == {(r.event_type, r.event_id, r.position) for r in want.collect()}


def test_windows_close_and_late_rows_stay_out(spark, tmp_path):
    rows = [(1, "2024-01-01 00:10:00", 5.0), (2, "2024-01-01 00:20:00", 1.0), (3, "2024-01-03 00:00:00", 1.0), (6, "2024-01-03 00:00:01", 1e-9), (4, "2024-01-01 00:30:00", 1e9), (5, "2024-01-05 00:00:00", 1.0), (7, "2024-01-05 00:00:01", 1.0)]
    for part in (rows[:2], rows[2:3], rows[3:4], rows[4:5], rows[5:6], rows[6:]):
        spark.createDataFrame(part, "event_id long, ts string, value double").selectExpr("event_id", "CAST(ts AS timestamp_ntz) ts", "value").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("event_id long, ts timestamp_ntz, value double").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    found = []
    out = window_reservoirs(stream, 3, weight="value", id_col="event_id", time="ts", width="1 day", width_us=86_400_000_000).writeStream.outputMode("update").foreachBatch(lambda df, b: found.extend(df.collect()))
    out.option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start().awaitTermination()
    closed = [r for r in found if r.closed]
    first = min(r.window_start for r in found)
    assert {r.id for r in closed if r.window_start == first} == {1, 2} and 4 not in {r.id for r in found}


def test_state_of_another_layout_is_refused():
    class State:
        exists, get = True, (99,)

    with pytest.raises(ValueError, match="layout"):
        held(State())


def test_state_goes_after_its_time():
    class State:
        def __init__(self, over):
            self.hasTimedOut, self.gone, self.time = over, False, None

        def remove(self):
            self.gone = True

        def setTimeoutDuration(self, ms):
            self.time = ms

    old, new, ever = State(True), State(False), State(False)
    assert expired(old, 5) and old.gone and not expired(new, 5) and new.time == 5 and not expired(ever, None) and ever.time is None
