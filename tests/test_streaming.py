"""Blocks of a stream are those of the batch form: late readings take their own places, the rest is flushed by a mark."""

import datetime

from meterpack.streaming import front

START = datetime.datetime(2024, 1, 1)


def test_late_readings_take_their_places(spark, tmp_path):
    """Three files, a micro-batch each: the second brings a reading half an hour behind, the third one far behind the watermark."""
    at = lambda minutes: START + datetime.timedelta(minutes=minutes)
    files = [[(1, at(0), 7, 1.0), (2, at(60), 7, 3.0)], [(3, at(30), 7, 2.0), (4, at(300), 7, 4.0), (4, at(300), 7, 4.0)], [(5, at(10), 7, 9.0), (6, at(310), 7, 5.0)]]
    path, marks, state = f"file://{tmp_path}/in", f"file://{tmp_path}/marks", f"file://{tmp_path}/state"
    found = []

    def take(rows, epoch):
        found.extend((r.stream_id, r.block_no, list(r.readings)) for r in rows.collect())

    def replay():
        events = front.read_events(spark, path).union(front.marks(spark, marks))
        blocks = front.assemble(front.readings(events), 2)
        blocks.writeStream.foreachBatch(take).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start().awaitTermination()

    for i, rows in enumerate(files):
        table = spark.createDataFrame([(e, ts, u, "k", v, "{}") for e, ts, u, v in rows], front.EVENTS)
        table.coalesce(1).write.parquet(f"file://{tmp_path}/out{i}")
        (tmp_path / "in").mkdir(exist_ok=True)
        next((tmp_path / f"out{i}").glob("*.parquet")).rename(tmp_path / "in" / f"events{i}.parquet")
        replay()
    front.close_input(spark, marks)
    replay()
    # as the batch form cuts them, without the reading behind the watermark
    assert sorted(found) == [(7, 0, [100, 200]), (7, 1, [300, 400]), (7, 2, [500])]
