"""Streams run as streams: windows with late rows, repeated events, sums kept in state, interval joins, restarts."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from rayfit import losses, streaming

START = dt.datetime(2024, 1, 1)


def rows(*hours_and_ids):
    return [(i, START + dt.timedelta(hours=h), i % 3, "purchase" if i % 2 else "view", float(i)) for h, i in hours_and_ids]


KINDS = "event_id long, ts timestamp, user_id long, event_type string, loss double"


class Feed:
    """Files that arrive one after another in a folder, and a query that reads what is there."""

    def __init__(self, spark, path, make, mode):
        self.spark, self.path, self.make, self.mode, self.n = spark, path, make, mode, 0
        (path / "in").mkdir()

    def send(self, *hours_and_ids):
        self.n += 1
        self.spark.createDataFrame(rows(*hours_and_ids), KINDS).coalesce(1).write.parquet(str(self.path / "in" / f"{self.n:03}"))
        out = []
        stream = self.spark.readStream.schema(KINDS).option("recursiveFileLookup", "true").parquet(str(self.path / "in"))
        query = self.make(stream).writeStream.outputMode(self.mode).option("checkpointLocation", str(self.path / "ck")).foreachBatch(lambda df, _: out.extend(df.collect())).trigger(availableNow=True).start()
        query.awaitTermination(120)
        self.progress = query.lastProgress
        return out


def test_windows_drop_late_rows_and_go_on_after_a_restart(spark, tmp_path):
    feed = Feed(spark, tmp_path, lambda s: streaming.window_loss(s, width="1 day", late="2 hours"), "append")
    assert feed.send((1, 1), (2, 3)) == []  # the day is not over
    feed.send((30, 5))  # a new run from the checkpoint: the first day is closed once the watermark has passed it
    late = feed.send((3, 7), (55, 9))  # one row for a day that is closed, one that closes the second
    done = {r.start: (r.n, r.loss) for r in late}
    assert START not in done
    total = {r.start: r.n for r in late} | {r.start: r.n for r in feed.send((90, 11))}
    assert total == {START + dt.timedelta(days=1): 1, START + dt.timedelta(days=2): 1}


def test_repeated_events_count_once(spark, tmp_path):
    feed = Feed(spark, tmp_path, lambda s: streaming.deduplicated(s, late="1 day"), "append")
    assert sorted(r.event_id for r in feed.send((1, 1), (1, 1), (2, 2))) == [1, 2]
    assert sorted(r.event_id for r in feed.send((2, 2), (3, 3))) == [3]


@pytest.mark.parametrize("mode", ["update", "complete"])
def test_sums_are_kept_in_state(spark, tmp_path, mode):
    def make(s):
        own = s.select(F.to_date("ts").alias("epoch"), F.lit(1.0).alias("y"), (F.col("loss") / 10).alias("z"), F.lit(1.0).alias("q"))
        return streaming.running_coefficients(own, losses.Logistic(), 2)

    feed = Feed(spark, tmp_path, make, mode)
    feed.send((1, 1), (2, 2))
    out = {str(r.epoch): r for r in feed.send((3, 3), (26, 4))}
    batch = {str(r.epoch): r for r in make(spark.createDataFrame(rows((1, 1), (2, 2), (3, 3), (26, 4)), KINDS)).collect()}
    assert set(out) == set(batch) and all(out[d][c] == pytest.approx(batch[d][c]) for d in out for c in ("n", "c0", "c1", "c2"))


def test_interval_join_of_streams(spark, tmp_path):
    feed = Feed(spark, tmp_path, lambda s: streaming.interval_join(s.filter("event_type = 'purchase'"), s, "user_id", "2 hours").select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b")), "append")
    assert feed.send((1, 1), (1.5, 4)) == [(1, 4)]  # both of user 1
    assert sorted(feed.send((2, 7), (9, 10))) == [(1, 7)]  # 1 waits in the state; 10 comes too late


def test_sessions_in_batches(spark):
    df = spark.createDataFrame(rows((0, 3), (0.5, 6), (4, 9), (4.2, 12)), KINDS)
    assert sorted((r.n, r.loss) for r in streaming.session_loss(df, "user_id", pause="1 hour").collect()) == [(2, 4.5), (2, 10.5)]
