"""Streams give what batches give."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from chartrel.operators import learned
from chartrel.sources import png
from chartrel.sources.tables import table
from chartrel.streaming import charts


def _folder(spark, small, tmp_path):
    path = str(tmp_path / "events")
    table(spark, small, "events").orderBy("event_id").coalesce(1).write.parquet(path)
    return path


def test_windows_equal_batch(spark, small, tmp_path):
    folder = _folder(spark, small, tmp_path)
    s = charts.windowed_sums(charts.events(spark, folder), "1 day")
    q = s.writeStream.format("memory").queryName("win").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination(120)
    b = table(spark, small, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "cents")
    assert sorted(map(tuple, spark.table("win").collect())) == sorted(map(tuple, b.collect()))


def test_stateful_relations_reach_the_batch(spark, small, tmp_path):
    from chartrel.operators import truth
    from chartrel.sources.families import FAMILIES

    folder = _folder(spark, small, tmp_path)
    q = charts.stateful_relations(charts.events(spark, folder)).writeStream.format("memory").queryName("rel").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {(r["user_id"], r["event_type"]): r["relation"] for r in spark.table("rel").collect()}
    want = {(r["chart_id"], r["series_key"]): r["relation"] for r in truth.relations(FAMILIES["user"](spark, small)).collect()}
    assert got == want


class Held:
    """State of one key, kept between batches."""

    exists, hasTimedOut, get = False, False, None

    def update(self, value):
        self.exists, self.get = True, value

    def setTimeoutDuration(self, _):
        pass


@pytest.mark.parametrize("most,n,relation", [(None, 1200, "increasing"), (400, 400, "decreasing")])
def test_state_keeps_every_point_unless_bounded(most, n, relation):
    x = np.arange(1200)
    y = np.where(x < 800, x, 2000 - x)  # rises for 800 points, falls for 400
    state, out = Held(), None
    for part in np.array_split(x, 7):
        out = pd.concat(charts._step(most, "1 day", (7, "view"), iter([pd.DataFrame({"x": part, "y": y[part]})]), state))
    assert out.to_dict("records") == [{"user_id": 7, "event_type": "view", "n": n, "relation": relation}]


def test_chart_files_stream(spark, tmp_path):
    src = tmp_path / "in"
    src.mkdir()
    for c in range(3):
        img = np.full((60, 80, 3), 255, np.uint8)
        for x in range(10, 70):
            img[50 - x // 2 if c % 2 else 10 + x // 2, x] = (255, 0, 0)
        (src / f"{c}.png").write_bytes(png.encode(img))
    q = charts.extract_stream(charts.chart_files(spark, str(src), 2), str(tmp_path / "out"), str(tmp_path / "cp"))
    q.awaitTermination(120)
    got = {r["chart_id"]: r["relation"] for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert got == {0: "decreasing", 1: "increasing", 2: "decreasing"}
    assert learned.predict(png.from_files(spark, str(src))).count() == 3
