from pyspark.sql import functions as F

from noisytree.plans import budget
from noisytree.plans.domain import EV
from noisytree.sources.points import table
from noisytree.streaming import windows
from tests.conftest import TINY


def timed(df):
    return df.select(F.col("ts").cast("timestamp").alias("ts"), "user_id", (F.dayofmonth("ts") - 1 + F.hour("ts") / 24).alias("x"), F.col("value").alias("y"))


def test_stream_releases_final_windows_once(spark, tmp_path):
    src, eps = str(tmp_path / "in"), budget.geometric(1.0, 1)
    table(spark, TINY, "events").orderBy("ts").coalesce(1).write.parquet(src)
    schema = table(spark, TINY, "events").schema
    stream = timed(spark.readStream.schema(schema).parquet(src))
    got = {}

    def sink(nodes, batch):
        for r in nodes.collect():
            assert (r.win_start, r.level, r.node_id) not in got
            got[r.win_start, r.level, r.node_id] = r.y

    windows.release_stream(stream, EV, 1, eps, sink, str(tmp_path / "cp")).awaitTermination(120)
    batch = windows.window_trees(windows.tumbling_leaves(timed(table(spark, TINY, "events")), EV, 1), 1, 2, eps)
    want = {(r.win_start, r.level, r.node_id): r.y for r in batch.collect()}
    assert got and all(abs(want[k] - y) < 1e-9 for k, y in got.items())
    assert len(want) - len(got) <= 2 * 5  # windows that the watermark has not passed


def test_shares_and_bounds(spark):
    assert windows.sliding_share(1.0, 24, 6) == 0.25
    e = table(spark, TINY, "events")
    assert windows.bounded(e, 3).groupBy("user_id").count().agg(F.max("count")).first()[0] <= 3
