"""What larger tables ask of plans and operators."""

import re

from pyspark.sql import functions as F

from hitcodec.sources import views as V


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_pulses_are_drawn_once(spark, sf):
    """A filter on the numbers of pulses does not repeat the arithmetic of the draw for each of their steps."""
    text = plan(V.or0(spark, sf).where("pulses > 0").groupBy("channel").count())
    assert len(re.findall("1000003", text)) < 30
    assert "transform(" not in plan(V.or1(spark, sf))
    want = V.or0(spark, sf).agg(F.sum("pulses")).first()[0]
    assert V.or1(spark, sf).count() == want


def test_streamed_rows_are_files(spark, sf):
    """Appended rows are read from files and not held by the driver."""
    from hitcodec.streaming import streams as S

    got = S.run(S.hits_of(spark, sf).drop("at"), "append")
    assert "FileScan parquet" in plan(got) and got.count() == V.ev1(spark, sf).count()


def test_packets_of_overlapping_pulses(spark):
    from hitcodec.operators import layout as L

    hits = [(1, 0, 0, 100), (1, 0, 0, 100), (1, 0, 40, 50), (1, 0, 50, 60), (1, 1, 7, 7), (1, 1, 7, 9), (2, 1, 5, 2**20), (2, 1, 6, 7)]
    df = spark.createDataFrame(hits, "event long, channel int, rise long, fall long")
    assert sorted(map(tuple, L.unpack_fixed(L.pack_fixed(df, 2), 2).collect())) == sorted(hits)


def test_intervals_are_not_broadcast(spark, sf):
    from hitcodec.operators import relational as R

    assert not re.findall(r"BroadcastHashJoin|HashedRelation", plan(R.join_interval(V.or1(spark, sf), 4096)))


def test_classes_are_not_broadcast(spark, sf):
    df = V.cu1(spark, sf)
    assert "BroadcastHashJoin" not in plan(df) and df.columns == ["event", "channel", "id", "pulses", "event_class"]


def test_large_tables_are_not_broadcast(spark, monkeypatch):
    from hitcodec.operators import relational as R

    a, b = spark.range(50), spark.range(40)
    assert "BroadcastHashJoin" in plan(R.join_with(a, b, "id", strategy="broadcast"))
    monkeypatch.setattr(R, "BROADCAST_ROWS", 39)
    both = R.join_with(a, b, "id", strategy="broadcast")
    assert "SortMergeJoin" in plan(both) and both.count() == 40


def test_width_bins_read_the_pulses_once(spark, sf):
    from hitcodec import registry

    for df in registry._or1_width_bins(spark, sf):
        assert "MapInArrow" not in plan(df) and "Window" not in plan(df)


def test_frames_are_coded_once(spark, sf, tmp_path):
    """Ranges of events are drawn from written frames: the coder runs over each hit once."""
    from hitcodec.operators import frames as FR
    from hitcodec.session import ship_package

    ship_package(spark)
    seen = spark.sparkContext.accumulator(0)

    def counted(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    h = V.ev1(spark, sf)
    models = FR.fit_models(h, V.CHANNELS)
    frames = FR.encode(h, models, V.CHANNELS)
    FR.write_frames(frames.mapInArrow(counted, FR.FRAME), str(tmp_path / "f"))
    assert seen.value == FR.read_frames(spark, str(tmp_path / "f")).count() > 0


def test_frames_step_in_small_grids():
    import numpy as np

    from hitcodec import registry

    sizes = np.array([0, 5, 1000, 3, 3, 400, 0, 90])
    groups = registry._groups(sizes, 800)
    assert sorted(np.concatenate(groups).tolist()) == list(range(8)) and registry._groups(sizes[:0]) == []
    assert all(len(g) == 1 or len(g) * sizes[g].max() <= 800 for g in groups)


def test_stream_join_buffers_pieces(spark, tmp_path):
    """Edges of several files meet; state is an entry for many events and not a row for each edge."""
    import random

    from hitcodec.session import ship_package
    from hitcodec.streaming import streams as S

    ship_package(spark)
    draw, second = random.Random(5), 1_000_000
    edges = sorted((draw.randrange(7200) * second, draw.randrange(90), draw.randrange(3), draw.random() < 0.5) for _ in range(3000))
    edges += [(86_400 * second, 1, 1, True), (86_401 * second, 1, 1, False), (86_401 * second, 1, 1, False)]
    schema = "tick long, event long, channel int, rising boolean"
    for part in (edges[:1500], edges[1500:3000], edges[3000:]):
        spark.createDataFrame(part, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "e"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "e"))
    stream = stream.withColumn("at", F.timestamp_micros(F.col("tick") + S.START_2024))
    got = S.run(S.rises_with_falls(stream), "append")
    want = [(a[1], a[2], a[0], b[0]) for a in edges for b in edges if a[1:3] == b[1:3] and a[3] and not b[3] and 0 < b[0] - a[0] <= 600 * second]
    assert sorted(map(tuple, got.collect())) == sorted(want) and len(want) > 100
    held = S.rises_with_falls(stream)._jdf.queryExecution().analyzed().toString()
    assert "FlatMapGroupsInPandasWithState" in held and "Join" not in held
