"""Frames with values that no model was fitted on, with models by channel, and packets that refuse what does not fit."""

import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from hitcodec.operators import frames as FR
from hitcodec.operators import layout as L
from hitcodec.session import ship_package

HITS = "event long, channel int, rise long, fall long"


def rows(df):
    return sorted(tuple(r) for r in df.select("event", "channel", "rise", "fall").collect())


@pytest.fixture(scope="module")
def hits(spark):
    ship_package(spark)
    return spark.range(4000).selectExpr("id div 20 as event", "cast(id * 7 % 5 as int) as channel", "id * 1000 + id % 13 as rise", "id * 1000 + 20 + (id * id) % (10 * (1 + id * 7 % 5)) as fall")


@pytest.mark.parametrize("scopes", [None, [0, 1, 2, 3, 4], [0, 0, 1, 1, 1]])
@pytest.mark.parametrize("backward", [False, True])
def test_scopes(hits, scopes, backward):
    models = FR.fit_models(hits, 5, scopes=scopes)
    frames = FR.encode(hits, models, 5, backward=backward, hide=True)
    assert rows(FR.decode(frames, models, 5, backward)) == rows(hits)
    if not backward:
        assert FR.count_at_least(frames, models, "width", 30, 5).first()["n"] == hits.where("fall - rise >= 30").count()
    size = 1 << models["pulses"]["coder"]["r"]
    assert {r["state"] for r in FR.hidden(frames, models, backward).collect()} <= {r["n_hits"] % size for r in frames.collect()}


@pytest.mark.parametrize("scopes", [None, [0, 1, 2, 3, 4]])
def test_unfitted_values(spark, hits, scopes):
    """70,000 pulses in one channel, and times up to 2**60 apart."""
    models = FR.fit_models(hits, 5, scopes=scopes)
    many = spark.range(70_000).selectExpr("3L as event", "2 as channel", "id * 10 as rise", "id * 10 + 1 as fall")
    far = spark.createDataFrame([(9, 0, 5, 2**60), (9, 0, 2**59, 2**59 + 1), (9, 4, 0, 1), (11, 1, -(2**60), -(2**60)), (70, 3, 2**61, 2**61 + 2)], HITS)
    odd = many.unionByName(far)
    assert rows(FR.decode(FR.encode(odd, models, 5), models, 5)) == rows(odd)


def test_units_in_one_plan(spark, hits):
    units = spark.createDataFrame([(0, 7), (1, 7), (2, 8), (3, 8), (4, 9)], "channel int, unit_id int")
    models = FR.fit_models(hits, 5)
    frames = FR.encode_by_unit(hits, units, models, 5)
    assert frames.columns == ["unit_id", *FR.NAMES] and {r["unit_id"] for r in frames.collect()} == {7, 8, 9}
    assert rows(FR.decode(FR.split_units(FR.merge_units(frames)), models, 5)) == rows(hits)


def test_packets_refuse(spark):
    one = lambda *r: spark.createDataFrame([r], HITS)
    assert rows(L.unpack_fixed(L.pack_fixed(one(1, 0, 0, 2**27 - 1), 2), 2)) == [(1, 0, 0, 2**27 - 1)]
    for bad in (one(1, 0, 0, 2**29), one(1, 0, 5, 4)):
        with pytest.raises(PySparkException):
            L.pack_fixed(bad, 2).collect()
    many = spark.range(16).selectExpr("1L as event", "0 as channel", "id as rise", "id as fall")
    with pytest.raises(PySparkException):
        L.pack_fixed(many, 2).collect()
    good = one(1, 127, 10, 510)
    assert sorted((r["tick"], r["rising"]) for r in L.unpack_words(L.pack_words(good)).where(F.col("channel") == 127).collect()) == [(10, True), (510, False)]
    for bad in (one(1, 200, 10, 20), one(1, 0, -1, 5), one(1, 0, 0, L.EPOCH_TICKS << 28)):
        with pytest.raises(PySparkException):
            L.pack_words(bad).collect()


def test_silent_channels_are_not_coded(spark, tmp_path):
    """Sparse frames: as many numbers of pulses as active channels; scopes, escapes and queries on compressed data work too."""
    import numpy as np
    from pyspark.sql import functions as F

    from hitcodec.operators import frames as FR
    from hitcodec.session import ship_package

    ship_package(spark)
    for places in ([], [0], [5], [10**9], [0, 1, 2, 3], [7, 4096, 4097, 10**6]):
        data = FR.pack_places(np.array(places, np.int64))
        got, used = FR.unpack_places(data + b"\xff\x01", len(places))
        assert got.tolist() == places and used == len(data)
    n = 20_000
    hits = spark.range(600).selectExpr("id div 4 AS event", "CAST(id * 7919 % 20000 AS INT) AS channel", "id * 10 AS rise", "id * 10 + 5 + id % 3 AS fall")
    hits = hits.union(spark.range(40).selectExpr("3L", "CAST(19999 AS INT)", "id * 100", "id * 100 + 50"))
    for scopes in (None, [k % 2 for k in range(n)]):
        models = FR.fit_models(hits, n, scopes=scopes, sparse=True)
        frames = FR.encode(hits, models, n, hide=True)
        assert frames.agg(F.sum("pulses_n")).first()[0] == hits.select("event", "channel").distinct().count()
        assert sorted(FR.decode(frames, models, n).collect()) == sorted(hits.collect())
        assert FR.count_at_least(frames, models, "width", 6, n).first()[0] == hits.where("fall - rise >= 6").count()
        size = 1 << models["pulses"]["coder"]["r"]
        assert sorted(tuple(r) for r in FR.hidden(frames, models).collect()) == sorted((r["frame"], r["n_hits"] % size) for r in frames.collect())
