"""Named queries of the relational operators, formats, streams and UDFs around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.functions import bits as B
from hitcodec.functions import udfs as U
from hitcodec.operators import bins as BN
from hitcodec.operators import frames as FR
from hitcodec.operators import layout as L
from hitcodec.operators import relational as R
from hitcodec.session import scratch, ship_package
from hitcodec.sources import tables as T
from hitcodec.sources import views as V
from hitcodec.streaming import streams as S

QUERIES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def named(name: str, f):
    QUERIES[name] = f


def t(spark, sf, name) -> DataFrame:
    return T.load(spark, sf, name)


# --- joins


def _inner(strategy):
    def f(spark, sf):
        line = t(spark, sf, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), V.cents("l_extendedprice").alias("price"))
        both = R.join_with(t(spark, sf, "orders").select("o_orderkey", "o_orderpriority"), line, "o_orderkey", strategy=strategy)
        return both.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum("price").alias("price"))

    return f


for _k, _s in (("smj", "merge"), ("shj", "shuffle_hash"), ("bhj", "broadcast")):
    named(f"join_inner_{_k}", _inner(_s))


def _outer(how):
    def f(spark, sf):
        # orders and shipments of each day: either has days without the other
        day = lambda c: F.date_format(c, "yyyy-MM-dd").alias("day")
        o = t(spark, sf, "orders").groupBy(day("o_orderdate")).agg(F.count(F.lit(1)).alias("ordered"))
        lines = t(spark, sf, "lineitem").groupBy(day("l_shipdate")).agg(F.count(F.lit(1)).alias("shipped"))
        return o.join(lines, "day", how).select("day", "ordered", "shipped")

    return f


for _k in ("left", "right", "full"):
    named(f"join_{_k}", _outer(_k))
named("join_semi", lambda spark, sf: t(spark, sf, "orders").select("o_orderkey").join(t(spark, sf, "lineitem").where("l_quantity > 45").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_semi"))
named("join_anti", lambda spark, sf: t(spark, sf, "orders").select("o_orderkey").join(t(spark, sf, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti"))
named("join_cross_small", lambda spark, sf: t(spark, sf, "nation").select("n_name").crossJoin(F.broadcast(t(spark, sf, "region").select("r_name"))))


@query
def join_theta(spark, sf):
    """Values and bins by a nested loop."""
    h = V.ev1(spark, sf).select((F.col("fall") - F.col("rise")).alias("v")).withColumn("vtype", F.lit("width"))
    hist = h.groupBy("vtype", "v").agg(F.count(F.lit(1)).alias("n"))
    bins = BN.adaptive_bins(hist, ["vtype"], share=16)
    return BN.assign_bin_join(hist, bins.drop("n", "vtype")).groupBy("bin").agg(F.sum("n").alias("n"))


named("join_interval", lambda spark, sf: R.join_interval(V.or1(spark, sf), 4096).groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"), F.sum("overlap").alias("ticks")))


@query
def join_asof(spark, sf):
    """For each pulse of channel 5, the last pulse of channel 3 in its event at or before it."""
    h = V.ev1(spark, sf)
    left = h.where("channel = 5").select("event", "rise", "fall")
    right = h.where("channel = 3").select("event", "rise", (F.col("fall") - F.col("rise")).alias("width"))
    return R.join_asof(left, right, "rise", ["event"], ["width"])


# --- aggregates

named("agg_hash", lambda spark, sf: V.ev1(spark, sf).withColumn("w", F.col("fall") - F.col("rise")).groupBy("channel").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("total"), F.min("w").alias("least"), F.max("w").alias("most"), F.round(F.avg("w"), 4).alias("mean")))
named("agg_collect", lambda spark, sf: V.ev1(spark, sf).groupBy("event").agg(F.array_join(F.transform(F.array_sort(F.collect_list("channel")), lambda c: c.cast("string")), ",").alias("channels")))
named("agg_distinct", lambda spark, sf: V.ev1(spark, sf).groupBy("event").agg(F.count_distinct("channel").alias("channels")))
named("agg_multi_distinct", lambda spark, sf: t(spark, sf, "events").agg(F.count_distinct("user_id").alias("users"), F.count_distinct("event_type").alias("kinds"), F.count_distinct("props").alias("props")))
named("agg_filter", lambda spark, sf: V.ev2(spark, sf).groupBy("channel").agg(F.count_if("rising").alias("rises"), F.count_if(~F.col("rising")).alias("falls"), F.count_if(F.col("rising").isNull()).alias("corrupt")))
named("agg_pivot", lambda spark, sf: L.value_streams(V.ev1(spark, sf)).groupBy("channel").pivot("vtype", list(L.TYPES)).agg(F.count(F.lit(1))))
named("agg_maxby", lambda spark, sf: V.ev1(spark, sf).groupBy("event").agg(F.min_by("channel", "rise").alias("first"), F.max_by("channel", "rise").alias("last")))
named("agg_salted", lambda spark, sf: R.salted_count(V.ev1(spark, sf), ["channel"]))


@query
def agg_percentile_exact(spark, sf):
    """The width of rank n div 2 (from 1) for each channel."""
    w = Window.partitionBy("channel").orderBy("w", "event", "rise")
    h = V.ev1(spark, sf).withColumn("w", F.col("fall") - F.col("rise")).withColumn("k", F.row_number().over(w)).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("channel")))
    return h.where("k = greatest(1, n div 2)").select("channel", F.col("w").alias("median"))


named("agg_moments", lambda spark, sf: V.em0(spark, sf).groupBy("channel").agg(F.round(F.stddev("v"), 2).alias("sd"), F.round(F.skewness("v"), 4).alias("skew")))


@query
def agg_approx_distinct(spark, sf):
    e = t(spark, sf, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.count_distinct("user_id").alias("b"))
    return e.select((F.abs(F.col("a") - F.col("b")) <= F.col("b") * 0.06 + 1).alias("close"))


@query
def agg_approx_quantile(spark, sf):
    """Is the share of values up to the approximate median within a hundredth of a half."""
    v = V.li2(spark, sf)
    m = v.agg(F.percentile_approx("v", 0.5, 10000).alias("m"))
    return v.crossJoin(F.broadcast(m)).agg((F.abs(F.avg((F.col("v") <= F.col("m")).cast("double")) - 0.5) < 0.01).alias("close"))


def class_values(spark, sf) -> DataFrame:
    v = L.value_streams(V.li1(spark, sf, None)).where("vtype <> 'pulses'")
    return v.join(F.broadcast(V.hierarchy(spark, sf)), "channel").withColumn("bits", B.bit_length("v"))


named("cube_cost", lambda spark, sf: class_values(spark, sf).cube("vtype", "unit_id").agg(F.sum("bits").alias("bits"), F.grouping_id().cast("int").alias("g")))
named("rollup_hierarchy", lambda spark, sf: class_values(spark, sf).rollup("unit_id", "class_id", "channel").agg(F.sum("bits").alias("bits"), F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("g")))


@query
def grouping_sets_cost(spark, sf):
    class_values(spark, sf).createOrReplaceTempView("class_values")
    return spark.sql("SELECT vtype, class_id, sum(bits) AS bits, CAST(grouping_id() AS INT) AS g FROM class_values GROUP BY GROUPING SETS ((vtype, class_id), (class_id), ())")


# --- windows, order, sets


def per_channel(spark, sf) -> DataFrame:
    return V.ev1(spark, sf).groupBy("event", "channel").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("fall") - F.col("rise")).alias("w"))


_by = lambda: Window.partitionBy("event").orderBy(F.col("w").desc(), "channel")
named("win_rank", lambda spark, sf: per_channel(spark, sf).select("event", "channel", F.row_number().over(_by()).alias("rn"), F.rank().over(Window.partitionBy("event").orderBy("n")).alias("rank"), F.dense_rank().over(Window.partitionBy("event").orderBy("n")).alias("dense")))
named("win_dense_ntile", lambda spark, sf: per_channel(spark, sf).select("event", "channel", F.ntile(4).over(_by()).alias("quarter")))
named("win_percent_rank", lambda spark, sf: per_channel(spark, sf).select("event", "channel", F.round(F.percent_rank().over(_by()), 6).alias("pr"), F.round(F.cume_dist().over(_by()), 6).alias("cd")))
named("win_lag_lead", lambda spark, sf: per_channel(spark, sf).select("event", "channel", F.lag("w").over(_by()).alias("before"), F.lead("w", 2).over(_by()).alias("after")))
named("win_running_rows", lambda spark, sf: per_channel(spark, sf).select("event", "channel", F.sum("w").over(_by().rowsBetween(-2, Window.currentRow)).alias("three")))
named("win_range_ticks", lambda spark, sf: V.ev1(spark, sf).select("event", "channel", "rise", F.count(F.lit(1)).over(Window.partitionBy("event").orderBy("rise").rangeBetween(-60_000_000, 0)).alias("recent")))
_all = lambda: _by().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
named("win_first_last_nth", lambda spark, sf: per_channel(spark, sf).select("event", "channel", F.first("w").over(_all()).alias("first"), F.last("w").over(_all()).alias("last"), F.nth_value("w", 2).over(_all()).alias("second")))
named("topk_global", lambda spark, sf: per_channel(spark, sf).orderBy(F.col("w").desc(), "event", "channel").limit(25))
named("topk_per_group", lambda spark, sf: R.topk_per_group(per_channel(spark, sf), ["event"], [F.col("w").desc(), F.col("channel")], 3))
named("limit_offset", lambda spark, sf: per_channel(spark, sf).orderBy("event", "channel").offset(100).limit(50))
named("sort_total", lambda spark, sf: per_channel(spark, sf).orderBy("event", "channel"))


def two_sets(spark, sf):
    a = V.ev1(spark, sf).where("event % 2 = 0").select("channel", (F.col("fall") - F.col("rise")).alias("w"))
    return a.select("channel", (F.col("w") % 100).alias("w")), V.ev1(spark, sf).where("event % 2 = 1").select("channel", ((F.col("fall") - F.col("rise")) % 100).alias("w"))


for _k, _f in {
    "set_union_all": lambda a, b: a.union(b), "set_union": lambda a, b: a.unionByName(b).distinct(), "set_intersect": lambda a, b: a.intersect(b),
    "set_intersect_all": lambda a, b: a.intersectAll(b), "set_except": lambda a, b: a.subtract(b), "set_except_all": lambda a, b: a.exceptAll(b),
}.items():
    named(_k, lambda spark, sf, f=_f: f(*two_sets(spark, sf)))

# --- scalar functions

named("fn_string", lambda spark, sf: t(spark, sf, "part").select("p_partkey", F.bin("p_size").alias("bits"), F.lpad(F.bin("p_size"), 8, "0").alias("padded"), F.hex(F.col("p_size").cast("long")).alias("hex"), F.conv(F.bin("p_size"), 2, 10).cast("int").alias("back"), F.length("p_name").alias("len"), F.upper(F.substring("p_name", 1, 3)).alias("head")))
named("fn_url", lambda spark, sf: t(spark, sf, "pages").select("page_id", F.regexp_extract("url", "://([^/]*)", 1).alias("host"), F.ascii("url").alias("first")))
named("fn_date", lambda spark, sf: t(spark, sf, "events").select("event_id", V.micros("ts").alias("us"), F.year("ts").alias("y"), F.dayofyear("ts").alias("doy"), F.hour("ts").alias("h"), F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")).alias("days")))
named("fn_math_bits", lambda spark, sf: t(spark, sf, "events").select("event_id", F.shiftleft("event_id", 3).alias("up"), F.shiftright("event_id", 2).alias("down"), F.bit_count("event_id").alias("ones"), F.pmod(-F.col("event_id"), F.lit(7)).alias("pm"), F.round(F.log2(F.col("event_id") + 1), 6).alias("lg"), F.col("event_id").bitwiseAND(F.lit(12)).alias("low")))
named("fn_array", lambda spark, sf: t(spark, sf, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.element_at(F.array_sort(F.transform("embedding", lambda x: F.round(x.cast("double") * 1024).cast("long"))), 1).alias("least"), F.size(F.slice("embedding", 3, 5)).alias("five")))
named("fn_map", lambda spark, sf: t(spark, sf, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m")).select("n_regionkey", F.size(F.map_keys("m")).alias("n"), F.array_min(F.map_keys("m")).alias("least"), F.element_at("m", F.array_min(F.map_keys("m"))).alias("name")))
named("fn_json", lambda spark, sf: t(spark, sf, "events").select("event_id", F.from_json("props", "k INT")["k"].alias("k"), F.get_json_object("props", "$.k").cast("int").alias("again")))
named("fn_conditional", lambda spark, sf: t(spark, sf, "events").select("event_id", F.when(F.col("event_type").isin("view", "click"), 1).when(F.col("event_type") == "error", -1).otherwise(0).alias("edge"), F.coalesce(F.nullif("event_type", F.lit("view")), F.lit("-")).alias("other")))
named("fn_cast", lambda spark, sf: t(spark, sf, "part").select("p_partkey", F.col("p_retailprice").cast("int").alias("whole"), F.expr("try_cast(p_brand AS INT)").alias("none"), V.cents("p_retailprice").alias("cents")))
named("filter_mixed", lambda spark, sf: t(spark, sf, "orders").where("o_totalprice BETWEEN 1000 AND 200000 AND o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '%H%' AND NOT (o_custkey <=> NULL)").select("o_orderkey", "o_orderpriority"))

# --- formats


def _io(form: str, name: str, columns: list[str], partition: list[str] | None = None):
    def f(spark, sf):
        rows = t(spark, sf, name).select(*columns)
        path = scratch(spark, f"io-{form}")
        T.write_as(rows, path, form, partition)
        schema = ", ".join(f"{x.name} {x.dataType.simpleString()}" for x in rows.schema.fields)
        return T.read_as(spark, path, form, schema).select(*columns)

    return f


named("io_csv", _io("csv", "nation", ["n_nationkey", "n_name", "n_regionkey"]))
named("io_json", _io("json", "region", ["r_regionkey", "r_name"]))
named("io_orc", _io("orc", "supplier", ["s_suppkey", "s_name", "s_nationkey"]))
named("io_partitioned", _io("parquet", "orders", ["o_orderkey", "o_custkey", "o_orderstatus"], ["o_orderstatus"]))


@query
def io_text(spark, sf):
    rows = t(spark, sf, "part").select(F.concat_ws("|", "p_partkey", "p_name", "p_size").alias("value"))
    path = scratch(spark, "io-text")
    T.write_as(rows, path, "text")
    return T.read_as(spark, path, "text", "value STRING")


@query
def io_frames_source(spark, sf):
    """Hits through the data source of frame files, with the range of events pushed to it."""
    from hitcodec.sources.frames_source import register, save_models

    ship_package(spark)
    register(spark)
    h = V.ev1(spark, sf)
    models = FR.fit_models(h, V.CHANNELS)
    path = scratch(spark, "frames-source")
    FR.write_frames(FR.encode(h, models, V.CHANNELS), path)
    return spark.read.format("hitframes").option("path", path).option("models", save_models(models)).option("channels", V.CHANNELS).option("lo", 5).load().where("event <= 40")


@query
def stream_frames_source(spark, sf):
    """Hits of a growing archive, streamed: files written in two rounds, each read once."""
    from hitcodec.sources.frames_source import register, save_models

    ship_package(spark)
    register(spark)
    h = V.ev1(spark, sf)
    models = FR.fit_models(h, V.CHANNELS)
    path, out, state = (scratch(spark, f"frames-stream-{x}") for x in ("in", "out", "state"))
    for turn in (0, 1):
        FR.encode(h.where((F.col("event") % 128 >= 64) == bool(turn)), models, V.CHANNELS).write.mode("append").parquet(path)
        s = spark.readStream.format("hitframes").option("path", path).option("models", save_models(models)).option("channels", V.CHANNELS).load()
        s.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


# --- streams


def day(w: str = "window.start"):
    return F.unix_micros(F.col(w)).alias("start")


named("stream_tumbling", lambda spark, sf: S.run(S.tumbling(S.hits_of(spark, sf)), "complete").select(day(), "channel", "n"))
named("stream_sliding", lambda spark, sf: S.run(S.sliding(S.hits_of(spark, sf)), "complete").select(day(), "n"))
named("stream_session", lambda spark, sf: S.run(S.sessions(S.hits_of(spark, sf)), "complete").select(F.unix_micros("session_window.start").alias("start"), "channel", "n"))


@query
def stream_pairing(spark, sf):
    ship_package(spark)
    return S.run(S.pairing(S.edges_of(spark, sf)), "append")


@query
def stream_late(spark, sf):
    ship_package(spark)
    return S.run(S.late_edges(S.edges_of(spark, sf), 0), "append").agg(F.count(F.lit(1)).alias("edges"), F.count_if("is_late").alias("late"))


named("stream_histogram", lambda spark, sf: S.run(S.value_histogram(S.hits_of(spark, sf)), "complete"))


@query
def stream_dedup(spark, sf):
    twice = S.hits_of(spark, sf)
    return S.run(S.deduplicated(twice.union(S.hits_of(spark, sf))), "append").select("event", "channel", "rise", "fall")


@query
def stream_join(spark, sf):
    ship_package(spark)
    return S.run(S.rises_with_falls(S.edges_of(spark, sf)), "append")


@query
def stream_frames(spark, sf):
    ship_package(spark)
    models = FR.fit_models(V.ev1(spark, sf), V.CHANNELS)
    path = scratch(spark, "stream-frames")
    S.write_frames(S.hits_of(spark, sf), models, V.CHANNELS, path)
    return FR.decode(FR.sound(FR.read_frames(spark, path)), models, V.CHANNELS)


@query
def stream_equals_batch(spark, sf):
    """Rows that a stream and the batch view do not share."""
    got = S.run(S.hits_of(spark, sf).drop("at"), "append")
    want = V.ev1(spark, sf)
    return got.exceptAll(want).union(want.exceptAll(got)).agg(F.count(F.lit(1)).alias("differ"))


# --- UDFs

named("udf_arrow", lambda spark, sf: V.or0(spark, sf).select("event", "channel", U.expgolomb_len()(F.col("pulses").cast("long")).alias("bits")))


@query
def udf_pandas(spark, sf):
    h = V.ev1(spark, sf).select("event", (F.col("fall") - F.col("rise")).alias("v"))
    return h.select("event", "v", U.assign_bin_np([0, 1000, 5000, 20000])("v").alias("bin"))


named("udf_agg", lambda spark, sf: V.or0(spark, sf).groupBy("channel").agg(F.round(U.entropy_bits()("pulses"), 4).alias("entropy")))


@query
def udtf_trace(spark, sf):
    ship_package(spark)
    U.register_all(spark)
    c = t(spark, sf, "customer").where("c_custkey is not null")
    c = c.select("c_custkey").repartition("c_custkey")  # a table function is work for many tasks, however small the file
    c.select("c_custkey", F.translate(F.bin("c_custkey"), "01", "ab").alias("text")).createOrReplaceTempView("customer_messages")
    return spark.sql("SELECT c_custkey, d.step, d.sym, d.state, d.bits, d.next_state FROM customer_messages, LATERAL tans_trace(text) d")


@query
def udtf_decode(spark, sf):
    """Words of each order's numbers of pulses, joined, and decoded by a table function for each row."""
    spark.udtf.register("expgolomb_decode_all", U.decode_udtf(1000))
    V.or0(spark, sf).groupBy("event").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("channel", B.expgolomb_encode("pulses").alias("w")))), lambda x: x["w"]), "").alias("bits")).createOrReplaceTempView("or0_words")
    return spark.sql("SELECT event, d.pos, d.sym FROM or0_words, LATERAL expgolomb_decode_all(bits) d")


@query
def udf_sql_registered(spark, sf):
    U.register_all(spark)
    V.or0(spark, sf).createOrReplaceTempView("or0_pulses")
    return spark.sql("SELECT CAST(pulses AS INT) AS pulses, expgolomb_len(CAST(pulses AS BIGINT)) AS bits, round(information_bits(count(*) / sum(count(*)) OVER ()), 4) AS info FROM or0_pulses GROUP BY pulses")
