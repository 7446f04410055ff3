import numpy as np
from pyspark.sql import functions as F

from farpoint.functions import features
from farpoint.functions.sql import register_sql
from farpoint.operators import assign as A
from farpoint.operators.farthest_first import farthest_first
from farpoint.operators.mlapi import KCenter
from farpoint.sources import io
from farpoint.sources.views import points_of
from farpoint.streaming.kcenter_stream import CenterLevels, stream_kcenter, windowed_kcenter


def test_table_function_by_partition(spark, sf):
    register_sql(spark)
    points_of(spark, sf, "customer_2d").createOrReplaceTempView("v_customer")
    got = spark.sql("SELECT * FROM k_center(TABLE(SELECT id, coords, c_mktsegment FROM v_customer) PARTITION BY (c_mktsegment), 3, 'manhattan')")
    assert got.count() == 15 and got.where("rank = 1").count() == 5


def test_estimator(spark, sf):
    p = points_of(spark, sf, "orders_2d").withColumnRenamed("id", "key_of").withColumn("note", F.lit("x"))
    for algorithm in ("blocked", "farthest_first", "distributed", "pivot_sampling"):
        model = KCenter(k=4, algorithm=algorithm, idCol="key_of", predictionCol="near").fit(p)
        out = model.transform(p)
        assert out.columns == [*p.columns, "near"] and out.count() == 1500 and out.select("near").distinct().count() == 4
        assert model.radius(p) > 0


def test_sources_and_sinks(spark, sf, tmp_path):
    p = points_of(spark, sf, "part_2d")
    flat = p.select("id", F.col("coords")[0].alias("x"), F.col("coords")[1].alias("y"))
    for fmt in ("parquet", "orc", "csv", "json"):
        io.write_result(flat, f"{tmp_path}/{fmt}", fmt=fmt)
        back = io.read_points(spark, fmt, f"{tmp_path}/{fmt}", "id long, x double, y double", "id", ["x", "y"])
        assert back.exceptAll(p).count() == 0 and back.count() == 200
    flat.select(F.concat_ws(" ", "id", "x", "y").alias("value")).write.text(f"{tmp_path}/text")
    assert io.read_text_points(spark, f"{tmp_path}/text", 2).exceptAll(p).count() == 0
    spark.createDataFrame([(0, 1, 2.0), (1, 2, 3.0)], "u long, v long, w double").write.parquet(f"{tmp_path}/edges")
    assert io.read_edges(spark, f"{tmp_path}/edges").count() == 4
    io.write_result(A.assign(p, farthest_first(p, 3)), f"{tmp_path}/served", partition_by="center_id")
    assert spark.read.parquet(f"{tmp_path}/served").count() == 200
    spark.dataSource.register(io.SyntheticPoints)
    s = spark.read.format("farpoint_synth").options(n=1000, dims=3, partitions=4).load()
    assert s.count() == 1000 and s.selectExpr("min(size(coords))", "max(coords[2])").first()[0] == 3
    io.run_only(s)
    flat.createOrReplaceTempView("v_flat")
    assert io.points_from_table(spark, "v_flat", "id", ["x", "y"], 10.0).where("coords[0] % 10 = 0").count() == 200


def test_features(spark):
    df = spark.createDataFrame([(1, "b", 2.0, 5.0), (2, "a", 4.0, 5.0), (3, None, 6.0, 5.0)], "id long, c string, x double, y double")
    p = features.to_points(df, "id", ["x", "y"])
    assert [list(r.coords) for r in features.min_max(p, 2).orderBy("id").collect()] == [[0, 0], [0.5, 0], [1, 0]]
    z = np.array([list(r.coords) for r in features.standardize(p, 2).collect()])
    assert abs(z[:, 0].mean()) < 1e-12 and abs(z[:, 0].std() - 1) < 1e-12 and (z[:, 1] == 0).all()
    assert [r.o for r in features.encode_ordinal(df, "c", "o").orderBy("id").collect()] == [1, 0, None]
    hot = features.encode_one_hot(df, "c", ["a", "b"]).orderBy("id").collect()
    assert [(r.c_a, r.c_b) for r in hot] == [(0, 1), (1, 0), (0, 0)]
    assert [list(r.coords) for r in features.to_points(df, "id", ["x"], {"x": 100}).orderBy("id").collect()] == [[200], [400], [600]]


def test_levels_are_a_binary_counter():
    rng = np.random.default_rng(0)
    levels = CenterLevels(4)
    x = rng.uniform(0, 100, (800, 2))
    for i in range(8):
        levels.add(*levels.reduced(np.arange(i * 100, i * 100 + 100), x[i * 100 : i * 100 + 100]))
    assert [s is not None for s in levels.levels] == [False, False, False, True]
    ids, centers = CenterLevels.load(4, levels.dump()).centers()
    from farpoint.operators import kernels

    best = kernels.farthest_first(x, 4)[2]
    assert kernels.nearest(x, centers)[1].max() <= (levels.guarantee**2) * best


def test_stream_of_events(spark, sf, tmp_path):
    rows = spark.read.parquet(f"{sf}/events.parquet").selectExpr("CAST(ts AS timestamp) AS ts", "event_id AS id", "array(value, CAST(hour(ts) AS DOUBLE)) AS coords").orderBy("ts")
    n = rows.count()
    for low in range(0, 1000, 250):  # ids follow the time; files are read in the order they were written
        rows.where((F.col("id") >= low) & (F.col("id") < low + 250)).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    sink, query = stream_kcenter(stream.select("id", "coords"), 5, f"{tmp_path}/cp")
    query.processAllAvailable()
    query.stop()
    ids, centers = sink.levels.centers()
    p = rows.select("id", "coords")
    full = A.covering_radius(p, farthest_first(p, 5)).first().radius
    got = A.covering_radius(p, spark.createDataFrame([(int(i), c.tolist()) for i, c in zip(ids, centers, strict=True)], "id long, coords array<double>")).first().radius
    assert len(ids) == 5 and got <= sink.levels.guarantee * full
    out = windowed_kcenter(stream, 3, "30 days", "1 day")
    q = out.writeStream.format("memory").queryName("windows").outputMode("append").option("checkpointLocation", f"{tmp_path}/cp2").start()
    q.processAllAvailable()
    q.stop()
    got = spark.table("windows").groupBy("window_start").agg(F.count("*").alias("k"), F.first("points").alias("points")).collect()
    assert got and all(r.k <= 3 for r in got) and sum(r.points for r in got) <= n
