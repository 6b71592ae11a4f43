import datetime as dt

import numpy as np

from devfed.functions import sqlfns
from devfed.operators import weighting
from devfed.streaming import activity, quorum


def _arrivals(n=8, rounds=2):
    r, t0, out = np.random.default_rng(3), dt.datetime(2024, 1, 1), []
    for k in range(rounds):
        for c in range(n):
            row = (t0 + dt.timedelta(minutes=5 * k, seconds=int(c * 7 % n)), c, c % 2, k, int(r.integers(1, 50)), [float(x) for x in r.normal(size=3)])
            out.append(row)
            if c == 3:
                out.append(row)  # arrives twice
    return out


def test_stream_merges_as_the_batch_does(spark, tmp_path):
    rows = _arrivals()
    df = spark.createDataFrame(rows, quorum.SCHEMA)
    df.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(quorum.SCHEMA).parquet(str(tmp_path / "in"))
    q = quorum.quorum_rounds(stream, 3).writeStream.format("memory").queryName("merged").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {(r["subserver_id"], r["round"]): r for r in spark.sql("SELECT * FROM merged").collect()}
    want = {(r["subserver_id"], r["round"]): r for r in quorum.quorum_batch(df, 3).collect()}
    assert set(got) == set(want) and len(got) == 4
    for key, row in got.items():
        assert row["complete"] and row["members"] == 3 and row["n_rows"] == want[key]["n_rows"]
        assert np.allclose(row["w"], want[key]["w"])
        own = sorted({(r[0], r[1], r[4], tuple(r[5])) for r in rows if (r[2], r[3]) == key})[:3]
        assert np.allclose(row["w"], weighting.merge_np(np.array([o[3] for o in own]), np.array([o[2] for o in own], float)))


def test_late_vectors_are_counted_and_states_expire(spark, tmp_path):
    t0 = dt.datetime(2024, 1, 1)
    row = lambda minutes, client, number: (t0 + dt.timedelta(minutes=minutes), client, 0, number, 2, [float(client), 1.0])
    # round 0 gets a quorum of 2 and two more; round 1 never gets it; round 9 moves the watermark; the last arrives behind it
    batches = [[row(0, 1, 0), row(1, 2, 0), row(2, 3, 0), row(2, 1, 1)], [row(3, 4, 0), row(3, 4, 0)], [row(300, 1, 9)], [row(1, 7, 0)], [row(301, 2, 9)], [row(600, 1, 10)]]
    for k, rows in enumerate(batches):
        spark.createDataFrame(rows, quorum.SCHEMA).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        stream = spark.readStream.schema(quorum.SCHEMA).parquet(str(tmp_path / "in"))
        q = quorum.quorum_rounds(stream, 2, watermark="10 minutes", expiry_ms=60_000).writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
        assert q.awaitTermination(120) and (k != 3 or quorum.dropped_late(q) >= 1)
    got = {(r["round"], r["complete"], r["members"], r["late"]) for r in spark.read.parquet(str(tmp_path / "out")).collect() if r["round"] < 9}
    assert got == {(0, True, 2, None), (0, True, 0, 2), (1, False, 1, 0)}


def test_arrivals_within_a_round(spark, tmp_path):
    t0 = dt.datetime(2024, 1, 1)
    arrivals = [(t0 + dt.timedelta(minutes=m), c, 0, r, 1, [0.5]) for m, c, r in ((-1, 1, 0), (0, 2, 0), (59, 3, 0), (60, 4, 0), (70, 5, 1))]
    a, b = spark.createDataFrame(arrivals, quorum.SCHEMA), spark.createDataFrame([(t0, 0), (t0 + dt.timedelta(hours=1), 1)], "opened_at timestamp, round int")
    assert {r["client_id"] for r in quorum.in_round(a, b, watermark=None).collect()} == {2, 3, 5}
    a.coalesce(1).write.parquet(str(tmp_path / "a"))
    b.coalesce(1).write.parquet(str(tmp_path / "b"))
    streams = [spark.readStream.schema(df.schema).parquet(str(tmp_path / n)) for df, n in ((a, "a"), (b, "b"))]
    q = quorum.in_round(*streams).writeStream.format("memory").queryName("joined").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert {r["client_id"] for r in spark.sql("SELECT * FROM joined").collect()} == {2, 3, 5}


def test_windows_and_running_moments_on_streams(spark, sf_dir, tmp_path):
    events = spark.read.parquet(f"{sf_dir}/events.parquet").selectExpr("event_id", "user_id", "CAST(ts AS timestamp) AS ts", "value").orderBy("ts")
    events.coalesce(1).write.parquet(str(tmp_path / "e"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "e"))
    q = activity.counts(stream, "tumbling", "1 hour").writeStream.outputMode("update").format("memory").queryName("hours").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.sql("SELECT sum(n) FROM hours").first()[0] == events.count()
    moments = quorum.running_moments(stream.withColumnRenamed("user_id", "client_id"), ["value"])
    q = moments.writeStream.outputMode("complete").format("memory").queryName("moments").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.sql("SELECT sum(n) FROM moments").first()[0] == events.count()
    out = []
    q = quorum.score_stream(stream.selectExpr("value AS x", "CAST(value > 50 AS int) AS label"), ["x"], lambda: [-50.0, 1.0], out).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sum(n for _, n, _ in out) == events.count() and all(a > 0.98 for _, _, a in out)


def test_sql_functions(spark):
    sqlfns.register(spark)
    assert spark.sql("SELECT fed_sigmoid(0e0), fed_dist2(array(0e0, 0e0), array(3e0, 4e0)), fed_dot(array(1e0, 2e0), array(3e0, 4e0))").first()[:] == (0.5, 5.0, 11.0)
    df = spark.createDataFrame([([1.0, 2.0], 1), ([3.0, 6.0], 3)], "w array<double>, n int")
    df.createOrReplaceTempView("vectors")
    assert spark.sql("SELECT fed_vec_wavg(w, n) AS m FROM vectors").first()["m"] == [2.5, 5.0]
    points = spark.sql("SELECT * FROM fed_roc_points(array(0.9D, 0.2D), array(1, 0))").collect()
    assert [(p["fpr"], p["tpr"]) for p in points] == [(0.0, 0.0), (0.0, 1.0), (1.0, 1.0)]


def test_counts_back_over_spans_equal_one_window(spark):
    from pyspark.sql import Window
    from pyspark.sql import functions as F

    r = np.random.default_rng(4)
    df = spark.createDataFrame([(k, int(u), dt.datetime(2024, 1, 1) + dt.timedelta(hours=int(h))) for k, (u, h) in enumerate(zip(r.integers(0, 3, 400), r.integers(0, 900, 400), strict=True))], "event_id long, user_id long, ts timestamp")
    week = 7 * 86400 * 10**6
    plain = df.withColumn("n", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros("ts")).rangeBetween(-week, 0)))
    assert sorted(map(tuple, activity.count_back(df, "user_id", "ts", week).collect())) == sorted(map(tuple, plain.collect()))
