import pyspark.sql.functions as F

from nzspan import sources, streaming


def test_triples_and_texts(spark, tmp_path):
    rows = [(0, 0, 1.5), (1, 2, -2.0)]
    df = spark.createDataFrame(rows, sources.ENTRY_SCHEMA)
    for fmt, read in (("csv", sources.read_triples_csv), ("json", sources.read_triples_json), ("orc", sources.read_triples_orc)):
        df.write.format(fmt).save(f"{tmp_path}/{fmt}")
        assert sorted(map(tuple, read(spark, f"{tmp_path}/{fmt}").collect())) == rows
    (tmp_path / "a.mtx").write_text("%%MatrixMarket matrix coordinate real general\n% note\n2 3 2\n1 1 1.5\n2 3 -2\n")
    assert sorted(map(tuple, sources.read_coordinate_text(spark, f"{tmp_path}/a.mtx").collect())) == rows
    (tmp_path / "a.svm").write_text("1 1:1.5\n-1 3:-2\n\n")
    entries, labels = sources.read_svm_lines(spark, f"{tmp_path}/a.svm")
    assert sorted(r["col"] for r in entries.collect()) == [0, 2] and sorted(r["label"] for r in labels.collect()) == [-1, 1]
    assert sources.is_column_major(df.coalesce(1).sort("col", "row")) and not sources.is_column_major(df.coalesce(1).sort(F.col("col").desc()))


def test_late_rows_go(spark, tmp_path):
    schema = "event_id long, ts timestamp, event_type string, user_id long"
    first = [(1, "2024-01-01 00:10:00", "a", 1), (2, "2024-01-03 00:00:00", "a", 1)]
    late = [(3, "2024-01-01 00:20:00", "a", 1), (4, "2024-01-05 00:00:00", "a", 1)]
    make = lambda rows: spark.createDataFrame(rows, "event_id long, t string, event_type string, user_id long").select("event_id", F.col("t").cast("timestamp").alias("ts"), "event_type", "user_id")
    path = f"{tmp_path}/in"
    make(first).coalesce(1).write.mode("append").parquet(path)

    def run():
        stream = spark.readStream.schema(schema).parquet(path)
        counted = streaming.tumbling(stream, "1 hour", "1 hour")
        q = counted.writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/state").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()

    run()
    make(late).coalesce(1).write.mode("append").parquet(path)
    run()
    counts = {str(r["start"]): r["n"] for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    assert counts["2024-01-01 00:00:00"] == 1  # the event that came after the watermark is not in it


def test_stream_pairs_and_drift(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00", 7), (2, "2024-01-01 00:30:00", 7), (3, "2024-01-01 03:00:00", 7)]
    df = spark.createDataFrame(rows, "event_id long, t string, user_id long").select("event_id", F.col("t").cast("timestamp").alias("ts"), "user_id")
    df.write.parquet(f"{tmp_path}/events")
    read = lambda: spark.readStream.schema(df.schema).parquet(f"{tmp_path}/events")
    pairs = streaming.finish(streaming.paired(read(), read(), "user_id"), "append")
    assert sorted((r["a_id"], r["b_id"]) for r in pairs.collect()) == [(1, 1), (1, 2), (2, 2), (3, 3)]
    entries = spark.createDataFrame([(0, c, 1.0) for c in (0, 1, 5, 9, 9)], sources.ENTRY_SCHEMA)
    entries.write.parquet(f"{tmp_path}/entries")
    drift = streaming.cover_drift(spark.readStream.schema(sources.ENTRY_SCHEMA).parquet(f"{tmp_path}/entries"), [0, 5])
    seen = {}
    for r in streaming.finish(drift, "update").collect():
        seen[r["part"]] = max(seen.get(r["part"], 0), r["nnz"])
    assert seen == {0: 2, 1: 3}


def _events(spark, folder, files):
    """events.parquet of the given (event_id, seconds) rows, a file for each list."""
    for rows in files:
        df = spark.createDataFrame([(i, float(at)) for i, at in rows], "event_id long, at double")
        df = df.selectExpr("event_id", "timestamp_micros(CAST(at * 1000000 AS BIGINT)) AS ts", "1L AS user_id", "'view' AS event_type")
        df.coalesce(1).write.mode("append").parquet(f"{folder}/events.parquet")


def test_sliding_rounds_seconds_as_its_sql(spark, tmp_path):
    import duckdb

    from nzspan import surroundings, workloads  # noqa: F401

    day = 1_704_067_200
    _events(spark, tmp_path, [[(1, day + 43199.7), (2, day + 43199.4), (3, day + 43200.2)], [(4, day + 86399.5), (5, day + 86398.5)]])
    got = sorted(tuple(r) for r in workloads.QUERIES["st_sliding"](spark, str(tmp_path)).select("start", "event_type", "n").collect())
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW events AS SELECT event_id, ts::TIMESTAMP AS ts, user_id, event_type FROM '{tmp_path}/events.parquet/*.parquet'")
    assert got == sorted(duck.execute(workloads.SQL["st_sliding"]).fetchall())


def test_dedup_counts_every_event_of_later_files(spark, tmp_path):
    from nzspan import surroundings, workloads  # noqa: F401

    day = 1_704_067_200
    _events(spark, tmp_path, [[(k, day + 7200 * k) for k in range(50)], [(k, day + 60 * k) for k in range(40, 90)], [(5, day), (100, day - 86400)]])
    assert workloads.QUERIES["st_dedup"](spark, str(tmp_path)).first()["n"] == 91
