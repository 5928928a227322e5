from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import functions as F

from tallymill.functions.hashing import hash_np
from tallymill.functions.keyed import uniform_py
from tallymill.params import SketchParams
from tallymill.streaming import counts


def files(spark, top, parts):
    for k, rows in enumerate(parts):
        spark.createDataFrame(rows, "event long, k string, key long, ts timestamp").coalesce(1).write.mode("append").parquet(f"{top}")
    return spark.readStream.schema("event long, k string, key long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(str(top))


def rows(spark, n, start=0, hour=0):
    import datetime as d

    t = d.datetime(2024, 1, 1) + d.timedelta(hours=hour)
    return [(start + e, "ab"[e % 2], (e * 7) % 13, t + d.timedelta(minutes=e)) for e in range(n)]


def test_windows_equal_batch_and_late_rows_drop(spark, tmp_path):
    p = SketchParams(2, 8)
    parts = [rows(spark, 60), rows(spark, 60, 100, 30), rows(spark, 60, 200, 60), rows(spark, 10)]
    stream = files(spark, tmp_path / "in", parts)
    cells = counts.collected(counts.tumbling(stream, "key", "k", p), f"t{uuid.uuid4().hex[:6]}", "complete", f"{tmp_path}/c1")
    batch = counts.tumbling(spark.createDataFrame(sum(parts, []), "event long, k string, key long, ts timestamp"), "key", "k", p)
    assert sorted(map(tuple, cells.collect())) == sorted(map(tuple, batch.collect()))
    q = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day"), "k").count().writeStream.outputMode("append").format("memory").queryName(f"l{uuid.uuid4().hex[:6]}").option("checkpointLocation", f"{tmp_path}/c2").trigger(availableNow=True).start()
    q.awaitTermination()
    assert counts.late_rows(q) >= 1
    once = counts.collected(counts.once(stream, "event", late="100 hours").select("event"), f"o{uuid.uuid4().hex[:6]}", "append", f"{tmp_path}/c3")
    assert once.count() == once.distinct().count() == 180


def test_counter_states_survive_batches(spark, tmp_path):
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", counts.ROCKSDB)
    try:
        p = SketchParams(2, 8, 1.3, 8, counter="correlated")
        parts = [rows(spark, 40), rows(spark, 40, 100, 5)]
        stream = files(spark, tmp_path / "in", parts)
        out = counts.collected(counts.counter_stream(stream.select("k", "key", "event"), p), f"s{uuid.uuid4().hex[:6]}", "update", f"{tmp_path}/c")
        last = {}
        for r in out.collect():
            m = np.frombuffer(r.payload, np.uint8)
            last[r.k] = max(last.get(r.k, (0, None)), (int(m.sum()), m.tobytes()))[0:2]
        for k in "ab":
            want = np.zeros((2, 8), int)
            for e, kk, x, _ in sum(parts, []):
                if kk == k:
                    for i in range(2):
                        c = hash_np(np.array([x]), i, p)[0]
                        want[i, c] += uniform_py("cc", p.seed, e) < 1.3 ** -want[i, c]
            assert last[k][0] == want.sum()
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)


def test_sessions_and_snapshots(spark):
    ev = spark.createDataFrame(rows(spark, 100), "event long, k string, key long, ts timestamp")
    assert counts.sessions(ev, "k").agg(F.sum("n")).first()[0] == 100
    snaps = spark.sql("SELECT explode(array(timestamp'2023-12-30 10:00:00', timestamp'2024-01-01 00:30:00')) AS snap_ts")
    got = counts.asof(ev, snaps).collect()
    assert len(got) == 100 and all((r.snap_ts.day == 30) == (r.ts.minute < 30 and r.ts.hour == 0) for r in got)


def test_online_topics_count_every_batch_once(spark):
    from pyspark.sql import functions as F

    from tallymill.functions.hashing import word_key
    from tallymill.functions.text import words
    from tallymill.models.online import OnlineTopics
    from tallymill.operators.matrix import RowSketches
    from tallymill.params import SketchParams

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", F.transform(words(F.col("text")), word_key).alias("vs"))
    fit = OnlineTopics(RowSketches(SketchParams(3, 2048, 1.08, 8, counter="independent"), 4))
    for batch in (0, 1, 1, 2):
        fit.update(docs.where(F.pmod("doc_id", F.lit(3)) == batch), batch)
    seen = docs.select(F.explode("vs").alias("v"))
    n, types = seen.count(), seen.distinct().count()
    assert [r["batch"] for r in fit.log] == [0, 1, 2]
    assert fit.log[-1]["total"] == n == sum(r["tokens"] for r in fit.log)
    assert abs(fit.log[-1]["types"] / types - 1) < 0.05
