"""Micro-batches give the batch result, survive a replay, and set bad rows aside; the stateful path agrees."""

import numpy as np
from checks import walk
from test_frames import FAMILY, frame, random_updates, truth

from setstream.operators.bins import BinShape, bins_apply
from setstream.schemas import UPDATES
from setstream.sources.recovery import LogSource
from setstream.sources.store import SketchStore
from setstream.streaming import live


def chopped(spark, rows, path, parts=4):
    n = len(rows) // parts
    for i in range(parts):
        frame(spark, rows[i * n : (i + 1) * n if i < parts - 1 else None]).coalesce(1).write.mode("append").parquet(str(path))


def test_maintain(spark, tmp_path):
    rows = random_updates(240, sets=5, seed=5)
    chopped(spark, rows + [(999, None, 1, 1)], tmp_path / "in")
    store = SketchStore(spark, f"file://{tmp_path}/store", buckets=4)
    source = LogSource(spark, f"file://{tmp_path}/log", fold=2)
    for _ in range(2):  # the second run finds nothing new
        stream = spark.readStream.schema(UPDATES).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
        q = live.maintain(stream, store, source, FAMILY, 2, f"{tmp_path}/checkpoint", f"file://{tmp_path}/bad")
        q.processAllAvailable()
        q.stop()
    got = {r["set_id"]: list(r["sig"]) for r in live.signatures_now(spark, store).where("sig is not null").collect()}
    # File order is not stream order, but each set's last update of an element decides: compare with what the log holds.
    held = {}
    for r in source.members().collect():
        held.setdefault(r["set_id"], set()).add(r["element"])
    assert got == truth(held)
    assert spark.read.parquet(f"file://{tmp_path}/bad").count() == 1
    before = sorted(map(str, store.read().collect()))
    store.commit(None, None, 0)  # a batch that runs again
    assert store.faults().count() >= 0 and before


def test_maintain_goes_on_after_a_restart(spark, tmp_path):
    """Every batch meets new source and store objects on the old folders, and the sets stay whole; old folders can be deleted."""
    rows = random_updates(300, sets=4, seed=9)
    for i in range(6):
        part = frame(spark, rows[i * 50 : (i + 1) * 50]).persist()
        store, source = SketchStore(spark, f"file://{tmp_path}/store", buckets=2), LogSource(spark, f"file://{tmp_path}/log", fold=3)
        part.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        stream = spark.readStream.schema(UPDATES).parquet(str(tmp_path / "in"))
        q = live.maintain(stream, store, source, FAMILY, 2, f"{tmp_path}/checkpoint")
        q.processAllAvailable()
        q.stop()
        if i == 3:
            store.vacuum(keep=1)
            source.vacuum()
    fresh = LogSource(spark, f"file://{tmp_path}/log")
    held = {}
    for r in fresh.members().collect():
        held.setdefault(r["set_id"], set()).add(r["element"])
    assert {k: v for k, v in walk(rows).items() if v} == held
    assert {r["set_id"]: list(r["sig"]) for r in live.signatures_now(spark, SketchStore(spark, f"file://{tmp_path}/store", buckets=2)).where("sig is not null").collect()} == truth(held)
    assert SketchStore(spark, f"file://{tmp_path}/store").faults().count() >= 0 and SketchStore.buckets_for(10**9, 544) > 10_000


def test_late_rows_are_set_aside(spark, tmp_path):
    store, source = SketchStore(spark, f"file://{tmp_path}/store", buckets=2), LogSource(spark, f"file://{tmp_path}/log")
    for rows in ([(10, 1, 5, -1), (11, 1, 6, 1)], [(3, 1, 5, 1), (4, 1, 7, 1), (12, 1, 8, 1)]):
        frame(spark, rows).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        q = live.maintain(spark.readStream.schema(UPDATES).parquet(str(tmp_path / "in")), store, source, FAMILY, 2, f"{tmp_path}/checkpoint", f"file://{tmp_path}/bad")
        q.processAllAvailable()
        q.stop()
    got = {r["set_id"]: list(r["sig"]) for r in live.signatures_now(spark, store).where("sig is not null").collect()}
    assert got == truth({1: {6, 7, 8}})
    assert [(r["seq"], r["element"]) for r in spark.read.parquet(f"file://{tmp_path}/bad").collect()] == [(3, 5)]


def test_stateful_over_many_batches(spark, tmp_path):
    """State goes from batch to batch; signatures, faults and the log are those of one sequential run; late rows change nothing."""
    from setstream.operators.replay import fault_log, replay

    rows = random_updates(160, sets=3, seed=6)
    late = [(-1, s, x, 1) for s, x in {(s, x) for _, s, x, _ in rows}]
    for i, part in enumerate([rows[:40], rows[40:80], rows[80:120], rows[120:], late]):
        frame(spark, part).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        for mode, name in (("update", "kept"), ("append", "logged")):
            stream = spark.readStream.schema(UPDATES).parquet(str(tmp_path / "in"))
            q = live.maintain_stateful(stream, FAMILY, 2, mode).writeStream.format("parquet" if mode == "append" else "memory").queryName(f"{name}{i}").outputMode(mode)
            if mode == "append":
                q = q.option("path", str(tmp_path / "log")).option("checkpointLocation", f"{tmp_path}/at-{mode}").start()
            else:
                q = live.maintain_stateful(stream, FAMILY, 2, mode).writeStream.foreachBatch(lambda b, n: b.write.mode("append").parquet(str(tmp_path / "sigs"))).outputMode(mode).option("checkpointLocation", f"{tmp_path}/at-{mode}").start()
            q.processAllAvailable()
            q.stop()
    want = {r["set_id"]: r for r in replay(frame(spark, rows), "reserve", FAMILY, 2).collect()}
    last = {}
    for r in spark.read.parquet(str(tmp_path / "sigs")).collect():
        if r["set_id"] not in last or r["faults"] >= last[r["set_id"]]["faults"]:
            last[r["set_id"]] = r
    assert {s: r["faults"] for s, r in last.items()} == {s: r["faults"] for s, r in want.items()} and sum(r["faults"] for r in want.values()) > 0
    got = sorted(tuple(r) for r in spark.read.parquet(str(tmp_path / "log")).collect())
    assert got == sorted(tuple(r) for r in fault_log(replay(frame(spark, rows), "reserve", FAMILY, 2)).collect())
    final = spark.read.parquet(str(tmp_path / "sigs")).where("sig is not null").selectExpr("set_id", "sig", "size").distinct().collect()
    for s, r in want.items():
        if r["sig"]:
            assert (s, list(r["sig"]), r["size"]) in [(x["set_id"], list(x["sig"]), x["size"]) for x in final]


def test_stateful_and_bins(spark, tmp_path):
    rows = random_updates(120, sets=3, seed=6)
    chopped(spark, rows, tmp_path / "in", parts=1)
    stream = spark.readStream.schema(UPDATES).parquet(str(tmp_path / "in"))
    q = live.maintain_stateful(stream, FAMILY, 2).writeStream.format("memory").queryName("kept").outputMode("update").start()
    q.processAllAvailable()
    q.stop()
    got = {r["set_id"]: list(r["sig"]) for r in spark.table("kept").where("sig is not null").collect()}
    assert got == truth(walk(rows))
    shape = BinShape(bins=8, levels=4)
    q = live.stream_bins(stream, shape).writeStream.format("memory").queryName("counted").outputMode("complete").start()
    q.processAllAvailable()
    q.stop()
    streamed = sorted(tuple(r) for r in spark.table("counted").where("cnt <> 0").collect())
    assert streamed == sorted(tuple(r) for r in bins_apply(None, frame(spark, rows), shape).collect())


def test_windows_and_expiry(spark):
    df = frame(spark, [(1, 1, 5, 1), (2, 1, 6, 1)]).selectExpr("*", "timestamp'2024-01-01 10:00:00' + make_interval(0, 0, 0, cast(seq as int)) as ts")
    assert live.window_signatures(df, FAMILY, "1 day").count() == 2
    assert live.session_signatures(df, FAMILY, "2 days").count() == 1
    out = live.expiring(df)
    assert out.where("op = -1").count() == 2 and np.all([r["seq"] for r in out.collect()])
    pairs = live.insert_delete_pairs(df, df.selectExpr("set_id", "element", "ts + interval 1 hour as ts"))
    assert pairs.count() == 2
