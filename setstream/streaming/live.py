"""Sketches maintained over streaming updates: the micro-batch path with recovery, the stateful exact path, counters and windows."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from ..operators.bins import BinShape
from ..operators.replay import kernel
from ..operators.reserve import reserve_apply, reserve_signature
from ..operators.streams import split_valid
from ..schemas import FAULTS
from ..sources.recovery import RecoverySource
from ..sources.store import SketchStore


def maintain(stream: DataFrame, store: SketchStore, recover: RecoverySource, family: HashFamily, reserve: int, checkpoint: str, quarantine: str | None = None):
    """Start the main path: each micro-batch is netted and applied, faulty sets are read from ``recover`` as of the batch, and
    the touched buckets are committed under the batch id, so that a batch which runs again changes nothing.

    Rows that are no updates, and late ones (their pair has a later update from an earlier batch, if ``recover`` knows), are set aside in
    ``quarantine`` and don't change a sketch: membership is decided by the last update of a pair, whenever it comes."""

    def step(batch: DataFrame, batch_id: int) -> None:
        if store.committed(batch_id):
            return
        good, bad = split_valid(batch)
        good = good.persist()
        late = recover.late(good)
        if late is not None:
            late = late.persist()
            bad = bad.unionByName(late, allowMissingColumns=True)
            # Older updates of a late pair in this batch are late as well.
            stale = late.select("set_id", "element")
            good = good.join(stale, ["set_id", "element"], "left_anti").persist()
        if quarantine and not bad.isEmpty():
            bad.write.mode("overwrite").parquet(f"{quarantine}/batch={batch_id}")
        if good.isEmpty():
            store.commit(None, None, batch_id)
        else:
            recover.advance(good, batch_id)
            old = store.read_touched(good)
            new, faults = reserve_apply(old, good, recover.members(), family, reserve)
            store.commit(new, faults, batch_id)
        for held in (good, late):
            if held is not None:
                held.unpersist()

    return stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).start()


STATE = "element array<bigint>, seq array<bigint>, op array<int>, buffer array<bigint>, lim array<bigint>, faults bigint"


def maintain_stateful(stream: DataFrame, family: HashFamily, reserve: int, mode: str = "update") -> DataFrame:
    """Exact sequential maintenance in arrival order within each set's state; for sets that fit a state row.

    In 'update' mode (set_id, sig, size, faults) after each batch; in 'append' mode the fault log (set_id, seq, slot, size_after). The state holds each
    element's last update (the recovery source, deletions too) and the sketch's rows as arrays, which are taken up as they are: only the batch's
    elements are hashed. A late row, older than its element's last update, changes nothing.
    """
    from pyspark.sql.streaming.state import GroupStateTimeout

    def walk(key, frames, state):
        sketch, faults, last = kernel("reserve", family, reserve), 0, {}
        if state.exists:
            element, seq, op, buffer, lim, faults = state.get
            last = dict(zip(element, zip(seq, op, strict=True), strict=True))
            sketch.held = {x for x, (_, o) in last.items() if o > 0}
            sketch.restore(np.array(buffer, np.int64), np.array(lim, np.int64))
        for rows in frames:
            rows = rows.sort_values(["seq", "element", "op"], kind="stable")
            seq, element, op = (rows[c].to_numpy("int64") for c in ("seq", "element", "op"))
            keep = []
            for i, x in enumerate(element.tolist()):
                if x not in last or last[x][0] <= seq[i]:
                    last[x] = int(seq[i]), int(op[i])
                    keep.append(i)
            sketch.run(seq[keep], element[keep], op[keep])
        faults += len(sketch.log)
        state.update(([*last], [s for s, _ in last.values()], [o for _, o in last.values()], sketch.buffer.ravel().tolist(), sketch.lim.tolist(), faults))
        if mode == "append":
            yield pd.DataFrame([(key[0], *x) for x in sketch.log], columns=["set_id", "seq", "slot", "size_after"])
        else:
            sig = sketch.signature().tolist() if sketch.held else None
            yield pd.DataFrame([{"set_id": key[0], "sig": sig, "size": len(sketch.held), "faults": faults}])

    out = FAULTS if mode == "append" else "set_id bigint, sig array<bigint>, size bigint, faults bigint"
    return stream.groupBy("set_id").applyInPandasWithState(walk, out, STATE, mode, GroupStateTimeout.NoTimeout)


def stream_bins(stream: DataFrame, shape: BinShape) -> DataFrame:
    """Counters of the bin sketch as a plain streaming aggregation (update mode)."""
    x = F.col("element")
    return stream.groupBy("set_id", shape.level(x).alias("level"), shape.bin(x).alias("bin")).agg(F.sum("op").alias("cnt"))


def window_signatures(updates: DataFrame, family: HashFamily, width: str = "1 day", slide: str | None = None, delay: str | None = None) -> DataFrame:
    """(window_start, set_id, sig): signatures of the elements inserted in each tumbling or sliding event-time window; batch or streaming."""
    rows = updates.withWatermark("ts", delay) if delay else updates
    windows = F.window("ts", width, slide) if slide else F.window("ts", width)
    least = [F.min(family.pair(i, F.col("element"))).alias(f"s{i}") for i in range(family.k)]
    return rows.where("op = 1").groupBy(windows.alias("w"), "set_id").agg(*least).select(F.col("w.start").alias("window_start"), "set_id", F.array(*[f"s{i}" for i in range(family.k)]).alias("sig"))


def session_signatures(updates: DataFrame, family: HashFamily, gap: str = "1 hour") -> DataFrame:
    """(session_start, set_id, sig) over sessions of each set."""
    least = [F.min(family.pair(i, F.col("element"))).alias(f"s{i}") for i in range(family.k)]
    grouped = updates.where("op = 1").groupBy(F.session_window("ts", gap).alias("w"), "set_id").agg(*least)
    return grouped.select(F.col("w.start").alias("session_start"), "set_id", F.array(*[f"s{i}" for i in range(family.k)]).alias("sig"))


def expiring(updates: DataFrame, width: str = "INTERVAL 1 DAY") -> DataFrame:
    """Inserts with the deletes that a sliding window implies, as an arbitrary update stream in time order."""
    put = updates.where("op = 1").select("set_id", "element", "ts", F.lit(1).alias("op"))
    out = put.select("set_id", "element", (F.col("ts") + F.expr(width)).alias("ts"), F.lit(-1).alias("op"))
    return put.unionByName(out).withColumn("seq", F.unix_micros(F.col("ts").cast("timestamp")))


def drop_repeated_events(stream: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """Events delivered more than once within the watermark count once."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def insert_delete_pairs(inserts: DataFrame, deletes: DataFrame, delay: str = "1 day") -> DataFrame:
    """Each insert with the deletes of the same element that follow within a day; joins streams or tables by event time."""
    a = inserts.select("set_id", "element", F.col("ts").alias("put_at")).withWatermark("put_at", delay)
    b = deletes.select(F.col("set_id").alias("s2"), F.col("element").alias("e2"), F.col("ts").alias("out_at")).withWatermark("out_at", delay)
    near = F.expr("set_id = s2 and element = e2 and out_at >= put_at and out_at <= put_at + interval 1 day")
    return a.join(b, near).select("set_id", "element", "put_at", "out_at")


def signatures_now(spark: SparkSession, store: SketchStore) -> DataFrame:
    """Signatures of the version committed last; reads no other column."""
    return reserve_signature(store.read())
