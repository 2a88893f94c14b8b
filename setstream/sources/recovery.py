"""Where a faulty set's current members are read from."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.streams import members_at, net
from ..schemas import UPDATES


class RecoverySource:
    """``fetch(ids)`` gives (set_id, element) of the sets in ``ids`` as they are now."""

    def members(self) -> DataFrame:
        raise NotImplementedError

    def advance(self, updates: DataFrame, batch_id: int) -> None:
        """Tells the source of a batch of updates; sources that are kept elsewhere need not listen."""

    def late(self, updates: DataFrame) -> DataFrame | None:
        """The netted updates whose pair has a later update already, in another batch; None if the source doesn't know."""
        return None

    def fetch(self, ids: DataFrame) -> DataFrame:
        return self.members().join(ids.select("set_id").distinct(), "set_id", "left_semi")


class TableSource(RecoverySource):
    """A members table that is kept elsewhere."""

    def __init__(self, members: DataFrame):
        self._members = members

    def members(self) -> DataFrame:
        return self._members


class CallbackSource(RecoverySource):
    """A function that gives the members table as it is at the time of the call."""

    def __init__(self, read: Callable[[], DataFrame]):
        self._read = read

    def members(self) -> DataFrame:
        return self._read()


class LogSource(RecoverySource):
    """Members worked out of an update log in a folder. Every batch has its own folder ``batch=N``; batches up to one are folded every ``fold``
    batches into ``folded=N``. What counts is read from the folders each time, so a new object on an old folder goes on where the old one
    stopped, and a fold or batch that stopped half-way (no ``_SUCCESS``) is as if it had not begun."""

    def __init__(self, spark, path: str, fold: int = 20):
        self.spark, self.path, self.fold = spark, path.rstrip("/"), fold

    def _found(self, kind: str) -> list[int]:
        root = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(root)]
        done = self.spark._jvm.org.apache.hadoop.fs.Path
        return sorted(int(n.split("=")[1]) for n in names if n.startswith(f"{kind}=") and fs.exists(done(f"{self.path}/{n}/_SUCCESS")))

    def _parts(self) -> list[str]:
        """The last fold and the batches after it."""
        folds = self._found("folded")
        last = folds[-1] if folds else None
        batches = [b for b in self._found("batch") if last is None or b > last]
        return [f"{self.path}/folded={last}"] * (last is not None) + [f"{self.path}/batch={b}" for b in batches]

    def advance(self, updates: DataFrame, batch_id: int) -> None:
        folds = self._found("folded")
        if batch_id in self._found("batch") or (folds and batch_id <= folds[-1]):
            return  # a batch that runs again
        net(updates).write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")
        if len(self._parts()) > self.fold:
            net(self._log()).write.mode("overwrite").parquet(f"{self.path}/folded={batch_id}")

    def vacuum(self) -> None:
        """Delete what the last fold has made superfluous; to be called while no batch runs."""
        folds = self._found("folded")
        for kind, numbers in (("folded", folds[:-1]), ("batch", [b for b in self._found("batch") if folds and b <= folds[-1]])):
            for n in numbers:
                p = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{kind}={n}")
                p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)

    def late(self, updates: DataFrame) -> DataFrame | None:
        parts = self._parts()
        if not parts:
            return None
        known = self._log().select("set_id", "element", F.col("seq").alias("_known"))
        if (known.agg(F.max("_known")).first()[0] or 0) < (updates.agg(F.min("seq")).first()[0] or 0):
            return None  # the batch is newer than all before
        once = known.groupBy("set_id", "element").agg(F.max("_known").alias("_known"))
        return net(updates).join(once, ["set_id", "element"]).where("seq < _known").select("seq", "set_id", "element", "op")

    def _log(self) -> DataFrame:
        parts = self._parts()
        return self.spark.read.schema(UPDATES).parquet(*parts) if parts else self.spark.createDataFrame([], UPDATES)

    def members(self) -> DataFrame:
        return members_at(self._log())
