"""Exact sequential maintenance of each set's sketch, in update order, with a log of every recovery.

A set's updates depend on one another, sets don't: rows are grouped by set and a numpy kernel walks each group once, all slots
side by side. The kernel also keeps the set itself, which stands for the store that recoveries read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from ..schemas import INFINITE
from .bins import BinShape

INF = np.int64(INFINITE)
#: Inserts in a row from which they enter a reserve at once.
LONG_RUN = 8
#: Sets of a batch of results.
RESULTS = 1024


class Sketch:
    """What all kernels share: the walk over updates and the fault log. ``held`` is the set as its store has it."""

    def __init__(self, family: HashFamily):
        self.family, self.held = family, set()
        self.log: list[tuple[int, int, int]] = []  # (seq, first empty slot, size read)

    def pairs(self, x: np.ndarray) -> np.ndarray:
        return self.family.pairs_numpy(x)

    def run(self, seq: np.ndarray, element: np.ndarray, op: np.ndarray) -> None:
        step = max(1, (1 << 20) // self.family.k)
        for a in range(0, len(seq), step):
            rows = self.pairs(element[a : a + step])
            for i in range(len(rows)):
                x = int(element[a + i])
                if op[a + i] > 0:
                    self.held.add(x)
                    self.insert(rows[i], x)
                else:
                    self.held.discard(x)
                    slot = self.delete(rows[i], x)
                    if slot is not None:
                        self.log.append((int(seq[a + i]), slot, len(self.held)))
                        self.recover()

    def start(self, elements: np.ndarray) -> None:
        """Begin from a set that need not be empty."""
        self.held = set(elements.tolist())
        self.recover()

    def members(self) -> np.ndarray:
        return np.fromiter(self.held, np.int64, len(self.held))

    def signature(self) -> np.ndarray:
        raise NotImplementedError


class Reserve(Sketch):
    """The reserve sketch: sorted rows of a (k, reserve) matrix, padded with the infinite pair."""

    def __init__(self, family: HashFamily, reserve: int, recover_when_empty: bool = False, rebuild: str = "all"):
        super().__init__(family)
        self.reserve, self.recover_when_empty, self.rebuild = reserve, recover_when_empty, rebuild
        self.buffer = np.full((family.k, reserve), INF)
        self.lim = np.full(family.k, INF)
        self.high = (self.lim >> 32).astype(np.int32)  # the limits' hashes
        self.by_hash = type(self) is Reserve and isinstance(family, HashFamily)

    def run(self, seq: np.ndarray, element: np.ndarray, op: np.ndarray) -> None:
        """As for every sketch, but pairs are made for those slots alone whose limit the hash doesn't pass, and long runs of inserts enter at once."""
        if not self.by_hash:
            return super().run(seq, element, op)
        turns = [0, *(np.flatnonzero((op[1:] > 0) != (op[:-1] > 0)) + 1).tolist(), len(op)]
        at = 0  # updates before it are done
        for a, b in zip(turns[:-1], turns[1:]):
            if b - a >= LONG_RUN and op[a] > 0:
                self.walk(seq[at:a], element[at:a], op[at:a])
                self.put_all(element[a:b])
                at = b
        self.walk(seq[at:], element[at:], op[at:])

    def put_all(self, element: np.ndarray) -> None:
        """Inserts in any order: of what is held and what is within the limits, the least pairs stay."""
        self.held.update(element.tolist())
        step = max(1, (1 << 21) // self.family.k)
        for a in range(0, len(element), step):
            x = np.unique(element[a : a + step])
            own = (self.family.hash_int32(x).astype(np.int64) << 32 | x[:, None]).T
            due = own <= self.lim[:, None]
            slots = np.flatnonzero(due.any(1))
            wide = np.concatenate([self.buffer[slots], np.where(due[slots], own[slots], INF)], axis=1)
            # A pair is there twice at most: held, and inserted again.
            some = min(2 * self.reserve, wide.shape[1])
            wide = np.sort(np.partition(wide, some - 1, axis=1)[:, :some], axis=1)
            wide[:, 1:][wide[:, 1:] == wide[:, :-1]] = INF
            wide.sort(axis=1)
            self.buffer[slots] = wide[:, : self.reserve]
            last = wide[:, self.reserve - 1]
            self.lim[slots] = lim = np.where(last < INF, last, self.lim[slots])
            self.high[slots] = lim >> 32

    def walk(self, seq: np.ndarray, element: np.ndarray, op: np.ndarray) -> None:
        step = max(1, (1 << 21) // self.family.k)
        for a in range(0, len(seq), step):
            hashes = self.family.hash_int32(element[a : a + step])
            for i, h in enumerate(hashes):
                x = int(element[a + i])
                due = np.flatnonzero(h <= self.high)
                own = h[due].astype(np.int64) << 32 | x
                below = own <= self.lim[due]
                due, own = due[below], own[below]
                if op[a + i] > 0:
                    self.held.add(x)
                    if len(due):
                        self.put(due, own)
                else:
                    self.held.discard(x)
                    slot = self.drop(due, own) if len(due) else None
                    if slot is not None:
                        self.log.append((int(seq[a + i]), slot, len(self.held)))
                        self.recover()

    def insert(self, p: np.ndarray, x: int) -> None:
        due = np.flatnonzero(p <= self.lim)
        if len(due):
            self.put(due, p[due])

    def delete(self, p: np.ndarray, x: int) -> int | None:
        due = np.flatnonzero(p <= self.lim)  # above its limit a pair isn't held
        return self.drop(due, p[due]) if len(due) else None

    def put(self, due: np.ndarray, own: np.ndarray) -> None:
        wide = np.empty((len(due), self.reserve + 1), np.int64)
        wide[:, :-1] = self.buffer[due]
        # A pair that is held already enters as infinite, that is not at all.
        wide[:, -1] = np.where((wide[:, :-1] == own[:, None]).any(1), INF, own)
        wide.sort(axis=1)
        self.buffer[due] = wide[:, :-1]
        last = wide[:, -2]
        self.lim[due] = lim = np.where(last < INF, last, self.lim[due])
        self.high[due] = lim >> 32

    def drop(self, due: np.ndarray, own: np.ndarray) -> int | None:
        rows = self.buffer[due]
        hit = rows == own[:, None]
        some = hit.any(1)
        rows[hit] = INF
        rows[some] = np.sort(rows[some], axis=1)
        self.buffer[due[some]] = rows[some]
        bare = rows[:, 0] == INF
        if not self.recover_when_empty:
            bare &= self.lim[due] < INF
        return int(due[bare.argmax()]) if bare.any() else None

    def recover(self) -> None:
        rows = self.pairs(self.members()).T
        bare = slice(None) if self.rebuild == "all" else np.flatnonzero(self.buffer[:, 0] == INF)
        fresh = np.full((self.family.k, self.reserve), INF)
        if rows.shape[1]:
            n = min(self.reserve, rows.shape[1])
            least = np.partition(rows, n - 1, axis=1)[:, :n] if n < rows.shape[1] else rows
            fresh[:, :n] = np.sort(least, axis=1)
        self.buffer[bare] = fresh[bare]
        self.lim[bare] = self.buffer[bare, -1]
        self.high = (self.lim >> 32).astype(np.int32)

    def restore(self, buffer: np.ndarray, lim: np.ndarray) -> None:
        """Take up a stored state; the set itself is taken up by ``held``."""
        self.buffer[:], self.lim[:] = np.reshape(buffer, self.buffer.shape), lim
        self.high = (self.lim >> 32).astype(np.int32)

    def signature(self) -> np.ndarray:
        return self.buffer[:, 0]


class UnorderedReserve(Reserve):
    """The same sketch with unordered rows, counts and a cached minimum of each slot."""

    def __init__(self, family: HashFamily, reserve: int, recover_when_empty: bool = False, rebuild: str = "all"):
        super().__init__(family, reserve, recover_when_empty, rebuild)
        self.least = np.full(family.k, INF)
        self.size = np.zeros(family.k, np.int64)

    def insert(self, p: np.ndarray, x: int) -> None:
        due = np.flatnonzero(p <= self.lim)
        due = due[~(self.buffer[due] == p[due, None]).any(1)]
        if not len(due):
            return
        room = due[self.size[due] < self.reserve]
        self.buffer[room, (self.buffer[room] == INF).argmax(1)] = p[room]
        self.size[room] += 1
        full = due[~np.isin(due, room)]
        self.buffer[full, self.buffer[full].argmax(1)] = p[full]
        self.least[due] = np.minimum(self.least[due], p[due])
        done = due[self.size[due] == self.reserve]
        self.lim[done] = self.buffer[done].max(1)

    def delete(self, p: np.ndarray, x: int) -> int | None:
        slot, at = np.nonzero(self.buffer == p[:, None])
        self.buffer[slot, at] = INF
        self.size[slot] -= 1
        stale = slot[self.least[slot] == p[slot]]
        self.least[stale] = self.buffer[stale].min(1)
        bare = self.size == 0
        if not self.recover_when_empty:
            bare &= self.lim < INF
        return int(bare.argmax()) if bare.any() else None

    def recover(self) -> None:
        super().recover()
        self.size = (self.buffer < INF).sum(1)
        self.least = self.buffer.min(1)

    def signature(self) -> np.ndarray:
        return self.least


class HashOnly(Reserve):
    """Holds hashes without elements: half the space, and right for legal streams only."""

    def pairs(self, x: np.ndarray) -> np.ndarray:
        return self.family.hash_numpy(x)

    def insert(self, p: np.ndarray, x: int) -> None:
        due = np.flatnonzero(p <= self.lim)
        wide = np.sort(np.column_stack([self.buffer[due], p[due]]), axis=1)[:, : self.reserve]
        self.buffer[due] = wide
        full = wide[:, -1] < INF
        self.lim[due[full]] = wide[full, -1]

    def delete(self, p: np.ndarray, x: int) -> int | None:
        hit = self.buffer == p[:, None]
        hit &= np.cumsum(hit, axis=1) == 1  # of equal hashes one goes
        rows = np.where(hit, INF, self.buffer)
        rows.sort(axis=1)
        self.buffer = rows
        bare = (rows[:, 0] == INF) & (self.lim < INF)
        return int(bare.argmax()) if bare.any() else None


class Rebuild(Sketch):
    """The baseline: the k minima alone; losing any of them reads the set again."""

    def __init__(self, family: HashFamily):
        super().__init__(family)
        self.least = np.full(family.k, INF)

    def insert(self, p: np.ndarray, x: int) -> None:
        np.minimum(self.least, p, out=self.least)

    def delete(self, p: np.ndarray, x: int) -> int | None:
        lost = self.least == p
        return int(lost.argmax()) if lost.any() else None

    def recover(self) -> None:
        rows = self.pairs(self.members())
        self.least = rows.min(0) if len(rows) else np.full(self.family.k, INF)

    def signature(self) -> np.ndarray:
        return self.least


class Naive(Reserve):
    """Refills whenever there is room and keeps no limit. Its signatures can be wrong; kept to show it."""

    def insert(self, p: np.ndarray, x: int) -> None:
        new = ~(self.buffer == p[:, None]).any(1)
        wide = np.sort(np.column_stack([self.buffer[new], p[new]]), axis=1)[:, : self.reserve]
        self.buffer[new] = wide

    def delete(self, p: np.ndarray, x: int) -> int | None:
        self.buffer = np.sort(np.where(self.buffer == p[:, None], INF, self.buffer), axis=1)
        bare = self.buffer[:, 0] == INF
        return int(bare.argmax()) if bare.any() and (self.held or self.recover_when_empty) else None


class Strict(Naive):
    """Always the least pairs there are: right, but a deleted pair that was held makes it read the set."""

    def delete(self, p: np.ndarray, x: int) -> int | None:
        hit = (self.buffer == p[:, None]).any(1)
        self.buffer = np.sort(np.where(self.buffer == p[:, None], INF, self.buffer), axis=1)
        short = hit & ((self.buffer < INF).sum(1) < len(self.held))
        return int(short.argmax()) if short.any() else None


class Bins(Sketch):
    """The bin sketch: counters by level and bin; the signature is computed when asked for."""

    def __init__(self, family: HashFamily, shape: BinShape):
        super().__init__(family)
        self.shape = shape
        self.count = np.zeros((shape.levels, shape.bins), np.int64)

    def pairs(self, x: np.ndarray) -> np.ndarray:
        return np.column_stack(self.shape.place_numpy(x))

    def insert(self, p: np.ndarray, x: int) -> None:
        self.count[p[0], p[1]] += 1

    def delete(self, p: np.ndarray, x: int) -> int | None:
        self.count[p[0], p[1]] -= 1
        return None

    def recover(self) -> None:
        self.count[:] = 0
        level, where = self.shape.place_numpy(self.members())
        np.add.at(self.count, (level, where), 1)

    def level(self) -> int:
        return self.shape.level_of(int(self.count.sum()))

    def signature(self) -> np.ndarray:
        taken = np.flatnonzero(self.count[self.level()])
        return self.family.pairs_numpy(taken).min(0) if len(taken) else np.full(self.family.k, INF)


class EagerBins(Bins):
    """Keeps every level's minima while updates come; a bin that empties and held one is a fault mended from the level's bins."""

    def __init__(self, family: HashFamily, shape: BinShape):
        super().__init__(family, shape)
        self.of_bin = family.pairs_numpy(np.arange(shape.bins))
        self.least = np.full((shape.levels, family.k), INF)

    def insert(self, p: np.ndarray, x: int) -> None:
        level, at = p
        self.count[level, at] += 1
        if self.count[level, at] == 1:
            np.minimum(self.least[level], self.of_bin[at], out=self.least[level])

    def delete(self, p: np.ndarray, x: int) -> int | None:
        level, at = p
        self.count[level, at] -= 1
        if self.count[level, at] == 0:
            lost = self.least[level] == self.of_bin[at]
            if lost.any():
                taken = self.count[level] != 0
                self.least[level] = self.of_bin[taken].min(0) if taken.any() else INF
                self.log.append((-1, int(lost.argmax()), int(taken.sum())))
        return None

    def recover(self) -> None:
        super().recover()
        for level in range(self.shape.levels):
            taken = self.count[level] != 0
            self.least[level] = self.of_bin[taken].min(0) if taken.any() else INF

    def signature(self) -> np.ndarray:
        return self.least[self.level()]


def kernel(kind: str, family: HashFamily, reserve: int = 8, shape: BinShape | None = None, **options) -> Sketch:
    """A fresh sketch of one set: reserve, unordered, hash_only, rebuild, naive, strict, bins or eager_bins."""
    if kind in ("bins", "eager_bins"):
        return (Bins if kind == "bins" else EagerBins)(family, shape or BinShape())
    if kind == "rebuild":
        return Rebuild(family)
    made = {"reserve": Reserve, "unordered": UnorderedReserve, "hash_only": HashOnly, "naive": Naive, "strict": Strict}[kind]
    return made(family, reserve, **options)


RESULT = "set_id bigint, sig array<bigint>, size bigint, ops bigint, faults bigint, reread bigint, log array<struct<seq: bigint, slot: int, size_after: bigint>>"

ARROW = pa.schema([
    ("set_id", pa.int64()), ("sig", pa.list_(pa.int64())), ("size", pa.int64()), ("ops", pa.int64()), ("faults", pa.int64()), ("reread", pa.int64()),
    ("log", pa.list_(pa.struct([("seq", pa.int64()), ("slot", pa.int32()), ("size_after", pa.int64())]))),
])


def replay(updates: DataFrame, kind: str, family: HashFamily, reserve: int = 8, shape: BinShape | None = None, start: DataFrame | None = None, **options) -> DataFrame:
    """One row for each set: signature (null if empty), size, updates, recoveries, elements read by them, and their log.

    ``start``: members before the first update (set_id, element).
    """

    def one(rows: pa.Table) -> dict:
        if any(rows.column(c).null_count for c in ("seq", "element", "op")):
            raise ValueError("an update without seq, element or op; see streams.split_valid")
        seq, element, op, first = (rows.column(c).to_numpy() for c in ("seq", "element", "op", "before"))
        sketch = kernel(kind, family, reserve, shape, **options)
        if first.any():
            sketch.start(element[first])
        sketch.run(seq[~first], element[~first], op[~first])
        sig = sketch.signature()
        log = [{"seq": a, "slot": b, "size_after": c} for a, b, c in sketch.log]
        sig = None if (sig == INF).all() else sig.tolist()
        return {"set_id": rows.column("set_id")[0].as_py(), "sig": sig, "size": len(sketch.held), "ops": int((~first).sum()), "faults": len(log), "reread": sum(x["size_after"] for x in log), "log": log}

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, out = [], []
        for batch in batches:
            if held and batch.num_rows and batch.column(0)[0] != held[-1].column(0)[0]:
                out.append(one(pa.Table.from_batches(held)))
                held = []
            # A null set is a set of its own; sorted first, it has no neighbour of the stand-in value.
            ids = batch.column(0).fill_null(np.iinfo(np.int64).min).to_numpy()
            ends = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
            for a, b in zip(ends[:-1], ends[1:]):
                held += [batch.slice(a, b - a)] if b > a else []
                if b < len(ids):
                    out.append(one(pa.Table.from_batches(held)))
                    held = []
                if len(out) >= RESULTS:
                    yield pa.RecordBatch.from_pylist(out, ARROW)
                    out = []
        if held:
            out.append(one(pa.Table.from_batches(held)))
        if out:
            yield pa.RecordBatch.from_pylist(out, ARROW)

    stream = updates.select(F.col("set_id").cast("bigint").alias("set_id"), F.col("seq").cast("bigint").alias("seq"), F.lit(False).alias("before"), "element", F.col("op").cast("int").alias("op"))
    if start is not None:
        before = start.select("set_id", F.lit(0).cast("bigint").alias("seq"), F.lit(True).alias("before"), "element", F.lit(1).alias("op"))
        stream = stream.unionByName(before)
    # Sets lie one after another in a task's rows: many small sets share batches, a set alone takes no call of its own.
    return stream.repartition("set_id").sortWithinPartitions("set_id", "seq", "element", "op").mapInArrow(walk, RESULT)


def fault_log(replayed: DataFrame) -> DataFrame:
    """(set_id, seq, slot, size_after): one row for each recovery."""
    return replayed.select("set_id", F.explode("log").alias("l")).select("set_id", "l.seq", "l.slot", "l.size_after")
