"""The monitor as a stream: stateful processor per source, checkpointed map state, both lists out."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from fsmeta.monitor.run import ACTIONS, Resolver
from fsmeta.monitor.state import PAIRS, Event, NodeRow, StateManager

EVENTS = "source_id long, seq long, ts timestamp, op string, fid long, is_dir boolean, parent_fid long, name string, size long"


class MapStore:
    """The state manager's store on map states; what a batch touches is kept in memory and written back once."""

    def __init__(self, nodes, below, renew: bool = False):
        self.nodes, self.below_, self.seen, self.dirty, self.kids, self.kid_dirty, self.renew = nodes, below, {}, set(), {}, set(), renew

    def get(self, fid: int) -> NodeRow | None:
        if fid not in self.seen:
            self.seen[fid] = NodeRow(*self.nodes.getValue((fid,))) if self.nodes.containsKey((fid,)) else None
        return self.seen[fid]

    def _kids(self, fid: int) -> set[int]:
        if fid not in self.kids:
            raw = self.below_.getValue((fid,))[0] if self.below_.containsKey((fid,)) else ""
            self.kids[fid] = set(map(int, raw.split())) if raw else set()
        return self.kids[fid]

    def put(self, fid: int, node: NodeRow) -> None:
        old = self.get(fid)
        if old is not None and old.parent_fid is not None and old.parent_fid != node.parent_fid:
            self._kids(old.parent_fid).discard(fid)
            self.kid_dirty.add(old.parent_fid)
        if node.parent_fid is not None and (old is None or old.parent_fid != node.parent_fid):
            self._kids(node.parent_fid).add(fid)
            self.kid_dirty.add(node.parent_fid)
        self.seen[fid] = node
        self.dirty.add(fid)

    def remove(self, fid: int) -> None:
        old = self.get(fid)
        if old is not None and old.parent_fid is not None:
            self._kids(old.parent_fid).discard(fid)
            self.kid_dirty.add(old.parent_fid)
        self.seen[fid] = None
        self.dirty.add(fid)

    def children(self, fid: int):
        return list(self._kids(fid))

    def flush(self) -> None:
        """Write back. With a time to live, what was read is written too: ancestors in use do not expire."""
        if self.renew:
            self.dirty |= {fid for fid, node in self.seen.items() if node is not None}
            for node in self.seen.values():
                if node is not None and node.parent_fid is not None and self._kids(node.parent_fid):
                    self.kid_dirty.add(node.parent_fid)
        for fid in self.dirty:
            node = self.seen[fid]
            if node is not None:
                self.nodes.updateValue((fid,), tuple(node))
            elif self.nodes.containsKey((fid,)):
                self.nodes.removeKey((fid,))
        for fid in self.kid_dirty:
            if self.kids[fid]:
                self.below_.updateValue((fid,), (" ".join(map(str, sorted(self.kids[fid]))),))
            elif self.below_.containsKey((fid,)):
                self.below_.removeKey((fid,))


class MetadataStateProcessor(StatefulProcessor):
    """Batches close at ``max_events``, or with the micro-batch; with ``idle_ms`` not with the micro-batch but
    after a pause of that length (between two events, or until a timer fires), and what is open is kept in
    the state, so that events of several micro-batches meet in one batch."""

    def __init__(self, max_events: int = 1000, drop: tuple[str, ...] = ("OPEN",), reduce: bool = True, ttl_ms: int | None = None, resolver: Resolver | None = None, idle_ms: int | None = None, pairs: tuple[tuple[str, str], ...] = PAIRS, override: str = "batch"):
        if ttl_ms is not None and resolver is None:
            raise ValueError("ttl_ms needs a resolver: expired nodes would be lost")
        self.resolver, self.idle_ms, self.rules = resolver, idle_ms, {"pairs": pairs, "override": override}
        self.max_events, self.drop, self.reduce_, self.ttl_ms = max_events, drop, reduce, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        node = "parent_fid long, name string, is_dir boolean, shown string, size long"
        self.handle = handle
        self.nodes = handle.getMapState("nodes", "fid long", node, self.ttl_ms)
        self.below = handle.getMapState("below", "fid long", "fids string", self.ttl_ms)
        self.last = handle.getValueState("last", "seq long, batch long, at double, timer long")
        self.open = handle.getListState("open", "seq long, op string, fid long, is_dir boolean, parent_fid long, name string, size long")

    def _manager(self, source: int) -> StateManager:
        return StateManager(MapStore(self.nodes, self.below, self.ttl_ms is not None), None if self.resolver is None else lambda fid: self.resolver(source, fid), **self.rules)

    def _frame(self, out: list) -> pd.DataFrame:
        frame = pd.DataFrame(out, columns=["action", "source_id", "fid", "path", "size", "last_seq", "batch_id"])
        return frame.astype({"size": "Int64"})

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N803
        seq, batch, at, timer = self.last.get() if self.last.exists() else (-(1 << 60), 0, None, None)
        got = pd.concat(list(rows)).sort_values("seq")
        source = int(key[0])
        manager = self._manager(source)
        none = lambda v, kind: None if pd.isna(v) else kind(v)
        held = [Event(*e) for e in self.open.get()] if self.idle_ms is not None and self.open.exists() else []
        out, pending, loaded = [], held, []

        def close():
            nonlocal pending, batch
            for a in manager.process(pending, self.reduce_):
                out.append((a.action, source, a.fid, a.path, a.size, a.last_seq, batch))
            pending, batch = [], batch + 1

        for r in got.itertuples(index=False):
            e = Event(int(r.seq), r.op, int(r.fid), bool(r.is_dir), none(r.parent_fid, int), none(r.name, str), none(r.size, int))
            if e.op == "NODE":
                manager.load(e.fid, NodeRow(e.parent_fid, e.name, e.is_dir, None, e.size))
                loaded.append(e.fid)  # directories too: files below may have come in an earlier micro-batch
                continue
            if loaded:
                manager.settle(loaded)
                loaded = []
            if e.seq <= seq or e.op in self.drop:  # replayed, or of little information
                continue
            seq = e.seq
            if self.idle_ms is not None and not pd.isna(r.ts):
                now = r.ts.timestamp()
                if pending and at is not None and 1000 * (now - at) > self.idle_ms:
                    close()
                at = now
            pending.append(e)
            if len(pending) >= self.max_events:
                close()
        manager.settle(loaded)
        if pending and self.idle_ms is None:
            close()
        manager.store.flush()
        if self.idle_ms is not None:
            self._keep(pending)
            if timer is not None:
                self.handle.deleteTimer(timer)
            timer = timerValues.getCurrentProcessingTimeInMs() + self.idle_ms if pending else None
            if timer is not None:
                self.handle.registerTimer(timer)
        self.last.update((seq, batch, at, timer))
        yield self._frame(out)

    def _keep(self, pending: list[Event]) -> None:
        if pending:
            self.open.put([tuple(e) for e in pending])
        elif self.open.exists():
            self.open.clear()

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N803
        """Nothing came for a while: the open batch closes."""
        seq, batch, at, _ = self.last.get()
        pending = [Event(*e) for e in self.open.get()] if self.open.exists() else []
        manager = self._manager(int(key[0]))
        out = [(a.action, int(key[0]), a.fid, a.path, a.size, a.last_seq, batch) for a in manager.process(pending, self.reduce_)] if pending else []
        manager.store.flush()
        self._keep([])
        self.last.update((seq, batch + bool(pending), at, None))
        yield self._frame(out)

    def close(self) -> None:
        pass


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def actions_stream(events: DataFrame, max_events: int = 1000, drop: tuple[str, ...] = ("OPEN",), reduce: bool = True, ttl_ms: int | None = None, resolver: Resolver | None = None, idle_ms: int | None = None, pairs: tuple[tuple[str, str], ...] = PAIRS, override: str = "batch") -> DataFrame:
    """Needs the RocksDB state store provider in the session (a runtime setting). With ``ttl_ms`` or ``idle_ms``
    the engine keeps looking at its timers, so a query with the available-now trigger does not end by itself."""
    keyed = events.groupBy("source_id")
    mode = "none" if ttl_ms is None and idle_ms is None else "processingTime"
    return keyed.transformWithStateInPandas(MetadataStateProcessor(max_events, drop, reduce, ttl_ms, resolver, idle_ms, pairs, override), ACTIONS, "append", mode)


def activity(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events per source in time windows; what is later than the watermark is left out."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, slide) if slide else F.window("ts", width), "source_id").count()


def unique(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each (source, sequence) once, within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["source_id", "seq"])
