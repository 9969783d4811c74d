"""The monitor over a table of events: one state owner per source, rows streamed in order.

Sources are independent, so the work spreads with their number; events of a source stay in order
in one task, as path construction needs all of them. Nothing but the state is held.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import asdict, fields

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.monitor.state import PAIRS, CostCounters, Event, NodeRow, Spilled, StateManager

ACTIONS = "action string, source_id long, fid long, path string, size long, last_seq long, batch_id long"
COSTS = "source_id long, " + ", ".join(f"{f.name} long" for f in fields(CostCounters))

#: Gives the node of (source_id, fid) where neither ``nodes`` nor the events do; runs in the tasks.
Resolver = Callable[[int, int], NodeRow | None]


def table_resolver(nodes: DataFrame, most: int = 1_000_000) -> Resolver:
    """A resolver over a table of directories (source_id, fid, parent_fid, name, is_dir, size) of at most
    ``most`` rows, which is broadcast. A larger one goes in as ``nodes`` of the monitor, by a shuffle."""
    rows = nodes.select("source_id", "fid", "parent_fid", "name", "is_dir", "size").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} nodes: give them to the monitor as its node table")
    shared = nodes.sparkSession.sparkContext.broadcast({(r["source_id"], r["fid"]): (r["parent_fid"], r["name"], r["is_dir"], None, r["size"]) for r in rows})

    def resolve(source: int, fid: int) -> NodeRow | None:
        found = shared.value.get((source, fid))
        return None if found is None else NodeRow(*found)

    return resolve


def _ordered(events: DataFrame, nodes: DataFrame | None, parts: int | None, timed: bool) -> DataFrame:
    at = [F.col("ts").cast("timestamp").cast("double").alias("at")] if timed else []
    e = events.select("source_id", "seq", "op", "fid", "is_dir", "parent_fid", "name", "size", *at)
    if nodes is not None:
        at = [F.lit(None).cast("double").alias("at")] if timed else []
        e = nodes.select("source_id", F.lit(-1).cast("long").alias("seq"), F.lit("NODE").alias("op"), "fid", "is_dir", "parent_fid", "name", "size", *at).unionByName(e)
    # sources are told apart by number, so that a few of them do not meet in one task by chance
    parts = parts or int(events.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    e = e.repartitionById(parts, F.pmod("source_id", F.lit(parts)).cast("int"))
    return e.sortWithinPartitions("source_id", "seq")


def _drive(events, nodes, reduce, max_events, drop, max_dirs, stat_mode, parts, want, resolver, idle_s, pairs, override, each=None):
    def owner(source):
        outer = None if resolver is None else lambda fid: resolver(source, fid)
        rules = {"stat_mode": stat_mode, "pairs": pairs, "override": override}
        if max_dirs is None:
            return StateManager(resolver=outer, **rules)
        out = Spilled(outer)
        return StateManager(resolver=out.get, spill=out.put, below=out.children, max_dirs=max_dirs, **rules)

    def work(batches):
        state, pending, source, number, loaded, last, watch = None, [], None, 0, [], None, None

        def rows(made):
            if made:
                yield pa.RecordBatch.from_arrays([pa.array(c) if i != 4 else pa.array(c, pa.int64()) for i, c in enumerate(zip(*[(a.action, source, a.fid, a.path, a.size, a.last_seq, number) for a in made], strict=True))], names=["action", "source_id", "fid", "path", "size", "last_seq", "batch_id"])

        def finish():
            nonlocal pending
            made = state.process(pending, reduce) if pending else []
            pending = []
            if want == "actions":
                yield from rows(made)
            elif source is not None:
                c = asdict(state.counters)
                yield pa.RecordBatch.from_arrays([pa.array([source], pa.int64()), *(pa.array([v], pa.int64()) for v in c.values())], names=["source_id", *c])

        for b in batches:
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if row[0] != source:
                    if source is not None:
                        yield from finish()
                    source, number, loaded, last, state = row[0], 0, [], None, owner(row[0])
                    watch = each(state.counters) if each is not None else None
                e = Event(*row[1:8])
                if e.op == "NODE":
                    state.load(e.fid, NodeRow(e.parent_fid, e.name, e.is_dir, None, e.size))
                    if not e.is_dir:
                        loaded.append(e.fid)
                    continue
                if loaded:  # all nodes of the source are in
                    state.settle(loaded)
                    loaded = []
                state.counters.events_in += 1
                if e.op in drop:
                    state.counters.opens_dropped += 1
                    continue
                if watch is not None:
                    watch(e)
                # a batch closes at its size, or before the first event after a pause
                pause = idle_s is not None and len(pending) > 0 and last is not None and row[8] is not None and row[8] - last > idle_s
                if idle_s is not None and row[8] is not None:
                    last = row[8]
                if not pause:
                    pending.append(e)
                if pause or len(pending) >= max_events:
                    made = state.process(pending, reduce)
                    if want == "actions":
                        yield from rows(made)
                    pending, number = [e] if pause else [], number + 1
        if source is not None:
            yield from finish()

    return _ordered(events, nodes, parts, idle_s is not None).mapInArrow(work, ACTIONS if want == "actions" else COSTS)


def monitor(events: DataFrame, nodes: DataFrame | None = None, reduce: bool = True, max_events: int = 1000, drop: tuple[str, ...] = ("OPEN",), max_dirs: int | None = None, stat_mode: str = "carried", parts: int | None = None, resolver: Resolver | None = None, idle_s: float | None = None, pairs: tuple[tuple[str, str], ...] = PAIRS, override: str = "batch") -> DataFrame:
    """Update and delete actions of all batches, in batch order per source."""
    return _drive(events, nodes, reduce, max_events, drop, max_dirs, stat_mode, parts, "actions", resolver, idle_s, pairs, override)


def costs(events: DataFrame, nodes: DataFrame | None = None, reduce: bool = True, max_events: int = 1000, drop: tuple[str, ...] = ("OPEN",), max_dirs: int | None = None, stat_mode: str = "call", parts: int | None = None, resolver: Resolver | None = None, idle_s: float | None = None, pairs: tuple[tuple[str, str], ...] = PAIRS, override: str = "batch") -> DataFrame:
    """The same work; what it cost per source."""
    return _drive(events, nodes, reduce, max_events, drop, max_dirs, stat_mode, parts, "costs", resolver, idle_s, pairs, override)


def throughput(df: DataFrame, events: int) -> dict:
    """Runs a plan without keeping its rows; events a second of wall time."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    s = time.perf_counter() - t
    return {"seconds": round(s, 3), "events_per_s": round(events / s)}
