"""Stateful monitor: hierarchy, handlers and both output lists, for one source at a time.

``StateManager`` works on a key-value store, so the same rules run inside a batch task (plain
dictionaries) and inside ``transformWithStateInPandas`` (map state). Paths come from parents;
only an object whose ancestors are unknown is resolved outside, once, and then kept. What can't be
resolved is counted (``unresolved``) and waits in the state: it is shown when its ancestors come.
"""

from __future__ import annotations

import sqlite3
from collections import OrderedDict
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from typing import NamedTuple


class Event(NamedTuple):
    seq: int
    op: str
    fid: int
    is_dir: bool
    parent_fid: int | None
    name: str | None
    size: int | None


class NodeRow(NamedTuple):
    parent_fid: int | None
    name: str
    is_dir: bool
    shown: str | None  # path last given to the index
    size: int | None


class Action(NamedTuple):
    action: str
    fid: int
    path: str
    size: int | None
    last_seq: int


@dataclass
class CostCounters:
    events_in: int = 0
    opens_dropped: int = 0
    coalesced: int = 0
    cancelled_files: int = 0
    cancelled_dirs: int = 0
    overrides: int = 0
    batches: int = 0
    lookups: int = 0
    lookup_hits: int = 0
    stat_calls: int = 0
    evicted: int = 0
    unresolved: int = 0
    updates: int = 0
    deletes: int = 0


class DictStore:
    """Nodes and children in dictionaries."""

    def __init__(self):
        self.nodes: dict[int, NodeRow] = {}
        self.below: dict[int, set[int]] = {}

    def get(self, fid: int) -> NodeRow | None:
        return self.nodes.get(fid)

    def put(self, fid: int, node: NodeRow) -> None:
        old = self.nodes.get(fid)
        if old is not None and old.parent_fid != node.parent_fid and old.parent_fid is not None:
            self.below.get(old.parent_fid, set()).discard(fid)
        self.nodes[fid] = node
        if node.parent_fid is not None:
            self.below.setdefault(node.parent_fid, set()).add(fid)

    def remove(self, fid: int) -> None:
        node = self.nodes.pop(fid, None)
        if node is not None and node.parent_fid is not None:
            self.below.get(node.parent_fid, set()).discard(fid)

    def children(self, fid: int) -> Iterable[int]:
        return list(self.below.get(fid, ()))


#: Pairs of operations that cancel each other where they are the first and the last of an object in a batch.
PAIRS = (("CREATE", "UNLINK"), ("MKDIR", "RMDIR"))


def _is_override(e: Event) -> bool:
    return e.op == "RENAME" and e.is_dir


def reduce_batch(batch: list[Event], counters: CostCounters, pairs: tuple[tuple[str, str], ...] = PAIRS, override: str = "batch") -> list[Event]:
    """The three rules on one batch, in sequence order. A batch with a directory rename passes as it is
    (``override='batch'``), or is cut into stretches around each such rename (``'barrier'``)."""
    renames = [i for i, e in enumerate(batch) if _is_override(e)]
    if not renames:
        return _reduced(batch, counters, pairs)
    counters.overrides += 1
    if override == "batch":
        return batch
    out, at = [], 0
    for i in renames:
        out += [*_reduced(batch[at:i], counters, pairs), batch[i]]
        at = i + 1
    return out + _reduced(batch[at:], counters, pairs)


def _reduced(batch: list[Event], counters: CostCounters, pairs: tuple[tuple[str, str], ...]) -> list[Event]:
    slots: dict[int, list[Event]] = {}
    for e in batch:
        slots.setdefault(e.fid, []).append(e)
    out = []
    for own in slots.values():
        first, last = own[0], own[-1]
        if (first.op, last.op) in pairs:
            if last.is_dir:
                counters.cancelled_dirs += 1
            else:
                counters.cancelled_files += 1
            continue
        counters.coalesced += len(own) - 1
        if len(own) == 1:
            out.append(first)
            continue
        place = next((e for e in reversed(own) if e.op in ("CREATE", "MKDIR", "RENAME")), None)
        size = next((e.size for e in reversed(own) if e.size is not None), None)
        if last.op in ("UNLINK", "RMDIR"):
            op = last.op
        elif first.op in ("CREATE", "MKDIR"):
            op = first.op
        else:
            op = "RENAME" if place else "SETATTR"
        out.append(Event(last.seq, op, first.fid, last.is_dir, place.parent_fid if place else None, place.name if place else None, size))
    return sorted(out)


class Spilled:
    """Evicted nodes of one source in a temporary local file; what is not there is asked of ``outer``."""

    def __init__(self, outer: Callable[[int], NodeRow | None] | None = None):
        self.outer, self.db = outer, sqlite3.connect("")
        self.db.execute("CREATE TABLE node (fid INTEGER PRIMARY KEY, parent_fid, name, is_dir, shown, size)")
        self.db.execute("CREATE INDEX below ON node (parent_fid)")

    def put(self, fid: int, node: NodeRow) -> None:
        self.db.execute("INSERT OR REPLACE INTO node VALUES (?, ?, ?, ?, ?, ?)", (fid, *node))

    def get(self, fid: int) -> NodeRow | None:
        """A node that is here moves back to the state."""
        row = self.db.execute("SELECT parent_fid, name, is_dir, shown, size FROM node WHERE fid = ?", (fid,)).fetchone()
        if row is not None:
            self.db.execute("DELETE FROM node WHERE fid = ?", (fid,))
            return NodeRow(row[0], row[1], bool(row[2]), row[3], row[4])
        return self.outer(fid) if self.outer is not None else None

    def children(self, fid: int) -> list[int]:
        return [r[0] for r in self.db.execute("SELECT fid FROM node WHERE parent_fid = ?", (fid,))]


@dataclass
class StateManager:
    store: object = field(default_factory=DictStore)
    resolver: Callable[[int], NodeRow | None] | None = None
    spill: Callable[[int, NodeRow], None] | None = None  # takes evicted nodes, for the resolver
    below: Callable[[int], Iterable[int]] | None = None  # children among evicted nodes
    max_dirs: int | None = None
    stat_mode: str = "carried"
    pairs: tuple[tuple[str, str], ...] = PAIRS
    override: str = "batch"
    counters: CostCounters = field(default_factory=CostCounters)

    def __post_init__(self):
        if self.max_dirs is not None and self.resolver is None:
            raise ValueError("max_dirs needs a resolver: evicted directories would be lost")
        self.recent: OrderedDict[int, None] = OrderedDict()
        self.handlers = {"CREATE": self._create, "MKDIR": self._create, "UNLINK": self._remove, "RMDIR": self._remove, "RENAME": self._rename, "SETATTR": self._update, "CLOSE": self._update, "OPEN": self._update}

    def load(self, fid: int, node: NodeRow) -> None:
        self.store.put(fid, node)

    def settle(self, fids: Iterable[int]) -> None:
        """Files of a baseline, loaded or below what was loaded, are taken to be in the index at their present path."""
        todo, seen = list(fids), set()
        while todo:
            fid = todo.pop()
            node = self.store.get(fid)
            if node is None or fid in seen:
                continue
            seen.add(fid)
            if node.is_dir:
                todo += self.store.children(fid)
            elif node.shown is None:
                self.store.put(fid, node._replace(shown=self.path(fid)))

    def children(self, fid: int) -> list[int]:
        """In the state and, where a directory was evicted with what it holds, outside."""
        own = list(self.store.children(fid))
        return own if self.below is None else own + [c for c in self.below(fid) if self.store.get(c) is None]

    def node(self, fid: int | None) -> NodeRow | None:
        """From the state, or once from outside."""
        if fid is None:
            return None
        found = self.store.get(fid)
        if found is None and self.resolver is not None:
            self.counters.lookups += 1
            found = self.resolver(fid)
            if found is not None:
                self.store.put(fid, found)
        if found is not None and found.is_dir:
            self.recent[fid] = None
            self.recent.move_to_end(fid)
        return found

    def path(self, fid: int) -> str | None:
        names, at, steps = [], fid, 0
        while at is not None:
            n = self.node(at)
            if n is None or steps > 4096:
                return None
            names.append(n.name)
            at, steps = n.parent_fid, steps + 1
        return "/" + "/".join(reversed(names))

    def process(self, batch: list[Event], reduce: bool = True) -> list[Action]:
        """Both lists of a batch in one, deletes first."""
        self.counters.batches += 1
        events = reduce_batch(batch, self.counters, self.pairs, self.override) if reduce else batch
        self.out: dict[tuple[str, int, str], Action] = {}
        for e in events:
            self.handlers[e.op](e)
        made = sorted(self.out.values(), key=lambda a: (a.action != "delete", a.last_seq, a.fid))
        self.counters.updates += sum(a.action == "update" for a in made)
        self.counters.deletes += sum(a.action == "delete" for a in made)
        if self.max_dirs is not None:
            self._evict()
        return made

    def _show(self, fid: int, seq: int, size: int | None) -> None:
        """Give the index an object's present path; an older one that it has is deleted."""
        node, path = self.node(fid), self.path(fid)
        if node is None or path is None:
            self.counters.unresolved += 1
            return
        size = node.size if size is None else size
        if node.shown is not None and node.shown != path:
            self._hide(fid, node.shown, seq)
        if self.stat_mode == "call":
            self.counters.stat_calls += 1
        self.store.put(fid, node._replace(shown=path, size=size))
        for key in [k for k in self.out if k[0] == "update" and k[1] == fid]:
            del self.out[key]
        self.out["update", fid, path] = Action("update", fid, path, size, seq)

    def _hide(self, fid: int, path: str, seq: int) -> None:
        for key in [("update", fid, path)]:
            self.out.pop(key, None)
        self.out["delete", fid, path] = Action("delete", fid, path, None, seq)

    def _create(self, e: Event) -> None:
        self.store.put(e.fid, NodeRow(e.parent_fid, e.name, e.is_dir, None, e.size))
        if e.is_dir:
            self._show_below(e.fid, e.seq)  # what waited for it
        else:
            self._show(e.fid, e.seq, e.size)

    def _show_below(self, fid: int, seq: int) -> None:
        todo = [fid]
        while todo:
            for c in self.children(todo.pop()):
                n = self.node(c)
                if n is None:
                    continue
                if n.is_dir:
                    todo.append(c)
                else:
                    self._show(c, seq, None)

    def _remove(self, e: Event) -> None:
        node = self.node(e.fid)
        if node is not None:
            if node.shown is not None:
                self._hide(e.fid, node.shown, e.seq)
            self.store.remove(e.fid)
        elif not e.is_dir:
            self.counters.unresolved += 1
        self.recent.pop(e.fid, None)

    def _update(self, e: Event) -> None:
        if not e.is_dir:
            self._show(e.fid, e.seq, e.size)

    def _rename(self, e: Event) -> None:
        node = self.node(e.fid)
        if node is None:
            node = NodeRow(None, e.name, e.is_dir, None, e.size)
        self.store.put(e.fid, node._replace(parent_fid=e.parent_fid, name=e.name, size=node.size if e.is_dir or e.size is None else e.size))
        if e.is_dir:
            self._show_below(e.fid, e.seq)
        else:
            self._show(e.fid, e.seq, e.size)

    def _evict(self) -> None:
        """Least recently used directories go with the files in them; they come back through the resolver. A
        directory with others in the state stays, as an ancestor of what lives, and so does one whose files wait."""
        spare = len(self.recent) - self.max_dirs
        for fid in list(self.recent):
            if spare <= 0:
                return
            held = [(c, self.store.get(c)) for c in self.store.children(fid)]
            if any(n is not None and (n.is_dir or n.shown is None) for _, n in held):
                continue
            for c, n in [*held, (fid, self.store.get(fid))]:
                if n is not None and self.spill is not None:
                    self.spill(c, n)
                self.store.remove(c)
            del self.recent[fid]
            self.counters.evicted += 1
            spare -= 1
