"""Group-wise upkeep of a certificate: a full buffer is merged with it and solved, then the next fills."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np

from sparsecert.kernels.certs import (
    FOREST_KERNELS, Edges, edge_cert, forest_and_odd, lighter_than_path, spanning_forest, vertex_cert,
)


@dataclass(frozen=True)
class GroupPolicy:
    """How many edges make a group, for n vertices."""

    kind: str = "linear"
    value: float = 0.0

    @staticmethod
    def linear() -> GroupPolicy:
        return GroupPolicy("linear")

    @staticmethod
    def nlogn(power: float = 1.0) -> GroupPolicy:
        return GroupPolicy("nlogn", power)

    @staticmethod
    def edges(r: int) -> GroupPolicy:
        return GroupPolicy("edges", r)

    @staticmethod
    def budget(held_bytes: int, edge_bytes: int = 32) -> GroupPolicy:
        """Two buffers and the certificate within so many bytes."""
        return GroupPolicy("edges", max(1, held_bytes // edge_bytes // 3))

    @staticmethod
    def fraction(share: float) -> GroupPolicy:
        return GroupPolicy("fraction", share)

    @staticmethod
    def whole() -> GroupPolicy:
        return GroupPolicy("whole")

    @staticmethod
    def adaptive(least: int = 1024) -> GroupPolicy:
        """As many as vertices were known when the last group closed, but no fewer than `least`."""
        return GroupPolicy("adaptive", least)

    def size(self, n: int) -> int:
        log = math.ceil(math.log2(n)) if n > 1 else 1
        return max(1, {"linear": lambda: n, "nlogn": lambda: math.ceil(n * log**self.value), "edges": lambda: int(self.value), "fraction": lambda: math.ceil(n * self.value), "whole": lambda: 1 << 62, "adaptive": lambda: max(n, int(self.value))}[self.kind]())


@dataclass(frozen=True)
class Property:
    """What a certificate is for: its kernel, what happens to the last group, and the bound on its size."""

    name: str
    k: int = 1
    kernel: str = "auto"
    tail: str = "append"
    prefilter: bool = False
    pad_tail: bool = False

    def keep(self, e: Edges) -> np.ndarray:
        if self.name == "components":
            return spanning_forest(e)
        if self.name == "bipartite":
            return forest_and_odd(e)
        if self.name == "bipartite_each":
            return forest_and_odd(e, per_component=True)
        if self.name == "vertex":
            return vertex_cert(e, self.k, self.kernel)
        if self.name == "edge":
            return edge_cert(e, self.k, self.kernel)
        if self.name == "min_forest":
            return FOREST_KERNELS[self.kernel](e)
        if self.name == "max_forest":
            return FOREST_KERNELS[self.kernel](Edges(e.u, e.v, -e.w, e.eid))
        raise ValueError(self.name)

    def bound(self, n: int) -> int:
        return {"components": n - 1, "bipartite": n, "bipartite_each": n, "min_forest": n - 1, "max_forest": n - 1}.get(self.name, self.k * (n - 1))


def of(name: str, k: int = 1, **options) -> Property:
    forests = name in ("min_forest", "max_forest")
    return Property(name, k, options.pop("kernel", "sort" if forests else "auto"), options.pop("tail", "resolve" if forests else "append"), **options)


#: Vertices that are assumed until the first group has told how many there are.
START = 1024


@dataclass
class Fold:
    """The state of one pass: certificate, buffer and a row of counters per group.

    Taking edges costs a view of what arrives; all else is done when a group closes. With overlap a
    closed group is solved by a second thread while the next one fills; `wait_ns` is what arrivals
    then had to wait for.
    """

    prop: Property
    policy: GroupPolicy
    n: int | None = None
    overlap: bool = False
    cert: Edges = field(default_factory=Edges.empty)
    buffer: list[Edges] = field(default_factory=list)
    held: int = 0
    groups: list[dict] = field(default_factory=list)
    known: int | None = None
    peak: int = 0
    edges_read: int = 0
    wait_ns: int = 0
    in_flight: int = 0
    pool: ThreadPoolExecutor | None = None
    pending: Future | None = None

    def __post_init__(self) -> None:
        if self.known is None:
            self.known = START if self.n is None else 0

    def _size(self) -> int:
        """A group's size; n that turns out to be below the number of vertices would make groups too small for O(1) an edge."""
        return self.policy.size(self.known if self.n is None else max(self.n, self.known))

    def add(self, e: Edges) -> None:
        """Takes edges as they arrive; whole groups are folded in on the way."""
        self.edges_read += len(e)
        at, size = 0, self._size()
        while at < len(e):
            part = e.slice(at, min(len(e), at + max(1, size - self.held)))
            at += len(part)
            self.buffer.append(part)
            self.held += len(part)
            self.peak = max(self.peak, len(self.cert) + self.held + self.in_flight)
            if self.held >= size:
                self._close()
                size = self._size()

    def _close(self, tail: bool = False) -> None:
        group, self.buffer, self.held = self.buffer, [], 0
        if not self.overlap:
            self._take(self._solved(self.cert, group, tail))
            return
        self.settle()
        self.pool = self.pool or ThreadPoolExecutor(1)
        self.in_flight = sum(map(len, group))
        self.pending = self.pool.submit(self._solved, self.cert, group, tail)

    def settle(self) -> None:
        """Waits for the group that is being solved, if any."""
        if self.pending is not None:
            began = time.perf_counter_ns()
            found = self.pending.result()
            self.wait_ns += time.perf_counter_ns() - began
            self.pending, self.in_flight = None, 0
            self._take(found)

    def _take(self, found: tuple[Edges, dict, int]) -> None:
        self.cert, row, self.known = found
        self.groups.append(row)

    def _solved(self, cert: Edges, buffer: list[Edges], tail: bool) -> tuple[Edges, dict, int]:
        began = time.perf_counter_ns()
        group = Edges.join(*buffer)
        before, arrived = len(cert), len(group)
        if self.prop.prefilter:
            group = group.take(lighter_than_path(cert, group))
        merged = Edges.join(cert, group)
        if tail and self.prop.pad_tail and len(merged) and self.policy.kind != "whole":  # all in one group is a whole group
            merged, real = _padded(merged, self._size() - arrived), len(merged)
            kept = self.prop.keep(merged)
            kept = kept[kept < real]
        else:
            kept = self.prop.keep(merged)
        out = merged.take(kept)
        # every vertex seen is an end of the certificate, as that spans all components
        known = len(np.unique(np.concatenate([out.u, out.v])))
        known = max(START, known) if self.n is None else known
        return out, {"edges_in": arrived, "cert_before": before, "merged": len(merged), "cert_after": len(kept), "update_ns": time.perf_counter_ns() - began}, known

    def finish(self, resolve: bool | None = None) -> Edges:
        """The last group is appended, or solved if the property asks for it."""
        if self.held and (self.prop.tail == "resolve" if resolve is None else resolve):
            self._close(tail=True)
        self.settle()
        if self.held:
            group = Edges.join(*self.buffer)
            self.groups.append({"edges_in": len(group), "cert_before": len(self.cert), "merged": len(self.cert) + len(group), "cert_after": len(self.cert) + len(group), "update_ns": 0})
            self.cert, self.buffer, self.held = Edges.join(self.cert, group), [], 0
        if self.pool is not None:
            self.pool.shutdown()
            self.pool = None
        return self.cert


def _padded(e: Edges, count: int) -> Edges:
    """With dummy edges heavier than all real ones between vertices that are there, up to a whole group."""
    count = max(0, count)
    ids = np.unique(np.concatenate([e.u, e.v]))
    at = np.arange(count)
    heavy = np.full(count, e.w.max() + 1)
    return Edges.join(e, Edges(ids[at % len(ids)], ids[(at * 7 + 1) % len(ids)], heavy, np.full(count, np.iinfo(np.int64).max)))


def fold_all(e: Edges, prop: Property, policy: GroupPolicy, n: int | None = None) -> Fold:
    out = Fold(prop, policy, n)
    out.add(e)
    out.finish()
    return out


def merged(a: Edges, b: Edges, prop: Property) -> Edges:
    """The union law: a certificate of the union of what two certificates stand for."""
    both = Edges.join(a, b)
    return both.take(prop.keep(both))


def over_time(batches: Iterator[Edges], prop: Property, policy: GroupPolicy, n: int | None, post: Callable[[Edges], object], overlap: bool = False) -> Iterator[tuple[int, int, object]]:
    """(group, edges read, answer) after each group, for callers that ask in mid-stream: the post-pass runs each time."""
    f, told = Fold(prop, policy, n, overlap), 0
    for e in batches:
        at = 0
        while at < len(e):
            step = max(1, f._size() - f.held)
            f.add(e.slice(at, at + step))
            at += step
            f.settle()
            if len(f.groups) > told:
                told = len(f.groups)
                yield told - 1, f.edges_read, post(f.cert)
    if f.held:
        yield told, f.edges_read, post(f.finish())
