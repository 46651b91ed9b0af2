"""Closed forms in block transfers, and the ledger that checks them against measured row counts."""

from __future__ import annotations

from dataclasses import dataclass, field
from math import ceil, floor, log2, sqrt

from ..model import MemoryModel


def scan_io(n: float, mm: MemoryModel) -> float:
    return ceil(n / mm.b)


def sort_io(n: float, mm: MemoryModel) -> float:
    """n log(n/B) / (B log M) + n/B, with logarithms of at least 1."""
    if n <= 0:
        return 0.0
    return n * max(1.0, log2(max(n / mm.b, 1.0))) / (mm.b * max(1.0, log2(mm.m))) + n / mm.b


def predicted_io(method: str, edges: int, mm: MemoryModel, *, vertices: int = 0, bases: int | None = None, k: int = 3) -> float:
    """Leading terms of each method's bound, without constants."""
    e, m, b = edges, mm.m, mm.b
    bounds = {
        "cells": lambda: e**1.5 / (sqrt(m) * b),
        "recursive": lambda: e**1.5 / (sqrt(m) * b),
        "steered": lambda: e**1.5 / (sqrt(m) * b),
        "base_scan": lambda: e**2 / (m * b),
        "sort_wedge": lambda: sort_io(e**1.5, mm),
        "base_edges": lambda: e / b + (e if bases is None else bases) * e / (m * b),
        "vertex": lambda: sort_io(e, mm),
        "cliques": lambda: e ** (k / 2) / (m ** (k / 2 - 1) * b),
        "clique_growth": lambda: e ** (k - 1) / (m ** (k - 2) * b),
    }
    return bounds[method]()


def gain(edges: int, mm: MemoryModel) -> float:
    """Improvement over the better of the two earlier bounds: min(sqrt(E/M), sqrt(M))."""
    return min(sqrt(edges / mm.m), sqrt(mm.m))


def max_triangles(edges: int) -> int:
    """No graph of so many edges has more triangles."""
    return floor(sqrt(2) / 3 * edges**1.5)


def lower_bound_io(triangles: int, mm: MemoryModel) -> float:
    """t / (sqrt(M) B) + t^(2/3) / B: what any method transfers, at best."""
    return triangles / (sqrt(mm.m) * mm.b) + triangles ** (2 / 3) / mm.b


def epoch_bound_io(triangles: int, mm: MemoryModel) -> float:
    """Epochs of M/B transfers, in each of which at most the triangles of 2M edges are met."""
    return floor(triangles / max(1, max_triangles(2 * mm.m))) * (mm.m / mm.b)


def search_memory(vertices: int, edges: int, mm: MemoryModel) -> float:
    """Counters that the search for a colouring holds: log^2 V log^2(E/M)."""
    return max(1.0, log2(max(vertices, 2))) ** 2 * max(1.0, log2(max(edges / mm.m, 2))) ** 2


def replication(c: int) -> int:
    """Copies of an edge over all cells, roles merged."""
    return 3 * c - 2


@dataclass
class IoLedger:
    """Transfers by named step, from measured row counts."""

    mm: MemoryModel
    steps: list[tuple[str, float]] = field(default_factory=list)

    def scan(self, name: str, n: float) -> IoLedger:
        self.steps.append((name, scan_io(n, self.mm)))
        return self

    def sort(self, name: str, n: float) -> IoLedger:
        self.steps.append((name, sort_io(n, self.mm)))
        return self

    def vertex_triangles(self, name: str, n: float, times: int = 1) -> IoLedger:
        self.steps.append((name, times * (scan_io(n, self.mm) + 2 * sort_io(n, self.mm))))
        return self

    def base_edges(self, name: str, bases: float, edges: float, alpha: float = 0.5) -> IoLedger:
        batches = ceil(bases / max(1.0, alpha * self.mm.m))
        self.steps.append((name, batches * scan_io(edges, self.mm) + scan_io(bases, self.mm)))
        return self

    def total(self) -> float:
        return sum(v for _, v in self.steps)


def regularity(total_at: dict[int, float]) -> dict[int, float]:
    """Q(M) / Q(2M) for each M whose double was measured too."""
    return {m: total_at[m] / total_at[2 * m] for m in total_at if 2 * m in total_at and total_at[2 * m]}
