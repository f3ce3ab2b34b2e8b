"""Closed-form costs: memory needs of the ways to run a round, crossovers, projections, fleets."""

from __future__ import annotations

from dataclasses import dataclass

GIB = 1 << 30


@dataclass(frozen=True)
class Tuning:
    """Block records, merge fan-in, sorter threads and mergers."""

    n: int
    k: int
    threads: int
    mergers: int


def tune(memory: int, cores: int, bandwidth: float, record: int = 16, block: int = 512 << 20, prefetch: int = 4 << 20, merger_bandwidth: float = 1e9) -> Tuning:
    """Blocks as large as fit memory while every sorter thread holds two of them, up to ``block`` bytes."""
    threads = max(1, min(16, cores // 2))
    size = max(1 << 20, min(block, memory // (2 * threads)))
    mergers = max(1, min(cores // 4, int(bandwidth // merger_bandwidth) or 1))
    k = max(2, min(64, memory // (4 * mergers * prefetch)))
    return Tuning(size // record, int(k), threads, mergers)


#: Bytes of state that each vertex needs in memory where values are not written out: old and new rank and the degree;
#: parent, and two words for marks and queue; parent, score, level and list links.
STATE = {"rank": 20, "bfs": 16, "betweenness": 28}


def memory_need(engine: str, vertices: int, edges: int, algorithm: str = "rank", threads: int = 16, block: int = 512 << 20, prefetch: int = 4 << 20, k: int = 16, mergers: int = 4) -> int:
    """Bytes of memory with which an engine runs at full speed."""
    state = vertices * STATE[algorithm]
    return {
        "sort_reduce": threads * block + prefetch * k * mergers,
        "semi_external": state,
        "edge_scan": vertices * 16,
        "multi_pass": state // 4,
        "cached": edges * 24 + state,
    }[engine]


ENGINES = ("sort_reduce", "semi_external", "edge_scan", "multi_pass", "cached")

#: Published sizes of the graphs compared: vertices and edges; fixed values.
PUBLISHED = {"social": (41_000_000, 1_470_000_000), "kron28": (268_000_000, 4_000_000_000), "kron30": (1_000_000_000, 17_000_000_000), "web": (3_000_000_000, 128_000_000_000)}


def needs(graphs: dict[str, tuple[int, int]] = PUBLISHED) -> list[tuple[str, str, str, int]]:
    """(graph, algorithm, engine, bytes) from vertices and edges of each graph."""
    return [(g, a, e, memory_need(e, n, m, a)) for g, (n, m) in graphs.items() for a in STATE for e in ENGINES]


def crossover(grid: tuple[int, ...] = (16, 32, 48, 64, 96, 128), graphs: dict[str, tuple[int, int]] = PUBLISHED) -> list[tuple[str, str, str, int, bool]]:
    """(graph, algorithm, engine, GiB, fits) over a grid of memory sizes."""
    return [(g, a, e, gib, need <= gib * GIB) for g, a, e, need in needs(graphs) for gib in grid]


def edge_scan_partitions(vertices: int, memory: int, value: int = 16) -> int:
    """Vertex partitions, doubled until the values of one fit the memory."""
    parts = 1
    while vertices * value > memory * parts:
        parts *= 2
    return parts


def project(rounds: int, seconds: float) -> float:
    """Seconds of a job whose every round costs the same."""
    return rounds * seconds


def fleet(size: int, node_memory: int, node_dollars: int = 2500, node_watts: int = 170) -> tuple[int, int, int]:
    """(nodes, dollars, watts) to hold a graph of ``size`` bytes in memory."""
    nodes = -(-size // node_memory)
    return nodes, nodes * node_dollars, nodes * node_watts


def page_waste(useful: int, page: int) -> float:
    return page / useful
