"""Where levels live: in memory, on disk, or by predicted size; and reading disk levels part by part with prefetch."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.balance.predict import split_even
from levelmine.explore import edge, vertex
from levelmine.explore.loop import children, explore, written
from levelmine.explore.vertex import EFilter, Level
from levelmine.graph.model import PropertyGraph
from levelmine.session import materialise
from levelmine.store.levels import LevelStore

#: Bytes of a row in memory besides its vertices, of a vertex of the path with its label, and of an entry of ext.
ROW_BYTES, VERTEX_BYTES, ENTRY_BYTES = 48, 12, 16


@dataclass(frozen=True)
class Predicted:
    """The next level before it is made: its rows, exactly, and its bytes in memory, at most."""

    rows: int
    bytes: int


def predicted(graph: PropertyGraph, level: Level, efilter: EFilter = None) -> Predicted:
    """A child holds its parent's candidates and those of its new vertex; the widest vertex bounds the latter."""
    made = children(level, efilter)
    sums = level.df.agg(F.sum(made).alias("n"), F.sum(made * F.size(F.map_keys("ext"))).alias("e")).first()
    rows, held = sums["n"] or 0, sums["e"] or 0
    degree = graph.stats().first()["avg_degree"] or 0 if rows else 0
    return Predicted(rows, int(rows * (ROW_BYTES + VERTEX_BYTES * (level.k + 1) + ENTRY_BYTES * degree) + ENTRY_BYTES * held))


class Storage:
    """memory: levels are cached with their candidates. disk: levels are written as links. hybrid: a level goes to disk if
    its predicted bytes exceed what is left of the budget."""

    def __init__(self, kind: str = "hybrid", budget_bytes: int = 1 << 30):
        if kind not in ("memory", "disk", "hybrid"):
            raise ValueError("storage: memory, disk, hybrid")
        self.kind, self.left, self.placed, self.sizes = kind, budget_bytes, [], []

    def keep(self, graph: PropertyGraph, level: Level, efilter: EFilter = None) -> Level:
        """The next level, kept as the storage says."""
        size = predicted(graph, level, efilter) if level.carried and self.kind != "disk" else None
        self.sizes.append(size)
        to_disk = self.kind == "disk" or (self.kind == "hybrid" and (size is None or size.bytes > self.left))
        self.placed.append("disk" if to_disk else "memory")
        if to_disk:
            return written(graph, level, efilter)
        self.left -= size.bytes if size else 0
        module = vertex if "path" in level.df.columns else edge
        grown = module.expand(graph, level, efilter)
        if level.carried:
            # the path itself names a row that may be computed again after a loss
            grown = Level(grown.df.withColumn("pos", F.col("path" if module is vertex else "eids")), grown.k, True)
        return Level(grown.df.persist(StorageLevel.MEMORY_AND_DISK), grown.k, grown.carried)


def explore_stored(graph: PropertyGraph, k: int, storage: Storage) -> DataFrame:
    """Level k, its predecessors kept as the storage says; the answer is the same for all kinds."""
    for level in explore(graph, k, keep=storage.keep):  # noqa: B007
        pass
    return level.df


class WindowReader:
    """A level's parts in order, the next ones loaded while one is worked on. `load` may return the windows of several
    levels; all of them move on together."""

    def __init__(self, load: Callable[[int], DataFrame | list[DataFrame]], parts: int, prefetch: int = 1):
        self.load, self.parts, self.prefetch = load, parts, prefetch

    def __iter__(self) -> Iterator[tuple[int, DataFrame | list[DataFrame]]]:
        def fetch(part: int):
            got = self.load(part)
            held = [df.persist(StorageLevel.MEMORY_AND_DISK) for df in (got if isinstance(got, list) else [got])]
            for df in held:
                df.count()
            return held if isinstance(got, list) else held[0]

        with ThreadPoolExecutor(max(1, self.prefetch)) as pool:
            waiting = [pool.submit(fetch, p) for p in range(min(self.parts, self.prefetch + 1))]
            for part in range(self.parts):
                got = waiting[part].result()
                if (after := part + self.prefetch + 1) < self.parts:
                    waiting.append(pool.submit(fetch, after))
                yield part, got
                for df in got if isinstance(got, list) else [got]:
                    df.unpersist()


def expand_by_part(graph: PropertyGraph, level: Level, parts: int, last: bool = True, prefetch: int = 1) -> DataFrame:
    """The next level, made part by part from a level on disk; each part has a folder of its own, and its children are
    written before the next."""
    store = LevelStore(graph.edges.sparkSession)
    placed = split_even(level.df.drop("ext", "pos"), parts, "path")
    store.write_parts(level.k, placed)
    reader = WindowReader(lambda p: store.part(level.k, p), parts, prefetch)
    done = []
    for p, df in reader:
        grown = vertex.expand(graph, vertex.with_ext(graph, df, level.k), last=last)
        done.append(materialise(grown.df, f"part{p}"))
    return reduce(DataFrame.unionByName, done)


def expand_windows(graph: PropertyGraph, store: LevelStore, parts: int, prefetch: int = 1) -> DataFrame:
    """The level after the store's last one, from parts of it on disk and the windows of the levels above that each part
    needs; nothing else of the store is read."""
    k = store.k
    store.write_parts(k, split_even(store.level(k).withColumnRenamed("pos", "own"), parts, "parent", "vert").drop("pos").withColumnRenamed("own", "pos"))
    reader = WindowReader(lambda p: store.window_paths(k, store.part(k, p)), parts, prefetch)
    done = [materialise(vertex.expand(graph, vertex.with_ext(graph, df, k), last=True).df, f"window{p}") for p, df in reader]
    return reduce(DataFrame.unionByName, done)
