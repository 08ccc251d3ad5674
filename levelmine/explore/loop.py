"""The exploration loop: one round a level, each written as links before the next, guarded by an exact prediction of its
rows. A written level is (pos, parent, vert, label, mask): a few numbers a row, whatever the degrees are."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelmine.explore import edge, vertex
from levelmine.explore.vertex import EFilter, Level
from levelmine.graph.model import PropertyGraph
from levelmine.graph.pendant import fold
from levelmine.plans.planner import Plan, plan
from levelmine.session import materialise


def children(level: Level, efilter: EFilter = None) -> Column:
    """Column: how many rows of the next level a row makes."""
    made = (vertex if "path" in level.df.columns else edge).extensions(level, efilter)
    return F.size(F.map_keys(made)).cast("long")


#: (graph, level, filter) -> the next level, kept somewhere.
Keep = Callable[[PropertyGraph, Level, EFilter], Level]


def numbered_links(rows: DataFrame, name: str) -> DataFrame:
    """Written rows with a unique pos, rising in the order of the files."""
    return materialise(rows.withColumn("pos", F.monotonically_increasing_id()), name)


def written(graph: PropertyGraph, level: Level, efilter: EFilter = None) -> Level:
    """The next level, written as links."""
    name = f"level{level.k + 1}"
    if not level.carried:
        grown = (vertex if "path" in level.df.columns else edge).expand(graph, level, efilter)
        return Level(materialise(grown.df, name), grown.k)
    if "path" in level.df.columns:
        return vertex.attached(graph, level, numbered_links(vertex.children(level, efilter), name))
    return edge.attached(graph, level, numbered_links(edge.children(graph, level, efilter), name))


def predicted_rows(level: Level, efilter: EFilter = None) -> int:
    """Exact number of rows of the next level, counted without making them."""
    return level.df.agg(F.sum(children(level, efilter))).first()[0] or 0


def explore(graph: PropertyGraph, k: int, mode: str = "vertex", efilter: EFilter = None, until: Callable[[Level], bool] | None = None,
            max_rows: int | None = None, strategy: str | None = None, start: int = 1, keep: Keep | None = None) -> Iterator[Level]:
    """Yields the levels from `start` to k. The last one is left lazy, so that what uses it runs in the same job.

    until: stops after the first level for which it is true. max_rows: a round that would make more is refused.
    keep: where the levels in between go; written as links unless given.
    """
    how: Plan = plan(graph, k, strategy)
    module = vertex if mode == "vertex" else edge
    level = module.init(graph, start, carry=how.carry) if mode == "vertex" else module.init(graph, carry=how.carry)
    while True:
        yield level
        if level.k >= k or (until is not None and until(level)):
            return
        if max_rows is not None and level.carried and (n := predicted_rows(level, efilter)) > max_rows:
            raise RuntimeError(f"level {level.k + 1} would have {n} rows; max_rows is {max_rows}")
        last = level.k + 1 == k
        level = module.expand(graph, level, efilter, last=True) if last else (keep or written)(graph, level, efilter)


def embeddings(graph: PropertyGraph, k: int, mode: str = "vertex", efilter: EFilter = None, strategy: str | None = None) -> DataFrame:
    """The rows of level k."""
    for level in explore(graph, k, mode, efilter, strategy=strategy):  # noqa: B007
        pass
    return level.df


def level_sizes(graph: PropertyGraph, k: int, mode: str = "vertex") -> DataFrame:
    """(k, n): rows of each level; an empty level ends the exploration, and the larger sizes are 0.

    Of vertices, trees are folded first: what remains is explored, and a row counts for all the sets that it stands for."""
    spark, sizes = graph.edges.sparkSession, [0] * k
    whole = fold(graph, k) if mode == "vertex" else None
    if whole is not None:
        graph, sizes = whole.graph, list(whole.inside)
    for level in explore(graph, k, mode, until=lambda x: x.df.isEmpty()):
        for i, n in enumerate(whole.stands_for(level.df, level.k) if whole is not None else [level.df.count()], level.k - 1):
            sizes[i] += n
    return spark.createDataFrame(list(enumerate(sizes, 1)), "k int, n long")
