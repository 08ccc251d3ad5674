"""Dense numbers in a global order without a global window: range partitions, their sizes, their bases."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelmine.session import materialise, shuffle_width


#: Rows of a block of running values; three levels of blocks hold 10**15 rows.
BLOCK = 100_000


def running(rows: DataFrame, n: str, value: str, fold: Callable[[Column | str], Column], both: Callable[[Column, Column], Column], name: str = "before", depth: int = 2) -> DataFrame:
    """Adds the fold of `value` over all rows before, in the order of the dense number n; null where there are none.

    Blocks of n are folded first, then blocks of blocks, so that no window spans more rows than a block has."""
    block, of, base = f"block_{depth}", f"of_{depth}", f"base_{depth}"
    cut = rows.withColumn(block, F.floor(F.col(n) / BLOCK))
    within = Window.partitionBy(block).orderBy(n).rowsBetween(Window.unboundedPreceding, -1)
    own = cut.withColumn(name, fold(value).over(within))
    if depth == 0:
        return own.drop(block)
    blocks = cut.groupBy(F.col(block).alias(of)).agg(fold(value).alias("folded"))
    bases = running(blocks, of, "folded", fold, both, base, depth - 1).select(of, base)
    joined = own.join(bases, F.col(block) == F.col(of), "left")
    total = F.when(F.col(name).isNull(), F.col(base)).when(F.col(base).isNull(), F.col(name)).otherwise(both(F.col(name), F.col(base)))
    return joined.withColumn(name, total).drop(block, of, base)


def numbered(df: DataFrame, *order: str, name: str = "pos", start: int = 0, width: int | None = None) -> DataFrame:
    """Adds a long column: the row's place in the given order. Ties are numbered in no fixed order.

    The sorted rows are written once, so that numbers and rows stay together whatever is computed again later. One
    number a partition goes through the driver and back in a broadcast.
    """
    spark = df.sparkSession
    ranged = df.repartitionByRange(width or shuffle_width(spark), *order).sortWithinPartitions(*order)
    low = F.monotonically_increasing_id()
    kept = materialise(ranged.withColumn("n_part", F.shiftright(low, 33).cast("int")).withColumn("n_row", low.bitwiseAND((1 << 33) - 1)), "numbered")
    sizes = {r["n_part"]: r["n"] for r in kept.groupBy("n_part").agg(F.count("*").alias("n")).collect()}
    at, bases = start, []
    for part in sorted(sizes):
        bases.append((part, at))
        at += sizes[part]
    base = F.broadcast(spark.createDataFrame(bases, "n_part int, n_base long"))
    return kept.join(base, "n_part").select((F.col("n_base") + F.col("n_row")).alias(name), *df.columns)
