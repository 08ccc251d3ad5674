"""How many groups to cut a table into, by its bytes."""

from __future__ import annotations

from pyspark.sql import DataFrame

from levelmine.session import shuffle_width

#: Stored bytes of the input for each group at most, and at least where the session's shuffle width asks for more groups.
GROUP_BYTES, LEAST_BYTES = 8 << 20, 1 << 18


def stored_bytes(df: DataFrame) -> int | None:
    """Bytes of the files and local rows under the plan, as the optimizer has them; None where it does not know."""
    leaves, total = df._jdf.queryExecution().optimizedPlan().collectLeaves(), 0
    for i in range(leaves.size()):
        size = int(str(leaves.apply(i).stats().sizeInBytes()))
        if size >= 1 << 60:
            return None
        total += size
    return total


def group_count(df: DataFrame, per_task: int = 1, group_bytes: int = GROUP_BYTES) -> int:
    """per_task groups a shuffle partition; more, so that no group has more than group_bytes; fewer where they would be tiny."""
    wanted, size = per_task * shuffle_width(df.sparkSession), stored_bytes(df)
    if size is None:
        return wanted
    return max(1, -(-size // group_bytes), min(wanted, -(-size // LEAST_BYTES)))
