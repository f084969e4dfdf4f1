"""Joins whose large side may have one key in a third of its rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from densegrid.plans.lineage import cut

#: A key is hot with more than one row in so many; there are no more such keys than that.
SHARE = 1000


def hot_join(big: DataFrame, small: DataFrame, key: str) -> DataFrame:
    """The inner join of ``big`` (best read from files) with ``small``, which has one row for each ``key``.

    The at most ``SHARE`` hot keys of ``big`` are broadcast with their rows of
    ``small``, so that their rows stay where they are; the others meet by a shuffle.
    """
    total = big.count()
    hot = cut(big.groupBy(key).agg(F.count("*").alias("_n")).where(F.col("_n") > max(1, total // SHARE)).select(key))
    if hot.isEmpty():
        return big.join(small, key)
    few = cut(small.join(F.broadcast(hot), key, "left_semi"))
    cold = big.join(F.broadcast(hot), key, "left_anti").join(small, key)
    return big.join(F.broadcast(few), key).unionByName(cold)
