"""Table functions and grouped aggregates for SQL: `register` makes them known to a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


class RingSchedule:
    """Rows (step, receiver, sender) of the ring schedule of some blocks in groups of some size."""

    def eval(self, blocks: int, group: int):
        per = max(1, (group - 1) // 2)
        for receiver in range(blocks):
            for off in range(1, blocks):
                yield (off - 1) // per + 1, receiver, (receiver - off) % blocks


class SplitSteps:
    """Rows (step, size, keep_size, cut_size, d) of the split of a template, given as its parent numbers in a string."""

    def eval(self, parents: str):
        from treecount.plans.templates import TreeTemplate, split_plan

        template = TreeTemplate(tuple(int(x) for x in parents.split()))
        for i, s in enumerate(split_plan(template).steps):
            yield (i + 1, *s.sizes, s.d)


class FreeTrees:
    """Rows (tree, parents, symmetries): all free trees with some number of vertices."""

    def eval(self, k: int):
        from treecount.plans.templates import all_free_trees

        for i, t in enumerate(all_free_trees(k)):
            yield i + 1, " ".join(map(str, t.parents)), t.automorphisms


def median_of_means_udaf():
    """Grouped aggregate (it, estimate, groups) -> median of the group means; a group's estimates fit one task."""

    @pandas_udf("double")
    def mom(it: pd.Series, estimate: pd.Series, groups: pd.Series) -> float:
        t = int(groups.iloc[0])
        return float(estimate.groupby(it % t).mean().median())

    return mom


def register(spark: SparkSession) -> None:
    """``ring_schedule``, ``split_steps``, ``free_trees``, ``median_of_means``, ``mask_size`` and ``tree_work`` in SQL."""
    spark.udtf.register("ring_schedule", udtf(RingSchedule, returnType="step int, receiver int, sender int"))
    spark.udtf.register("split_steps", udtf(SplitSteps, returnType="step int, size int, keep_size int, cut_size int, d int"))
    spark.udtf.register("free_trees", udtf(FreeTrees, returnType="tree int, parents string, symmetries int"))
    spark.udf.register("median_of_means", median_of_means_udaf())
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mask_size(m INT) RETURNS INT RETURN bit_count(m)")
