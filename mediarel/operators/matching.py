"""One-to-one resolution: greedy by score, as a grouped function or as distributed rounds; closure over links."""

from __future__ import annotations

from collections.abc import Sequence

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mediarel.sources import stored


def greedy(df: DataFrame, within: Sequence[str], left: str, right: str, score: str) -> DataFrame:
    """Keep pairs in descending score (then left, right) unless a side is already used in the group. For groups that fit a task.

    Pairs whose sides have no other pair are kept by window counts; only groups with conflicts reach the grouped function.
    One shuffle by ``within`` serves the windows and the groups.
    """

    def settle(group: pd.DataFrame) -> pd.DataFrame:
        ordered = group.sort_values([score, left, right], ascending=[False, True, True], kind="stable")
        used_left, used_right, kept = set(), set(), []
        for a, b in zip(ordered[left], ordered[right], strict=True):
            fits = a not in used_left and b not in used_right
            kept.append(fits)
            if fits:
                used_left.add(a)
                used_right.add(b)
        return ordered[kept]

    seen = lambda side: F.count("*").over(Window.partitionBy(*within, side))
    counted = df.withColumn("_alone", (seen(left) == 1) & (seen(right) == 1))
    alone = counted.where("_alone").select(*df.columns)
    return alone.unionByName(counted.where("NOT _alone").select(*df.columns).groupBy(*within).applyInPandas(settle, df.schema))


def _best(df: DataFrame, keys: Sequence[str], left: str, right: str, score: str) -> DataFrame:
    """The first pair of each key as a pre-aggregated minimum, so no task holds a key's pairs."""
    return df.groupBy(*keys).agg(F.min(F.struct((-F.col(score)).alias("s"), F.col(left).alias("l"), F.col(right).alias("r"))).alias("best"))


def mutual_best(df: DataFrame, within: Sequence[str], left: str, right: str, score: str, folder: str | None = None) -> DataFrame:
    """The same matching for groups of any size, in rounds: a pair that is the best of both its sides is what greedy would keep.

    Every round settles all such pairs of all groups and drops what shares a side with them. Rounds are
    written to ``folder`` (a shared one), so a lost executor costs one round at most.
    """
    spark = df.sparkSession
    at = stored.new_path(spark, "settle", folder)
    kept = lambda frame, name: stored.write(frame, f"{at}/{name}")
    rest, step = kept(df, "rest-0"), 0
    while rest.limit(1).count():
        step += 1
        by_left = _best(rest, [*within, left], left, right, score).select(*within, left, F.col("best.r").alias("_l_pick"))
        by_right = _best(rest, [*within, right], left, right, score).select(*within, right, F.col("best.l").alias("_r_pick"))
        marked = rest.join(by_left, [*within, left]).join(by_right, [*within, right])
        # All rounds write into one table, so the result has one branch.
        won = kept(marked.where((F.col(right) == F.col("_l_pick")) & (F.col(left) == F.col("_r_pick"))).select(*df.columns), f"won/_round={step}")
        rest = kept(rest.join(won.select(*within, left), [*within, left], "left_anti").join(won.select(*within, right), [*within, right], "left_anti").select(*df.columns), f"rest-{step}")
        stored.remove(spark, f"{at}/rest-{step - 1}")
    return spark.read.schema(df.schema).parquet(f"{at}/won").select(*df.columns) if step else rest


def keep_best(df: DataFrame, keys: Sequence[str], order: Sequence) -> DataFrame:
    """One record of each set of equivalent ones: the first in ``order``."""
    place = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    return df.withColumn("_place", place).where(F.col("_place") == 1).drop("_place")


def connected_groups(edges: DataFrame, a: str = "a", b: str = "b", folder: str | None = None) -> DataFrame:
    """(node, group): smallest node reachable, by least labels with pointer jumps; each round is written to a shared folder."""
    spark = edges.sparkSession
    at, step = stored.new_path(spark, "groups", folder), 0
    both = stored.write(edges.select(F.col(a).alias("node"), F.col(b).alias("near")).unionByName(edges.select(F.col(b).alias("node"), F.col(a).alias("near"))).distinct(), f"{at}/edges")
    labels = stored.write(both.groupBy("node").agg(F.least(F.min("node"), F.min("near")).alias("group")), f"{at}/labels-0")
    while True:
        step += 1
        pulled = both.join(labels.withColumnRenamed("node", "near"), "near").groupBy("node").agg(F.min("group").alias("pull"))
        hooked = labels.join(pulled, "node").select("node", "group", F.least("group", "pull").alias("to"))
        roots = labels.select(F.col("node").alias("to"), F.col("group").alias("root"))
        final = F.least("to", F.coalesce("root", "to"))
        following = stored.write(hooked.join(roots, "to", "left").select("node", final.alias("group"), (final != F.col("group")).alias("moved")), f"{at}/labels-{step}")
        labels = following.drop("moved")
        stored.remove(spark, f"{at}/labels-{step - 1}")
        if not following.where("moved").limit(1).count():
            stored.remove(spark, f"{at}/edges")
            return labels
