"""The knowledge base: relations, edges, neighbour tables, balls and their min-plus composition."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.operators import inplace
from unischema.sources.taxonomy import concept_id


def extract_relations(concepts: DataFrame, links: DataFrame, kinds: list[str] | None = None) -> DataFrame:
    """Six-field relations from ``concepts(id, name, type)`` and ``links(sub_id, super_id)``."""
    c = concepts.select("id", "name", "type")
    if kinds is not None:
        c = c.where(F.col("type").isin(kinds))
    sub = c.select(F.col("id").alias("sub_id"), F.col("name").alias("sub_name"), F.col("type").alias("sub_type"))
    sup = c.select(F.col("id").alias("super_id"), F.col("name").alias("super_name"), F.col("type").alias("super_type"))
    return links.select("sub_id", "super_id").join(sub, "sub_id").join(sup, "super_id").distinct().select("sub_id", "sub_name", "sub_type", "super_id", "super_name", "super_type")


def from_two_level(raw: DataFrame) -> DataFrame:
    """A two-level base (``type, topic`` with a ``domain``): topics below types, types below domains."""
    topic = raw.select(F.col("topic").alias("sub_name"), F.lit("topic").alias("sub_type"), F.col("type").alias("super_name"), F.lit("type").alias("super_type"))
    kind = raw.select(F.col("type").alias("sub_name"), F.lit("type").alias("sub_type"), F.col("domain").alias("super_name"), F.lit("domain").alias("super_type"))
    both = topic.unionByName(kind).where("sub_name IS NOT NULL AND super_name IS NOT NULL").distinct()
    return both.select(concept_id(F.col("sub_name")).alias("sub_id"), "sub_name", "sub_type", concept_id(F.col("super_name")).alias("super_id"), "super_name", "super_type")


def restrict(relations: DataFrame, types: list[str] | None = None, seeds: DataFrame | None = None, radius: int = 2) -> DataFrame:
    """Only relations of given types, or with both ends in the ball about ``seeds(concept)``."""
    if types is not None:
        relations = relations.where(F.col("sub_type").isin(types) & F.col("super_type").isin(types))
    if seeds is not None:
        ball = k_hop(seeds, neighbour_table(edges(relations)), radius).select("end").distinct()
        relations = relations.join(ball, relations["sub_name"] == ball["end"], "left_semi").join(ball, relations["super_name"] == ball["end"], "left_semi")
    return relations


def edges(relations: DataFrame) -> DataFrame:
    """``sub, sup``: distinct directed edges between different names."""
    return relations.select(F.col("sub_name").alias("sub"), F.col("super_name").alias("sup")).where("sub <> sup").distinct()


def neighbour_table(edge_set: DataFrame, directed: bool = False) -> DataFrame:
    """``concept, neighbour`` at one hop: both directions, or only from sub to super."""
    up = edge_set.select(F.col("sub").alias("concept"), F.col("sup").alias("neighbour"))
    return up if directed else up.unionByName(edge_set.select(F.col("sup").alias("concept"), F.col("sub").alias("neighbour"))).distinct()


def degree(h1: DataFrame) -> DataFrame:
    return h1.groupBy("concept").agg(F.count(F.lit(1)).alias("degree"))


def guarded(h1: DataFrame, max_degree: int | None) -> DataFrame:
    """The table without rows that lead on from hubs: they may be reached, but not expanded."""
    if max_degree is None:
        return h1
    return h1.join(degree(h1).where(F.col("degree") > max_degree).select("concept"), "concept", "left_anti")


#: From so many starts on, with at most so many edges, balls are built without an exchange of their rows.
MANY_STARTS, BROADCAST_EDGES = 1024, 500_000
#: Starts of one task then.
DEAL = 256


def deal(starts: DataFrame, h1: DataFrame) -> int | None:
    """The tasks to deal ``starts(concept)`` to, if they are many and the base is small enough to be everywhere.

    The balls of many starts outgrow both by far. Dealt by their starts, each step meets the base in
    place (``balls``), so that no row is exchanged or written between steps. The rows are the same.
    """
    n = starts.select("concept").distinct().count()
    if n < MANY_STARTS or h1.count() > BROADCAST_EDGES:
        return None
    return max(int(h1.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-n // DEAL))


def balls(starts: DataFrame, step: DataFrame, steps: list[str], tasks: int) -> DataFrame:
    """``start, end, len`` of ``starts(concept)`` by ``steps`` over the one-hop table ``step`` (see ``balls_in_place``)."""
    names = every_end(starts, step).where("concept IS NOT NULL").toArrow()["concept"].combine_chunks()
    number = lambda column: np.asarray(pc.index_in(column.combine_chunks(), names), dtype="int64")
    rows = step.where("concept IS NOT NULL AND neighbour IS NOT NULL").select("concept", "neighbour").distinct().toArrow()
    own, to = number(rows["concept"]), number(rows["neighbour"])
    order = np.argsort(own, kind="stable")
    begin = np.concatenate([[0], np.cumsum(np.bincount(own, minlength=len(names)))])
    first = number(starts.select("concept").where("concept IS NOT NULL").distinct().toArrow()["concept"])
    return inplace.balls_in_place(step.sparkSession, names, first, begin, to[order], steps, tasks)


def k_hop(seeds: DataFrame, h1: DataFrame, k: int, max_degree: int | None = None) -> DataFrame:
    """``start, end, len`` with the least length up to ``k``, starts at 0, from ``seeds(concept)``.

    Only concepts first reached in one round are expanded in the next; a round that reaches nothing
    new ends the loop.
    """
    step = guarded(h1, max_degree)
    tasks = deal(seeds, h1)
    if tasks is not None:
        null = seeds.select(F.col("concept").alias("start"), F.col("concept").alias("end"), F.lit(0).alias("len")).where("start IS NULL").distinct()
        return balls(seeds, step, ["new"] * k, tasks).unionByName(null)
    frontier = cut(seeds.select(F.col("concept").alias("start"), F.col("concept").alias("end")).distinct())
    reached = frontier.withColumn("len", F.lit(0))
    for length in range(1, k + 1):
        new = frontier.join(step, frontier["end"] == step["concept"]).select("start", F.col("neighbour").alias("end")).distinct()
        frontier = cut(new.join(reached, ["start", "end"], "left_anti"))
        if frontier.isEmpty():
            break
        reached = reached.unionByName(frontier.withColumn("len", F.lit(length)))
    return reached


def hop_table(h1: DataFrame, k: int) -> DataFrame:
    """``concept, neighbour`` pairs whose least path is exactly ``k`` long."""
    all_seeds = h1.select("concept").distinct()
    return k_hop(all_seeds, h1, k).where(F.col("len") == k).select(F.col("start").alias("concept"), F.col("end").alias("neighbour"))


def unit_ball(h1: DataFrame) -> DataFrame:
    """``a, b, len`` within one hop, each concept with itself at 0."""
    own = h1.select("concept").union(h1.select("neighbour")).distinct()
    return own.select(F.col("concept").alias("a"), F.col("concept").alias("b"), F.lit(0).alias("len")).unionByName(h1.select(F.col("concept").alias("a"), F.col("neighbour").alias("b"), F.lit(1).alias("len")))


def compose(x: DataFrame, y: DataFrame) -> DataFrame:
    """Min-plus product of two balls: the least sum over the meeting concept."""
    met = x.alias("x").join(y.alias("y"), F.col("x.b") == F.col("y.a"))
    return met.groupBy(F.col("x.a").alias("a"), F.col("y.b").alias("b")).agg(F.min(F.col("x.len") + F.col("y.len")).alias("len"))


def hop_plan(gamma: int) -> list[int]:
    """The powers of two that make up ``gamma``, largest first."""
    return [1 << k for k in range(gamma.bit_length() - 1, -1, -1) if gamma >> k & 1]


def ball_table(h1: DataFrame, k: int) -> DataFrame:
    """``a, b, len`` within ``k``, by doubling stored balls and composing the powers in ``k``."""
    if k == 0:
        return unit_ball(h1).where("len = 0")
    stored = {1: cut(unit_ball(h1))}
    tasks = deal(h1, h1)
    for power in range(1, k.bit_length()):
        half = stored[1 << (power - 1)]
        ball = compose(half, half) if power > 1 or tasks is None else ball_from(every_end(h1, h1), h1, 2, tasks)
        stored[1 << power] = ball if 1 << power == k else cut(ball)
    return reduce(compose, [stored[p] for p in hop_plan(k)])


def ball_from(starts: DataFrame, h1: DataFrame, power: int, tasks: int | None = None) -> DataFrame:
    """``a, b, len`` within ``power`` (a power of two) of ``starts(concept)`` alone, by doubling.

    The second half starts from what the first has reached, so hubs far from the starts are never squared.
    With ``tasks`` (see ``deal``) it starts from all concepts, which many starts reach anyway, and balls of
    one and two hops are made in place.
    """
    if tasks is not None and power <= 2:
        return balls(starts, h1, ["all"] * power, tasks).toDF("a", "b", "len")
    if power == 1:
        own = starts.select(F.col("concept").alias("a"), F.col("concept").alias("b"), F.lit(0).alias("len"))
        return own.unionByName(h1.join(starts, "concept").select(F.col("concept").alias("a"), F.col("neighbour").alias("b"), F.lit(1).alias("len")))
    near = ball_from(starts, h1, power // 2, tasks)
    if tasks is not None:
        return compose(near, ball_from(every_end(starts, h1), h1, power // 2, tasks))
    near = cut(near)
    return compose(near, ball_from(cut(near.select(F.col("b").alias("concept")).distinct()), h1, power // 2))


def every_end(starts: DataFrame, h1: DataFrame) -> DataFrame:
    """``concept``: all that a path from ``starts`` can be at."""
    return h1.select("concept").union(h1.select("neighbour")).union(starts.select("concept")).distinct()


def read_balls(spark, path: str, powers: list[int]) -> dict[int, DataFrame]:
    """What ``build_balls`` stored, by radius."""
    return {k: spark.read.parquet(f"{path}/k={k}") for k in powers}


def build_balls(h1: DataFrame, powers: list[int], path: str, buckets: int = 16, starts: DataFrame | None = None) -> None:
    """Chosen balls, built offline: one folder per radius, files clustered and sorted by start.

    Of all concepts, whose balls outgrow the base with the square of its hubs; or, with ``starts(concept)``,
    all that ``expand_by_plan`` looks up from them with these powers of two: the largest balls of the starts
    themselves, each next of what the one before has reached.
    """
    for k in sorted(powers, reverse=True):
        ball = ball_table(h1, k) if starts is None else ball_from(cut(starts.select("concept").distinct()), h1, k)
        ball.repartition(buckets, "a").sortWithinPartitions("a", "b").write.mode("overwrite").parquet(f"{path}/k={k}")
        if starts is not None:
            starts = read_balls(h1.sparkSession, path, [k])[k].select(F.col("b").alias("concept"))


def expand_by_plan(seeds: DataFrame, balls: dict[int, DataFrame], gamma: int) -> DataFrame:
    """``start, end, len`` from seeds by one join per power of two in ``gamma``."""
    rows = seeds.select(F.col("concept").alias("a"), F.col("concept").alias("b"), F.lit(0).alias("len")).distinct()
    for power in hop_plan(gamma):
        rows = compose(rows, balls[power])
    return rows.select(F.col("a").alias("start"), F.col("b").alias("end"), "len")


def path_sets(paths: DataFrame) -> DataFrame:
    """Paths grouped by their end: ``end, paths`` with sorted (start, len)."""
    return paths.groupBy("end").agg(F.sort_array(F.collect_set(F.struct("start", "len"))).alias("paths"))


def weighted_reach(seeds: DataFrame, h1: DataFrame, cap: float) -> DataFrame:
    """``start, end, len`` with the least sum of weights ``w`` up to ``cap``: rounds until nothing improves."""
    best = cut(seeds.select(F.col("concept").alias("start"), F.col("concept").alias("end"), F.lit(0.0).alias("len")).distinct())
    changed = best
    while not changed.isEmpty():
        new = changed.join(h1, changed["end"] == h1["concept"]).select("start", F.col("neighbour").alias("end"), (F.col("len") + F.col("w")).alias("len")).where(F.col("len") <= cap)
        new = new.groupBy("start", "end").agg(F.min("len").alias("len"))
        old = best.select("start", "end", F.col("len").alias("old"))
        changed = cut(new.join(old, ["start", "end"], "left").where("old IS NULL OR len < old").select("start", "end", "len"))
        best = cut(best.unionByName(changed).groupBy("start", "end").agg(F.min("len").alias("len")))
    return best
