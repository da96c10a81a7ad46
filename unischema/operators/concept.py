"""The concept join: bounded path expansion over the knowledge base, match lanes, merge."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.operators import inplace
from unischema.operators.clusters import least_halo, merge_all
from unischema.operators.knowledge import ball_from, balls, compose, deal, every_end, guarded, hop_plan, k_hop, unit_ball


def seed_paths(members: DataFrame, h1: DataFrame, anchors: DataFrame | None = None) -> DataFrame:
    """One-hop paths of ``members(attr)``; misspelt names start from their anchors."""
    starts = members.select("attr").distinct()
    starts = starts.select(F.col("attr").alias("concept")) if anchors is None else starts.join(anchors, "attr").select("concept").distinct()
    return starts.join(h1, "concept").select(F.col("concept").alias("start"), F.col("neighbour").alias("end"), F.lit(1).alias("len"))


def expand_paths(paths: DataFrame, h1: DataFrame, gamma: int, dedup: bool = True, max_degree: int | None = None) -> DataFrame:
    """``gamma - 1`` more rounds. With ``dedup`` each (start, end) keeps its least length and only new
    ends go on; without it every walk that does not turn back at once or pass its start is kept."""
    step = guarded(h1, max_degree)
    if dedup:
        frontier = cut(paths.groupBy("start", "end").agg(F.min("len").alias("len")).where("start <> end"))
        reached = frontier
        for length in range(2, gamma + 1):
            new = frontier.join(step, frontier["end"] == step["concept"]).select("start", F.col("neighbour").alias("end")).where("start <> end").distinct()
            frontier = cut(new.join(reached, ["start", "end"], "left_anti").withColumn("len", F.lit(length)))
            if frontier.isEmpty():
                break
            reached = reached.unionByName(frontier)
        return reached
    walks = cut(paths.select("start", F.col("start").alias("before"), "end", "len").where("len = 1"))
    found = walks
    for length in range(2, gamma + 1):
        met = walks.join(step, walks["end"] == step["concept"]).where("neighbour <> before AND neighbour <> start")
        walks = cut(met.select("start", F.col("end").alias("before"), F.col("neighbour").alias("end"), F.lit(length).alias("len")))
        found = found.unionByName(walks)
    return found.select("start", "end", "len")


def walk_energy(starts: DataFrame, h1: DataFrame, longest: int, limit: int, max_degree: int | None = None) -> DataFrame:
    """``a, b, energy``: pairs of ``starts(concept)`` whose sum of squared lengths over all walks of up to
    ``longest`` steps is within ``limit``; walks as in ``expand_paths`` without ``dedup``.

    Walks are counted by start and last step, not listed: onto a next step go all that have come to its
    begin, but for those that would turn back. The last step only leads to starts.
    """
    own = cut(starts.select("concept").distinct())
    step = guarded(h1, max_degree)
    to_starts = lambda rows: rows.join(own.select(F.col("concept").alias("neighbour")), "neighbour", "left_semi").select("concept", "neighbour")
    first = lambda rows: own.join(rows, "concept").select(F.col("concept").alias("start"), F.col("concept").alias("before"), F.col("neighbour").alias("end"), F.lit(1).cast("decimal(38,0)").alias("n"))

    def onward(rows: DataFrame) -> DataFrame:
        come = walks.groupBy("start", "end").agg(F.sum("n").alias("n"))
        gone = come.join(rows, come["end"] == rows["concept"]).where("neighbour <> start").select("start", F.col("end").alias("before"), F.col("neighbour").alias("end"), "n")
        back = walks.select("start", F.col("end").alias("before"), F.col("before").alias("end"), F.col("n").alias("back"))
        left = gone.join(back, ["start", "before", "end"], "left").withColumn("n", F.col("n") - F.coalesce("back", F.lit(0)))
        return left.where("n > 0").select("start", "before", "end", F.col("n").cast("decimal(38,0)").alias("n"))

    found, walks = first(to_starts(h1)).withColumn("len", F.lit(1)), cut(first(h1))
    for length in range(2, longest + 1):
        found = found.unionByName(onward(to_starts(step)).withColumn("len", F.lit(length)))
        if length < longest:
            walks = cut(onward(step))
    summed = found.groupBy(F.col("start").alias("a"), F.col("end").alias("b")).agg(F.sum(F.col("n") * F.col("len") * F.col("len")).alias("energy"))
    return summed.where(F.col("energy") <= limit).withColumn("energy", F.col("energy").cast("long"))


def related_concepts(inputs: DataFrame, h1: DataFrame, gamma: int, plan: str = "frontier", max_degree: int | None = None) -> DataFrame:
    """``start, end, len``: all concepts within ``gamma`` of ``inputs(concept)``, inputs at 0.

    ``plan``: ``frontier`` (semi-naive rounds), ``binary`` (balls of the powers of two in ``gamma``, made of
    what is reachable), or ``meet`` (two half-balls).
    """
    if plan == "binary":
        step, tasks = guarded(h1, max_degree), deal(inputs, h1)
        if tasks is not None and gamma <= 3:
            # the ball of two hops is the product of those of one, and meets that of one
            return balls(inputs, step, ["all"] * sum(hop_plan(gamma)), tasks)
        if tasks is not None:
            first, *others = hop_plan(gamma)
            rows = ball_from(inputs.select("concept").distinct(), step, first, tasks)
            for power in others:
                rows = compose(rows, ball_from(every_end(inputs, step), step, power, tasks))
            return rows.select(F.col("a").alias("start"), F.col("b").alias("end"), "len")
        rows = inputs.select(F.col("concept").alias("a"), F.col("concept").alias("b"), F.lit(0).alias("len")).distinct()
        for power in hop_plan(gamma):
            rows = cut(rows)
            rows = compose(rows, ball_from(cut(rows.select(F.col("b").alias("concept")).distinct()), step, power))
        return rows.select(F.col("a").alias("start"), F.col("b").alias("end"), "len")
    if plan == "meet":
        tasks = deal(inputs, h1)
        if tasks is not None and gamma // 2 <= 1:
            # half-balls of the starts meet those of one hop
            return balls(inputs, guarded(h1, max_degree), ["new"] * (gamma - gamma // 2) + ["all"] * (gamma // 2), tasks)
        near = k_hop(inputs, h1, gamma - gamma // 2, max_degree).select(F.col("start").alias("a"), F.col("end").alias("b"), "len")
        ends = near.select(F.col("b").alias("concept")).distinct() if tasks is None else every_end(inputs, h1)
        far = k_hop(ends, h1, gamma // 2, max_degree).select(F.col("start").alias("a"), F.col("end").alias("b"), "len")
        return compose(near, far).select(F.col("a").alias("start"), F.col("b").alias("end"), "len")
    return k_hop(inputs, h1, gamma, max_degree)


def concept_pairs(concepts: DataFrame, h1: DataFrame, gamma: int, mode: str = "frontier", max_degree: int | None = None) -> DataFrame:
    """``a, b, d`` with a < b of given ``concepts(concept)`` within ``gamma`` hops.

    Concepts of over ``max_degree`` neighbours are reached but not expanded. ``mode='meet'`` lets balls of half the radius meet: no ball of the whole radius is built.
    """
    if mode == "meet":
        half, rest = gamma // 2, gamma - gamma // 2
        x = k_hop(concepts, h1, rest, max_degree).alias("x")
        y = k_hop(concepts, h1, half, max_degree).alias("y")
        met = x.join(y, F.col("x.end") == F.col("y.end")).where(F.col("x.start") != F.col("y.start"))
        return met.groupBy(F.least("x.start", "y.start").alias("a"), F.greatest("x.start", "y.start").alias("b")).agg(F.min(F.col("x.len") + F.col("y.len")).alias("d"))
    reach = k_hop(concepts, h1, gamma, max_degree)
    own = concepts.select(F.col("concept").alias("end")).distinct()
    return reach.join(own, "end", "left_semi").where("start < end").select(F.col("start").alias("a"), F.col("end").alias("b"), F.col("len").alias("d"))


def concept_matches(family: dict[str, DataFrame], h1: DataFrame, gamma: int, lanes: tuple[str, ...] = ("mm", "mh", "hm"), strict_halo: bool = False, max_degree: int | None = None) -> DataFrame:
    """``a, b, lane``: pairs of cluster ids whose members, or members and halos, are within ``gamma``."""
    member = family["member"].select("cluster_id", "attr")
    paths = k_hop(member.select(F.col("attr").alias("concept")), h1, gamma, max_degree)
    paths = cut(paths.join(member.select(F.col("attr").alias("start"), F.col("cluster_id").alias("from_id")), "start"))
    found = None
    if "mm" in lanes:
        ends = member.select(F.col("attr").alias("end"), F.col("cluster_id").alias("to_id"))
        found = paths.join(ends, "end").select("from_id", "to_id", F.lit("mm").alias("lane"))
    if "mh" in lanes or "hm" in lanes:
        halo = family["halo"].select(F.col("concept").alias("end"), F.col("cluster_id").alias("to_id"), F.coalesce("d_sem", F.lit(0)).alias("d_sem"))
        total = F.col("len") + F.col("d_sem")
        met = paths.join(halo, "end").where(total < gamma if strict_halo else total <= gamma)
        for lane in ("mh", "hm"):
            if lane in lanes:
                ids = ("from_id", "to_id") if lane == "mh" else ("to_id", "from_id")
                more = met.select(F.col(ids[0]).alias("from_id"), F.col(ids[1]).alias("to_id"), F.lit(lane).alias("lane"))
                found = more if found is None else found.unionByName(more)
    return found.where("from_id <> to_id").select(F.least("from_id", "to_id").alias("a"), F.greatest("from_id", "to_id").alias("b"), "lane").distinct()


def concept_match_pairs(family: dict[str, DataFrame], h1: DataFrame, gamma: int, lanes: tuple[str, ...] = ("mm", "mh", "hm"), strict_halo: bool = False, max_degree: int | None = None) -> DataFrame:
    """``a, b``: the pairs of ``concept_matches`` whatever their lanes, which may be nearly all pairs of a base.

    Up to ``inplace.ROWS`` rows of paths and halos they are made in place, without an exchange of pairs.
    """
    member = family["member"].select("cluster_id", "attr").where("cluster_id IS NOT NULL")
    paths = k_hop(member.select(F.col("attr").alias("concept")), h1, gamma, max_degree)
    paths = cut(paths.join(member.select(F.col("attr").alias("start"), F.col("cluster_id").alias("id")), "start").select("id", F.col("end").alias("at"), F.col("len").cast("long").alias("cost")))
    targets = []
    if "mm" in lanes:
        targets.append(member.select(F.col("cluster_id").alias("id"), F.col("attr").alias("at"), F.lit(0).cast("long").alias("cost")))
    if "mh" in lanes or "hm" in lanes:
        near = F.coalesce("d_sem", F.lit(0)).cast("long") + (1 if strict_halo else 0)
        targets.append(family["halo"].where("cluster_id IS NOT NULL").select(F.col("cluster_id").alias("id"), F.col("concept").alias("at"), near.alias("cost")))
    met = cut(reduce(DataFrame.unionByName, targets).where("at IS NOT NULL"))
    if paths.count() + met.count() > inplace.ROWS:
        return concept_matches(family, h1, gamma, lanes, strict_halo, max_degree).select("a", "b").distinct()
    one, other = paths.toArrow(), met.toArrow()
    column = lambda name: pa.concat_arrays([one[name].combine_chunks(), other[name].combine_chunks()])
    ids, ats, cost = column("id"), column("at"), np.asarray(column("cost"), dtype="int64")
    names, places = ids.unique().sort(), ats.unique()
    number, at = np.asarray(pc.index_in(ids, names), dtype="int64"), np.asarray(pc.index_in(ats, places), dtype="int64")
    # a path of either name of a pair may lead to what the other has: both ways meet at places of their own
    n, least, width = one.num_rows, int(cost.min(initial=0)), int(cost.max(initial=0) - cost.min(initial=0)) + 1
    side = np.concatenate([np.zeros(n, "int64"), np.ones(len(number) - n, "int64")])
    key = (2 * at + 1 - side) * width + cost - least
    order = np.argsort(key, kind="stable")
    first = (2 * at + side) * width
    starts = np.searchsorted(key[order], first)
    ends = np.searchsorted(key[order], first + np.clip(gamma - cost - least, -1, width - 1), "right")
    kind = family["member"].schema["cluster_id"].dataType.simpleString()
    return inplace.pairs_in_place(h1.sparkSession, names, number, starts, np.maximum(ends, starts), number[order], f"a {kind}, b {kind}")


def ball_halo(members: DataFrame, h1: DataFrame, gamma: int, policy: str = "ball", cap: int = 16, anchors: DataFrame | None = None) -> DataFrame:
    """Halos of ``members(cluster_id, attr)``: whole balls, a few hubs at one hop, or nothing."""
    from pyspark.sql import Window

    from unischema.operators.knowledge import degree

    start = members.select("cluster_id", F.col("attr").alias("concept"), F.lit(0).alias("d_lit"))
    if anchors is not None:
        start = members.join(anchors, "attr").select("cluster_id", "concept", F.col("d_lit").cast("int"))
    if policy == "none":
        return members.sparkSession.createDataFrame([], "cluster_id string, concept string, d_lit int, d_sem int")
    if policy == "top_degree":
        near = start.join(h1, "concept").join(degree(h1).withColumnRenamed("concept", "neighbour"), "neighbour")
        order = Window.partitionBy("cluster_id", "concept").orderBy(F.col("degree").desc(), "neighbour")
        top = near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= cap)
        rows = top.select("cluster_id", F.col("neighbour").alias("concept"), "d_lit", F.lit(1).alias("d_sem"))
    else:
        reach = k_hop(start.select("concept"), h1, gamma)
        rows = start.join(reach, start["concept"] == reach["start"]).select("cluster_id", F.col("end").alias("concept"), "d_lit", F.col("len").alias("d_sem"))
    return least_halo(rows)


def concept_join(family: dict[str, DataFrame], h1: DataFrame, gamma: int, lanes: tuple[str, ...] = ("mm",), max_degree: int | None = None) -> dict[str, DataFrame]:
    """Clusters that share a concept within ``gamma`` merged; halos by least distance."""
    return merge_all(concept_matches(family, h1, gamma, lanes, max_degree=max_degree), family)


def concept_join_recursive(spark: SparkSession, inputs: DataFrame, h1: DataFrame, gamma: int) -> DataFrame:
    """The logical form, a bounded recursive query: ``start, end, len`` with least lengths.

    From many inputs (see ``deal``) names are numbered, and the last step of all walks is an array of neighbours
    that meets the walks of its start in place: walks of ``gamma`` steps are neither exchanged nor written.
    """
    tasks = deal(inputs, h1) if gamma else None
    if tasks is None:
        inputs.createOrReplaceTempView("unischema_inputs")
        h1.createOrReplaceTempView("unischema_h1")
        return spark.sql(f"""
          WITH RECURSIVE walk(start, node, len) AS (
            SELECT DISTINCT concept, concept, 0 FROM unischema_inputs
            UNION ALL
            SELECT walk.start, h.neighbour, walk.len + 1 FROM walk JOIN unischema_h1 h ON walk.node = h.concept WHERE walk.len < {int(gamma)}
          )
          SELECT start, node AS end, min(len) AS len FROM (SELECT * FROM walk LIMIT ALL) GROUP BY start, node
        """)
    ids = cut(every_end(inputs, h1).withColumn("id", F.monotonically_increasing_id()))
    numbers = lambda old, new: F.broadcast(ids.select(F.col("concept").alias(f"{old}_name"), F.col("id").alias(new)))
    number = lambda rows, old, new: rows.join(numbers(old, new), F.col(old).eqNullSafe(F.col(f"{old}_name"))).drop(old, f"{old}_name")
    cut(number(inputs.select(F.col("concept").alias("name")).distinct(), "name", "concept")).createOrReplaceTempView("unischema_inputs")
    rows = h1.where("concept IS NOT NULL").select(F.col("concept").alias("x"), F.col("neighbour").alias("y")).distinct()
    steps = cut(number(number(rows, "x", "concept"), "y", "neighbour"))
    steps.createOrReplaceTempView("unischema_h1")
    cut(steps.groupBy("concept").agg(F.collect_list("neighbour").alias("neighbours"))).createOrReplaceTempView("unischema_last")
    ids.createOrReplaceTempView("unischema_ids")
    at = [f"collect_set(node) FILTER (WHERE len = {n}) AS n{n}" for n in range(gamma)]
    nearer = lambda n: "concat(" + ", ".join(f"n{i}" for i in range(n)) + ")"
    levels = ["struct(n0 AS nodes, 0 AS len)", *(f"struct(array_except(n{n}, {nearer(n)}) AS nodes, {n} AS len)" for n in range(1, gamma + 1))]
    return spark.sql(f"""
      WITH RECURSIVE walk(start, node, len) AS (
        SELECT concept, concept, 0 FROM unischema_inputs
        UNION ALL
        SELECT walk.start, h.neighbour, walk.len + 1 FROM walk JOIN unischema_h1 h ON walk.node = h.concept WHERE walk.len < {int(gamma) - 1}
      ),
      dealt AS (SELECT /*+ REPARTITION({tasks}, start) */ * FROM (SELECT * FROM walk LIMIT ALL)),
      whole AS (
        SELECT /*+ BROADCAST(l) */ start, {", ".join(at)}, flatten(collect_list(neighbours)) AS n{int(gamma)}
        FROM dealt LEFT JOIN unischema_last l ON CASE WHEN len = {int(gamma) - 1} THEN node END = l.concept GROUP BY start
      ),
      least AS (SELECT start, inline(array({", ".join(levels)})) FROM whole),
      named AS (SELECT /*+ BROADCAST(i) */ i.concept AS start, nodes, len FROM least JOIN unischema_ids i ON least.start = i.id),
      ends AS (SELECT start, explode(nodes) AS node, len FROM named)
      SELECT /*+ BROADCAST(i) */ start, i.concept AS end, len FROM ends JOIN unischema_ids i ON ends.node = i.id
    """)


__all__ = ["ball_halo", "concept_join", "concept_join_recursive", "concept_match_pairs", "concept_matches", "concept_pairs", "expand_paths", "related_concepts", "seed_paths", "unit_ball", "walk_energy"]
