"""Resolving clusters that are not transitive, and the global schema of what results.

Input is ``member(cluster_id, attr)`` and ``near(a, b)``: the pairs within the tolerance. Output is
``parts(cluster_id, part_id, attr)``; an attribute may be in several parts of its cluster.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unischema.functions.lineage import cut


def conflicts(members: DataFrame, near: DataFrame) -> DataFrame:
    """``cluster_id, a, b`` with a < b: members of one cluster that are not within the tolerance."""
    x, y = members.alias("x"), members.alias("y")
    pairs = x.join(y, F.col("x.cluster_id") == F.col("y.cluster_id")).where("x.attr < y.attr").select(F.col("x.cluster_id").alias("cluster_id"), F.col("x.attr").alias("a"), F.col("y.attr").alias("b"))
    ok = near.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    return pairs.join(ok, ["a", "b"], "left_anti").select("cluster_id", "a", "b")


PARTS = "cluster_id string, part_id string, attr string"


def _cluster_rows(members: DataFrame, near: DataFrame) -> DataFrame:
    """``cluster_id, names, near``: each cluster of a bounded size as one row, with its pairs within the tolerance."""
    own = members.select("cluster_id", "attr").distinct()
    pairs = near.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    left, right = own.select("cluster_id", F.col("attr").alias("a")), own.select("cluster_id", F.col("attr").alias("b"))
    inside = pairs.join(left, "a").join(right, ["cluster_id", "b"]).groupBy("cluster_id").agg(F.collect_list(F.struct("a", "b")).alias("near"))
    return own.groupBy("cluster_id").agg(F.sort_array(F.collect_list("attr")).alias("names")).join(inside, "cluster_id", "left")


def _bits(names: list[str], near: list[dict] | None) -> list[int]:
    """For each name, the set of names within the tolerance, as bits."""
    place = {name: i for i, name in enumerate(names)}
    bits = [0] * len(names)
    for pair in near or []:
        i, j = place[pair["a"]], place[pair["b"]]
        bits[i] |= 1 << j
        bits[j] |= 1 << i
    return bits


def _places(bits: int) -> Iterator[int]:
    while bits:
        yield (bits & -bits).bit_length() - 1
        bits &= bits - 1


def _maximal(bits: list[int], most: int) -> list[int] | None:
    """All maximal sets of names that are pairwise within the tolerance; none if there are over ``most``.

    A published branching over candidates and excluded names, with the pivot that leaves fewest branches.
    """
    found, stack = [], [(0, (1 << len(bits)) - 1, 0)]
    while stack:
        part, open_, shut = stack.pop()
        if not open_ and not shut:
            found.append(part)
            if len(found) > most:
                return None
            continue
        pivot = max(_places(open_ | shut), key=lambda i: (open_ & bits[i]).bit_count())
        for i in _places(open_ & ~bits[pivot]):
            stack.append((part | 1 << i, open_ & bits[i], shut & bits[i]))
            open_ &= ~(1 << i)
            shut |= 1 << i
    return found


def _peeled(bits: list[int]) -> list[int]:
    """Disjoint sets: the name with most conflicts leaves (of several the last) until none has any; then again with those that left."""
    rest, out = (1 << len(bits)) - 1, []
    while rest:
        part = rest
        while True:
            clashes = [((part & ~bits[i] & ~(1 << i)).bit_count(), i) for i in _places(part)]
            worst = max(clashes)
            if not worst[0]:
                break
            part &= ~(1 << worst[1])
        out.append(part)
        rest &= ~part
    return out


def _solved(rows: DataFrame, solve, by_level: bool = False) -> DataFrame:
    """``cluster_id, part_id, attr`` by ``solve(bits)``; clusters that it gives up have one row without a part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: tuple[list, list, list] = ([], [], [])
            for row in batch.to_pylist():
                names, parts = row["names"], solve(_bits(row["names"], row["near"]))
                if parts is None:
                    for column, value in zip(out, (row["cluster_id"], None, None), strict=True):
                        column.append(value)
                for level, part in enumerate(parts or []):
                    held = [names[i] for i in _places(part)]
                    out[0].extend([row["cluster_id"]] * len(held))
                    out[1].extend([f"{row['cluster_id']}/{level}" if by_level else "|".join(held)] * len(held))
                    out[2].extend(held)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in out], ["cluster_id", "part_id", "attr"])

    return rows.mapInArrow(run, PARTS)


def _by_size(members: DataFrame, max_members: int) -> tuple[DataFrame, DataFrame]:
    """The members of clusters up to a size, and those of larger ones."""
    sizes = members.groupBy("cluster_id").agg(F.count_distinct("attr").alias("n"))
    large = cut(sizes.where(F.col("n") > max_members).select("cluster_id"))
    return members.join(large, "cluster_id", "left_anti"), members.join(large, "cluster_id", "left_semi")


def resolve_overlap(members: DataFrame, near: DataFrame, max_parts: int = 1000, near_half: DataFrame | None = None, max_members: int = 1000) -> DataFrame:
    """The two ends of a conflict part; everything else goes to both sides.

    Carried through, that makes of each cluster all its maximal sets without a conflict. Their number may
    grow exponentially, and the pairs with the square of a cluster; so a cluster is split as one row
    only up to ``max_members`` members and ``max_parts`` parts. Others are covered by balls of
    ``near_half``: pairs within half the tolerance. No part has a conflict and no member is lost either
    way. Without ``near_half`` every member is its own ball there, as pairs of ``near`` could bring a
    conflict into one part.
    """
    half = near.limit(0) if near_half is None else near_half
    small, large = _by_size(members, max_members)
    split = cut(_solved(_cluster_rows(small, near), lambda bits: _maximal(bits, max_parts)))
    over = large.unionByName(members.join(split.where("part_id IS NULL").select("cluster_id"), "cluster_id", "left_semi"))
    parts = split.where("part_id IS NOT NULL")
    over = cut(over.select("cluster_id", "attr"))
    return parts if over.isEmpty() else parts.unionByName(resolve_cover(over, half))


def resolve_cover(members: DataFrame, near_half: DataFrame) -> DataFrame:
    """Balls about centres of a maximal independent set: for clusters too large to split exactly.

    ``near_half`` holds pairs within half the tolerance; by the triangle inequality two members of a
    ball are within the whole. Each round a member becomes a centre if its priority is the least
    among the uncovered members near it.
    """
    pairs = near_half.select("a", "b").union(near_half.select("b", "a"))
    own = members.select("cluster_id", F.col("attr").alias("a"))
    near = cut(own.join(pairs, "a").join(members.select("cluster_id", F.col("attr").alias("b")), ["cluster_id", "b"]).select("cluster_id", "a", "b").distinct())
    open_ = cut(members.select("cluster_id", "attr").distinct())
    centres = None
    while not open_.isEmpty():
        ranked = open_.withColumn("p", F.xxhash64("attr"))
        rivals = near.join(ranked.select("cluster_id", F.col("attr").alias("b"), F.col("p").alias("pb")), ["cluster_id", "b"]).groupBy("cluster_id", "a").agg(F.min("pb").alias("least"))
        new = cut(ranked.join(rivals, (ranked["cluster_id"] == rivals["cluster_id"]) & (ranked["attr"] == rivals["a"]), "left").where("least IS NULL OR p < least").select(ranked["cluster_id"], "attr"))
        centres = new if centres is None else centres.unionByName(new)
        taken = new.unionByName(near.join(new.withColumnRenamed("attr", "b"), ["cluster_id", "b"]).select("cluster_id", F.col("a").alias("attr")))
        open_ = cut(open_.join(taken.distinct(), ["cluster_id", "attr"], "left_anti"))
    named = centres.select("cluster_id", F.col("attr").alias("part_id"))
    around = near.select("cluster_id", F.col("b").alias("part_id"), F.col("a").alias("attr"))
    balls = named.join(around, ["cluster_id", "part_id"]).unionByName(named.select("cluster_id", "part_id", F.col("part_id").alias("attr")))
    return balls.select("cluster_id", "part_id", "attr").distinct()


def resolve_dense(members: DataFrame, near: DataFrame, max_members: int = 1000, near_half: DataFrame | None = None) -> DataFrame:
    """Disjoint parts by peeling: the member with most conflicts leaves for a later part, until none is left.

    Clusters of over ``max_members`` members are covered by balls, as in ``resolve_overlap``.
    """
    small, large = _by_size(members, max_members)
    parts = _solved(_cluster_rows(small, near), _peeled, by_level=True)
    large = cut(large.select("cluster_id", "attr"))
    return parts if large.isEmpty() else parts.unionByName(resolve_cover(large, near.limit(0) if near_half is None else near_half))


def resolve_none(members: DataFrame) -> DataFrame:
    return members.select("cluster_id", F.col("cluster_id").alias("part_id"), "attr")


def conflict_counts(parts: DataFrame, near: DataFrame) -> DataFrame:
    """``n_parts, n_conflicts``: parts of a result, and pairs in one part that are not within the tolerance."""
    sets = parts.select(F.concat_ws("/", "cluster_id", "part_id").alias("cluster_id"), "attr")
    found = conflicts(sets, near).agg(F.count(F.lit(1)).alias("n_conflicts"))
    return sets.agg(F.count_distinct("cluster_id").alias("n_parts")).crossJoin(found)


def global_schema(parts: DataFrame, pooled: DataFrame) -> DataFrame:
    """``part_id, global_attr, size``: of each part the name in most schemas, then the shortest, then the last."""
    ranked = parts.join(pooled, "attr", "left").withColumn("n", F.coalesce("n_schemas", F.lit(0)))
    return ranked.groupBy("cluster_id", "part_id").agg(F.max_by("attr", F.struct("n", -F.length("attr"), "attr")).alias("global_attr"), F.count(F.lit(1)).alias("size"))


def mapping(schemas: DataFrame, parts: DataFrame, globals_: DataFrame) -> DataFrame:
    """``schema_id, attr, part_id, global_attr`` for every attribute of every schema."""
    return schemas.select("schema_id", "attr").distinct().join(parts, "attr").join(globals_.select("cluster_id", "part_id", "global_attr"), ["cluster_id", "part_id"]).select("schema_id", "attr", "part_id", "global_attr")


def coverage_violations(mapped: DataFrame, schemas: DataFrame, near: DataFrame) -> DataFrame:
    """Attributes without any global name within the tolerance; must be empty."""
    ok = near.select("a", "b").union(near.select("b", "a"))
    good = mapped.where("attr = global_attr").select("schema_id", "attr")
    close = mapped.join(ok, (mapped["attr"] == ok["a"]) & (mapped["global_attr"] == ok["b"])).select("schema_id", "attr")
    return schemas.select("schema_id", "attr").where("attr IS NOT NULL").distinct().join(good.union(close).distinct(), ["schema_id", "attr"], "left_anti")


def path_energy_pairs(paths: DataFrame, limit: int) -> DataFrame:
    """``a, b, energy``: pairs whose sum of squared path lengths over all paths is within ``limit``."""
    squared = paths.groupBy(F.col("start").alias("a"), F.col("end").alias("b")).agg(F.sum(F.col("len") * F.col("len")).cast("long").alias("energy"))
    return squared.where(F.col("energy") <= limit)


def tune_beta(run, grid: list[float]) -> float:
    """The least beta of a grid with the best score; ``run(beta)`` gives the score of one try."""
    scores = {beta: run(beta) for beta in sorted(grid)}
    return max(scores, key=lambda beta: (scores[beta], -beta))


def pair_score(parts: DataFrame, gold: DataFrame) -> DataFrame:
    """``recall, precision, f1`` of pairs of one part against ``gold(a, b)``, a < b; 0 where undefined."""
    x, y = parts.alias("x"), parts.alias("y")
    both = x.join(y, (F.col("x.cluster_id") == F.col("y.cluster_id")) & (F.col("x.part_id") == F.col("y.part_id")) & (F.col("x.attr") < F.col("y.attr")))
    found = both.select(F.col("x.attr").alias("a"), F.col("y.attr").alias("b"), F.lit(1).alias("f")).distinct()
    met = found.join(gold.select("a", "b", F.lit(1).alias("g")).distinct(), ["a", "b"], "full")
    counts = met.agg(F.count("f").alias("found"), F.count("g").alias("gold"), F.count_if(F.col("f").isNotNull() & F.col("g").isNotNull()).alias("common"))
    ratio = lambda n, d: F.coalesce(F.try_divide(F.col(n), F.col(d)), F.lit(0.0))
    scored = counts.select(ratio("common", "gold").alias("recall"), ratio("common", "found").alias("precision"))
    f1 = F.coalesce(F.try_divide(2 * F.col("recall") * F.col("precision"), F.col("recall") + F.col("precision")), F.lit(0.0))
    return scored.select(F.round("recall", 6).alias("recall"), F.round("precision", 6).alias("precision"), F.round(f1, 6).alias("f1"))
