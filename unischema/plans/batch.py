"""Batch integration: pool, literal join, concept join, verification, resolving, global schema."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unischema.config import DEFAULT, Config
from unischema.functions.lineage import cut
from unischema.operators import resolve
from unischema.operators.components import label_nodes
from unischema.operators.concept import related_concepts, walk_energy
from unischema.operators.distance import anchor
from unischema.operators.knowledge import degree
from unischema.operators.literal import literal_pairs
from unischema.operators.verify import verify_names
from unischema.sources.tables import pool_attributes


@dataclass
class Integration:
    """What a batch gives: cluster members, parts, the global schema, the mapping, reached concepts."""

    members: DataFrame
    parts: DataFrame
    global_schema: DataFrame
    mapping: DataFrame
    pairs: DataFrame
    related: DataFrame | None


def _literal(pooled: DataFrame, cfg: Config) -> DataFrame:
    found = literal_pairs(pooled, cfg.eps_t, cfg.q, cfg.bound, cfg.verify)
    return found.select("a", "b", F.lit("literal").alias("kind"))


@dataclass
class Reach:
    """Anchors of the attributes and, from one expansion, the concepts around them: ``start, end, len``."""

    anchors: DataFrame
    paths: DataFrame

    def pairs(self, radius: int) -> DataFrame:
        """``a, b`` with a < b: attributes of which two anchors are within ``radius``."""
        ends = self.anchors.select(F.col("concept").alias("end"), F.col("attr").alias("y"))
        starts = self.anchors.select(F.col("concept").alias("start"), F.col("attr").alias("x"))
        met = self.paths.where(F.col("len") <= radius).join(ends, "end").join(starts, "start").where("x <> y")
        return met.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def reach_of(pooled: DataFrame, h1: DataFrame, cfg: Config) -> Reach:
    """The base is expanded once, to the largest radius that any later step asks for."""
    concepts = h1.select("concept").union(h1.select("neighbour"))
    anchors = cut(anchor(pooled, concepts, cfg.eps_t if cfg.literal else 0, cfg.anchor, cfg.q))
    radius = cfg.gamma if cfg.resolve == "none" else max(cfg.gamma, int(cfg.beta * cfg.gamma))
    return Reach(anchors, cut(related_concepts(anchors.select("concept").distinct(), h1, radius, cfg.expand_plan, cfg.max_degree)))


def _energy_pairs(reach: Reach, h1: DataFrame, limit: float, cfg: Config) -> DataFrame:
    """``a, b``: attributes whose anchors have a sum of squared lengths, over all paths, within ``limit``.

    One path of length l alone makes l * l, so no longer path than the root of the limit counts.
    """
    longest = int(limit**0.5)
    if longest == 0:
        return Reach(reach.anchors, reach.paths).pairs(0)
    kept = walk_energy(reach.anchors.select("concept"), h1, longest, int(limit), cfg.max_degree)
    own = reach.anchors.select("concept").distinct().select(F.col("concept").alias("start"), F.col("concept").alias("end"), F.lit(0).alias("len"))
    return Reach(reach.anchors, own.unionByName(kept.select(F.col("a").alias("start"), F.col("b").alias("end"), F.lit(0).alias("len")))).pairs(0)


def _tolerance(pooled: DataFrame, h1: DataFrame | None, reach: Reach | None, cfg: Config, half: bool = False) -> DataFrame:
    """Pairs within beta times a threshold (half of it for balls), by the distance that resolving uses."""
    share = cfg.beta / 2 if half else cfg.beta
    near = literal_pairs(pooled, int(share * cfg.eps_t), cfg.q).select("a", "b") if cfg.literal else pooled.select(F.col("attr").alias("a"), F.col("attr").alias("b")).limit(0)
    if reach is None or cfg.distance == "literal":
        return near
    # a sum of squares within a quarter of the limit means lengths within half of the tolerance
    wide = _energy_pairs(reach, h1, (share * cfg.gamma) ** 2, cfg) if cfg.distance == "energy" else reach.pairs(int(share * cfg.gamma))
    return near.unionByName(wide).distinct()


def resolve_members(members: DataFrame, pooled: DataFrame, h1: DataFrame | None, cfg: Config, reach: Reach | None = None, denied: DataFrame | None = None) -> DataFrame:
    """The parts of clusters; pairs in ``denied(a, b)`` count as beyond any tolerance."""
    if cfg.resolve == "none":
        return resolve.resolve_none(members)
    if reach is None and cfg.semantic and h1 is not None:
        reach = reach_of(pooled, h1, cfg)

    def near(half: bool = False) -> DataFrame:
        rows = _tolerance(pooled, h1, reach, cfg, half)
        return cut(rows if denied is None else rows.join(denied, ["a", "b"], "left_anti"))

    if cfg.resolve == "cover":
        return resolve.resolve_cover(members, near(half=True))
    if cfg.resolve == "dense":
        return resolve.resolve_dense(members, near(), cfg.max_members, near(half=True))
    return resolve.resolve_overlap(members, near(), cfg.max_parts, near(half=True), cfg.max_members)


def integrate_batch(schemas: DataFrame, h1: DataFrame | None = None, cfg: Config = DEFAULT, profile: DataFrame | None = None) -> Integration:
    """Integrate ``schemas(schema_id, attr)``; with a ``profile`` pairs are verified by values.

    A pair of names is denied if the schemas' values deny it in every combination that has values.
    Denied pairs are not joined, or, with ``verify_stage='after'``, parted again by resolving.
    """
    pooled = cut(pool_attributes(schemas))
    pairs, reach = None, None
    if cfg.literal:
        pairs = _literal(pooled, cfg)
    if cfg.semantic and h1 is not None:
        reach = reach_of(pooled, h1, cfg)
        more = reach.pairs(cfg.gamma).select("a", "b", F.lit("concept").alias("kind"))
        pairs = more if pairs is None else pairs.unionByName(more)
    pairs = cut(pairs.distinct())
    denied = None
    if profile is not None:
        kept = cut(verify_names(pairs, schemas, profile))
        if cfg.verify_stage == "before":
            pairs = kept
        else:
            denied = cut(pairs.select("a", "b").distinct().join(kept, ["a", "b"], "left_anti"))
    labels = label_nodes(pooled.select(F.col("attr").alias("node")), pairs.select("a", "b"))
    members = cut(labels.select(F.col("label").alias("cluster_id"), F.col("node").alias("attr")))
    parts = cut(resolve_members(members, pooled, h1, cfg, reach, denied))
    globals_ = resolve.global_schema(parts, pooled)
    related = None if reach is None else reach.paths.where(F.col("len") <= cfg.gamma)
    return Integration(members, parts, globals_, resolve.mapping(schemas, parts, globals_), pairs, related)


def rule_disagreements(pairs: DataFrame, concepts: DataFrame, h1: DataFrame, cfg: Config = DEFAULT) -> DataFrame:
    """Joined pairs that the two-case rule does not call related."""
    from unischema.operators.distance import related

    return related(pairs, concepts, h1, cfg.eps_t, cfg.gamma).where("NOT related").select("a", "b")


def advise_gamma(inputs: DataFrame, h1: DataFrame, budget: int, most: int = 4) -> DataFrame:
    """``concept, gamma, n``: for each input the largest threshold whose ball stays within ``budget``.

    A ball that holds a concept of ``budget`` neighbours or more is beyond the budget one step on, so it
    is never built: no ball expands more concepts than the budget, each to fewer neighbours than that.
    """
    degrees = cut(degree(h1).select(F.col("concept").alias("end"), "degree"))
    ball = cut(inputs.select(F.col("concept").alias("start"), F.col("concept").alias("end"), F.lit(0).alias("len")).distinct())
    found = None
    for gamma in range(most + 1):
        sizes = ball.join(degrees, "end", "left").groupBy("start").agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.max("degree"), F.lit(0)).alias("widest"))
        fits = cut(sizes.where(F.col("n") <= budget))
        rows = fits.select("start", F.lit(gamma).alias("gamma"), "n")
        found = rows if found is None else found.unionByName(rows)
        on = fits.where(F.col("widest") < budget).select(F.col("start").alias("concept"))
        if gamma == most or on.isEmpty():
            break
        kept = ball.join(on, ball["start"].eqNullSafe(on["concept"]), "left_semi")
        new = kept.where(F.col("len") == gamma).join(h1, F.col("end") == h1["concept"]).select("start", F.col("neighbour").alias("end")).distinct()
        ball = cut(kept.unionByName(new.join(kept, ["start", "end"], "left_anti").withColumn("len", F.lit(gamma + 1))))
    return found.groupBy(F.col("start").alias("concept")).agg(F.max("gamma").alias("gamma"), F.max("n").alias("n"))
