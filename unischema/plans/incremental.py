"""Incremental integration: arriving schemas against kept clusters and their halos.

The state is three tables, ``member``, ``halo`` and ``mapping``. A name that meets a member by the
literal join, or a halo concept within the thresholds, belongs to that cluster; all others open
clusters of their own with a halo from the knowledge base. Hits are verified by values and votes, and
clusters that grow are resolved. No path is expanded for a name that hits, unless its cluster has to be
looked at for conflicts.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.config import DEFAULT, Config
from unischema.functions.lineage import cut
from unischema.operators.clusters import HALO, least_halo
from unischema.operators.components import label_nodes
from unischema.operators.concept import ball_halo
from unischema.operators.distance import anchor
from unischema.operators.grams import gram_index
from unischema.operators.literal import literal_lookup
from unischema.operators.verify import verify_names
from unischema.plans.batch import integrate_batch, resolve_members
from unischema.sources.tables import pool_attributes

MEMBER = "cluster_id string, attr string"
MAPPING = "schema_id string, attr string, cluster_id string, how string"


@dataclass
class State:
    member: DataFrame
    halo: DataFrame
    mapping: DataFrame
    #: Stored grams of all members and halo concepts (more do no harm), and the q they were cut by.
    postings: DataFrame | None = None
    q: int | None = None

    def words(self) -> DataFrame:
        """Every name that an arrival may meet."""
        return self.member.select("attr").union(self.halo.select(F.col("concept").alias("attr"))).distinct()

    @staticmethod
    def empty(spark: SparkSession) -> State:
        return State(*(spark.createDataFrame([], s) for s in (MEMBER, HALO, MAPPING)))

    def cut(self) -> State:
        return State(cut(self.member), cut(self.halo), cut(self.mapping.distinct()))


def halo_hits(names: DataFrame, state: State, cfg: Config = DEFAULT) -> DataFrame:
    """``attr, cluster_id, how``: clusters that names hit, by member or by halo, without expansion.

    ``halo_rule='combined'`` asks an edit distance within ``eps_t`` of a halo concept at a semantic
    distance within ``gamma``; ``'subtract'`` takes the literal distance off ``eps_t`` instead. One lookup
    serves members and halos, on stored grams if the state has them.
    """
    with_halo = cfg.semantic and cfg.halo_policy != "none"
    kept = state.words() if with_halo else state.member.select("attr")
    stored = state.postings if state.q == cfg.q else None
    near = cut(literal_lookup(names, kept, cfg.eps_t if cfg.literal else 0, cfg.q, stored))
    how = F.when(F.col("d") == 0, "same").otherwise("literal")
    hits = near.join(state.member.withColumnRenamed("attr", "b"), "b").select(F.col("a").alias("attr"), "cluster_id", how.alias("how"))
    if with_halo:
        close = F.coalesce("d_sem", F.lit(0)) <= cfg.gamma if cfg.halo_rule == "combined" else F.col("d") <= (cfg.eps_t if cfg.literal else 0) - F.coalesce("d_lit", F.lit(0))
        met = near.join(state.halo.withColumnRenamed("concept", "b"), "b").where(close)
        hits = hits.unionByName(met.select(F.col("a").alias("attr"), "cluster_id", F.lit("halo").alias("how")))
    return hits.distinct()


def open_clusters(names: DataFrame, h1: DataFrame | None, cfg: Config = DEFAULT) -> tuple[DataFrame, DataFrame]:
    """Members and halos of new singletons: anchored in the knowledge base, then their neighbourhood."""
    member = names.select(F.col("attr").alias("cluster_id"), "attr").distinct()
    if h1 is None or not cfg.semantic:
        return member, names.sparkSession.createDataFrame([], HALO)
    concepts = h1.select("concept").union(h1.select("neighbour"))
    anchors = anchor(names, concepts, cfg.eps_t if cfg.literal else 0, cfg.anchor, cfg.q)
    return member, ball_halo(member, h1, cfg.gamma, cfg.halo_policy, cfg.halo_cap, anchors)


def verified_hits(hits: DataFrame, schema: DataFrame, state: State, profile: DataFrame | None, verdicts: DataFrame | None) -> DataFrame:
    """The hits ``attr, cluster_id, how`` that neither people nor values deny.

    ``verdicts(a, b)`` holds denied pairs (name, cluster). By ``profile`` a hit is denied if the values
    deny every pair of the name with another member of the cluster. The same name is never parted from itself.
    """
    if verdicts is not None:
        hits = hits.join(verdicts.select(F.col("a").alias("attr"), F.col("b").alias("cluster_id")), ["attr", "cluster_id"], "left_anti")
    if profile is None:
        return hits
    hits = cut(hits)
    asked = hits.select("attr", "cluster_id").join(state.member.withColumnRenamed("attr", "kept"), "cluster_id")
    pairs = cut(asked.select(F.col("attr").alias("a"), F.col("kept").alias("b"), "cluster_id").distinct())
    occurrences = schema.select("schema_id", "attr").unionByName(state.mapping.select("schema_id", "attr"))
    good = verify_names(pairs.where("a <> b"), occurrences, profile).select(F.col("a").alias("attr"), "cluster_id").distinct()
    same = pairs.where("a = b").select(F.col("a").alias("attr"), "cluster_id")
    return hits.join(good.union(same).distinct(), ["attr", "cluster_id"], "left_semi")


def resolve_touched(state: State, touched: DataFrame, h1: DataFrame | None, cfg: Config) -> State:
    """The state with the clusters in ``touched(cluster_id)`` resolved again.

    A cluster without conflict keeps its id; of one that is split each part is a cluster, named by its
    first member, or by all of them where two parts begin alike; its halo is that of its members.
    Clusters of one or two members have no conflict, as they met directly.
    """
    grown = state.member.join(touched.distinct(), "cluster_id", "left_semi").groupBy("cluster_id").agg(F.count_distinct("attr").alias("n")).where("n > 2").select("cluster_id")
    grown = cut(grown)
    if cfg.resolve == "none" or grown.isEmpty():
        return state
    members = cut(state.member.join(grown, "cluster_id", "left_semi").distinct())
    pooled = cut(pool_attributes(state.mapping.join(members.select("attr").distinct(), "attr", "left_semi")))
    parts = cut(resolve_members(members, pooled, h1, cfg))
    split = cut(parts.groupBy("cluster_id").agg(F.count_distinct("part_id").alias("n")).where("n > 1").select("cluster_id"))
    if split.isEmpty():
        return state
    pieces = parts.join(split, "cluster_id", "left_semi").select("cluster_id", F.concat_ws("/", "cluster_id", "part_id").alias("new_id"), "attr")
    pieces = cut(pieces)
    member = pieces.select(F.col("new_id").alias("cluster_id"), "attr").distinct()
    halo = state.halo.limit(0)
    if h1 is not None and cfg.semantic:
        concepts = h1.select("concept").union(h1.select("neighbour"))
        anchors = anchor(member, concepts, cfg.eps_t if cfg.literal else 0, cfg.anchor, cfg.q)
        halo = ball_halo(member, h1, cfg.gamma, cfg.halo_policy, cfg.halo_cap, anchors)
    moved = state.mapping.join(split, "cluster_id", "left_semi").join(pieces, ["cluster_id", "attr"]).select("schema_id", "attr", F.col("new_id").alias("cluster_id"), "how")
    rest = lambda df: df.join(split, "cluster_id", "left_anti")
    return State(rest(state.member).unionByName(member), rest(state.halo).unionByName(halo), rest(state.mapping).select("schema_id", "attr", "cluster_id", "how").unionByName(moved))


def integrate_one(state: State, schema: DataFrame, h1: DataFrame | None = None, cfg: Config = DEFAULT, verdicts: DataFrame | None = None, profile: DataFrame | None = None) -> State:
    """One arriving schema ``(schema_id, attr)``: join, verify, insert, resolve.

    Hits that ``verified_hits`` leaves are mapped, all other names are inserted. Names that hit are added
    to the members of every cluster they hit unless ``absorb`` is off; clusters that grew are resolved
    unless ``resolve`` is ``none``. New names of one schema that are within the literal threshold of each
    other open one cluster.
    """
    names = cut(schema.where("attr IS NOT NULL").select("attr").distinct())
    hits = cut(verified_hits(halo_hits(names, state, cfg), schema, state, profile, verdicts))
    fresh = cut(names.join(hits.select("attr").distinct(), "attr", "left_anti"))
    if fresh.isEmpty():
        member, halo = (schema.sparkSession.createDataFrame([], s) for s in (MEMBER, HALO))
    else:
        member, halo = _join_fresh(fresh, *open_clusters(fresh, h1, cfg), cfg)
    best = hits.groupBy("attr", "cluster_id").agg(F.min_by("how", F.when(F.col("how") == "same", 0).when(F.col("how") == "literal", 1).otherwise(2)).alias("how"))
    grown = state.member.unionByName(member)
    if cfg.absorb:
        grown = grown.unionByName(best.select("cluster_id", "attr"))
    mapped = schema.select("schema_id", "attr").distinct().join(best, "attr").unionByName(schema.select("schema_id", "attr").distinct().join(member, "attr").withColumn("how", F.lit("new")))
    done = State(grown.distinct(), least_halo(state.halo.unionByName(halo)), state.mapping.unionByName(mapped.select("schema_id", "attr", "cluster_id", "how"))).cut()
    if cfg.absorb and cfg.resolve != "none":
        touched = best.where("how <> 'same'").select("cluster_id").distinct()
        if not fresh.isEmpty():
            touched = touched.union(member.select("cluster_id").distinct())
        done = resolve_touched(done, touched, h1, cfg)
        return done.cut()
    return done


def _join_fresh(fresh: DataFrame, member: DataFrame, halo: DataFrame, cfg: Config) -> tuple[DataFrame, DataFrame]:
    from unischema.operators.literal import literal_pairs

    if not cfg.literal:
        return member, halo
    pairs = cut(literal_pairs(fresh, cfg.eps_t, cfg.q))
    if pairs.isEmpty():
        return member, halo
    labels = cut(label_nodes(fresh.select(F.col("attr").alias("node")), pairs))
    renamed = lambda df: df.join(labels, df["cluster_id"] == labels["node"]).withColumn("cluster_id", F.col("label")).drop("node", "label")
    return renamed(member).distinct(), least_halo(renamed(halo))


def batch_every_arrival(schemas: list[DataFrame], h1: DataFrame | None = None, cfg: Config = DEFAULT):
    """What incremental integration is compared with: the whole batch again after each arrival; the last result."""
    done = seen = None
    for schema in schemas:
        seen = schema if seen is None else seen.unionByName(schema)
        done = integrate_batch(seen, h1, cfg)
    return done


def integrate_many(state: State, schemas: list[DataFrame], h1: DataFrame | None = None, cfg: Config = DEFAULT) -> State:
    for schema in schemas:
        state = integrate_one(state, schema, h1, cfg)
    return state


class StateStore:
    """Versions of the state in a shared folder; a version counts once its pointer exists.

    Beside the three tables the grams of all names that may be met are kept, so that an arrival is looked
    up without cutting the whole state into grams again.

    Each version holds only the rows that are new in it and the clusters that it took away, so that
    saving costs what an arrival changes, not what was kept before. Every ``COMPACT`` versions the whole
    state is written once. Pointers are numbered files, made by renaming; the largest one counts. A
    crash at any moment leaves the last finished version as it was, and a batch id that a pointer
    already records is not applied again.
    """

    COMPACT = 64
    KEYS = {"member": ["cluster_id", "attr"], "halo": ["cluster_id", "concept", "d_lit", "d_sem"], "mapping": ["schema_id", "attr", "cluster_id", "how"]}

    def __init__(self, spark: SparkSession, path: str, q: int = DEFAULT.q) -> None:
        self.spark, self.path, self.q = spark, path.rstrip("/"), q
        self._fs = spark._jvm.org.apache.hadoop.fs.Path(self.path).getFileSystem(spark._jsc.hadoopConfiguration())

    def _file(self, name: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")

    def pointer(self) -> dict:
        """``version``, ``base`` (the last whole one) and ``batch`` of the largest finished version."""
        folder = self._file("pointers")
        names = [f.getPath().getName() for f in self._fs.listStatus(folder)] if self._fs.exists(folder) else []
        at = max((int(n.split(".")[0]) for n in names if n.endswith(".json")), default=None)
        if at is None:
            return {"version": -1, "base": 0, "batch": -1}
        return json.loads("".join(r[0] for r in self.spark.read.text(f"{self.path}/pointers/{at}.json").collect()))

    def load(self) -> State:
        at = self.pointer()
        if at["version"] < 0:
            return State.empty(self.spark)
        versions = range(at["base"], at["version"] + 1)
        read = lambda name: self.spark.read.option("basePath", self.path).parquet(*[f"{self.path}/v={v}/{name}" for v in versions]).withColumnRenamed("v", "since")
        gone = read("gone").groupBy("cluster_id").agg(F.max("since").alias("until"))
        tables = []
        for name, key in self.KEYS.items():
            rows = read(name).join(gone, "cluster_id", "left").where("until IS NULL OR since >= until").select(*key)
            tables.append(least_halo(rows) if name == "halo" else rows.distinct())
        return State(*tables, read("grams").select("attr", "len", "gram", "occ", "pos"), self.q)

    def save(self, state: State, batch: int) -> None:
        at = self.pointer()
        version = at["version"] + 1
        whole = at["version"] < 0 or version - at["base"] >= self.COMPACT
        before = State.empty(self.spark) if whole else self.load()
        gone = before.member.select("cluster_id").distinct().join(state.member.select("cluster_id").distinct(), "cluster_id", "left_anti")
        out = {"gone": gone}
        for name, key in self.KEYS.items():
            out[name] = getattr(state, name).select(*key).join(getattr(before, name).select(*key), key, "left_anti")
        added = State(out["member"], out["halo"], out["mapping"]).words()
        out["grams"] = gram_index(added.join(before.words(), "attr", "left_anti"), self.q)
        for name, rows in out.items():
            rows.write.mode("overwrite").parquet(f"{self.path}/v={version}/{name}")
        self._point({"version": version, "base": version if whole else at["base"], "batch": batch})

    def _point(self, to: dict) -> None:
        """A numbered pointer: written aside, then renamed, which is one step of the file system."""
        aside = self._file(f"pointers/{to['version']}.tmp")
        out = self._fs.create(aside, True)
        out.write(bytearray(json.dumps(to).encode()))
        out.close()
        self._fs.rename(aside, self._file(f"pointers/{to['version']}.json"))

    def apply(self, batch: int, schema: DataFrame, h1: DataFrame | None, cfg: Config) -> None:
        if batch <= self.pointer()["batch"]:
            return
        self.save(integrate_one(self.load(), schema, h1, cfg), batch)


__all__ = ["State", "StateStore", "batch_every_arrival", "halo_hits", "integrate_many", "integrate_one", "open_clusters", "resolve_touched", "verified_hits"]
