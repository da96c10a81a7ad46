"""Resolving beyond its limits, verified and resolved arrivals, crash-safe state, hot grams, ranks."""

import random

import pytest
from pyspark.sql import functions as F

from unischema.config import DEFAULT
from unischema.operators import baselines, grams, knowledge, literal, resolve, verify
from unischema.plans import batch, incremental, workloads
from unischema.plans.incremental import State, StateStore
from unischema.sources.fixtures import frame


def stars(spark, n=10, rays=5):
    """Clusters of one centre with rays that are near the centre alone; half tolerance holds only at the centre of a pair."""
    member = [(f"c{i}", f"c{i}-{j}") for i in range(n) for j in range(rays + 1)]
    near = [(f"c{i}-0", f"c{i}-{j}") for i in range(n) for j in range(1, rays + 1)]
    half = [(f"c{i}-0", f"c{i}-1") for i in range(n)]
    make = lambda rows, schema: frame(spark, rows, schema)
    return make(member, "cluster_id string, attr string"), make(near, "a string, b string"), make(half, "a string, b string")


@pytest.mark.parametrize("limits", [{}, {"max_parts": 3}, {"max_members": 4}])
def test_no_conflict_is_left_whatever_the_limit(spark, limits):
    member, near, half = stars(spark)
    parts = resolve.resolve_overlap(member, near, near_half=half, **limits)
    counts = resolve.conflict_counts(parts, near).first()
    assert counts["n_conflicts"] == 0
    assert parts.select("attr").distinct().count() == member.count()


def test_resolving_splits_a_grown_cluster(spark):
    """Of a chain the ends part, the middle stays with both; ids of other clusters stay."""
    pie = knowledge.neighbour_table(frame(spark, [("a", "b"), ("b", "c"), ("c", "d"), ("x", "y")], "sub string, sup string")).cache()
    cfg = DEFAULT.but(gamma=1, eps_t=0, beta=1.0)
    state = State.empty(spark)
    for name in "abcx":
        state = incremental.integrate_one(state, frame(spark, [("s" + name, name)], "schema_id string, attr string"), pie, cfg)
    groups = sorted(sorted(r["m"]) for r in state.member.groupBy("cluster_id").agg(F.collect_set("attr").alias("m")).collect())
    near = frame(spark, [("a", "b"), ("b", "c")], "a string, b string")
    assert resolve.conflicts(state.member, near).isEmpty() and {n for g in groups for n in g} == set("abcx") and ["x"] in groups
    assert state.mapping.select("schema_id").distinct().count() == 4
    loose = State.empty(spark)
    for name in "abc":
        loose = incremental.integrate_one(loose, frame(spark, [("s", name)], "schema_id string, attr string"), pie, cfg.but(resolve="none"))
    assert not resolve.conflicts(loose.member, near).isEmpty() or loose.member.select("cluster_id").distinct().count() > 1


def test_arrivals_are_verified_by_values(spark):
    profile = spark.createDataFrame([("s", "turn", "integer", None, None, None, 5), ("t", "turns", "text", None, None, None, 5), ("u", "turnt", "integer", None, None, None, 0)], verify.PROFILE)
    cfg = DEFAULT.but(semantic=False)
    state = State.empty(spark)
    for schema, name in (("s", "turn"), ("t", "turns"), ("u", "turnt")):
        state = incremental.integrate_one(state, frame(spark, [(schema, name)], "schema_id string, attr string"), None, cfg, profile=profile)
    how = {(r["attr"], r["how"]) for r in state.mapping.collect()}
    assert ("turns", "new") in how and ("turnt", "literal") in how


def test_verification_after_joining_parts_denied_names(spark):
    schemas = frame(spark, [("s", "turn"), ("t", "turns"), ("u", "turnz")], "schema_id string, attr string")
    profile = spark.createDataFrame([("s", "turn", "integer", None, None, None, 5), ("t", "turns", "text", None, None, None, 5), ("u", "turnz", "text", None, None, None, 5)], verify.PROFILE)
    for stage in ("before", "after"):
        done = batch.integrate_batch(schemas, None, DEFAULT.but(semantic=False, verify_stage=stage), profile)
        together = {tuple(sorted(r["m"])) for r in done.parts.groupBy("cluster_id", "part_id").agg(F.collect_set("attr").alias("m")).collect()}
        assert together == {("turn",), ("turns", "turnz")}, stage


def test_affix_support_survives_odd_values(spark):
    table = spark.createDataFrame([("$10",)] * 0 + [(f"abc{i}",) for i in range(9)] + [("odd",), (None,)], "v string")
    found = {(r["side"], r["affix"], r["support"]) for r in verify.affix_support({"t": table}, 0.8).collect()}
    assert found == {("prefix", "abc", 0.9)} and verify.profile_table("t", table).first()["prefix"] is None


def test_containment_of_empty_and_missing(spark):
    tables = {"x": spark.createDataFrame([(1,), (2,)], "k int"), "y": spark.createDataFrame([(1,), (2,), (3,)], "k long"), "z": spark.createDataFrame([], "k int")}
    pairs = frame(spark, [("x", "k", "y", "k"), ("x", "k", "z", "k")], "schema_a string, a string, schema_b string, b string")
    got = {(r["schema_b"], r["verdict"]) for r in verify.rule_containment(pairs, verify.unpivot_values(tables)).collect()}
    assert got == {("y", "keep"), ("z", "unknown")}
    assert verify.rule_containment(pairs.limit(0), verify.unpivot_values(tables)).count() == 0


def test_state_survives_a_crash_at_any_moment(spark, tmp_path, monkeypatch):
    store = StateStore(spark, str(tmp_path / "state"))
    arrive = lambda n: frame(spark, [(f"s{n}", f"name{n}x")], "schema_id string, attr string")
    cfg = DEFAULT.but(semantic=False)
    store.apply(0, arrive(0), None, cfg)
    with monkeypatch.context() as broken:
        broken.setattr(store, "_point", lambda to: (_ for _ in ()).throw(OSError("killed")))
        with pytest.raises(OSError):
            store.apply(1, arrive(9), None, cfg)
    assert store.pointer()["version"] == 0 and {r["attr"] for r in store.load().member.collect()} == {"name0x"}
    store.apply(1, arrive(9), None, cfg)
    store.apply(1, arrive(7), None, cfg)  # a replayed batch changes nothing
    again = StateStore(spark, str(tmp_path / "state"))
    assert {r["attr"] for r in again.load().member.collect()} == {"name0x", "name9x"}
    delta = spark.read.parquet(str(tmp_path / "state" / "v=1" / "mapping"))
    assert [r["attr"] for r in delta.collect()] == ["name9x"]


def test_state_is_compacted_and_loses_split_clusters(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(StateStore, "COMPACT", 2)
    store = StateStore(spark, str(tmp_path / "state"))
    rows = lambda *ids: State(spark.createDataFrame([(i, i) for i in ids], incremental.MEMBER), spark.createDataFrame([], incremental.HALO), spark.createDataFrame([("s", i, i, "new") for i in ids], incremental.MAPPING))
    for batch_no, ids in enumerate((["a", "b"], ["a", "c"], ["a", "c", "d"], ["b", "d"])):
        store.save(rows(*ids), batch_no)
        kept = store.load()
        assert {r["attr"] for r in kept.member.collect()} == set(ids) == {r["attr"] for r in kept.mapping.collect()}
    assert store.pointer() == {"version": 3, "base": 2, "batch": 3}


@pytest.mark.parametrize("eps", [1, 2])
def test_hot_grams_lose_no_pair(spark, eps):
    rng = random.Random(3)
    names = sorted({f"Customer#{rng.randrange(400):06d}" for _ in range(120)} | {"Custome#000001", "x", "xy", "speed", "sped"})
    words = frame(spark, names, "attr string")
    want = {tuple(r) for r in baselines.bruteforce_literal(words, eps).collect()}
    for hot in (0, 3, 10**6):
        assert {tuple(r) for r in literal.literal_pairs(words, eps, hot=hot).collect()} == want
    looked = literal.literal_lookup(words, words, eps, 2, grams.gram_index(words, 2)).where("a < b")
    assert {tuple(r) for r in looked.collect()} == want


def test_ranks_have_no_gaps(spark):
    edges = [(f"n{i}", f"m{i % 7}") for i in range(60)]
    ranked = workloads.ranked(knowledge.neighbour_table(frame(spark, edges, "sub string, sup string"))).collect()
    assert [r["k"] for r in sorted(ranked, key=lambda r: (r["degree"], r["concept"]))] == list(range(1, len(ranked) + 1))


def test_binary_expansion_equals_frontier(spark):
    from unischema.operators.concept import related_concepts

    rng = random.Random(8)
    h1 = knowledge.neighbour_table(frame(spark, sorted({(f"n{rng.randrange(30)}", f"m{rng.randrange(30)}") for _ in range(50)}), "sub string, sup string")).cache()
    seeds = frame(spark, ["n1", "n2", "nowhere"], "concept string")
    for gamma in range(1, 6):
        assert {tuple(r) for r in related_concepts(seeds, h1, gamma, "binary").collect()} == {tuple(r) for r in related_concepts(seeds, h1, gamma).collect()}
