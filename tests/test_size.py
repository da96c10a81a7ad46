"""Work that must not grow with the number of walks, pairs or hub neighbours."""

import itertools
import math

import pytest
from pyspark.sql import functions as F

from unischema.operators import baselines, concept, distance, inplace, knowledge, normalize, resolve
from unischema.plans import batch, experiment_queries, operator_queries  # noqa: F401
from unischema.plans.method_queries import QUERIES
from unischema.sources import fixtures, tables
from unischema.sources.fixtures import frame


def star_base(spark, hubs: int, rays: int):
    """Each ray under all hubs, as neighbour table."""
    rows = spark.range(rays).select(F.concat(F.lit("ray"), "id").alias("sub"), F.explode(F.array(*[F.lit(f"hub{i}") for i in range(hubs)])).alias("sup"))
    return knowledge.neighbour_table(rows).cache()


# F1


def test_counted_walks_have_the_energy_of_listed_ones(spark):
    h1 = star_base(spark, 3, 4)
    starts = frame(spark, ["hub0", "hub1", "ray0", "ray3"], "concept string")
    for longest, limit in ((1, 1), (4, 500)):
        walks = concept.expand_paths(concept.seed_paths(starts.withColumnRenamed("concept", "attr"), h1), h1, longest, dedup=False)
        listed = resolve.path_energy_pairs(walks, limit).join(starts.withColumnRenamed("concept", "b"), "b", "left_semi")
        want = sorted(tuple(r) for r in listed.select("a", "b", "energy").collect())
        assert sorted(tuple(r) for r in concept.walk_energy(starts, h1, longest, limit).collect()) == want


def test_walks_over_hubs_are_counted(spark):
    """3,000 rays under two hubs: 3,000 squared walks of four steps, none listed."""
    h1 = star_base(spark, 2, 3_000)
    found = concept.walk_energy(frame(spark, ["hub0", "hub1"], "concept string"), h1, 4, 10**6).collect()
    assert {tuple(r) for r in found} == {("hub0", "hub1", 4 * 3_000), ("hub1", "hub0", 4 * 3_000)}


# F2


def test_theta_pairs_are_counted_not_listed(spark, tmp_path):
    """45 billion pairs of one brand; ties, nulls and a brand without a pair in others."""
    odd = [("B", 1.0), ("B", 1.0), ("B", 2.0), ("B", float("nan")), ("B", None), ("C", 5.0), ("C", 5.0), (None, 1.0), (None, 2.0)]
    rows = spark.range(300_000).select(F.lit("A").alias("p_brand"), F.col("id").cast("double").alias("p_retailprice"))
    rows.unionByName(spark.createDataFrame(odd, "p_brand string, p_retailprice double")).write.parquet(str(tmp_path / "part.parquet"))
    found = {tuple(r) for r in QUERIES["op_join_theta"][0](spark, str(tmp_path)).collect()}
    assert found == {("A", 300_000 * 299_999 // 2), ("B", 5)}


# F4


def test_advised_thresholds(spark):
    """As by whole balls on a small base; hubs of 3,000 neighbours are not expanded from their rays."""
    h1 = knowledge.neighbour_table(frame(spark, [(x, y) for x, y in zip("abcdefg", "bcdefgh", strict=True)] + [("b", f"b{i}") for i in range(4)], "sub string, sup string")).cache()
    inputs = h1.select("concept").distinct().unionByName(frame(spark, ["absent"], "concept string"))
    for budget in (5,):
        sizes = {}
        for r in baselines.bruteforce_semantic(h1, 3).groupBy("a", "len").count().collect():
            sizes.setdefault(r["a"], {})[r["len"]] = r["count"]
        sizes["absent"] = {0: 1}
        want = set()
        for name, counts in sizes.items():
            n = [sum(c for length, c in counts.items() if length <= g) for g in range(4)]
            fit = [g for g in range(4) if n[g] <= budget]
            want |= {(name, fit[-1], n[fit[-1]])} if fit else set()
        assert {tuple(r) for r in batch.advise_gamma(inputs, h1, budget, 3).collect()} == want
    wide = star_base(spark, 2, 3_000)
    found = batch.advise_gamma(wide.select("concept").distinct(), wide, 500).groupBy("gamma", "n").count().collect()
    assert {tuple(r) for r in found} == {(0, 1, 2), (1, 3, 3_000)}


# F25


def test_words_of_every_document(spark):
    words = frame(spark, [(d, w) for d in (1, 2) for w in ("x", "y")] + [(1, "z")], "doc_id int, word string")
    found = {(r["a"], r["b"]): r["d"] for r in distance.cooccurrence_distance(words, everywhere=math.nan).collect()}
    assert math.isnan(found["x", "y"]) and found["x", "z"] == 1.0
    assert {r["d"] for r in distance.cooccurrence_distance(words).where("a = 'x' AND b = 'y'").collect()} == {0.0}


# F5, F8, F10, F12 to F14, F18, F24


def test_balls_of_many_starts_are_the_same(spark, monkeypatch):
    h1 = knowledge.neighbour_table(frame(spark, [(x, y) for x, y in zip("abcdefg", "bcdefgh", strict=True)] + [("b", f"b{i}") for i in range(4)], "sub string, sup string")).cache()
    inputs = h1.select("concept").distinct().unionByName(frame(spark, ["absent"], "concept string"))
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    want = rows(knowledge.k_hop(inputs, h1, 3))
    monkeypatch.setattr(knowledge, "MANY_STARTS", 1)
    monkeypatch.setattr(knowledge, "DEAL", 2)
    for plan in ("frontier", "binary", "meet"):
        assert rows(concept.related_concepts(inputs, h1, 3, plan)) == want
    assert rows(baselines.expand_by_single_hops(inputs.where("concept <> 'absent'"), h1, 3)) == [r for r in want if r[0] != "absent"]
    hop = knowledge.k_hop(inputs, h1, 2, max_degree=2)
    assert ("a", "b", 1) in rows(hop) and ("a", "c", 2) not in rows(hop)


# F26, F7


def test_recursive_query_has_no_row_limit(spark):
    """1,100 rays under one hub: over a million walks of two steps."""
    h1 = star_base(spark, 1, 1_100)
    found = concept.concept_join_recursive(spark, h1.select("concept").distinct(), h1, 2)
    assert found.count() == 1_101 * 1_101


# F3


def test_vector_pairs_by_blocks(spark, monkeypatch):
    """Across blocks, with copies; a vector of zeros, null or empty is near none (one of zeros was near all)."""
    import random

    dealer = random.Random(3)
    rows = [(i, [dealer.gauss(0, 1) for _ in range(8)]) for i in range(90)]
    rows += [(100 + i, rows[i % 3][1]) for i in range(9)] + [(200, [0.0] * 8), (201, None), (202, [])]
    monkeypatch.setattr(distance, "VECTORS", 20)
    monkeypatch.setattr(distance, "SLICE", 7)
    vectors = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    exact = {(r["a"], r["b"]): r["cosine"] for r in distance.edges_from_vectors(vectors.where("vec_id < 200"), 0.5).collect()}
    listed = distance.edges_from_vectors(vectors, 0.5, lsh_bucket=1.0).collect()
    found = {(r["a"], r["b"]): r["cosine"] for r in listed}
    assert len(found) == len(listed) and set(found) <= set(exact) and len(found) >= 0.98 * len(exact)
    assert all(abs(exact[p] - c) < 1e-6 for p, c in found.items())
    assert {(i, 100 + i) for i in range(3)} <= set(found)
    assert distance.edges_from_vectors(vectors.where("vec_id >= 200"), 0.5, lsh_bucket=1.0).isEmpty()


# F16 F17 F20 F22


def test_candidates_of_rare_grams_are_those_of_all_grams(spark, monkeypatch):
    """Both bounds, short and long words, repeated grams, blocks of one row; then 20,000 words of one common gram, whose 200 million pairs are not listed."""
    import random

    from unischema.operators import grams

    dealer = random.Random(7)
    words = {"".join(dealer.choice("aab") for _ in range(dealer.randint(1, 9))) for _ in range(120)} | {"aaaaaaaaaa", "abababab", "ééab", "aa"}
    p, other = (grams.gram_index(frame(spark, sorted(words), "attr string"), 3).cache() for _ in range(2))
    other = other.select("*")
    for block in (10_000, 1):
        monkeypatch.setattr(grams, "GRAM_BLOCK", block)
        for bound in ("max", "self"):
            want = sorted(tuple(r) for r in grams.gram_candidates(p, other, 3, 1, bound).select("a", "b", "shared").collect())
            assert want and sorted(tuple(r) for r in grams.gram_candidates(p, p, 3, 1, bound).select("a", "b", "shared").collect()) == want
    many = spark.range(20_000).select(F.concat(F.lit("abc"), F.translate(F.md5(F.col("id").cast("string")), "0123456789", "ghijklmnop")).alias("attr"))
    p = grams.gram_index(many, 3).cache()
    assert grams.gram_candidates(p, p, 3, 1).isEmpty()


# F6


def test_nested_loop_compares_near_lengths_in_many_tasks(spark):
    """As without the comparison of lengths and letters; the loop does not run in one task."""
    import random

    dealer = random.Random(11)
    words = sorted({"".join(dealer.choice("abé") for _ in range(dealer.randint(0, 5))) for _ in range(60)} | {"A!", "a!"})
    attrs = frame(spark, [*words, None], "attr string")
    for eps in (0, 1, 2):
        met = attrs.alias("x").crossJoin(attrs.alias("y")).where("x.attr < y.attr").where(F.levenshtein("x.attr", "y.attr") <= eps)
        want = sorted(tuple(r) for r in met.select("x.attr", "y.attr", F.levenshtein("x.attr", "y.attr")).collect())
        found = baselines.bruteforce_literal(attrs, eps)
        assert sorted(tuple(r) for r in found.collect()) == want
    assert found.rdd.getNumPartitions() >= 8


# F31


def test_bucket_addresses_of_a_table(spark, tmp_path):
    """The names come from the given table: those of the worked example, with their published addresses."""
    from unischema.plans import registry
    from unischema.sources import fixtures

    rows = [(n,) for n, _ in fixtures.BUCKET_NAMES] + [("Name",), (None,)]
    spark.createDataFrame(rows, "c_name string").write.parquet(str(tmp_path / "customer.parquet"))
    found = [tuple(r) for r in registry.QUERIES["bucket_address"](spark, str(tmp_path)).collect()]
    assert sorted(found) == sorted((n, a - 1_000_000, a) for n, a in fixtures.BUCKET_NAMES)


# F11


def exchanges_above_arrow(df) -> bool:
    """Whether pairs are exchanged after they are made in place, or not made in place at all."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return "MapInArrow" not in plan or "Exchange" in plan.split("MapInArrow")[0]


@pytest.mark.parametrize("step", [2_000_000, 3])
def test_cooccurrences_are_counted_in_place(spark, monkeypatch, step):
    """All pairs with their counts, no pair exchanged; a step of 3 counts names in parts. Nulls, a lone word, ``é``."""
    monkeypatch.setattr(inplace, "STEP", step)
    docs = {1: ["ox", "yak", "é", "ant"], 2: ["yak", "ox", "ox"], 3: ["é", "yak"], 4: ["lone"], 5: [None], 6: []}
    rows = [(d, w) for d, words in docs.items() for w in words]
    found = distance.cooccurrence_distance(spark.createDataFrame(rows, "doc_id long, word string"))
    assert not exchanges_above_arrow(found)
    sets = [set(words) - {None} for words in docs.values()]
    f = {w: sum(w in s for s in sets) for w in set().union(*sets)}
    want = {}
    for a, b in itertools.combinations(sorted(f), 2):
        if both := sum({a, b} <= s for s in sets):
            want[a, b] = (math.log(max(f[a], f[b])) - math.log(both)) / (math.log(5) - math.log(min(f[a], f[b])))
    got = [tuple(r) for r in found.collect()]
    assert len(got) == len(want) and all(abs(want[a, b] - d) < 1e-12 for a, b, d in got)


# F9


@pytest.mark.parametrize("lanes", [("mh", "hm"), ("mm",), ("mm", "mh")])
def test_pairs_of_halos_are_made_in_place(spark, lanes):
    """As by lanes, for clusters of several members, costs that differ, a far halo, nulls; no pair is exchanged."""
    h1 = star_base(spark, 2, 5)
    member = frame(spark, [("c1", "ray0"), ("c1", "hub1"), ("c2", "ray1"), ("c3", "far"), ("c4", "hub0"), (None, "ray2")], "cluster_id string, attr string")
    halo = frame(spark, [("c1", "hub0", 1), ("c2", "ray3", None), ("c2", "far", 2), ("c3", "ray3", -1), ("c4", "ray4", 3), ("c4", None, 0)], "cluster_id string, concept string, d_sem int")
    family = {"member": member, "halo": halo}
    for gamma, strict in ((0, False), (1, False), (2, False), (2, True)):
        found = concept.concept_match_pairs(family, h1, gamma, lanes, strict)
        want = {tuple(r)[:2] for r in concept.concept_matches(family, h1, gamma, lanes, strict).collect()}
        rows = [tuple(r) for r in found.collect()]
        assert not exchanges_above_arrow(found) and sorted(rows) == sorted(want)


# F15


def test_stored_balls_of_what_starts_reach(spark, tmp_path):
    """The same lookups as from the balls of all concepts, without the balls of hubs that no lookup needs."""
    sides = spark.range(3_000).selectExpr("concat('x', id) AS sub", "'farhub' AS sup")
    chain = [(f"n{i}", f"n{i + 1}") for i in range(6)] + [("n1", "m"), ("n6", "farhub")]
    h1 = knowledge.neighbour_table(frame(spark, chain, "sub string, sup string").unionByName(sides)).cache()
    starts = frame(spark, ["n0", "n0", "m", "absent"], "concept string")
    for gamma in (1, 2, 3):
        path = str(tmp_path / f"g{gamma}")
        knowledge.build_balls(h1, knowledge.hop_plan(gamma), path, 2, starts)
        balls = knowledge.read_balls(spark, path, knowledge.hop_plan(gamma))
        want = {tuple(r) for r in knowledge.k_hop(starts.distinct(), h1, gamma).collect()}
        found = [tuple(r) for r in knowledge.expand_by_plan(starts, balls, gamma).collect()]
        assert sorted(found) == sorted(want) and all(b.count() < 100 for b in balls.values())


# F27 F28 F30 F32 F33 F34 F35 F37


def test_catalog_is_read_from_rows(spark):
    """All queries on the catalog take it from here: every column with the values that its table's rows have."""
    found = {(r["schema_id"], r["attr"]): r["n_values"] for r in tables.catalog(spark, "/root/testdata/sf0.001").collect()}
    for name in tables.TABLES:
        own = tables.table(spark, "/root/testdata/sf0.001", name)
        want = own.agg(*[F.count(c).alias(c) for c in own.columns]).first().asDict()
        assert {c: found[name, c] for c in own.columns} == want and max(want.values()) > 0
    assert len(found) == sum(len(tables.table(spark, "/root/testdata/sf0.001", name).columns) for name in tables.TABLES)


def test_catalog_of_tables_without_rows(spark, tmp_path):
    for name in tables.TABLES:
        spark.createDataFrame([], "k long, v array<float>").write.parquet(str(tmp_path / f"{name}.parquet"))
    rows = [tuple(r) for r in tables.catalog(spark, str(tmp_path)).collect()]
    assert sorted(rows) == sorted((t, c, i, d, 0) for t in tables.TABLES for c, i, d in (("k", 1, "bigint"), ("v", 2, "array<float>")))


def trade_tables(spark, folder, parts) -> str:
    """A folder with tables of ``parts(p_partkey, p_name)`` and no other concepts."""
    columns = {
        "part": "p_partkey long, p_name string, p_brand string, p_type string",
        "customer": "c_custkey long, c_name string, c_nationkey int, c_mktsegment string",
        "supplier": "s_suppkey long, s_name string, s_nationkey int",
        "nation": "n_nationkey int, n_name string, n_regionkey int",
        "region": "r_regionkey int, r_name string",
    }
    for name, schema in columns.items():
        rows = [(k, n, "B", "T") for k, n in parts] if name == "part" else []
        spark.createDataFrame(rows, schema).write.parquet(f"{folder}/{name}.parquet")
    return str(folder)


# F29


def test_balls_of_part_names_come_from_the_table(spark, tmp_path):
    folder = trade_tables(spark, tmp_path, [(1, "red bolt"), (2, "red gear"), (3, "old gear"), (4, "red bolt"), (5, "odd")])
    found = {(r["a"], r["b"]): r["hops"] for r in QUERIES["ball4_minplus"][0](spark, folder).collect()}
    assert {b: d for (a, b), d in found.items() if a == "red bolt"} == {"red bolt": 0, "red": 1, "bolt": 1, "red gear": 2, "gear": 3, "old gear": 4}
    assert ("bolt", "old") not in found and not any("odd" in pair for pair in found)


def test_balls_of_the_worked_example(spark):
    found = {(r["a"], r["b"]): r["len"] for r in knowledge.ball_table(knowledge.neighbour_table(frame(spark, fixtures.PIE_EDGES, "sub string, sup string")), 4).collect()}
    want = {"American pies": 1, "Sweet pies": 1, "Key lime pie": 2, "pie": 2, "Natchitoches meat pie": 2, "Strawberry pie": 2, "Savoury pies": 3, "Tiropita": 4, "Blackberry pie": 0}
    assert {b: d for (a, b), d in found.items() if a == "Blackberry pie"} == want


# F36


def test_compounds_come_from_the_documents(spark, tmp_path):
    """``line`` and ``item`` are known words, ``rare`` is not; other languages do not count."""
    rows = [("en", "line item order " * 5), ("en", "lineitem orderlineitem rareline lineit"), ("de", "itemline"), ("en", None)]
    spark.createDataFrame([(i, t, g) for i, (g, t) in enumerate(rows)], "doc_id long, text string, lang string").write.parquet(str(tmp_path / "documents.parquet"))
    found = {tuple(r) for r in QUERIES["compound_cuts"][0](spark, str(tmp_path)).collect()}
    assert found == {("lineitem", "line item"), ("orderlineitem", "order line item")}


def test_compounds_of_the_vocabulary(spark):
    words = frame(spark, ["streetname", "orderlinenumber", "keykeykey", "nameless"], "word string")
    found = {tuple(r) for r in normalize.compound_cuts(words, frame(spark, fixtures.VOCABULARY, "word string"), 3).collect()}
    assert found == {("streetname", "street name"), ("orderlinenumber", "order line number"), ("keykeykey", "key key key")}


# F38


def test_conflicts_come_from_part_names(spark, tmp_path):
    """Two clusters of chained names, one of them without a conflict, and a name that shares no word."""
    folder = trade_tables(spark, tmp_path, [(1, "red bolt"), (2, "red gear"), (3, "old gear"), (4, "red bolt"), (5, "new rod"), (6, "new nut"), (7, "odd"), (8, None)])
    assert [tuple(r) for r in QUERIES["conflict_pairs"][0](spark, folder).collect()] == [("old gear", "old gear", "red bolt")]


def test_conflict_of_the_worked_chain(spark):
    near = frame(spark, [*fixtures.CHAIN, ("xa", "xj"), ("xi", "xb")], "a string, b string")
    members = frame(spark, [("c", x) for x in ("xa", "xi", "xj", "xb")], "cluster_id string, attr string")
    assert [tuple(r) for r in resolve.conflicts(members, near).collect()] == [("c", "xa", "xb")]
