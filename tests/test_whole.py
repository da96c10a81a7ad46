"""Queries take their whole input, not a part of it."""

import math
import re
from re import _parser

import pytest

from unischema.operators import baselines, distance, resolve
from unischema.plans import integration_queries, registry
from unischema.plans.method_queries import _concepts, _h1, _part_names
from unischema.sources import fixtures, tables
from unischema.sources.fixtures import frame

SF = "/root/testdata/sf0.001"


def values(df, name):
    return {r[0] for r in df.select(name).distinct().collect()}


@pytest.mark.parametrize(("query", "column"), [("expand_frontier_g3_all", "start_concept"), ("related_concepts_g2_all", "start_concept"), ("advise_gamma_all", "concept"), ("halo_top_degree_all", "cluster_id")])
def test_expansion_starts_at_every_concept(spark, query, column):
    assert values(registry.QUERIES[query](spark, SF), column) == values(_concepts(_h1(spark, SF)), "concept")


@pytest.mark.parametrize(("query", "column"), [("semantic_distance_all", "b"), ("batch_taxonomy_all", "attr"), ("batch_all_overlap", "attr")])
def test_names_are_all_integrated(spark, query, column):
    assert values(registry.QUERIES[query](spark, SF), column) == values(_part_names(spark, SF), "concept")


@pytest.mark.parametrize("query", ["incremental_policy_none", "incremental_policy_none_all"])
def test_policies_take_all_arrivals(spark, monkeypatch, query):
    seen = []
    monkeypatch.setattr(integration_queries.incremental, "integrate_many", lambda state, arrivals, *_: seen.extend(r["attr"] for a in arrivals for r in a.collect()) or state)
    registry.QUERIES[query](spark, SF)
    assert len(set(seen)) == (_part_names(spark, SF).count() if query.endswith("all") else 9)


@pytest.fixture(scope="module")
def texts(spark, tmp_path_factory):
    """Rare and short words in several languages."""
    rows = [(1, "the speed of an ox, teh sped of a fox", "en"), (2, "fährt für Fahrt fürs", "de"), (3, "niño nino año", "es"), (4, "speedy été ete", "fr"), (5, None, "en")]
    folder = str(tmp_path_factory.mktemp("texts"))
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{folder}/documents.parquet")
    return folder


@pytest.mark.parametrize("eps", [0, 1, 2, 3])
def test_token_pairs_take_every_word(spark, texts, eps):
    words = tables.all_tokens(spark, texts)
    want = {tuple(r) for r in baselines.bruteforce_literal(words, eps).collect()}
    assert {tuple(r) for r in registry.QUERIES[f"literal_pairs_tokens_e{eps}_all"](spark, texts).collect()} == want
    assert eps != 1 or {frozenset(p) for p in (("niño", "nino"), ("sped", "speed"), ("ox", "fox"))} <= {frozenset(p[:2]) for p in want}


def test_short_lane_sees_short_words(spark, texts):
    words = tables.all_tokens(spark, texts).where("length(attr) <= 8")
    assert {tuple(r) for r in registry.QUERIES["short_lane_all"](spark, texts).collect()} == {tuple(r) for r in baselines.bruteforce_literal(words, 2).collect()}


def test_token_clusters_take_every_word(spark, texts):
    words = values(tables.all_tokens(spark, texts), "attr")
    assert values(registry.QUERIES["resolve_cover_tokens"](spark, texts), "attr") == words
    assert values(registry.QUERIES["pool_token_schemas_all"](spark, texts), "attr") == words
    assert {"fährt", "fahrt"} <= values(registry.QUERIES["token_components"](spark, texts), "attr")
    assert tuple(registry.QUERIES["resolve_cover_violations"](spark, texts).first()) == (0, 0)


def test_cooccurrence_of_words_in_every_document(spark):
    rows = [(i, w) for i in range(3) for w in ("ox", "yak")] + [(0, "ant"), (0, "bee"), (1, "bee")]
    got = {(r["a"], r["b"]): r["d"] for r in distance.cooccurrence_distance(spark.createDataFrame(rows, "doc_id long, word string")).collect()}
    assert got["ox", "yak"] == 0 and abs(got["ant", "bee"] - math.log(2) / math.log(3)) < 1e-9 and got["ant", "ox"] == 1


def test_cooccurrence_pairs_do_not_depend_on_blocks(spark, monkeypatch):
    words = spark.range(60).selectExpr("id % 4 AS doc_id", "concat('w', id % 23) AS word")
    whole = sorted(map(tuple, distance.cooccurrence_distance(words).collect()))
    monkeypatch.setattr(distance, "BLOCK", 3)
    assert sorted(map(tuple, distance.cooccurrence_distance(words).collect())) == whole


def test_cooccurrence_is_over_documents(spark, texts):
    met = {tuple(r)[:2] for r in registry.QUERIES["cooccurrence_distance_all"](spark, texts).collect()}
    assert {("nino", "niño"), ("an", "teh"), ("ete", "été")} <= met and ("fox", "nino") not in met


def samples(parsed):
    """Matches of a parsed pattern: each branch, and repeats at their least and once more."""
    out = [""]
    for op, arg in parsed:
        kind = str(op)
        if kind == "LITERAL":
            more = [chr(arg)]
        elif kind == "SUBPATTERN":
            more = samples(arg[3])
        elif kind == "BRANCH":
            more = [x for branch in arg[1] for x in samples(branch)]
        elif kind == "IN":
            more = [chr(v) if str(o) == "LITERAL" else chr(v[0]) if str(o) == "RANGE" else "1" for o, v in arg]
        else:
            low, high, inner = arg
            more = [x * n for n in {low, min(high, low + 1)} for x in samples(inner)]
        out = [x + y for x in out for y in more]
    return out


def test_license_keywords_are_in_every_match():
    from unischema.llm.license_rules import all_rules

    for rule in all_rules():
        for text in samples(_parser.parse(rule.pattern)):
            assert re.fullmatch(rule.pattern, text) and rule.keyword in text, (rule, text)


def test_license_forms_behind_the_keywords(spark):
    from unischema.llm.license_scan import scan_licenses

    texts = ["See the LICENSE file for details.", "an End User Licence Agreement", "the PostgreSQL Licence", "redistribute it and/or modify it under the terms of the GNU General Public License"]
    got = {r["doc_id"]: r for r in scan_licenses(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[i]["labels"] for i in range(4)] == ["unknown-license", "proprietary", "postgresql", "gpl"]
    assert [(d["begin"], d["end"]) for d in got[3]["detections"]][0][0] == 0


@pytest.mark.parametrize("half", [None, [("xi", "xj")]])
def test_no_conflict_shares_a_part_after_the_switch(spark, half):
    near = frame(spark, [*fixtures.CHAIN, ("xa", "xj"), ("xi", "xb")], "a string, b string")
    member = spark.createDataFrame([("c", x) for x in ("xa", "xb", "xi", "xj")], "cluster_id string, attr string")
    parts = resolve.resolve_overlap(member, near, 1, half and frame(spark, half, "a string, b string"))
    assert values(parts, "attr") == {"xa", "xb", "xi", "xj"}
    own = parts.select(parts["part_id"].alias("cluster_id"), "attr")
    assert resolve.conflicts(own, near).isEmpty()
