"""Balls of many starts are made in place: the rows of small ones, and no exchange of their rows."""

import pytest

from unischema.operators import baselines, concept, inplace, knowledge, metrics
from unischema.sources.fixtures import frame


@pytest.fixture
def base(spark, monkeypatch):
    """A chain with a hub, another component, and inputs with an absent name and a null."""
    h1 = knowledge.neighbour_table(frame(spark, [(x, y) for x, y in zip("abcdefg", "bcdefgh", strict=True)] + [("b", f"b{i}") for i in range(4)] + [("y", "z")], "sub string, sup string")).cache()
    every = h1.select("concept").distinct()
    inputs = every.unionByName(frame(spark, ["absent", None], "concept string"))
    want = {gamma: rows(knowledge.k_hop(inputs, h1, gamma)) for gamma in (1, 2, 3)}
    for name, value in (("MANY_STARTS", 1), ("DEAL", 2)):
        monkeypatch.setattr(knowledge, name, value)
    monkeypatch.setattr(inplace, "CELLS", 30)
    monkeypatch.setattr(inplace, "STEP", 3)
    monkeypatch.setattr(inplace, "BATCH", 4)
    return h1, every, inputs, want


def rows(df):
    return sorted((tuple(r) for r in df.collect()), key=str)


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def known(found):
    return [r for r in found if r[0] not in ("absent", None)]


def in_place(df):
    return "MapInArrow" in plan(df) and "Join" not in plan(df)


# F7, F9, F12


@pytest.mark.parametrize("gamma", [1, 2, 3])
def test_hops_in_place(spark, base, gamma):
    h1, every, inputs, want = base
    found = concept.related_concepts(inputs, h1, gamma)
    assert rows(found) == want[gamma] and in_place(found)
    table = knowledge.hop_table(h1, gamma)
    assert rows(table) == [r[:2] for r in known(want[gamma]) if r[2] == gamma] and in_place(table)
    guard = knowledge.k_hop(inputs, h1, gamma, max_degree=2)
    assert ("a", "b", 1) in rows(guard) and ("a", "c", 2) not in rows(guard)
    stats = metrics.frontier_stats(knowledge.k_hop(every, h1, gamma))
    assert {r["len"]: (r["n_paths"], r["n_ends"]) for r in stats.collect()} == {n: (len(some), len({r[1] for r in some})) for n in range(gamma + 1) if (some := [r for r in known(want[gamma]) if r[2] == n])}
    assert "Join" not in plan(stats)


# F2


def test_ball_tables_in_place(spark, base):
    h1, _, _, want = base
    found = knowledge.ball_table(h1, 2)
    assert rows(found) == known(want[2]) and in_place(found)
    assert rows(knowledge.ball_table(h1, 3)) == known(want[3])
    assert rows(knowledge.ball_table(h1, 4)) == rows(knowledge.k_hop(h1.select("concept").distinct(), h1, 4))


# F4


@pytest.mark.parametrize("gamma", [1, 2, 3])
def test_semantic_loop_in_place(spark, base, gamma):
    h1, _, _, want = base
    found = baselines.bruteforce_semantic(h1, gamma)
    assert rows(found) == known(want[gamma]) and in_place(found)


# F6, F8


@pytest.mark.parametrize("how", ["binary", "meet"])
@pytest.mark.parametrize("gamma", [1, 2, 3])
def test_plans_in_place(spark, base, how, gamma):
    h1, every, inputs, want = base
    found = concept.related_concepts(inputs.where("concept IS NOT NULL"), h1, gamma, how)
    assert rows(found) == [r for r in want[gamma] if r[0] is not None] and in_place(found)
    assert rows(concept.related_concepts(every, h1, 5, how)) == rows(knowledge.k_hop(every, h1, 5))
    assert rows(concept.related_concepts(every, h1, 0, how)) == rows(knowledge.k_hop(every, h1, 0))


# F10


@pytest.mark.parametrize("gamma", [1, 2, 3])
def test_single_hops_in_place(spark, base, gamma):
    h1, _, inputs, want = base
    found = baselines.expand_by_single_hops(inputs, h1, gamma)
    assert rows(found) == known(want[gamma]) and in_place(found)


# F3


@pytest.mark.parametrize("gamma", [1, 2, 3])
def test_last_steps_of_the_recursive_query_are_not_exchanged(spark, base, gamma):
    h1, _, inputs, want = base
    found = concept.concept_join_recursive(spark, inputs, h1, gamma)
    assert rows(found) == want[gamma]
    assert "explode(" in plan(found).split("Exchange")[0]
