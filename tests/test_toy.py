"""Exact results on the four-hyperedge example."""

import math

import pytest
from pyspark.sql import functions as F

from hgengine import pairwise, profile
from hgengine.algorithms import labels, pagerank, paths
from hgengine.model import HyperFrame
from hgengine.placement import report
from hgengine.placement.strategies import GreedyCut, HybridCut, greedy_hyperedge_cut, random_vertex_cut


def table(df, key, value):
    return {r[key]: r[value] for r in df.collect()}


def near(found, expected, tol=1e-6):
    assert found.keys() == expected.keys()
    for k, v in expected.items():
        assert found[k] == pytest.approx(v, abs=tol), k


V, E = range(1, 6), range(1, 5)


def test_degrees(toy):
    assert table(profile.degrees(toy), "vid", "degree") == dict(zip(V, (3, 2, 2, 3, 1)))
    assert table(profile.cardinalities(toy), "hid", "cardinality") == dict(zip(E, (2, 4, 3, 2)))
    assert set(toy.validate().values()) == {0}


def test_pairs(toy):
    found = {(r.src, r.dst) for r in pairwise.to_pairwise(toy).collect()}
    assert found == {(1, 2), (1, 3), (1, 4), (1, 5), (2, 3), (2, 4), (3, 4), (4, 5)}
    assert profile.pairwise_cost(toy).first().pairs_upper == 11
    with pytest.raises(pairwise.PairwiseTooLarge):
        pairwise.to_pairwise(toy, most_pairs=10)


def test_pagerank_rounds(toy):
    one = pagerank.pagerank(toy, max_rounds=1)
    near(table(one.vertices, "vid", "rank"), dict(zip(V, (1.330556, 0.858333, 0.858333, 1.330556, 0.622222))))
    near(table(one.hyperedges, "hid", "rank"), dict(zip(E, (0.833333, 1.666667, 1.666667, 0.833333))))
    thirty = pagerank.pagerank(toy, max_rounds=30)
    near(table(thirty.vertices, "vid", "rank"), dict(zip(V, (1.313900, 0.908299, 0.908299, 1.313900, 0.555602))))
    near(table(thirty.hyperedges, "hid", "rank"), dict(zip(E, (0.892116, 1.784232, 1.431535, 0.892116))))


def test_pagerank_weighted_and_pairwise(weighted):
    expected = dict(zip(V, (1.013276, 0.767141, 1.288657, 1.534791, 0.396134)))
    found = table(pagerank.pagerank(weighted, max_rounds=30).vertices, "vid", "rank")
    near(found, expected)
    near(table(pairwise.pagerank_pairwise(weighted, max_rounds=30), "vid", "rank"), found, 1e-12)


def test_message_start_converges_to_the_same(toy):
    found = table(pagerank.pagerank(toy, max_rounds=60, init="message").vertices, "vid", "rank")
    near(found, table(pagerank.pagerank(toy, max_rounds=60).vertices, "vid", "rank"), 1e-3)


def test_tolerance_ends_early(toy):
    assert pagerank.run(toy, max_rounds=100, tol=1e-3).rounds < 40


@pytest.mark.parametrize("form", ["algebraic", "sequence"])
def test_entropy(toy, weighted, form):
    found = pagerank.pagerank_entropy(toy, max_rounds=31, form=form).hyperedges
    near(table(found, "hid", "entropy"), dict(zip(E, (0.975833, 1.975833, 1.493434, 0.975833))), 1e-5)
    found = pagerank.pagerank_entropy(weighted, max_rounds=31, form=form, evenness=True).hyperedges
    near(table(found, "hid", "entropy"), dict(zip(E, (0.986170, 1.953937, 1.408894, 0.994511))), 1e-5)
    assert table(found, "hid", "evenness")[3] == pytest.approx(1.408894 / math.log2(3), abs=1e-5)


def test_labels(toy):
    one = labels.label_propagation(toy, 1, until_stable=False)
    assert table(one.hyperedges, "hid", "label") == dict(zip(E, (2, 4, 5, 4)))
    assert table(one.vertices, "vid", "label") == dict(zip(V, (5, 4, 4, 5, 5)))
    run = labels.run(toy)
    assert run.rounds == 3
    assert set(table(run.frame.vertices, "vid", "label").values()) == {5}


def test_paths(toy):
    found = paths.shortest_paths(toy, 1)
    assert table(found.vertices, "vid", "hops") == dict(zip(V, (0, 1, 1, 1, 1)))
    assert table(found.hyperedges, "hid", "hops") == dict(zip(E, (1, 1, 1, 2)))
    assert paths.separation(toy, 2, 5) == 2


def test_chain(spark):
    hf = HyperFrame.from_rows(spark, [(1, 1), (2, 1), (2, 2), (3, 2), (3, 3), (4, 3)], vertices=[5], hyperedges=[9])
    found = paths.shortest_paths(hf, 1, keep_parent=True)
    assert table(found.vertices, "vid", "hops") == {1: 0, 2: 1, 3: 2, 4: 3, 5: None}
    assert table(found.hyperedges, "hid", "hops") == {1: 1, 2: 2, 3: 3, 9: None}
    assert table(found.vertices, "vid", "parent")[4] == 3
    assert table(labels.components(hf), "vid", "component") == {1: 4, 2: 4, 3: 4, 4: 4, 5: 5}
    assert table(labels.components(hf, "two_phase"), "vid", "component") == {1: 4, 2: 4, 3: 4, 4: 4, 5: 5}
    assert table(pagerank.pagerank(hf, max_rounds=3).vertices, "vid", "rank")[5] == pytest.approx(0.15)
    assert [r.hid for r in hf.isolated_hyperedges().collect()] == [9]
    assert [r.vid for r in hf.isolated_vertices().collect()] == [5]


def test_groups_are_lost_in_pairs(spark):
    """Two hypergraphs with one pair graph."""
    one = HyperFrame.from_rows(spark, [(1, 1), (2, 1), (3, 1)])
    two = HyperFrame.from_rows(spark, [(1, 1), (2, 1), (2, 2), (3, 2), (1, 3), (3, 3)])
    pairs = [{(r.src, r.dst) for r in pairwise.to_pairwise(hf).collect()} for hf in (one, two)]
    assert pairs[0] == pairs[1]
    assert one.hyperedges.count() != two.hyperedges.count()




def fixed(monkeypatch, of):
    from hgengine.placement import strategies

    expr = lambda parts, *ids: F.element_at(F.create_map(*(F.lit(x) for k, v in of.items() for x in (k, v))), ids[0].cast("int")).cast("int")
    monkeypatch.setitem(strategies.HASHES, "fixed", expr)


def parts_of(df, key):
    return {k: {r.part for r in df.collect() if r[key] == k} for k in {r[key] for r in df.collect()}}


def test_random_vertex_cut(toy, monkeypatch):
    fixed(monkeypatch, {1: 0, 2: 0, 3: 1, 4: 1, 5: 1})
    placed = random_vertex_cut("fixed").assign(toy, 2)
    row = report.placement_report(placed, 2).first()
    assert parts_of(placed, "vid")[1] == {0, 1}
    assert row.rf_vertex == pytest.approx(8 / 5)
    assert row.cut_hyperedges == 0


@pytest.mark.parametrize(("unit", "chosen"), [("frozen", {1: 0, 2: 0, 3: 1, 4: 1}), ("hyperedges", {1: 0, 2: 1, 3: 1, 4: 1}), ("incidences", {1: 0, 2: 1, 3: 1, 4: 1})])
def test_greedy_vertex_cut(toy, monkeypatch, unit, chosen):
    fixed(monkeypatch, {1: 0, 2: 0, 3: 1, 4: 1, 5: 1})
    assert table(GreedyCut(unit, hash="fixed").choose(toy, 2), "hid", "part") == chosen


def test_greedy_hyperedge_cut(toy, monkeypatch):
    fixed(monkeypatch, {1: 0, 2: 0, 3: 1, 4: 1})
    placed = greedy_hyperedge_cut(load_unit="frozen", hash="fixed").assign(toy, 2)
    assert {k: min(v) for k, v in parts_of(placed, "vid").items()} == {1: 0, 2: 0, 3: 0, 4: 1, 5: 1}


def test_hybrid_cutoff_is_strict(spark):
    rows = [(v, 1) for v in range(100)] + [(v, 2) for v in range(101)]
    hf = HyperFrame.from_rows(spark, rows)
    found = parts_of(HybridCut(100).assign(hf, 8), "hid")
    assert len(found[1]) == 1
    assert len(found[2]) == 8


def test_placed_plan_gives_the_same_labels(toy):
    for rule in (random_vertex_cut(), HybridCut(2), GreedyCut()):
        assert set(table(labels.label_propagation(toy, placement=rule.assign(toy, 3), parts=3).vertices, "vid", "label").values()) == {5}
