"""Invariants on seeded random hypergraphs, and plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from hgengine.algorithms import labels, pagerank, paths
from hgengine.baseline.direct_lp import direct_labels
from hgengine.model import HyperFrame
from hgengine.placement import report
from hgengine.placement.strategies import GreedyCut, GreedyHybridCut, IterativeCut, random_both_cut, random_hyperedge_cut, random_vertex_cut, seven
from hgengine.plans.layout import layout_of
from hgengine.programs import Combiner, Program, infer_combiners
from hgengine.runtime import half_round
from hgengine.session import cut


@pytest.fixture(scope="module", params=[1, 2])
def hf(spark, request):
    draw = np.random.default_rng(request.param)
    rows = [(int(v), h) for h in range(25) for v in draw.choice(40, size=draw.integers(1, 7), replace=False)]
    return HyperFrame.from_rows(spark, rows, {h: float(draw.integers(1, 5)) for h in range(25)}).persist()


def test_rank_mass(hf):
    n = hf.incidence.select("vid").distinct().count()
    found = pagerank.pagerank(hf, max_rounds=7).vertices.join(hf.incidence.select("vid").distinct(), "vid")
    assert found.agg(F.sum("rank")).first()[0] == pytest.approx(n)


def test_labels_are_components(hf):
    by = [{r[0]: r[1] for r in df.collect()} for df in (labels.label_propagation(hf).vertices, labels.components(hf, "two_phase"), direct_labels(hf))]
    assert by[0] == by[1] == by[2]


def test_hops_differ_by_one_in_a_hyperedge(hf):
    source = hf.incidence.agg(F.min("vid")).first()[0]
    found = paths.shortest_paths(hf, source)
    within = hf.incidence.join(found.vertices, "vid").groupBy("hid").agg((F.max("hops") - F.min("hops")).alias("d"), (F.min("hops") + 1).alias("e"))
    for r in within.join(found.hyperedges, "hid").collect():
        assert r.d is None or r.d <= 1
        assert r.e == r.hops


def test_placements_assign_each_membership_once(hf):
    n = hf.incidence.count()
    for rule in [*seven(), GreedyCut(mode="streams"), GreedyCut(mode="epochs"), GreedyHybridCut(3), IterativeCut(3)]:
        placed = rule.assign(hf, 5)
        assert placed.count() == n == placed.select("vid", "hid").distinct().count()
        assert placed.where("part < 0 or part >= 5").count() == 0
    whole = report.placement_report(random_vertex_cut().assign(hf, 5), 5).first()
    assert whole.rf_hyperedge == 1
    assert report.placement_report(random_hyperedge_cut().assign(hf, 5), 5).first().rf_vertex == 1
    assert report.placement_report(random_both_cut().assign(hf, 1), 1).first().rf_total == 1


def test_greedy_beats_random_on_communities(spark):
    draw = np.random.default_rng(3)
    rows = {(int(b * 20 + draw.integers(20)) if draw.random() < 0.95 else int(draw.integers(160)), b * 30 + h) for b in range(8) for h in range(30) for _ in range(6)}
    hf = HyperFrame.from_rows(spark, sorted(rows))
    greedy, random = (report.placement_report(r.assign(hf, 8), 8).first().rf_vertex for r in (GreedyCut(load_unit="incidences"), random_vertex_cut()))
    assert greedy < random


def test_dual_of_dual(hf):
    twice = hf.dual().dual().incidence
    assert twice.exceptAll(hf.incidence.select(*twice.columns)).count() == 0


def paths_to_scans(node, path=()):
    """(name, output) of the nodes from the root to each scan of a kept table."""
    path = (*path, (node.nodeName(), node.output().mkString(",")))
    if "InMemoryTableScan" in node.nodeName():
        yield path
    children = node.children()
    for i in range(children.size()):
        yield from paths_to_scans(children.apply(i), path)


@pytest.mark.parametrize("rule", [None, random_both_cut()])
def test_no_exchange_above_the_memberships(spark, hf, rule):
    """In either half round, with states too large to broadcast, state and message rows are exchanged and the kept
    memberships are not."""
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    layout = layout_of(hf, rule, 4)
    try:
        program = Program(emit={"x": F.col("x")}, combine={"x": Combiner.MAX})
        for key, other, nodes in (("vid", "hid", hf.vertices), ("hid", "vid", hf.hyperedges)):
            kept = layout.copies[key] if rule is None else layout.incidence
            kept.count()
            states = cut(nodes.select(key, F.col(key).alias("x")))
            found = half_round(states, layout, program, key, other)
            found.count()
            joined = 0
            for path in paths_to_scans(found._jdf.queryExecution().executedPlan().initialPlan()):
                if all(f"{c}#" in path[-1][1] for c in ("vid", "hid")):
                    at = max(i for i, (name, _) in enumerate(path) if "Join" in name)
                    assert not any("Exchange" in name for name, _ in path[at:])
                    joined += 1
            assert joined == 1
    finally:
        layout.release()
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_layouts_agree(hf):
    """All applications, on two copies and on placements, with combiners of every kind."""
    source = hf.incidence.agg(F.min("vid")).first()[0]
    costly = hf.with_hyperedge_columns(cost=F.col("weight"))
    found = []
    for rule in (None, random_both_cut(), GreedyCut(mode="streams")):
        ranks = pagerank.pagerank_entropy(hf, max_rounds=6, placement=rule, parts=3)
        far = paths.shortest_paths(costly, source, weight="cost", keep_parent=True, placement=rule, parts=3)
        layout = layout_of(hf, rule, 3)
        emit = {"n": F.lit(1), "ids": F.array("vid"), "least": F.col("vid"), "big": F.col("vid") > 20}
        kinds = {"n": Combiner.COUNT, "ids": Combiner.CONCAT, "least": Combiner.MIN, "big": Combiner.BOOL_OR}
        sent = half_round(hf.vertices, layout, Program(emit=emit, combine=kinds), "vid", "hid").select("hid", "_msg_n", F.sort_array("_msg_ids"), "_msg_least", "_msg_big")
        tables = [ranks.vertices.select("vid", F.round("rank", 9)), ranks.hyperedges.select("hid", F.round("entropy", 9)), labels.label_propagation(hf, placement=rule, parts=3).vertices, far.vertices.select("vid", "hops", "parent"), sent]
        found.append([sorted(map(tuple, t.collect()), key=repr) for t in tables])
        layout.release()
    assert found[0] == found[1] == found[2]


def test_nothing_stays_cached(spark, hf):
    before = spark.sparkContext._jsc.getPersistentRDDs().size()
    pagerank.pagerank(hf, max_rounds=2)
    labels.label_propagation(hf, placement=random_both_cut(), parts=3)
    labels.components(hf, "two_phase")
    paths.multi_source(hf, [1, 2])
    assert spark.sparkContext._jsc.getPersistentRDDs().size() == before


def test_multi_source_is_each_source(hf):
    sources = [r.vid for r in hf.incidence.select("vid").distinct().orderBy("vid").limit(3).collect()]
    costly = hf.with_hyperedge_columns(cost=F.col("weight"))
    for weight in (None, "cost"):
        found = {(r.source, r.vid): r.hops for r in paths.multi_source(costly, sources, weight).collect()}
        assert found == {(s, r.vid): r.hops for s in sources for r in paths.shortest_paths(costly, s, weight=weight).vertices.collect()}


def test_filters_reach_the_scan(spark):
    from hgengine.sources.standins import plain_basket
    from hgengine.sources.tables import load

    text = load(spark, "/root/testdata/sf0.001", "part", ["p_partkey"], "p_size > 25")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(p_size), GreaterThan(p_size,25)]" in text
    text = plain_basket(spark, "/root/testdata/sf0.001").incidence._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in text


def test_combiners_by_type(spark):
    schema = spark.createDataFrame([], "a double, b boolean, c array<int>, d struct<x: int, y: double>").schema
    assert set(infer_combiners(schema)) == {"a", "b", "c", "d"}
    with pytest.raises(TypeError):
        infer_combiners(spark.createDataFrame([], "s string").schema)
