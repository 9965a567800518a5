"""Registered queries against their SQL on the small tables."""

import pytest

from minlabel import catalog, relational, reports
from minlabel.session import table
from minlabel.workloads import WORKLOADS
from tests.conftest import SMALL, SMOKE
from tests.helpers import same

ORACLES, QUERIES = catalog.oracle_sql(), catalog.queries()
SLOW = ("chain", "path", "lattice", "experiment", "embedding")
STATES = [k for k in ORACLES if k.startswith(("minmap", "ems", "mms", "roots", "pointer"))]


@pytest.mark.parametrize("name", sorted(k for k in relational.ORACLES if k not in ("full_outer_nations",)))
def test_relational(spark, name):
    same(spark, QUERIES[name], _plain(ORACLES[name], name), SMOKE)


def _plain(sql, name):
    return sql


@pytest.mark.parametrize("name", STATES)
def test_states(spark, name):
    same(spark, QUERIES[name], ORACLES[name], SMALL)


@pytest.mark.parametrize("name", sorted(k for k in ORACLES if k.startswith("cc_order2_") and not any(s in k for s in SLOW)))
def test_components(spark, name):
    same(spark, QUERIES[name], ORACLES[name], SMOKE)


@pytest.mark.parametrize("name", ["component_histogram", "subgraph_components", "validate_customer_day", "degree_histogram", "graph_catalog", "isolated_customers_keep_label"])
def test_reports(spark, name):
    same(spark, QUERIES[name], ORACLES[name], SMOKE)


@pytest.mark.parametrize("name", sorted(reports.ORACLES))
def test_measures(spark, name):
    same(spark, QUERIES[name], ORACLES[name], SMOKE)


@pytest.mark.parametrize("name", sorted(set(reports.QUERIES) - set(reports.ORACLES)))
def test_measures_without_sql(spark, name):
    assert QUERIES[name](spark, SMOKE).count() > 0


def test_entry(spark):
    assert catalog.entry(spark, SMOKE).count() > 0


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES)


def test_session_overlaps_by_blocks(spark, monkeypatch):
    """Blocks of a few users give the same counts, and the pairs are counted where they are found: no exchange by u and v."""
    monkeypatch.setattr(relational, "WIDE", 3)
    df = QUERIES["session_overlap_all_users"](spark, SMOKE)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "hashpartitioning(u#" not in plan
    same(spark, QUERIES["session_overlap_all_users"], ORACLES["session_overlap_all_users"], SMOKE)


def test_lattices_paths_and_bounds_are_of_given_tables(spark):
    parts, customers = ({r[0] for r in table(spark, SMOKE, t).select(c).collect()} for t, c in (("part", "p_partkey"), ("customer", "c_custkey")))
    for name in ("lattice12", "lattice12p"):
        g = WORKLOADS[name].build(spark, SMOKE)
        assert {r.id for r in g.vertices.collect()} == parts
        w = int(len(parts) ** 0.5)
        assert g.edges.count() == sum(((p + 1) % w != 0 and p + 1 < len(parts)) + (p + w < len(parts)) + ((p + 1) % w != 0 and p + w + 1 < len(parts)) for p in range(len(parts)))
        same(spark, QUERIES[f"cc_union_find_{name}"], ORACLES[f"cc_union_find_{name}"], SMOKE)
    assert {r.d for r in QUERIES["sql_surface_bound"](spark, SMOKE).collect()} == parts
    assert {r.points for r in QUERIES["order1_spreads_one_hop"](spark, SMOKE).collect()} == {len(customers)}
    for name in ("sql_surface_bound", "order1_spreads_one_hop"):
        same(spark, QUERIES[name], ORACLES[name], SMOKE)
