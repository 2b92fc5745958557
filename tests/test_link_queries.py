"""The queries that link: rows of their SQL, and no edge to contract where one domain holds all points."""

import pathlib

import pytest

from tests.test_workloads import rows_of
from zplane.operators import linking

LINKED = [
    "link_clump",
    "link_orders",
    "catalogue_orders",
    "catalogue_min20",
    "group_sizes",
    "group_of_first",
    "largest_groups",
    "catalogue_velocity",
    "link_clump_periodic",
]


@pytest.mark.parametrize("name", LINKED)
def test_one_domain_leaves_nothing_to_contract(spark, sf, monkeypatch, name):
    sizes, keep = [], linking.components_with_rounds
    monkeypatch.setattr(linking, "components_with_rounds", lambda e, *a: sizes.append(e.count()) or keep(e, *a))
    got, want = rows_of(spark, pathlib.Path(sf), name, ["orders"])
    assert got == want and got
    assert sizes == [0]
