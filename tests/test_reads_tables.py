"""Queries that once made their data up follow the given tables."""

from __future__ import annotations

import shutil

import pytest

from tests.conftest import TINY
from tracefl import registry
from tracefl.carriers import read

NAMES = ("e10_discrete_gaussian", "e14_footprint", "e7_font_probe", "e9_noise_by_features", "f5_admissible", "f6_feature_sets", "f6a_set_algebra", "jn_cross_grid", "k10_feature_budget", "k5_k6_comparisons", "k7_importance")


@pytest.fixture(scope="module")
def fewer(spark, tmp_path_factory):
    """The tables with a few rows of the larger ones."""
    d = tmp_path_factory.mktemp("fewer")
    shutil.copytree(TINY, d, dirs_exist_ok=True)
    for t in ("lineitem", "orders", "events"):
        read(spark, TINY, t).limit(9).coalesce(1).write.parquet(f"{d}/few/{t}.parquet")
    return f"{d}/few"


@pytest.mark.parametrize("name", NAMES)
def test_result_follows_the_table(spark, fewer, name):
    run = registry.queries()[name]
    rows = lambda d: sorted(map(str, run(spark, d).collect()))
    assert rows(TINY) != rows(fewer)
