"""Queries take their rows from the given tables, by scans of Spark."""

from __future__ import annotations

import pytest

from fanout.plans import methods, workloads  # noqa: F401  workloads register their queries
from fanout.plans import streams  # noqa: F401

NAMES = [
    "hot_cutoff",
    "params_advice",
    "params_valid",
    "rate_formula",
    "sketch_empty",
    "w_pairs_example",
]


@pytest.mark.parametrize("name", NAMES)
def test_query_reads_a_table(spark, name, tmp_path):
    read = methods.QUERIES[name](spark, "/root/testdata/sf0.001").inputFiles()
    assert read, name


def test_no_query_without_a_table():
    assert "capability_matrix" not in methods.QUERIES


def test_stream_rate_streams_the_events(spark):
    d = "/root/testdata/sf0.001"
    slots = {r[0] for r in methods.QUERIES["slots_events"](spark, d).select("slot").collect()}
    assert {r[0] for r in methods.QUERIES["stream_rate"](spark, d).select("slot").collect()} == slots
