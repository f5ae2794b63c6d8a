import subprocess
import sys
from pathlib import Path

import pandas as pd
import pytest

from stepgraph.model import Graph
from stepgraph.operators import flood, local
from stepgraph.plans import reports


def test_queries_need_no_session():
    """The names of queries are asked for before a session is there."""
    code = "import __spark_entry__ as e; assert e.queries() and e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).parents[1], check=True, timeout=120)


def test_gini_of_a_histogram():
    flat = [3, 1, 1, 7, 3, 2]
    direct = sum(abs(a - b) for a in flat for b in flat) / (2 * len(flat) * sum(flat))
    hist = pd.Series(flat).value_counts()
    assert reports.gini(pd.Series(hist.index), pd.Series(hist.values)) == pytest.approx(direct)


def test_small_and_large_components_give_the_eccentricities_of_floods(spark):
    chain = [(k, k + 1) for k in range(9)]
    edges = spark.createDataFrame([*chain, (20, 21), (21, 22), (20, 22), (30, 30), (41, 40), (40, 41)], "src long, dst long")
    g = Graph.from_edges(edges)
    want = {tuple(r) for r in flood.eccentricity(g).collect()}
    assert {r.ecc for r in local.eccentricity(g).where("id < 10").collect()} == {5, 6, 7, 8, 9}
    for limit in (4, 100):
        assert {tuple(r) for r in local.eccentricity(g, limit).collect()} == want


def test_directed_graphs_are_refused(spark):
    with pytest.raises(ValueError, match="undirected"):
        local.eccentricity(Graph.from_edges(spark.createDataFrame([(1, 2)], "src long, dst long"), directed=True))
