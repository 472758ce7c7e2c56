"""Named queries over the given tables, with the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from peertrust.estimate import estimate, rank
from peertrust.operators import expressions, extended, relational
from peertrust.queries import detection, ledger, mechanisms, ranking, updates, workloads
from peertrust.sources.tables import peer_edges
from peertrust.walks import simulate_walks

_MODULES = (ledger, ranking, updates, workloads, detection, mechanisms, workloads, relational, expressions, extended)
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {k: q for m in _MODULES for k, q in m.QUERIES.items()}
ORACLE_SQL: dict[str, str] = {k: q for m in _MODULES for k, q in m.ORACLE_SQL.items()}


def entry(spark: SparkSession) -> DataFrame:
    """From the ledger to a ranking: the ten peers that peer 0 trusts most."""
    return rank(estimate(simulate_walks(peer_edges(spark, "/root/testdata/sf0.001"), 0)), 10)
