"""Choices that Catalyst cannot make for iterative methods, and plan checks."""

from __future__ import annotations

from pyspark.sql import DataFrame

from peertrust.walks import BROADCAST_EDGES


def choose_walk_strategy(n_edges: int, max_degree: int, n_walks: int) -> str:
    """The adjacency goes to the tasks while it is small; else ends of walks join
    intervals, binned where a hub would meet its edges one by one."""
    if n_edges <= BROADCAST_EDGES:
        return "broadcast"
    return "binned" if max_degree > 64 or n_walks > 10_000 else "frontier"


def choose_iteration(n_nodes: int, n_edges: int) -> str:
    """Power iteration in one task, with a broadcast vector, or by shuffled joins."""
    if n_edges <= BROADCAST_EDGES:
        return "local"
    return "broadcast_vector" if n_nodes <= 10_000_000 else "shuffle"


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def assert_plan(df: DataFrame, has: tuple[str, ...] = (), lacks: tuple[str, ...] = ("CartesianProduct",)) -> None:
    """Raises where the physical plan lacks a node, or has an unwanted one."""
    text = plan_text(df)
    for name in has:
        if name not in text:
            raise AssertionError(f"{name} is not in the plan:\n{text}")
    for name in lacks:
        if name in text:
            raise AssertionError(f"{name} is in the plan:\n{text}")
