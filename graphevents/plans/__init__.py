"""Choices between physical forms, from sizes that are measured."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class Choice:
    what: str
    form: str
    why: str


def estimated_bytes(df: DataFrame) -> int:
    """The optimiser's estimate of a plan's size."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def choose_dictionary(dictionary: DataFrame, limit: int = 64 << 20) -> Choice:
    """A trie on the map side for a dictionary of a checked size, else a join by n-gram."""
    size = estimated_bytes(dictionary)
    form = "trie" if size <= limit else "join"
    return Choice("dictionary", form, f"{size} bytes estimated, limit {limit}")


def choose_trees(forest_rows: int, limit: int = 4_000_000) -> Choice:
    form = "broadcast" if forest_rows <= limit else "paths"
    return Choice("sentence trees", form, f"{forest_rows} nodes, limit {limit}")


def choose_layer(largest_graph_nodes: int, limit: int = 50_000) -> Choice:
    """The kernel holds a whole graph in one task; larger ones run relationally, a shuffle a layer."""
    form = "kernel" if largest_graph_nodes <= limit else "relational"
    return Choice("layer", form, f"largest graph has {largest_graph_nodes} nodes, limit {limit}")


def explain_choice(*choices: Choice) -> str:
    return "\n".join(f"{c.what}: {c.form} ({c.why})" for c in choices)


def physical(df: DataFrame) -> str:
    """The formatted physical plan as text, for plan tests."""
    return df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")
