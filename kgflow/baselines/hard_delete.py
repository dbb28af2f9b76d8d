"""A store that removes retired edges: the same active graph, without a word on what held before."""

from __future__ import annotations

from pyspark.sql import DataFrame

from kgflow.session import settled
from kgflow.store.graph import KEY


def after(adds: DataFrame, downs: DataFrame, batches: list[int]) -> DataFrame:
    """Edges left after the batches, each taking its retired edges out of the table and its new ones in."""
    edges = adds.limit(0)
    for k in batches:
        gone = downs.where(downs.batch_id == k).select(*KEY).distinct()
        edges = settled(edges.join(gone, KEY, "left_anti").select(*adds.columns).unionByName(adds.where(adds.batch_id == k)))
    return edges
