"""Named queries over the given tables, and their SQL."""

from __future__ import annotations

from .queries import clusters, measures, network, surrounding  # noqa: F401  each module adds its queries

QUERIES = network.QUERIES
ORACLES = network.ORACLES


def flagship(spark, sf_dir: str):
    return QUERIES["mutual_partition_docs"](spark, sf_dir)
