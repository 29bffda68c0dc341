"""Registered queries of the engine: workloads (``W..``) and surrounding operators (``O_..``)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from codeprov.workloads import basics, clones, hashes, source, streams, study, variants

FLAGSHIP = "W01_clone_search"
MODULES = (clones, hashes, study, source, variants, streams, basics)
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {k: q for m in MODULES for k, q in m.QUERIES.items()}
